"""The methods in SQL: functions that Catalyst inlines, table functions, and temporary views."""

from __future__ import annotations

import math

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

from .functions.responses import ANSWER, ANSWER_END, ORDER, STEP, THINK, THINK_END
from .ontology import LABELS, load_ontology
from .operators.schedule import batch_quota
from .sources.tables import build_samples, logged_groups


_LABELS = "array(" + ", ".join(f"'{x}'" for x in LABELS) + ")"
_TEXT = "btrim(coalesce(response, ''), ' \\t\\n\\r')"


def _once(tag: str) -> str:
    return f"length(response) - length(replace(response, '{tag}', '')) = {len(tag)}"


def _block(opening: str, closing: str) -> str:
    inner = f"substring_index(substring_index(response, '{closing}', 1), '{opening}', -1)"
    return f"CASE WHEN {_once(opening)} AND {_once(closing)} AND instr(response, '{opening}') < instr(response, '{closing}') THEN {inner} ELSE '' END"


FUNCTIONS = {
    "answer_of(response STRING) RETURNS STRING": f"btrim({_block(ANSWER, ANSWER_END)}, ' \\t\\n\\r')",
    "thoughts_of(response STRING) RETURNS STRING": _block(THINK, THINK_END),
    "step_order_of(response STRING) RETURNS STRING": f"array_join(regexp_extract_all(thoughts_of(response), '{STEP}', 1), ',')",
    "is_well_laid(response STRING) RETURNS BOOLEAN": f"startswith({_TEXT}, '{THINK}') AND endswith({_TEXT}, '{ANSWER_END}') AND btrim(substring_index(substring_index(response, '{ANSWER}', 1), '{THINK_END}', -1), ' \\t\\n\\r') = '' AND startswith(btrim(thoughts_of(response), ' \\t\\n\\r'), 'Step 1:')",
    "format_reward(response STRING) RETURNS DOUBLE": f"cast(coalesce(is_well_laid(response) and step_order_of(response) = '{ORDER}' and array_contains({_LABELS}, answer_of(response)), false) as double)",
    "length_reward(response STRING, threshold INT) RETURNS DOUBLE": "cast(coalesce(length(response) > threshold, false) as double)",
    "answer_reward(predicted STRING, gold STRING) RETURNS DOUBLE": "cast(predicted <=> gold as double)",
    "policy_ratio(lp_cur DOUBLE, lp_old DOUBLE) RETURNS DOUBLE": "exp(greatest(-20D, least(20D, lp_cur - lp_old)))",
    "clipped_term(ratio DOUBLE, adv DOUBLE, eps DOUBLE) RETURNS DOUBLE": "least(ratio * adv, greatest(1 - eps, least(1 + eps, ratio)) * adv)",
    "divergence_term(lp_cur DOUBLE, lp_ref DOUBLE) RETURNS DOUBLE": "exp(greatest(-20D, least(20D, lp_ref - lp_cur))) - greatest(-20D, least(20D, lp_ref - lp_cur)) - 1",
    "mix_ratio(t INT, alpha DOUBLE) RETURNS DOUBLE": "pow(alpha, t - 1)",
}


@udtf(returnType="epoch int, easy int, hard int, steps int")
class BatchPlan:
    """batch_plan(batch, alpha, epochs, hard rows): the quotas and steps of each epoch."""

    def eval(self, batch: int, alpha: float, epochs: int, hard_rows: int):
        for t in range(1, epochs + 1):
            easy, hard = batch_quota(batch, t, alpha)
            yield t, easy, hard, math.ceil(hard_rows / hard)


@udtf(returnType="number int, step string")
class StepsOf:
    """steps_of(response): a row for each numbered step."""

    def eval(self, response: str):
        import re

        block = re.search(r"(?s)<think>(.*?)</think>", response or "")
        parts = re.split(r"Step ([0-9]+):", block[1] if block else "")
        for n, text in zip(parts[1::2], parts[2::2], strict=True):
            yield int(n), text.strip()


def register_sql(spark: SparkSession, sf_dir: str | None = None) -> None:
    """Registers the functions, and with a folder of tables the views rel_samples, rollouts and ontology."""
    for head, body in FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {head} RETURN {body}")
    spark.udtf.register("batch_plan", BatchPlan)
    spark.udtf.register("steps_of", StepsOf)
    load_ontology(spark).createOrReplaceTempView("ontology")
    if sf_dir:
        build_samples(spark, sf_dir).createOrReplaceTempView("rel_samples")
        logged_groups(spark, sf_dir).createOrReplaceTempView("rollouts")


