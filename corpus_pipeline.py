"""The corpus pipeline: toxicity, line dedup, near-duplicate join, decontamination, mixing.

Every stage takes what the one before it kept, written as Parquet in the shared folder and read again.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from stagedrel.llm.common import materialize
from stagedrel.llm.decontaminate import without_leaks
from stagedrel.llm.line_templates import drop_recurring_lines
from stagedrel.llm.mixing import mix
from stagedrel.llm.ngram_join import one_of_each_class
from stagedrel.llm.queries import WEIGHTS, table, with_domain
from stagedrel.llm.toxicity import fit_toxicity, score_toxicity

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


def toxicity(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps documents whose score is below the threshold."""
    model = fit_toxicity(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))
    return score_toxicity(docs, model).where("predicted = 0").select(*COLUMNS)


def line_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Takes recurring lines out of the texts; n_chars follows the text. Documents stay."""
    cleaned = drop_recurring_lines(docs.drop("n_chars")).selectExpr("*", "cast(length(text) as bigint) as n_chars")
    return cleaned.select(*COLUMNS)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps one document of each class of linked texts."""
    return one_of_each_class(docs).select(*COLUMNS)


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops documents that leak a benchmark item."""
    return without_leaks(docs, table(spark, sf_dir, "benchmark")).select(*COLUMNS)


def mixing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The mixture's documents, once per epoch."""
    mixed = mix(with_domain(docs), weights=WEIGHTS, budget_share=1.0)
    return mixed.select(*COLUMNS, "domain", "epoch", "n_tokens")


STAGES = [("toxicity", toxicity), ("line_dedup", line_dedup), ("near_duplicates", near_duplicates), ("decontamination", decontamination), ("mixing", mixing)]
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = materialize(stage(spark, docs, sf_dir), f"pipeline-{name}")
    return STAGES[-1][1](spark, docs, sf_dir)
