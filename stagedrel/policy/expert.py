"""A rule-based annotator in the place of a paid model: writes six steps and an answer, with faults by hash."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.labels import NONE
from ..functions.portable import hash_hex


#: What the annotator says at length, so that its reasoning is a long one.
AT_LENGTH = " It is looked at from edge to edge and in its parts before anything is said of it." * 13


def rule_response(seed: int = 9) -> Column:
    """About one response in eight is faulty: no think block, a missing step, no answer, an unknown label, a wrong answer."""
    f = F.substring(hash_hex(seed, "expert", F.col("sample_id")), 1, 2)
    line = lambda *x: F.concat(*[F.lit(v) if isinstance(v, str) else v for v in x], F.lit("\n"))
    none = F.col("gold") == NONE
    think = F.concat(
        F.lit("<think>"), line("Step 1: a picture with an object and ", F.col("entity"), AT_LENGTH), line("Step 2: related ", F.when(none, "no").otherwise("yes")),
        F.when(f < "10", "").otherwise("Step 3: matched\n"), line("Step 4: types ", F.col("obj_type"), " and ", F.coalesce("ent_type", F.lit("unknown"))),
        line("Step 5: narrowed"), line("Step 6: decided"), F.lit("</think>"),
    )
    said = F.when((f >= "14") & (f < "18"), "no/such").when((f >= "18") & (f < "20"), F.when(none, "/per/per/peer").otherwise(NONE)).otherwise(F.col("gold"))
    answer = F.when((f >= "10") & (f < "14"), "").otherwise(F.concat(F.lit("<answer>"), said, F.lit("</answer>")))
    return F.concat(F.when(f < "08", "").otherwise(think), answer)


def annotate(drawn: DataFrame, done: DataFrame | None = None, seed: int = 9) -> DataFrame:
    """(sample_id, gold, response); rows that ``done`` has already are left out, so a second run costs nothing."""
    todo = drawn if done is None else drawn.join(done.select("sample_id"), "sample_id", "left_anti")
    return todo.select("sample_id", "gold", rule_response(seed).alias("response"))


def zero_shot_uniform(samples: DataFrame, seed: int = 7) -> DataFrame:
    """An untrained answer: any label, by hash."""
    from ..functions.portable import hash_int
    from ..ontology import LABELS

    at = (hash_int(seed, "uniform", F.col("sample_id")) % len(LABELS)).cast("int")
    return samples.select("sample_id", "gold", F.get(F.array(*[F.lit(x) for x in LABELS]), at).alias("pred"))


def zero_shot_prior(samples: DataFrame, ontology: DataFrame) -> DataFrame:
    """An untrained answer: the first relation that the types allow, or none."""
    first = ontology.where("not is_none").groupBy("obj_type", "ent_type").agg(F.min_by("label", "seq").alias("first"))
    both = samples.join(F.broadcast(first), ["obj_type", "ent_type"], "left")  # at most a row per pair of types
    return both.select("sample_id", "gold", F.coalesce("first", F.lit(NONE)).alias("pred"))


def majority(train: DataFrame, samples: DataFrame) -> DataFrame:
    """The most frequent training label for every sample."""
    top = train.groupBy("gold").count().agg(F.max(F.struct("count", "gold"))["gold"].alias("pred"))
    return samples.select("sample_id", "gold").crossJoin(F.broadcast(top))  # one row
