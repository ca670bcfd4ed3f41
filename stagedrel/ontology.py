"""The label set as data: 20 relations between typed objects and entities, and none. New relations are new rows."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .functions.labels import NONE, compose_label, split_label

#: Fixed values: (object type, entity type, relations).
RELATIONS = (
    ("per", "per", ("peer", "couple", "relative_of", "colleague_of")),
    ("per", "org", ("opposed_to", "leader_of", "member_of")),
    ("per", "loc", ("resident_of", "visitor_of")),
    ("per", "misc", ("maker_of", "user_of", "winner_of")),
    ("org", "org", ("part_of", "rival_of")),
    ("org", "loc", ("based_in",)),
    ("org", "misc", ("maker_of",)),
    ("loc", "loc", ("inside_of",)),
    ("misc", "misc", ("variant_of",)),
    ("misc", "loc", ("held_at",)),
    ("loc", "org", ("site_of",)),
)
TYPES = ("per", "org", "loc", "misc")
Row = tuple[str, str | None, str | None, str, bool]


def rows(extra: Sequence[tuple[str, str, str]] = ()) -> list[Row]:
    real = [(o, e, r) for o, e, rs in RELATIONS for r in rs] + list(extra)
    return [(f"/{o}/{e}/{r}", o, e, r, False) for o, e, r in real] + [(NONE, None, None, NONE, True)]


LABELS = [r[0] for r in rows()]


def load_ontology(spark: SparkSession, path: str | None = None, extra: Sequence[tuple[str, str, str]] = ()) -> DataFrame:
    """(label, obj_type, ent_type, relation, is_none, seq): the default rows, a Parquet table of such rows, or with more relations."""
    if path:
        return spark.read.parquet(path)
    schema = "label string, obj_type string, ent_type string, relation string, is_none boolean, seq int"
    return spark.createDataFrame([(*r, k) for k, r in enumerate(rows(extra))], schema)


def candidates(ontology: DataFrame) -> DataFrame:
    """(obj_type, ent_type, labels): for all pairs of types the labels they allow, none among them."""
    types = ontology.sparkSession.createDataFrame([(o, e) for o in TYPES for e in TYPES], "obj_type string, ent_type string")
    real = ontology.where("not is_none").groupBy("obj_type", "ent_type").agg(F.sort_array(F.collect_list(F.struct("seq", "label"))).alias("x"))
    found = types.join(F.broadcast(real), ["obj_type", "ent_type"], "left")  # as many rows as pairs of types
    return found.select("obj_type", "ent_type", F.concat(F.coalesce(F.col("x.label"), F.array().cast("array<string>")), F.array(F.lit(NONE))).alias("labels"))


def recompose(labels: DataFrame) -> DataFrame:
    """labels with ``again``: what ``label`` is once it has been split and composed again."""
    parts = split_label(F.col("label"))
    return labels.withColumn("again", compose_label(parts["obj_type"], parts["ent_type"], parts["relation"]))
