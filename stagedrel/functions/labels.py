"""Labels: object type, entity type and relation in one string, and ``none``."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

NONE = "none"


def compose_label(obj_type: Column, ent_type: Column, relation: Column) -> Column:
    return F.when(relation.isNull() | (relation == NONE), NONE).otherwise(F.concat(F.lit("/"), F.concat_ws("/", obj_type, ent_type, relation)))


def split_label(label: Column) -> Column:
    """struct(obj_type, ent_type, relation); for none and malformed labels the types are null."""
    parts = F.split(label, "/")
    real = (F.size(parts) == 4) & (F.get(parts, F.lit(0)) == "")
    return F.struct(
        F.when(real, F.get(parts, F.lit(1))).alias("obj_type"),
        F.when(real, F.get(parts, F.lit(2))).alias("ent_type"),
        F.when(real, F.get(parts, F.lit(3))).otherwise(F.when(label == NONE, NONE)).alias("relation"),
    )
