"""Draws and ranks by hash, exact and without putting any class in one task.

A first pass counts rows by stratum and leading hash digits. Prefix sums over these counts give the range that holds
the boundary of each stratum; ranges below it are taken whole, and only rows of the boundary range are ranked.
The result is the same as ``row_number`` over the hash in each stratum.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.portable import hash_hex, hex_cut
from ..sources.io import write_stage

ROUNDINGS = ("half_up", "floor", "ceil")


def quota(n: Column, fraction: float, rounding: str = "half_up") -> Column:
    """Rows to draw from a class of n: the rounded share, but one at least."""
    if rounding not in ROUNDINGS:
        raise ValueError(f"rounding is one of {ROUNDINGS}")
    share = n * F.lit(fraction)
    rounded = {"half_up": F.floor(share + 0.5), "floor": F.floor(share), "ceil": F.ceil(share)}[rounding]
    return F.greatest(rounded, F.lit(1)).cast("long")


def hash_select(df: DataFrame, strata: list[str], order: Column, tie: list[str], quotas: DataFrame, digits: int = 4) -> DataFrame:
    """Of each stratum the ``quota`` rows with the lowest ``order`` (a hex text). quotas: strata and quota."""
    keyed = df.withColumns({"_order": order, "_range": F.substring(order, 1, digits)})
    before = W.partitionBy(*strata).orderBy("_range").rowsBetween(W.unboundedPreceding, -1)
    counts = keyed.groupBy(*strata, "_range").count().withColumn("_before", F.coalesce(F.sum("count").over(before), F.lit(0)))
    cuts = counts.join(quotas, strata).where("_before < quota and quota <= _before + count").select(*strata, F.col("_range").alias("_cut"), (F.col("quota") - F.col("_before")).alias("_rest"))
    sizes = counts.groupBy(*strata).agg(F.sum("count").alias("_n")).join(quotas, strata)
    plan = sizes.join(cuts, strata, "left").select(*strata, "_cut", "_rest", (F.col("quota") >= F.col("_n")).alias("_all"))
    rows = keyed.join(plan, strata)
    sure = rows.where("_all or _range < _cut")
    edge = rows.where("not _all and _range = _cut").withColumn("_rn", F.row_number().over(W.partitionBy(*strata).orderBy("_order", *tie))).where("_rn <= _rest")
    return sure.select(*df.columns).union(edge.select(*df.columns))


def stratified_draw(df: DataFrame, by: str = "gold", frac: float = 0.25, seed: int = 42, rounding: str = "half_up", exact: bool = True, key: str = "sample_id", stream: str = "cold") -> tuple[DataFrame, DataFrame]:
    """(drawn, rest): a share of every class; rest is what was not drawn. ``exact=False`` filters by hash alone.

    The exact draw works on a written table of keys and classes, so that what df is made of runs once for the draw
    and once for its result; wide columns (pictures, texts) don't go through its passes.
    """
    order = hash_hex(seed, stream, F.col(key))
    if not exact:
        drawn = order < hex_cut(frac)
        return df.where(drawn), df.where(~drawn)
    slim = write_stage(df.select(key, by), "draw")
    quotas = slim.groupBy(by).agg(quota(F.count("*"), frac, rounding).alias("quota"))
    ids = write_stage(hash_select(slim, [by], order, [key], quotas).select(key), "drawn")
    return df.join(ids, key, "left_semi"), df.join(ids, key, "left_anti")


def hash_rank(df: DataFrame, order: Column, tie: list[str], digits: int = 3, name: str = "rank") -> DataFrame:
    """Adds the row's number from 0 in hash order, with the rows ranked range by range."""
    keyed = df.withColumns({"_order": order, "_range": F.substring(order, 1, digits)})
    counts = keyed.groupBy("_range").count()
    before = counts.withColumn("_before", F.coalesce(F.sum("count").over(W.orderBy("_range").rowsBetween(W.unboundedPreceding, -1)), F.lit(0))).select("_range", "_before")
    ranked = keyed.withColumn("_rn", F.row_number().over(W.partitionBy("_range").orderBy("_order", *tie)))
    return ranked.join(before, "_range").withColumn(name, (F.col("_before") + F.col("_rn") - 1).cast("long")).select(*df.columns, name)
