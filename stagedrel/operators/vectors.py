"""Nearest vectors for a stated query set against all rows."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y), F.lit(0.0), lambda s, x: s + x)


def cosine(a: Column, b: Column) -> Column:
    return F.try_divide(dot(a, b), F.sqrt(dot(a, a) * dot(b, b)))


def nearest(vectors: DataFrame, is_query: Column, k: int, key: str = "vec_id", within: str = "label") -> DataFrame:
    """(key, other, cosine): the k nearest rows of the same label for each query. Partial top-k lists meet in one aggregate."""
    q = vectors.where(is_query).select(F.col(key), F.col(within), F.col("embedding").alias("q"))
    rows = vectors.select(F.col(key).alias("other"), F.col(within), "embedding")
    pairs = q.join(rows, within).where(F.col(key) != F.col("other")).select(key, "other", cosine(F.col("q"), F.col("embedding")).alias("cosine"))
    # two levels: the best of each slice of candidates, then the best of those
    best = lambda df, *by: df.groupBy(*by).agg(F.slice(F.array_sort(F.collect_list(F.struct((-F.col("cosine")).alias("m"), "other"))), 1, k).alias("b")).select(*by, F.explode("b").alias("x")).select(*by, F.col("x.other").alias("other"), (-F.col("x.m")).alias("cosine"))
    sliced = best(pairs.withColumn("slice", F.pmod(F.xxhash64("other"), F.lit(64))), key, "slice").drop("slice")
    return best(sliced, key).select(key, "other", F.round("cosine", 6).alias("cosine"))
