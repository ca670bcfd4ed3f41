"""Shared pieces: tables in the cluster's shared folder, row identity, connected components."""

from __future__ import annotations

import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share (``spark.checkpoint.dir``); a local one only for local masters."""
    at = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir", None)
    if at:
        return at.rstrip("/")
    master = spark.sparkContext.master
    if master.startswith("local") and not master.startswith("local-cluster"):
        return "file:///tmp/checkpoints"
    raise ValueError("spark.checkpoint.dir must name a folder that all executors share")


def materialize(df: DataFrame, tag: str) -> DataFrame:
    """Writes df once as Parquet in the shared folder and reads it back: cuts lineage, survives lost executors."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{tag}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


#: Sets of keys up to this many rows (tens of bytes each) are broadcast; more are joined by a shuffle.
BROADCAST_ROWS = 1_000_000


def small(keys: DataFrame, size: str = "1") -> DataFrame:
    """keys (a written table), to be broadcast if the sum of ``size`` over its rows is within the bound."""
    total = keys.agg(F.sum(F.expr(size))).first()[0] or 0
    return F.broadcast(keys) if total <= BROADCAST_ROWS else keys


def content_key(text: Column) -> list[Column]:
    """Two independent hashes that identify a text (null and empty are one)."""
    t = F.coalesce(text, F.lit(""))
    return [F.xxhash64(t), F.crc32(t.cast("binary"))]


def components(edges: DataFrame, tag: str = "components") -> DataFrame:
    """(u, v) edges of any orderable id type -> (node, root) with root the smallest id of the component.

    Alternating large-star and small-star rounds; every round is one aggregation and one join of slim
    rows, written to the shared folder. Nodes without an edge don't appear. An empty input gives no rows.
    """
    current = materialize(_small_star(edges.where("u <> v").select("u", "v")), tag)
    seen = None
    while True:
        state = current.agg(F.count("*"), F.bit_xor(F.xxhash64("u", "v"))).first()
        if seen == tuple(state):
            return current.select(F.col("u").alias("node"), F.col("v").alias("root")).union(
                current.select(F.col("v").alias("node"), F.col("v").alias("root")).distinct()
            )
        seen = tuple(state)
        current = materialize(_small_star(_large_star(current)), tag)


def _large_star(edges: DataFrame) -> DataFrame:
    both = edges.union(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
    low = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
    return both.join(low, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()


def _small_star(edges: DataFrame) -> DataFrame:
    down = edges.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct()
    low = down.groupBy("u").agg(F.min("v").alias("m"))
    moved = down.join(low, "u").where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
    return moved.union(low.select("u", F.col("m").alias("v"))).distinct()
