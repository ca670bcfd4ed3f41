"""Stage tables: written once in the folder that the cluster shares, and read back."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession


def stage_dir(spark: SparkSession) -> str:
    """spark.checkpoint.dir; a local folder only where the session is local and has none."""
    at = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir", None)
    if at:
        return at.rstrip("/")
    master = spark.sparkContext.master
    if master.startswith("local") and not master.startswith("local-cluster"):
        return "file:///tmp/checkpoints"
    raise ValueError("spark.checkpoint.dir must name a folder that all executors share")


def write_stage(df: DataFrame, name: str, partition_by: tuple[str, ...] = ()) -> DataFrame:
    """Writes a stage's table once (partitioned for pruning if asked) and reads it: model calls aren't repeated, lineage ends here."""
    path = f"{stage_dir(df.sparkSession)}/{name}-{uuid.uuid4().hex}"
    df.write.partitionBy(*partition_by).parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def append_new(df: DataFrame, path: str, key: list[str]) -> int:
    """Appends rows whose key the table at path does not hold yet (idempotent); the number of rows added."""
    spark = df.sparkSession
    try:
        known = spark.read.parquet(path).select(*key)
    except Exception as e:  # no table yet
        if "PATH_NOT_FOUND" not in str(e):
            raise
        known = None
    fresh = write_stage(df if known is None else df.join(known, key, "left_anti"), "append")
    fresh.write.mode("append").parquet(path)
    return fresh.count()


def export_chat_lines(df: DataFrame, path: str) -> None:
    """One JSON text a line, from a column ``line``."""
    df.select("line").write.text(path)


def export_report(metrics: DataFrame, path: str) -> None:
    metrics.write.option("header", True).csv(path)


def binary_pictures(spark: SparkSession, path: str) -> DataFrame:
    """Real pictures as another carrier of images: path, size and bytes."""
    return spark.read.format("binaryFile").load(path).select("path", "length", "content")
