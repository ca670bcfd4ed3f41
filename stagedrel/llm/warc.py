"""WARC archives: a writer with revisit records and a reader that salvages damaged files.

Writing: each partition rolls archives of gzip members, one record each, through a file system that all executors
reach. A record's payload of at least ``min_revisit`` bytes that a record with a larger id holds too is written as a
revisit of that one. The manifest of archives is a table written once, so files of lost attempts are never read.

Control characters of a url are percent-encoded in the header, which may be of any length up to a record's limit.

Reading: an archive is read in blocks. Every record must inflate, begin with a version line, have its length and its
SHA-1 digest. After a failed check the reader searches for the next member or version line whose record passes,
logs the bytes between as a quarantined gap with the reason, and goes on. Memory holds one record (256 MB at most, a
longer one fails its check) and a block.

Defined results: a null text is an empty payload; null ids come before all others; rows with equal id and payload
are written alike (both responses, or both revisits); an empty table writes no archive and reads as no rows; other
columns play no part.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import kernels
from .common import materialize, shared_dir, small

RECORDS = "path string, offset long, status string, reason string, gap_bytes long, record_type string, record_id string, uri string, page_id long, refers_to long, payload_bytes long, payload_digest string, payload binary"


def with_revisits(pages: DataFrame, min_revisit: int = 1000, id_col: str = "page_id", uri_col: str = "url", text_col: str = "html") -> DataFrame:
    """(page_id, uri, payload, digest, bytes, record_type, refers_to) per row of pages."""
    rows = pages.select(F.col(id_col).cast("long").alias("page_id"), F.col(uri_col).cast("string").alias("uri"), F.coalesce(F.col(text_col), F.lit("")).cast("binary").alias("payload"))
    rows = rows.withColumns({"digest": F.sha1("payload"), "bytes": F.octet_length("payload").cast("long")})
    keeper = rows.where(F.col("bytes") >= min_revisit).groupBy("digest").agg(F.max("page_id").alias("keeper"), F.count("*").alias("copies"))
    keeper = small(materialize(keeper.where("copies > 1").drop("copies"), "warc-keepers"))  # payloads are shuffled only if there are very many
    again = F.col("keeper").isNotNull() & (F.col("page_id").isNull() | (F.col("page_id") < F.col("keeper")))
    return rows.join(keeper, "digest", "left").select(
        "page_id", "uri", F.when(again, F.lit(None)).otherwise(F.col("payload")).alias("payload"), "digest", "bytes",
        F.when(again, "revisit").otherwise("response").alias("record_type"), F.when(again, F.col("keeper")).alias("refers_to"),
    )


def write_archives(pages: DataFrame, folder: str | None = None, roll_bytes: int = 64 << 20, **how) -> DataFrame:
    """Writes the archives and returns their manifest (path, records, bytes), itself a written table."""
    folder = folder or f"{shared_dir(pages.sparkSession)}/warc"
    write = kernels.archive_writer(folder, roll_bytes)
    rows = with_revisits(pages, **how)
    rows = rows.withColumns({c: F.col(c).cast("string") for c in ("page_id", "refers_to")})
    return materialize(rows.mapInPandas(write, "path string, records long, bytes long"), "warc-manifest")


def read_archives(spark: SparkSession, manifest: DataFrame, payloads: bool = True, block: int = 4 << 20) -> DataFrame:
    """Records and gaps of the archives in ``manifest.path``; status is ``record`` or ``gap``."""
    read = kernels.archive_reader(payloads, block)
    paths = manifest.select("path")
    return paths.repartition(max(1, spark.sparkContext.defaultParallelism) * 4).mapInPandas(read, RECORDS)
