"""Queries of the training-data operators over their whole tables, and their SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import oracles
from .chat_snapshots import render_chats
from .decontaminate import leaks
from .license_index import BASE, LOWER, UPPER, licence_index, scan_licenses
from .line_templates import drop_recurring_lines
from .mixing import mix, token_count
from .ngram_join import jaccard_links
from .ppm_language import fit_languages, predict_language
from .ppm_language import held_out as held_out_lang
from .projection_passes import vector_links
from .toxicity import fit_toxicity, score_toxicity
from .toxicity import held_out as held_out_toxic
from .warc import read_archives, write_archives

#: The mixture of the queries and the pipeline. A source's domain is its number modulo 4.
DOMAINS = ("web", "reference", "forum", "code")
WEIGHTS = {"domain": {"web": 4, "reference": 3, "forum": 2, "code": 1}, "lang": {"en": 6, "fr": 2, "de": 2, "es": 2}}


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def with_domain(docs: DataFrame) -> DataFrame:
    number = F.try_element_at(F.regexp_extract_all("source", F.lit(r"(\d{1,6})")), F.lit(1)).cast("int")
    return docs.withColumn("domain", F.get(F.array(*[F.lit(d) for d in DOMAINS]), number % len(DOMAINS)))


def op1_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = with_domain(table(spark, sf_dir, "documents").select("doc_id", "lang", "source", token_count(F.col("text")).alias("tokens")))
    mixed = mix(docs, weights=WEIGHTS, tokens_col="tokens")
    return mixed.select("doc_id", "domain", "lang", "source", "epoch", "n_tokens")


def op2_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    read = read_archives(spark, write_archives(table(spark, sf_dir, "pages")), payloads=False)
    return read.where("status = 'record'").select("page_id", "payload_bytes", "payload_digest", "record_type", "refers_to")


def op3_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    return drop_recurring_lines(table(spark, sf_dir, "documents").select("doc_id", "text"))


def op4_licenses(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan_licenses(table(spark, sf_dir, "documents"))


def op5_chats(spark: SparkSession, sf_dir: str) -> DataFrame:
    return render_chats(table(spark, sf_dir, "conversations"))


def op6_leaks(spark: SparkSession, sf_dir: str) -> DataFrame:
    return leaks(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark")).drop("h1", "h2")


def op7_vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    return vector_links(table(spark, sf_dir, "embeddings"))


def op8_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    model = fit_toxicity(docs, table(spark, sf_dir, "labels"))
    scored = score_toxicity(docs.select("doc_id", "text"), model)
    return scored.select("doc_id", F.coalesce(held_out_toxic(F.col("doc_id")), F.lit(False)).alias("held_out"), "score", "predicted")


def op9_jaccard(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard_links(table(spark, sf_dir, "documents")).select("doc_id", "n_links", "class_id")


def op10_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    predicted = predict_language(docs.select("doc_id", "text"), fit_languages(docs))
    return predicted.select("doc_id", F.coalesce(held_out_lang(F.col("doc_id")), F.lit(False)).alias("held_out"), "lang_pred", "score")


QUERIES = {f.__name__: f for f in (op1_mixing, op2_warc, op3_lines, op4_licenses, op5_chats, op6_leaks, op7_vectors, op8_toxicity, op9_jaccard, op10_language)}
ORACLE_SQL = {"op1_mixing": oracles.mixing(DOMAINS, WEIGHTS), "op2_warc": oracles.WARC, "op4_licenses": oracles.licenses(BASE, licence_index()[0], UPPER, LOWER), "op5_chats": oracles.CHATS, "op7_vectors": oracles.VECTORS, "op9_jaccard": oracles.JACCARD}
