"""Toxicity: FTRL-proximal logistic regression over hashed word n-grams and skip-grams.

Features are the distinct hashed words, word pairs and pairs with up to ``skip`` words between of the whole
lower-cased text. Each coordinate has its own learning rate; L1 keeps most weights at zero, so the model that is sent
to the executors is a short list of coordinates. It is fitted in one task on a bounded sample of labelled rows
(``max_rows``, the lowest hashes of doc_id, one text each), and scores every text. The driver gets the weights only.

Defined results: null and empty texts get the score of the bias; labels that are null are not learned from; a doc_id
with several labels counts as toxic if one says so; of several texts with one doc_id that with the lowest hash teaches;
without labelled rows all scores are 0; repeated rows score alike;
other columns play no part or pass through; an empty table gives an empty result.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import kernels


def held_out(doc_id: Column) -> Column:
    """The documents that nothing is learned from."""
    return F.crc32(doc_id.cast("string").cast("binary")) % 4 == 2


@dataclass
class ToxicityModel:
    at: np.ndarray
    weights: np.ndarray
    bias: float
    bits: int
    skip: int

    def score(self, text: Column) -> Column:
        bound = kernels.gram_scorer(self.at, self.weights, self.bias, self.bits, self.skip)
        return F.pandas_udf(bound, "double")(text)


def training_rows(docs: DataFrame, labels: DataFrame, max_rows: int) -> DataFrame:
    """(label, text) of at most ``max_rows`` labelled documents (a bounded sample) that are not held out."""
    known = labels.where(F.col("doc_id").isNotNull() & F.col("toxic").isNotNull() & ~held_out(F.col("doc_id")))
    known = known.groupBy("doc_id").agg(F.max(F.col("toxic").cast("int")).alias("label"))
    sample = known.orderBy(F.md5(F.col("doc_id").cast("string").cast("binary")), "doc_id").limit(max_rows)
    rows = docs.select("doc_id", "text").join(F.broadcast(sample), "doc_id")  # at most max_rows ids
    one = F.min(F.struct(F.xxhash64("text").alias("h"), "text"))["text"].alias("text")  # and a row of each
    return rows.groupBy("doc_id", "label").agg(one).select("label", "text")


def fit_toxicity(docs: DataFrame, labels: DataFrame, max_rows: int = 8000, bits: int = 20, skip: int = 1, alpha: float = 3.0, beta: float = 1.0, l1: float = 6.0, l2: float = 0.0, epochs: int = 10, seed: int = 3) -> ToxicityModel:
    """Learns from ``training_rows``, whose features (a few KB each) meet in one task."""
    grams = training_rows(docs, labels, max_rows).mapInPandas(kernels.gram_rows(bits, skip), "label int, grams binary")
    trainer = kernels.ftrl_rows(bits, alpha, beta, l1, l2, epochs, seed)
    fitted = grams.repartition(1).mapInPandas(trainer, "at binary, weights binary, bias double").collect()  # one row, or none
    if not fitted:
        return ToxicityModel(np.zeros(0, np.uint32), np.zeros(0), -40.0, bits, skip)
    at, weights, bias = fitted[0]
    return ToxicityModel(np.frombuffer(at, np.uint32), np.frombuffer(weights), bias, bits, skip)


def score_toxicity(docs: DataFrame, model: ToxicityModel, threshold: float = 0.3, text_col: str = "text") -> DataFrame:
    """docs with ``score`` and ``predicted`` added (1 where score >= threshold)."""
    scored = docs.withColumn("score", model.score(F.col(text_col)))
    return scored.withColumn("predicted", (F.col("score") >= threshold).cast("int"))
