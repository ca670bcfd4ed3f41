import math
import random
import zlib
from collections import defaultdict

import numpy as np
import pandas as pd
from pyspark.sql import functions as F

from stagedrel.llm import kernels
from stagedrel.llm.queries import op8_toxicity, table
from stagedrel.llm.toxicity import fit_toxicity, score_toxicity, training_rows

SF = "/root/testdata/sf0.1"
WORDS = [f"{a}{b}{c}" for a in "bdfgk" for b in "aeiou" for c in "lmnrst"]


def labelled(make_docs, spark, n=400):
    rng = random.Random(1)
    rows = []
    for i in range(n):
        words = rng.choices(WORDS, k=60)
        if i % 5 == 0:
            words[rng.randrange(60)] = "vileword"
        rows.append((i, " ".join(words)))
    return make_docs(rows, clash=True), spark.createDataFrame([(i, 1, int(i % 5 == 0)) for i in range(n)], "doc_id long, quality int, toxic int")


def test_held_out_rows_of_the_query(spark):
    rows = op8_toxicity(spark, SF).join(table(spark, SF, "labels"), "doc_id").where("held_out").collect()
    toxic, clean = [r for r in rows if r["toxic"] == 1], [r for r in rows if r["toxic"] == 0]
    assert sum(r["predicted"] for r in toxic) >= 0.75 * len(toxic)
    assert sum(r["predicted"] for r in clean) <= 0.01 * len(clean)
    assert all(0 <= r["score"] <= 1 and r["predicted"] == int(r["score"] >= 0.3) for r in rows)
    assert all(r["held_out"] == (zlib.crc32(str(r["doc_id"]).encode()) % 4 == 2) for r in rows)


def test_labels_of_held_out_rows_teach_nothing(spark, make_docs):
    docs, labels = labelled(make_docs, spark)
    out = F.crc32(F.col("doc_id").cast("string").cast("binary")) % 4 == 2
    other = labels.withColumn("toxic", F.when(out, 1 - F.col("toxic")).otherwise(F.col("toxic")))
    a, b = fit_toxicity(docs, labels), fit_toxicity(docs.repartition(5), other.repartition(3))
    assert a.at.tolist() == b.at.tolist() and abs(a.weights - b.weights).max() < 1e-12 and 0 < len(a.at) < 2000
    got = score_toxicity(docs, a).collect()
    assert all(r["predicted"] == int(r["doc_id"] % 5 == 0) for r in got)


def slow_ftrl(rows, bits, alpha, beta, l1, l2, epochs, seed):
    """The update rule with dictionaries, coordinate by coordinate."""
    z, n, bias = defaultdict(float), defaultdict(float), 1 << bits

    def weight(i):
        return 0.0 if abs(z[i]) <= l1 else -(z[i] - math.copysign(l1, z[i])) / ((beta + math.sqrt(n[i])) / alpha + l2)

    rng = np.random.default_rng(seed)
    for _ in range(epochs):
        for k in rng.permutation(len(rows)):
            y, grams = rows[k]
            on = [*map(int, grams), bias]
            w = {i: weight(i) for i in on}
            g = 1 / (1 + math.exp(-sum(w.values()))) - y
            for i in on:
                z[i] += g - (math.sqrt(n[i] + g * g) - math.sqrt(n[i])) / alpha * w[i]
                n[i] += g * g
    return {i: weight(i) for i in z if i != bias and weight(i)}, weight(bias)


def test_weights_equal_a_plain_ftrl():
    rng = np.random.default_rng(1)
    rows = [(int(k % 3 == 0), np.unique(np.append(rng.integers(0, 200, 20), 7 if k % 3 == 0 else 9)).astype(np.uint32)) for k in range(120)]
    for l1, l2 in ((0.5, 0.0), (1.0, 0.3)):
        at, weights, bias = kernels.ftrl(rows, 8, 0.5, 1.0, l1, l2, 3, 5)
        slow, slow_bias = slow_ftrl(rows, 8, 0.5, 1.0, l1, l2, 3, 5)
        assert sorted(slow) == at.tolist() and all(abs(slow[i] - w) < 1e-9 for i, w in zip(at.tolist(), weights, strict=True)) and abs(bias - slow_bias) < 1e-9


def test_grams_by_the_definition():
    """Words, pairs of neighbours, and pairs with one word between: as many features as there are different ones."""
    words = "a b c a b d".split()
    h = kernels.word_hasher()(words)
    want = len({*words, *zip(words, words[1:], strict=False), *((x, "", y) for x, y in zip(words, words[2:], strict=False))})
    assert len(kernels.gram_hashes(h, 30, 1)) == want


def test_a_repeated_id_teaches_once(spark, make_docs):
    docs, labels = labelled(make_docs, spark, 50)
    many = docs.union(make_docs([(7, f"other text {i}") for i in range(3000)], clash=True))
    assert sum(1 for _ in learned(many, labels)) <= 50


def learned(docs, labels):
    seen = []
    real = kernels.ftrl
    try:
        kernels.ftrl = lambda rows, *a: (seen.extend(rows), real(rows, *a))[1]
        fit_toxicity(docs, labels)
    finally:
        kernels.ftrl = real
    return seen


def test_odd_rows_and_empty(spark, odd_docs, make_docs):
    docs, labels = labelled(make_docs, spark)
    strange = spark.createDataFrame([(None, 1, 1), (1, 1, None), (3, 0, 0), (3, 0, 1)], labels.schema)
    model = fit_toxicity(docs, labels.union(strange))
    got = score_toxicity(odd_docs, model)
    assert got.count() == odd_docs.count() and got.where("score is null or score < 0 or score > 1").count() == 0
    assert score_toxicity(make_docs([]), model).count() == 0
    none = fit_toxicity(docs, labels.limit(0))
    assert score_toxicity(docs, none).where("predicted = 1").count() == 0


def test_the_driver_gets_weights_only(spark, make_docs, monkeypatch):
    """The features of the learning sample stay in Spark: the driver collects one row of weights while it fits."""
    docs, labels = labelled(make_docs, spark)
    sizes, collect = [], type(docs).collect
    monkeypatch.setattr(type(docs), "collect", lambda df: (got := collect(df), sizes.append((len(got), sum(len(x) for r in got for x in r if isinstance(x, (bytes, bytearray))))))[0])
    model = fit_toxicity(docs, labels)
    assert sizes == [(1, model.at.nbytes + model.weights.nbytes)]


def test_weights_of_the_task_equal_those_of_all_rows_at_once(spark, make_docs):
    docs, labels = labelled(make_docs, spark)
    rows = training_rows(docs, labels, 8000).collect()
    gram = next(kernels.gram_rows(20, 1)([pd.DataFrame(rows, columns=["label", "text"])]))
    data = [(y, np.frombuffer(g, np.uint32)) for y, g in sorted(zip(gram["label"], gram["grams"], strict=True))]
    at, weights, bias = kernels.ftrl(data, 20, 3.0, 1.0, 6.0, 0.0, 10, 3)
    model = fit_toxicity(docs, labels)
    assert model.at.tolist() == at.tolist() and model.weights.tolist() == weights.tolist() and model.bias == bias


def test_a_repeated_id_is_one_training_row(spark, make_docs):
    docs, labels = labelled(make_docs, spark, 50)
    many = docs.union(make_docs([(7, f"other text {i}") for i in range(3000)], clash=True))
    assert 0 < training_rows(many, labels, 8000).count() <= 50 and training_rows(many, labels, 9).count() == 9
