"""Language identification by partial matching: variable-order byte context trees with escapes.

Every language has a tree of byte contexts; a text's code length under a language's frozen counts is exact, over all
its bytes, and the shortest code wins. The score is the winner's share of 2^-length over the languages. Trees are
fitted in the driver on a bounded sample: about ``sample_docs`` documents a language, chosen by a hash of doc_id, one
text each, up to ``sample_bytes`` characters a language (both documented bounds). Texts of up to a quarter of it teach
first; every language keeps one text at least, and if that is longer than the bound it teaches by pieces taken evenly
from all of it. The bounds hold for fitting only, never for scoring.

Defined results: null texts and texts without a letter are ``und`` with score 0; rows whose lang is null teach
nothing; equal code lengths go to the language that sorts first; without any labelled text all is ``und``; other
columns play no part or pass through; an empty table gives an empty result.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from . import kernels


def held_out(doc_id: Column) -> Column:
    """The documents that nothing is learned from."""
    return F.crc32(doc_id.cast("string").cast("binary")) % 3 == 1


def fit_languages(docs: DataFrame, order: int = 4, sample_docs: int = 200, sample_bytes: int = 400_000, lang_col: str = "lang", text_col: str = "text", id_col: str = "doc_id") -> kernels.ContextTrees:
    """Trees learned from rows that are not held out and have a language and a text."""
    usable = docs.where(F.col(lang_col).isNotNull() & F.col(id_col).isNotNull() & ~held_out(F.col(id_col)))
    count = {r[0]: r[1] for r in usable.groupBy(F.col(lang_col).cast("string").alias("k")).count().collect()}  # a row per language
    key = F.md5(F.col(id_col).cast("string").cast("binary"))
    cuts = [(lang, f"{min(int(share * 16**8), 16**8 - 1):08x}" if (share := min(1.0, sample_docs / n)) < 1 else "g") for lang, n in count.items()]
    if not cuts:
        return kernels.ContextTrees(order).fit({})
    cuts = F.broadcast(docs.sparkSession.createDataFrame(cuts, "lang string, cut string"))  # a row per language
    rows = usable.where(F.length(text_col) > 0).select(F.col(lang_col).cast("string").alias("lang"), key.alias("key"), F.col(text_col).alias("text"))
    rows = rows.join(cuts, "lang")
    first = rows.groupBy("lang").agg(F.min("key").alias("first"))  # a language whose cut holds no row keeps one all the same
    rows = rows.join(F.broadcast(first), "lang").where((F.substring("key", 1, 8) < F.col("cut")) | (F.col("key") == F.col("first")))
    size = F.length("text")
    rows = rows.groupBy("lang", "key").agg(F.min(F.struct(size.alias("size"), F.xxhash64("text").alias("h"), "text")).alias("x")).select("lang", "key", "x.size", "x.text")
    late = (F.col("size") > sample_bytes // 4).cast("int")
    order_by = W.partitionBy("lang").orderBy(late, F.when(late == 1, F.col("size")).otherwise(0), "key")  # rows of the sample only
    rows = rows.withColumns({"before": F.sum("size").over(order_by), "n": F.row_number().over(order_by)}).where((F.col("before") <= sample_bytes) | (F.col("n") == 1))
    piece = sample_bytes // 100
    spread = F.array_join(F.transform(F.sequence(F.lit(0), F.lit(99)), lambda i: F.substring(F.col("text"), (F.col("size") / 100 * i).cast("int") + 1, F.lit(piece))), "")
    got = rows.select("lang", "key", F.when(size > sample_bytes, spread).otherwise(F.col("text")).alias("text")).collect()  # sample_bytes a language at most
    texts: dict[str, list[str]] = {}
    for lang, _, text in sorted(map(tuple, got)):
        texts.setdefault(lang, []).append(text)
    return kernels.ContextTrees(order).fit(texts)


def predict_language(docs: DataFrame, trees: kernels.ContextTrees, text_col: str = "text") -> DataFrame:
    """docs with ``lang_pred`` and ``score`` added."""
    shared = docs.sparkSession.sparkContext.broadcast(vars(trees))  # bounded by the sample: at most its bytes times the order in nodes
    make, rebuilt = kernels.language_scorer, kernels.ContextTrees.of

    def run(texts):
        import pandas as pd

        return pd.DataFrame(make(rebuilt(shared.value))(texts), columns=["lang", "score"])

    both = F.pandas_udf(run, "lang string, score double")(F.col(text_col))
    out = docs.withColumn("__lang", both)
    return out.withColumns({"lang_pred": F.col("__lang.lang"), "score": F.col("__lang.score")}).drop("__lang")
