import pytest

from pyspark.sql import functions as F

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"


@pytest.fixture(scope="session")
def make_docs(spark):
    def make(rows, clash=False):
        """rows: (doc_id, text) or with lang and source. clash adds columns named as operators name theirs."""
        full = [(r[0], r[1], r[2] if len(r) > 2 else "en", r[3] if len(r) > 3 else "src0", len(r[1] or "")) for r in rows]
        df = spark.createDataFrame(full, SCHEMA)
        for c in ("set", "h1", "h2", "n", "id", "epoch", "score", "label", "pos", "leaf", "tokens", "item", "did", "tpl", "raw") if clash else ():
            df = df.withColumn(c, F.lit("clash"))
        return df

    return make


@pytest.fixture(scope="session")
def odd_docs(make_docs):
    """Nulls in any column, empty and blank texts, repeated rows, a long text, a token without an end."""
    long = " ".join(f"word{i % 977}" for i in range(60_000))
    rows = [(None, None, None, None), (1, None), (2, ""), (3, " \n\n "), (4, "one"), (4, "one"), (5, long, None, "src1"), (6, long, "fr", None), (7, "x" * 300_000), (None, "a null id with a text of its own here"), (None, "a null id with a text of its own here")]
    return make_docs(rows, clash=True)
