from collections import Counter

import corpus_pipeline as P
from stagedrel.llm.queries import table

SF = "/root/testdata/sf0.01"


def test_stages_and_run(spark):
    assert [n for n, _ in P.STAGES] == ["toxicity", "line_dedup", "near_duplicates", "decontamination", "mixing"]
    docs, sizes = table(spark, SF, "documents"), {}
    labels = {r["doc_id"]: r["toxic"] for r in table(spark, SF, "labels").collect()}
    first = docs.count()
    for name, f in P.STAGES:
        docs = P.materialize(f(spark, docs, SF), "test")
        sizes[name] = docs.count()
        if name != "mixing":
            assert docs.columns == P.COLUMNS
        if name == "toxicity":
            left = Counter(labels.get(r["doc_id"]) for r in docs.select("doc_id").collect())
            assert left[1] < 0.6 * sum(labels.values()) and left[0] > 0.98 * (len(labels) - sum(labels.values()))
    assert first > sizes["toxicity"] == sizes["line_dedup"] > sizes["near_duplicates"] > sizes["decontamination"] > 0
    again = P.run(spark, SF)
    assert sorted(map(tuple, again.select("doc_id", "epoch").collect())) == sorted(map(tuple, docs.select("doc_id", "epoch").collect()))


def test_odd_rows_and_empty(spark, odd_docs, make_docs):
    for docs in (odd_docs.select(*P.COLUMNS), make_docs([]), odd_docs):
        for _, f in P.STAGES:
            docs = P.materialize(f(spark, docs, SF), "odd")
        assert set(P.COLUMNS) <= set(docs.columns)
