import compare
from pyspark.sql import functions as F

from stagedrel.llm import mixing, oracles
from stagedrel.llm.queries import DOMAINS, WEIGHTS, op1_mixing

SF = "/root/testdata/sf0.001"


def test_query_equals_sql(spark):
    assert compare.differs(op1_mixing(spark, SF), compare.duck(SF), oracles.mixing(DOMAINS, WEIGHTS)) is None


def leaves(spark, rows):
    return spark.createDataFrame(rows, "a string, b string, tokens long")


def quotas(spark, rows, weights, budget, epochs=1):
    out = mixing.leaf_budgets(leaves(spark, rows), ["a", "b"], weights, F.lit(budget), epochs)
    return {(r["a"], r["b"]): r["quota"] for r in out.collect()}


def test_budgets_follow_weights(spark):
    got = quotas(spark, [("x", "p", 1000), ("x", "q", 1000), ("y", "p", 1000)], {"a": {"x": 3}, "b": {"p": 2}}, 400)
    assert got == {("x", "p"): 200, ("x", "q"): 100, ("y", "p"): 100}


def test_siblings_take_a_shortage_before_other_families(spark):
    got = quotas(spark, [("x", "p", 10), ("x", "q", 1000), ("y", "p", 1000)], {}, 400)
    assert got == {("x", "p"): 10, ("x", "q"): 190, ("y", "p"): 200}
    got = quotas(spark, [("x", "p", 10), ("x", "q", 50), ("y", "p", 1000)], {}, 400)
    assert got == {("x", "p"): 10, ("x", "q"): 50, ("y", "p"): 340}


def test_zero_weight_and_more_budget_than_tokens(spark):
    got = quotas(spark, [("x", "p", 10), ("y", "p", 10)], {"a": {"x": 0}}, 400, 2)
    assert got == {("x", "p"): 0, ("y", "p"): 20}


def test_prefixes_and_epochs(spark, make_docs):
    docs = make_docs([(i, "w " * (1 + i % 5)) for i in range(300)])
    total = sum(1 + i % 5 for i in range(300))
    got = mixing.mix(docs, ("lang",), budget_tokens=total + 100, max_epochs=2).collect()
    first, second = [r for r in got if r["epoch"] == 0], [r for r in got if r["epoch"] == 1]
    assert len(first) == 300 and 100 <= sum(r["n_tokens"] for r in second) < 105
    other = mixing.mix(docs.repartition(7), ("lang",), budget_tokens=total + 100, max_epochs=2).collect()
    assert sorted((r["doc_id"], r["epoch"]) for r in got) == sorted((r["doc_id"], r["epoch"]) for r in other)


def test_odd_rows_and_empty(odd_docs, make_docs):
    out = mixing.mix(odd_docs, ("lang", "source"), budget_share=1.0, max_epochs=1)
    tokens = sum(r["n_tokens"] for r in out.collect())
    assert tokens == 60_000 * 2 + 2 + 1 + 20
    assert mixing.mix(make_docs([]), ("lang",)).count() == 0
