import re

from stagedrel.llm.decontaminate import leaks, without_leaks
from stagedrel.llm.queries import op6_leaks, table

SF = "/root/testdata/sf0.01"
ITEM = "A train leaves the station at 9 with Anna on board and travels 120 km in 3 hours before Anna gets off at the lake"


def bench(spark, *texts):
    return spark.createDataFrame(list(enumerate(texts)), "item_id long, text string").selectExpr("*", "'x' as h1", "1 as doc_id")


def hits(spark, docs, *items):
    return {(r["doc_id"], r["item_id"]): r for r in leaks(docs, bench(spark, *items)).collect()}


def test_query_finds_every_passage(spark):
    flat = lambda t: " ".join(re.findall(r"\w+", t.lower()))
    items = [(r["item_id"], flat(r["text"])) for r in table(spark, SF, "benchmark").collect()]
    want = {(r["doc_id"], i) for r in table(spark, SF, "documents").collect() for i, t in items if t in flat(r["text"])}
    got = {(r["doc_id"], r["item_id"]) for r in op6_leaks(spark, SF).collect()}
    assert want and want == got


def test_other_numbers_names_and_units(spark, make_docs):
    other = ITEM.replace("Anna", "Boris").replace("120 km", "85 miles").replace("at 9", "at 11")
    mixed = ITEM.replace("Anna on", "Boris on")
    docs = make_docs([(1, "Some words before. " + ITEM + ". And after."), (2, other.upper()[:1] + other[1:]), (3, mixed), (4, ITEM.lower()), (5, "A train is late and nothing else is the same in this text at all")], clash=True)
    got = hits(spark, docs, ITEM)
    assert {k[0] for k in got} >= {1, 2, 4} and 5 not in {k[0] for k in got}
    assert got[(1, 0)]["verbatim"] and not got[(2, 0)]["verbatim"]
    assert 3 not in {k[0] for k in got}  # Anna can't be Boris here and Anna there


def test_letter_cases(spark, make_docs):
    docs = make_docs([(1, "BEFORE!! " + ITEM.upper() + "!! AFTER"), (2, ITEM.title()), (3, ITEM.lower()), (4, "he said, " + ITEM)])
    assert {k[0] for k in hits(spark, docs, ITEM)} == {1, 2, 3, 4}


def test_parts_of_a_passage(spark, make_docs):
    words = [f"{a}{b}o" for a in "bcdfgh" for b in "klmnpq"]
    item = " ".join(words)
    docs = make_docs([(1, " ".join(words[5:30])), (2, " ".join(words[:9]) + " and then quite other things follow here until the end")])
    assert {k[0] for k in hits(spark, docs, item)} == {1}


def test_short_items_at_every_offset(spark, make_docs):
    words = [f"{a}{b}u" for a in "bcdfgh" for b in "klmnpq"]
    items = [" ".join(words[10 * k : 10 * k + n]) for k, n in enumerate((8, 9, 10))]
    docs = make_docs([(100 * k + at, " ".join(["so"] * at + [t] + ["and", "then", "more"])) for k, t in enumerate(items) for at in range(8)])
    assert set(hits(spark, docs, *items)) == {(100 * k + at, k) for k in range(3) for at in range(8)}


def test_short_items_of_numbers_and_names(spark, make_docs):
    few, bare = "is 12 plus 30 minus 7 above 31", "12 30 45 km 17 19 23 29 31"
    docs = make_docs([(10 * k + at, " ".join(["so"] * at + [t] + ["and", "then", "more"])) for k, t in enumerate((few, bare)) for at in range(5)])
    other = make_docs([(90, "so is 13 plus 40 minus 8 above 32 then"), (91, "1 2 3 km 4 5 6 7 8 9"), (92, "is 12 times 30 over 7 below 31")])
    got = hits(spark, docs.union(other), few, bare)
    assert set(got) == {(10 * k + at, k) for k in range(2) for at in range(5)} | {(90, 0)}


def test_runs_at_every_offset(spark, make_docs):
    """A run of 9 tokens of an item of 16 is over half of it, wherever it stands; items of 5 to 7 tokens are met as a whole, shorter ones not."""
    words = [f"{a}{b}u" for a in "bcdfgh" for b in "klmnpq"]
    long, shorts = " ".join(words[:16]), [" ".join(words[20 : 20 + n]) for n in (4, 5, 6, 7)]
    docs = [(100 * k + at, " ".join(["so"] * at + words[k : k + 9] + ["and", "then", "more"])) for k in range(8) for at in range(9)]
    docs += [(10_000 + 10 * n + at, " ".join(["and"] * at + words[20 : 20 + n] + ["so"])) for n in (4, 5, 6, 7) for at in range(3)]
    got = set(hits(spark, make_docs(docs), long, *shorts))
    assert {(d, i) for d, i in got if i == 0} == {(100 * k + at, 0) for k in range(8) for at in range(9)}
    assert {(d, i) for d, i in got if i > 0} == {(10_000 + 10 * n + at, i) for i, m in ((2, 5), (3, 6), (4, 7)) for n in (4, 5, 6, 7) if n >= m for at in range(3)}


def test_slots_are_checked_against_brute_force(spark, make_docs):
    """One question with other figures and names in each slot: leaked if equal slots stay equal and unequal ones unequal."""
    import itertools

    item = "the red boat of Anna sails 12 miles with Carl on board before Anna rows 30 km home to the old lake"
    docs, want = [], set()
    for n, (a, b, c, x, y) in enumerate(itertools.product(("Anna", "Olga"), ("Carl", "Olga"), ("Anna", "Olga"), ("12", "30"), ("30", "7"))):
        docs.append((n, f"so the red boat of {a} sails {x} miles with {b} on board before {c} rows {y} km home to the old lake again"))
        if a == c and a != b and x != y:
            want.add(n)
    assert {d for d, _ in hits(spark, make_docs(docs), item)} == want


def test_odd_rows_and_empty(spark, odd_docs, make_docs):
    assert {k[0] for k in hits(spark, odd_docs, "a null id with a text of its own here", "", "one two", None)} == {None}
    assert not hits(spark, make_docs([]), ITEM) and not hits(spark, odd_docs.limit(3))
    kept = without_leaks(odd_docs, bench(spark, "a null id with a text of its own here"))
    assert kept.count() == odd_docs.count() - 2 and kept.columns == odd_docs.columns
