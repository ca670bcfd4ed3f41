import math
import random
import re

import compare

from stagedrel.llm import oracles
from stagedrel.llm.common import components
from stagedrel.llm.ngram_join import bands_and_rows, jaccard_links, one_of_each_class
from stagedrel.llm.queries import op9_jaccard

SF = "/root/testdata/sf0.01"


def shingles(t):
    w = re.findall(r"\w+", (t or "").lower())
    n = min(5, len(w))
    return {tuple(w[i : i + n]) for i in range(len(w) - n + 1)} if w else set()


def brute(rows):
    s = [shingles(t) for _, t in rows]
    link = [[j for j in range(len(s)) if j != i and s[i] and len(s[i] & s[j]) >= 0.8 * len(s[i] | s[j])] for i in range(len(s))]
    out = []
    for i, (d, _) in enumerate(rows):
        seen, todo = {i}, [i]
        while todo:
            for j in link[todo.pop()]:
                if j not in seen:
                    seen.add(j)
                    todo.append(j)
        known = [rows[k][0] for k in seen if rows[k][0] is not None]
        out.append((d, len(link[i]), min(known) if known else d))
    return sorted(out, key=repr)


def ours(df):
    return sorted(((r["doc_id"], r["n_links"], r["class_id"]) for r in df.collect()), key=repr)


def corpus(n_near=120, edits=2):
    rng = random.Random(2)
    word = lambda: "".join(rng.choices("abcdefghij", k=5))
    base = [word() for _ in range(90)]
    rows = []
    for i in range(n_near):
        w = list(base)
        for _ in range(rng.randrange(edits + 1)):
            w[rng.randrange(90)] = word()
        rows.append((1000 - i, " ".join(w)))
    copy = " ".join(word() for _ in range(40))
    rows += [(2000 + i, copy) for i in range(40)] + [(2000, copy), (1, copy.upper())]
    rows += [(3000 + i, " ".join(word() for _ in range(60))) for i in range(50)]
    return rows


def test_query_equals_sql(spark):
    assert compare.differs(op9_jaccard(spark, SF), compare.duck(SF), oracles.JACCARD) is None


def test_links_of_large_groups(make_docs):
    rows = corpus()
    assert ours(jaccard_links(make_docs(rows, clash=True), tile=16)) == brute(rows)


def test_groups_beyond_the_bands_fall_apart_into_them(make_docs):
    """Tiles of two texts: the group has more tiles than there are bands."""
    rows = corpus()
    want, got = {w[0]: w for w in brute(rows)}, {r[0]: r for r in ours(jaccard_links(make_docs(rows), tile=2))}
    assert all(got[d][1] <= w[1] and got[d][2] == w[2] for d, w in want.items())
    assert sum(g[1] for g in got.values()) >= 0.995 * sum(w[1] for w in want.values())


def test_unlike_texts_tied_together_have_no_links(make_docs):
    """A chain of texts of which each shares half of its words with the next, with bands of one row: all are one candidate group."""
    rng = random.Random(4)
    words = ["".join(rng.choices("abcdefghij", k=6)) for _ in range(3000)]
    rows = [(i, " ".join(words[20 * i : 20 * i + 40])) for i in range(140)]
    for tile in (96, 1):
        assert ours(jaccard_links(make_docs(rows), recall=0.9, hashes=2, tile=tile)) == brute(rows)


def test_bands_and_rows_reach_the_recall():
    assert bands_and_rows(0.8, 0.998) == (34, 8)
    for recall in (0.9, 0.99, 0.998):
        bands, rows = bands_and_rows(0.8, recall)
        assert 1 - (1 - 0.8**rows) ** bands >= recall > 1 - (1 - 0.8**rows) ** (bands - 1)
        assert bands * rows <= 288 < (rows + 1) * math.ceil(math.log(1 - recall) / math.log(1 - 0.8 ** (rows + 1)))


def test_odd_rows_and_empty(odd_docs, make_docs):
    rows = [(r["doc_id"], r["text"]) for r in odd_docs.collect()]
    assert ours(jaccard_links(odd_docs)) == brute(rows)
    assert jaccard_links(make_docs([])).count() == 0 and one_of_each_class(make_docs([])).count() == 0


def test_one_stays(odd_docs, make_docs):
    rows = corpus(30)
    kept = [r["doc_id"] for r in one_of_each_class(make_docs(rows, clash=True)).collect()]
    classes = {c for _, _, c in brute(rows)}
    assert sorted(kept) == sorted(classes)
    odd = one_of_each_class(odd_docs)
    assert odd.columns == odd_docs.columns
    assert sorted((r["doc_id"] or 0, len(r["text"] or "")) for r in odd.collect()) == sorted([(0, 0), (1, 0), (2, 0), (3, 4), (4, 3), (5, len(rows_of(odd_docs, 5))), (7, 300_000), (0, 37)])


def test_classes_with_null_or_repeated_ids_stay_apart(make_docs):
    rng = random.Random(7)
    text = lambda: " ".join("".join(rng.choices("abcdefghij", k=5)) for _ in range(40))
    null, same, copy = [text() for _ in range(6)], [text() for _ in range(2)], text()
    rows = [(None, t) for t in null] + [(5, t) for t in same] + [(None, copy), (9, copy), (None, null[0])]
    kept = [(r["doc_id"], r["text"]) for r in one_of_each_class(make_docs(rows)).collect()]
    assert sorted(kept, key=repr) == sorted([*[(None, t) for t in null], *[(5, t) for t in same], (9, copy)], key=repr)


def rows_of(df, i):
    return df.where(f"doc_id = {i}").first()["text"]


def test_components(spark):
    rng = random.Random(3)
    edges = [(i, i + 1) for i in range(0, 60)] + [(100 + rng.randrange(40), 100 + rng.randrange(40)) for _ in range(30)] + [(200, 201 + i) for i in range(50)]
    up = {}

    def root(x):
        while up.setdefault(x, x) != x:
            x = up[x]
        return x

    for a, b in edges:
        if a != b:
            x, y = root(a), root(b)
            up[max(x, y)] = min(x, y)
    rng.shuffle(edges)
    got = components(spark.createDataFrame(edges, "u long, v long"))
    assert {(r["node"], r["root"]) for r in got.collect()} == {(x, root(x)) for x in list(up)} - {(x, x) for x in up if all(x not in e or e[0] == e[1] for e in edges)}
    assert components(spark.createDataFrame([], "u long, v long")).count() == 0
