import random
import re
from collections import Counter, defaultdict

import pytest

from stagedrel.llm.line_templates import drop_recurring_lines
from stagedrel.llm.queries import op3_lines, table

SF = "/root/testdata/sf0.001"


def own(i, n=6):
    rng = random.Random(i * 1000)
    return [" ".join("".join(rng.choices("abcdefghiklmnoprstu", k=rng.randrange(4, 13))) for _ in range(12)) for _ in range(n)]


def result(df):
    return {r["doc_id"]: r for r in df.collect()}


def test_exact_and_variable_lines_go(make_docs):
    docs = make_docs([(i, "\n".join([*own(i), "Page 12 of 90", f"Posted on 2024-01-{i:02d} by user{i}"])) for i in range(1, 6)])
    got = result(drop_recurring_lines(docs))
    for i in range(1, 6):
        assert got[i]["text"] == "\n".join(own(i)) and got[i]["n_dropped"] == 2 and got[i]["n_lines"] == 8


def test_words_that_vary_inside_a_template_go(make_docs):
    names = ["anna", "boris", "clara", "dmitri", "elena"]
    docs = make_docs([(i, "\n".join([*own(i), f"you are reading the daily letter of {n} sent to all our friends", f"Posted by {n} in Sports"])) for i, n in enumerate(names)])
    got = result(drop_recurring_lines(docs))
    assert all(got[i]["n_dropped"] == 2 and got[i]["text"] == "\n".join(own(i)) for i in range(5))


def test_several_templates_of_one_leaf_go(make_docs):
    """Equal token count and leading tokens, half of the lines each, and lines of neither among them."""
    a, b = "the daily letter of the town {} is sent to all friends at noon", "the daily letter of our club was written by {} before the game"
    body = lambda i: own(i, 3)
    names = ["anna", "boris", "clara", "dmitri", "elena", "fatma"]
    rows = [(i, "\n".join([*body(i), a.format(n)])) for i, n in enumerate(names)] + [(10 + i, "\n".join([*body(10 + i), b.format(n)])) for i, n in enumerate(names)]
    rows += [(20 + i, "\n".join([*body(20 + i), "the daily letter of " + " ".join(own(50 + i, 1)[0].split()[:9])])) for i in range(4)]
    got = result(drop_recurring_lines(make_docs(rows)))
    assert all(got[i]["n_dropped"] == 1 and got[i]["text"] == "\n".join(body(i)) for i in [*range(6), *range(10, 16)])
    assert all(got[i]["n_dropped"] == 0 for i in range(20, 24))


@pytest.mark.parametrize("line", ["We use cookies on this site, see our policy.", " ".join(f"footer{chr(97 + i % 26)}{chr(97 + i // 26)}" for i in range(60))])
def test_a_shared_line_goes_from_all_short_documents(make_docs, line):
    docs = make_docs([(i, "\n".join([" ".join(own(i, 1)[0].split()[:3]), line])) for i in range(400)])
    got = result(drop_recurring_lines(docs))
    assert all(got[i]["text"] == " ".join(own(i, 1)[0].split()[:3]) and got[i]["n_dropped"] == 1 for i in range(400))


def test_equal_texts_count_once(make_docs):
    text = "\n".join(["A header of the site", *own(3, 20)])
    alone = [(i, text) for i in range(400)]
    assert all(r["n_dropped"] == 0 and r["text"] == text for r in drop_recurring_lines(make_docs(alone)).collect())
    others = [(1000 + i, "\n".join(["A header of the site", *own(100 + i)])) for i in range(2)]
    got = result(drop_recurring_lines(make_docs([*alone, *others])))
    assert all(r["n_dropped"] == 1 and "header" not in r["text"] for r in got.values())


def test_a_document_made_of_shared_lines_stays_whole(make_docs):
    lines = own(3, 20)
    near = [(i, "\n".join([*lines[:i], " ".join([*lines[i].split()[:6], f"edit{'abcdefgh'[i]}e", *lines[i].split()[7:]]), *lines[i + 1 :]])) for i in range(8)]
    got = result(drop_recurring_lines(make_docs([*near, (20, "\n".join([*own(20), lines[4]]))])))
    assert all(got[i]["text"] == t and got[i]["n_dropped"] == 0 for i, t in near)
    assert got[20]["text"] == "\n".join(own(20))


def test_lines_of_fields_and_two_carriers_stay(make_docs):
    long = " ".join(f"tok{chr(97 + i % 26)}{chr(97 + i // 26)}" for i in range(55))
    docs = make_docs([(i, "\n".join([*own(i), f"12 x{i} 2024-01-{i:02d} ok", *([long] if i < 3 else [])])) for i in range(1, 6)])
    assert all(r["n_dropped"] == 0 for r in drop_recurring_lines(docs).collect())


def test_odd_rows_and_empty(odd_docs, make_docs):
    out = drop_recurring_lines(odd_docs)
    assert sorted(map(repr, (r["text"] for r in out.collect()))) == sorted(map(repr, (r["text"] for r in odd_docs.collect())))
    assert set(odd_docs.columns) <= set(out.columns)
    assert drop_recurring_lines(make_docs([])).count() == 0


def masked(line):
    tokens = ["<*>" if re.search(r"\d", t) or re.match(r"https?://", t) or re.match(r"[^@]+@", t) else t for t in line.split()]
    return tokens if tokens and 2 * tokens.count("<*>") <= len(tokens) else []


def test_query_against_brute_force(spark):
    """By the definition: every line whose masked tokens stand in three texts goes; any other that goes has two texts with lines much like it."""
    docs = [(r["doc_id"], r["text"]) for r in table(spark, SF, "documents").collect()]
    texts, kin = defaultdict(set), defaultdict(set)
    for _, t in docs:
        for line in t.split("\n"):
            if m := masked(line):
                texts[tuple(m)].add(t)
                kin[(len(m), *m[: max(1, min(4, len(m) // 2))])].add((tuple(m), t))

    def alike(m):
        near = {t for other, t in kin[(len(m), *m[: max(1, min(4, len(m) // 2))])] if sum(a == b for a, b in zip(m, other, strict=True)) >= 0.4 * len(m)}
        return len(near) >= 3

    got, dropped = result(op3_lines(spark, SF)), 0
    for i, t in docs:
        lines, left = t.split("\n"), got[i]["text"].split("\n")
        assert not Counter(left) - Counter(lines)
        hit = {line for line in lines if len(texts[tuple(masked(line))]) >= 3 and masked(line)}
        if got[i]["n_dropped"]:
            gone = list((Counter(lines) - Counter(left)).elements())
            assert not hit & set(left) and len(gone) == got[i]["n_dropped"]
            assert all(line in hit or alike(masked(line)) for line in gone)
            dropped += len(gone)
        elif hit:  # it would lose every word
            assert all(not re.search(r"[^\W\d]", line) or line in hit or alike(masked(line)) for line in lines)
    assert dropped > 50
