import re

import compare

from stagedrel.llm import queries
from stagedrel.llm.license_index import BASE, licence_index, scan_licenses
from stagedrel.llm.queries import op4_licenses, table

SF = "/root/testdata/sf0.001"
LOWER = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


def expected(text):
    w = re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", (text or "").translate(LOWER))
    at = [(k, v) for p, v in BASE.items() for k in range(len(w)) if w[k : k + len(p.split())] == p.split()]
    return len(w), len(at), min((k for k, _ in at), default=None), max((k for k, _ in at), default=None), ",".join(sorted({v for _, v in at}))


def base(r):
    return r["n_words"], r["n_base"], r["first_word"], r["last_word"], r["base_labels"]


def test_query_equals_sql(spark):
    assert compare.differs(op4_licenses(spark, SF), compare.duck(SF), queries.ORACLE_SQL["op4_licenses"]) is None


def test_query_against_brute_force(spark):
    texts = {r["doc_id"]: r["text"] for r in table(spark, SF, "documents").collect()}
    rows = op4_licenses(spark, SF).collect()
    assert len(rows) == len(texts)
    assert all(base(r) == expected(texts[r["doc_id"]]) for r in rows)
    assert all(0 <= r["score"] <= 1 and set(r["base_labels"].split(",")) <= set(r["labels"].split(",")) | {""} for r in rows)


def test_cases(make_docs):
    texts = [
        "This WORK is licensed under the GNU General-Public License, version 3. GNU general public license",
        "x CC BY cc.by CC BY-NC 4.0", "Apache License apache license", "mit licenseé MIT LICENSE", "Kelvin: mit Kicense", "MİT License", "all rights were reserved",
        "Permission is hereby granted, free of charge, to any person obtaining a copy", "source and binary forms", "", None, "...", "ÉTÉ mit license",
    ]
    got = {r["doc_id"]: r for r in scan_licenses(make_docs(list(enumerate(texts)), clash=True)).collect()}
    for i, t in enumerate(texts):
        assert base(got[i]) == expected(t), t
    assert got[0]["labels"] == "gpl,gpl-3.0" and got[0]["score"] == 1.0
    assert got[1]["labels"] == "cc-by,cc-by-nc" and got[7]["labels"] == "mit" and got[6]["labels"] == ""
    assert got[9]["score"] == 0 and got[10]["n_words"] == 0


def test_whole_licences_and_other_rows(make_docs):
    """Every template is found in a text of its own with other words around, whatever other rows hold; without its key phrase it isn't."""
    index, _ = licence_index()
    texts = [(t, "so " * (t % 5) + "# " + " ".join(seq).upper() + " and then") for t, (seq, *_) in enumerate(index)]
    cut = [(1000 + t, " ".join([*seq[:at], "x", *seq[at + 1 :]])) for t, (seq, _, at, _, _) in enumerate(index)]
    got = {r["doc_id"]: r for r in scan_licenses(make_docs([*texts, *cut])).collect()}
    alone = {r["doc_id"]: r for r in scan_licenses(make_docs(texts[-3:])).collect()}
    assert all(label in got[t]["labels"].split(",") and got[t]["score"] == 1.0 for t, (*_, label, _) in enumerate(index))
    assert all(tuple(alone[t]) == tuple(got[t]) for t in alone)
    keys = [(" ".join(key), label) for _, key, _, label, _ in index]
    for (t, text), (*_, label, _) in zip(cut, index, strict=True):
        others = any(k in text for k, name in keys if name == label) or label in got[t]["base_labels"]
        assert others or label not in got[t]["labels"].split(",")
    mozilla = scan_licenses(make_docs([(1, "the mozilla public license applies")])).first()
    assert mozilla["labels"] == "mpl"


def test_odd_rows_and_empty(odd_docs, make_docs):
    assert sorted(r["n_words"] for r in scan_licenses(odd_docs).collect())[-2:] == [60_000, 60_000]
    assert scan_licenses(odd_docs).count() == odd_docs.count()
    assert scan_licenses(make_docs([])).count() == 0
