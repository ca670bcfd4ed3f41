import math
import zlib
from collections import Counter, defaultdict

import numpy as np

from stagedrel.llm import kernels
from stagedrel.llm.ppm_language import fit_languages, predict_language
from stagedrel.llm.queries import op10_language, table

SF = "/root/testdata/sf0.01"


def slow_bits(train: list[str], text: str, order: int) -> float:
    """Code length by the definition: counts of each context, escapes to shorter ones, 8 bits at the end."""
    count = defaultdict(Counter)
    for t in train:
        raw = t.encode()
        for i in range(len(raw)):
            for k in range(min(i, order) + 1):
                count[raw[i - k : i]][raw[i]] += 1
    bits, raw = 0.0, text.encode()
    for i in range(len(raw)):
        for k in range(min(i, order), -1, -1):
            c = count.get(raw[i - k : i])
            if not c:
                continue
            t, q = sum(c.values()), len(c)
            if c[raw[i]]:
                bits -= math.log2(c[raw[i]] / (t + q))
                break
            bits -= math.log2(q / (t + q))
        else:
            bits += 8
    return bits


def test_code_lengths_are_exact():
    train = {"a": ["the cat sat on the mat", "a cat and a hat"], "b": ["die katze saß auf der matte", ""], "c": ["zzz"]}
    for order in (0, 1, 2, 4):
        trees = kernels.ContextTrees(order).fit(train)
        texts = ["the hat sat", "die matte", "zq", "katze Ω!", "z" * 30]
        raw = [t.encode() for t in texts]
        starts = np.cumsum([0, *map(len, raw)])[:-1]
        got = trees.lengths(np.frombuffer(b"".join(raw), np.uint8), starts)
        want = [[slow_bits(train[x], t, order) for x in trees.langs] for t in texts]
        assert np.allclose(got, want), order


def test_pieces_of_a_long_text_add_up():
    trees = kernels.ContextTrees(3).fit({"a": ["abcabcabd" * 20], "b": ["xyzabc" * 20]})
    text = "abcxyzabd" * 500
    whole = kernels.language_scorer(trees, 1 << 18)([text, "", None, "123", text])
    assert kernels.language_scorer(trees, 64)([text, "", None, "123", text]) == whole
    assert whole[1] == whole[2] == whole[3] == ("und", 0.0)


def test_held_out_accuracy(spark):
    rows = op10_language(spark, SF).join(table(spark, SF, "documents").select("doc_id", "lang"), "doc_id").collect()
    out = [r for r in rows if r["held_out"]]
    assert sum(r["lang_pred"] == r["lang"] for r in out) >= 0.98 * len(out)
    assert all(r["held_out"] == (zlib.crc32(str(r["doc_id"]).encode()) % 3 == 1) for r in rows)


def test_languages_with_long_texts_only_are_learned(make_docs):
    """One language has texts beyond a quarter of the bound, one a single text beyond the bound, one an id that repeats."""
    a, b, c = "the cat sat on the mat and ran off ", "die katze saß auf der matte und lief ", "el gato se sienta en la silla y corre "
    ids = [i for i in range(400) if zlib.crc32(str(i).encode()) % 3 != 1]
    rows = [(i, a * 3000, "en") for i in ids[:4]] + [(ids[5], b * 20_000, "de")] + [(ids[7], c + str(i), "es") for i in range(2000)]
    trees = fit_languages(make_docs(rows))
    assert trees.langs == ["de", "en", "es"]
    got = {r["doc_id"]: r["lang_pred"] for r in predict_language(make_docs([(1, a), (2, b), (3, c)]), trees).collect()}
    assert got == {1: "en", 2: "de", 3: "es"}


def test_odd_rows_and_empty(spark, odd_docs, make_docs):
    trees = fit_languages(table(spark, SF, "documents"))
    got = predict_language(odd_docs, trees)
    assert got.where("lang_pred = 'und'").count() == 4 and got.where("score < 0 or score > 1 or score is null").count() == 0
    assert predict_language(make_docs([]), trees).count() == 0
    assert {r["lang_pred"] for r in predict_language(odd_docs, fit_languages(make_docs([]))).collect()} == {"und"}
