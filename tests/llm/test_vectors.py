import math

import numpy as np
import pytest

from stagedrel.llm.projection_passes import passes_for, vector_links
from stagedrel.llm.queries import op7_vectors, table

SCHEMA = "vec_id long, embedding array<double>, label int, node string, unit string, keys string"


def frame(spark, rows):
    return spark.createDataFrame([(i, v, lab, "x", "y", "z") for i, v, lab in rows], SCHEMA)


def brute(rows, cosine=0.93):
    n, good = len(rows), []
    for _, v, lab in rows:
        ok = v is not None and lab is not None and len(v) > 0 and all(x is not None and math.isfinite(x) for x in v) and any(v)
        good.append(np.array(v, float) / np.linalg.norm(v) if ok else None)
    link = [[j for j in range(n) if j != i and good[i] is not None and good[j] is not None and rows[i][2] == rows[j][2] and good[i] @ good[j] >= cosine] for i in range(n)]
    out = {}
    for i in range(n):
        seen, todo = {i}, [i]
        while todo:
            for j in link[todo.pop()]:
                if j not in seen:
                    seen.add(j)
                    todo.append(j)
        out[i] = (len(link[i]), min(rows[k][0] for k in seen))
    return out


def corpus(seed=0, dim=16):
    rng = np.random.default_rng(seed)
    rows = []
    for label in range(3):
        base = rng.standard_normal(dim)
        for noise, n in ((0.0, 30), (0.02, 150), (0.25, 60)):
            rows += [(base + noise * rng.standard_normal(dim), label) for _ in range(n)]
        rows += [(rng.standard_normal(dim), label) for _ in range(200)]
    order = rng.permutation(len(rows))
    return [(int(k), rows[j][0].tolist(), rows[j][1]) for k, j in enumerate(order)]


@pytest.mark.parametrize("window", [512, 24])
def test_links_against_brute_force(spark, window):
    rows = corpus()
    want = brute(rows)
    got = {r["vec_id"]: (r["n_links"], r["component_id"], r["kept"]) for r in vector_links(frame(spark, rows), window=window, tile=16).collect()}
    assert all(got[i][0] <= want[i][0] for i in want)
    if window == 512:
        assert {i: g[:2] for i, g in got.items()} == want
    assert sum(g[0] for g in got.values()) >= 0.95 * sum(w[0] for w in want.values())
    assert all(g[2] == (g[1] == i) for i, g in got.items())


def test_query_recall(spark):
    sf = "/root/testdata/sf0.1"
    rows = [(r["vec_id"], r["embedding"], r["label"]) for r in table(spark, sf, "embeddings").collect()]
    want = brute(rows)
    got = {r["vec_id"]: r for r in op7_vectors(spark, sf).collect()}
    assert len(got) == len(rows)
    assert sum(got[rows[i][0]]["n_links"] for i in want) >= 0.9 * sum(w[0] for w in want.values())
    assert all(got[rows[i][0]]["n_links"] <= w[0] for i, w in want.items())


def counts(x, label, cosine=0.93):
    unit = x.astype(np.float64) / np.linalg.norm(x.astype(np.float64), axis=1, keepdims=True)
    return ((unit @ unit.T >= cosine) & (label[:, None] == label[None, :])).sum(axis=1) - 1


def test_recall_on_large_labels_and_loose_groups(spark):
    """12,000 vectors of one label, among them a loose group of 3,000 (cosines about 0.95) and pairs at the threshold; and a hot vector."""
    rng = np.random.default_rng(5)
    base = rng.standard_normal(64)
    base /= np.linalg.norm(base)
    loose = base + 0.028 * rng.standard_normal((3000, 64))
    left = rng.standard_normal((2000, 64))
    left /= np.linalg.norm(left, axis=1, keepdims=True)
    pairs = np.concatenate([left, left + 0.046 * rng.standard_normal((2000, 64))])
    x = np.concatenate([loose, pairs, np.repeat(rng.standard_normal((1, 64)), 500, 0), rng.standard_normal((4500, 64))]).astype(np.float32)
    label = np.array([1] * 11_900 + [2] * (len(x) - 11_900))
    want = counts(x, label)
    df = spark.createDataFrame([(i, v.tolist(), int(lab)) for i, (v, lab) in enumerate(zip(x, label, strict=True))], "vec_id long, embedding array<float>, label int")
    got = {r["vec_id"]: r["n_links"] for r in vector_links(df).collect()}
    got = np.array([got[i] for i in range(len(x))])
    assert (got <= want).all() and want[:3000].mean() > 2000
    for part in (slice(0, 3000), slice(3000, 7000), slice(7000, 7500)):
        assert got[part].sum() >= 0.95 * want[part].sum()


def test_lengths_are_kept_apart_and_ids_come_back(spark):
    v, odd, big = [1.0, 0.5], [0.25] * 65, 9007199254740993
    rows = [(big + i, v, 1) for i in range(5)] + [(7, odd, 1), (8, odd, 2), (None, [0.5] * 65, 1), (big + 9, odd, 1), (big + 10, [0.0, 1.0], 1)]
    got = {r["vec_id"]: (r["n_links"], r["component_id"]) for r in vector_links(frame(spark, rows)).collect()}
    assert got == {**{big + i: (4, big) for i in range(5)}, 7: (2, 7), None: (2, 7), big + 9: (2, 7), 8: (0, 8), big + 10: (0, big + 10)}


def test_odd_rows_and_empty(spark):
    v, nan = [1.0, 0.0], float("nan")
    rows = [(1, v, 1), (1, v, 1), (2, [2.0, 0.0], 1), (3, v, None), (4, None, 1), (5, [], 1), (6, [0.0, 0.0], 1), (7, [1.0, None], 1), (8, [nan, 1.0], 1), (9, [float("inf"), 1.0], 1), (10, [1.0, 0.0, 0.0], 1), (0, v, 2), (11, [1e-300, 0.0], 1), (12, [0.1] * 200_000, 1)]
    got = sorted((r["vec_id"], r["n_links"], r["component_id"]) for r in vector_links(frame(spark, rows)).collect())
    assert got == [(0, 0, 0), (1, 3, 1), (1, 3, 1), (2, 3, 1), *[(i, 0, i) for i in range(3, 11)], (11, 3, 1), (12, 0, 12)]
    assert vector_links(frame(spark, rows).limit(0)).count() == 0
    assert vector_links(frame(spark, [(4, None, 1), (5, v, None)])).count() == 2


def test_passes():
    assert passes_for(10**9, 128, 0.93, 0.97) > passes_for(10**4, 128, 0.93, 0.97) >= 2
