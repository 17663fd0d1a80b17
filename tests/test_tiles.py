"""Searches and joins of vectors by tiles, against brute force, with blocks that are far smaller than their tables."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from twinsift.operators import matching

DIM = 8


@pytest.fixture
def small(monkeypatch):
    monkeypatch.setattr(matching, "BLOCK", 7)
    monkeypatch.setattr(matching, "WIDE", 8 * DIM * 7)
    monkeypatch.setattr(matching, "AT_ONCE", 50)


@pytest.fixture
def rows(spark):
    rnd = np.random.default_rng(5)
    base = rnd.normal(size=(30, DIM))
    x = np.concatenate([base, base[:20] + 0.2 * rnd.normal(size=(20, DIM)), base[:5]])
    frame = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)] + [(len(x), None)], "vec_id long, embedding array<double>").cache()
    unit = x / np.linalg.norm(x, axis=1, keepdims=True)
    return x, unit @ unit.T, frame


def shared_bits(x, planes):
    code = np.einsum("tbd,nd->ntb", planes, x) > 0
    return (code[:, None] == code[None]).all(3).any(2)


def test_exact_search_by_tiles(small, rows):
    _, cos, e = rows
    got = {(r.query_id, r["rank"]): (r.target_id, r.score) for r in matching.knn(e.filter("vec_id % 5 = 0"), e, 3, ("vec_id", "embedding"), ("vec_id", "embedding"), skip_same=True).collect()}
    for q in range(0, len(cos), 5):
        order = sorted((j for j in range(len(cos)) if j != q), key=lambda j: (-round(cos[q, j], 12), j))[:3]
        assert [got[q, k + 1][0] for k in range(3)] == order
    assert len(got) == 3 * len(range(0, len(cos), 5))


def test_pairs_by_tiles(small, rows):
    _, cos, e = rows
    n = len(cos)
    assert sorted((r.a, r.b) for r in matching.pairs(e, 0.5).collect()) == [(i, j) for i in range(n) for j in range(i + 1, n) if cos[i, j] >= 0.5]
    of = e.withColumn("doc", F.floor(F.col("vec_id") / 10))
    assert sorted((r.a, r.b) for r in matching.pairs(of, 0.5, group="doc").collect()) == [(i, j) for i in range(n) for j in range(i + 1, n) if cos[i, j] >= 0.5 and i // 10 != j // 10]


def test_sign_search_counts_each_pair_once(small, rows):
    x, cos, e = rows
    found, compared = matching.sign_search(e.filter("vec_id % 5 = 0"), e, DIM, 1, 4, 3, skip_same=True, seed=2)
    share = shared_bits(x, matching._planes(DIM, 4, 3, 2))
    ask = range(0, len(x), 5)
    assert compared.first()[0] == sum(int(share[q].sum()) for q in ask)
    want = {q: min((j for j in range(len(x)) if j != q and share[q, j]), key=lambda j: (-round(cos[q, j], 12), j), default=None) for q in ask}
    assert {r.query_id: r.target_id for r in found.collect()} == {q: j for q, j in want.items() if j is not None}


def test_inverted_lists_compare_probed_cells_only(small, rows):
    x, cos, e = rows
    centres = x[[0, 3, 9, 14]]
    cells = matching.assign_cells(e, centres, 1)
    found, compared = matching.ivf_search(e.filter("vec_id % 5 = 0"), e, cells, centres, 1, 2, skip_same=True)
    far = (centres**2).sum(1)[None] - 2 * x @ centres.T
    near = np.argsort(far, axis=1, kind="stable")
    met = {q: [j for j in range(len(x)) if near[j, 0] in near[q, :2]] for q in range(0, len(x), 5)}
    assert compared.first()[0] == sum(map(len, met.values()))
    want = {q: min((j for j in js if j != q), key=lambda j: (-round(cos[q, j], 12), j), default=None) for q, js in met.items()}
    assert {r.query_id: r.target_id for r in found.collect()} == {q: j for q, j in want.items() if j is not None}


def test_recall_of_the_join_is_that_of_near_pairs(small, rows):
    x, cos, e = rows
    n = len(x)
    got = {r.threshold: (r.exact, r.found, r.compared) for r in matching.near_recall(e, (0.9, 0.8), DIM, 0.5, "vec_id", "embedding").collect()}
    for t in (0.9, 0.8):
        share = shared_bits(x, matching._planes(DIM, *matching.plan_signs(t, n, 0.5), 3))
        up = np.triu(np.ones((n, n), bool), 1)
        assert got[t] == (int((up & (cos >= t)).sum()), matching.near_pairs(e, t, DIM, 0.5, "vec_id", "embedding").count(), int((up & share).sum()))
