"""The library without the training-data subpackage: SQL oracles on the smallest tables, exact definitions, invariants."""

import math
import random

import numpy as np
import pandas as pd
import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry_module
from twinsift.augment import policy
from twinsift.augment.lexicons import with_lexicons
from twinsift.catalogue import everything
from twinsift.encoder import net, training
from twinsift.functions import text as tx
from twinsift.operators import clustering, joins, metrics, sketches
from twinsift.operators.components import components

SF = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
QUERIES, ORACLES = everything()


@pytest.fixture(scope="module")
def duck():
    import duckdb

    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"create view {t} as select * from '{SF}/{t}.parquet'")
    return con


def rows_of(df):
    def plain(v):
        if v is None or v is pd.NA or (isinstance(v, float) and math.isnan(v)):
            return ""
        if hasattr(v, "isoformat"):
            return str(v)[:19]
        return f"{float(v):.5f}" if isinstance(v, (int, float, np.number)) and not isinstance(v, bool) else str(v)

    cols = sorted(df.columns)
    return sorted(tuple(plain(v) for v in r) for r in df[cols].astype(object).itertuples(index=False)), cols


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_against_sql(spark, duck, name):
    got, cols = rows_of(QUERIES[name](spark, SF).toPandas())
    want, names = rows_of(duck.sql(ORACLES[name]).df())
    assert cols == names and got == want


def test_entry_has_rows(spark):
    assert entry_module.entry(spark).count() > 0
    assert set(entry_module.oracle_sql()) <= set(entry_module.queries())


@pytest.mark.parametrize("small", [0, 10**6])
def test_components(spark, small):
    rnd = random.Random(3)
    edges = [(rnd.randint(0, 120), rnd.randint(0, 120)) for _ in range(90)] + [(200, 200), (300, 301)] + [(k, k + 1) for k in range(400, 460)]
    root = {}

    def top(x):
        while root.setdefault(x, x) != x:
            x = root[x]
        return x

    for a, b in edges:
        p, q = top(a), top(b)
        root[max(p, q)] = min(p, q)
    got = {r.id: r.component for r in components(spark.createDataFrame(edges, "a long, b long"), small=small).collect()}
    assert got == {i: top(i) for i in root}
    assert components(spark.createDataFrame([], "a long, b long"), small=small).count() == 0


def test_chunks_and_bits(spark):
    texts = ["", " ", "a", "a" * 511, "a" * 512, "a" * 513, "a" * 1024, "\U0001d4b3x́‍"]
    df = spark.createDataFrame(list(enumerate([*texts, None])), "id int, text string")
    got = {r.id: r.c for r in df.select("id", tx.chunk_array(F.col("text"), 512).alias("c")).collect()}
    assert [len(got[i]) for i in range(len(texts))] == [1, 1, 1, 1, 1, 2, 2, 1] and got[len(texts)] is None
    assert all("".join(c.chunk for c in got[i]) == t for i, t in enumerate(texts))
    x, mask = net.bits(texts[:3] + texts[-1:], 8)
    assert net.unbits(x, mask) == texts[:3] + texts[-1:]
    native = df.filter("id = 7").select(tx.bit_rows(F.col("text"))).first()[0]
    assert np.array(native).tolist() == net.bits(texts[-1:], len(texts[-1]))[0][0].astype(int).tolist()


def test_published_parameter_count():
    assert net.n_params(net.Config()) == 535_810
    assert len(net.grid(net.Config(), "blocks x hidden")) == 12 and len(training.LOSS_GRID) == 8


@pytest.mark.parametrize("block", net.BLOCKS)
@pytest.mark.parametrize("pool", net.POOLS)
def test_gradients(block, pool):
    c = net.Config(chunk=16, hidden=8, dim=6, qk=4, heads=2, block=block, pool=pool)
    w = {k: v.astype(np.float64) for k, v in net.init(c, 1).items()}
    texts, ids = ["abc de", "abd de", "xyz", "xyq w"], np.array([0, 0, 1, 1])
    _, grads = training.gradients(w, c, texts, ids)
    for k in w:
        flat = w[k].reshape(-1)
        i, kept, e = len(flat) // 2, flat[len(flat) // 2], 1e-4
        flat[i] = kept + e
        up = training.gradients(w, c, texts, ids)[0]
        flat[i] = kept - e
        down = training.gradients(w, c, texts, ids)[0]
        flat[i] = kept
        slope = (up - down) / (2 * e)
        assert abs(slope - grads[k].reshape(-1)[i]) < 1e-3 * (1 + abs(slope)), k


def test_pooling_bounds():
    x = net.Node(np.abs(np.random.default_rng(0).normal(size=(3, 7, 5))).astype(np.float32))
    mask = np.ones((3, 7), np.float32)
    mean, top = net.pool(x, mask, "avg").value, net.pool(x, mask, "max").value
    assert np.allclose(net.pool(x, mask, "gem", 1.0).value, mean, atol=1e-5)
    last = mean
    for p in (2.0, 3.0, 8.0):
        now = net.pool(x, mask, "gem", p).value
        assert (now >= last - 1e-5).all() and (now <= top + 1e-4).all()
        last = now


def test_training_lowers_loss_and_repeats():
    rnd = random.Random(1)
    views = []
    for k in range(24):
        t = "".join(rnd.choice("abcdefgh ") for _ in range(40))
        views.append((k, t, t[:20] + rnd.choice("xyz") + t[21:]))
    c = net.Config(chunk=48, hidden=16, dim=16, qk=8)
    w, losses = training.fit(views, c, 30, 12)
    again, _ = training.fit(views, c, 30, 12)
    assert np.mean(losses[-5:]) < np.mean(losses[:5]) and all(np.array_equal(w[k], again[k]) for k in w)


def test_lamb_by_hand():
    w = {"x": np.array([3.0, 4.0], np.float32)}
    training.Lamb(w, eps=0.0).step(w, {"x": np.array([0.5, -2.0], np.float32)}, 0.1)
    assert np.allclose(w["x"], np.array([3, 4]) - 0.1 * 5 / math.sqrt(2) * np.array([1, -1]), atol=1e-5)


def test_distributed_training(spark):
    views = spark.createDataFrame([(k, f"text number {k} aaa", f"text number {k} aab") for k in range(8)], "class_id long, view_a string, view_b string")
    c = net.Config(chunk=32, hidden=8, dim=8, qk=4)
    w = training.fit_distributed(views, c, 3, workers=2, size=4)
    assert {k: v.shape for k, v in w.items()} == net.shapes(c)


def test_measures_by_hand(spark):
    label = lambda xs: spark.createDataFrame(list(enumerate(xs)), "id long, cluster long")
    a = [0, 0, 1, 1]
    value = lambda x, y: metrics.ari(label(x), label(y)).first()[0]
    assert value(a, a) == 1 and value(a, [5, 5, 3, 3]) == 1 and value([0] * 4, [0] * 4) == 1 and value([0, 1, 2, 3], [0, 1, 2, 3]) == 1
    assert abs(value(a, [0, 0, 1, 2]) - 4 / 7) < 1e-6
    v = metrics.v_measure(label(a), label([0, 0, 1, 2])).first()
    assert v.homogeneity == 1 and v.completeness < 1
    for h, c, want in ((0.937, 0.963, 0.949), (0.867, 0.876, 0.871), (0.856, 0.955, 0.903)):
        assert abs(2 * h * c / (h + c) - want) < 1.01e-3


def test_linkage_against_brute_force(spark):
    rng = np.random.default_rng(4)
    x = rng.normal(size=(5, 8))[rng.integers(0, 5, 40)] + rng.normal(size=(40, 8)) * 0.35
    unit = x / np.linalg.norm(x, axis=1, keepdims=True)
    far = 1 - unit @ unit.T
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<double>")
    for linkage, join in (("single", np.min), ("complete", np.max), ("average", np.mean)):
        groups = [[i] for i in range(40)]
        while len(groups) > 1:
            d, p, q = min((join(far[np.ix_(a, b)]), i, j) for i, a in enumerate(groups) for j, b in enumerate(groups) if i < j)
            if d > 0.3:
                break
            groups[p] += groups.pop(q)
        want = {i: min(g) for g in groups for i in g}
        assert {r.id: r.cluster for r in clustering.agglomerative(df, linkage, 0.3).collect()} == want, linkage


def test_minhash_engines_agree(spark, docs):
    hashed = sketches.shingle_hashes(docs)
    arrow = {r.id: r.signature for r in sketches.sign_hashes(hashed, 16).collect()}
    native = {r.id: r.s for r in hashed.select("id", sketches.minhash(F.col("hashes"), 16).alias("s")).collect()}
    assert arrow == native
    bands, rows = sketches.choose_bands(0.8, 128)
    assert bands * rows <= 128
    exact = {(r.a, r.b) for r in sketches.jaccard_join(hashed, 0.8).collect()}
    found = {tuple(sorted((r.a, r.b))) for r in sketches.minhash_pairs(docs, 0.8, 128).collect()}
    same = sketches.minhash_pairs(docs, 0.8, 128).filter("score = 1").count()
    assert found <= exact and same > 0
    votes = {r.id: r.fingerprint for r in sketches.simhash_votes(docs, 5).collect()}
    plain = {r.doc_id: r.f for r in docs.limit(20).select("doc_id", sketches.simhash(tx.char_shingles(F.col("text"), 5)).alias("f")).collect()}
    assert all(votes[k] == v for k, v in plain.items())


def test_corruption_at_rate_zero_and_bounds(spark, docs):
    rows = with_lexicons(docs).cache()
    texts = {r.doc_id: r.text for r in docs.collect()}
    for name in ("char_delete", "word_swap", "sent_repeat", "attack_invisible"):
        assert all(r.text == texts[r.doc_id] for r in policy.corrupt_one(rows, name, 0.0).collect())
    cut = {r.doc_id: r.text for r in policy.corrupt_one(rows, "char_delete", 0.1).collect()}
    share = 1 - sum(map(len, cut.values())) / sum(map(len, texts.values()))
    assert 0.08 < share < 0.12
    report = policy.apply(rows, policy.BENCH, "x").collect()
    assert len(report) == len(texts) and all(len(r.report) == 4 for r in report)


def test_joins(spark):
    left = spark.createDataFrame([(1, 2.0, 5.0), (2, 9.0, 9.0), (3, 7.0, 6.0)], "id int, lo double, hi double")
    right = spark.createDataFrame([(10, 2.0), (11, 5.0), (12, 5.1), (13, 9.0)], "pid int, at double")
    got = sorted((r.id, r.pid) for r in joins.range_join(left, right, F.col("lo"), F.col("hi"), F.col("at"), 1.5).collect())
    assert got == [(1, 10), (1, 11), (2, 13)]
    salted = joins.salted_join(right.withColumn("k", F.lit(1)), spark.createDataFrame([(1, "x")], "k int, v string"), "k", 4, F.col("pid"))
    assert salted.count() == 4


def test_sweep_and_two_class(spark):
    pairs = spark.createDataFrame([(0.9, 1), (0.8, 0), (0.7, 1), (0.2, 0)], "score double, truth long")
    from twinsift.operators.matching import sweep

    got = {round(r.threshold, 2): (r.tp, r.fp, r.fn) for r in sweep(pairs, [0.1, 0.75, 0.95]).collect()}
    assert got == {0.1: (2, 2, 0), 0.75: (1, 1, 1), 0.95: (0, 0, 2)}
    scores = metrics.two_class(spark.createDataFrame([(1, 1)] * 5 + [(0, 1)] * 5 + [(1, 0)] + [(0, 0)] * 9, "pred int, truth int")).first()
    assert (scores.tp, scores.fp, scores.fn, scores.tn) == (5, 1, 5, 9) and scores.accuracy == 0.7
