"""Sweeps of thresholds over vectors count pairs by tiles; all pairs are the definition."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from twinsift.experiments import workloads as w
from twinsift.operators import matching

SF = "/root/testdata/sf0.001"


@pytest.mark.parametrize("single", [True, False])
def test_counts_are_those_of_all_pairs(spark, monkeypatch, single):
    monkeypatch.setattr(matching, "PACKED", 8 * 4 * 12)
    monkeypatch.setattr(matching, "AT_ONCE", 60)
    rnd = np.random.default_rng(3)
    doc = np.sort(rnd.integers(0, 25, 70))
    x = rnd.normal(size=(70, 8)) + 1.5
    x[40:50] = x[:10]
    x[60] = 0
    x = x.astype(np.float32).astype(float) if single else x
    rows = [(i, int(d), int(d) // 3, v.tolist()) for i, (d, v) in enumerate(zip(doc, x, strict=True))]
    v = spark.createDataFrame(rows, "vec_id long, doc_id long, cluster long, v array<double>")
    grid = [0.6, 0.7, 0.8, 0.9]
    want = {}
    for r in matching.doc_pairs_from_chunks(matching.pairs(v, 0.6, "vec_id", "v", group="doc_id"), v).collect():
        if r.score >= 0.6:
            key = max(t for t in grid if r.score >= t), int(r.doc_a // 3 == r.doc_b // 3)
            want[key] = want.get(key, 0) + 1
    assert {(r.score, r.truth): r.n for r in matching.swept_counts(v, grid).collect()} == want and want


def test_sweep_writes_no_pairs(spark, monkeypatch):
    texts = w.cut(w.news(spark, SF, True))
    assert sorted(map(tuple, texts.collect())) == sorted(map(tuple, w._slice(w.news(spark, SF), True).collect()))
    scored, grid = w.scored_by(texts, "chunk", w.SETTINGS["news"])
    one, two = (texts.select(F.col("doc_id").alias(i), F.col("cluster").alias(c)) for i, c in (("a", "ca"), ("b", "cb")))
    want = matching.sweep(scored.join(one, "a").join(two, "b").select("score", (F.col("ca") == F.col("cb")).cast("long").alias("truth")), grid, w._true_pairs(texts).count()).collect()
    monkeypatch.setattr(matching, "pairs", None)
    got = w.swept(texts, "chunk", w.SETTINGS["news"]).collect()
    assert sorted(got)[:-1] == sorted(want)[:-1]  # at 1.0 the last digit of a sum decides
