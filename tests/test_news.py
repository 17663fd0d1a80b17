"""Planted news: whole texts, the same scanner noise as the operator, SimHash pairs by tiles."""

from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from twinsift.augment import places, policy
from twinsift.augment.operators import Spark, expression
from twinsift.experiments import workloads as w
from twinsift.operators import fingerprints, matching, sketches
from twinsift.operators.components import components
from twinsift.sources.tables import read_table

SF = "/root/testdata/sf0.001"


def test_news_keeps_whole_texts(spark):
    docs = {r.text for r in read_table(spark, SF, "documents").collect() if r.text}
    rows = w.cut(w.news(spark, SF)).collect()
    assert {r.text for r in rows if r.doc_id % 4 == 0} == docs and max(map(len, docs)) > 4000
    assert len({r.doc_id for r in rows}) == len(rows) > 1.5 * len(docs) and all(r.doc_id // 4 == r.cluster for r in rows)


@pytest.mark.parametrize("block", [55, 0])
def test_noise_of_one_pass_is_that_of_the_operator(spark, monkeypatch, block):
    monkeypatch.setattr(places, "BLOCK", block)
    rows = [(i, "en", t) for i, t in enumerate(["l O1eacS5B8 " * 30, "", "😀 a𝒳 eée\x00 ", None, " " * 200, "x"])] + [(10**15, "de", "see also 5 8 B" * 900)]
    docs = spark.createDataFrame(rows, "doc_id long, lang string, text string")
    docs.createOrReplaceTempView("noise_rows")
    want = spark.sql(expression("noise_scan", 0.3, "news", Spark(), "noise_rows"))
    got = sorted(map(tuple, policy.corrupt_one(docs, "noise_scan", 0.3, "news").collect()))
    assert got == sorted(map(tuple, want.collect())) and got[0][2] != rows[0][2]


def test_simhash_tiles_are_all_pairs(spark, monkeypatch):
    monkeypatch.setattr(fingerprints, "WIDE", 40)
    monkeypatch.setattr(fingerprints, "AT_ONCE", 100)
    monkeypatch.setattr(fingerprints, "HELD", 3)
    rnd = np.random.default_rng(4)
    x = rnd.integers(-(2**63), 2**63 - 1, 60)
    x = np.concatenate([x, x[:30] ^ (1 << rnd.integers(0, 62, 30)), x[:20]])
    signed = spark.createDataFrame([(i, int(v), i % 30) for i, v in enumerate(x)] + [(500, None, 1)], "id long, fingerprint long, tag long")
    want = {(r.a, r.b): r.distance for r in sketches.simhash_pairs(signed.drop("tag").filter("fingerprint is not null"), 14).collect()}
    assert len(want) > 50 and {(r.a, r.b): r.distance for r in fingerprints.pairs(signed, 14).collect()} == want
    assert {(r.a, r.b) for r in fingerprints.pairs(signed, 14, "tag").collect()} == {(a, b) for a, b in want if a % 30 == b % 30}
    told = {(r.distance, r.truth): r.n for r in fingerprints.counts(signed, 14, "tag").collect()}
    assert told == Counter((d, int(a % 30 == b % 30)) for (a, b), d in want.items())
    found = {r.id: r.component for r in components(fingerprints.links(signed, 14)).collect()}
    pairs = spark.createDataFrame(list(want), "a long, b long")
    assert found == {r.id: r.component for r in components(pairs).collect()}


@pytest.mark.parametrize("name", ["minhash", "simhash"])
def test_sweep_counts_those_pairs(spark, name):
    texts = w.cut(w.news(spark, SF, True))
    scored, grid = w.scored_by(texts, name, w.SETTINGS["news"])
    one, two = (texts.select(F.col("doc_id").alias(i), F.col("cluster").alias(c)) for i, c in (("a", "ca"), ("b", "cb")))
    marked = scored.join(one, "a").join(two, "b").select("score", (F.col("ca") == F.col("cb")).cast("long").alias("truth"))
    want = matching.sweep(marked, grid, w._true_pairs(texts).count()).collect()
    assert sorted(w.swept(texts, name, w.SETTINGS["news"]).collect()) == sorted(want)


def test_thresholds_are_those_of_all_clusters(spark, monkeypatch):
    seen = []
    monkeypatch.setattr(w, "swept", lambda texts, *_: seen.append(texts) or spark.createDataFrame([(0.5, 1.0, 1.0, 1.0)], "threshold double, precision double, recall double, f1 double"))
    w.w_thresholds(spark, SF, ("minhash",)).collect()
    assert sorted(map(tuple, seen[0].collect())) == sorted(map(tuple, w.news(spark, SF).collect()))
