"""Texts that share a run of words: by anchors, against all runs."""

import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from twinsift.operators import clustering, exact

SF = "/root/testdata/sf0.01"


def by_all_runs(spark, docs, n, split):
    win = exact.token_windows(docs, n).select("id", F.xxhash64("window", "check").alias("rep"))
    return clustering.rates(spark.createDataFrame([], "a long, b long"), win.withColumn("text", F.col("id")), split, "text")


@pytest.mark.parametrize("sent", [10**6, 0])
def test_rates_by_anchors(spark, monkeypatch, sent):
    monkeypatch.setattr(exact, "SENT", sent)
    rnd = random.Random(7)
    texts = [" ".join(rnd.choice("abcdefghij") for _ in range(rnd.randint(0, 40))) for _ in range(120)]
    texts += texts[:10] + [texts[0].upper(), texts[20] + " k l m", "", None]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    split = docs.select(F.col("doc_id").alias("id"), F.when(F.col("doc_id") % 3 == 0, "valid").otherwise("train").alias("split"))
    for n in (5, 6, 8):
        want = {tuple(r) for r in by_all_runs(spark, docs, n, split).collect()}
        assert {tuple(r) for r in exact.window_rates(docs, n, split).collect()} == want


def test_anchors_are_few_and_shared():
    rnd = np.random.default_rng(1)
    x = rnd.integers(0, 2**63, 3000).astype(np.uint64)
    own = exact.anchors(x, 50)
    assert len(own) == 2951 and (exact.anchors(x[700:760], 50) == own[700:711]).all()
    assert len(np.unique(own)) < 300  # of 2951 runs


def test_rates_of_the_documents(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    split = docs.select(F.col("doc_id").alias("id"), F.when(F.col("doc_id") % 10 == 0, "valid").otherwise("train").alias("split"))
    assert sorted(map(tuple, exact.window_rates(docs, 50, split).collect())) == sorted(map(tuple, by_all_runs(spark, docs, 50, split).collect()))
