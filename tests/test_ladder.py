"""Clusters of all cuts by climbing from cut to cut are those of all vectors at once; campaigns are made in one pass."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from twinsift.augment import policy
from twinsift.augment.lexicons import with_lexicons
from twinsift.experiments import workloads as w
from twinsift.operators import clustering, matching, metrics
from twinsift.sources.tables import read_table

SF = "/root/testdata/sf0.001"


def planted() -> np.ndarray:
    """Vectors whose threshold graph hangs together, though its clusters are small; a zero and copies among them."""
    rnd = np.random.default_rng(4)
    centres = np.cumsum(rnd.normal(size=(12, 8)), axis=0) + 2
    x = np.repeat(centres, 20, axis=0) + rnd.normal(scale=0.8, size=(240, 8))
    x[7], x[100:103] = 0, x[100]
    return x.astype(np.float32)


@pytest.mark.parametrize("linkage", ["average", "complete"])
@pytest.mark.parametrize("wide,matrix", [(1 << 24, 4000), (64 * 40, 4000), (64 * 40, 3)])
def test_ladder_is_agglomeration_of_all_vectors(spark, monkeypatch, linkage, wide, matrix):
    x, ids, cuts = planted(), np.arange(240, dtype=np.int64) * 3 + 1, (0.05, 0.1, 0.3)
    whole = {c: clustering.agglomerate(matching._unit(x.astype(np.float64)), ids, linkage, c) for c in cuts}
    monkeypatch.setattr(clustering, "WIDE", wide)
    monkeypatch.setattr(clustering, "MATRIX", matrix)
    rows = spark.createDataFrame([(int(i), v.tolist()) for i, v in zip(ids, x, strict=True)], "id long, v array<float>").repartition(5, "id")
    held = clustering.packed_blocks(rows)
    got = {c: {r.id: r.cluster for r in found.collect()} for c, found in clustering.ladder(held, linkage, cuts)}
    assert list(got) == list(cuts)
    for c in cuts:
        assert got[c] == dict(zip(ids.tolist(), whole[c].tolist(), strict=True))
        assert 1 < len(set(got[c].values())) < 240


def test_ladder_of_nothing(spark):
    held = clustering.packed_blocks(spark.createDataFrame([], "id long, v array<float>"))
    assert [found.count() for _, found in clustering.ladder(held, "average", (0.1, 0.2))] == [0, 0]


def test_picked_operators_are_those_of_corrupt_one(spark):
    docs = read_table(spark, SF, "documents").limit(200)
    pick = F.pmod("doc_id", F.lit(len(w.ATTACKS) + 1))  # the last has no operator
    rows = with_lexicons(docs).withColumn("pick", F.when(pick < len(w.ATTACKS), pick))
    seeds = [f"s{i}" for i in range(len(w.ATTACKS))]
    got = {r.doc_id: r.text for r in policy.corrupt_picked(rows, w.ATTACKS, 0.2, seeds).select("doc_id", "text").collect()}
    want = {r.doc_id: r.text for r in docs.collect()}
    for i, name in enumerate(w.ATTACKS):
        want |= {r.doc_id: r.text for r in policy.corrupt_one(rows.filter(F.col("pick") == i), name, 0.2, seeds[i]).collect()}
    assert got == want


def test_campaigns_write_messages_once_and_no_pairs(spark, monkeypatch):
    written, real = [], w.cut
    monkeypatch.setattr(w, "cut", lambda df: written.append(df.dtypes) or real(df))
    monkeypatch.setattr(clustering, "pairs", lambda *a, **k: pytest.fail("pairs of messages leave the tiles"))
    rows = w.w_campaigns(spark, SF, methods=("char stand-in",), cuts=(0.1, 0.3)).collect()
    assert len(rows) == 16 and all(-1 <= r.value <= 1 for r in rows)
    assert sum(("text", "string") in kinds for kinds in written) == 1 and not any(kind.startswith("array<double") for kinds in written for _, kind in kinds)


def test_scores_of_many_labellings_are_those_of_each(spark):
    rnd = np.random.default_rng(8)
    truth = spark.createDataFrame([(i, i // 7) for i in range(90)], "id long, cluster long")
    found = {k: spark.createDataFrame([(i, int(c)) for i, c in enumerate(np.where(rnd.random(90) < k, rnd.integers(0, 9, 90), np.arange(90) // 7))], "id long, cluster long") for k in (0.0, 0.3, 1.0)}
    found |= {"one": truth.select("id", F.lit(0).alias("cluster")), "own": truth.select("id", F.col("id").alias("cluster"))}
    t = w.union([metrics.contingency(truth, f).withColumn("k", F.lit(str(k))) for k, f in found.items()])
    got = {r.k: tuple(r)[1:] for r in metrics.clustering_scores(t, "k").collect()}
    for k, f in found.items():
        assert got[str(k)] == pytest.approx((*metrics.v_measure(truth, f).first(), metrics.ari(truth, f).first()[0]), abs=2e-6)


def test_messages_are_made_by_many_tasks(spark):
    assert w.campaigns(spark, SF).rdd.getNumPartitions() == 4 * spark.sparkContext.defaultParallelism
