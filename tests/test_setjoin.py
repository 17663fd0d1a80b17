"""The packed joins of sets: exact against brute force, small on disk."""

import random
from pathlib import Path

import numpy as np
import pytest

from twinsift.functions import text as tx
from twinsift.operators import setjoin, sketches
from twinsift.sources.tables import read_table

SF = "/root/testdata/sf0.01"


def some_sets(seed: int = 5):
    """Random sets, near copies of one of them in a large group, exact copies, an empty and a missing one; ids of all sizes."""
    rng = random.Random(seed)
    word = lambda: rng.getrandbits(63) - (1 << 62)
    common = [word() for _ in range(6)]
    base = [word() for _ in range(30)]
    rows = [[word() for _ in range(rng.randint(1, 40))] + rng.sample(common, rng.randint(0, 6)) for _ in range(60)]
    rows += [rng.sample(base, rng.randint(20, 30)) for _ in range(50)] + [base] * 4 + [rows[0], rows[1]]
    ids = rng.sample(range(-(1 << 40), 1 << 40), len(rows))
    return [(i, list(dict.fromkeys(r))) for i, r in zip(ids, rows, strict=True)] + [(7, []), (8, None)]


def brute(rows, t):
    sets, out = {i: set(r) for i, r in rows if r}, {}
    for a in sets:
        for b in sets:
            if a < b and (s := len(sets[a] & sets[b]) / len(sets[a] | sets[b])) >= t:
                out[a, b] = round(s, 9)
    return out


@pytest.mark.parametrize("t", [0.2, 0.5, 0.8])
@pytest.mark.parametrize("hot", [2000, 7])
def test_join_against_brute_force(spark, monkeypatch, t, hot):
    monkeypatch.setattr(setjoin, "HOT", hot)
    monkeypatch.setattr(setjoin, "SENT_IDS", 1_000_000 if hot == 7 else 0)
    rows = some_sets()
    df = spark.createDataFrame(rows, "id long, hashes array<long>").repartition(3)
    found = [(r.a, r.b, round(r.score, 9)) for r in sketches.jaccard_join(df, t).collect()]
    assert len(found) == len(set(found)) and {(a, b): s for a, b, s in found} == brute(rows, t)


def test_pack():
    for cols in ([np.zeros(0, np.int64)], [np.arange(300), np.full(300, -1)], [np.array([1 << 62, 0])]):
        assert all((a == b).all() for a, b in zip(cols, setjoin.unpack(setjoin.pack(*cols)), strict=True))


def test_shingles_are_those_of_the_plan(spark):
    rows = [(1, "One two, THREE four ÄÖ"), (2, "a b"), (3, ""), (4, None), (5, "x  y\nz x y z"), (6, "ﬁn 𝒜b c² d_e")]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    from pyspark.sql import functions as F

    want = {r.doc_id: r.h and sorted(r.h) for r in df.select("doc_id", F.transform(tx.word_shingles(F.col("text"), 3), tx.md5_int).alias("h")).collect()}
    assert {r.id: r.hashes for r in sketches.shingle_hashes(df).collect()} == want
    assert {r.id: r.hashes and len(r.hashes) for r in sketches.shingle_hashes(df, fast=True).collect()} == {i: h and len(h) for i, h in want.items()}


def test_sets_are_not_written(spark, monkeypatch):
    """What a join of all documents leaves in the checkpoint folder is less than their text: no set is among it but those of the sample."""
    monkeypatch.setattr(setjoin, "SAMPLE_TASK", 5)
    before = folder_bytes(spark)
    docs = read_table(spark, SF, "documents")
    near, _ = sketches.jaccard_classes(sketches.shingle_sets(docs), 0.5)
    assert near.count() > 0
    assert folder_bytes(spark) - before < Path(SF, "documents.parquet").stat().st_size


def folder_bytes(spark) -> int:
    from twinsift.plans.checkpoints import ensure_checkpoint_dir

    ensure_checkpoint_dir(spark)
    return sum(f.stat().st_size for f in Path(spark.sparkContext.getCheckpointDir().removeprefix("file:")).rglob("*") if f.is_file())
