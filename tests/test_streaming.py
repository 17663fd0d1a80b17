"""Streams over files: one batch or many, restarts, late rows, and agreement with the batch twins."""

from datetime import datetime

import pytest
from pyspark.sql import functions as F

from twinsift.streaming import guard

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def source(spark, tmp_path_factory):
    path = str(tmp_path_factory.mktemp("arrivals") / "in")
    rows = guard.arrivals(spark.read.parquet(f"{SF}/documents.parquet"), spark.read.parquet(f"{SF}/events.parquet"))
    rows.repartition(5, "doc_id").write.parquet(path)
    return path


def test_exact_many_batches_as_one(spark, source, tmp_path):
    out = []
    for n in (1, 100):
        folder = str(tmp_path / f"e{n}")
        guard.drain(guard.exact(guard.file_stream(spark, source, n), "3650 days"), folder)
        got = spark.read.parquet(f"{folder}/out")
        out.append(sorted(r.text_hash for r in got.collect()))
        assert len(out[-1]) == len(set(out[-1]))
    texts = spark.read.parquet(source).select("text").distinct().count()
    assert out[0] == out[1] and len(out[0]) == texts
    folder = str(tmp_path / "e1")
    guard.drain(guard.exact(guard.file_stream(spark, source, 1), "3650 days"), folder)  # goes on, nothing new
    assert spark.read.parquet(f"{folder}/out").count() == texts


def test_near_guard(spark, source, tmp_path):
    rows = spark.read.parquet(source)
    index, keys = guard.build_index(rows.filter("doc_id % 2 = 0"), 0.8)
    index, keys = index.cache(), keys.cache()
    put = guard.append_once(str(tmp_path / "n"))
    guard.drain(guard.file_stream(spark, source, 2).filter("doc_id % 2 = 1"), str(tmp_path / "q"), put=lambda b, i: put(guard.near(b, index, keys, 0.8), i))
    streamed = sorted(map(tuple, spark.read.parquet(str(tmp_path / "n")).select("doc_id", "match").collect()))
    batch = sorted(map(tuple, guard.near(rows.filter("doc_id % 2 = 1"), index, keys, 0.8).select("doc_id", "match").collect()))
    assert streamed == batch and streamed


def test_windows_and_late(spark, source, tmp_path):
    stream = guard.file_stream(spark, source, 2).withWatermark("ts", "3650 days").withColumn("is_repeat", F.lit(0))
    guard.drain(guard.tumbling(stream), str(tmp_path / "w"), "complete", put=lambda b, i: b.write.mode("overwrite").parquet(str(tmp_path / "wout")))
    batch = guard.tumbling(spark.read.parquet(source).withColumn("is_repeat", F.lit(0)))
    assert sorted(map(tuple, spark.read.parquet(str(tmp_path / "wout")).collect())) == sorted(map(tuple, batch.collect()))
    guard.drain(guard.file_stream(spark, source, 1), str(tmp_path / "l"), put=guard.count_late(str(tmp_path / "late"), 60))
    tops = {r.number: r.top for r in spark.read.parquet(str(tmp_path / "late/newest")).collect()}
    assert len(tops) == 5
    order = sorted(tops)
    got = {r["batch"]: r["n"] for r in spark.read.parquet(str(tmp_path / "late/late")).groupBy("batch").agg(F.count("*").alias("n")).collect()}
    assert sum(got.values()) > 0 and set(got) <= set(order[1:])


def test_late_rows_after_a_restart(spark, tmp_path):
    """A sink that is made anew knows what came before; a batch that runs again gives the same."""
    batch = lambda *hours: spark.createDataFrame([(datetime(2024, 1, 1, h),) for h in hours], "ts timestamp")
    guard.count_late(str(tmp_path), 3600)(batch(1, 12), 0)
    for _ in range(2):
        guard.count_late(str(tmp_path), 3600)(batch(3, 11, 13), 1)
    guard.count_late(str(tmp_path), 3600)(batch(11, 14), 2)
    assert sorted((r["batch"], r["ts"].hour) for r in spark.read.parquet(f"{tmp_path}/late").collect()) == [(1, 3), (2, 11)]


def test_recent_arrivals_forget_nothing(spark, tmp_path):
    """One text arrives 150 times over three batches, and a near copy of it: every pair is told, none is lost to a bound."""
    words = [f"w{k}" for k in range(60)]
    rows = [(i, " ".join(words)) for i in range(150)] + [(150, " ".join([*words[:-1], "end"])), (151, "another text of its own that nobody else has sent here")]
    path = str(tmp_path / "in")
    spark.createDataFrame([(datetime(2024, 1, 1, 0, i % 60), i, 1, t) for i, t in rows], guard.SCHEMA).repartition(3, "doc_id").write.parquet(path)
    guard.drain(guard.recent(guard.file_stream(spark, path, 1), 0.8), str(tmp_path / "r"))
    got = {frozenset((r.doc_id, r.match)) for r in spark.read.parquet(str(tmp_path / "r/out")).collect()}
    assert got >= {frozenset((a, b)) for a in range(150) for b in range(a)} and not any(151 in pair for pair in got)
    assert any(150 in pair for pair in got)


def test_interval_join(spark, source, tmp_path):
    guard.drain(guard.interval_pairs(guard.file_stream(spark, source, 5), 60 * 24 * 400, "900 days"), str(tmp_path / "j"))
    rows = spark.read.parquet(source).select("doc_id", "text")
    want = rows.join(rows.select(F.col("doc_id").alias("b"), "text"), "text").filter("doc_id < b").select("doc_id", "b")
    assert sorted(map(tuple, spark.read.parquet(str(tmp_path / "j/out")).select("a", "b").collect())) == sorted(map(tuple, want.collect()))
