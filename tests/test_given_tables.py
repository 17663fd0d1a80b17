"""Queries that once made their rows up read a given table; breakdowns of retrieval ask for the stated rows."""

import pytest
from pyspark.sql import functions as F

from twinsift.catalogue import everything
from twinsift.experiments import workloads as w
from twinsift.sources.tables import read_table

SF = "/root/testdata/sf0.001"
QUERIES = everything()[0]


@pytest.mark.parametrize("name", ["c_footprint", "t_cosine_lr"])
def test_reads_the_documents(spark, name):
    assert any("documents.parquet" in f for f in QUERIES[name](spark, SF).inputFiles())


def test_breakdown_by_amount_asks_for_stated_rows_against_all(spark, monkeypatch):
    seen = []
    monkeypatch.setattr(w, "retrieval", lambda found, queries, *_: seen.append((found, queries)))
    w.w_by_amount(spark, SF)
    found, queries = seen[0]
    once = w.targets(read_table(spark, SF, "documents"))
    assert found.count() == once.count()
    asked = {r.target for r in queries.select("target").distinct().collect()}
    assert asked == {r.doc_id for r in once.filter("doc_id % 50 = 0").collect()} and asked
    assert queries.groupBy("amount").agg(F.count("*").alias("n")).count() == len(w.RATES)
