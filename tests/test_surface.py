"""SQL functions, table functions, views, sources and sinks, and plans."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from twinsift.functions import registry
from twinsift.functions import text as tx
from twinsift.functions import vectors as vx
from twinsift.sources import tables

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def sql(spark):
    registry.register(spark, SF, encoder=True)
    return spark.sql


def test_sql_functions(spark, sql, docs):
    docs.createOrReplaceTempView("ts_docs")
    a = {r[0]: sorted(r[1]) for r in sql("select doc_id, ts_shingles(text) from ts_docs").collect()}
    b = {r[0]: sorted(r[1]) for r in docs.select("doc_id", tx.word_shingles(F.col("text"), 3)).collect()}
    assert a == b
    assert sql("select ts_hamming(0, 7), round(ts_cosine(array(1D, 0D), array(0.6D, 0.8D)), 6), ts_cosine(array(0D), array(1D)), ts_md5_int('a')").first()[:3] == (3, 0.6, None)
    assert sql("select ts_nfkc('ﬁ１')").first()[0] == "fi1"
    assert abs(np.linalg.norm(sql("select ts_encode_doc(text) from ts_docs where length(text) > 100").first()[0]) - 1) < 1e-4


def test_table_functions_and_views(spark, sql, docs):
    docs.createOrReplaceTempView("ts_docs")
    assert sql("select count(*) from ts_docs, lateral ts_chunks(text, 512, 512)").first()[0] == sql("select count(*) from nd_chunks").first()[0]
    n = sql("select count(*) from ts_docs, lateral ts_shingle_rows(text, 3)").first()[0]
    assert n == docs.agg(F.sum(F.size(tx.word_shingles(F.col("text"), 3)))).first()[0]
    assert sql("select count(*) from lateral ts_band_keys(array(1, 2, 3, 4), 2, 2)").first()[0] == 2
    assert sql("select count(*) from lateral ts_augmentations('some text', 3)").first()[0] == 3
    assert sql("select count(*) from nd_pairs").first()[0] > 0 and sql("select count(distinct id) from nd_clusters").first()[0] == docs.count()


def test_grouped_aggregates(spark, sql):
    e = spark.read.parquet(f"{SF}/embeddings.parquet").withColumn("d", F.floor(F.col("vec_id") / 8))
    e.createOrReplaceTempView("ts_e")
    got = {r[0]: r[1] for r in sql("select d, ts_mean_vector(embedding) from ts_e group by d").collect()}
    want = {r[0]: r[1] for r in e.groupBy("d").agg(vx.mean_vector("embedding", 64)).collect()}
    assert all(np.allclose(got[k], want[k], atol=1e-6) for k in want)
    gem = {r[0]: r[1] for r in sql("select d, ts_gem(embedding) from ts_e group by d").collect()}
    same = {r[0]: r[1] for r in e.groupBy("d").agg(vx.gem_vector("embedding", 64)).collect()}
    assert all(np.allclose(gem[k], same[k], atol=1e-6) for k in same)


def test_sources_and_sinks(spark, docs, tmp_path):
    for form in ("json", "orc", "parquet", "csv"):
        path = str(tmp_path / form)
        (docs.write.option("header", True).option("escape", '"') if form == "csv" else docs.write).format(form).save(path)
        rows, bad = tables.read_corpus(spark, path, form)
        assert len(rows.collect()) == docs.count() and (bad is None or not bad.collect()), form
    tables.write_store(docs, str(tmp_path / "by"), "lang")
    assert spark.read.parquet(str(tmp_path / "by")).filter("lang = 'en'").count() == docs.filter("lang = 'en'").count()
    with pytest.raises(ValueError):
        docs.drop("text").write.parquet(str(tmp_path / "x/documents.parquet"))
        tables.read_table(spark, str(tmp_path / "x"), "documents")


def plan(df) -> str:
    return df._jdf.queryExecution().toString()


def test_malformed_rows_are_kept_aside(spark, tmp_path):
    (tmp_path / "j.json").write_text('{"doc_id": 1, "text": "a"}\nnot json\n')
    rows, bad = tables.read_corpus(spark, str(tmp_path / "j.json"), "json")
    assert [r.doc_id for r in rows.collect()] == [1] and [r.bad for r in bad.collect()] == ["not json"]


def test_plans(spark):
    SF = "/root/testdata/sf0.01"  # the small table is cached by other tests
    docs = tables.read_table(spark, SF, "documents")
    from twinsift.catalogue import everything
    from twinsift.encoder import api

    q = everything()[0]
    usable = plan(q["t_usable"](spark, SF))
    assert "PushedFilters: [IsNotNull(n_chars), GreaterThanOrEqual(n_chars,16)]" in usable and "text:string" not in usable
    for name in ("b_minhash_lsh", "b_jaccard", "b_simhash_blocks", "h_join_range", "h_join_interval"):
        assert "Cartesian" not in plan(q[name](spark, SF)) and "NestedLoop" not in plan(q[name](spark, SF)), name
    weights, c = api.model("tiny")
    done = api.encode_texts(docs, weights, c)
    physical = plan(done.select("id", F.size("doc_vector"), F.size("chunk_vectors"))).split("== Physical Plan ==")[1]
    assert physical.count("MapInPandas") == 1 and "hashpartitioning" not in physical
