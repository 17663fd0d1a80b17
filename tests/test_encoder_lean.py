"""The encoder without gradients gives the numbers of `forward`, whatever texts share its batch; both kinds of vectors come from one pass."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from twinsift.encoder import api, net
from twinsift.encoder.tape import Node
from twinsift.experiments import workloads as w
from twinsift.operators import matching
from twinsift.sources.tables import read_table

SF = "/root/testdata/sf0.001"
TEXTS = ["", "a", "x" * 128, "word " * 20, "日本語 text", "\U0001f600 far point", "y" * 97, "z" * 113, "ünïcode " * 9]


def alone(weights, c, text):
    length = min(c.chunk, -(-max(1, len(text)) // 16) * 16)
    x, mask = net.bits([text], length)
    mask[:, 0] = np.maximum(mask[:, 0], 1e-6)
    return net.forward({k: Node(v, track=False) for k, v in weights.items()}, c, x, mask).value[0]


@pytest.mark.parametrize("trained", [True, False])
def test_lean_encoder_is_forward_of_each_text_alone(trained):
    weights, c = api.model("tiny", trained)
    want = np.array([alone(weights, c, t) for t in TEXTS])
    assert np.abs(net.encode(weights, c, TEXTS) - want).max() < 2e-6
    assert np.abs(net.encode(weights, c, TEXTS[::-1], batch=3)[::-1] - want).max() < 2e-6


@pytest.mark.parametrize("trained", [True, False])
def test_encoder_of_a_task_looks_up_the_first_block_of_full_chunks(trained, monkeypatch):
    weights, c = api.model("tiny", trained)
    rnd = np.random.default_rng(3)
    texts = ["".join(map(chr, rnd.integers(1, 256, c.chunk))) for _ in range(9)] + TEXTS + ["x" * 127 + "\u0100"]
    want = np.array([alone(weights, c, t) for t in texts])
    ready, gates = net.lean(weights, c), []
    assert np.abs(net.encode(weights, c, texts, ready=ready) - want).max() < 2e-6
    real = ready._gates
    monkeypatch.setattr(ready, "_gates", lambda i, *a: gates.append(i) or real(i, *a))
    assert np.abs(net.encode(weights, c, texts[:9], ready=ready) - want[:9]).max() < 2e-6
    assert set(gates) == {1}


def test_vectors_of_texts(spark):
    weights, c = api.model("tiny")
    docs = spark.createDataFrame([(1, "ab" * 200), (2, ""), (3, None)], "doc_id long, text string")
    rows = {r.id: r for r in api.encode_texts(docs, weights, c).collect()}
    chunks = [("ab" * 200)[i : i + 128] for i in range(0, 400, 128)]
    assert np.allclose(rows[1].chunk_vectors, net.encode(weights, c, chunks), atol=1e-6)
    mean = np.mean(rows[1].chunk_vectors, 0)
    assert np.allclose(rows[1].doc_vector, mean / np.linalg.norm(mean), atol=1e-6)
    assert len(rows[2].chunk_vectors) == 1 and rows[3].chunk_vectors is None and rows[3].doc_vector is None
    bare = {r.id: r for r in api.encode_texts(docs, weights, c, parts=False).collect()}
    assert bare[1].doc_vector == rows[1].doc_vector and bare[1].chunk_vectors is None


def test_index_cost_encodes_the_texts_once_and_writes_no_chunk_vectors(spark, monkeypatch):
    whole, written, real, cut = [], [], api.encode_texts, w.cut
    monkeypatch.setattr(api, "encode_texts", lambda docs, *a, **k: whole.append(docs.count()) or real(docs, *a, **k))
    monkeypatch.setattr(w, "cut", lambda df: written.append(df.columns) or cut(df))
    rows = {r.method.split(",")[0]: r for r in w.c_index_cost(spark, SF).collect()}
    docs = read_table(spark, SF, "documents")
    n, texts = docs.count(), docs.filter("text is not null")
    many = texts.agg(F.sum(F.greatest(F.lit(1), F.ceil(F.length("text") / 128)))).first()[0]
    assert len(whole) == 4 and whole[1] == n and set(rows) == {"doc", "chunk", "minhash bands"}
    assert not any("chunk_vectors" in c for c in written)
    assert rows["chunk"].vectors_per_document == many / n and rows["doc"].vectors_per_document == texts.count() / n


def test_cells_of_parts(spark):
    rnd = np.random.default_rng(2)
    centres = rnd.normal(size=(5, 4))
    parts = [[[float(y) for y in x] for x in rnd.normal(size=(k, 4)).astype(np.float32)] for k in (3, 1, 4)]
    done = spark.createDataFrame([(i, None, p) for i, p in enumerate(parts)] + [(3, None, None)], "id long, doc_vector array<float>, chunk_vectors array<array<float>>")
    got = {r.id: r.cells for r in matching.cells_of_parts(done, centres).collect()}
    near = lambda x: int(((np.array(x) - centres) ** 2).sum(1).argmin())
    assert got == {i: [near(x) for x in p] for i, p in enumerate(parts)} | {3: []}


def test_inverted_lists_ship_probed_cells_only(spark, monkeypatch):
    rnd = np.random.default_rng(4)
    x = rnd.normal(size=(300, 8))
    e = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<double>")
    cells, centres = matching.ivf_build(e, 30)
    assert centres.shape == (30, 8) and cells.count() == 300
    shipped, real = [], matching._search
    monkeypatch.setattr(matching, "_search", lambda q, t, *a, **k: shipped.append(t.count()) or real(q, t, *a, **k))
    found, _ = matching.ivf_search(e.filter("vec_id < 2"), e, cells, centres, 1, 2, skip_same=False)
    assert {r.query_id: r.target_id for r in found.collect()} == {0: 0, 1: 1} and shipped[0] < 150


def test_texts_are_dealt_over_all_cores(spark):
    docs = read_table(spark, SF, "documents").coalesce(2)
    dealt = w.spread(docs)
    assert dealt.rdd.getNumPartitions() == 4 * spark.sparkContext.defaultParallelism and dealt.count() == docs.count()
