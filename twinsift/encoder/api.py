"""The encoder over DataFrames: both kinds of vectors in one pass, weights sent to the tasks once."""

from collections.abc import Iterator
from pathlib import Path

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from twinsift.encoder.net import PRESETS, Config, encode, init, lean
from twinsift.functions.shipping import by_value
from twinsift.functions.text import chunk_array

by_value(__name__)

WEIGHTS = Path(__file__).parent / "weights"


def model(preset: str = "tiny", trained: bool = True, seed: int = 0) -> tuple[dict, Config]:
    """Weights and configuration; untrained weights are the floor that training must beat."""
    c = PRESETS[preset]
    if not trained:
        return init(c, seed), c
    with np.load(WEIGHTS / f"{preset}.npz") as f:
        return {k: f[k].astype(np.float32) for k in f.files}, c


def encode_chunks(chunks: DataFrame, weights: dict, c: Config) -> DataFrame:
    """(doc_id, chunk_no, vector) of rows (doc_id, chunk_no, chunk). Equal chunks are encoded once and joined back by hash."""
    sent = chunks.sparkSession.sparkContext.broadcast(weights)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for rows in batches:
            for a in range(0, len(rows), 2048):
                part = rows.iloc[a : a + 2048]
                v = encode(sent.value, c, [t[: c.chunk] for t in part["chunk"]])
                yield pd.DataFrame({"h": part["h"].to_numpy(), "vector": list(v)})

    keyed = chunks.select("doc_id", "chunk_no", F.sha2(F.col("chunk").cast("binary"), 256).alias("h"), "chunk")
    vectors = keyed.select("h", "chunk").dropDuplicates(["h"]).mapInPandas(run, "h string, vector array<float>")
    return keyed.select("doc_id", "chunk_no", "h").join(vectors, "h").select("doc_id", "chunk_no", "vector")


def encode_texts(docs: DataFrame, weights: dict, c: Config, id_col: str = "doc_id", text_col: str = "text", parts: bool = True) -> DataFrame:
    """(id, doc_vector, chunk_vectors): one forward pass gives both; a document's chunks stay together, so nothing is shuffled.

    A null text has null vectors; the empty text is one empty chunk. Chunks are encoded in groups of bounded size, whatever the length of a text.
    Without parts the chunk vectors are null, and do not leave Python."""
    sent = docs.sparkSession.sparkContext.broadcast(weights)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        ready = lean(sent.value, c)
        for rows in (b.iloc[k : k + 256] for b in batches for k in range(0, len(b), 256)):
            texts = rows["text"].tolist()
            count = np.array([0 if t is None else max(1, -(-len(t) // c.chunk)) for t in texts], np.int64)
            flat = [t[i : i + c.chunk] for t in texts if t is not None for i in range(0, max(1, len(t)), c.chunk)]
            v = np.concatenate([encode(sent.value, c, flat[k : k + 4096], ready=ready) for k in range(0, len(flat), 4096)]) if flat else np.zeros((0, c.dim), np.float32)
            ends = np.concatenate([[0], np.cumsum(count)])
            mean = np.array([v[a:b].mean(0) if b > a else np.zeros(c.dim, np.float32) for a, b in zip(ends[:-1], ends[1:], strict=True)], np.float32)
            size = np.array([np.linalg.norm(m) for m in mean], np.float32)
            whole = [m / z if z > 0 else None for m, z in zip(mean, size, strict=True)]
            own = [list(v[a:b]) if parts and b > a else None for a, b in zip(ends[:-1], ends[1:], strict=True)]
            yield pd.DataFrame({"id": rows["id"].to_numpy(), "doc_vector": whole, "chunk_vectors": own})

    return docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text")).mapInPandas(run, "id long, doc_vector array<float>, chunk_vectors array<array<float>>")


def pool_documents(chunk_vectors: DataFrame, dim: int, how: str = "mean", network: list[tuple[np.ndarray, np.ndarray]] | None = None) -> DataFrame:
    """(doc_id, vector) from (doc_id, vector, n_chars): plain mean, mean by length, or a deep-averaging network over the mean; unit length, zero becomes null."""
    from twinsift.functions.vectors import l2_normalize, mean_vector, weighted_vector

    pooled = chunk_vectors.groupBy("doc_id").agg((weighted_vector("vector", "n_chars", dim) if how == "length" else mean_vector("vector", dim)).alias("vector"))
    if how != "dan":
        return pooled.select("doc_id", l2_normalize(F.col("vector")).alias("vector"))

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for rows in batches:
            x = np.array(rows["vector"].tolist()).reshape(len(rows), -1)
            for k, (w, b) in enumerate(network):
                x = x @ w + b
                x = np.maximum(x, 0) if k < len(network) - 1 else x
            size = np.linalg.norm(x, axis=1, keepdims=True)
            yield pd.DataFrame({"doc_id": rows["doc_id"], "vector": list(np.divide(x, size, out=np.zeros_like(x), where=size > 0))})

    return pooled.mapInPandas(run, "doc_id long, vector array<double>")


def chunks_of(docs: DataFrame, c: Config) -> DataFrame:
    return docs.filter("text is not null").select("doc_id", F.posexplode(chunk_array(F.col("text"), c.chunk)).alias("chunk_no", "x")).select("doc_id", "chunk_no", "x.chunk")
