"""Clusters from vectors, and what deduplication keeps."""

import zlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from twinsift.functions.shipping import by_value
from twinsift.operators.components import components
from twinsift.operators.matching import AT_ONCE, SENT, WIDE, _unit, pairs
from twinsift.plans.checkpoints import cut as written

by_value(__name__)

MATRIX = 4000  # vectors whose distances to one another are kept: 128 MB
RUNG = 0.05  # distance between the heights that `ladder` stops at


def label_all(ids: DataFrame, edges: DataFrame, id_col: str = "id") -> DataFrame:
    """(id, cluster) of every id; ids in no edge are clusters of their own."""
    parts = components(edges.select("a", "b")).withColumnRenamed("component", "cluster")
    return ids.select(F.col(id_col).alias("id")).join(parts, "id", "left").select("id", F.coalesce("cluster", "id").alias("cluster"))


def _labels(ids: np.ndarray, merges: list[tuple[float, int, int]], cut: float) -> np.ndarray:
    """The smallest id of each place's cluster after all merges up to the cut."""
    n = len(ids)
    root = np.arange(n)

    def top(i):
        while root[i] != i:
            root[i] = root[root[i]]
            i = root[i]
        return i

    for height, a, b in merges:
        if height <= cut + 1e-12:
            p, q = top(a), top(b)
            root[max(p, q)] = min(p, q)
    label = np.array([top(i) for i in range(n)])
    least = np.full(n, np.iinfo(np.int64).max)
    np.minimum.at(least, label, ids)
    return least[label]


def agglomerate_lean(x: np.ndarray, ids: np.ndarray, linkage: str, cut: float, begun: np.ndarray | None = None) -> np.ndarray:
    """The clusters of `agglomerate` in memory of the size of the vectors: distances are computed when a chain asks for them. begun: clusters of the rows that were merged before.

    The mean cosine of two clusters is the product of their mean vectors; for complete linkage the farthest member counts, one member of the asking cluster at a time.
    Chains end at the cut: beyond it no merge changes the labels."""
    n = len(ids)
    sums, size, alive = x.copy(), np.ones(n), np.ones(n, bool)
    members: dict[int, list[int]] = {i: [i] for i in range(n)}
    owner = np.arange(n)
    merges, done = [], np.zeros(n, bool)
    if begun is not None:
        _, first, of = np.unique(begun, return_index=True, return_inverse=True)
        for k in np.flatnonzero(first[of] != np.arange(n)).tolist():
            a = int(first[of[k]])
            sums[a] += sums[k]
            size[a] += 1
            owner[k], alive[k], sums[k] = a, False, 0
            members[a] += members.pop(k)
            merges.append((-np.inf, a, k))

    def row(a: int) -> np.ndarray:
        if linkage == "average":
            far = 1 - (sums @ sums[a]) / (size * size[a])
        else:
            far = np.full(n, np.inf if linkage == "single" else -np.inf)
            pick = np.minimum.at if linkage == "single" else np.maximum.at
            for k in members[a]:
                pick(far, owner, 1 - x @ x[k])
        far[~alive] = np.inf
        far[a] = np.inf
        return far

    chain: list[int] = []
    while True:
        if not chain:
            left = np.flatnonzero(alive & ~done)
            if not len(left):
                break
            chain.append(int(left[0]))
        a = chain[-1]
        far = row(a)
        b = int(far.argmin())
        if len(chain) > 1 and far[chain[-2]] <= far[b]:
            b = chain[-2]
        if far[b] > cut + 1e-12:  # nothing within the cut: what led here may still have other neighbours
            done[a] = True
            chain.pop()
            continue
        if len(chain) > 1 and b == chain[-2]:
            del chain[-2:]
            merges.append((float(far[b]), a, b))
            sums[a] += sums[b]
            size[a] += size[b]
            owner[members[b]] = a
            members[a] += members.pop(b)
            alive[b] = False
            sums[b], size[b] = 0, 1
        else:
            chain.append(b)
    return _labels(ids, merges, cut)


def agglomerate(x: np.ndarray, ids: np.ndarray, linkage: str, cut: float) -> np.ndarray:
    """Cluster label (smallest id) of each unit vector: merge nearest pairs of clusters by cosine distance up to the cut."""
    n = len(ids)
    if n > MATRIX:
        return agglomerate_lean(x, ids, linkage, cut)
    return _labels(ids, _merges(1 - x @ x.T, np.ones(n), linkage), cut)


def _merges(far: np.ndarray, size: np.ndarray, linkage: str) -> list[tuple[float, int, int]]:
    """All merges (height, a, b) of clusters of these distances and sizes; both arrays are changed."""
    np.fill_diagonal(far, np.inf)
    alive = np.ones(len(far), bool)
    chain: list[int] = []
    merges = []
    while alive.sum() > 1:
        if not chain:
            chain.append(int(np.flatnonzero(alive)[0]))
        while True:
            a = chain[-1]
            row = np.where(alive, far[a], np.inf)
            b = int(row.argmin())
            if len(chain) > 1 and row[chain[-2]] <= row[b]:
                b = chain[-2]
            if len(chain) > 1 and b == chain[-2]:
                break
            chain.append(b)
        chain.pop()
        chain.pop()
        height = far[a, b]
        merges.append((height, a, b))
        if linkage == "complete":
            new = np.maximum(far[a], far[b])
        elif linkage == "single":
            new = np.minimum(far[a], far[b])
        else:
            new = (size[a] * far[a] + size[b] * far[b]) / (size[a] + size[b])
        far[a], far[:, a] = new, new
        far[a, a] = np.inf
        alive[b] = False
        size[a] += size[b]
    return merges


def _heads(labels: np.ndarray) -> np.ndarray:
    """Where the clusters of sorted labels begin."""
    return np.flatnonzero(np.diff(labels, prepend=labels[:1] - 1))


def _means(x: np.ndarray, start: np.ndarray) -> np.ndarray:
    return np.add.reduceat(x, start, axis=0) / np.diff(np.append(start, len(x)))[:, None]


def _close_clusters(x: np.ndarray, y: np.ndarray, sx: np.ndarray, sy: np.ndarray, linkage: str, low: float) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(i, j) of clusters of unit vectors x and y, beginning at sx and sy, whose similarity by a linkage is low or more: in single precision first, and in double what is near low.

    The mean cosine is the product of the mean vectors; of complete linkage the least cosine of two members counts."""
    if linkage == "average":
        x, y = _means(x, sx), _means(y, sy)
        sx, sy = np.arange(len(x)), np.arange(len(y))
    ends, off = np.append(sx, len(x)), 2e-7 * (8 + x.shape[1])
    x32, y32 = x.astype(np.float32), np.ascontiguousarray(y.T, np.float32)
    upto, p = np.append(sy, len(y)), 0
    while p < len(sx):
        q = max(p + 1, int(np.searchsorted(ends, ends[p] + max(1, AT_ONCE // max(1, len(y))), "right")) - 1)
        score = x32[ends[p] : ends[q]] @ y32
        if linkage == "complete":
            score = np.minimum.reduceat(np.minimum.reduceat(score, sx[p:q] - ends[p], axis=0), sy, axis=1)
        i, j = np.nonzero(score >= low - off)
        sure = score[i, j] >= low + off
        for k in np.flatnonzero(~sure).tolist():
            a, b = p + i[k], j[k]
            sure[k] = (x[ends[a] : ends[a + 1]] @ y[upto[b] : upto[b + 1]].T).min() >= low
        yield p + i[sure], j[sure]
        p = q


def _linked(i: np.ndarray, j: np.ndarray, n: int) -> np.ndarray:
    """The least place that each of n places is linked with, over any number of pairs."""
    least = np.arange(n)
    while True:
        m = np.minimum(least[i], least[j])
        now = least.copy()
        np.minimum.at(now, i, m)
        np.minimum.at(now, j, m)
        now = now[now]
        if (now == least).all():
            return least
        least = now


def _climbed(ids: np.ndarray, clusters: np.ndarray, x: np.ndarray, linkage: str, cut: float) -> np.ndarray:
    """The clusters of all rows, in the order given, after all merges up to the cut; rows are sorted by the clusters that they are in already."""
    start = _heads(clusters)
    if len(start) == 1:
        return clusters
    x = _unit(x.astype(np.float64))
    if len(start) > MATRIX:
        return agglomerate_lean(x, ids, linkage, cut, clusters)
    if linkage == "complete":
        far = np.concatenate([np.maximum.reduceat((1 - x[a:b] @ x.T).max(0, keepdims=True), start, axis=1) for a, b in zip(start, np.append(start[1:], len(x)), strict=True)])
    else:
        m = _means(x, start)
        far = 1 - m @ m.T
    size = np.diff(np.append(start, len(x)))
    return np.repeat(_labels(clusters[start], _merges(far, size.astype(np.float64), linkage), cut), size)


BLOCKS = "i long, ids binary, clusters binary, width int, v binary"


def _packed(ids: np.ndarray, clusters: np.ndarray, x: np.ndarray) -> pa.RecordBatch:
    """A block of whole clusters, sorted by cluster."""
    order = np.lexsort((ids, clusters))
    own, of, v = (np.ascontiguousarray(a[order]).tobytes() for a in (ids, clusters, x.astype(np.float32, copy=False)))
    return pa.record_batch({"i": pa.array([int(ids.min())], pa.int64()), "ids": [own], "clusters": [of], "width": pa.array([x.shape[1]], pa.int32()), "v": pa.array([zlib.compress(v, 1)], pa.binary())})


def _unpacked(batch: pa.RecordBatch, no: str = "") -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(ids, clusters, vectors) of the blocks of a batch."""
    for k in range(batch.num_rows):
        own, of, width, v = (batch.column(f"{c}{no}")[k].as_py() for c in ("ids", "clusters", "width", "v"))
        yield np.frombuffer(own, np.int64), np.frombuffer(of, np.int64), np.frombuffer(zlib.decompress(v), np.float32).reshape(-1, width)


def _flat(column: pa.Array | pa.ChunkedArray, n: int) -> np.ndarray:
    chunks = column.chunks if isinstance(column, pa.ChunkedArray) else [column]
    return np.concatenate([c.flatten().to_numpy(zero_copy_only=False) for c in chunks]).reshape(n, -1)


def packed_blocks(vectors: DataFrame, id_col: str = "id", vector: str = "v") -> DataFrame:
    """The vectors that are there as `ladder` takes them: in single precision, packed in blocks as they come, each a cluster of its own. Written once, and nothing is shuffled."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kept, size = [], 0
        for batch in batches:
            if batch.num_rows:
                kept.append((batch.column("id").to_numpy(), _flat(batch.column("v"), batch.num_rows)))
                size += 8 * kept[-1][1].size
            if size >= WIDE:
                ids, x = (np.concatenate(c) for c in zip(*kept, strict=True))
                yield _packed(ids, ids, x)
                kept, size = [], 0
        if kept:
            ids, x = (np.concatenate(c) for c in zip(*kept, strict=True))
            yield _packed(ids, ids, x)

    return written(vectors.select(F.col(id_col).cast("long").alias("id"), F.col(vector).cast("array<float>").alias("v")).filter("v is not null").mapInArrow(run, BLOCKS))


def ladder(held: DataFrame, linkage: str, cuts: tuple[float, ...]) -> Iterator[tuple[float, DataFrame]]:
    """(cut, clusters (id, cluster)) for each cut in order: what `agglomerative` gives by average or complete linkage; held: as `packed_blocks` gives them.

    Heights are climbed by rungs. With both linkages a merge never brings clusters nearer than their nearest parts were, so what merges up to a rung stays within
    the components of the graph of clusters, as the last rung left them, that are that near by the linkage itself. These components are small, where one of the graph of vectors may
    hold most rows. Each is clustered by itself. Vectors are written once a rung; pairs of blocks are read from there, and only a forest of their links leaves a task."""
    if linkage not in ("average", "complete"):
        raise ValueError(f"linkage {linkage}: average or complete")

    def links(low: float):
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for one, two, (_, a, x), (_, b, y) in zip(batch.column("i1").to_pylist(), batch.column("i2").to_pylist(), _unpacked(batch, "1"), _unpacked(batch, "2"), strict=True):
                    sa, sb = _heads(a), _heads(b)
                    met = list(_close_clusters(_unit(x.astype(np.float64)), _unit(y.astype(np.float64)), sa, sb, linkage, low))
                    i, j = (np.concatenate([m[side] for m in met]) for side in (0, 1))
                    own, j = (a[sa], j) if one == two else (np.concatenate([a[sa], b[sb]]), len(sa) + j)
                    least = _linked(i, j, len(own))
                    at = np.flatnonzero(least != np.arange(len(own)))
                    yield pa.record_batch([pa.array(own[at]), pa.array(own[least[at]])], ["a", "b"])

        return run

    def apart(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for ids, clusters, x in _unpacked(batch):
                for k in range(0, len(ids), 1024):
                    some = x[k : k + 1024]
                    ends = pa.array(np.arange(len(some) + 1, dtype=np.int32) * x.shape[1])
                    yield pa.record_batch([pa.array(ids[k : k + 1024]), pa.array(clusters[k : k + 1024]), pa.ListArray.from_arrays(ends, pa.array(some.ravel()))], ["id", "cluster", "v"])

    def climb(rung: float):
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            rows = pa.Table.from_batches(list(batches))
            ids, clusters, parts = (rows[c].to_numpy() for c in ("id", "cluster", "part"))
            order = np.lexsort((ids, clusters, parts))
            x = _flat(rows["v"], len(ids))[order]
            ids, clusters, parts = ids[order], clusters[order], parts[order]
            start = _heads(parts)
            for a, b in zip(start, np.append(start[1:], len(ids)), strict=True):
                clusters[a:b] = _climbed(ids[a:b], clusters[a:b], x[a:b], linkage, rung)
            yield _packed(ids, clusters, x)

        return run

    def labels(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for ids, clusters, _ in _unpacked(batch):
                yield pa.record_batch([pa.array(ids), pa.array(clusters)], ["id", "cluster"])

    n, size = held.agg(F.coalesce(F.sum(F.octet_length("ids") / 8), F.lit(0)).cast("long"), F.coalesce(F.sum(F.octet_length("ids") * F.col("width")), F.lit(0)).cast("long")).first()
    many = max(1, -(-size // WIDE), min(held.sparkSession.sparkContext.defaultParallelism, n // 1000))
    at = min(cuts)
    for cut in sorted(cuts):
        rung = None
        while rung != cut:
            rung = min(at, cut) if cut - at > 1e-9 else cut
            left, right = (held.select(*(F.col(c).alias(f"{c}{no}") for c in held.columns)) for no in (1, 2))
            parts = components(left.join(right, F.col("i1") <= F.col("i2")).mapInArrow(links(1 - rung - 1e-12), "a long, b long")).select(F.col("id").alias("cluster"), F.col("component").alias("part"))
            parts = F.broadcast(parts) if parts.count() <= SENT else parts
            rows = held.mapInArrow(apart, "id long, cluster long, v array<float>").join(parts, "cluster", "left").withColumn("part", F.coalesce("part", "cluster"))
            rows = rows.select("id", "cluster", "part", "v", F.pmod(F.xxhash64("part"), F.lit(many)).alias("bucket"))
            held = written(rows.repartition(many, "bucket").groupBy("bucket").applyInArrow(climb(rung), BLOCKS))
            at = rung + RUNG
        yield cut, held.mapInArrow(labels, "id long, cluster long")


def agglomerative(vectors: DataFrame, linkage: str = "average", cut: float = 0.3, id_col: str = "vec_id", vector: str = "embedding") -> DataFrame:
    """(id, cluster) by single, complete or average linkage of cosine distances, cut at a distance.

    A merge at or below the cut needs a pair at or below it, so clusters never cross the components of the threshold graph;
    each component is clustered by itself, in one task that holds its vectors. Single linkage is the components."""
    edges = pairs(vectors, 1 - cut, id_col, vector)
    parts = label_all(vectors, edges, id_col)
    if linkage == "single":
        return parts
    rows = vectors.select(F.col(id_col).alias("id"), F.col(vector).cast("array<double>").alias("v")).join(parts, "id")
    size = parts.groupBy("cluster").agg(F.count("*").alias("n"))
    rows = rows.join(size, "cluster")

    def run(key: tuple, part: pd.DataFrame) -> pd.DataFrame:
        part = part.sort_values("id")
        x = np.array(part["v"].tolist())
        length = np.linalg.norm(x, axis=1, keepdims=True)
        x = np.divide(x, length, out=np.zeros_like(x), where=length > 0)
        return pd.DataFrame({"id": part["id"], "cluster": agglomerate(x, part["id"].to_numpy(), linkage, cut)})

    alone = rows.filter("n = 1").select("id", "cluster")
    return rows.filter("n > 1").groupBy("cluster").applyInPandas(run, "id long, cluster long").union(alone)


def keep_one(docs: DataFrame, clusters: DataFrame, keep: str = "min_id", id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, cluster, cluster_size, kept): one document of each cluster stays, the smallest id or the longest text.

    Members are picked by an aggregate, so a cluster that holds a third of all documents is no window of its own."""
    rows = docs.select(F.col(id_col).alias("id"), F.length(text_col).alias("n")).join(clusters, "id")
    rank = F.struct(F.lit(0).alias("n"), (-F.col("id")).alias("id")) if keep == "min_id" else F.struct(F.col("n").alias("n"), (-F.col("id")).alias("id"))
    best = rows.groupBy("cluster").agg(F.max(rank).alias("b"), F.count("*").alias("cluster_size")).select("cluster", (-F.col("b.id")).alias("best"), "cluster_size")
    return rows.join(best, "cluster").select("id", "cluster", "cluster_size", (F.col("id") == F.col("best")).cast("int").alias("kept"))


def rates(near: DataFrame, members: DataFrame, split: DataFrame, owner: str = "id") -> DataFrame:
    """(split, n, with_duplicate, percent): texts with another text of the train part that equals them or is linked with them.

    near: links (a, b) of classes of equal rows; members: (id, rep), and the text a row is a part of (owner) if rows are parts; split: (id, split) of texts,
    'train' or another name. A class carries the smallest and the largest of its train texts, which tell whether it has another one; copies are never paired."""
    rows = members.select("rep", F.col(owner).alias("text")).distinct().join(split.select(F.col("id").alias("text"), "split"), "text")
    train = F.when(F.col("split") == "train", F.col("text"))
    ends = rows.groupBy("rep").agg(F.min(train).alias("lo"), F.max(train).alias("hi")).filter("lo is not null")
    both = near.select("a", "b").union(near.select("b", "a"))
    beside = both.join(ends.withColumnRenamed("rep", "b"), "b").groupBy(F.col("a").alias("rep")).agg(F.min("lo").alias("lo2"), F.max("hi").alias("hi2"))
    other = F.greatest(*(F.coalesce((F.col(c) != F.col("text")).cast("int"), F.lit(0)) for c in ("lo", "hi", "lo2", "hi2")))
    hit = rows.join(ends, "rep", "left").join(beside, "rep", "left").groupBy("text").agg(F.max(other).alias("hit"))
    out = split.select(F.col("id").alias("text"), "split").join(hit, "text", "left").groupBy("split").agg(F.count("*").alias("n"), F.coalesce(F.sum("hit"), F.lit(0)).alias("with_duplicate"))
    return out.withColumn("percent", F.round(F.try_divide(100.0 * F.col("with_duplicate"), "n"), 6))


def rate_within(ids: DataFrame, near: DataFrame, members: DataFrame) -> DataFrame:
    """(n, with_duplicate, percent): ids whose text equals another's or is linked with it, over all ids."""
    return rates(near, members, ids.select("id", F.lit("train").alias("split"))).drop("split")


def rate_across(split: DataFrame, near: DataFrame, members: DataFrame) -> DataFrame:
    """The same for valid ids that have a train partner; split: (id, split)."""
    return rates(near, members, split).filter("split = 'valid'").drop("split")


def drop_chunks(chunks: DataFrame, mark: str = "chunk") -> DataFrame:
    """(doc_id, text, dropped): documents put together again from the chunks that no smaller (doc_id, chunk_no) has.

    chunks: doc_id, chunk_no, chunk and a column that is equal for repeated chunks; the first place is found by an aggregate, not a window."""
    first = chunks.filter(F.length("chunk") > 0).groupBy(F.sha2(F.col(mark).cast("binary"), 256).alias("k")).agg(F.min(F.struct("doc_id", "chunk_no")).alias("f"))
    rows = chunks.withColumn("k", F.sha2(F.col(mark).cast("binary"), 256)).join(first, "k", "left")
    keep = F.col("f").isNull() | (F.col("f") == F.struct("doc_id", "chunk_no"))
    parts = F.array_sort(F.collect_list(F.when(keep, F.struct("chunk_no", "chunk"))))
    return rows.groupBy("doc_id").agg(F.array_join(F.transform(parts, lambda p: p["chunk"]), "").alias("text"), F.count(F.when(~keep, 1)).alias("dropped"))


def top_window(df: DataFrame, by: list[str], order: list, n: int) -> DataFrame:
    return df.withColumn("rn", F.row_number().over(Window.partitionBy(*by).orderBy(*order))).filter(F.col("rn") <= n)
