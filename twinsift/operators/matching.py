"""Nearest neighbours and threshold joins over vectors."""

import math
import time
from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from twinsift.functions.shipping import by_value
from twinsift.operators.sketches import candidates
from twinsift.plans.checkpoints import cut

by_value(__name__)

BLOCK = 2000
#: Bytes of vectors in the largest block of a tile, tiles wanted at least, and scores or pairs that a tile looks at at a time.
WIDE, TILES, AT_ONCE = 1 << 24, 21, 1 << 21


def _matrix(column: pd.Series) -> np.ndarray:
    return _unit(np.array(column.tolist(), np.float64))


def _unit(x: np.ndarray) -> np.ndarray:
    length = np.linalg.norm(x, axis=1, keepdims=True)
    return np.divide(x, length, out=np.zeros_like(x), where=length > 0)


def _vectors(df: DataFrame, id_col: str, vector: str, *more: Column) -> tuple[DataFrame, int, int]:
    """(id, v, ...) of the rows that have a vector, how many there are, and how many of them a block may hold."""
    df = df.select(F.col(id_col).cast("long").alias("id"), F.col(vector).cast("array<double>").alias("v"), *more).filter("v is not null")
    n, dim = df.agg(F.count("*"), F.max(F.size("v"))).first()
    return df, n, max(BLOCK, WIDE // (8 * max(1, dim or 1)))


def _dealt(df: DataFrame, blocks: int, name: str) -> DataFrame:
    return df.withColumn(name, F.pmod(F.xxhash64("id"), F.lit(blocks)).cast("int"))


def _whole(batches: Iterator[pa.RecordBatch]) -> tuple[dict[str, np.ndarray], np.ndarray]:
    """The plain columns of a group, and its vectors as a matrix."""
    rows = pa.Table.from_batches(list(batches))
    flat = [c.flatten().to_numpy(zero_copy_only=False) for c in rows["v"].chunks]
    return {c: rows[c].to_numpy() for c in rows.column_names if not pa.types.is_list(rows[c].type)}, np.concatenate(flat).astype(np.float64, copy=False).reshape(len(rows), -1)


def _shared(q: np.ndarray, t: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Rows of q and t that have a key in common, each two once, some at a time; q and t: a row of keys each."""
    flat = t.ravel()
    order = np.argsort(flat, kind="stable")
    flat, owner = flat[order], order // t.shape[1]
    by = np.argsort(q, axis=None, kind="stable")  # sought in order, which the search takes far less time for
    lo, hi = np.empty(q.size, np.int64), np.empty(q.size, np.int64)
    lo[by], hi[by] = (np.searchsorted(flat, q.ravel()[by], side) for side in ("left", "right"))
    count, lo = (hi - lo).reshape(q.shape), lo.reshape(q.shape)
    upto = np.cumsum(count.sum(1))
    at = 0
    while at < len(q):
        end = max(at + 1, int(np.searchsorted(upto, (upto[at - 1] if at else 0) + AT_ONCE, "right")))
        c = count[at:end].ravel()
        place = np.arange(c.sum()) + np.repeat(lo[at:end].ravel() - (np.cumsum(c) - c), c)
        row = np.repeat(np.repeat(np.arange(at, end), q.shape[1]), c)
        yield np.divmod(np.unique(row * len(t) + owner[place]), len(t))
        at = end


def _scores(a: np.ndarray, b: np.ndarray, x: np.ndarray, y: np.ndarray) -> np.ndarray:
    step = 1 << 16
    return np.concatenate([np.einsum("ij,ij->i", a[x[k : k + step]], b[y[k : k + step]]) for k in range(0, len(x), step)] or [np.zeros(0)])


def _best(own: np.ndarray, ids: np.ndarray, x: np.ndarray, y: np.ndarray, score: np.ndarray, k: int) -> pa.RecordBatch:
    """The k best of pairs (x, y) by row x, ties to the smallest id."""
    order = np.lexsort((ids[y], -score, x))
    x, y, score = x[order], y[order], score[order]
    keep = np.arange(len(x)) - np.searchsorted(x, x) < k
    return pa.record_batch({"query_id": own[x[keep]], "target_id": ids[y[keep]], "score": score[keep], "compared": np.zeros(keep.sum(), np.int64)})


def _search(queries: DataFrame, targets: DataFrame, k: int, q: tuple[str, str], t: tuple[str, str], skip_same: bool, keys: Callable | None = None, extra: tuple[Column, Column] | None = None) -> DataFrame:
    """(query_id, target_id, score, compared): the k best of each query in each block of targets; and rows without a target, with the number of pairs compared.

    Blocks of queries meet blocks of targets as groups, so no pair leaves Python. keys(matrix, column) gives a row of keys of each vector, of which a query and a target
    must share one to be compared; extra: an array column for either side that it may use."""
    more = [[x.alias("extra")] for x in extra] if extra else [[], []]
    (qs, a, most), (ts, b, _) = _vectors(queries, *q, *more[0]), _vectors(targets, *t, *more[1])
    nq = max(1, -(-a // most))
    nt = max(1, -(-b // most), min(-(-b // BLOCK), -(-TILES // nq)))
    told = extra is not None
    names = ["id", "v", *(["extra"] if told else [])]
    qs = _dealt(qs, nq, "i").withColumn("j", F.explode(F.sequence(F.lit(0), F.lit(nt - 1)))).select("i", "j", F.lit(0).alias("side"), *names)
    ts = _dealt(ts, nt, "j").withColumn("i", F.explode(F.sequence(F.lit(0), F.lit(nq - 1)))).select("i", "j", F.lit(1).alias("side"), *names)

    def tile(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        batches = list(batches)
        rows, v = _whole(batches)
        one, two = (np.flatnonzero(rows["side"] == x) for x in (0, 1))
        if not len(one) or not len(two):
            return
        two = two[np.argsort(rows["id"][two], kind="stable")]
        own, ids, x, y = rows["id"][one], rows["id"][two], _unit(v[one]), _unit(v[two])
        if keys is None:
            step = max(1, AT_ONCE // len(two))
            for at in range(0, len(one), step):
                score = np.round(x[at : at + step] @ y.T, 12)
                score[~np.isfinite(score)] = -np.inf
                if skip_same:
                    score[own[at : at + step, None] == ids[None]] = -np.inf
                row = np.arange(len(score))
                for _ in range(min(k, len(two))):
                    col = score.argmax(1)  # the first of equal ones has the smallest id
                    top = score[row, col]
                    fine = np.isfinite(top)
                    yield pa.record_batch({"query_id": own[at : at + step][fine], "target_id": ids[col[fine]], "score": top[fine], "compared": np.zeros(fine.sum(), np.int64)})
                    score[row, col] = -np.inf
            return
        column = pa.chunked_array([c["extra"] for c in batches]) if told else None
        kq, kt = (keys(v[side], column.take(pa.array(side)) if told else None) for side in (one, two))
        compared = 0
        for i, j in _shared(kq, kt):
            compared += len(i)
            if skip_same:
                other = own[i] != ids[j]
                i, j = i[other], j[other]
            yield _best(own, ids, i, j, np.round(_scores(x, y, i, j), 12), k)
        yield pa.record_batch([pa.array([None], pa.int64()), pa.array([None], pa.int64()), pa.array([None], pa.float64()), pa.array([compared], pa.int64())], ["query_id", "target_id", "score", "compared"])

    return qs.union(ts).groupBy("i", "j").applyInArrow(tile, "query_id long, target_id long, score double, compared long")


def _ranked(found: DataFrame, k: int) -> DataFrame:
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "target_id")
    return found.filter("target_id is not null").withColumn("rank", F.row_number().over(order)).filter(F.col("rank") <= k).select("query_id", "rank", "target_id", "score")


def knn(queries: DataFrame, targets: DataFrame, k: int = 1, q: tuple[str, str] = ("query_id", "embedding"), t: tuple[str, str] = ("target_id", "embedding"), skip_same: bool = False) -> DataFrame:
    """Exact: (query_id, rank, target_id, score), best cosine first, ties to the smallest id; each tile hands on k rows a query."""
    return _ranked(_search(queries, targets, k, q, t, skip_same), k)


def _tiled(base: DataFrame, blocks: int) -> DataFrame:
    """(i, j, b, ...): each block of rows (id, ...) with each block, itself included."""
    both = _dealt(base, blocks, "b").withColumn("o", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))))
    return both.select(F.least("b", "o").alias("i"), F.greatest("b", "o").alias("j"), "b", *base.columns)


def _blocks(n: int, most: int) -> int:
    return max(1, -(-n // most), min(-(-n // BLOCK), math.isqrt(2 * TILES)))


def _sides(key: tuple[pa.Scalar, ...], rows: dict[str, np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """Places of the rows of either block of a tile."""
    return tuple(np.flatnonzero(rows["b"] == k.as_py()) for k in key)


def _close(x: np.ndarray, y: np.ndarray, threshold: float) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(i, j, score) of unit vectors with cosine >= threshold: single precision less a bound of its error first, then double."""
    x32, y32 = x.astype(np.float32), y.astype(np.float32)
    low = threshold - 1e-12 - (x.shape[1] + 8) * 2e-7
    step = max(1, AT_ONCE // max(1, len(y)))
    for at in range(0, len(x), step):
        i, j = np.nonzero(x32[at : at + step] @ y32.T >= low)
        i += at
        score = _scores(x, y, i, j)
        sure = score >= threshold - 1e-12
        yield i[sure], j[sure], score[sure]


def _once(a: np.ndarray, b: np.ndarray, diagonal: bool, *more: np.ndarray) -> list[np.ndarray]:
    """Ids of pairs in order, each pair of a tile once."""
    keep = a < b if diagonal else a != b
    return [np.minimum(a, b)[keep], np.maximum(a, b)[keep], *(x[keep] for x in more)]


def pairs(vectors: DataFrame, threshold: float, id_col: str = "vec_id", vector: str = "embedding", group: str | None = None) -> DataFrame:
    """(a, b, score) with a < b and cosine >= threshold; only survivors leave Python. Pairs of one group (a document's chunks) can be left out."""
    base, n, most = _vectors(vectors, id_col, vector, (F.col(group).cast("long") if group else F.lit(0).cast("long")).alias("g"))

    def join(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows, v = _whole(batches)
        left, right = _sides(key, rows)
        v = _unit(v)
        for i, j, score in _close(v[left], v[right], threshold):
            i, j = left[i], right[j]
            if group:
                apart = rows["g"][i] != rows["g"][j]
                i, j, score = i[apart], j[apart], score[apart]
            yield pa.record_batch(_once(rows["id"][i], rows["id"][j], key[0] == key[1], score), ["a", "b", "score"])

    return _tiled(base, _blocks(n, most)).groupBy("i", "j").applyInArrow(join, "a long, b long, score double")


def doc_pairs_from_chunks(chunk_pairs: DataFrame, chunks: DataFrame) -> DataFrame:
    """(doc_a, doc_b, score, hits): the best chunk pair of two texts decides; chunks: (vec_id, doc_id)."""
    left, right = chunks.select(F.col("vec_id").alias("a"), F.col("doc_id").alias("da")), chunks.select(F.col("vec_id").alias("b"), F.col("doc_id").alias("db"))
    both = chunk_pairs.join(left, "a").join(right, "b").filter("da <> db")
    return both.groupBy(F.least("da", "db").alias("doc_a"), F.greatest("da", "db").alias("doc_b")).agg(F.max("score").alias("score"), F.count("*").alias("hits"))


def spans(chunk_pairs: DataFrame, chunks: DataFrame) -> DataFrame:
    """Where two texts overlap: (doc_a, start_a, doc_b, start_b, score); chunks: (vec_id, doc_id, start)."""
    left = chunks.select(F.col("vec_id").alias("a"), F.col("doc_id").alias("doc_a"), F.col("start").alias("start_a"))
    right = chunks.select(F.col("vec_id").alias("b"), F.col("doc_id").alias("doc_b"), F.col("start").alias("start_b"))
    return chunk_pairs.join(left, "a").join(right, "b").filter("doc_a <> doc_b").select("doc_a", "start_a", "doc_b", "start_b", "score")


def top_by(results: DataFrame, query: str, target: str, score: str, low: bool = False, ties: str | None = None) -> DataFrame:
    """(query, target, score, ties): the best target of each query, ties to the smallest id and counted (a column may say how many a row stands for).

    Rows are counted by score before anything is shuffled, so neither ties nor the other results leave the task that found them."""
    value = -F.col(score) if low else F.col(score)
    some = F.sum(ties) if ties else F.count("*")
    by = results.groupBy(query, score).agg(F.min(target).alias(target), some.alias("ties"))
    best = by.groupBy(query).agg(F.max_by(F.struct(target, score, "ties"), value).alias("best"))
    return best.select(query, f"best.{target}", f"best.{score}", "best.ties")


def vector_classes(vectors: DataFrame, id_col: str = "vec_id", vector: str = "embedding") -> tuple[DataFrame, DataFrame]:
    """Equal vectors as one: (id, v) of the smallest id of each, and (id, rep) of every vector that is there. Two 64-bit hashes tell vectors apart."""
    marks = [F.xxhash64("v").alias("mark"), F.xxhash64(F.lit("check"), "v").alias("check")]
    rows = vectors.select(F.col(id_col).alias("id"), F.col(vector).cast("array<double>").alias("v")).filter("v is not null").select("id", "v", *marks)
    reps = cut(rows.groupBy("mark", "check").agg(F.min("id").alias("rep"), F.first("v").alias("v")))
    return reps.select(F.col("rep").alias("id"), "v"), rows.select("id", "mark", "check").join(reps.select("mark", "check", "rep"), ["mark", "check"]).select("id", "rep")


def plan_signs(threshold: float, n: int, recall: float = 0.95) -> tuple[int, int]:
    """Tables and bits for a threshold join of n vectors: codes long enough that unrelated vectors rarely share one, and as many tables as the recall at the threshold asks for.

    A random hyperplane parts two vectors with the probability angle / pi."""
    bits = min(30, max(8, math.ceil(math.log2(max(2, n))) - 2))
    same = (1 - math.acos(threshold) / math.pi) ** bits
    return max(1, math.ceil(math.log(1 - recall) / math.log(1 - same))), bits


def near_pairs(vectors: DataFrame, threshold: float, dim: int, recall: float = 0.95, id_col: str = "id", vector: str = "v", seed: int = 3) -> DataFrame:
    """(a, b, score): pairs with cosine >= threshold among those that share a sign code in some table; a pair right at the threshold is found with
    probability recall, a nearer one more often. Candidates are an equi-join of codes; what they cost follows from `plan_signs`, not from n squared."""
    rows = cut(vectors.select(F.col(id_col).alias("id"), F.col(vector).cast("array<double>").alias("v")).filter("v is not null"))
    tables, bits = plan_signs(threshold, rows.count(), recall)
    keys = sign_codes(rows, dim, tables, bits, seed, "id", "v").select("id", F.xxhash64("no", "code").alias("key"))
    met = cut(candidates(keys))
    one, two = rows.select(F.col("id").alias("a"), F.col("v").alias("va")), rows.select(F.col("id").alias("b"), F.col("v").alias("vb"))
    return met.join(one, "a").join(two, "b").mapInPandas(_cosines, "a long, b long, score double").filter(F.col("score") >= threshold - 1e-12)


def near_recall(vectors: DataFrame, thresholds: tuple[float, ...], dim: int, recall: float = 0.95, id_col: str = "id", vector: str = "v", seed: int = 3) -> DataFrame:
    """(threshold, exact, found, compared): how many pairs there are, how many of them `near_pairs` finds, and how many it compares.

    All pairs are compared by tiles. The pairs that share a code are found anew in each tile from the same hyperplanes, so neither they nor their vectors are written."""
    base, n, most = _vectors(vectors, id_col, vector)
    plans = [(t, _planes(dim, *plan_signs(t, n, recall), seed)) for t in thresholds]

    def count(key: tuple[pa.Scalar, ...], batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows, v = _whole(batches)
        left, right = _sides(key, rows)
        ids, diagonal, unit = rows["id"], key[0] == key[1], _unit(v)
        exact, out = np.zeros(len(plans), np.int64), []
        for i, j, score in _close(unit[left], unit[right], min(thresholds)):
            score = _once(ids[left[i]], ids[right[j]], diagonal, score)[2]
            exact += [(score >= t - 1e-12).sum() for t, _ in plans]
        for t, planes in plans:
            found = compared = 0
            for i, j in _shared(_keys(v[left], planes), _keys(v[right], planes)):
                i, j = left[i], right[j]
                a, _, i, j = _once(ids[i], ids[j], diagonal, i, j)
                compared += len(a)
                found += int((_scores(unit, unit, i, j) >= t - 1e-12).sum())
            out.append((found, compared))
        yield pa.record_batch([pa.array(list(thresholds)), pa.array(exact), *(pa.array(x, pa.int64()) for x in zip(*out, strict=True))], ["threshold", "exact", "found", "compared"])

    by = _tiled(base, _blocks(n, most)).groupBy("i", "j").applyInArrow(count, "threshold double, exact long, found long, compared long")
    return by.groupBy("threshold").agg(*(F.sum(c).alias(c) for c in ("exact", "found", "compared")))


def _cosines(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    for rows in batches:
        x, y = (_matrix(rows[c]) if len(rows) else np.zeros((0, 1)) for c in ("va", "vb"))
        yield pd.DataFrame({"a": rows["a"], "b": rows["b"], "score": np.einsum("ij,ij->i", x, y)})


def _planes(dim: int, tables: int, bits: int, seed: int) -> np.ndarray:
    return np.random.default_rng(seed).normal(size=(tables * bits, dim)).reshape(tables, bits, dim)


def _codes(x: np.ndarray, planes: np.ndarray) -> np.ndarray:
    """A column of codes for each table: bits of the sides of its hyperplanes."""
    weight = 1 << np.arange(planes.shape[1], dtype=np.int64)
    return np.stack([(x @ p.T > 0) @ weight for p in planes], axis=1)


def _keys(x: np.ndarray, planes: np.ndarray, _=None) -> np.ndarray:
    """Codes that differ between tables."""
    return _codes(x, planes) + (np.arange(len(planes), dtype=np.int64) << planes.shape[1])


def sign_codes(vectors: DataFrame, dim: int, tables: int, bits: int, seed: int = 3, id_col: str = "vec_id", vector: str = "embedding") -> DataFrame:
    """(id, no, code): bits of the sides of random hyperplanes, `tables` codes a vector."""
    planes = _planes(dim, tables, bits, seed)

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for rows in batches:
            code = _codes(np.array(rows["v"].tolist()).reshape(len(rows), dim), planes)
            yield pd.DataFrame({"id": np.repeat(rows["id"].to_numpy(), tables), "no": np.tile(np.arange(tables), len(rows)), "code": code.ravel()})

    return vectors.select(F.col(id_col).alias("id"), F.col(vector).cast("array<double>").alias("v")).filter("v is not null").mapInPandas(run, "id long, no long, code long")


def sign_search(queries: DataFrame, targets: DataFrame, dim: int, k: int = 1, tables: int = 24, bits: int = 6, skip_same: bool = True, seed: int = 3) -> tuple[DataFrame, DataFrame]:
    """Approximate: targets that share a code with the query are compared in full. (query_id, rank, target_id, score), and (compared): how many pairs were, in one row."""
    planes = _planes(dim, tables, bits, seed)
    return _counted(_search(queries, targets, k, ("vec_id", "embedding"), ("vec_id", "embedding"), skip_same, lambda x, _: _keys(x, planes)), k)


def _counted(found: DataFrame, k: int) -> tuple[DataFrame, DataFrame]:
    found = cut(found)
    return _ranked(found, k), found.agg(F.coalesce(F.sum("compared"), F.lit(0)).alias("compared"))


def _lloyd(x: np.ndarray, lists: int, seed: int, rounds: int = 8) -> np.ndarray:
    """Centres of k-means over the rows of x, begun at rows that differ; a centre without rows begins again at the row that is farthest from its own."""
    first = np.unique(x, axis=0)
    c = first[np.random.default_rng(seed).permutation(len(first))[:lists]].astype(np.float64)
    for _ in range(rounds):
        cell, far = np.empty(len(x), np.int64), np.empty(len(x))
        for k in range(0, len(x), 1024):
            part = x[k : k + 1024]
            d = (c**2).sum(1)[None] - 2 * part @ c.T
            cell[k : k + 1024] = d.argmin(1)
            far[k : k + 1024] = d.min(1) + (part**2).sum(1)
        order = np.argsort(cell, kind="stable")
        start = np.flatnonzero(np.diff(cell[order], prepend=-1))
        size = np.diff(np.append(start, len(x)))
        c[cell[order][start]] = np.add.reduceat(x[order], start) / size[:, None]
        lone = np.setdiff1d(np.arange(len(c)), cell)
        c[lone] = x[np.argsort(-far, kind="stable")[: len(lone)]]
    return c


def ivf_fit(some: DataFrame, lists: int, seed: int = 1) -> np.ndarray:
    """Centres of cells by k-means on a bounded sample of vectors, in one task of an executor; at most as many as the sample has rows."""

    def fit(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        batches = [b for b in batches if b.num_rows]
        if batches:
            flat, x = _whole(batches)
            c = _lloyd(x[np.argsort(flat["vec_id"], kind="stable")], lists, seed)
            yield pa.record_batch({"cell": np.arange(len(c)), "v": pa.array(list(c))})

    rows = some.select(F.col("vec_id").cast("long").alias("vec_id"), F.col("embedding").cast("array<double>").alias("v")).filter("v is not null")
    told = rows.repartition(1).mapInArrow(fit, "cell long, v array<double>").toArrow().sort_by("cell")
    return np.array(told["v"].to_pylist(), np.float64) if len(told) else np.zeros((1, 1))


def sampled(vec_id: Column, n: int, sample: int = 20_000, seed: int = 1) -> Column:
    """Whether a vector is one of those that cells are learned from: about `sample` of n."""
    return F.pmod(F.xxhash64(vec_id, F.lit(seed)), F.lit(1 << 30)) < min(1.0, sample / max(1, n)) * (1 << 30)


def ivf_build(vectors: DataFrame, lists: int, sample: int = 20_000, seed: int = 1) -> tuple[DataFrame, np.ndarray]:
    """(vec_id, cell) of every vector, and the cells' centres."""
    n = vectors.filter("embedding is not null").count()
    centres = ivf_fit(vectors.filter(sampled(F.col("vec_id"), n, sample, seed)), lists, seed)
    return assign_cells(vectors, centres, 1).select("vec_id", "cell"), centres


def _nearest(x: np.ndarray, across: np.ndarray, square: np.ndarray, probes: int = 1) -> np.ndarray:
    far = square - 2 * x @ across
    return far.argmin(1)[:, None] if probes == 1 else np.argsort(far, axis=1, kind="stable")[:, :probes]


def assign_cells(vectors: DataFrame, centres: np.ndarray, probes: int) -> DataFrame:
    """(vec_id, cell) with the nearest `probes` centres of each vector."""
    sent = vectors.sparkSession.sparkContext.broadcast((np.ascontiguousarray(centres.T), (centres**2).sum(1)[None]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in (b.slice(k, 256) for b in batches for k in range(0, b.num_rows, 256)):  # distances of a few vectors to all centres at a time
            rows, x = _whole([batch])
            near = _nearest(x, *sent.value, probes)
            yield pa.record_batch({"vec_id": np.repeat(rows["vec_id"], near.shape[1]), "cell": near.ravel()})

    return vectors.select(F.col("vec_id").cast("long").alias("vec_id"), F.col("embedding").cast("array<double>").alias("v")).filter("v is not null").mapInArrow(run, "vec_id long, cell long")


def cells_of_parts(done: DataFrame, centres: np.ndarray) -> DataFrame:
    """(id, doc_vector, cells, seconds): the cell of each chunk vector instead of the vector, and how long a task took to find them."""
    sent = done.sparkSession.sparkContext.broadcast((np.ascontiguousarray(centres.T), (centres**2).sum(1)[None]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in (b.slice(k, 64) for b in batches for k in range(0, b.num_rows, 64)):
            began = time.perf_counter()
            lists = batch.column(2)
            vectors = lists.flatten()
            x = vectors.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(len(vectors), len(sent.value[0]))
            near = np.concatenate([np.zeros(0, np.int64), *(_nearest(x[k : k + 256], *sent.value)[:, 0] for k in range(0, len(x), 256))])
            ends = np.concatenate([[0], np.cumsum(pa.compute.fill_null(pa.compute.list_value_length(lists), 0).to_numpy(zero_copy_only=False))])
            cells = pa.ListArray.from_arrays(pa.array(ends.astype(np.int32)), pa.array(near, pa.int64()))
            seconds = np.zeros(batch.num_rows)
            seconds[0] = time.perf_counter() - began
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), cells, pa.array(seconds)], names=["id", "doc_vector", "cells", "seconds"])

    return done.select("id", "doc_vector", "chunk_vectors").mapInArrow(run, "id long, doc_vector array<float>, cells array<long>, seconds double")


#: Ids that are sent to all tasks; more of them are joined.
SENT = 1_000_000


def ivf_search(queries: DataFrame, vectors: DataFrame, cells: DataFrame, centres: np.ndarray, k: int = 1, probes: int = 4, skip_same: bool = True) -> tuple[DataFrame, DataFrame]:
    """Approximate: only vectors of the probed cells are compared. (query_id, rank, target_id, score), and (compared): how many pairs were, in one row.

    Vectors of cells that no query probes stay where they are."""
    near = cut(assign_cells(queries, centres, probes))
    asked = near.select("cell").distinct()  # no more than there are centres, which all tasks have
    held = cut(cells.join(F.broadcast(asked), "cell", "left_semi").select("vec_id", F.array("cell").alias("cells")))
    q = queries.select("vec_id", "embedding").join(near.groupBy("vec_id").agg(F.collect_list("cell").alias("cells")), "vec_id")
    t = vectors.select("vec_id", "embedding").join(F.broadcast(held) if held.count() <= SENT else held, "vec_id")
    keys = lambda _, column: np.array(column.to_pylist(), np.int64)
    return _counted(_search(q, t, k, ("vec_id", "embedding"), ("vec_id", "embedding"), skip_same, keys, (F.col("cells"), F.col("cells"))), k)


#: Bytes of vectors of a packed block, which pairs of blocks are read from without a shuffle.
PACKED = 1 << 24


def _ladder(top: np.ndarray, same: np.ndarray, grid: np.ndarray) -> np.ndarray:
    """How many scores are at each step of the grid or above it and below the next, true pairs apart."""
    step = np.searchsorted(grid, top, "right")
    return np.bincount(2 * step + same, minlength=2 * len(grid) + 2)


def swept_counts(vectors: DataFrame, grid: list[float]) -> DataFrame:
    """(score, truth, n): pairs of texts by the grid step of their nearest two vectors, pairs below the grid left out; vectors: (vec_id, doc_id, cluster, v).

    Vectors are packed in blocks of whole texts and written once. Each pair of blocks is a task that reads both; a text's pairs are compared in it and only counted,
    in single precision first and in double where that could change a count."""
    base = vectors.select(*(F.col(c).cast("long").alias(c) for c in ("vec_id", "doc_id", "cluster")), F.col("v").cast("array<double>").alias("v")).filter("v is not null")
    n, dim = base.agg(F.count("*"), F.max(F.size("v"))).first()
    blocks = max(1, -(-n * 4 * (dim or 1) // PACKED), min(-(-n // BLOCK), math.isqrt(2 * TILES)))
    steps = np.array(sorted(grid))

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rows, v = _whole(batches)
        order = np.lexsort((rows["vec_id"], rows["doc_id"]))
        v = v[order]
        single = v.astype(np.float32)
        blob = single if (single == v).all() else v
        docs, cluster = (np.ascontiguousarray(rows[c][order], np.int64).tobytes() for c in ("doc_id", "cluster"))
        yield pa.record_batch({"i": pa.array([int(rows["i"][0])], pa.int32()), "docs": [docs], "clusters": [cluster], "v": pa.array([blob.tobytes()], pa.binary())})

    held = cut(base.withColumn("i", F.pmod(F.xxhash64("doc_id"), F.lit(blocks)).cast("int")).repartition(blocks, "i").groupBy("i").applyInArrow(pack, "i int, docs binary, clusters binary, v binary"))
    left, right = held.select(*(F.col(c).alias(f"{c}1") for c in held.columns)), held.select(*(F.col(c).alias(f"{c}2") for c in held.columns))

    def side(batch: pa.RecordBatch, no: int, k: int) -> tuple:
        docs, cluster = (np.frombuffer(batch.column(f"{c}{no}")[k].as_py(), np.int64) for c in ("docs", "clusters"))
        raw = batch.column(f"v{no}")[k].as_py()
        x = np.frombuffer(raw, np.float32 if len(raw) == 4 * dim * len(docs) else np.float64).reshape(len(docs), dim)
        start = np.flatnonzero(np.diff(docs, prepend=docs[0] - 1))
        return docs[start], cluster[start], np.append(start, len(docs)), _unit(x.astype(np.float64))

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(2 * len(steps) + 2, np.int64)
        for batch in batches:
            for k in range(batch.num_rows):
                total += _compared(side(batch, 1, k), side(batch, 2, k), steps, batch.column("i1")[k].as_py() == batch.column("i2")[k].as_py())
        at = np.flatnonzero(total[2:]) + 2
        yield pa.record_batch({"score": steps[at // 2 - 1], "truth": at % 2, "n": total[at]})

    return left.join(right, F.col("i1") <= F.col("i2")).mapInArrow(count, "score double, truth long, n long").groupBy("score", "truth").agg(F.sum("n").alias("n"))


def _compared(one: tuple, two: tuple, steps: np.ndarray, diagonal: bool) -> np.ndarray:
    """The ladder of all pairs of texts of two blocks; a block: texts, their clusters, where their vectors begin, and the vectors."""
    (a, ca, sa, x), (b, cb, sb, y) = one, two
    x32, y32 = x.astype(np.float32), np.ascontiguousarray(y.astype(np.float32).T)
    off = 2e-7 + x.shape[1] * 6e-8  # of a cosine in single precision
    total, p = np.zeros(2 * len(steps) + 2, np.int64), 0
    while p < len(a):
        q = max(p + 1, int(np.searchsorted(sa, sa[p] + max(1, AT_ONCE // y32.shape[1]), "right")) - 1)
        score = x32[sa[p] : sa[q]] @ y32
        top = np.maximum.reduceat(np.maximum.reduceat(score, sa[p:q] - sa[p], axis=0), sb[:-1], axis=1).astype(np.float64)
        met = a[p:q, None] < b[None] if diagonal else np.ones(top.shape, bool)
        met &= top >= steps[0] - off
        i, j = np.nonzero(met)
        top = top[i, j]
        near = np.minimum(np.searchsorted(steps, top), len(steps) - 1)
        for k in np.flatnonzero((np.abs(top - steps[near]) <= off) | (np.abs(top - steps[np.maximum(near - 1, 0)]) <= off)).tolist():
            u, v = p + i[k], j[k]
            r, c = np.nonzero(score[sa[u] - sa[p] : sa[u + 1] - sa[p], sb[v] : sb[v + 1]] >= top[k] - 2 * off)
            top[k] = _scores(x, y, sa[u] + r, sb[v] + c).max()
        total += _ladder(top, (ca[p:q][i] == cb[j]).astype(np.int64), steps)
        p = q
    return total


def sweep(scored: DataFrame, grid: list[float], positives: int | None = None, weight: str | None = None) -> DataFrame:
    """(threshold, tp, fp, fn, precision, recall, f1) of scored pairs (score, truth 0/1), in one pass; weight: a column that says how many pairs a row stands for.

    Pairs are counted by grid step and summed from the top; positives counts true pairs that were never scored too."""
    steps = sorted(grid)
    at = F.lit(-1)
    for i, t in enumerate(steps):
        at = F.when(F.col("score") >= t, i).otherwise(at) if i == 0 else F.when(F.col("score") >= t, F.lit(i)).otherwise(at)
    many = F.col(weight) if weight else F.lit(1)
    counts = scored.withColumn("step", at).groupBy("step").agg(F.sum(F.col("truth") * many).alias("p"), F.sum((1 - F.col("truth")) * many).alias("n"))
    spark = scored.sparkSession
    ladder = spark.createDataFrame([(i, float(t)) for i, t in enumerate(steps)], "step int, threshold double")
    total = counts.agg(F.coalesce(F.sum("p"), F.lit(0)).alias("all_p"))
    up = Window.orderBy(F.desc("step")).rowsBetween(Window.unboundedPreceding, Window.currentRow)  # one row a grid step
    rows = ladder.join(counts, "step", "left").fillna(0, ["p", "n"]).withColumn("tp", F.sum("p").over(up)).withColumn("fp", F.sum("n").over(up))
    rows = rows.crossJoin(F.broadcast(total)) if positives is None else rows.withColumn("all_p", F.lit(positives))
    rows = rows.withColumn("fn", F.col("all_p") - F.col("tp"))
    p, r = F.try_divide("tp", F.col("tp") + F.col("fp")), F.try_divide("tp", F.col("tp") + F.col("fn"))
    rows = rows.withColumn("precision", F.coalesce(p, F.lit(1.0))).withColumn("recall", F.coalesce(r, F.lit(1.0)))
    f1 = F.coalesce(F.try_divide(2 * F.col("precision") * F.col("recall"), F.col("precision") + F.col("recall")), F.lit(0.0))
    return rows.withColumn("f1", f1).select("threshold", "tp", "fp", "fn", "precision", "recall", "f1")
