"""All pairs of 64-bit fingerprints within a Hamming distance: blocks are written once, each pair of blocks is a task that reads both, and only what is asked for leaves it."""

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from twinsift.functions.shipping import by_value
from twinsift.operators.clustering import _linked
from twinsift.plans.checkpoints import cut

by_value(__name__)

#: Fingerprints of a block at most, tiles wanted at least, distances looked at at a time, and pairs that a task holds before it links them.
WIDE, TILES, AT_ONCE, HELD = 1 << 15, 21, 1 << 18, 1 << 20


def _pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    rows = pa.Table.from_batches(list(batches))
    order = np.argsort(rows["id"].to_numpy(), kind="stable")
    blobs = {c: [np.ascontiguousarray(rows[c].to_numpy()[order], np.int64).tobytes()] for c in ("id", "fingerprint", "tag")}
    yield pa.record_batch({"i": pa.array([int(rows["i"][0].as_py())], pa.int32())} | {c: pa.array(b, pa.binary()) for c, b in blobs.items()})


def _hits(x: np.ndarray, y: np.ndarray, limit: int, diagonal: bool) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(i, j, distance) of rows of x and y within the limit, some at a time; of a block with itself i < j."""
    step = max(1, AT_ONCE // max(1, len(y)))
    for p in range(0, len(x), step):
        far = np.bitwise_count(x[p : p + step, None] ^ y[None]).ravel()
        at = np.flatnonzero(far <= limit)
        i, j = np.divmod(at, len(y))
        i += p
        if diagonal:
            once = i < j
            i, j, at = i[once], j[once], at[once]
        yield i, j, far[at].astype(np.int64)


def _tiles(signed: DataFrame, visit, schema: str, tag: str | None) -> DataFrame:
    """What visit(one, two, diagonal) gives for each pair of blocks (id, fingerprint, tag)."""
    rows = cut(signed.filter("fingerprint is not null").select(F.col("id").cast("long").alias("id"), F.col("fingerprint").cast("long").alias("fingerprint"), (F.col(tag) if tag else F.lit(0)).cast("long").alias("tag")))
    n = rows.count()
    blocks = max(1, -(-n // WIDE), min(-(-n // 2000), math.isqrt(2 * TILES)))
    held = cut(rows.withColumn("i", F.pmod(F.xxhash64("id"), F.lit(blocks)).cast("int")).repartition(blocks, "i").groupBy("i").applyInArrow(_pack, "i int, id binary, fingerprint binary, tag binary"))
    left, right = (held.select(*(F.col(c).alias(f"{c}{no}") for c in held.columns)) for no in (1, 2))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            side = lambda no, k: tuple(np.frombuffer(batch.column(f"{c}{no}")[k].as_py(), t) for c, t in (("id", np.int64), ("fingerprint", np.uint64), ("tag", np.int64)))  # noqa: B023, E731
            for k in range(batch.num_rows):
                yield from visit(side(1, k), side(2, k), batch.column("i1")[k].as_py() == batch.column("i2")[k].as_py())

    return left.join(right, F.col("i1") <= F.col("i2")).mapInArrow(run, schema)


def counts(signed: DataFrame, limit: int, tag: str) -> DataFrame:
    """(distance, truth, n): how many pairs within the limit there are, those of one tag apart. No pair leaves a task."""

    def visit(one, two, diagonal):
        total = np.zeros(2 * limit + 2, np.int64)
        for i, j, far in _hits(one[1], two[1], limit, diagonal):
            total += np.bincount(2 * far + (one[2][i] == two[2][j]), minlength=len(total))
        at = np.flatnonzero(total)
        yield pa.record_batch([pa.array(at // 2), pa.array(at % 2), pa.array(total[at])], ["distance", "truth", "n"])

    return _tiles(signed, visit, "distance long, truth long, n long", tag).groupBy("distance", "truth").agg(F.sum("n").alias("n"))


def pairs(signed: DataFrame, limit: int, tag: str | None = None) -> DataFrame:
    """(a, b, distance): all pairs a < b within the limit; tag: a column that only pairs of which are wanted have in common."""

    def visit(one, two, diagonal):
        for i, j, far in _hits(one[1], two[1], limit, diagonal):
            if tag:
                same = one[2][i] == two[2][j]
                i, j, far = i[same], j[same], far[same]
            if len(i):
                a, b = one[0][i], two[0][j]
                yield pa.record_batch([pa.array(np.minimum(a, b)), pa.array(np.maximum(a, b)), pa.array(far)], ["a", "b", "distance"])

    return _tiles(signed, visit, "a long, b long, distance long", tag)


def links(signed: DataFrame, limit: int) -> DataFrame:
    """(a, b): as few of the pairs within the limit, or pairs that such pairs connect, as connect all that they connect in each pair of blocks. Enough for components."""

    def visit(one, two, diagonal):
        own = one[0] if diagonal else np.concatenate([one[0], two[0]])
        shift, i, j, held = 0 if diagonal else len(one[0]), [], [], 0
        for p, q, _ in _hits(one[1], two[1], limit, diagonal):
            i.append(p)
            j.append(q + shift)
            held += len(p)
            if held > HELD:
                least = _linked(np.concatenate(i), np.concatenate(j), len(own))
                at = np.flatnonzero(least != np.arange(len(own)))
                i, j, held = [at], [least[at]], 0
        least = _linked(np.concatenate(i), np.concatenate(j), len(own)) if i else np.arange(len(own))
        at = np.flatnonzero(least != np.arange(len(own)))
        yield pa.record_batch([pa.array(own[least[at]]), pa.array(own[at])], ["a", "b"])

    return _tiles(signed, visit, "a long, b long", None)
