"""Exact joins of sets of 64-bit numbers that keep few bytes on disk: keys travel packed, pairs are counted where they meet, and a set is sent once to each task that verifies it."""

from collections.abc import Callable

import numpy as np
import pyarrow as pa
import pyarrow.compute
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from twinsift.functions.shipping import by_value
from twinsift.plans.checkpoints import cut

by_value(__name__)

COMMON = 200_000  # frequent elements whose rank all tasks know: 3 MB
SAMPLE, SAMPLE_TASK = 6000, 200  # sets in all, and at most of one task, that tell which elements are frequent; their choice changes no result
SHARED = 8  # elements of the prefixes that a pair must share
MANY = 1_000_000  # keys a bucket, and pairs that a task holds before it sums them
HELD = 500_000  # keys that a task holds before it packs them
ROWS = 1000  # sets a batch
HOT = 2000  # sets of one key that one task pairs with one another
SENT_IDS = 2_000_000  # ids that are sent to all tasks: 32 MB; beyond it the sets go through a join
VERIFIED = 8 << 20  # bytes of sets a group that verifies pairs
PLACE = 40  # bits of a key that travel; equal ones only make a candidate
ODD = (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9)
WIDEST = (1 << 16) - 1  # sizes beyond it travel as it


def mixed(x: np.ndarray, k: int = 0) -> np.ndarray:
    """Spread 64-bit numbers, one to one."""
    u = x.astype(np.int64, copy=False).view(np.uint64) * np.uint64(ODD[k])
    u = (u ^ (u >> np.uint64(32))) * np.uint64(ODD[(k + 1) % 3])
    return u ^ (u >> np.uint64(29))


def pack(*columns: np.ndarray) -> bytes:
    """Columns of whole numbers by bytes of equal weight, as many as the largest number has."""
    n = len(columns[0])
    out = [n.to_bytes(8, "little")]
    for c in columns:
        u = np.ascontiguousarray(c, np.int64).view(np.uint64)
        width = (int(u.max(initial=0)).bit_length() + 7) // 8
        out += [bytes([width]), np.ascontiguousarray(u.view(np.uint8).reshape(n, 8)[:, :width].T).tobytes()]
    return b"".join(out)


def unpack(blob: bytes) -> list[np.ndarray]:
    n, at, out = int.from_bytes(blob[:8], "little"), 8, []
    while at < len(blob):
        width, at = blob[at], at + 1
        wide = np.zeros((n, 8), np.uint8)
        wide[:, :width] = np.frombuffer(blob, np.uint8, n * width, at).reshape(width, n).T
        out.append(wide.view(np.int64)[:, 0])
        at += n * width
    return out


def lists_of(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Values of a list column end to end, and where each row begins and the last ends."""
    offsets = column.offsets.to_numpy()
    return column.flatten().to_numpy(zero_copy_only=False), offsets - offsets[0]


class Sets:
    """(id, hashes) by a function of Arrow batches over the rows of a table: made again whenever they are asked for, in the task that needs them, and never written."""

    def __init__(self, rows: DataFrame, stage: Callable | None = None):
        self.rows, self.stage = rows, stage or (lambda batches: batches)

    def then(self, step: Callable) -> "Sets":
        before = self.stage
        return Sets(self.rows, lambda batches: step(before(batches)))

    def run(self, step: Callable, schema: str) -> DataFrame:
        return self.rows.mapInArrow(self.then(step).stage, schema)

    def frame(self, id_type: str = "long") -> DataFrame:
        return self.rows.mapInArrow(self.stage, f"id {id_type}, hashes array<long>")


def sets_of(hashed: "DataFrame | Sets") -> Sets:
    """Sets with an id and an element at least."""
    if not isinstance(hashed, Sets):
        hashed = Sets(hashed.select("id", "hashes"))
    rows = hashed.rows.filter("id is not null").withColumn("id", F.col("id").cast("long"))
    return Sets(rows, hashed.stage).then(_full)


def _full(batches):
    for batch in batches:
        yield batch.filter(pa.compute.greater(pa.compute.list_value_length(batch.column(1)), 0))


def steps(sorted_: np.ndarray) -> np.ndarray:
    return np.diff(sorted_, prepend=sorted_[:1])


def _marks(batches):
    """(id, n, mark, check, some): 128 bits of each set, and the sets of the ids whose spread numbers are lowest in the task."""
    import hashlib

    rows, some = [], []
    for batch in batches:
        flat, at = lists_of(batch.column(1))
        ids = batch.column(0).to_numpy()
        if not len(ids):
            continue
        flat = np.ascontiguousarray(flat[np.lexsort((flat, np.repeat(np.arange(len(ids)), np.diff(at))))])
        digests = b"".join(hashlib.md5(flat[at[i] : at[i + 1]]).digest() for i in range(len(ids)))
        two = np.frombuffer(digests, np.int64).reshape(-1, 2)
        rows.append((ids, np.diff(at).astype(np.int64), two[:, 0], two[:, 1]))
        lot = mixed(ids)
        some += [(int(lot[k]), int(ids[k]), flat[at[k] : at[k + 1]].copy()) for k in np.argsort(lot)[:SAMPLE_TASK].tolist()]
        some = sorted(some, key=lambda s: s[:2])[:SAMPLE_TASK]
    if rows:
        ids, n, mark, check = (np.concatenate(x) for x in zip(*rows, strict=True))
        named = {i: s for _, i, s in some}
        yield pa.RecordBatch.from_arrays([pa.array(ids), pa.array(n), pa.array(mark), pa.array(check), pa.array([named.pop(i, None) for i in ids.tolist()], pa.list_(pa.int64()))], names=["id", "n", "mark", "check", "some"])


def _frequent(batches):
    """The elements that several of the sets have, most frequent first."""
    seen = [lists_of(b.column(0))[0] for b in batches]
    values, often = np.unique(np.concatenate(seen) if seen else np.zeros(0, np.int64), return_counts=True)
    order = np.lexsort((values, -often))[: min(COMMON, int((often > 1).sum()))]
    yield pa.RecordBatch.from_arrays([pa.array(values[order])], names=["h"])


def keyed(sets: Sets, keys_of: Callable, buckets: int) -> DataFrame:
    """(bucket, first, keys): what keys_of says of each Arrow batch of (id, hashes) - key, id, size - sorted by the key and packed."""

    def flush(held):
        key, ids, n = (np.concatenate(x) for x in zip(*held, strict=True))
        place = (mixed(key) >> np.uint64(64 - PLACE)).astype(np.int64)
        order = np.argsort(place, kind="stable")
        place, ids, n = place[order], ids[order], np.minimum(n[order], WIDEST)
        edges = np.searchsorted((place * buckets) >> PLACE, np.arange(buckets + 1))
        full = [b for b in range(buckets) if edges[b] < edges[b + 1]]
        parts = [slice(edges[b], edges[b + 1]) for b in full]
        return pa.RecordBatch.from_arrays([pa.array(full, pa.int32()), pa.array([int(place[p.start]) for p in parts], pa.int64()), pa.array([pack(steps(place[p]), ids[p], n[p]) for p in parts], pa.binary())], names=["bucket", "first", "keys"])

    def run(batches):
        held, size = [], 0
        for batch in batches:
            held.append(keys_of(batch))
            size += len(held[-1][0])
            if size >= HELD:
                yield flush(held)
                held, size = [], 0
        if size:
            yield flush(held)

    return sets.run(run, "bucket int, first long, keys binary")


def _summed(a, b, w, need):
    """Equal pairs as one with the sum of their weights."""
    order = np.lexsort((b, a))
    a, b, w, need = a[order], b[order], w[order], need[order]
    first = np.flatnonzero(np.concatenate([np.ones(min(1, len(a)), bool), (a[1:] != a[:-1]) | (b[1:] != b[:-1])]))
    return a[first], b[first], np.minimum(np.add.reduceat(w, first) if len(first) else w, 255), need[first]


PAIRS = pa.schema([("kind", pa.int32()), ("q", pa.int32()), ("first", pa.int64()), ("one", pa.binary()), ("two", pa.binary())])
PAIRS_SQL = "kind int, q int, first long, one binary, two binary"


def _dealt(found, buckets: int) -> list[tuple]:
    """Rows of PAIRS for pairs (a, b, w, need), by a."""
    a, b, w, need = _summed(*(np.concatenate(x) for x in zip(*found, strict=True)))
    q = (mixed(a, 1) % np.uint64(buckets)).astype(np.int64)
    rows = []
    for k in np.unique(q).tolist():
        x, y = a[q == k], b[q == k]
        rows.append((0, k, int(x[0]), pack(steps(x), y - x, w[q == k], need[q == k]), None))
    return rows


def _as_batch(rows: list[tuple]) -> pa.Table:
    return pa.Table.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows, strict=True) if rows else [[]] * 5, PAIRS, strict=True)], schema=PAIRS)


def _met(a, b, na, nb, w, threshold: float, shared: int):
    """Pairs of different ids whose sizes may reach the threshold; w: how many keys stand behind each."""
    ok = (a != b) & (np.minimum(na, nb) >= np.maximum(na, nb) * threshold - 1e-9)
    a, b, least, w = a[ok], b[ok], np.minimum(na, nb)[ok], w[ok]
    need = np.maximum(1, np.minimum(shared, np.ceil(least * threshold - 1e-9))).astype(np.int64)
    return np.minimum(a, b), np.maximum(a, b), w, need


def pairs_of_keys(packed: DataFrame, buckets: int, threshold: float = 0.0, shared: int = 1) -> DataFrame:
    """(a, b) with a < b that share as many keys as they must: `shared`, or what their smaller size allows; sizes within the threshold of each other.

    A list of ids that several keys have is paired once and weighs as many. A list longer than HOT is dealt over pairs of blocks, which other tasks take."""
    wide = 4 * buckets

    def meet(table: pa.Table) -> pa.Table:
        cols = [(np.cumsum(d) + f, i, n) for f, (d, i, n) in zip(table["first"].to_pylist(), map(unpack, table["keys"].to_pylist()), strict=True)]
        place, ids, n = (np.concatenate(x) for x in zip(*cols, strict=True))
        del cols
        order = np.argsort(place, kind="stable")
        place = place[order]
        twice = np.zeros(len(place) + 1, bool)
        twice[1:-1] = place[1:] == place[:-1]
        kept = twice[1:] | twice[:-1]
        place, order = place[kept], order[kept]
        ids, n = ids[order], n[order]
        if not len(ids):
            return _as_batch([])
        order = np.lexsort((ids, place))
        place, ids, n = place[order], ids[order], n[order]
        starts = np.flatnonzero(np.concatenate([[True], place[1:] != place[:-1]]))
        size = np.diff(np.append(starts, len(place)))
        one, two = np.add.reduceat(mixed(ids), starts), np.add.reduceat(mixed(ids, 1), starts)
        by = np.lexsort((two, one, size))
        fresh = np.concatenate([[True], (one[by][1:] != one[by][:-1]) | (two[by][1:] != two[by][:-1]) | (size[by][1:] != size[by][:-1])])
        pick = by[fresh]
        weight = np.diff(np.append(np.flatnonzero(fresh), len(by)))
        rows, found, many = [], [], 0
        for s, m, w in zip(starts[pick].tolist(), size[pick].tolist(), weight.tolist(), strict=True):
            if m > HOT:
                cuts = [slice(k, min(k + HOT, s + m)) for k in range(s, s + m, HOT)]
                rows += [(1, (i * len(cuts) + j) % wide, w, pack(ids[x], n[x]), pack(ids[y], n[y]) if i != j else None) for i, x in enumerate(cuts) for j, y in enumerate(cuts) if i <= j]
        cool = size[pick] <= HOT
        begin, end, w = starts[pick][cool], (starts + size)[pick][cool], weight[cool]
        at = np.concatenate([np.zeros(0, np.int64), *(np.arange(b, e) for b, e in zip(begin, end, strict=True))])
        last, w = np.repeat(end, end - begin), np.repeat(w, end - begin)
        for d in range(1, int((end - begin).max(initial=1))):
            more = at + d < last
            at, last, w = at[more], last[more], w[more]
            found.append(_met(ids[at], ids[at + d], n[at], n[at + d], w, threshold, shared))
            many += len(found[-1][0])
            if many > MANY // 2:
                found = [_summed(*(np.concatenate(x) for x in zip(*found, strict=True)))]
                many = 0
        return _as_batch(rows + (_dealt(found, wide) if sum(len(f[0]) for f in found) else []))

    def tiles(batches):
        for batch in batches:
            for w, one, two in zip(batch["first"].to_pylist(), batch["one"].to_pylist(), batch["two"].to_pylist(), strict=True):
                ids, n = unpack(one)
                if two is None:
                    x, y = np.triu_indices(len(ids), 1)
                    found = _met(ids[x], ids[y], n[x], n[y], np.full(len(x), w), threshold, shared)
                else:
                    far, m = unpack(two)
                    x, y = np.repeat(np.arange(len(ids)), len(far)), np.tile(np.arange(len(far)), len(ids))
                    found = _met(ids[x], far[y], n[x], m[y], np.full(len(x), w), threshold, shared)
                if len(found[0]):
                    yield from _as_batch(_dealt([found], wide)).to_batches()

    def settle(table: pa.Table) -> pa.Table:
        cols = []
        for first, blob in zip(table["first"].to_pylist(), table["one"].to_pylist(), strict=True):
            d, y, w, need = unpack(blob)
            x = np.cumsum(d) + first
            cols.append((x, x + y, w, need))
        a, b, w, need = _summed(*(np.concatenate(x) for x in zip(*cols, strict=True)))
        return pa.table({"a": a[w >= need], "b": b[w >= need]})

    met = cut(packed.groupBy("bucket").applyInArrow(meet, PAIRS_SQL))
    hot = met.filter("kind = 1").repartition("q").mapInArrow(tiles, PAIRS_SQL)
    return met.filter("kind = 0").unionByName(hot).groupBy("q").applyInArrow(settle, "a long, b long")


def without(sets: Sets, ids: DataFrame) -> Sets:
    """The sets of all other ids."""
    n = ids.count()
    if not n:
        return sets
    if n > SENT_IDS:
        return Sets(sets.frame().join(ids.select("id"), "id", "left_anti"))
    gone = ids.sparkSession.sparkContext.broadcast(np.sort(ids.select("id").toArrow()["id"].to_numpy()))

    def run(batches):
        for batch in batches:
            mine = batch.column(0).to_numpy()
            at = np.minimum(np.searchsorted(gone.value, mine), len(gone.value) - 1)
            yield batch.filter(pa.array(gone.value[at] != mine))

    return sets.then(run)


class Classes:
    """Equal sets as one. reps: the sets of the smallest id of each; members: (id, rep) of every row with a set; 128 bits tell sets apart."""

    def __init__(self, hashed: "DataFrame | Sets"):
        sets = sets_of(hashed)
        marked = cut(sets.run(_marks, "id long, n long, mark long, check long, some array<long>"))
        rep = marked.groupBy("mark", "check").agg(F.min("id").alias("rep"))
        self.members = cut(marked.select("id", "n", "mark", "check").join(rep, ["mark", "check"]).select("id", "rep", "n"))
        self.reps = without(sets, self.members.filter("id <> rep"))
        self.n, self.total = self.members.filter("id = rep").agg(F.count("*"), F.coalesce(F.sum("n"), F.lit(0))).first()
        self._some = marked.filter("some is not null").select("id", "some")
        self.members = self.members.select("id", "rep")

    def frequent(self) -> np.ndarray:
        """Frequent elements by a sample of the sets, most frequent first."""
        share = min(1.0, SAMPLE / max(1, self._some.count()))
        some = self._some.filter(F.pmod(F.xxhash64("id", F.lit("some")), F.lit(1 << 30)) < share * (1 << 30)).select("some")
        return some.repartition(1).mapInArrow(_frequent, "h long").toArrow()["h"].to_numpy()


def rare_first(known: np.ndarray, threshold: float, shared: int, sent) -> Callable:
    """keys_of for `keyed`: of each set of n the n - ceil(t n) + shared elements that come first, rare ones before common ones.

    Two sets that reach t share that many of these in any common order; the order only decides how many others do."""

    def keys_of(batch):
        common, rank = sent.value
        flat, at = lists_of(batch.column(1))
        n = np.diff(at).astype(np.int64)
        owner = np.repeat(np.arange(len(n)), n)
        near = np.minimum(np.searchsorted(common, flat), max(0, len(common) - 1))
        place = np.where(common[near] == flat, rank[near], 0) if len(common) else np.zeros(len(flat), np.int64)
        order = np.lexsort((mixed(flat, 2), place, owner))
        least = np.ceil(n * threshold - 1e-9).astype(np.int64)
        keep = n - least + np.maximum(1, np.minimum(shared, least))
        first = (np.arange(len(flat)) - np.repeat(at[:-1], n)) < np.repeat(keep, n)
        who = owner[first]
        return flat[order][first], batch.column(0).to_numpy()[who], n[who]

    return keys_of


def buckets_of(keys: float) -> int:
    return max(8, min(1 << 16, -(-int(keys) // MANY)))


def near_sets(classes: Classes, threshold: float, shared: int = SHARED) -> DataFrame:
    """(a, b): all pairs of classes that may reach the threshold, and few others."""
    known = classes.frequent()
    order = np.argsort(known)
    sent = classes.members.sparkSession.sparkContext.broadcast((known[order], len(known) - order))
    buckets = buckets_of(classes.total * (1 - threshold) + classes.n * shared)
    return pairs_of_keys(keyed(classes.reps, rare_first(known, threshold, shared, sent), buckets), buckets, threshold, shared)


def verified(sets: Sets, pairs: DataFrame, threshold: float, average: float = 500.0) -> DataFrame:
    """(a, b, score): the pairs whose sets reach the threshold, from the sets themselves.

    Pairs are grouped by the smallest partners of both ends, so that a set goes once to each group that needs it and not once for each pair;
    ends with a large number of partners are spread over blocks."""
    pairs = cut(pairs)
    ends = pairs.select(F.col("b").alias("id"), F.col("a").alias("m")).unionByName(pairs.select(F.col("a").alias("id"), F.col("a").alias("m"))).groupBy("id").agg(F.min("m").alias("m"))
    ends = cut(ends)
    many = ends.count()
    parts = ends.groupBy("m").agg(F.ceil(F.count("*") / F.lit(256)).alias("parts"))
    block = cut(ends.join(parts, "m").select("id", F.xxhash64("m", F.pmod(F.xxhash64("id"), "parts")).alias("block")))
    groups = max(8, int(many * average * 8 // VERIFIED) + 1)
    side = lambda i: block.select(F.col("id").alias(i), F.col("block").alias(f"block_{i}"))
    tiled = cut(pairs.join(side("a"), "a").join(side("b"), "b").select("a", "b", F.pmod(F.xxhash64(F.least("block_a", "block_b"), F.greatest("block_a", "block_b")), F.lit(groups)).cast("int").alias("g")))
    wanted = cut(tiled.select(F.col("a").alias("id"), "g").union(tiled.select(F.col("b").alias("id"), "g")).distinct())
    if wanted.count() <= SENT_IDS:
        table = wanted.toArrow()
        ids, g = table["id"].to_numpy(), table["g"].to_numpy()
        order = np.argsort(ids, kind="stable")
        sent = pairs.sparkSession.sparkContext.broadcast((ids[order], g[order]))

        def run(batches):
            ids, g = sent.value
            for batch in batches:
                mine = batch.column(0).to_numpy()
                lo, hi = np.searchsorted(ids, mine), np.searchsorted(ids, mine, "right")
                rows = np.repeat(np.arange(len(mine)), hi - lo)
                at = np.arange(len(rows)) - np.repeat(np.cumsum(hi - lo) - (hi - lo), hi - lo) + np.repeat(lo, hi - lo)
                if len(rows):
                    some = batch.take(pa.array(rows))
                    yield pa.RecordBatch.from_arrays([pa.array(g[at].astype(np.int32)), some.column(0), some.column(1)], names=["g", "id", "hashes"])

        given = sets.run(run, "g int, id long, hashes array<long>")
    else:
        given = sets.frame().join(wanted.select("id", F.col("g").alias("to")), "id").select(F.col("to").alias("g"), "id", "hashes")

    def compare(left: pa.Table, right: pa.Table) -> pa.Table:
        at = {i: k for k, i in enumerate(left["id"].to_pylist())}
        flat, offsets = lists_of(left["hashes"].combine_chunks()) if len(at) else (np.zeros(0, np.int64), np.zeros(1, np.int64))
        fresh = np.zeros(len(flat) + 1, bool)
        fresh[offsets] = True
        if not ((flat[1:] > flat[:-1]) | fresh[1:-1]).all():  # sets of texts come sorted
            flat = flat[np.lexsort((flat, np.repeat(np.arange(len(at)), np.diff(offsets))))]
        a, b = right["a"].to_numpy(), right["b"].to_numpy()
        score = np.zeros(len(a))
        for k, (x, y) in enumerate(zip(a.tolist(), b.tolist(), strict=True)):
            one, two = flat[offsets[at[x]] : offsets[at[x] + 1]], flat[offsets[at[y]] : offsets[at[y] + 1]]
            if len(one) > len(two):
                one, two = two, one
            place = np.searchsorted(two, one)
            place[place == len(two)] = 0
            same = int((two[place] == one).sum())
            score[k] = same / (len(one) + len(two) - same)
        ok = score >= threshold
        return pa.table({"a": a[ok], "b": b[ok], "score": score[ok]})

    return given.groupBy("g").cogroup(tiled.groupBy("g")).applyInArrow(compare, "a long, b long, score double")
