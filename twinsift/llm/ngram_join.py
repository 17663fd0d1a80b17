"""N-gram Jaccard join by a universe partition and the pigeonhole principle.

A document's set holds the hashes of its distinct shingles of `size` words. Sizes are
cut into bands; for each band the universe of hashes is dealt by hash into m
segments. Two sets that reach the threshold differ in at most H shingles (H
follows from the band), so if every segment is indexed exactly (worth 1) or with its
one-deletion neighbourhood (worth 2) and the worths add up to H + S, segments worth
S or more must agree. How many segments of either kind a band gets is
chosen by estimated cost: index rows to write against rows that meet by accident, for the band's number of sets.
S leaves room for segments that are too empty to tell anything: they are not
indexed unless a set has so many of them that they use up S; such sets index them under a mark of
their own, where only their like meets them. So no pair is lost and nothing is capped.

A set writes index rows under the parameters of its own band and of the next lower one.
Rows that share a key are candidates. They are compared in three rounds, so that
a large group of copies never becomes all its pairs: first each member with the
smallest of its bucket; what the verified links connect is one part. Then, in buckets
where several parts meet, the nearest pairs that would join them (a spanning forest, fewer than parts).
Last, in buckets where parts are still apart, all their pairs that have not been compared yet. Before
exact verification a parity sketch (one bit flipped for each shingle; BITS bits, and in pairs at least a bit for
each shingle up to WIDE_BITS) gives a lower bound of the difference, so it drops pairs but never a link.

A key that a run of documents holds often is written with a salt, so that no task has to take all rows of a common key, and one
row of the run stays without; salted groups are joined through their smallest members.

Equal sets are one set from the start: two 64-bit sums of their mixed hashes and their size tell sets apart. The first of them numbers
a set in the search for candidates; there a collision costs a comparison, and what is compared is told apart by both.
A shingle is a 64-bit hash of its words' hashes.

Defined cases: null or blank text, and fewer words than a shingle (one shingle of all words), as documented in
`shingle_sets`; an empty set is its own component; a null id stands in the component of its set's smallest
id, and a set that only rows without an id have links others like any set (a component without any id is null); repeated rows share their id; an empty table gives an empty one; further columns are ignored.
"""

import math

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from twinsift.functions.shipping import by_value
from twinsift.llm.common import slices, small_batches, text_bytes
from twinsift.operators.components import components
from twinsift.plans.checkpoints import cut

by_value(__name__)

SHINGLE = 4  # words, unless the caller of jaccard_components says otherwise; so is the threshold
NUMER, DENOM = 85, 100  # the threshold as a fraction
BAND_RATIO = 1.4
COMMON = 0.1  # share of four-word shingles that two unrelated sets are taken to have in common, a tenth of it for each word more; for the cost estimate only
BITS = 1024
WIDE_BITS = 1 << 16  # of the widest sketch; it has a bit for each shingle of a set up to that, and tells longer sets apart less well
BROADCAST_IDS = 1_000_000  # 8 MB of ids
BUCKET = 1500
SLICES = 1024  # in which sets without an id are numbered
TOP = 57  # the salt's lowest bit in a place
HOT, SALTS = 64, 64  # a key that so many sets of a run of 2 MB of text share is dealt over so many groups
RUN = 1 << 18  # bytes of text whose hashes are computed at a time
_BASE = 0x9E3779B97F4A7C15 | 1


def mix64(x: np.ndarray) -> np.ndarray:
    """A one-to-one scrambling of 64-bit numbers."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> np.uint64(27))
    x = x * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


class Shingler:
    """Word shingles of many texts at once, from their UTF-8 bytes."""

    def __init__(self, size: int = SHINGLE, seed: int = 5):
        self.size = size
        value = np.random.default_rng(seed).integers(1, 1 << 63, 256, np.uint64)
        value[ord("A") : ord("Z") + 1] = value[ord("a") : ord("z") + 1]
        self.value = value
        self.space = np.zeros(256, bool)
        self.space[[0x20, *range(0x09, 0x0E)]] = True
        self.up = self.down = np.ones(1, np.uint64)

    def _powers(self, n: int) -> None:
        if len(self.up) < n:
            inverse = pow(_BASE, -1, 1 << 64)
            for name, by in (("up", _BASE), ("down", inverse)):
                steps = np.full(n, by, np.uint64)
                steps[0] = 1
                setattr(self, name, np.cumprod(steps))

    def words(self, data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Hash of each word, and the number of words before each text."""
        n = len(data)
        solid = ~self.space[data]
        first, last = solid.copy(), solid.copy()
        first[1:] &= ~solid[:-1]
        last[:-1] &= ~solid[1:]
        edges = offsets[1:-1]
        edges = edges[(edges > 0) & (edges < n)]
        first[edges] = solid[edges]
        last[edges - 1] = solid[edges - 1]
        starts, ends = np.flatnonzero(first), np.flatnonzero(last)
        hashes = np.empty(len(starts), np.uint64)
        i = 0
        while i < len(starts):  # runs of words of bounded length in bytes; a longer word comes alone
            j = max(i + 1, int(np.searchsorted(ends, starts[i] + RUN)))
            part = data[starts[i] : ends[j - 1] + 1]
            self._powers(len(part) + 1)
            total = np.concatenate([np.zeros(1, np.uint64), np.cumsum(self.value[part] * self.up[: len(part)], dtype=np.uint64)])
            a, z = starts[i:j] - starts[i], ends[i:j] + 1 - starts[i]
            hashes[i:j] = mix64((total[z] - total[a]) * self.down[a] + (z - a).astype(np.uint64))
            i = j
        return hashes, np.searchsorted(starts, offsets)

    def shingle_sets(self, data: np.ndarray, offsets: np.ndarray):
        """The sorted distinct shingle hashes of each text: none without words, one with fewer words than a shingle holds."""
        hashes, at = self.words(data, offsets)
        odd = mix64(np.arange(1, self.size + 1, dtype=np.uint64)) | np.uint64(1)  # one multiplier a place, in no simple relation
        k = self.size
        rolled = np.zeros(max(0, len(hashes) - k + 1), np.uint64)
        for j in range(k):
            rolled += hashes[j : j + len(rolled)] * odd[j]
        rolled = mix64(rolled)
        for a, b in zip(at.tolist(), at[1:].tolist(), strict=False):
            if b - a >= k:
                yield np.unique(rolled[a : b - k + 1])
            elif b > a:
                yield mix64((hashes[a:b] * odd[: b - a]).sum(keepdims=True) + np.uint64(b - a))
            else:
                yield np.zeros(0, np.uint64)


def most_apart(a: int, b: int, numer: int = NUMER, denom: int = DENOM) -> int:
    """How many elements two sets of these sizes may differ in at most, to reach the threshold."""
    return (a + b) * (denom - numer) // (denom + numer)


def band_edges(limit: int = 1 << 31) -> np.ndarray:
    """Smallest size of each band."""
    edges, at = [1], 1
    while at < limit:
        at = max(at + 1, math.ceil(at * BAND_RATIO))
        edges.append(at)
    return np.array(edges, np.int64)


EDGES = band_edges()


def plan_band(band: int, sets: int, common: float = COMMON, numer: int = NUMER, denom: int = DENOM) -> tuple[int, int, int]:
    """Segments indexed exactly, segments with one-deletion neighbourhoods, and S.

    Of two unrelated sets a share `common` of shingles is taken to be the same. The cost counts index rows and
    the rows that meet others by accident, for a band of this many sets."""
    low, high = int(EDGES[band]), int(EDGES[band + 1]) - 1
    h = most_apart(high, high * denom // numer, numer, denom)
    mean = (low + high) / 2
    best = None
    for two in sorted({round((h + 1) // 2 * k / 8) for k in range(9)}):
        room = 1
        for _ in range(3):
            one = max(0, h + room - 2 * two)
            m = one + two
            if m == 0:
                m, one = 1, 1
            each = mean / m
            blank = one * math.exp(-low / m) + 2 * two * math.exp(-low / m) * (1 + low / m)
            room = 1 + math.ceil(blank + 2 * math.sqrt(blank)) if h else 1
        room = one + 2 * two - h  # S, as it is with these segments
        rows = one + two * (1 + each)
        meets = sets * (one * common**each + two * each * common ** max(0.0, each - 1))
        cost = rows + 0.2 * min(meets, 1e12)
        if best is None or cost < best[0]:
            best = (cost, one, two, room)
    return best[1:]


def _segment_keys(values: np.ndarray, band: int, plan: tuple[int, int, int]) -> np.ndarray:
    """Index keys of one set under the parameters of a band."""
    one, two, room = plan
    m = one + two
    place = (mix64(values ^ np.uint64((band + 1) * 0x9E37 << 20)) % np.uint64(m)).astype(np.int64)
    mixed = mix64(values + np.uint64(band + 1))
    count = np.bincount(place, minlength=m)
    total = np.zeros(m, np.uint64)
    np.add.at(total, place, mixed)
    label = (np.arange(m, dtype=np.uint64) + np.uint64(1)) * np.uint64(0xD6E8FEB86659FD93) + mix64(np.full(1, band + 1, np.uint64))
    parts = [mix64(total + label)[count > 0]]
    if two:
        # the last segments have one-deletion neighbourhoods
        deep = (place >= one) & (count[place] > 1)
        parts.append(mix64(total[place[deep]] - mixed[deep] + label[place[deep]]))
    blank = np.where(np.arange(m) < one, count == 0, count <= 1)
    worth = np.where(np.arange(m) < one, 1, 2)
    if (worth * blank).sum() >= room:
        parts.append(mix64(label[blank] ^ np.uint64(0x5851F42D4C957F2D)))
    return np.concatenate(parts)


def number_of(values: np.ndarray, seed: int = 0x1234567) -> int:
    """64-bit number of a set."""
    total = mix64(values + np.uint64(seed)).sum(dtype=np.uint64)
    return int(mix64(np.array([total + np.uint64(len(values))], np.uint64)).view(np.int64)[0])


def check_of(values: np.ndarray) -> int:
    """A second number, so that the two tell sets apart by 128 bits."""
    return number_of(values ^ np.uint64(0xA5A5A5A55A5A5A5A), 0x7654321)


def parity(values: np.ndarray, bits: int = BITS) -> bytes:
    """One bit flipped for each shingle: sketches of two sets differ in no more bits than the sets in elements."""
    odd = np.bincount((values % np.uint64(bits)).astype(np.int64), minlength=bits) & 1
    return np.packbits(odd.astype(np.uint8)).tobytes()


def wide_parity(values: np.ndarray) -> bytes | None:
    """A parity sketch with a bit or more for each shingle, for sets of more than BITS shingles: there BITS bits tell nothing any more."""
    return parity(values, min(WIDE_BITS, 1 << (len(values) - 1).bit_length())) if len(values) > BITS else None


def folded(sketches: np.ndarray, words: int) -> np.ndarray:
    """Parity sketches (a row each) brought down to this many 64-bit words, a power of two: the halves' exclusive or is the sketch of half the bits."""
    while sketches.shape[1] > words:
        half = sketches.shape[1] // 2
        sketches = sketches[:, :half] ^ sketches[:, half:]
    return sketches


def describe(docs: DataFrame, size: int = SHINGLE) -> DataFrame:
    """doc_id, n, number, check, sketch, wide of each document's set; all but the first two are null for an empty set, and wide for sets of up to BITS shingles."""

    def run(batches):
        shingler = Shingler(size)
        for piece in slices(batches, 2 << 20):
            n, number, check, sketch, wide = [], [], [], [], []
            for values in shingler.shingle_sets(*text_bytes(piece.column(1))):
                n.append(len(values))
                number.append(number_of(values) if len(values) else None)
                check.append(check_of(values) if len(values) else None)
                sketch.append(parity(values) if len(values) else None)
                wide.append(wide_parity(values))
            yield pa.RecordBatch.from_arrays([piece.column(0), pa.array(n, pa.int64()), pa.array(number, pa.int64()), pa.array(check, pa.int64()), pa.array(sketch, pa.binary()), pa.array(wide, pa.binary())], names=["doc_id", "n", "number", "check", "sketch", "wide"])

    return docs.select(docs["doc_id"].cast("long"), docs["text"]).mapInArrow(run, "doc_id long, n long, number long, check long, sketch binary, wide binary")


def salted(keys: np.ndarray, numbers: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Salt of each index row of a run: 0, or 1 to SALTS by the set's number where the run has the key HOT times; and which rows besides
    go without a salt: one of each such key, the smallest number, so that the unsalted group of the key knows it."""
    order = np.lexsort((numbers, keys))
    k = keys[order]
    first = np.flatnonzero(np.concatenate([[True], k[1:] != k[:-1]]))
    count = np.diff(np.concatenate([first, [len(k)]]))
    hot = np.repeat(count >= HOT, count)
    salt = np.zeros(len(keys), np.int32)
    salt[order] = np.where(hot, 1 + (mix64(numbers[order].view(np.uint64)) % np.uint64(SALTS)).astype(np.int32), 0)
    return salt, order[first[count >= HOT]]


def index_rows(docs: DataFrame, plans: list[tuple[int, int, int]], size: int = SHINGLE, numer: int = NUMER, denom: int = DENOM) -> DataFrame:
    """(place, number, n): the index rows of every distinct set. A task writes those of equal sets once.

    A row's place is its key with the salt in the highest bits; the salt also stands above the 32 bits of n, so the key can be had again. The unsalted copy of a salted row has its n negative."""

    def run(batches):
        shingler, seen = Shingler(size), set()
        for piece in slices(batches, 2 << 20):
            keys, numbers, sizes, lens = [], [], [], []
            for values in shingler.shingle_sets(*text_bytes(piece.column(1))):
                if not len(values) or (both := (number_of(values), check_of(values))) in seen:
                    continue
                seen.add(both)
                band = int(np.searchsorted(EDGES, len(values), "right")) - 1
                for b in (band, band - 1):
                    high = int(EDGES[b + 1]) - 1
                    if b < 0 or b < band and len(values) > high * denom // numer:
                        continue
                    if most_apart(high, high * denom // numer, numer, denom) == 0:
                        continue  # in so small a band only equal sets link
                    own = _segment_keys(values, b, plans[b])
                    keys.append(own)
                    numbers.append(both[0])
                    sizes.append(len(values))
                    lens.append(len(own))
            if keys:
                key, number, n = np.concatenate(keys).view(np.int64), np.repeat(np.array(numbers, np.int64), lens), np.repeat(np.array(sizes, np.int32), lens)
                salt, plain = salted(key, number)
                every = np.concatenate([np.arange(len(key)), plain])
                salt = np.concatenate([salt, np.zeros(len(plain), np.int32)]).astype(np.int64)
                n = np.concatenate([n, -n[plain]]).astype(np.int64) + (salt << 32)
                yield pa.RecordBatch.from_arrays([pa.array(key[every] ^ (salt << TOP)), pa.array(number[every]), pa.array(n)], names=["place", "number", "n"])

    return docs.select(docs["doc_id"].cast("long"), docs["text"]).mapInArrow(run, "place long, number long, n long")


def sets_of(docs: DataFrame, wanted: DataFrame, size: int = SHINGLE) -> DataFrame:
    """(number, check, set) of the sets in wanted (number, check, doc_id): one row of each is looked up by its id, or by its set if it has none."""
    ids = cut(wanted.select("doc_id").distinct())
    bare = not ids.filter("doc_id is null").isEmpty()
    ids = ids.filter("doc_id is not null")
    if ids.count() <= BROADCAST_IDS:
        ids = F.broadcast(ids)
    texts = docs.select(docs["doc_id"].cast("long").alias("doc_id"), docs["text"])
    found = texts.join(ids, "doc_id", "left_semi")
    found = found.unionByName(texts.filter("doc_id is null")) if bare else found

    def run(batches):
        shingler, seen = Shingler(size), set()
        for piece in slices(batches, 2 << 20):
            made = []
            for v in shingler.shingle_sets(*text_bytes(piece.column(1))):
                if len(v) and (both := (number_of(v), check_of(v))) not in seen:
                    seen.add(both)
                    made.append((*both, v.tobytes()))
            yield pa.RecordBatch.from_arrays([pa.array([x[0] for x in made], pa.int64()), pa.array([x[1] for x in made], pa.int64()), pa.array([x[2] for x in made], pa.binary())], names=["number", "check", "set"])

    rows = found.mapInArrow(run, "number long, check long, set binary")
    if bare:
        rows = rows.join(wanted.select("number", "check"), ["number", "check"], "left_semi")
    return rows.repartition("number").dropDuplicates(["number", "check"])  # dealt as the joins that follow ask for


def verify(pairs: DataFrame, sets: DataFrame, numer: int = NUMER, denom: int = DENOM) -> DataFrame:
    """The pairs (x, y) whose sets reach the threshold, by exact intersection, with the checks of both sets."""

    def run(batches):
        for batch in batches:
            keep = []
            for x, y in zip(batch.column(4), batch.column(5), strict=True):
                a, b = np.frombuffer(x.as_buffer(), np.uint64), np.frombuffer(y.as_buffer(), np.uint64)
                both = np.concatenate([a, b])
                both.sort()
                same = int(np.count_nonzero(both[1:] == both[:-1]))
                keep.append(denom * same >= numer * (len(a) + len(b) - same))
            yield batch.select([0, 1, 2, 3]).filter(pa.array(keep, pa.bool_()))

    one, two = (sets.select(F.col("number").alias(c), F.col("check").alias(f"check_{c}"), F.col("set").alias(f"set_{c}")) for c in "xy")
    return pairs.join(one, "x").join(two, "y").select("x", "y", "check_x", "check_y", "set_x", "set_y").mapInArrow(run, "x long, y long, check_x long, check_y long")


def _across(table: pa.Table, bits_apart: int, bits_sum: int, forest: bool) -> tuple[np.ndarray, np.ndarray]:
    """In one bucket (or tile of one): pairs of different parts whose sketches and sizes allow a link.

    forest: only as many as connect all parts that such pairs connect, the nearest first."""
    number, part, n, side = (table[c].to_numpy() for c in ("number", "part", "n", "block"))
    words = np.frombuffer(b"".join(table["sketch"].to_pylist()), np.uint64).reshape(len(number), -1)
    i, j = table["i"][0].as_py(), table["j"][0].as_py()
    left = np.flatnonzero(side == i)
    right = np.flatnonzero(side == j)
    xs, ys, far = [], [], []
    step = max(1, (1 << 21) // max(1, len(right) * words.shape[1]))
    for k in range(0, len(left), step):
        a = left[k : k + step]
        ok = (part[a][:, None] != part[right][None]) & (number[a][:, None] < number[right][None] if i == j else np.ones((len(a), len(right)), bool))
        if not ok.any():
            continue
        apart = np.bitwise_count(words[a][:, None, :] ^ words[right][None, :, :]).sum(2, dtype=np.int64)
        total = n[a][:, None] + n[right][None]
        p, q = np.nonzero(ok & (apart * bits_sum <= total * bits_apart))
        xs.append(a[p])
        ys.append(right[q])
        far.append(apart[p, q] / total[p, q])
    none = np.zeros(0, np.int64)
    x, y, d = (np.concatenate(v) if v else none for v in (xs, ys, far))
    if forest and len(x) > 1:
        order = np.argsort(d, kind="stable")
        x, y = x[order], y[order]
        root: dict[int, int] = {}

        def top(v):
            while (u := root.get(v, v)) != v:
                root[v] = root.get(u, u)
                v = u
            return v

        used = []
        for k, (u, v) in enumerate(zip(part[x].tolist(), part[y].tolist(), strict=True)):
            u, v = top(u), top(v)
            if u != v:
                root[max(u, v)] = min(u, v)
                used.append(k)
        x, y = x[used], y[used]
    x, y = number[x], number[y]
    return np.minimum(x, y), np.maximum(x, y)


def pairs_across(rows: DataFrame, sketches: DataFrame, forest: bool, numer: int = NUMER, denom: int = DENOM) -> DataFrame:
    """(x, y) of different parts in one bucket; rows (key, number, n, part). Large buckets go as tiles of blocks, each a group of its own."""
    size = rows.groupBy("key").agg(F.ceil(F.count("*") / BUCKET).cast("int").alias("blocks"), F.min("part").alias("p"), F.max("part").alias("q")).filter("p <> q").select("key", "blocks")
    rows = rows.join(size, "key").withColumn("block", F.pmod(F.xxhash64("number"), F.col("blocks")).cast("int"))
    rows = rows.select("key", "number", "n", "part", "block", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("other"))
    rows = rows.select("key", F.least("block", "other").alias("i"), F.greatest("block", "other").alias("j"), "number", "n", "part", "block").join(sketches, "number")
    rows = rows.repartition("key", "i", "j").sortWithinPartitions("key", "i", "j")

    def run(batches):
        kept = None  # rows of a bucket that the next batch may go on with
        for batch in batches:
            table = pa.Table.from_batches([batch])
            table = pa.concat_tables([kept, table]).combine_chunks() if kept is not None else table
            key, i, j = (table[c].to_numpy() for c in ("key", "i", "j"))
            cuts = np.flatnonzero((np.diff(key) != 0) | (np.diff(i) != 0) | (np.diff(j) != 0)) + 1
            edges = [0, *cuts.tolist()]
            done = [_across(table.slice(a, b - a), denom - numer, denom + numer, forest) for a, b in zip(edges, edges[1:], strict=False)]
            kept = table.slice(edges[-1])
            yield from out(done)
        if kept is not None and kept.num_rows:
            yield from out([_across(kept, denom - numer, denom + numer, forest)])

    def out(done):
        if any(len(x) for x, _ in done):
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate([x for x, _ in done])), pa.array(np.concatenate([y for _, y in done]))], names=["x", "y"])

    return rows.select("key", "i", "j", "number", "n", "part", "block", "sketch").mapInArrow(run, "x long, y long").distinct()


def jaccard_components(docs: DataFrame, size: int = SHINGLE, numer: int = NUMER, denom: int = DENOM) -> DataFrame:
    """doc_id, n_shingles and component_id of every document; links are pairs of sets of `size`-word shingles with Jaccard numer / denom or more."""
    if not 0 < numer < denom <= BAND_RATIO * numer:
        raise ValueError(f"the threshold must be below 1 and at least 1 / {BAND_RATIO}: sets of two neighbouring bands are compared")
    small_batches(docs.sparkSession)
    described = cut(describe(docs, size))
    full = described.filter("n > 0")
    sets = cut(full.groupBy("number", "check", "n").agg(F.min("doc_id").alias("node"), F.first("sketch").alias("sketch"), F.first("wide").alias("wide")))
    edge = F.lit(0)
    for e in EDGES[1:].tolist():
        edge = edge + (F.col("n") >= e).cast("int")
    sizes = {r["band"]: r["sets"] for r in sets.groupBy(edge.alias("band")).agg(F.count("*").alias("sets")).collect()}
    plans = [plan_band(b, sizes.get(b, 0) + sizes.get(b + 1, 0), min(0.5, COMMON ** (size - 3)), numer, denom) for b in range(len(EDGES) - 1)]

    met = Window.partitionBy("place")
    rows = index_rows(docs, plans, size, numer, denom).withColumn("pivot", F.min("number").over(met)).withColumn("last", F.max("number").over(met))
    salt = F.greatest(F.shiftright("n", 32), F.lit(0).cast("long"))
    parted = (F.col("n") < 0) | (salt > 0)
    key = F.col("place").bitwiseXOR(F.shiftleft(salt, TOP))
    rows = cut(rows.filter((F.col("pivot") != F.col("last")) | parted).select(key.alias("key"), parted.alias("parted"), "number", F.abs(F.col("n") - F.shiftleft(salt, 32)).alias("n"), "pivot"))

    sketches = sets.select("number", "n", "sketch", "wide")
    groups = rows.filter("parted").select("key", F.col("pivot").alias("y")).distinct()  # what salting has parted meets again through the smallest of all
    least = groups.groupBy("key").agg(F.min("y").alias("x"), F.max("y").alias("z")).filter("x <> z").select("key", "x")
    star = rows.filter("number <> pivot").select(F.col("pivot").alias("x"), F.col("number").alias("y")).union(groups.join(least, "key").filter("x <> y").select("x", "y")).distinct()
    tested = _near(star, sketches, numer, denom)
    links = _links(docs, tested, sets, size, numer, denom)
    for forest in (True, False):
        parts = components(links.select(F.col("x").alias("a"), F.col("y").alias("b")))
        labelled = rows.join(parts.select(F.col("id").alias("number"), F.col("component").alias("part")), "number", "left").withColumn("part", F.coalesce("part", "number"))
        mixed = labelled.select("key", "number", "n", "part").distinct()
        found = cut(pairs_across(mixed, sketches.select("number", "sketch"), forest, numer, denom).join(tested, ["x", "y"], "left_anti"))
        links, tested = links.union(_links(docs, _near(found, sketches, numer, denom), sets, size, numer, denom)), tested.union(found)

    # a set without an id of its own gets a number below all ids that are there
    nodes = sets.select("number", "check", "n", "node")
    floor = nodes.agg(F.least(F.coalesce(F.min("node"), F.lit(0)), F.lit(0))).first()[0]
    bare = nodes.filter("node is null")
    if not bare.isEmpty():
        place = Window.partitionBy("slice").orderBy("number", "check", "n")
        bare = bare.withColumn("slice", F.pmod("number", F.lit(SLICES)).cast("int")).withColumn("nth", F.row_number().over(place))
        nodes = nodes.filter("node is not null").unionByName(bare.select("number", "check", "n", (F.lit(floor) - 1 - (F.col("nth") - 1) * SLICES - F.col("slice")).alias("node")))
    nodes = cut(nodes)
    one, two = (nodes.select(F.col("number").alias(c), F.col("check").alias(f"check_{c}"), F.col("node").alias(a)) for c, a in (("x", "a"), ("y", "b")))
    edges = links.join(one, ["x", "check_x"]).join(two, ["y", "check_y"])
    # parts by their smallest number; where that is no id, the smallest id of the part counts
    parts = components(edges.select("a", "b")).withColumnRenamed("id", "node")
    parts = nodes.join(parts, "node", "left").withColumn("component", F.coalesce("component", "node"))
    named = parts.filter(F.col("component") < floor).groupBy("component").agg(F.min(F.when(F.col("node") >= floor, F.col("node"))).alias("name"))
    of_set = parts.join(_small(named), "component", "left").withColumn("component", F.when(F.col("component") < floor, F.col("name")).otherwise(F.col("component"))).select("number", "check", "n", "component")
    out = described.select("doc_id", "n", "number", "check").join(of_set, ["number", "check", "n"], "left")
    return out.select("doc_id", F.col("n").alias("n_shingles"), F.coalesce("component", "doc_id").alias("component_id"))


def _small(df: DataFrame) -> DataFrame:
    """Broadcast, if it has few rows."""
    df = cut(df)
    return F.broadcast(df) if df.count() <= BROADCAST_IDS else df


def _near(pairs: DataFrame, sketches: DataFrame, numer: int, denom: int) -> DataFrame:
    """The pairs whose sizes and sketches allow a link."""

    def run(batches):
        for batch in batches:
            if not batch.num_rows:
                continue
            apart = np.zeros(batch.num_rows, np.int64)
            bytes_x, bytes_y = (pc.binary_length(batch.column(c)).to_numpy(zero_copy_only=False) for c in (4, 5))
            for kind in set(zip(bytes_x.tolist(), bytes_y.tolist(), strict=True)):  # sketches of two lengths are compared at the shorter one
                at = np.flatnonzero((bytes_x == kind[0]) & (bytes_y == kind[1]))
                a, b = (folded(np.frombuffer(b"".join(batch.column(c).take(pa.array(at)).to_pylist()), np.uint64).reshape(len(at), -1), min(kind) // 8) for c in (4, 5))
                apart[at] = np.bitwise_count(a ^ b).sum(1, dtype=np.int64)
            keep = apart * (denom + numer) <= (batch.column(2).to_numpy() + batch.column(3).to_numpy()) * (denom - numer)
            yield batch.select([0, 1]).filter(pa.array(keep))

    one = sketches.select(F.col("number").alias("x"), F.col("n").alias("nx"), F.coalesce("wide", "sketch").alias("sx"))
    two = sketches.select(F.col("number").alias("y"), F.col("n").alias("ny"), F.coalesce("wide", "sketch").alias("sy"))
    both = pairs.join(one, "x").join(two, "y").filter(f"least(nx, ny) * {denom} >= greatest(nx, ny) * {numer}")
    return cut(both.select("x", "y", "nx", "ny", "sx", "sy").mapInArrow(run, "x long, y long"))


def _links(docs: DataFrame, pairs: DataFrame, sets: DataFrame, size: int, numer: int, denom: int) -> DataFrame:
    """The pairs that are links."""
    numbers = pairs.select(F.explode(F.array("x", "y")).alias("number")).distinct()
    wanted = cut(sets.join(numbers, "number").select("number", "check", F.col("node").alias("doc_id")))
    return cut(verify(pairs, sets_of(docs, wanted, size), numer, denom))
