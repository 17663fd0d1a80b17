"""MinHash and SimHash, exact Jaccard joins, and banded candidate search."""

import hashlib
from collections.abc import Callable
from functools import cache

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from twinsift.functions.shipping import by_value
from twinsift.functions.text import PRIME31, WORD_BREAK, char_shingles, hamming, md5_int
from twinsift.operators import setjoin
from twinsift.operators.setjoin import ROWS, lists_of, mixed  # by name: a module does not travel with a function
from twinsift.plans.checkpoints import cut

by_value(__name__)

MAX_BROADCAST_KEYS = 100_000


def shingle_hashes(df: DataFrame, n: int = 3, kind: str = "word", id_col: str = "doc_id", text_col: str = "text", fast: bool = False) -> DataFrame:
    """(id, hashes): distinct 60-bit md5 numbers of the shingles; fast uses numbers that DuckDB lacks."""
    if kind == "word":
        return shingle_sets(df, n, id_col, text_col, fast).frame(df.select(id_col).schema[0].dataType.simpleString())
    grams = F.array_distinct(char_shingles(F.col(text_col), n))
    one = (lambda g: F.xxhash64(g)) if fast else md5_int
    return df.select(F.col(id_col).alias("id"), F.array_distinct(F.transform(grams, one)).alias("hashes"))


WORDS_KNOWN = 400_000  # words of which a task remembers the number


class _Numbers(dict):
    """64-bit numbers of words."""

    def __missing__(self, word: str) -> int:
        if len(self) > WORDS_KNOWN:
            self.clear()
        self[word] = number = int.from_bytes(hashlib.md5(word.encode("utf-8", "surrogatepass")).digest()[:8], "little")
        return number


def shingle_sets(df: DataFrame, n: int = 3, id_col: str = "doc_id", text_col: str = "text", fast: bool = True) -> setjoin.Sets:
    """The sets of `shingle_hashes` of words, each sorted; fast: a shingle's number comes from those of its words in order."""

    def exact(words: str) -> np.ndarray:
        text = words.encode("utf-8", "surrogatepass")
        gaps = np.flatnonzero(np.frombuffer(text, np.uint8) == 32)
        if not text or len(gaps) < n - 1:
            return np.zeros(0, np.int64)
        start, end = [0, *(gaps + 1).tolist()], [*gaps.tolist(), len(text)]
        md5 = hashlib.md5
        digests = b"".join([md5(text[a:b]).digest()[:8] for a, b in zip(start, end[n - 1 :], strict=False)])
        return np.unique((np.frombuffer(digests, ">u8") >> np.uint64(4)).astype(np.int64))

    def run(batches):
        numbers = _Numbers()

        def quick(words: str) -> np.ndarray:
            parts = words.split()
            if len(parts) < n:
                return np.zeros(0, np.int64)
            w = np.fromiter(map(numbers.__getitem__, parts), np.uint64, len(parts))
            h = np.zeros(len(parts) - n + 1, np.uint64)
            for k in range(n):
                h = mixed((h + w[k : k + len(h)]).view(np.int64), k % 3)
            return np.unique(h.view(np.int64))

        for batch in (b.slice(k, ROWS) for b in batches for k in range(0, b.num_rows, ROWS)):
            sets = [None if words is None else quick(words) if fast else exact(words) for words in batch.column(1).to_pylist()]
            ends = np.concatenate([[0], np.cumsum([0 if s is None else len(s) for s in sets], dtype=np.int64)]).astype(np.int32)
            flat = np.concatenate([np.zeros(0, np.int64), *(s for s in sets if s is not None)])
            mask = pa.array([s is None for s in sets], pa.bool_())
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.ListArray.from_arrays(pa.array(ends), pa.array(flat), mask=mask)], names=["id", "hashes"])

    words = F.trim(F.regexp_replace(F.lower(F.col(text_col)), WORD_BREAK, " "))
    return setjoin.Sets(df.select(F.col(id_col).alias("id"), words.alias("words")), run)


def coefficients(k: int) -> list[tuple[int, int]]:
    """Multiplier and addend of each slot, from the md5 of its number."""
    pick = lambda text: int(hashlib.md5(text.encode()).hexdigest()[:15], 16) % PRIME31
    return [(max(1, pick(f"a{i}")), pick(f"b{i}")) for i in range(k)]


def minhash(hashes: Column, k: int) -> Column:
    """k minima of (a h + b) mod (2^31 - 1); null where there is no shingle. The array is never exploded."""
    small = F.transform(hashes, lambda h: F.pmod(h, F.lit(PRIME31)))
    slots = F.array(*(F.struct(F.lit(a).cast("long").alias("a"), F.lit(b).cast("long").alias("b")) for a, b in coefficients(k)))
    minima = F.transform(slots, lambda s: F.array_min(F.transform(small, lambda h: (h * s["a"] + s["b"]) % F.lit(PRIME31))))
    return F.when(F.size(hashes) > 0, minima)


def sign(df: DataFrame, k: int = 256, n: int = 3, **how) -> DataFrame:
    """(id, signature) of texts."""
    return sign_hashes(shingle_hashes(df, n, **how), k)


def sign_hashes(hashed: DataFrame, k: int) -> DataFrame:
    """(id, signature): the minima of `minhash`, slot by slot over an Arrow batch of sets in numpy."""
    sign = signatures(k)

    def run(batches):
        for batch in batches:
            full = np.diff(batch.column(1).offsets.to_numpy()) > 0
            out = sign(batch.column(1))
            ends = np.concatenate([[0], np.cumsum(full * k)]).astype(np.int32)
            signature = pa.ListArray.from_arrays(pa.array(ends), pa.array(out.ravel(), pa.int64()), mask=pa.array(~full))
            yield pa.RecordBatch.from_arrays([batch.column(0), signature], names=["id", "signature"])

    return hashed.select(F.col("id").cast("long").alias("id"), F.coalesce("hashes", F.array().cast("array<bigint>")).alias("hashes")).mapInArrow(run, "id long, signature array<long>")


def signatures(k: int) -> Callable:
    """A function from a list column to the minima of its lists that are not empty, one row each."""
    pairs = coefficients(k)

    def sign(lists: pa.ListArray) -> np.ndarray:
        flat, at = lists_of(lists)
        flat, full = flat % PRIME31, np.diff(at) > 0
        out = np.empty((int(full.sum()), k), np.int64)
        if len(out):
            for i, (a, b) in enumerate(pairs):
                out[:, i] = np.minimum.reduceat((flat * a + b) % PRIME31, at[:-1][full])
        return out

    return sign


def agreement(a: Column, b: Column) -> Column:
    """Share of equal slots, the estimate of the Jaccard coefficient."""
    return F.aggregate(F.zip_with(a, b, lambda x, y: (x == y).cast("int")), F.lit(0), lambda s, v: s + v) / F.size(a)


@cache
def choose_bands(threshold: float, k: int, weight: float = 0.5, recall: float = 0.0) -> tuple[int, int]:
    """Bands and rows with bands * rows <= k that make the weighted areas of wrong candidates and of missed pairs smallest.

    recall: only choices that find a pair right at the threshold with this probability at least."""
    below, above = np.linspace(0, threshold, 401), np.linspace(threshold, 1, 401)
    best = None
    for rows in range(1, k + 1):
        for bands in range(1, k // rows + 1):
            if recall and 1 - (1 - threshold**rows) ** bands < recall:
                continue
            cost = weight * np.trapezoid(1 - (1 - below**rows) ** bands, below) + (1 - weight) * np.trapezoid((1 - above**rows) ** bands, above)
            if best is None or cost < best[0] - 1e-12:
                best = (cost, bands, rows)
    if best is None:
        raise ValueError(f"{k} hashes cannot find pairs at {threshold} with probability {recall}")
    return best[1], best[2]


def band_keys(signed: DataFrame, bands: int, rows: int) -> DataFrame:
    """(key, id): one row a band. The key is a 64-bit hash of the band number and its slots."""
    keys = F.transform(F.sequence(F.lit(0), F.lit(bands - 1)), lambda b: F.xxhash64(b, F.slice("signature", b * rows + 1, rows)))
    return signed.filter("signature is not null").select("id", F.explode(keys).alias("key"))


HOT_KEY = 2000  # rows of a key that one task pairs with one another


def candidates(keys: DataFrame, such_that: Column | None = None) -> DataFrame:
    """Distinct pairs a < b of ids that share a key; rows (key, id, and columns that such_that sees as <name>_a and <name>_b).

    The rows of a key beyond HOT_KEY are dealt over blocks, and each pair of blocks is a group of its own: no task pairs a common key alone."""
    keys = cut(keys)
    rest = [c for c in keys.columns if c not in ("key", "id")]
    hot = keys.groupBy("key").agg(F.ceil(F.count("*") / HOT_KEY).cast("int").alias("blocks")).filter("blocks > 1")
    hot = cut(hot)
    small = hot.count() <= MAX_BROADCAST_KEYS
    dealt = keys.join(F.broadcast(hot) if small else hot, "key", "left").withColumn("blocks", F.coalesce("blocks", F.lit(1))).withColumn("block", F.pmod(F.xxhash64("id"), F.col("blocks")).cast("int"))
    left = dealt.select("key", "block", F.col("id").alias("a"), *(F.col(c).alias(f"{c}_a") for c in rest), F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("other"))
    right = dealt.select("key", F.col("block").alias("other"), F.col("id").alias("b"), *(F.col(c).alias(f"{c}_b") for c in rest), F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)).alias("block"))
    both = left.join(right, ["key", "block", "other"]).filter("a < b")
    return (both if such_that is None else both.filter(such_that)).select("a", "b").distinct()


def exact_pairs(hashed: DataFrame, pairs: DataFrame, threshold: float) -> DataFrame:
    """(a, b, score): pairs whose shingle sets reach the threshold, from the sets themselves."""
    return setjoin.verified(setjoin.sets_of(hashed), pairs, threshold)


def expand(near: DataFrame, members: DataFrame) -> DataFrame:
    """All pairs (a < b, score) of rows from links of classes (a, b, score) and membership (id, rep): as many rows as there are pairs."""
    own = members.select("rep").distinct().select(F.col("rep").alias("a"), F.col("rep").alias("b"), F.lit(1.0).alias("score"))
    left, right = members.select(F.col("rep").alias("a"), F.col("id").alias("i")), members.select(F.col("rep").alias("b"), F.col("id").alias("j"))
    full = near.select("a", "b", "score").unionByName(own).join(left, "a").join(right, "b").filter((F.col("a") != F.col("b")) | (F.col("i") < F.col("j")))
    return full.select(F.least("i", "j").alias("a"), F.greatest("i", "j").alias("b"), "score")


def stars(members: DataFrame) -> DataFrame:
    """(a, b, score): each copy with the smallest id of its class, instead of all pairs of copies."""
    return members.filter("id <> rep").select(F.col("rep").alias("a"), F.col("id").alias("b"), F.lit(1.0).alias("score"))


def banded(k: int, bands: int, rows: int) -> Callable:
    """keys_of for `setjoin.keyed`: one number a band, of its place and its slots."""
    sign = signatures(k)

    def keys_of(batch):
        out = sign(batch.column(1))[:, : bands * rows].reshape(-1, bands, rows)
        key = np.tile(np.arange(bands, dtype=np.int64), (len(out), 1))
        for i in range(rows):
            key = mixed((key + out[:, :, i]).ravel(), i % 3).view(np.int64).reshape(key.shape)
        return key.ravel(), np.repeat(batch.column(0).to_numpy(), bands), np.zeros(key.size, np.int64)

    return keys_of


def banded_pairs(classes: setjoin.Classes, threshold: float, k: int, recall: float = 0.0) -> DataFrame:
    """(a, b, score): classes that share a band of MinHash and reach the threshold, by the sets themselves."""
    bands, rows = choose_bands(threshold, k, recall=recall)
    buckets = setjoin.buckets_of(classes.n * bands)
    met = setjoin.pairs_of_keys(setjoin.keyed(classes.reps, banded(k, bands, rows), buckets), buckets)
    return setjoin.verified(classes.reps, met, threshold, classes.total / max(1, classes.n))


def minhash_classes(df: DataFrame, threshold: float, k: int = 256, n: int = 3, recall: float = 0.0, kind: str = "word", id_col: str = "doc_id", text_col: str = "text", fast: bool = False) -> tuple[DataFrame, DataFrame]:
    """Links (a, b, score) of classes of equal sets, and membership (id, rep): banded MinHash candidates, verified exactly."""
    classes = setjoin.Classes(shingle_sets(df, n, id_col, text_col, fast) if kind == "word" else shingle_hashes(df, n, kind, id_col, text_col, fast))
    return banded_pairs(classes, threshold, k, recall), classes.members


def minhash_pairs(df: DataFrame, threshold: float, k: int = 256, n: int = 3, recall: float = 0.0, **how) -> DataFrame:
    """The links of minhash_classes, and each copy with the smallest id of its set: enough for components, not all pairs (see `expand`)."""
    near, members = minhash_classes(df, threshold, k, n, recall, **how)
    return near.unionByName(stars(members))


def jaccard_links(classes: setjoin.Classes, threshold: float) -> DataFrame:
    """(a, b, score): all classes of equal sets that reach the threshold. Exact."""
    return setjoin.verified(classes.reps, setjoin.near_sets(classes, threshold), threshold, classes.total / max(1, classes.n))


def jaccard_classes(hashed: DataFrame | setjoin.Sets, threshold: float) -> tuple[DataFrame, DataFrame]:
    """Links (a, b, score) of all classes of equal sets that reach the threshold, and membership (id, rep). Exact."""
    classes = setjoin.Classes(hashed)
    return jaccard_links(classes, threshold), classes.members


def jaccard_join(hashed: DataFrame | setjoin.Sets, threshold: float) -> DataFrame:
    """All pairs (a < b, score) of sets at the threshold, copies too."""
    return expand(*jaccard_classes(hashed, threshold))


def containment_pairs(hashed: DataFrame, threshold: float) -> DataFrame:
    """(a, b, score) with score = shared / smaller set."""
    rows = hashed.select("id", F.size("hashes").alias("n"), F.explode("hashes").alias("h"))
    other = rows.select(F.col("id").alias("b"), F.col("n").alias("nb"), "h")
    shared = rows.withColumnRenamed("id", "a").join(other, "h").filter("a < b").groupBy("a", "b").agg(F.count("*").alias("same"), F.first(F.least("n", "nb")).alias("least"))
    return shared.withColumn("score", F.col("same") / F.col("least")).filter(F.col("score") >= threshold).select("a", "b", "score")


SIM_HALF = 32


def simhash(grams: Column) -> Column:
    """64-bit fingerprint of a bag of shingles: two 32-bit halves of their md5, every bit by weighted vote. Null without shingles.

    The votes are counted in one pass over the bag, each half's 32 counters packed in an array."""
    def half(part: int) -> Column:
        number = lambda g: F.conv(F.substring(F.md5(g.cast("binary")), 1 + 8 * part, 8), 16, 10).cast("long")
        numbers = F.transform(grams, number)
        vote = lambda b: F.aggregate(numbers, F.lit(0), lambda s, h: s + F.getbit(h, b).cast("int") * 2 - 1)
        bits = F.transform(F.sequence(F.lit(0), F.lit(SIM_HALF - 1)), lambda b: F.when(vote(b) > 0, F.call_function("shiftleft", F.lit(1).cast("long"), b)).otherwise(F.lit(0).cast("long")))
        return F.aggregate(bits, F.lit(0).cast("long"), lambda s, v: s.bitwiseOR(v))

    return F.when(F.size(grams) > 0, F.shiftleft(half(0), SIM_HALF).bitwiseOR(half(1)))


def simhash_votes(df: DataFrame, n: int = 5, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, fingerprint): the same numbers by a count within the row: nothing is shuffled.

    A run of texts becomes one array of code points; its distinct n-grams are hashed once, and each text's votes are the sum of its grams' bits."""

    def run(batches):
        for batch in batches:
            for piece in runs_of(batch, SIM_RUN):
                texts = piece.column(1).to_pylist()
                yield pa.RecordBatch.from_arrays([piece.column(0), pa.array(fingerprints(texts, n), pa.int64())], names=["id", "fingerprint"])

    return df.select(F.col(id_col).cast("long").alias("id"), F.lower(F.col(text_col)).alias("t")).mapInArrow(run, "id long, fingerprint long")


SIM_RUN = 1 << 20  # bytes of text


def runs_of(batch: pa.RecordBatch, most: int, column: int = 1):
    """The batch in slices with at most so many bytes in a text column; a longer text comes alone."""
    lens = pa.compute.fill_null(pa.compute.binary_length(batch.column(column)), 0).to_numpy(zero_copy_only=False).astype(np.int64)
    start, total = 0, 0
    for i, size in enumerate(lens.tolist()):
        if i > start and total + size > most:
            yield batch.slice(start, i - start)
            start, total = i, 0
        total += size
    if start < batch.num_rows:
        yield batch.slice(start)


def fingerprints(texts: list[str | None], n: int) -> list[int | None]:
    """64-bit fingerprints of texts that are lower-case already; null where a text has fewer than n characters."""
    whole = "".join(t or "" for t in texts)
    lens = np.array([len(t or "") for t in texts], np.int64)
    ends = np.cumsum(lens)
    points = np.frombuffer(whole.encode("utf-32-le", "surrogatepass"), np.uint32)
    if len(points) < n:
        return [None] * len(texts)
    owner = np.repeat(np.arange(len(texts)), lens)
    starts = np.flatnonzero(owner[: len(points) - n + 1] == owner[n - 1 :])
    letters, number = np.unique(points, return_inverse=True)
    codes = np.zeros(len(starts), np.int64)
    for k in range(n):  # grams numbered step by step, so any alphabet fits
        codes = codes * len(letters) + number[starts + k]
        if k < n - 1 and float(codes.max(initial=0) + 1) * len(letters) > 2**62:
            codes = np.unique(codes, return_inverse=True)[1]
    _, first, inverse = np.unique(codes, return_index=True, return_inverse=True)
    digests = b"".join(hashlib.md5(whole[i : i + n].encode("utf-8", "surrogatepass")).digest()[:8] for i in starts[first].tolist())
    bits = np.unpackbits(np.frombuffer(digests, np.uint8).reshape(-1, 8), axis=1)
    ones, of = np.zeros((len(texts), 64), np.int64), owner[starts]
    for k in range(0, len(starts), 1 << 16):
        part = of[k : k + (1 << 16)]
        edges = np.flatnonzero(np.concatenate([[True], part[1:] != part[:-1]]))
        ones[part[edges]] += np.add.reduceat(bits[inverse[k : k + (1 << 16)]], edges, axis=0, dtype=np.int64)
    grams = np.bincount(of, minlength=len(texts))
    found = np.packbits(2 * ones > grams[:, None], axis=1).view(">i8")[:, 0]
    return [int(v) if g else None for v, g in zip(found, grams, strict=True)]


def simhash_pairs(signed: DataFrame, limit: int) -> DataFrame:
    """All pairs within the Hamming limit by comparing everything: the definition, for small inputs."""
    other = signed.select(F.col("id").alias("b"), F.col("fingerprint").alias("fb"))
    far = hamming(F.col("fingerprint"), F.col("fb"))
    return signed.withColumnRenamed("id", "a").join(other, F.col("a") < F.col("b")).withColumn("distance", far).filter(F.col("distance") <= limit).select("a", "b", "distance")


def simhash_block_pairs(signed: DataFrame, limit: int, blocks: int | None = None) -> DataFrame:
    """The same pairs from blocks of bits: with more blocks than the limit, some block is equal. Equal fingerprints are compared once."""
    blocks = blocks or limit + 1
    if blocks <= limit:
        raise ValueError("a lossless search needs more blocks than the limit")
    edges = [64 * i // blocks for i in range(blocks + 1)]
    marks = signed.filter("fingerprint is not null").groupBy("fingerprint").agg(F.min("id").alias("rep"))
    keys = F.array(*(F.struct(F.lit(i).alias("no"), F.shiftrightunsigned("fingerprint", lo).bitwiseAND(F.lit((1 << (hi - lo)) - 1).cast("long")).alias("bits")) for i, (lo, hi) in enumerate(zip(edges, edges[1:], strict=False))))
    rows = marks.select(F.col("fingerprint").alias("id"), F.explode(keys).alias("k")).select("id", F.xxhash64("k.no", "k.bits").alias("key"))
    near = candidates(rows).select(F.col("a").alias("fingerprint"), F.col("b").alias("fb")).withColumn("distance", hamming(F.col("fingerprint"), F.col("fb"))).filter(F.col("distance") <= limit)
    near = near.unionByName(marks.select("fingerprint", F.col("fingerprint").alias("fb"), F.lit(0).alias("distance")))
    left, right = signed.select(F.col("id").alias("i"), "fingerprint"), signed.select(F.col("id").alias("j"), F.col("fingerprint").alias("fb"))
    full = near.join(left, "fingerprint").join(right, "fb").filter((F.col("distance") > 0) | (F.col("i") < F.col("j")))
    return full.select(F.least("i", "j").alias("a"), F.greatest("i", "j").alias("b"), "distance")
