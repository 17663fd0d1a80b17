"""Exact duplicates: whole texts, titles, rows and shared passages."""

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from twinsift.functions.shipping import by_value
from twinsift.functions.text import words
from twinsift.operators.setjoin import lists_of, mixed  # by name: a module does not travel with a function
from twinsift.plans.checkpoints import cut

by_value(__name__)


def folded(text: Column) -> Column:
    return F.trim(F.regexp_replace(F.lower(text), r"\s+", " "))


def title(text: Column) -> Column:
    """The first line, folded."""
    return folded(F.split(text, "\n")[0])


def groups(df: DataFrame, key: Column, id_col: str = "doc_id") -> DataFrame:
    """(id, group_id, group_size) of rows whose key occurs at least twice; group_id is the smallest id. The key goes as a hash."""
    rows = df.filter(key.isNotNull()).select(F.col(id_col).alias("id"), F.sha2(key.cast("binary"), 256).alias("k"))
    many = rows.groupBy("k").agg(F.min("id").alias("group_id"), F.count("*").alias("group_size")).filter("group_size > 1")
    return rows.join(many, "k").select("id", "group_id", "group_size")


def row_groups(df: DataFrame, columns: list[str]) -> DataFrame:
    """Rows equal in the named columns: (key columns, copies) of those that repeat."""
    return df.groupBy(*columns).agg(F.count("*").alias("copies")).filter("copies > 1")


def token_windows(df: DataFrame, n: int, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, start, window, check): two 64-bit numbers of every run of n words, 128 bits together.

    Words are hashed once; the numbers of runs follow from one running sum each, so a word costs the same for any n."""
    toks = df.select(F.col(id_col).cast("long").alias("id"), F.transform(words(F.col(text_col)), lambda w: F.xxhash64(w)).alias("w")).filter(F.size("w") >= n)

    def run(batches):
        for batch in batches:
            lists = batch.column(1)
            flat = lists.flatten().to_numpy(zero_copy_only=False).view(np.uint64)
            offsets = lists.offsets.to_numpy().astype(np.int64) - lists.offsets.to_numpy()[0]
            ids = batch.column(0).to_numpy()
            for k in range(len(ids)):
                own = flat[offsets[k] : offsets[k + 1]]
                window, check = (rolled(own, n, base) for base in BASES)
                count = len(window)
                yield pa.RecordBatch.from_arrays([pa.array(np.full(count, ids[k])), pa.array(np.arange(count, dtype=np.int32)), pa.array(window), pa.array(check)], names=["id", "start", "window", "check"])

    return toks.mapInArrow(run, "id long, start int, window long, check long")


# Two odd multipliers: a run's number is the sum of its word hashes, each times the power of its place.
BASES = (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F)


def rolled(hashes: np.ndarray, n: int, base: int) -> np.ndarray:
    """The number of each run of n hashes, modulo 2 ** 64: the number of the last n, from running sums over powers of the base."""
    powers = np.full(len(hashes) + 1, base, np.uint64)
    powers[0] = 1
    up = np.cumprod(powers, dtype=np.uint64)
    powers[1:] = pow(base, -1, 1 << 64)
    down = np.cumprod(powers, dtype=np.uint64)
    mixed = hashes ^ (hashes >> np.uint64(29))
    total = np.concatenate([np.zeros(1, np.uint64), np.cumsum(mixed * up[: len(hashes)], dtype=np.uint64)])
    return ((total[n:] - total[:-n]) * down[: len(hashes) - n + 1]).view(np.int64)


#: Ids and anchors that are sent to all tasks; more of them are joined.
SENT = 1_000_000


def anchors(hashes: np.ndarray, n: int) -> np.ndarray:
    """For each run of n words the least number of the runs of half as many words in it: equal for equal runs, and mostly equal for neighbours."""
    half = max(1, n // 2)
    return np.lib.stride_tricks.sliding_window_view(mixed(rolled(hashes, half, BASES[0])).view(np.int64), n - half + 1).min(1)


def window_rates(docs: DataFrame, n: int, split: DataFrame) -> DataFrame:
    """(split, n, with_duplicate, percent) of `clustering.rates` for texts (doc_id, text) that share a run of n words; split: (id, split).

    Texts with equal words go as one. Every run has an anchor, which equal runs share; a text has far fewer anchors than runs, so anchors travel first,
    and then the runs of anchors that another text has too, all of them."""
    rows = docs.select(F.col("doc_id").cast("long").alias("id"), "text")
    toks = lambda df, *more: df.select("id", F.transform(words(F.col("text")), lambda w: F.xxhash64(w)).alias("w"), *more).filter(F.size("w") >= n)
    marked = cut(toks(rows).select("id", F.xxhash64("w").alias("mark"), F.xxhash64(F.lit("check"), "w").alias("check")))
    train = F.when(F.col("split") == "train", F.col("id"))
    reps = marked.join(split, "id").groupBy("mark", "check").agg(F.min("id").alias("rep"), F.min(train).alias("lo"), F.max(train).alias("hi"))
    reps = cut(reps)
    own = reps.select(F.col("rep").alias("id"), "lo", "hi")
    few = own.count() <= SENT

    def lead(batches):
        for batch in batches:
            flat, at = _words_of(batch.column(1))
            found = [np.unique(anchors(flat[a:b], n)) for a, b in zip(at[:-1], at[1:], strict=True)]
            yield pa.RecordBatch.from_arrays([pa.array(np.repeat(batch.column(0).to_numpy(), [len(f) for f in found])), pa.array(np.concatenate([np.zeros(0, np.int64), *found]))], names=["id", "anchor"])

    alone = own.select("id")
    led = toks(rows.join(F.broadcast(alone) if few else alone, "id", "left_semi")).mapInArrow(lead, "id long, anchor long").repartition("anchor")  # once, for both uses
    common = led.groupBy("anchor").agg(F.min("id").alias("x"), F.max("id").alias("y")).filter("x <> y").select("anchor")
    asked = cut(led.join(common, "anchor").groupBy("id").agg(F.collect_list("anchor").alias("anchors")).join(own, "id"))
    small = (asked.agg(F.sum(F.size("anchors"))).first()[0] or 0) <= SENT

    def runs(batches):
        for batch in batches:
            flat, at = _words_of(batch.column(1))
            wanted, ends = _words_of(batch.column(2))
            ids, lo, hi = (batch.column(k) for k in (0, 3, 4))
            for k in range(batch.num_rows):
                mine = flat[at[k] : at[k + 1]]
                hit = np.isin(anchors(mine, n), wanted[ends[k] : ends[k + 1]].view(np.int64))
                both = np.unique(np.stack([rolled(mine, n, base)[hit] for base in BASES]), axis=1)
                spot = pa.array(np.full(both.shape[1], k))
                yield pa.RecordBatch.from_arrays([pa.array(both[0]), pa.array(both[1]), ids.take(spot), lo.take(spot), hi.take(spot)], names=["window", "check", "id", "lo", "hi"])

    met = toks(rows.join(F.broadcast(asked) if small else asked, "id"), "anchors", "lo", "hi").mapInArrow(runs, "window long, check long, id long, lo long, hi long").repartition("window", "check")
    by = met.groupBy("window", "check").agg(F.min("lo").alias("wlo"), F.max("hi").alias("whi"), F.min("id").alias("x"), F.max("id").alias("y")).filter("x <> y")
    beside = met.select("window", "check", "id").join(by, ["window", "check"]).groupBy("id").agg(F.min("wlo").alias("wlo"), F.max("whi").alias("whi"))
    ends = reps.join(beside.withColumnRenamed("id", "rep"), "rep", "left").select("mark", "check", F.least("lo", "wlo").alias("lo"), F.greatest("hi", "whi").alias("hi"))
    hit = marked.join(ends, ["mark", "check"]).select("id", ((F.col("lo") != F.col("id")) | (F.col("hi") != F.col("id"))).cast("int").alias("hit"))
    out = split.join(hit, "id", "left").groupBy("split").agg(F.count("*").alias("n"), F.coalesce(F.sum("hit"), F.lit(0)).alias("with_duplicate"))
    return out.withColumn("percent", F.round(F.try_divide(100.0 * F.col("with_duplicate"), "n"), 6))


def _words_of(column: pa.ListArray) -> tuple[np.ndarray, np.ndarray]:
    """Numbers of a list column end to end, and where each row begins and the last ends."""
    flat, at = lists_of(column)
    return flat.view(np.uint64), at.astype(np.int64)


def shared_windows(windows: DataFrame) -> DataFrame:
    """Windows that occur in two documents or more, with (id, start)."""
    spread = windows.groupBy("window", "check").agg(F.min("id").alias("lo"), F.max("id").alias("hi")).filter("lo <> hi").select("window", "check")
    return windows.join(spread, ["window", "check"])


def shared_spans(windows: DataFrame, n: int) -> DataFrame:
    """(id, first, words): maximal runs of words of which every window of n is shared."""
    hit = shared_windows(windows).select("id", "start").distinct()
    order = Window.partitionBy("id").orderBy("start")
    runs = hit.withColumn("island", F.col("start") - F.row_number().over(order))
    return runs.groupBy("id", "island").agg(F.min("start").alias("first"), (F.max("start") - F.min("start") + n).alias("words")).drop("island")


def _leads(k: int):
    return lambda at: F.struct(at.alias("at"), F.xxhash64(F.array_join(F.slice("w", at, F.lit(k)), " ")).alias("key"))


def passage_hits(df: DataFrame, passages: DataFrame) -> DataFrame:
    """(doc_id, item_id): documents that hold a passage word for word. Passages go by their first words, so no document meets them all."""
    lead = 8
    known = passages.select("item_id", words(F.col("text")).alias("p")).filter("size(p) > 0")
    known = known.withColumn("k", F.least(F.size("p"), F.lit(lead))).withColumn("key", F.xxhash64(F.array_join(F.expr("slice(p, 1, k)"), " ")))
    w = df.select("doc_id", words(F.col("text")).alias("w"))
    sizes = [r["k"] for r in known.select("k").distinct().collect()]  # at most `lead` numbers
    found = None
    for k in sizes:  # positions meet the passages by a hash; only documents with a hit bring their words
        start = F.sequence(F.lit(1), F.size("w") - k + 1)
        places = F.transform(start, _leads(k))
        rows = w.filter(F.size("w") >= k).select("doc_id", F.explode(places).alias("x")).select("doc_id", "x.at", "x.key")
        some = known.filter(F.col("k") == k).select("key", "item_id")
        hit = rows.join(some, "key").select("doc_id", "at", "item_id")
        found = hit if found is None else found.union(hit)
    if found is None:
        return df.select("doc_id", F.lit(None).cast("long").alias("item_id")).limit(0)
    full = cut(found).join(w, "doc_id").join(known.select("item_id", "p"), "item_id")
    return full.filter(F.expr("slice(w, at, size(p))") == F.col("p")).select("doc_id", "item_id").distinct()
