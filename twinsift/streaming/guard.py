"""Near-duplicate guards on streams: exact repeats, a stored index, recent arrivals, and windows over what was found."""

from collections.abc import Callable, Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from twinsift.functions.shipping import by_value
from twinsift.functions.text import md5_int, word_shingles
from twinsift.operators import sketches
from twinsift.plans.checkpoints import cut, ensure_checkpoint_dir

by_value(__name__)

RECALL = 0.9999  # of a pair right at the threshold
SENT = 1_000_000  # ids that are sent to all tasks
SCHEMA = "ts timestamp, doc_id long, user_id long, text string"


def arrivals(docs: DataFrame, events: DataFrame) -> DataFrame:
    """Documents with the clock of the event of the same number."""
    return docs.select("doc_id", "text").join(events.select(F.col("event_id").alias("doc_id"), "ts", "user_id"), "doc_id").select("ts", "doc_id", "user_id", "text")


def file_stream(spark: SparkSession, path: str, files_a_batch: int = 1, form: str = "parquet") -> DataFrame:
    """Arriving files of a fixed schema. Another source of the same schema (rate, Kafka) can take its place."""
    return spark.readStream.schema(SCHEMA).option("maxFilesPerTrigger", files_a_batch).format(form).load(path)


def exact(stream: DataFrame, lateness: str = "1 hour") -> DataFrame:
    """The first of equal texts within the watermark; state is one hash a text."""
    marked = stream.withColumn("text_hash", F.sha2(F.col("text").cast("binary"), 256)).withWatermark("ts", lateness)
    return marked.dropDuplicatesWithinWatermark(["text_hash"])


def near(batch: DataFrame, index: DataFrame, signed_index: DataFrame, threshold: float, k: int = 64) -> DataFrame:
    """(doc_id, match, score): for each arriving text its best stored text at the threshold, if any; a text is no match of itself.

    index: (id, hashes), signed_index: (key, id) band keys as they were written. Candidates are an equi-join on band keys, verified by the sets."""
    bands, rows = sketches.choose_bands(threshold, k, recall=RECALL)
    hashed = sketches.shingle_hashes(batch).filter("size(hashes) > 0")
    keys = sketches.band_keys(sketches.sign_hashes(hashed, k), bands, rows)
    met = keys.select(F.col("id").alias("a"), "key").join(signed_index.select(F.col("id").alias("b"), "key"), "key").filter("a <> b").select("a", "b").distinct()
    met = cut(met)
    stored = met.select(F.col("b").alias("id")).distinct()
    if stored.count() <= SENT:  # sets that no candidate needs stay where they are
        index = index.join(F.broadcast(stored), "id", "left_semi")
    left, right = hashed.select(F.col("id").alias("a"), F.col("hashes").alias("ha")), index.select(F.col("id").alias("b"), F.col("hashes").alias("hb"))
    same = F.size(F.array_intersect("ha", "hb"))
    scored = met.join(left, "a").join(right, "b").withColumn("score", F.try_divide(same, F.size("ha") + F.size("hb") - same)).filter(F.col("score") >= threshold)
    best = scored.groupBy("a").agg(F.max(F.struct("score", (-F.col("b")).alias("b"))).alias("x"))
    return best.select(F.col("a").alias("doc_id"), (-F.col("x.b")).alias("match"), F.col("x.score").alias("score"))


def signed(hashed: DataFrame, k: int = 64) -> DataFrame:
    return sketches.sign_hashes(hashed, k)


def keys_of(signatures: DataFrame, threshold: float, k: int = 64) -> DataFrame:
    """Band keys (key, id) that `near` seeks."""
    return sketches.band_keys(signatures, *sketches.choose_bands(threshold, k, recall=RECALL))


def build_index(docs: DataFrame, threshold: float, k: int = 64) -> tuple[DataFrame, DataFrame]:
    """Sets and band keys of stored texts, for `near`."""
    hashed = sketches.shingle_hashes(docs).filter("size(hashes) > 0")
    return hashed, keys_of(signed(hashed, k), threshold, k)


def recent(stream: DataFrame, threshold: float = 0.8, k: int = 32, ttl_ms: int = 3_600_000, lateness: str = "1 hour") -> DataFrame:
    """(doc_id, match, score) among recent arrivals: for each band key the state keeps the signatures of all texts whose time is at most ttl_ms behind the watermark.

    The estimate decides. Nothing is forgotten before its time, so a key's state grows with what arrives within it; a key that is silent so long loses its state.
    A pair that shares several keys comes once for each."""
    from pyspark.sql.streaming.state import GroupStateTimeout

    bands, rows = sketches.choose_bands(threshold, k)

    def remember(key: tuple, parts: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        now = state.getCurrentWatermarkMs()
        arrived = pd.concat(list(parts), ignore_index=True)
        ids, signatures = arrived["doc_id"].to_numpy(np.int64), np.array(arrived["signature"].tolist(), np.int64).reshape(len(arrived), -1)
        times = arrived["at"].to_numpy(np.int64)
        held = 0
        if state.exists:
            was_ids, was_times, was = (np.array(x, np.int64) for x in state.get)
            young = was_times > now - ttl_ms
            held = int(young.sum())
            ids, times, signatures = np.concatenate([was_ids[young], ids]), np.concatenate([was_times[young], times]), np.concatenate([was.reshape(len(was_ids), -1)[young], signatures])
        out = []
        for i in range(held, len(ids)):
            score = (signatures[:i] == signatures[i]).mean(1)
            out += [(int(ids[i]), int(ids[j]), float(score[j])) for j in np.flatnonzero((score >= threshold) & (ids[:i] != ids[i]))]
        state.update((ids.tolist(), times.tolist(), signatures.ravel().tolist()))
        state.setTimeoutTimestamp(max(int(times.max()), now) + ttl_ms)
        yield pd.DataFrame(out, columns=["doc_id", "match", "score"])

    hashed = F.array_distinct(F.transform(word_shingles(F.col("text"), 3), md5_int))
    timed = stream.filter("text is not null and ts is not null").withWatermark("ts", lateness).select("ts", F.col("doc_id").cast("long").alias("doc_id"), sketches.minhash(hashed, k).alias("signature")).filter("signature is not null")
    keys = F.transform(F.sequence(F.lit(0), F.lit(bands - 1)), lambda b: F.xxhash64(b, F.slice("signature", b * rows + 1, rows)))
    keyed = timed.select("ts", F.explode(keys).alias("key"), "doc_id", F.unix_millis("ts").alias("at"), "signature")
    schema = "ids array<long>, times array<long>, signatures array<long>"
    return keyed.groupBy("key").applyInPandasWithState(remember, "doc_id long, match long, score double", schema, "append", GroupStateTimeout.EventTimeTimeout)


def tumbling(found: DataFrame, width: str = "1 hour") -> DataFrame:
    """(start, n, repeats): texts and repeats in each window; found has ts and is_repeat 0/1."""
    by = found.groupBy(F.window("ts", width).alias("w")).agg(F.count("*").alias("n"), F.sum("is_repeat").alias("repeats"))
    return by.select(F.col("w.start").alias("start"), "n", "repeats")


def sliding(found: DataFrame, key: str, width: str = "1 hour", step: str = "15 minutes") -> DataFrame:
    by = found.groupBy(F.window("ts", width, step).alias("w"), key).agg(F.count("*").alias("n"))
    return by.select(F.col("w.start").alias("start"), key, "n")


def sessions(found: DataFrame, key: str, gap: str = "30 minutes") -> DataFrame:
    by = found.groupBy(F.session_window("ts", gap).alias("w"), key).agg(F.count("*").alias("n"))
    return by.select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), key, "n")


def interval_pairs(stream: DataFrame, minutes: int = 10, lateness: str = "1 hour") -> DataFrame:
    """(a, b): equal texts that arrive within so many minutes of each other: both buffers are bounded by the watermark."""
    h = F.sha2(F.col("text").cast("binary"), 256)
    left = stream.select(h.alias("h"), F.col("doc_id").alias("a"), F.col("ts").alias("t1")).withWatermark("t1", lateness)
    right = stream.select(h.alias("h2"), F.col("doc_id").alias("b"), F.col("ts").alias("t2")).withWatermark("t2", lateness)
    near_in_time = F.expr(f"t2 >= t1 - interval {minutes} minutes and t2 <= t1 + interval {minutes} minutes")
    return left.join(right, (F.col("h") == F.col("h2")) & near_in_time & (F.col("a") < F.col("b"))).select("a", "b")


def append_once(path: str) -> Callable[[DataFrame, int], None]:
    """A foreachBatch sink: a batch that runs again overwrites its own folder and nothing else."""
    def put(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/batch={number}")

    return put


def count_late(path: str, lateness_s: int = 3600) -> Callable[[DataFrame, int], None]:
    """A foreachBatch sink before the stateful step: rows behind the largest time seen so far, less the lateness, go to a side table.

    The largest time of each batch is written beside it, so a stream that starts again knows what came before; a batch that runs again sees the batches before it only."""

    def put(batch: DataFrame, number: int) -> None:
        spark = batch.sparkSession
        batch.agg(F.max("ts").alias("top")).withColumn("number", F.lit(number)).write.mode("overwrite").parquet(f"{path}/newest/of={number}")
        newest = spark.read.parquet(f"{path}/newest").filter(F.col("number") < number).agg(F.max("top")).first()[0]
        if newest is not None:
            late = batch.filter(F.col("ts") < F.lit(newest) - F.expr(f"interval {lateness_s} seconds"))
            late.write.mode("overwrite").parquet(f"{path}/late/batch={number}")

    return put


def drain(stream: DataFrame, folder: str, mode: str = "append", put: Callable | None = None) -> None:
    """Run a stream over all that is there, and stop. Progress is kept under the folder, so a second call goes on where the first ended."""
    ensure_checkpoint_dir(stream.sparkSession)
    writer = stream.writeStream.outputMode(mode).option("checkpointLocation", f"{folder}/progress").trigger(availableNow=True)
    query = writer.foreachBatch(put or append_once(f"{folder}/out")).start()
    query.awaitTermination()
