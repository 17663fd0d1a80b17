"""Trains the tiny preset on a bounded sample of the given documents: python -m twinsift.experiments.train_tiny [directory] [steps] [workers].

Data-parallel in a barrier stage. Documents whose id hashes to 0 modulo 10 are never learned from."""

import os
import sys

import numpy as np
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from twinsift.augment import policy
from twinsift.augment.lexicons import lexicons
from twinsift.catalogue.lexical import language_balanced, sentence_chunks
from twinsift.encoder import net, training
from twinsift.encoder.api import WEIGHTS
from twinsift.functions.text import md5_int
from twinsift.sources.tables import read_table

PAIRS, MOST = 5, 6000
SHIFT = 48  # characters: the second view of a chunk begins up to so much later, as chunks of an edited text do


def views(docs, c: net.Config, most: int = MOST, pairs: int = PAIRS) -> list[tuple[int, str, str]]:
    """(class id, text, text): corrupted copies of sentence chunks, `pairs` a chunk, of about `most` documents balanced by language."""
    train = docs.filter((F.col("n_chars") >= 16) & (md5_int(F.col("doc_id").cast("string")) % 10 != 0))
    some = language_balanced(train.select("doc_id", "lang", "text"), most)
    chunks = sentence_chunks(some.select("doc_id", "text"), size=c.chunk + SHIFT).filter("chunk_no < 2").join(some.select("doc_id", "lang"), "doc_id")
    numbered = chunks.select(F.xxhash64("doc_id", "chunk_no").alias("doc_id"), "lang", F.substring("chunk", 1, c.chunk + SHIFT).alias("text"))
    rows = numbered.join(F.broadcast(lexicons(some)), "lang").select("doc_id", "lang", "text", "donors", "all_words", "lang_words", "letters")
    rows = rows.withColumn("copy", F.explode(F.sequence(F.lit(1), F.lit(pairs)))).withColumn("chunk_id", F.col("doc_id")).withColumn("doc_id", F.xxhash64("doc_id", "copy"))
    late = F.pmod(F.xxhash64("doc_id", F.lit("shift")), F.least(F.lit(SHIFT), F.length("text"))).cast("int")
    begin = {"a": F.lit(1), "b": F.when(F.length("text") > c.chunk, late + 1).otherwise(1)}
    one, two = (policy.apply(rows, policy.TRAIN, s).select("doc_id", "chunk_id", F.substring(F.col("text"), begin[s], F.lit(c.chunk)).alias(s)) for s in ("a", "b"))
    got = one.join(two.drop("chunk_id"), "doc_id").select("chunk_id", "a", "b").collect()
    return sorted((r["chunk_id"], r["a"] or " ", r["b"] or " ") for r in got)


def main(sf_dir: str = "/root/testdata/sf0.1", steps: int = 1500, workers: int = 8) -> None:
    os.environ["OMP_NUM_THREADS"] = os.environ["OPENBLAS_NUM_THREADS"] = "1"  # of each worker, whose heap keeps the arrays of a step for the next
    os.environ["MALLOC_MMAP_THRESHOLD_"], os.environ["MALLOC_TRIM_THRESHOLD_"], os.environ["MALLOC_TOP_PAD_"] = str(1 << 32), str(1 << 33), str(1 << 28)
    spark = SparkSession.builder.master(f"local[{workers}]").config("spark.sql.shuffle.partitions", "8").config("spark.driver.memory", "6g").config("spark.ui.enabled", "false").getOrCreate()
    c = net.PRESETS["tiny"]
    got = views(read_table(spark, sf_dir, "documents"), c)
    held = {k for k in {v[0] for v in got} if k % 40 == 0}
    test, learn = [next(v for v in got if v[0] == k) for k in sorted(held)], [v for v in got if v[0] not in held]
    print(len(learn), "pairs; untrained recall", training.separation(net.init(c, 0), c, test), "of", len(test), flush=True)
    rows = spark.createDataFrame(learn, "class_id long, view_a string, view_b string")
    weights = training.fit_distributed(rows, c, steps, workers, size=48, peak=2e-2, every=10)
    print("recall", training.separation(weights, c, test))
    WEIGHTS.mkdir(exist_ok=True)
    np.savez_compressed(WEIGHTS / "tiny.npz", **{k: v.astype(np.float16) for k, v in weights.items()})
    spark.stop()


if __name__ == "__main__":
    main(*(f(x) for f, x in zip((str, int, int), sys.argv[1:], strict=False)))
