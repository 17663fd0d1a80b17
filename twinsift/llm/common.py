"""What the operators of this subpackage share."""

import ctypes
import gc

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from twinsift.functions.shipping import by_value

by_value(__name__)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def id_remainder(n: int, col: str = "doc_id") -> Column:
    """crc32 of the id as text, modulo n: the folds of the learned operators."""
    return F.crc32(F.col(col).cast("string").cast("binary")) % n


BATCH_BYTES = 4 << 20


def small_batches(spark: SparkSession) -> None:
    """Arrow batches of at most BATCH_BYTES go to Python (a run-time setting): memory of the workers does not depend on how long texts are on average."""
    name = "spark.sql.execution.arrow.maxBytesPerBatch"
    if spark.conf.get(name, None) != str(BATCH_BYTES):
        spark.conf.set(name, str(BATCH_BYTES))


def hand_back() -> None:
    """Returns freed memory to the system: Python workers live on after a task, and their heaps add up from stage to stage."""
    gc.collect()
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):  # another C library
        pass


def slices(batches, max_bytes: int = 8 << 20):
    """Arrow batches whose second column is text or binary, cut to runs of at most max_bytes of it (a longer row comes alone). At the end memory is handed back."""
    try:
        yield from _slices(batches, max_bytes)
    finally:
        hand_back()


def _slices(batches, max_bytes: int):
    for batch in batches:
        lens = np.asarray(pa.compute.fill_null(pa.compute.binary_length(batch.column(1)), 0), dtype=np.int64)
        start, total = 0, 0
        for i, n in enumerate(lens.tolist()):
            if i > start and total + n > max_bytes:
                yield batch.slice(start, i - start)
                start, total = i, 0
            total += n
        if start < batch.num_rows:
            yield batch.slice(start)


def text_bytes(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """UTF-8 bytes of a text column one after another, and the offsets of its rows; null counts as empty."""
    filled = pa.compute.fill_null(column, "").cast(pa.large_binary())
    offsets = np.frombuffer(filled.buffers()[1], np.int64)[filled.offset : filled.offset + len(filled) + 1]
    data = filled.buffers()[2]
    whole = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    return whole[offsets[0] : offsets[-1]], offsets - offsets[0]


def text_first(docs: DataFrame, first: Column, keep: tuple[str, ...]) -> DataFrame:
    """A value, the text, and the other columns in keep: a text that is kept goes to Python once."""
    return docs.select(first.alias("_first"), docs["text"].alias("_text"), *(docs[c] for c in keep if c != "text"))


def kept_columns(piece: pa.RecordBatch, keep: tuple[str, ...]) -> list[pa.Array]:
    """The columns in keep of a batch of text_first."""
    rest = iter(range(2, piece.num_columns))
    return [piece.column(1) if c == "text" else piece.column(next(rest)) for c in keep]


LEARN_BYTES = 48 << 20  # text that learning may bring to the driver


def learning_rows(rows: DataFrame, max_rows: int, max_bytes: int, seed: str) -> list:
    """A sample of labelled rows for learning, on the driver: about max_rows of them, no text over max_bytes,
    LEARN_BYTES of text in expectation at most. Which rows is fixed by a hash of doc_id and text. Column text must be there; rows come ordered by id.

    Rows are chosen by a threshold on the hash, so their number and bytes scatter around the bound by a few deviations; of repeated rows one comes."""
    rows = rows.filter(F.octet_length("text") <= max_bytes)
    many, size = rows.agg(F.count("*"), F.coalesce(F.sum(F.octet_length("text")), F.lit(0))).first()
    share = min(1.0, max_rows / max(1, many), LEARN_BYTES / max(1, size))
    if share < 1:
        rows = rows.filter(F.pmod(F.xxhash64(F.col("doc_id"), F.col("text"), F.lit(seed)), F.lit(1 << 40)) < int(share * (1 << 40)))
    return sorted(rows.distinct().collect(), key=lambda r: (r["doc_id"], r["text"]))
