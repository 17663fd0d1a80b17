"""Quality classifier: a byte-level convolutional network in numpy.

A filter looks at WIDTH bytes and is a table of weights by place and byte (a
convolution over one-hot bytes). The filters run over the whole document; their
largest response in each of its overlapping chunks is kept, and the largest and
the mean over chunks go into one logistic unit. Learning follows the gradient
through the places of the maxima (Adam, fixed seed).

For scoring, the tables of two neighbouring places are added up once into tables by
byte pair, so a byte costs WIDTH / 2 look-ups and no multiplication.

Learned on a bounded sample: about FIT_ROWS labelled rows, none over FIT_BYTES;
every document is scored whole. Defined cases: null and empty texts are scored
as one padding window; rows without a usable label, a text or an id teach nothing; if
no row can teach, or all have one label, the score is the share of that label (0.5
without any). Repeated rows repeat; an empty table gives an empty one; further columns are ignored.
"""

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from twinsift.functions.shipping import by_value
from twinsift.llm.common import id_remainder, kept_columns, learning_rows, slices, small_batches, text_bytes, text_first

by_value(__name__)

WIDTH, FILTERS = 6, 24
CELL, CELLS_IN_CHUNK, CELLS_APART = 128, 4, 3  # chunks of 512 bytes, one every 384
FIT_ROWS, FIT_BYTES, STEPS, BATCH = 3000, 32_768, 700, 24
PAD = 256
THRESHOLD = 0.7


def chunk_starts(cells: int) -> np.ndarray:
    """First cells of a document's chunks; the last chunk ends with the document."""
    return np.arange(0, max(1, cells - CELLS_IN_CHUNK + CELLS_APART), CELLS_APART)[: max(1, -(-(cells - CELLS_IN_CHUNK) // CELLS_APART) + 1)]


class ByteCnn:
    def __init__(self, seed: int = 7):
        rng = np.random.default_rng(seed)
        self.rng = rng
        self.params = {
            "table": rng.normal(0, 0.3, (WIDTH, 257, FILTERS)).astype(np.float32),
            "bias": np.zeros(FILTERS, np.float32),
            "out": rng.normal(0, 0.1, 2 * FILTERS).astype(np.float32),
            "b": np.zeros(1, np.float32),
        }
        self.params["table"][:, PAD] = 0
        self.constant = None

    def fit(self, texts: list[bytes], labels: list[int], steps: int = STEPS) -> "ByteCnn":
        y = np.array(labels, np.float32)
        if len(y) == 0 or y.min() == y.max():
            self.constant = float(y.mean()) if len(y) else 0.5
            return self
        self.params["b"][0] = np.log(y.mean() / (1 - y.mean()))
        state = {k: (np.zeros_like(v), np.zeros_like(v)) for k, v in self.params.items()}
        order: list[int] = []
        for step in range(1, steps + 1):
            if len(order) < min(BATCH, len(y)):
                order = self.rng.permutation(len(y)).tolist()
            take, order = order[:BATCH], order[BATCH:]
            grads = self._gradients([texts[i] for i in take], y[take])
            rate = 0.01 * 0.5 * (1 + np.cos(np.pi * step / steps)) + 1e-4
            for k, g in grads.items():
                m, v = state[k]
                m += 0.1 * (g - m)
                v += 0.01 * (g * g - v)
                self.params[k] -= (rate * (m / (1 - 0.9**step)) / (np.sqrt(v / (1 - 0.99**step)) + 1e-8)).astype(np.float32)
        return self

    def _gradients(self, texts: list[bytes], y: np.ndarray) -> dict:
        table, bias, out, b = (self.params[k] for k in ("table", "bias", "out", "b"))
        grads = {k: np.zeros_like(v) for k, v in self.params.items()}
        for text, label in zip(texts, y, strict=True):
            cells = max(1, -(-len(text) // CELL))
            sym = np.full(cells * CELL + WIDTH - 1, PAD, np.int64)
            sym[: len(text)] = np.frombuffer(text, np.uint8)
            n = cells * CELL
            act = bias + sum(table[w][sym[w : w + n]] for w in range(WIDTH))
            act[max(1, len(text)) :] = -np.inf
            by_cell = act.reshape(cells, CELL, FILTERS)
            where = by_cell.argmax(1)
            top = np.take_along_axis(by_cell, where[:, None], 1)[:, 0]
            where = where + np.arange(cells)[:, None] * CELL
            starts = chunk_starts(cells)
            inside = np.minimum(starts[:, None] + np.arange(CELLS_IN_CHUNK), cells - 1)
            pick = top[inside].argmax(1)
            cell = np.take_along_axis(inside, pick, 1)
            peaks = np.take_along_axis(top, cell, 0)
            at = np.take_along_axis(where, cell, 0)
            live = np.maximum(peaks, 0)
            best = live.argmax(0)
            x = np.concatenate([live.max(0), live.mean(0)])
            p = 1 / (1 + np.exp(-(x @ out + b[0])))
            d = (p - label) / len(y)
            grads["out"] += d * x
            grads["b"] += d
            up = np.repeat((d * out[FILTERS:] / len(starts))[None], len(starts), 0)
            up[best, np.arange(FILTERS)] += d * out[:FILTERS]
            up *= peaks > 0
            grads["bias"] += up.sum(0)
            f = np.broadcast_to(np.arange(FILTERS), at.shape)
            for w in range(WIDTH):
                np.add.at(grads["table"][w], (sym[at + w], f), up)
        grads["table"][:, PAD] = 0
        return grads

    def prepare(self) -> "ByteCnn":
        """Tables by byte pair, in which 256 stands for padding."""
        t = self.params["table"]
        self.pairs = [(t[w][:, None, :] + t[w + 1][None, :, :]).reshape(257 * 257, FILTERS) for w in range(0, WIDTH, 2)]
        self.pairs[0] = self.pairs[0] + self.params["bias"]
        return self

    def cell_tops(self, data: np.ndarray) -> np.ndarray:
        """Largest response of each filter in each cell of one text."""
        n = max(1, len(data))
        sym = np.full(n + WIDTH - 1, PAD, np.int32)
        sym[: len(data)] = data
        pair = sym[:-1] * 257 + sym[1:]
        tops = []
        step = 64 * CELL
        for a in range(0, n, step):
            b = min(n, a + step)
            act = self.pairs[0][pair[a:b]]
            for k in range(1, WIDTH // 2):
                act += self.pairs[k][pair[a + 2 * k : b + 2 * k]]
            tops.append(np.maximum.reduceat(act, np.arange(0, b - a, CELL), axis=0))
        return np.concatenate(tops)

    def score(self, data: np.ndarray) -> float:
        if self.constant is not None:
            return self.constant
        tops = np.maximum(self.cell_tops(data), 0)
        starts = chunk_starts(len(tops))
        inside = np.minimum(starts[:, None] + np.arange(CELLS_IN_CHUNK), len(tops) - 1)
        live = tops[inside].max(1)
        z = float(np.concatenate([live.max(0), live.mean(0)]) @ self.params["out"] + self.params["b"][0])
        return float(1 / (1 + np.exp(-min(60.0, max(-60.0, z)))))


def fit_quality(docs: DataFrame, labels: DataFrame) -> ByteCnn:
    """Learn `quality` from the rows whose crc32(doc_id) mod 4 is not 2."""
    marks = labels.filter("doc_id is not null and quality in (0, 1)").groupBy("doc_id").agg(F.max("quality").alias("quality"))
    rows = docs.select("doc_id", "text").filter((id_remainder(4) != 2) & F.col("text").isNotNull()).join(marks, "doc_id")
    known = docs.select("doc_id").filter(id_remainder(4) != 2).join(marks, "doc_id")
    share = F.pmod(F.xxhash64("doc_id", F.lit("quality")), F.lit(1 << 40)) / float(1 << 40)
    many = known.count()
    if many > FIT_ROWS:  # chosen by id first, so only the chosen rows' texts are joined
        picked = F.col("doc_id").isNotNull() & (share < FIT_ROWS / many)
        marks = marks.filter(picked)
        rows = docs.select("doc_id", "text").filter((id_remainder(4) != 2) & picked & F.col("text").isNotNull()).join(F.broadcast(marks) if marks.count() <= 4 * FIT_ROWS else marks, "doc_id")
    got = learning_rows(rows, FIT_ROWS, FIT_BYTES, "quality")
    return ByteCnn().fit([r["text"].encode() for r in got], [int(r["quality"]) for r in got])


def score_quality(docs: DataFrame, model: ByteCnn, keep: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """The columns in keep, and the score of every whole text."""
    spark = docs.sparkSession
    small_batches(spark)
    sent = spark.sparkContext.broadcast((model.params, model.constant))

    def run(batches):
        net = ByteCnn()
        net.params, net.constant = sent.value
        net.prepare()
        for piece in slices(batches):
            data, offsets = text_bytes(piece.column(1))
            at = offsets.tolist()
            scores = [net.score(data[a:b]) for a, b in zip(at, at[1:], strict=False)]
            yield pa.RecordBatch.from_arrays([*kept_columns(piece, keep), pa.array(scores, pa.float64())], names=[*keep, "score"])

    rows = text_first(docs, F.lit(0), keep)
    return rows.mapInArrow(run, docs.select(*keep).schema.add("score", "double"))
