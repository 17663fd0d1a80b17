"""Metric learning of the encoder: pair mining and loss, LAMB, schedule, and the loop on one or several workers."""

import base64
import pickle
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession

from twinsift.encoder.net import Config, bits, encode, forward, init
from twinsift.encoder.tape import Node, wrap
from twinsift.functions.shipping import by_value

by_value(__name__)

# The loss settings of the ablation: alpha, beta, lambda.
LOSS_GRID = tuple((a, b, lam) for a in (2, 4) for b in (20, 40) for lam in (0.5, 1.0))


def multi_similarity(v: Node, ids: np.ndarray, alpha: float = 4.0, beta: float = 40.0, lam: float = 0.5, eps: float = 0.1) -> Node:
    """Mean over anchors; pairs are mined by how far they are from the hardest of the other kind."""
    s = v @ v.swap()
    same = (ids[:, None] == ids[None]) & ~np.eye(len(ids), dtype=bool)
    other = ids[:, None] != ids[None]
    x = s.value
    worst = np.where(same, x, np.inf).min(1, keepdims=True)
    best = np.where(other, x, -np.inf).max(1, keepdims=True)
    pos, neg = (same & (x < best + eps)).astype(np.float32), (other & (x > worst - eps)).astype(np.float32)
    one = (((s - lam) * -alpha).exp() * pos).sum(1) + 1.0
    two = (((s - lam) * beta).exp() * neg).sum(1) + 1.0
    return ((one.log() * (1 / alpha)) + (two.log() * (1 / beta))).sum() * (1.0 / len(ids))


def cosine_rate(step: int, total: int, peak: float = 1e-3, end: float = 0.0) -> float:
    return end + (peak - end) * (1 + np.cos(np.pi * step / total)) / 2


class Lamb:
    def __init__(self, weights: dict, b1: float = 0.9, b2: float = 0.999, eps: float = 1e-6):
        self.b1, self.b2, self.eps, self.t = b1, b2, eps, 0
        self.m, self.v = ({k: np.zeros_like(x) for k, x in weights.items()} for _ in range(2))

    def step(self, weights: dict, grads: dict, rate: float) -> None:
        self.t += 1
        for k, g in grads.items():
            self.m[k] += (1 - self.b1) * (g - self.m[k])
            self.v[k] += (1 - self.b2) * (g * g - self.v[k])
            r = self.m[k] / (1 - self.b1**self.t) / (np.sqrt(self.v[k] / (1 - self.b2**self.t)) + self.eps)
            a, b = np.linalg.norm(weights[k]), np.linalg.norm(r)
            weights[k] -= (rate * (a / b if a > 0 and b > 0 else 1.0) * r).astype(np.float32)


def gradients(weights: dict, c: Config, texts: list[str], ids: np.ndarray, loss=(4.0, 40.0, 0.5, 0.1)) -> tuple[float, dict]:
    w = {k: Node(v, track=True) for k, v in weights.items()}
    length = min(c.chunk, max(1, max(map(len, texts))))
    x, mask = bits([t[: c.chunk] for t in texts], length)
    mask[:, 0] = 1
    out = multi_similarity(forward(w, c, x, mask), ids, *loss)
    out.backward()
    return float(out.value.ravel()[0]), {k: np.zeros_like(n.value) if n.grad is None else n.grad for k, n in w.items()}


def batches(views: list[tuple[int, str, str]], size: int, seed: int) -> Iterator[tuple[list[str], np.ndarray]]:
    """Endless: size pairs at a time, both views of a pair in the same batch."""
    rng = np.random.default_rng(seed)
    while True:
        order = rng.permutation(len(views))
        for a in range(0, len(order) - size + 1, size):
            own = [views[i] for i in order[a : a + size]]
            yield [t for _, x, y in own for t in (x, y)], np.array([k for k, _, _ in own for _ in (0, 1)])
        if len(order) < size:
            yield [t for _, x, y in views for t in (x, y)], np.array([k for k, _, _ in views for _ in (0, 1)])


def fit(views: list[tuple[int, str, str]], c: Config, steps: int, size: int = 32, seed: int = 0, peak: float = 1e-2, loss=(4.0, 40.0, 0.5, 0.1)) -> tuple[dict, list[float]]:
    """Weights and the loss of each step; views: (class id, text, text) in memory, a bounded sample."""
    weights, losses = init(c, seed), []
    lamb, source = Lamb(weights), batches(views, size, seed)
    for step in range(steps):
        texts, ids = next(source)
        value, grads = gradients(weights, c, texts, ids, loss)
        lamb.step(weights, grads, cosine_rate(step, steps, peak))
        losses.append(value)
    return weights, losses


def fit_distributed(views: DataFrame, c: Config, steps: int, workers: int = 2, size: int = 16, seed: int = 0, peak: float = 1e-2, every: int = 1) -> dict:
    """Data-parallel: a barrier stage whose tasks meet after each `every` steps; one of them hands on the result.

    every = 1: they share gradients and so keep equal weights. More (a meeting takes about a second, whatever is shared): each goes on by itself
    from step to step, and they go on from the mean of their weights. views: (class_id, view_a, view_b), dealt over the workers.
    A lost task restarts the stage, as barrier stages do."""

    def run(rows: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        from pyspark import BarrierTaskContext

        ctx = BarrierTaskContext.get()

        def mean(mine: dict | None) -> dict:
            got = [pickle.loads(base64.b64decode(x)) for x in ctx.allGather(base64.b64encode(pickle.dumps(mine)).decode())]
            got = [g for g in got if g is not None]
            return {k: sum(g[k] for g in got) / len(got) for k in got[0]} if got else {}

        own = [(int(k), a, b) for part in rows for k, a, b in zip(part["class_id"], part["view_a"], part["view_b"], strict=True)]
        weights = init(c, seed)
        lamb, source = Lamb(weights), batches(own, size, seed + ctx.partitionId()) if own else None
        for step in range(steps):
            mine = gradients(weights, c, *next(source))[1] if own else None
            if every == 1:
                mine = mean(mine)
            if mine:
                lamb.step(weights, mine, cosine_rate(step, steps, peak))
            if every > 1 and (step % every == every - 1 or step == steps - 1):
                weights = mean(weights if own else None) or weights
        if ctx.partitionId() == 0:
            yield pd.DataFrame({"name": list(weights), "shape": [list(v.shape) for v in weights.values()], "value": [v.ravel().tolist() for v in weights.values()]})

    dealt = views.select("class_id", "view_a", "view_b").repartition(workers)
    return from_rows(dealt.mapInPandas(run, "name string, shape array<int>, value array<float>", barrier=True))


def save(spark: SparkSession, weights: dict, path: str) -> None:
    rows = [(k, list(v.shape), v.ravel().tolist()) for k, v in weights.items()]
    spark.createDataFrame(rows, "name string, shape array<int>, value array<float>").coalesce(1).write.mode("overwrite").parquet(path)


def from_rows(df: DataFrame) -> dict:
    return {r["name"]: np.array(r["value"], np.float32).reshape(r["shape"]) for r in df.collect()}


def load(spark: SparkSession, path: str) -> dict:
    return from_rows(spark.read.parquet(path))


def separation(weights: dict, c: Config, views: list[tuple[int, str, str]]) -> float:
    """Recall@1 of second views among all second views: a quick held-out measure."""
    a, b = (encode(weights, c, [v[k][: c.chunk] for v in views]) for k in (1, 2))
    return float(((a @ b.T).argmax(1) == np.arange(len(views))).mean())


__all__ = ["LOSS_GRID", "Lamb", "batches", "cosine_rate", "fit", "fit_distributed", "gradients", "load", "multi_similarity", "save", "separation", "wrap"]
