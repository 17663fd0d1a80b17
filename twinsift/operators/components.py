"""Connected components of an edge table by alternating star contraction."""

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from twinsift.functions.shipping import by_value
from twinsift.plans.checkpoints import cut

by_value(__name__)

SMALL = 500_000  # edges: 8 MB


def _large_star(e: DataFrame) -> DataFrame:
    """Every larger neighbour of a node is linked with the node's smallest neighbour (or itself)."""
    both = e.select("u", "v").union(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
    least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
    return both.filter("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v"))


def _small_star(e: DataFrame) -> DataFrame:
    """Every smaller neighbour of a node, and the node, is linked with the smallest of them."""
    down = e.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v"))
    least = down.groupBy("u").agg(F.min("v").alias("m"))
    rest = down.join(least, "u").filter("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
    return rest.union(least.select("u", F.col("m").alias("v")))


def _union_find(batches):
    """All components of a small edge table, in one task on an executor."""
    root: dict[int, int] = {}

    def top(x):
        while (y := root.setdefault(x, x)) != x:
            root[x] = root.setdefault(y, y)
            x = y
        return x

    for batch in batches:
        for u, v in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
            u, v = top(u), top(v)
            if u != v:
                root[max(u, v)] = min(u, v)
    ids = np.fromiter(root, np.int64, len(root))
    found = np.fromiter(map(top, ids.tolist()), np.int64, len(ids))
    yield pa.RecordBatch.from_arrays([pa.array(ids), pa.array(found)], names=["id", "component"])


def components(edges: DataFrame, small: int = SMALL, max_rounds: int = 60) -> DataFrame:
    """(id, component) of every node in edges (a, b); component is the smallest id that it can reach.

    Up to `small` edges (counted first) go through one task of an executor; more of them go through rounds
    of joins, with the same result. Rounds stop when the edge table no longer changes; each is written to the checkpoint
    folder. Only two numbers a round reach the driver. Self loops keep a node alone; null ends are ignored."""
    ends = edges.select(F.col("a").cast("long").alias("u"), F.col("b").cast("long").alias("v")).filter("u is not null and v is not null")
    ends = cut(ends)
    if ends.count() <= small:
        return cut(ends.coalesce(1).mapInArrow(_union_find, "id long, component long"))
    e, was = cut(ends.filter("u <> v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct()), None
    for _ in range(max_rounds):
        e = cut(_small_star(_large_star(e)).distinct())
        now = tuple(e.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first())
        if now == was:
            break
        was = now
    else:
        raise RuntimeError(f"components: no fixed point after {max_rounds} rounds")
    roots = e.select(F.col("v").alias("id")).distinct().select("id", F.col("id").alias("component"))
    labelled = e.select(F.col("u").alias("id"), F.col("v").alias("component")).union(roots)
    alone = ends.filter("u = v").select(F.col("u").alias("id"), F.col("u").alias("component")).join(labelled, "id", "left_anti").distinct()
    return labelled.union(alone)
