"""Embedding near-duplicates by int8 tile products with rigorous error bounds.

Vectors of a label are dealt by a hash over blocks of about BLOCK rows, and each pair of blocks is a tile.
Every vector x of unit length is written as s * q + e with q in int8; the products of the q are whole numbers
(exact in float32 for up to 1,000 dimensions, float64 beyond). From |x.y - s_x s_y q_x.q_y| <= |e_y| |s_x q_x| + |e_x|
follows which pairs may reach the threshold. Tiles are gone through twice. First only the codes (a byte for each
component, and three numbers) are sent to them, which leaves the rows that may have a link in that tile; then these rows' vectors
are, and the pairs that the bound cannot rule out are computed in double precision. A tile hands on the number
of links of each vector and a spanning forest of its links, never the links themselves, so a large group of
copies costs rows in proportion to its size.

No tile can be skipped exactly on vectors without structure: with arccos .98 = .2 a tile of two cells goes only if the
angle between their centres exceeds both radii and .2, and in 64 dimensions radii are over 1.

Equal vectors are first taken together: one of them stands for all.

Defined cases: vectors that are null, empty, zero or hold a null or non-finite component, and rows with a
null label, link with nothing; vectors of different length do not link; rows
that repeat (id, label and vector) count as one vector and come back as often; rows of one id with
different vectors share a component, and n_links counts linked vectors. Null ids link with nothing. Empty
table: empty result. Further columns are ignored.
"""

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from twinsift.functions.shipping import by_value
from twinsift.llm.common import small_batches
from twinsift.operators.components import components
from twinsift.plans.checkpoints import cut

by_value(__name__)

THRESHOLD = 0.98
BLOCK = 4096
STRIP = 512  # rows of a block that are compared at a time
MAX_BROADCAST_LABELS = 20_000
SLACK = 1e-9  # more than the rounding of the float64 bounds themselves


def quantise(unit: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """int8 codes, scales, and the lengths of the quantised vectors and of their errors."""
    scale = np.maximum(np.abs(unit).max(1), 1e-30) / 127
    codes = np.rint(unit / scale[:, None]).astype(np.int8)
    near = codes * scale[:, None]
    return codes, scale, np.linalg.norm(near, axis=1), np.linalg.norm(unit - near, axis=1)


def linked_pairs(a: np.ndarray, b: np.ndarray, threshold: float, same: bool) -> tuple[np.ndarray, np.ndarray, int]:
    """Row pairs of two unit matrices with cosine >= threshold (i < j where same: the second then begins with the rows of the first), and how many were computed in full."""
    qa, sa, na, ea = quantise(a)
    qb, sb, nb, eb = quantise(b)
    kind = np.float32 if a.shape[1] * 127 * 127 < 1 << 24 else np.float64
    product = (qa.astype(kind) @ qb.astype(kind).T).astype(np.float64) * sa[:, None] * sb[None]
    bound = na[:, None] * eb[None] + ea[:, None] + SLACK
    i, j = np.nonzero(product + bound >= threshold)
    if same:
        i, j = i[i < j], j[i < j]
    keep = np.zeros(len(i), bool)
    for k in range(0, len(i), 65_536):
        keep[k : k + 65_536] = np.einsum("ij,ij->i", a[i[k : k + 65_536]], b[j[k : k + 65_536]]) >= threshold
    return i[keep], j[keep], len(i)


def forest(i: np.ndarray, j: np.ndarray, root: dict[int, int]) -> np.ndarray:
    """Which of the links (i, j) join two parts that were apart until then; root holds the parts and goes on from call to call."""
    used = np.zeros(len(i), bool)

    def top(x):
        while (y := root.get(x, x)) != x:
            root[x] = root.get(y, y)
            x = y
        return x

    for k, (x, y) in enumerate(zip(i.tolist(), j.tolist(), strict=True)):
        x, y = top(x), top(y)
        if x != y:
            root[max(x, y)] = min(x, y)
            used[k] = True
    return used


CODED = "code binary, scale double, near double, off double"


def code(vectors: DataFrame) -> DataFrame:
    """Each vector as int8 codes with their scale, and the lengths of the quantised vector and of its error; columns as in vectors, then those of CODED."""
    names = vectors.columns

    def run(batches):
        for batch in batches:
            if not batch.num_rows:
                continue
            lists = batch.column(names.index("embedding"))
            parts = [pa.array([None] * batch.num_rows, t) for t in (pa.binary(), pa.float64(), pa.float64(), pa.float64())]
            found: list = [[None] * batch.num_rows for _ in parts]
            sizes = pa.compute.list_value_length(lists).to_numpy(zero_copy_only=False)
            for n in np.unique(sizes).tolist():
                own = np.flatnonzero(sizes == n)
                x = unit_rows(lists.take(pa.array(own)).flatten().to_numpy(zero_copy_only=False).reshape(len(own), n))
                q, scale, near, off = quantise(x)
                for k, values in enumerate(([row.tobytes() for row in q], scale.tolist(), near.tolist(), off.tolist())):
                    for i, v in zip(own.tolist(), values, strict=True):
                        found[k][i] = v
            yield pa.RecordBatch.from_arrays([*batch.columns, *(pa.array(f, p.type) for f, p in zip(found, parts, strict=True))], names=[*names, "code", "scale", "near", "off"])

    schema = StructType(vectors.schema.fields[:])
    for column in CODED.split(", "):
        schema = schema.add(*column.split())
    return vectors.mapInArrow(run, schema)


def unit_rows(x: np.ndarray) -> np.ndarray:
    """Rows of unit length; scaled by the largest component first, so neither the square of a huge nor of a tiny one leaves the range."""
    x = x.astype(np.float64)
    x = x / np.abs(x).max(1, keepdims=True)
    return x / np.linalg.norm(x, axis=1, keepdims=True)


def _sides(rows: pa.Table) -> tuple[np.ndarray, np.ndarray, bool]:
    """Places of the rows of the two blocks of a tile, and whether both are the same block."""
    side, one = rows["block"].to_numpy(), rows["i"][0].as_py() == rows["j"][0].as_py()
    if one:
        return np.arange(len(side)), np.arange(len(side)), True
    return np.flatnonzero(side == rows["i"][0].as_py()), np.flatnonzero(side == rows["j"][0].as_py()), False


def _near_in_tile(rows: pa.Table, threshold: float) -> pa.Table:
    """The rows of a tile that int8 products cannot rule out: they may reach the threshold with a row of the other block."""
    left, right, one = _sides(rows)
    may = np.zeros(rows.num_rows, bool)
    if len(left) and len(right):
        q = np.frombuffer(b"".join(rows["code"].to_pylist()), np.int8).reshape(rows.num_rows, -1)
        scale, near, off = (rows[c].to_numpy() for c in ("scale", "near", "off"))
        kind = np.float32 if q.shape[1] * 127 * 127 < 1 << 24 else np.float64
        qr, sr, bound_r = q[right].astype(kind).T, scale[right], off[right]
        for k in range(0, len(left), STRIP):
            a = left[k : k + STRIP]
            top = (q[a].astype(kind) @ qr) * scale[a][:, None].astype(np.float64) * sr[None] + near[a][:, None] * bound_r[None] + off[a][:, None] + SLACK
            if one:
                top[np.arange(len(a)), k + np.arange(len(a))] = -np.inf
            hit = top >= threshold
            may[a] |= hit.any(1)
            may[right] |= hit.any(0)
    return rows.select(["label", "dim", "i", "j", "block", "mark", "check"]).filter(pa.array(may))


def _tile(rows: pa.Table, threshold: float) -> pa.Table:
    ids, many = rows["node"].to_numpy(), rows["many"].to_numpy()
    x = unit_rows(rows["embedding"].combine_chunks().flatten().to_numpy(zero_copy_only=False).reshape(len(ids), -1))
    left, right, one = _sides(rows)
    links = np.zeros(len(ids))
    a, b = [], []
    kept: dict[int, int] = {}
    for k in range(0, len(left), STRIP):
        own = left[k : k + STRIP]
        i, j, _ = linked_pairs(x[own], x[right[k:] if one else right], threshold, one)
        i, j = own[i], (right[k:] if one else right)[j]
        links += np.bincount(i, many[j], len(ids)) + np.bincount(j, many[i], len(ids))
        tree = forest(i, j, kept)
        a.append(i[tree])
        b.append(j[tree])
    none = np.zeros(0, np.int64)
    i, j = (np.concatenate(v) if v else none for v in (a, b))
    linked = np.flatnonzero(links)
    marks, checks = rows["mark"].to_numpy(), rows["check"].to_numpy()
    labels = rows["label"].take(pa.array(np.concatenate([i, linked])))
    n = np.concatenate([np.zeros(len(i), np.int64), links[linked].astype(np.int64)])
    return pa.table({"label": labels, "mark": np.concatenate([marks[i], marks[linked]]), "check": np.concatenate([checks[i], checks[linked]]), "a": pa.array(np.concatenate([ids[i], ids[linked]]), pa.int64()), "b": pa.array(ids[j].tolist() + [None] * len(linked), pa.int64()), "links": pa.array(n, pa.int64())})


def near_duplicates(vectors: DataFrame, threshold: float = THRESHOLD, block: int = BLOCK) -> DataFrame:
    """vec_id, n_links, component_id, kept for every row of (vec_id, embedding, label)."""
    small_batches(vectors.sparkSession)
    rows = vectors.select(F.col("vec_id").cast("long").alias("vec_id"), F.transform(F.col("embedding").cast("array<double>"), lambda x: x + F.lit(0.0)).alias("embedding"), "label")  # -0.0 becomes 0.0
    whole = F.forall("embedding", lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))) & F.exists("embedding", lambda x: x != 0)
    good = F.coalesce(whole, F.lit(False)) & F.col("label").isNotNull() & F.col("vec_id").isNotNull()
    # two hashes of other beginnings stand for a vector: 128 bits
    rows = rows.withColumn("mark", F.when(good, F.xxhash64("embedding", F.lit(1)))).withColumn("check", F.when(good, F.xxhash64(F.lit("check"), "embedding")))
    sound = rows.filter("mark is not null")

    # one row for equal vectors of a label; node is their smallest id
    apart = sound.groupBy("label", "mark", "check", "vec_id").agg(F.first("embedding").alias("embedding")).groupBy("label", "mark", "check").agg(F.min("vec_id").alias("node"), F.count("*").alias("many"), F.first("embedding").alias("embedding"))
    apart = cut(apart.withColumn("dim", F.size("embedding")))
    sizes = cut(apart.groupBy("label", "dim").agg(F.ceil(F.count("*") / block).cast("int").alias("blocks")))
    sizes = F.broadcast(sizes) if sizes.count() <= MAX_BROADCAST_LABELS else sizes
    blocked = apart.join(sizes, ["label", "dim"]).withColumn("block", F.pmod("mark", F.col("blocks")).cast("int"))

    coded = code(blocked.select("label", "dim", "mark", "check", "block", "blocks", "embedding")).drop("embedding")
    other = F.explode(F.sequence(F.lit(0), F.col("blocks") - 1))
    dealt = coded.select("label", "dim", "mark", "check", "block", *(c.split()[0] for c in CODED.split(", ")), other.alias("with"))
    dealt = dealt.withColumn("i", F.least("block", "with")).withColumn("j", F.greatest("block", "with")).drop("with")
    tile_of = "i int, j int, block int, mark long, check long"
    label = apart.schema["label"].dataType.simpleString()
    may = cut(dealt.groupBy("label", "dim", "i", "j").applyInArrow(lambda t: _near_in_tile(t, threshold), f"label {label}, dim int, {tile_of}"))
    full = may.join(apart, ["label", "dim", "mark", "check"])
    found = cut(full.groupBy("label", "dim", "i", "j").applyInArrow(lambda t: _tile(t, threshold), f"label {label}, mark long, check long, a long, b long, links long"))

    identity = ["label", "mark", "check"]
    links = found.filter("b is null").groupBy(*identity).agg(F.sum("links").alias("links"))
    edges = found.filter("b is not null").select("a", "b")
    same = sound.join(apart.filter("many > 1").select(*identity, "node"), identity).filter("vec_id <> node").select(F.col("vec_id").alias("a"), F.col("node").alias("b"))
    parts = components(edges.union(same))
    of_class = apart.select(*identity, "many").join(links, identity, "left")
    of_class = of_class.select(*identity, (F.coalesce("links", F.lit(0)) + F.col("many") - 1).alias("n_links"))
    out = rows.select("vec_id", *identity).join(of_class, identity, "left").join(parts.withColumnRenamed("id", "vec_id"), "vec_id", "left")
    component = F.coalesce("component", "vec_id")
    return out.select("vec_id", F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"), component.alias("component_id"), F.coalesce(component == F.col("vec_id"), F.lit(True)).alias("kept"))
