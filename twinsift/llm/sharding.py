"""Balanced label propagation: linked documents move to their neighbours' shards under quotas.

Documents with equal texts are linked through their group, so a link costs one
row and not one for each pair. A document's bucket is a hash of its id; the documents of
one group and bucket are alike, so the state is a table of cells (group,
bucket, shard, documents), small even for a group that holds a third of all rows.

In each round a cell looks at how many of its group are in each shard and asks
to move to the one, with room left, that has most. The requests to a shard share
its quota in proportion (a quota table of shards x shards is all the driver
sees); rounds go on until none asks to move. A move goes from fewer to more of a group, so
the squares of a group's counts only grow and the rounds come to an end; a group larger than many quotas fills
about one shard a round. Documents without links yield
their places: in the end every shard keeps its linked documents first and hands
the rest over to shards with free places, so counts differ by one at most.

Places are counted in two steps, within a small bucket of a shard and by running
sums over bucket counts, so no shard is sorted as a whole.

Defined cases: null text is the empty text; repeated rows are separate
documents of one group; a null id is hashed like an empty one; fewer documents than shards
leave shards empty; an empty table gives an empty one; further columns are ignored.
"""

import warnings

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from twinsift.plans.checkpoints import cut

SHARDS = 40
ROWS_PER_BUCKET = 4096


def hash01(*cols) -> Column:
    """A number in [0, 1) that the columns fix."""
    return F.pmod(F.xxhash64(*cols), F.lit(1 << 40)) / float(1 << 40)


def describe(docs: DataFrame) -> DataFrame:
    """doc_id, size, text_crc32, group, h: all that sharding needs of a document."""
    text = F.coalesce(docs["text"], F.lit("")).cast("binary")
    key = docs["doc_id"].cast("long")
    return docs.select(key.alias("doc_id"), (F.octet_length(text) + 16).cast("long").alias("size"), F.crc32(text).alias("text_crc32"), F.xxhash64(text, F.octet_length(text)).alias("group"), F.xxhash64(F.coalesce(key, F.lit(0)), F.lit("shard")).alias("h"))


def propagate(cells: DataFrame, quotas: list[int], rounds: int | None = None) -> tuple[DataFrame, list[dict]]:
    """cells: group, bucket, shard, n, all of groups of two or more documents. Returns the cells after the last round and what each round did.

    Rounds end when no cell asks to move; a warning tells if `rounds` (4 a shard and 32 more, if not given) were too few for that."""
    spark = cells.sparkSession
    report = []
    cells = cut(cells)
    rounds = 4 * len(quotas) + 32 if rounds is None else rounds
    for turn in range(rounds):
        held = {r["shard"]: r["n"] for r in cells.groupBy("shard").agg(F.sum("n").alias("n")).collect()}
        # a shard with a 32nd of its quota left counts as full, else a few last places would hold up the rest of a large group
        room = spark.createDataFrame([(s, max(0, q - q // 32 - held.get(s, 0))) for s, q in enumerate(quotas)], "shard int, room long")
        here = cells.groupBy("group", "shard").agg(F.sum("n").alias("near")).join(F.broadcast(room), "shard")
        rank = F.when(F.col("room") > 0, F.struct("near", F.xxhash64("group", "shard").alias("tie"), F.col("shard").alias("to")))
        best = here.groupBy("group").agg(F.max(rank).alias("best")).filter("best is not null").select("group", "best.*")
        asks = cells.join(here.select("group", "shard", F.col("near").alias("own")), ["group", "shard"]).join(best, "group")
        tie = F.xxhash64("group", "shard")
        asks = asks.withColumn("moves", (F.col("to") != F.col("shard")) & ((F.col("near") > F.col("own")) | ((F.col("near") == F.col("own")) & (F.col("tie") > tie))))
        asked = {r["to"]: r["n"] for r in asks.filter("moves").groupBy("to").agg(F.sum("n").alias("n")).collect()}
        if not asked:
            break
        part = spark.createDataFrame([(s, min(1.0, max(0, quotas[s] - held.get(s, 0)) / n)) for s, n in asked.items()], "to int, part double")
        going = cells.join(asks.filter("moves").select("group", "bucket", "shard", "to"), ["group", "bucket", "shard"], "left").join(F.broadcast(part), "to", "left")
        # a part of a cell's documents goes: the whole number below, and one more with the chance of the rest
        share = F.col("n") * F.coalesce("part", F.lit(0.0))
        gone = (F.floor(share) + (hash01("group", "bucket", "shard", F.lit(turn)) < share - F.floor(share)).cast("long")).cast("long")
        going = going.withColumn("gone", gone)
        split = going.select("group", "bucket", F.explode(F.array(F.struct("shard", (F.col("n") - F.col("gone")).alias("n")), F.struct(F.coalesce("to", "shard").alias("shard"), F.col("gone").alias("n")))).alias("c"))
        cells = cut(split.select("group", "bucket", "c.*").filter("n > 0").groupBy("group", "bucket", "shard").agg(F.sum("n").alias("n")))
        report.append({"round": turn, "asked": sum(asked.values()), "room": sum(max(0, q - held.get(s, 0)) for s, q in enumerate(quotas))})
    else:
        warnings.warn(f"documents still ask to move after {rounds} rounds", stacklevel=2)
    return cells, report


def numbered(rows: DataFrame, keys: list[str], small: list[str], order: list) -> DataFrame:
    """place: gapless from 0 within keys, in the order of the small buckets; no window is larger than one of these."""
    inner = Window.partitionBy(*keys, *small).orderBy(*order)
    rows = rows.withColumn("inner", F.row_number().over(inner) - 1)
    counts = rows.groupBy(*keys, *small).agg(F.count("*").alias("many"))
    before = Window.partitionBy(*keys).orderBy(*small).rowsBetween(Window.unboundedPreceding, -1)
    counts = counts.select(*keys, *small, F.coalesce(F.sum("many").over(before), F.lit(0)).alias("before"))
    return rows.join(counts, [*keys, *small]).withColumn("place", F.col("before") + F.col("inner")).drop("before", "inner")


def balance(docs: DataFrame, shards: int = SHARDS, rounds: int | None = None) -> DataFrame:
    """doc_id, size, text_crc32, group, shard, slot; counts of the shards differ by one at most."""
    spark = docs.sparkSession
    base = cut(describe(docs))
    total = base.count()
    fine = max(1, total // (shards * ROWS_PER_BUCKET) + 1)
    quotas = [total // shards + (s < total % shards) for s in range(shards)]
    base = base.withColumn("bucket", F.pmod("h", F.lit(shards * fine)).cast("int"))
    linked = base.groupBy("group").agg(F.count("*").alias("n")).filter("n > 1").select("group")
    cells = base.groupBy("group", "bucket").agg(F.count("*").alias("n")).join(linked, "group").select("group", "bucket", (F.col("bucket") % shards).alias("shard"), "n")
    cells, _ = propagate(cells, quotas, rounds)

    # Which documents of a group's bucket go where: by their place in it, against the running counts of its cells.
    upto = Window.partitionBy("group", "bucket").orderBy("shard").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    ends = cells.withColumn("end", F.sum("n").over(upto))
    ends = ends.groupBy("group", "bucket").agg(F.array_sort(F.collect_list(F.struct("end", "shard"))).alias("ends"))
    place = Window.partitionBy("group", "bucket").orderBy("h", "doc_id", "size")
    placed = base.join(ends, ["group", "bucket"], "left").withColumn("nth", F.row_number().over(place))
    own = F.filter("ends", lambda e: e["end"] >= F.col("nth"))[0]["shard"]
    placed = placed.withColumn("single", F.col("ends").isNull().cast("int")).withColumn("at", F.coalesce(own, F.col("bucket") % shards).cast("int")).drop("ends", "nth")
    placed = cut(placed.withColumn("small", F.floor(F.col("bucket") / shards).cast("int")))

    ranked = cut(numbered(placed, ["at"], ["single", "small"], ["group", "h", "doc_id", "size"]))
    counts = {r["at"]: r["n"] for r in ranked.groupBy("at").agg(F.count("*").alias("n")).collect()}
    over, free, given, room = [], [], 0, 0
    for s, q in enumerate(quotas):
        n = counts.get(s, 0)
        over.append((s, min(n, q), q, given))
        given += max(0, n - q)
        free.append((room, room + max(0, q - n), s, n))
        room += max(0, q - n)
    own = spark.createDataFrame(over, "at int, kept long, quota long, given long")
    gaps = spark.createDataFrame([f for f in free if f[1] > f[0]], "lo long, hi long, to int, has long")
    ranked = ranked.join(F.broadcast(own), "at")
    stays = ranked.filter("place < quota").withColumn("shard", F.col("at")).withColumn("slot", F.col("place"))
    moved = ranked.filter("place >= quota").withColumn("k", F.col("given") + F.col("place") - F.col("quota"))
    moved = moved.join(F.broadcast(gaps), (F.col("k") >= F.col("lo")) & (F.col("k") < F.col("hi"))).withColumn("shard", F.col("to")).withColumn("slot", F.col("has") + F.col("k") - F.col("lo"))
    names = ["doc_id", "size", "text_crc32", "group", "shard", "slot"]
    return stays.select(*names).unionByName(moved.select(*names))


def cut_links(placed: DataFrame) -> DataFrame:
    """One row: documents of groups of two or more, and how many of them are not in the shard that has most of their group."""
    by = placed.groupBy("group", "shard").agg(F.count("*").alias("n"))
    groups = by.groupBy("group").agg(F.sum("n").alias("n"), F.max("n").alias("most")).filter("n > 1")
    return groups.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("linked"), F.coalesce(F.sum(F.col("n") - F.col("most")), F.lit(0)).alias("apart"))
