"""Mixing sources to target weights by Pareto order sampling.

Sources in code-point order (null last) weigh 1, 2, 3, repeating, and share the
words of the whole input; a target stops at CAP times its source's size and the
excess is shared again by weight. In closed form: with sources ordered by size
over weight, the common level is the largest of (words left) / (weight left),
and a target is the smaller of its cap and level times weight.

A source's target divided by its size gives every document so many certain
whole copies; the rest is sampled. Each document has the uniform number u of
its id and the seed; documents are ranked by odds(u) over the odds of their
inclusion, which are the source's odds times (size / mean size) ** TILT, and
taken from the front until the source's remaining words are used up (nearest
document). So the sample has a fixed size in words and reruns agree.

No source is ever sorted as a whole: a histogram of the ranking value finds the
interval in which the cut falls, a second one the part of that interval, and only the rows of that part are ordered. Both
histograms have about as many steps as the square root of the number of rows. Rows of equal source, odds, id and size are alike:
the part holds one row for them and their number, so ties, however many, are no large window. Running sums over
all sources go by ranges of sources, so many sources are no single task either.

Defined cases: null or blank text has size 0 and is never taken; a null source
is one source, the last; repeated rows are sampled as separate documents (ties
in rank are alike, so which of them is taken makes no difference); an empty
table gives an empty one; further columns are ignored.
"""

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from twinsift.plans.checkpoints import cut

CAP = 3
SEED = "mix-1"
RUN = 10_000  # rows that are alike and are put out by one task at most
MAX_BROADCAST_SOURCES = 20_000
SPACE = r"[\x20\x09-\x0D]+"


def word_count(text: Column) -> Column:
    """How many runs of other characters than ASCII white space."""
    inner = F.btrim(F.coalesce(text, F.lit("")), F.lit(" \t\n\x0b\f\r"))
    return F.when(inner == "", F.lit(0)).otherwise(F.size(F.split(inner, SPACE))).cast("long")


def uniform(doc_id: Column, seed: str) -> Column:
    """A number between 0 and 1, both excluded, that the id and the seed fix."""
    digits = F.substring(F.md5(F.concat(F.coalesce(doc_id.cast("string"), F.lit("")), F.lit(":" + seed)).cast("binary")), 1, 13)
    return (F.conv(digits, 16, 10).cast("double") + 0.5) / float(1 << 52)


def running(rows: DataFrame, order: list[Column], sums: dict[str, str]) -> DataFrame:
    """Sums of columns over all earlier rows of a total order, as new columns {name: column}; whole numbers.

    Rows are dealt by ranges of the order: sums within a range, and those of the ranges before it, which are one row each."""
    parts = rows.sparkSession.sparkContext.defaultParallelism
    ranged = cut(rows.repartitionByRange(parts, *order).withColumn("range", F.spark_partition_id()))
    before = Window.partitionBy("range").orderBy(*order).rowsBetween(Window.unboundedPreceding, -1)
    totals = ranged.groupBy("range").agg(*(F.sum(c).alias(n) for n, c in sums.items()))
    ahead = Window.orderBy("range").rowsBetween(Window.unboundedPreceding, -1)  # `parts` rows
    starts = totals.select("range", *(F.coalesce(F.sum(n).over(ahead), F.lit(0)).alias(f"start_{n}") for n in sums))
    for n, c in sums.items():
        ranged = ranged.withColumn(n, F.coalesce(F.sum(c).over(before), F.lit(0)))
    done = ranged.join(F.broadcast(starts), "range")
    return done.select(*rows.columns, *((F.col(n) + F.col(f"start_{n}")).alias(n) for n in sums))


def source_targets(sized: DataFrame) -> DataFrame:
    """source, source_size, mean_size, target; input (source, size)."""
    by = cut(sized.groupBy("source").agg(F.sum("size").alias("source_size"), F.sum((F.col("size") > 0).cast("long")).alias("filled")))
    by = running(by.withColumn("one", F.lit(1)), [F.col("source").asc_nulls_last()], {"number": "one"})
    by = by.withColumn("weight", F.col("number") % 3 + 1).withColumn("cap", CAP * F.col("source_size"))
    by = by.withColumn("ratio", F.col("cap") / F.col("weight"))
    by = running(by, [F.col("ratio"), F.col("source").asc_nulls_last()], {"caps": "cap", "weights": "weight"})
    total = by.agg(F.sum("source_size").alias("total_size"), F.sum("weight").alias("total_weight"))
    by = cut(by.crossJoin(F.broadcast(total)))  # one row
    level = by.agg(F.max((F.col("total_size") - F.col("caps")).cast("double") / (F.col("total_weight") - F.col("weights"))).alias("level"))
    target = F.least(F.col("cap").cast("double"), F.col("level") * F.col("weight"))
    return by.crossJoin(F.broadcast(level)).select("source", "source_size", F.try_divide("source_size", "filled").alias("mean_size"), target.alias("target"))


def _cut_of(counts: DataFrame, step: str) -> DataFrame:
    """source, cut_at, cut_before: the step in which a source's rest is used up, and the words before it. counts: source, step, words, rest, base."""
    upto = Window.partitionBy("source").orderBy(step).rowsBetween(Window.unboundedPreceding, -1)
    counts = counts.withColumn("before", F.col("base") + F.coalesce(F.sum("words").over(upto), F.lit(0)))
    return cut(counts.filter("before <= rest and before + words > rest").select("source", F.col(step).alias("cut_at"), F.col("before").alias("cut_before")))


def mix(docs: DataFrame, seed: str = SEED) -> DataFrame:
    """doc_id, source, size, source_size, target, copies, taken for every row."""
    sized = cut(docs.select(docs["doc_id"].cast("long").alias("doc_id"), docs["source"], word_count(docs["text"]).alias("size")))
    sources = cut(source_targets(sized))
    small = sources.count() <= MAX_BROADCAST_SOURCES
    near = (lambda df: F.broadcast(df)) if small else (lambda df: df)
    whole = F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(0)
    sources = sources.withColumn("whole", whole).withColumn("rest", F.col("target") - F.col("whole") * F.col("source_size"))
    sources = sources.withColumn("share", F.try_divide("rest", "source_size"))

    def beside(left: DataFrame, right: DataFrame) -> DataFrame:
        right = right.withColumnRenamed("source", "of_source")
        return left.join(near(right), F.col("source").eqNullSafe(F.col("of_source")), "left").drop("of_source")

    u = uniform(F.col("doc_id"), seed)
    tilted = F.sqrt(F.try_divide("size", "mean_size"))  # the power TILT is one half
    rows = beside(sized, sources).withColumn("odds", F.when(F.col("size") > 0, u / (1 - u) / tilted))
    rows = rows.withColumn("rank_value", F.try_divide(F.col("odds") * (1 - F.col("share")), "share"))
    steps = max(16, math.isqrt(sized.count()) + 1)
    rows = rows.withColumn("fine", F.floor(F.col("odds") / (1 + F.col("odds")) * steps * steps).cast("long")).withColumn("coarse", F.floor(F.col("fine") / steps).cast("long"))

    counts = rows.filter("size > 0").groupBy("source", "coarse").agg(F.sum("size").alias("words"), F.first("rest").alias("rest"))
    first = _cut_of(counts.withColumn("base", F.lit(0).cast("long")), "coarse")
    inside = beside(rows.filter("size > 0"), first).filter("coarse = cut_at").groupBy("source", "fine").agg(F.sum("size").alias("words"), F.first("rest").alias("rest"), F.first("cut_before").alias("base"))
    cuts = _cut_of(inside, "fine")

    rows = beside(rows, cuts)
    close = F.coalesce(F.col("fine") == F.col("cut_at"), F.lit(False))
    clear = rows.filter(~close).withColumn("extra", F.coalesce((F.col("fine") < F.col("cut_at")).cast("int"), (F.col("rest") >= F.col("source_size")).cast("int"), F.lit(0)))
    alike = ["source", "odds", "doc_id", "size"]
    held = [c for c in ("source_size", "target", "whole", "rest", "cut_before", "rank_value")]
    groups = rows.filter(close).groupBy(*alike).agg(F.count("*").alias("n"), *(F.first(c).alias(c) for c in held))
    order = Window.partitionBy("source").orderBy("odds", "doc_id", "size").rowsBetween(Window.unboundedPreceding, -1)
    base = F.col("cut_before") + F.coalesce(F.sum(F.col("n") * F.col("size")).over(order), F.lit(0))
    # how many of a group's n rows are taken: the last that is nearer to the rest with it than without it
    fits = lambda k: 2 * (F.col("base") + k * F.col("size")) - F.col("size") <= 2 * F.col("rest")
    guess = F.floor((2 * (F.col("rest") - F.col("base")) + F.col("size")) / (2 * F.col("size")))
    groups = groups.withColumn("base", base).withColumn("k", F.greatest(F.lit(0), F.least("n", guess)))
    groups = groups.withColumn("k", F.when(F.col("k") > 0, F.when(fits(F.col("k")), F.col("k")).otherwise(F.col("k") - 1)).otherwise(F.lit(0)))
    groups = groups.withColumn("k", F.when((F.col("k") < F.col("n")) & fits(F.col("k") + 1), F.col("k") + 1).otherwise(F.col("k")))
    runs = groups.withColumn("run", F.explode(F.sequence(F.lit(0).cast("long"), F.col("n") - 1, F.lit(RUN).cast("long")))).repartition(F.col("source"), F.col("doc_id"), F.col("run"))
    each = runs.withColumn("at", F.explode(F.sequence(F.col("run"), F.least(F.col("run") + RUN, F.col("n")) - 1)))
    out = clear.select(*alike, "source_size", "target", "whole", "rank_value", "extra").unionByName(each.select(*alike, "source_size", "target", "whole", "rank_value", (F.col("at") < F.col("k")).cast("int").alias("extra")))
    copies = F.when(F.col("size") > 0, F.col("whole") + F.col("extra")).otherwise(0).cast("long")
    return out.select("doc_id", "source", "size", "source_size", "target", copies.alias("copies"), (copies * F.col("size")).cast("long").alias("taken"), "rank_value")


ORACLE = rf"""
with sized as (select doc_id, source, len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+'))::bigint as size from documents),
named as (select source, sum(size)::bigint as source_size, count(*) filter (size > 0) as filled from sized group by 1),
weighed as (select *, (row_number() over (order by source asc nulls last) - 1) % 3 + 1 as weight, {CAP} * source_size as cap from named),
levels as (select *, (sum(source_size) over () - coalesce(sum(cap) over (order by cap / weight, source asc nulls last rows between unbounded preceding and 1 preceding), 0))::double
  / sum(weight) over (order by cap / weight, source asc nulls last rows between current row and unbounded following) as level from weighed),
targets as (select source, source_size, source_size / filled as mean_size, least(cap::double, max(level) over () * weight) as target from levels),
wholes as (select *, case when source_size > 0 then floor(target / source_size) else 0 end as whole from targets),
drawn as (select doc_id, d.source, size, source_size, mean_size, target, whole, target - whole * source_size as rest,
  (('0x' || substr(md5(coalesce(doc_id::varchar, '') || ':{SEED}'), 1, 13))::bigint::double + 0.5) / {float(1 << 52)} as u
  from sized d join wholes w on d.source is not distinct from w.source),
ranked as (select *, sum(size) over (partition by source order by case when size > 0 then u / (1 - u) / sqrt(size / mean_size) end nulls last, doc_id, size rows between unbounded preceding and current row) as upto from drawn)
select doc_id, size, source_size, target, (case when size > 0 then (whole + (2 * upto - size <= 2 * rest)::int) * size else 0 end)::bigint as taken from ranked
"""
