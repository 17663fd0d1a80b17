"""Accuracy and cost measures as small aggregates."""

import time

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

DIGITS = 6


def recall_at(results: DataFrame, truth: DataFrame, k: int = 1, by: tuple[str, ...] = ()) -> DataFrame:
    """Share of queries whose target is in the first k; queries without any result count as missed. truth: query_id, target_id and slices."""
    hit = results.filter(F.col("rank") <= k).select("query_id", "target_id").distinct().withColumn("hit", F.lit(1))
    rows = truth.join(hit, ["query_id", "target_id"], "left")
    return rows.groupBy(*by).agg(F.count("*").alias("queries"), F.round(F.avg(F.coalesce("hit", F.lit(0))), DIGITS).alias("recall"))


def macro(by_slice: DataFrame, column: str = "recall") -> DataFrame:
    return by_slice.agg(F.round(F.avg(column), DIGITS).alias("mean"))


def _pairs_of(n):
    return n * (n - 1) / 2


def contingency(a: DataFrame, b: DataFrame) -> DataFrame:
    """(x, y, n): how many ids have cluster x in the first labelling and y in the second; inputs (id, cluster)."""
    both = a.select("id", F.col("cluster").alias("x")).join(b.select("id", F.col("cluster").alias("y")), "id")
    return both.groupBy("x", "y").agg(F.count("*").alias("n"))


def ari(a: DataFrame, b: DataFrame) -> DataFrame:
    """Adjusted Rand index from the contingency table alone."""
    t = contingency(a, b)
    s = t.agg(F.sum(_pairs_of(F.col("n"))).alias("s"), F.sum("n").alias("total"))
    sx = t.groupBy("x").agg(F.sum("n").alias("n")).agg(F.sum(_pairs_of(F.col("n"))).alias("sx"))
    sy = t.groupBy("y").agg(F.sum("n").alias("n")).agg(F.sum(_pairs_of(F.col("n"))).alias("sy"))
    one = s.crossJoin(sx).crossJoin(sy)  # one row each
    chance = F.coalesce(F.try_divide(F.col("sx") * F.col("sy"), _pairs_of(F.col("total"))), F.lit(0.0))
    value = F.coalesce(F.try_divide(F.col("s") - chance, (F.col("sx") + F.col("sy")) / 2 - chance), F.lit(1.0))
    return one.select(F.round(value, DIGITS).alias("ari"))


def v_measure(truth: DataFrame, found: DataFrame, beta: float = 1.0) -> DataFrame:
    """Homogeneity, completeness and their weighted harmonic mean."""
    t = contingency(truth, found)
    total = t.agg(F.sum("n").alias("total"))
    nx, ny = t.groupBy("x").agg(F.sum("n").alias("nx")), t.groupBy("y").agg(F.sum("n").alias("ny"))
    rows = t.join(nx, "x").join(ny, "y").crossJoin(F.broadcast(total))
    share = F.col("n") / F.col("total")
    cond = rows.agg(-F.sum(share * F.log(F.col("n") / F.col("ny"))), -F.sum(share * F.log(F.col("n") / F.col("nx")))).toDF("hxy", "hyx")
    entropy = lambda d, c, name: d.crossJoin(F.broadcast(total)).agg((-F.sum(F.col(c) / F.col("total") * F.log(F.col(c) / F.col("total")))).alias(name))
    one = cond.crossJoin(entropy(nx, "nx", "hx")).crossJoin(entropy(ny, "ny", "hy"))
    h = F.when(F.col("hx") > 1e-12, 1 - F.col("hxy") / F.col("hx")).otherwise(1.0)
    c = F.when(F.col("hy") > 1e-12, 1 - F.col("hyx") / F.col("hy")).otherwise(1.0)
    v = F.coalesce(F.try_divide((1 + beta) * h * c, beta * h + c), F.lit(0.0))
    return one.select(F.round(h, DIGITS).alias("homogeneity"), F.round(c, DIGITS).alias("completeness"), F.round(v, DIGITS).alias("v_measure"))


def clustering_scores(t: DataFrame, *by: str) -> DataFrame:
    """(by..., homogeneity, completeness, v_measure, ari) of many labellings in one pass, as `v_measure` and `ari` give them for one; t: contingency tables (by..., x, y, n), x of the truth."""
    nx, ny = (t.groupBy(*by, c).agg(F.sum("n").alias(f"n{c}")) for c in ("x", "y"))
    log = lambda c: F.sum(F.col(c) * F.log(F.col(c).cast("double")))
    both = t.join(nx, [*by, "x"]).join(ny, [*by, "y"]).groupBy(*by).agg(
        F.sum("n").alias("total"), F.sum(_pairs_of(F.col("n"))).alias("s"), (-F.sum(F.col("n") * F.log(F.col("n") / F.col("ny")))).alias("hxy"), (-F.sum(F.col("n") * F.log(F.col("n") / F.col("nx")))).alias("hyx")
    )
    ends = [d.groupBy(*by).agg(F.sum(_pairs_of(F.col(c))).alias(f"s{c}"), log(c).alias(f"l{c}")) for d, c in ((nx, "nx"), (ny, "ny"))]
    one = both.join(ends[0], list(by)).join(ends[1], list(by))
    entropy = lambda c: F.log(F.col("total").cast("double")) - F.col(c) / F.col("total")
    share = lambda part, whole: F.when(entropy(whole) > 1e-12, 1 - F.col(part) / F.col("total") / entropy(whole)).otherwise(1.0)
    h, c = share("hxy", "lnx"), share("hyx", "lny")
    chance = F.coalesce(F.try_divide(F.col("snx") * F.col("sny"), _pairs_of(F.col("total"))), F.lit(0.0))
    value = F.coalesce(F.try_divide(F.col("s") - chance, (F.col("snx") + F.col("sny")) / 2 - chance), F.lit(1.0))
    v = F.coalesce(F.try_divide(2 * h * c, h + c), F.lit(0.0))
    return one.select(*by, *(F.round(x, DIGITS).alias(k) for k, x in (("homogeneity", h), ("completeness", c), ("v_measure", v), ("ari", value))))


def two_class(records: DataFrame, pred: str = "pred", truth: str = "truth") -> DataFrame:
    """Precision, recall and F1 of duplicates and of the rest, accuracy, and macro F1 by both definitions."""
    c = lambda p, t: F.sum(((F.col(pred) == p) & (F.col(truth) == t)).cast("long"))
    n = records.agg(c(1, 1).alias("tp"), c(1, 0).alias("fp"), c(0, 1).alias("fn"), c(0, 0).alias("tn"))
    div = lambda a, b: F.coalesce(F.try_divide(a, b), F.lit(0.0))
    f1 = lambda p, r: div(2 * p * r, p + r)
    tp, fp, fn, tn = (F.col(x) for x in ("tp", "fp", "fn", "tn"))
    pd, rd, pn, rn = div(tp, tp + fp), div(tp, tp + fn), div(tn, tn + fn), div(tn, tn + fp)
    out = {"p_dup": pd, "r_dup": rd, "f1_dup": f1(pd, rd), "p_non": pn, "r_non": rn, "f1_non": f1(pn, rn), "accuracy": div(tp + tn, tp + fp + fn + tn), "f1_of_macro": f1((pd + pn) / 2, (rd + rn) / 2), "macro_of_f1": (f1(pd, rd) + f1(pn, rn)) / 2}
    return n.select("tp", "fp", "fn", "tn", *(F.round(v, DIGITS).alias(k) for k, v in out.items()))


def detection_by_ratio(found: DataFrame, truth: DataFrame) -> DataFrame:
    """(ratio, pairs, rate): share of true pairs that were found, by round(longer / shorter); truth: a, b, len_a, len_b."""
    hit = found.select("a", "b").distinct().withColumn("hit", F.lit(1))
    rows = truth.join(hit, ["a", "b"], "left").withColumn("ratio", F.round(F.try_divide(F.greatest("len_a", "len_b"), F.least("len_a", "len_b"))).cast("int"))
    return rows.groupBy("ratio").agg(F.count("*").alias("pairs"), F.round(F.avg(F.coalesce("hit", F.lit(0))), DIGITS).alias("rate"))


def tie_rate(results: DataFrame) -> DataFrame:
    """Share of queries whose best score is held by several targets; results: (query_id, ties)."""
    return results.agg(F.count("*").alias("queries"), F.round(F.avg((F.col("ties") > 1).cast("int")), DIGITS).alias("tie_rate"))


def error_samples(found: DataFrame, truth: DataFrame, docs: DataFrame, n: int = 20, seed: str = "errors") -> DataFrame:
    """n wrong pairs of each kind with 512-character excerpts, in an order that the seed fixes."""
    from twinsift.functions.text import md5_int
    from twinsift.operators.clustering import top_window

    keys = ["a", "b"]
    wrong = found.select(*keys).distinct().join(truth.select(*keys), keys, "left_anti").withColumn("kind", F.lit("false positive"))
    missed = truth.select(*keys).distinct().join(found.select(*keys), keys, "left_anti").withColumn("kind", F.lit("false negative"))
    picked = top_window(wrong.union(missed).withColumn("o", md5_int(F.concat_ws("-", "a", "b", F.lit(seed)))), ["kind"], ["o", "a", "b"], n)
    part = lambda i: docs.select(F.col("doc_id").alias(i), F.substring("text", 1, 512).alias(f"text_{i}"))
    return picked.join(part("a"), "a").join(part("b"), "b").select("kind", "a", "b", "text_a", "text_b")


def throughput(spark: SparkSession, name: str, df: DataFrame, examples: int) -> DataFrame:
    """(method, examples, seconds, per_second) of writing a plan to nowhere; reading counts, indexing does not."""
    began = time.perf_counter()
    df.write.format("noop").mode("overwrite").save()
    s = time.perf_counter() - began
    return spark.createDataFrame([(name, examples, s, examples / s)], "method string, examples long, seconds double, per_second double")
