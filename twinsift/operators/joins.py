"""Joins that Spark has no operator for: ranges, as-of and intervals, by bins and windows."""

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def range_join(left: DataFrame, right: DataFrame, lo: Column, hi: Column, point: Column, width: float) -> DataFrame:
    """Rows of left (bounds lo, hi) with rows of right (point) inside: bins of the given width make it an equi-join; both bounds included."""
    bins = F.explode(F.sequence(F.floor(lo / width), F.floor(hi / width)))
    a = left.filter(lo <= hi).withColumn("_lo", lo).withColumn("_hi", hi).withColumn("_bin", bins)
    b = right.withColumn("_at", point).withColumn("_bin", F.floor(point / width))
    return a.join(b, "_bin").filter((F.col("_at") >= F.col("_lo")) & (F.col("_at") <= F.col("_hi"))).drop("_bin", "_lo", "_hi", "_at")


def asof_join(left: DataFrame, right: DataFrame, by: str, ts: str, value: str, out: str) -> DataFrame:
    """For each left row the last right value at or before its time within `by`: one union and one window, no pairs."""
    a = left.withColumn("_v", F.lit(None).cast(right.schema[value].dataType)).withColumn("_left", F.lit(1))
    b = right.select(by, ts, F.col(value).alias("_v")).withColumn("_left", F.lit(0))
    w = Window.partitionBy(by).orderBy(ts, "_left").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    both = a.unionByName(b, allowMissingColumns=True).withColumn(out, F.last("_v", ignorenulls=True).over(w))
    return both.filter("_left = 1").drop("_v", "_left")


def salted_join(left: DataFrame, right: DataFrame, key: str, salts: int, spread: Column) -> DataFrame:
    """An equi-join whose left rows of a key are dealt over `salts` tasks; the right side, small for each key, is repeated."""
    a = left.withColumn("_salt", F.pmod(F.xxhash64(spread), F.lit(salts)).cast("int"))
    b = right.withColumn("_salt", F.explode(F.sequence(F.lit(0), F.lit(salts - 1))))
    return a.join(b, [key, "_salt"]).drop("_salt")
