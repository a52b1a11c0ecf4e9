"""Joins that Spark lacks by name: range, interval, as-of."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window


def seconds(column: str):
    return F.unix_timestamp(F.col(column).cast("timestamp"))


def range_join(points: DataFrame, ranges: DataFrame, at: str, start: str, end: str, bin_seconds: int) -> DataFrame:
    """points within [start, end): an equi-join on time bins, then the exact test. A range is copied to each
    bin it touches, a point to one, so nothing is compared outside its bin."""
    first, last = F.floor(seconds(start) / bin_seconds), F.floor(seconds(end) / bin_seconds)
    cut = ranges.withColumn("_bin", F.explode(F.sequence(first, last)))
    return points.withColumn("_bin", F.floor(seconds(at) / bin_seconds)).join(cut, "_bin").where((F.col(at) >= F.col(start)) & (F.col(at) < F.col(end))).drop("_bin")


def interval_join(left: DataFrame, right: DataFrame, key: str, t0: str, t1: str, within: int) -> DataFrame:
    """Pairs of a key with t0 <= t1 <= t0 + within seconds: bins of that length, each left row in two."""
    a = left.withColumn("_bin", F.explode(F.array(F.floor(seconds(t0) / within), F.floor(seconds(t0) / within) + 1)))
    b = right.withColumn("_bin", F.floor(seconds(t1) / within))
    limit = F.col(t0) + F.make_dt_interval(F.lit(0), F.lit(0), F.lit(0), F.lit(within))
    return a.join(b, [key, "_bin"]).where((F.col(t1) >= F.col(t0)) & (F.col(t1) <= limit)).drop("_bin")


def as_of_join(left: DataFrame, right: DataFrame, key: str, at: str, value: str) -> DataFrame:
    """left with the last value of right at or before each row: one union and one window, no pairs."""
    a = left.withColumn("_v", F.lit(None).cast(right.schema[value].dataType)).withColumn("_left", F.lit(1))
    names = [c for c in left.columns if c not in (key, at)]
    b = right.select(*[F.lit(None).cast(left.schema[c].dataType).alias(c) for c in names], key, at, F.col(value).alias("_v"), F.lit(0).alias("_left"))
    w = Window.partitionBy(key).orderBy(at, "_left").rowsBetween(Window.unboundedPreceding, 0)
    return a.unionByName(b).withColumn(value, F.last("_v", ignorenulls=True).over(w)).where("_left = 1").drop("_v", "_left")
