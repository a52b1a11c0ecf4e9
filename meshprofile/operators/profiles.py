"""Representative daily profiles from readings, and their standardisation."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from meshprofile.sources.tables import slot_of


def build(df: DataFrame, key: str, ts: str, value: str, slots: int = 48, how: str = "sum", fill: float = 0.0, trim: float = 0.1) -> DataFrame:
    """(id, y): one array of `slots` numbers for each key.

    sum adds all readings of a slot: one grouping with a conditional sum for each slot, so partial
    sums meet in a single shuffle and no row is exploded. mean, median and trimmed_mean take the daily
    sums of a slot first; slots without readings hold `fill`. Null values are skipped, null keys kept."""
    base = df.select(F.col(key).alias("id"), slot_of(ts, slots).alias("slot"), F.to_date(ts).alias("day"), F.col(value).cast("double").alias("v"))
    if how == "sum":
        return base.groupBy("id").agg(F.array(*[F.coalesce(F.sum(F.when(F.col("slot") == s, F.col("v"))), F.lit(fill)) for s in range(slots)]).alias("y"))
    daily = base.groupBy("id", "day", "slot").agg(F.sum("v").alias("v"))
    if how == "mean":
        cell = F.avg("v")
    elif how == "median":
        cell = F.median("v")
    elif how == "trimmed_mean":
        sorted_ = F.sort_array(F.collect_list("v"))  # at most one entry a day
        cut = F.floor(F.size(sorted_) * trim).cast("int")
        kept = F.slice(sorted_, cut + 1, F.size(sorted_) - 2 * cut)
        cell = F.aggregate(kept, F.lit(0.0), lambda a, x: a + x) / F.size(kept)
    else:
        raise ValueError(f"how is sum, mean, median or trimmed_mean, not {how}")
    cells = daily.groupBy("id", "slot").agg(cell.alias("v"))
    return cells.groupBy("id").agg(F.array(*[F.coalesce(F.max(F.when(F.col("slot") == s, F.col("v"))), F.lit(fill)) for s in range(slots)]).alias("y"))


def grouped(df: DataFrame, key: str, place, value: str, size: int) -> DataFrame:
    """(id, y) with y[i] the sum of value where place = i: month or weekday profiles, for example."""
    base = df.select(F.col(key).cast("long").alias("id"), place.cast("int").alias("_p"), F.col(value).cast("double").alias("_v"))
    return base.groupBy("id").agg(F.array(*[F.coalesce(F.sum(F.when(F.col("_p") == i, F.col("_v"))), F.lit(0.0)) for i in range(size)]).alias("y"))


def standardise(df: DataFrame, how: str = "peak") -> DataFrame:
    """Row-wise scalings are local to a party; zscore_col uses moments over all rows (see
    consensus.masked_moments for the same without pooling). Profiles of zeros stay zero."""
    if how == "peak":
        return df.withColumn("y", F.expr("transform(y, v -> coalesce(v / nullif(array_max(y), 0D), 0D))"))
    if how == "unit_sum":
        return df.withColumn("y", F.expr("transform(y, v -> coalesce(v / nullif(aggregate(y, 0D, (a, b) -> a + b), 0D), 0D))"))
    if how == "minmax":
        return df.withColumn("y", F.expr("transform(y, v -> coalesce((v - array_min(y)) / nullif(array_max(y) - array_min(y), 0D), 0D))"))
    if how == "zscore_row":
        df = df.withColumn("_m", F.expr("aggregate(y, 0D, (a, b) -> a + b) / size(y)"))
        df = df.withColumn("_s", F.expr("sqrt(aggregate(y, 0D, (a, b) -> a + (b - _m) * (b - _m)) / size(y))"))
        return df.withColumn("y", F.expr("transform(y, v -> coalesce((v - _m) / nullif(_s, 0D), 0D))")).drop("_m", "_s")
    if how == "zscore_col":
        size = df.select(F.size("y")).first()
        d = size[0] if size else 0
        moments = df.agg(*[f(F.col("y")[i]).alias(f"{n}{i}") for i in range(d) for n, f in (("m", F.avg), ("s", F.stddev_pop))]).first()
        scaled = [F.coalesce((F.col("y")[i] - F.lit(moments[f"m{i}"])) / F.nullif(F.lit(moments[f"s{i}"]), F.lit(0.0)), F.lit(0.0)) for i in range(d)]
        return df.withColumn("y", F.array(*scaled)) if d else df
    raise ValueError(f"how is peak, unit_sum, minmax, zscore_row or zscore_col, not {how}")


def long_form(df: DataFrame, *keep: str) -> DataFrame:
    """Rows (keep..., slot, v) of array profiles."""
    return df.select(*keep, F.posexplode("y").alias("slot", "v"))
