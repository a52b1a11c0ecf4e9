"""Structured Streaming over readings: windows, late rows, replays, joins, state, periodic refits.

Queries run the file stream with availableNow into Parquet and give back the result.
timestamps without a zone are cast before any watermark."""

from __future__ import annotations

from collections.abc import Callable
from datetime import timedelta

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupStateTimeout
from pyspark.sql.types import LongType, StructField, StructType

from meshprofile.operators import cluster, consensus
from meshprofile.plans import duck
from meshprofile.session import place
from meshprofile.sources.graphs import main_graph
from meshprofile.sources.tables import slot_of, table

SCHEMA = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def stream(spark: SparkSession, sf_dir: str, delay: str = "1 hour") -> DataFrame:
    """The events file as a stream, watermarked."""
    files = spark.readStream.schema(SCHEMA).option("pathGlobFilter", "events.parquet").option("maxFilesPerTrigger", 1).parquet(sf_dir)
    return files.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", delay)


def finish(df: DataFrame, keys: tuple[str, ...] = ()) -> DataFrame:
    """Run to the end of what is there and return the result's rows, from Parquet in the shared folder. Without keys
    in append mode; with keys in update mode: each batch writes the rows it changed, and a key's last row counts,
    so state older than the watermark is let go and no batch passes through the driver."""
    spark = df.sparkSession
    to = place(spark, "sink")
    out = df.writeStream.option("checkpointLocation", place(spark, "sink-log")).trigger(availableNow=True)
    if not keys:
        out.outputMode("append").format("parquet").option("path", to).start().awaitTermination()
        return spark.read.schema(df.schema).parquet(to)

    def each(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{to}/batch={number}")

    out.outputMode("update").foreachBatch(each).start().awaitTermination()
    rows = spark.read.schema(StructType([*df.schema.fields, StructField("batch", LongType())])).parquet(to)
    last = rows.groupBy(*keys).agg(F.max_by(F.struct(*df.columns), "batch").alias("r"))
    return last.select("r.*")


def finish_whole(df: DataFrame) -> DataFrame:
    """The same in complete mode, for what update mode lacks (session windows): each batch writes the whole result."""
    spark = df.sparkSession
    to = place(spark, "sink")

    def each(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(to)

    df.writeStream.option("checkpointLocation", place(spark, "sink-log")).trigger(availableNow=True).outputMode("complete").foreachBatch(each).start().awaitTermination()
    return spark.read.schema(df.schema).parquet(to)


def windowed(df: DataFrame, window) -> DataFrame:
    got = df.groupBy(window.alias("w")).agg(F.count(F.lit(1)).alias("n"), F.round(F.sum("value"), 4).alias("v"))
    return got.select(F.unix_timestamp("w.start").alias("start"), "n", "v")


def tumbling(spark: SparkSession, d: str) -> DataFrame:
    return finish(windowed(stream(spark, d), F.window("ts", "30 minutes")), ("start",))


def sliding(spark: SparkSession, d: str) -> DataFrame:
    return finish(windowed(stream(spark, d), F.window("ts", "1 hour", "30 minutes")), ("start",))


def session(spark: SparkSession, d: str) -> DataFrame:
    got = stream(spark, d).groupBy("user_id", F.session_window("ts", "6 hours").alias("w")).agg(F.count(F.lit(1)).alias("n"))
    return finish_whole(got.select("user_id", F.unix_timestamp("w.start").alias("start"), "n"))


def dedup(spark: SparkSession, d: str) -> DataFrame:
    """Rows replayed within the watermark appear once."""
    twice = stream(spark, d, "2 hours").withColumn("copy", F.explode(F.array(F.lit(0), F.lit(1)))).drop("copy")
    return finish(twice.dropDuplicatesWithinWatermark(["event_id"]).select("event_id", "user_id"))


def thirds(e: DataFrame) -> list[DataFrame]:
    """Rows of e in three parts by even ranges of ts, the first and last open; rows without a ts are in the first."""
    low, high = e.agg(F.min("ts"), F.max("ts")).first()
    if low is None:
        return [e]
    a, b = (F.lit(low + (high - low) * i / 3).cast("timestamp_ntz") for i in (1, 2))
    ts = F.col("ts")
    return [e.where(ts.isNull() | (ts < a)), e.where((ts >= a) & (ts < b)), e.where(ts >= b)]


def late(spark: SparkSession, d: str) -> DataFrame:
    """Batches in time order, then one of rows long past the watermark, then a row that closes all windows:
    append mode emits each window once and the late rows are dropped. Each batch, of as many files as it has,
    is written and taken up by the query before the next."""
    base, to, log = (place(spark, n) for n in ("late", "late-sink", "late-log"))
    e = table(spark, d, "events")
    low, high = e.agg(F.min("ts"), F.max("ts")).first()
    old = e.where(F.col("ts") < F.lit(low + (high - low) / 30 if low else None).cast("timestamp_ntz")).withColumn("event_id", F.col("event_id") + 1_000_000_000)
    last = e.limit(1).withColumn("ts", F.lit(high + timedelta(365) if low else None).cast("timestamp_ntz"))
    for i, part in enumerate([*thirds(e), old, last]):
        part.write.parquet(f"{base}/{i}")
        files = spark.readStream.schema(SCHEMA).option("recursiveFileLookup", True).parquet(base)
        got = windowed(files.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", "1 hour"), F.window("ts", "30 minutes"))
        got.writeStream.outputMode("append").option("checkpointLocation", log).trigger(availableNow=True).format("parquet").option("path", to).start().awaitTermination()
    return spark.read.schema(got.schema).parquet(to)


def with_parties(spark: SparkSession, d: str) -> DataFrame:
    """Stream joined with the static party directory."""
    c = table(spark, d, "customer").select(F.col("c_custkey").cast("long").alias("user_id"), F.col("c_nationkey").cast("long").alias("party"))
    return finish(stream(spark, d).join(c, "user_id").groupBy("party").agg(F.count(F.lit(1)).alias("n")), ("party",))


def conversions(spark: SparkSession, d: str) -> DataFrame:
    """Purchases within six hours of a click by the same user: two watermarked streams."""
    e = stream(spark, d).select("event_id", "user_id", "ts", "event_type")
    c = e.where("event_type = 'click'").select(F.col("event_id").alias("click"), "user_id", F.col("ts").alias("t0"))
    p = e.where("event_type = 'purchase'").select(F.col("event_id").alias("buy"), F.col("user_id").alias("u"), F.col("ts").alias("t1"))
    return finish(c.join(p, F.expr("user_id = u and t1 >= t0 and t1 <= t0 + interval 6 hours")).select("click", "buy"))


def slot_state(spark: SparkSession, d: str) -> DataFrame:
    """Per-user slot sums kept in state between batches; each batch emits the users it touched."""

    def work(key, frames, state):
        total = np.array(state.get[0]) if state.exists else np.zeros(48)
        for f in frames:
            np.add.at(total, f["slot"].to_numpy(), f["value"].to_numpy())
        state.update((total.tolist(),))
        yield pd.DataFrame({"user_id": [key[0]], "total": [float(total.sum())], "used": [int((total > 0).sum())]})

    slots = stream(spark, d).select("user_id", slot_of("ts").alias("slot"), "value")
    got = slots.groupBy("user_id").applyInPandasWithState(work, "user_id long, total double, used long", "y array<double>", "append", GroupStateTimeout.NoTimeout)
    return finish(got).select("user_id", F.round("total", 4).alias("total"), "used")


def slot_sums(df: DataFrame) -> DataFrame:
    """Mergeable per-user slot sums of one batch: new days never rescan old ones."""
    return df.groupBy("user_id", slot_of("ts").alias("slot")).agg(F.sum("value").alias("v"))


REFIT_MU = cluster.public_random(2, 48, "refit")


def refit(spark: SparkSession, d: str, masked: bool = True, sink: Callable[[int, np.ndarray], None] | None = None) -> DataFrame:
    """Every batch adds its slot sums to a table and refits k-means from the last model, under masks over ten
    parties: (batch, k, slot, mu)."""
    base = place(spark, "refit")
    seen: dict[str, np.ndarray] = {}
    setting = consensus.Setting(main_graph(), 10, eps=1e-10) if masked else None

    def each(batch: DataFrame, number: int) -> None:
        own = batch.sparkSession
        slot_sums(batch).write.mode("overwrite").parquet(f"{base}/sums/batch={number}")
        sums = own.read.parquet(f"{base}/sums").groupBy("user_id").agg(F.array(*[F.coalesce(F.sum(F.when(F.col("slot") == s, F.col("v"))), F.lit(0.0)) for s in range(48)]).alias("y"))
        df = sums.select(F.pmod("user_id", F.lit(10)).cast("int").alias("party"), F.col("user_id").alias("id"), F.expr("transform(y, v -> coalesce(v / nullif(array_max(y), 0D), 0D))").alias("y"))
        model, _ = cluster.fit_kmeans(df, seen.get("mu", REFIT_MU), setting, iterations=3, stop="fixed")
        seen["mu"] = model.mu
        own.createDataFrame([(number, i, m.tolist()) for i, m in enumerate(model.mu)], "batch long, k int, mu array<double>").write.mode("overwrite").parquet(f"{base}/models/at={number}")
        if sink:
            sink(number, model.mu)

    stream(spark, d).writeStream.foreachBatch(each).option("checkpointLocation", f"{base}/log").trigger(availableNow=True).start().awaitTermination()
    rows = spark.read.parquet(f"{base}/models").select("batch", "k", F.posexplode("mu").alias("slot", "mu"))
    return rows.select("batch", F.col("k").cast("long").alias("k"), F.col("slot").cast("long").alias("slot"), F.round("mu", 4).alias("mu"))


BIN = "time_bucket(interval '30 minutes', ts, timestamp '2000-01-01')"
Q: dict[str, tuple] = {
    "stream_tumbling": (tumbling, f"select floor(epoch({BIN}))::bigint as start, count(*) as n, round(sum(value), 4) as v from events group by all"),
    "stream_sliding": (
        sliding,
        f"select start, count(*) as n, round(sum(value), 4) as v from (select value, floor(epoch({BIN}))::bigint - o * 1800 as start from events, range(2) r(o)) group by all",
    ),
    "stream_session": (
        session,
        """select user_id, floor(epoch(min(ts)))::bigint as start, count(*) as n from (select *, sum(new) over (partition by user_id order by ts) as s from
(select *, case when ts - lag(ts) over (partition by user_id order by ts) < interval 6 hour then 0 else 1 end as new from events)) group by user_id, s""",
    ),
    "stream_watermark_late": (late, f"select floor(epoch({BIN}))::bigint as start, count(*) as n, round(sum(value), 4) as v from events group by all"),
    "stream_dedup": (dedup, "select event_id, user_id from events"),
    "stream_join_static": (with_parties, "select c_nationkey::bigint as party, count(*) as n from events join customer on c_custkey = user_id group by all"),
    "stream_join_stream": (
        conversions,
        "select c.event_id as click, p.event_id as buy from events c join events p on c.user_id = p.user_id and c.event_type = 'click' and p.event_type = 'purchase' and p.ts >= c.ts and p.ts <= c.ts + interval 6 hour",
    ),
    "stream_state": (
        slot_state,
        "select user_id, round(sum(v), 4) as total, count(*) filter (v > 0) as used from (select user_id, (hour(ts) * 60 + minute(ts)) // 30 as slot, sum(value) as v from events group by all) group by user_id",
    ),
    "stream_refit": (refit, f"with {duck.peak_profiles(48)},\n{duck.kmeans(REFIT_MU, 3)}\nselect 0::bigint as batch, k::bigint as k, slot::bigint as slot, round(mu, 4) as mu from m3"),
}
