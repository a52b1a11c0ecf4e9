"""The given tables as carriers of profiles: readings, parties, planted profiles."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from meshprofile.functions.hashing import uniform


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def readings(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(user_id, ts, value): only these columns are read."""
    return table(spark, sf_dir, "events").select("user_id", "ts", "value")


def slot_of(ts: str, slots: int = 48) -> Column:
    """Slot of the day, 0..slots-1; slots must divide 1440 minutes."""
    if 1440 % slots:
        raise ValueError("slots must divide the minutes of a day")
    return F.floor((F.hour(ts) * 60 + F.minute(ts)) / (1440 // slots)).cast("int")


#: Centre and width of each planted archetype's daily peak, in half-hour slots.
CENTRES = (4, 12, 18, 26, 36, 42)
WIDTHS = (3, 4, 3, 6, 3, 4)


def planted(spark: SparkSession, sf_dir: str, slots: int = 48, consumers: int | None = None, copies: int = 1) -> DataFrame:
    """(party, id, archetype, y): six archetypes over ten parties; party 0 holds archetypes 1 and 2 only.
    consumers keeps the customers below that key (a fixture's size); copies gives each customer so many consumers."""
    c = table(spark, sf_dir, "customer").select(F.col("c_custkey").cast("long").alias("id"))
    if consumers is not None:
        c = c.where(F.col("id") < consumers)
    if copies > 1:
        c = c.select("id", F.explode(F.sequence(F.lit(0), F.lit(copies - 1))).alias("copy")).select((F.col("id") * copies + F.col("copy")).alias("id"))
    c = c.withColumn("archetype", F.pmod("id", F.lit(6)).cast("int")).withColumn("home", F.pmod(F.floor(F.col("id") / 6), F.lit(10)).cast("int"))
    moved = (F.col("home") == 0) & ~F.col("archetype").isin(1, 2)
    c = c.withColumn("party", F.when(moved, 1 + F.pmod(F.floor(F.col("id") / 60), F.lit(9))).otherwise(F.col("home")).cast("int"))
    at, width = (F.element_at(F.array(*map(F.lit, v)), F.col("archetype") + 1) for v in (CENTRES, WIDTHS))
    step = 48 // slots

    def value(s: int) -> Column:
        s *= step
        noise = uniform(F.concat_ws(":", F.lit("11"), F.col("id"), F.lit(s))) - 0.5
        return 0.1 + F.exp(-F.pow(F.lit(s) - at, F.lit(2)) / (2 * width * width)) + 0.5 * noise

    return c.select("party", "id", "archetype", F.array(*[value(s) for s in range(slots)]).alias("y"))


def parties_of_users(df: DataFrame, parties: int = 10, key: str = "id") -> DataFrame:
    return df.withColumn("party", F.pmod(F.col(key), F.lit(parties)).cast("int"))
