"""Round trips and sinks in the shared folder."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from meshprofile import session

ALLOWED = {"outer", "t", "src", "dst", "comp", "x_plus"}


def place(df: DataFrame, name: str) -> str:
    return session.place(df.sparkSession, name)


def round_trip(df: DataFrame, kind: str) -> DataFrame:
    """df written as csv, json, orc or parquet and read back with its own schema."""
    path = place(df, kind)
    writer = df.write.option("header", True) if kind == "csv" else df.write
    writer.format(kind).save(path)
    reader = df.sparkSession.read.schema(df.schema)
    return (reader.option("header", True) if kind == "csv" else reader).format(kind).load(path)


def partitioned(df: DataFrame, *keys: str) -> DataFrame:
    """Parquet by key folders: later reads with a filter on a key open its folder alone."""
    path = place(df, "partitioned")
    df.write.partitionBy(*keys).parquet(path)
    back = df.sparkSession.read.parquet(path)
    return back.select(*[back[f.name].cast(f.dataType).alias(f.name) for f in df.schema.fields])


def replaced(df: DataFrame, key: str, stale: DataFrame) -> DataFrame:
    """df by key folders over an older table: only the folders that df has rows for are replaced."""
    path = place(df, "replaced")
    stale.write.partitionBy(key).parquet(path)
    df.write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy(key).parquet(path)
    back = df.sparkSession.read.parquet(path)
    return back.select(*[F.col(f.name).cast(f.dataType).alias(f.name) for f in df.schema.fields])


def bucketed(df: DataFrame, key: str, buckets: int) -> DataFrame:
    """A table bucketed and sorted by key: joins and groupings on it need no shuffle."""
    name = f"bucketed_{uuid.uuid4().hex}"
    df.write.bucketBy(buckets, key).sortBy(key).option("path", place(df, "bucketed")).saveAsTable(name)
    return df.sparkSession.table(name)


def message_sink(messages: DataFrame, path: str) -> None:
    """Append messages; refuses any column that is not public."""
    extra = set(messages.columns) - ALLOWED
    if extra:
        raise ValueError(f"columns that must not leave a party: {sorted(extra)}")
    messages.write.mode("append").parquet(path)
