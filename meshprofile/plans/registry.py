"""Every query of the engine and its SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from meshprofile.plans import methods, relational
from meshprofile.streaming import streams

ALL = methods.build() | relational.Q | streams.Q


def entry(spark: SparkSession) -> DataFrame:
    return methods.q_entry(spark, "/root/testdata/sf0.001")


def queries() -> dict:
    return {k: fn for k, (fn, _) in ALL.items()}


def oracle_sql() -> dict:
    return {k: sql for k, (_, sql) in ALL.items() if sql}
