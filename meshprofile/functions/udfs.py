"""SQL-callable faces of the methods: Arrow, pandas and SQL functions, a table function."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_type
from pyspark.sql.types import DoubleType


def norm_arrow():
    @F.arrow_udf(DoubleType())
    def norm(v: pa.Array) -> pa.Array:
        x = v.flatten().to_numpy(zero_copy_only=False).astype(float).reshape(len(v), -1) if len(v) else np.zeros((0, 1))
        return pa.array(np.sqrt((x * x).sum(1)))

    return norm


def norm_pandas():
    @F.pandas_udf(DoubleType())
    def norm(v: pd.Series) -> pd.Series:
        x = np.stack(v.to_numpy()).astype(float) if len(v) else np.zeros((0, 1))
        return pd.Series(np.sqrt((x * x).sum(1)))

    return norm


def vector_totals(df: DataFrame, key: str, vector: str) -> DataFrame:
    """(key, total) with total the sum of a group's vectors: each task adds up what it sees of a group, so one
    row a task and group is shuffled and no group is gathered. Null vectors add nothing; groups hold vectors of
    one length. A vector aggregate that SQL functions lack."""

    def partial(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums: dict = {}
        for batch in batches:
            batch = batch.filter(batch.column("v").is_valid())
            keys = batch.column("k").dictionary_encode()
            for i, k in enumerate(keys.dictionary.to_pylist()):
                own = batch.column("v").filter(pc.equal(keys.indices, i))
                total = own.flatten().to_numpy(zero_copy_only=False).astype(float).reshape(len(own), -1).sum(0)
                sums[k] = sums[k] + total if k in sums else total
        yield pa.record_batch([pa.array(list(sums), kind), pa.array([v.tolist() for v in sums.values()], pa.list_(pa.float64()))], names=["k", "v"])

    kind = to_arrow_type(df.schema[key].dataType)
    parts = df.select(F.col(key).alias("k"), F.col(vector).alias("v")).where("k is not null").mapInArrow(partial, f"k {df.schema[key].dataType.simpleString()}, v array<double>")
    cells = parts.select("k", F.posexplode("v").alias("i", "v")).groupBy("k", "i").agg(F.sum("v").alias("v"))
    return cells.groupBy("k").agg(F.transform(F.sort_array(F.collect_list(F.struct("i", "v"))), lambda c: c["v"]).alias("total")).withColumnRenamed("k", key)


class ConsensusRounds:
    """consensus_rounds(table of (party, comp, x), rounds): (t, party, comp, x) on the main graph."""

    def __init__(self):
        self.rows: list[tuple[int, int, float]] = []
        self.rounds = 0

    def eval(self, row, rounds: int):
        self.rows.append((row["party"], row["comp"], row["x"]))
        self.rounds = rounds

    def terminate(self):
        from meshprofile.operators import topology
        from meshprofile.sources.graphs import main_graph

        if not self.rows:
            return
        comps = sorted({c for _, c, _ in self.rows})
        x = np.zeros((10, len(comps)))
        for p, c, v in self.rows:
            x[p, comps.index(c)] += v
        w = topology.boosted_matrix(topology.mixing_matrix(main_graph()))
        for t in range(self.rounds + 1):
            for p in range(10):
                for i, c in enumerate(comps):
                    yield t, p, c, float(x[p, i])
            x = w @ x


def register(spark: SparkSession) -> None:
    spark.udtf.register("consensus_rounds", F.udtf(ConsensusRounds, returnType="t int, party int, comp int, x double"))


def rounds_by_udtf(spark: SparkSession, sf_dir: str) -> DataFrame:
    from meshprofile.plans.methods import first_states

    register(spark)
    got = spark.sql("select * from consensus_rounds(table(select party, comp, x from {s}) partition by (comp), 5)", s=first_states(spark, sf_dir))
    return got.select(*[F.col(c).cast("long").alias(c) for c in ("t", "party", "comp")], F.round("x", 6).alias("x"))


def sql_functions(spark: SparkSession, sf_dir: str) -> DataFrame:
    spark.sql("create or replace temporary function dot(a array<double>, b array<double>) returns double return aggregate(zip_with(a, b, (x, y) -> x * y), 0D, (s, v) -> s + v)")
    e = spark.read.parquet(f"{sf_dir}/embeddings.parquet").select("vec_id", F.expr("transform(embedding, v -> cast(v as double))").alias("y"))
    return spark.sql("select vec_id, round(dot(y, y), 4) as q from {e}", e=e)
