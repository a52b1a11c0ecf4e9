"""Session helper and schema checks."""

from __future__ import annotations

import re
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import types as T


def local_session(cores: str = "*", partitions: int = 8) -> SparkSession:
    """A local session for tests and the bench; on a cluster the session comes as it is."""
    return (
        SparkSession.builder.master(f"local[{cores}]")
        .config("spark.sql.shuffle.partitions", str(partitions))
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.sql.adaptive.enabled", "true")
        .config("spark.driver.memory", "8g")
        .config("spark.ui.enabled", "false")
        .getOrCreate()
    )


def require_schema(df: DataFrame, spec: dict[str, T.DataType]) -> DataFrame:
    """df, after a check that the columns of spec are there with their types (nullability aside)."""
    have = {f.name: f.dataType for f in df.schema.fields}
    for name, kind in spec.items():
        if name not in have:
            raise ValueError(f"column {name} is missing; there are {sorted(have)}")
        if have[name].simpleString() != kind.simpleString():
            raise ValueError(f"column {name} is {have[name].simpleString()}, not {kind.simpleString()}")
    return df


PROFILES = {"party": T.IntegerType(), "id": T.LongType(), "y": T.ArrayType(T.DoubleType())}
STATE = {"party": T.IntegerType(), "comp": T.IntegerType(), "x": T.DoubleType()}


def shared_folder(spark: SparkSession) -> str:
    """The folder all executors share, as the session names it; where it names none, a local one in a session of
    one process, else an error."""
    sc = spark.sparkContext
    got = spark.conf.get("spark.checkpoint.dir", None) or sc._jsc.sc().getCheckpointDir().getOrElse(None)
    if not got:
        if not re.fullmatch(r"local(\[[^]]*\])?", sc.master):
            raise RuntimeError("spark.checkpoint.dir must name a folder that the driver and all executors share")
        sc.setCheckpointDir(tempfile.mkdtemp(prefix="shared-"))
        got = sc._jsc.sc().getCheckpointDir().get()
    return got.rstrip("/")


#: Paths that this driver has written to the shared folder and not deleted.
_written: list[str] = []


def place(spark: SparkSession, name: str) -> str:
    """A new path in the shared folder, remembered for clear()."""
    path = f"{shared_folder(spark)}/{name}-{uuid.uuid4().hex}"
    _written.append(path)
    return path


def settle(df: DataFrame, name: str) -> DataFrame:
    """Write df to the shared folder and read it back: flat lineage that survives lost executors."""
    path = place(df.sparkSession, name)
    df.write.parquet(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out._settled_at = path
    return out


def _delete(spark: SparkSession, path: str) -> None:
    at = spark._jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(at, True)


def discard(df: DataFrame) -> None:
    """Delete what settle wrote for df; nothing may read it afterwards."""
    path = getattr(df, "_settled_at", None)
    if path in _written:
        _written.remove(path)
        _delete(df.sparkSession, path)


def clear(spark: SparkSession, since: int = 0) -> int:
    """Delete all that this driver has written to the shared folder, from the `since`-th path on; for when
    no result reads it any more. Gives the number of paths."""
    old = _written[since:]
    del _written[since:]
    for path in old:
        _delete(spark, path)
    return len(old)
