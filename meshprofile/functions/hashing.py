"""Keyed uniforms that any engine can recompute: the first 32 bits of a SHA-256."""

from __future__ import annotations

import hashlib

from pyspark.sql import Column
from pyspark.sql import functions as F


def uniform(key: Column) -> Column:
    """Column in [0, 1): equal under task retries and in any SQL with sha256."""
    return F.conv(F.substring(F.sha2(key.cast("string"), 256), 1, 8), 16, 10).cast("double") / F.lit(4294967296.0)


def uniform_py(key: str) -> float:
    return int(hashlib.sha256(key.encode()).hexdigest()[:8], 16) / 4294967296.0


def uniform_sql(key: str) -> str:
    """The same in Spark SQL, for use inside lambdas."""
    return f"(cast(conv(substring(sha2({key}, 256), 1, 8), 16, 10) as double) / 4294967296D)"


def uniform_duck(key: str) -> str:
    """The same in DuckDB."""
    return f"(('0x' || substr(sha256({key}), 1, 8))::bigint / 4294967296.0)"


def lane_duck(key: str, lane: str) -> str:
    """One of the eight uniforms of a key's SHA-256, in DuckDB."""
    return f"(('0x' || substr(sha256({key}), ({lane}) * 8 + 1, 8))::bigint / 4294967296.0)"
