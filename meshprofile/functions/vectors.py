"""Vector expressions on array columns, in SQL."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def l2sq(a: str, b: str) -> str:
    return f"aggregate(zip_with({a}, {b}, (p, q) -> (p - q) * (p - q)), 0D, (s, v) -> s + v)"


def dot(a: str, b: str) -> str:
    return f"aggregate(zip_with({a}, {b}, (p, q) -> p * q), 0D, (s, v) -> s + v)"


def array_literal(values) -> str:
    """Nested lists of numbers as a SQL array of doubles."""
    if hasattr(values, "__len__"):
        return "array(" + ", ".join(array_literal(v) for v in values) + ")"
    return f"{float(values)!r}D"


def total(column: str) -> Column:
    return F.expr(f"aggregate({column}, 0D, (s, v) -> s + v)")
