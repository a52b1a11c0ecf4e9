"""Pieces shared by the trained models: bounded labelled samples, splits, Adam."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: A classifier is fitted on at most so many labelled documents of each class. Of a text longer than LONGEST
#: characters the sample holds so many equal stretches, evenly spread from its first character to its last.
SAMPLE, LONGEST, STRETCHES = 2000, 40_000, 8


def fold(of: int = 5, column: str = "doc_id") -> Column:
    """crc32 of the id as text, modulo `of`; null for a null id."""
    return F.crc32(F.col(column).cast("string").cast("binary")) % of


def labelled_sample(docs: DataFrame, labels: DataFrame, label: str, held_out: int = 0, sample: int = SAMPLE, longest: int = LONGEST, stretches: int = STRETCHES) -> tuple[list[str], np.ndarray]:
    """Texts and 0/1 labels outside the held-out fold: per class the `sample` first ids by hash, so the
    driver gets at most 2 * sample texts of about `longest` characters, however large the tables are. Longer
    texts take part by evenly spread stretches."""
    known = labels.where(F.col("doc_id").isNotNull() & F.col(label).isin(0, 1) & (fold() != held_out)).groupBy("doc_id").agg(F.max(label).alias("_y"))
    known = known.withColumn("_o", F.xxhash64("doc_id"))
    ids = known.where("_y = 1").orderBy("_o").limit(sample).union(known.where("_y = 0").orderBy("_o").limit(sample)).select("doc_id", "_y")
    picked = {r[0]: r[1] for r in ids.collect()}
    if not picked:
        return [], np.zeros(0, np.float32)
    small = docs.sparkSession.createDataFrame(sorted(picked.items()), "_id long, _y int")
    one = longest // stretches
    text = F.expr(f"if(length(text) <= {longest}, text, array_join(transform(sequence(0, {stretches - 1}), i -> substring(text, 1 + cast(floor(i * (length(text) - {one}) / {stretches - 1}) as int), {one})), ' '))")
    rows = docs.select("doc_id", "text").where("text is not null").join(F.broadcast(small), F.col("doc_id") == F.col("_id")).select("_id", "_y", text.alias("text")).collect()
    seen = {}
    for i, y, t in rows:
        seen[i] = min(seen.get(i, (t, y)), (t, y))  # a repeated id counts once
    return [seen[i][0] for i in sorted(seen)], np.array([seen[i][1] for i in sorted(seen)], np.float32)


class Adam:
    def __init__(self, params: dict[str, np.ndarray], rate: float = 0.01, decay: float = 0.0):
        self.params, self.rate, self.decay, self.t = params, rate, decay, 0
        self.m = {k: np.zeros_like(v) for k, v in params.items()}
        self.v = {k: np.zeros_like(v) for k, v in params.items()}
        self.free = {k: (np.empty_like(v), np.empty_like(v)) for k, v in params.items()}

    def step(self, grads: dict[str, np.ndarray]) -> None:
        self.t += 1
        for k, g in grads.items():
            m, v, (a, b) = self.m[k], self.v[k], self.free[k]
            np.subtract(g, m, out=a)
            a *= 0.1
            m += a
            np.multiply(g, g, out=a)
            a -= v
            a *= 0.01
            v += a
            if self.decay:
                self.params[k] *= 1 - self.rate * self.decay
            np.divide(v, 1 - 0.99**self.t, out=a)
            np.sqrt(a, out=a)
            a += 1e-8
            np.divide(m, 1 - 0.9**self.t, out=b)
            b *= self.rate
            b /= a
            self.params[k] -= b


def sigmoid(x: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(x, -30, 30)))
