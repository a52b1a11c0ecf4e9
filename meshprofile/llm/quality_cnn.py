"""Quality by a convolutional network over bytes, trained in numpy.

A text's UTF-8 bytes are covered by chunks of CHUNK bytes that overlap by what a filter spans, so every
filter sees every place (at a step of two bytes) of the whole document. Filter outputs pass a rectifier
and are max-pooled over a chunk; a document is the mean and the maximum of its chunks' pools, combined
by one logistic unit into one probability.

Nulls and odd input: null and empty texts are one chunk of padding; a null doc_id is not held out;
repeated rows score alike; without labels of both kinds scores are 1; an empty table gives an empty
result; extra columns are neither read nor changed.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType

from meshprofile.llm.common import bounded_batches, flat_bytes, give_back, table, text_chunks
from meshprofile.llm.learning import Adam, fold, labelled_sample, sigmoid

CHUNK, SPAN, STEP, BYTE_DIM, FILTERS, BATCH = 256, 8, 2, 4, 16, 1024
PAD = 256


def chunk_table(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Byte chunks (PAD beyond the end) and the text of each; neighbours share SPAN bytes."""
    raw, offsets = flat_bytes(texts)
    n = np.diff(offsets)
    stride = CHUNK - SPAN
    count = np.maximum(1, -(-np.maximum(n - SPAN, 0) // stride))
    owner = np.repeat(np.arange(len(n)), count)
    start = (np.arange(len(owner)) - np.repeat(np.cumsum(count) - count, count)) * stride
    padded = np.r_[raw, np.zeros(CHUNK, np.uint8)]
    spots = np.minimum((offsets[owner] + start)[:, None] + np.arange(CHUNK), len(padded) - 1)
    return np.where(start[:, None] + np.arange(CHUNK) < n[owner][:, None], padded[spots].astype(np.int16), np.int16(PAD)), owner


class Network:
    def __init__(self, seed: int = 7):
        rng = np.random.default_rng(seed)
        self.p = {
            "byte": rng.normal(0, 0.5, (257, BYTE_DIM)),
            "filter": rng.normal(0, (SPAN * BYTE_DIM) ** -0.5, (SPAN * BYTE_DIM, FILTERS)),
            "shift": np.zeros(FILTERS),
            "out": rng.normal(0, 0.3, 2 * FILTERS),
            "bias": np.zeros(1),
        }
        self.p = {k: v.astype(np.float32) for k, v in self.p.items()}

    def pools(self, chunks: np.ndarray, keep: bool = False) -> tuple[np.ndarray, np.ndarray | None]:
        """Max-pooled filter outputs of each chunk, and the place of each maximum."""
        taps, places = SPAN // STEP, (CHUNK - SPAN) // STEP + 1
        pairs = self.p["byte"][chunks].reshape(len(chunks), CHUNK // STEP, STEP * BYTE_DIM)
        parts = self.p["filter"].reshape(taps, STEP * BYTE_DIM, FILTERS)
        y = pairs[:, :places] @ parts[0]
        for k in range(1, taps):
            y += pairs[:, k : k + places] @ parts[k]
        top = y.max(1) + self.p["shift"]
        return np.maximum(top, 0), y.argmax(1) if keep else None

    def combine(self, pools: np.ndarray, owner: np.ndarray, docs: int) -> tuple[np.ndarray, np.ndarray]:
        """Logit of each text, and its features: mean and maximum of its chunks."""
        first = np.flatnonzero(np.r_[True, owner[1:] != owner[:-1]])
        n = np.bincount(owner, minlength=docs)[:, None]
        feats = np.hstack([np.add.reduceat(pools, first) / n, np.maximum.reduceat(pools, first)])
        return feats @ self.p["out"] + self.p["bias"][0], feats

    def score(self, texts: pa.Array) -> np.ndarray:
        if not len(texts):
            return np.zeros(0)
        chunks, owner = chunk_table(texts)
        pools = np.concatenate([self.pools(chunks[i : i + BATCH])[0] for i in range(0, len(chunks), BATCH)])
        return sigmoid(self.combine(pools, owner, len(texts))[0].astype(np.float64))

    def gradients(self, chunks: np.ndarray, owner: np.ndarray, y: np.ndarray, weight: np.ndarray) -> dict[str, np.ndarray]:
        pools, where = self.pools(chunks, keep=True)
        logit, feats = self.combine(pools, owner, len(y))
        d = ((sigmoid(logit) - y) * weight / weight.sum()).astype(np.float32)
        g = {"out": feats.T @ d, "bias": np.array([d.sum()])}
        n = np.bincount(owner, minlength=len(y)).astype(np.float32)
        highest = pools == feats[owner, FILTERS:]
        highest &= np.cumsum(highest, 0) - (np.cumsum(highest, 0) - highest)[np.searchsorted(owner, owner)] == 1  # the first on ties
        dp = d[owner, None] * (self.p["out"][:FILTERS] / n[owner, None] + self.p["out"][FILTERS:] * highest)
        dp *= pools > 0
        g["shift"] = dp.sum(0)
        at = where[..., None] * STEP + np.arange(SPAN)  # chunk, filter, tap
        codes = chunks[np.arange(len(chunks))[:, None, None], at]
        taps = self.p["byte"][codes]
        g["filter"] = np.einsum("cf,cfsb->sbf", dp, taps).reshape(SPAN * BYTE_DIM, FILTERS)
        dtaps = dp[..., None, None] * self.p["filter"].reshape(SPAN, BYTE_DIM, FILTERS).transpose(2, 0, 1)
        g["byte"] = np.zeros_like(self.p["byte"])
        np.add.at(g["byte"], codes.ravel(), dtaps.reshape(-1, BYTE_DIM))
        return {k: v.astype(np.float32) for k, v in g.items()}


def train(texts: list[str], y: np.ndarray, epochs: int = 8, batch: int = 64, rate: float = 0.01, steps: int = 400, seed: int = 7) -> Network | None:
    if not len(texts) or y.min() == y.max():
        return None
    net, rng = Network(seed), np.random.default_rng(seed)
    adam = Adam(net.p, rate)
    chunks, owner = chunk_table(pa.array(texts, pa.large_string()))
    first = np.searchsorted(owner, np.arange(len(texts) + 1))
    # both classes weigh as in a balanced sample; the prior returns by the threshold
    weight = np.where(y > 0, 0.5 / y.mean(), 0.5 / (1 - y.mean())).astype(np.float32)
    batch = max(16, min(batch, len(texts) // 16))
    epochs = max(epochs, -(-steps * batch // len(texts)))
    for epoch in range(epochs):
        adam.rate = rate * (1 - epoch / epochs) + rate / 10
        order = rng.permutation(len(texts))
        for i in range(0, len(order), batch):
            part = order[i : i + batch]
            rows = np.concatenate([np.arange(first[j], first[j + 1]) for j in part])
            adam.step(net.gradients(chunks[rows], np.repeat(np.arange(len(part)), first[part + 1] - first[part]), y[part], weight[part]))
    return net


def score_column(net: Network | None, text: str = "text") -> Column:
    if net is None:
        return F.lit(1.0)
    bounded_batches()

    @F.arrow_udf(DoubleType())
    def score(texts: pa.Array) -> pa.Array:
        parts = [net.score(t) for _, t in text_chunks(iter([pa.record_batch([texts], names=["text"])]))]
        return pa.array(np.concatenate(parts) if parts else np.zeros(0))

    return score(F.col(text))


def fit_quality(docs: DataFrame, labels: DataFrame) -> Network | None:
    net = train(*labelled_sample(docs, labels, "quality"))
    give_back()
    return net


def op8_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    scored = docs.select("doc_id", F.coalesce(fold() == 0, F.lit(False)).alias("held_out"), score_column(fit_quality(docs, table(spark, sf_dir, "labels"))).alias("score"))
    return scored.withColumn("predicted", (F.col("score") >= 0.3).cast("int"))


QUERIES = {"op8_quality_classifier": op8_quality_classifier}
ORACLES = {}
