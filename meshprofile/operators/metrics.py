"""Accuracy measures: consensus error, silhouette, squared error, centroid gaps, sizes, parity."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from meshprofile.functions.vectors import l2sq
from meshprofile.session import discard, settle

#: Exact silhouettes: rows of a block, of a tile, and of a part, of which two make a task; parts at most; bytes of
#: totals that a task holds before it hands them on.
BLOCK, TILE, PART, MOST_PARTS, HELD = 8192, 256, 65_536, 512, 256 << 20


def consensus_error(trace: DataFrame, exact: DataFrame, parties: int, by: tuple[str, ...] = ("kind",)) -> DataFrame:
    """Per round: mean and maximum over parties of the relative distance of M times a state from the exact totals (comp, total)."""
    joined = trace.join(exact, "comp")
    per = joined.groupBy(*by, "t", "party").agg((F.sqrt(F.sum(F.pow(parties * F.col("state") - F.col("total"), 2))) / F.sqrt(F.sum(F.col("total") * F.col("total")))).alias("e"))
    return per.groupBy(*by, "t").agg(F.avg("e").alias("mean_error"), F.max("e").alias("max_error"))


def rounds_to(errors: DataFrame, eps: float = 1e-6, by: tuple[str, ...] = ("kind",)) -> DataFrame:
    return errors.groupBy(*by).agg(F.min(F.when(F.col("mean_error") < eps, F.col("t"))).alias("rounds"))


def spread(state: DataFrame, column: str = "x") -> DataFrame:
    """Disagreement of parties for each component."""
    return state.groupBy("comp").agg((F.max(column) - F.min(column)).alias("spread"))


def sse(assigned: DataFrame, model: DataFrame) -> DataFrame:
    """Within-cluster sum of squares of (k, y) rows about model (k, mu): the model, K rows, is broadcast."""
    return assigned.join(F.broadcast(model.select("k", "mu")), "k").agg(F.sum(F.expr(l2sq("y", "mu"))).alias("sse"))


def sizes(assigned: DataFrame) -> DataFrame:
    return assigned.groupBy("k").agg(F.count(F.lit(1)).alias("n"))


def silhouette(assigned: DataFrame, how: str = "squared", sample: int = 2_000) -> float:
    """Mean silhouette of rows (id, k, y). exact compares all pairs in Euclidean distance, block by
    block (quadratic in rows, which stay on the executors); sample does so on the rows first by hash;
    squared is linear in rows: squared distances need only each cluster's count, sums and squares."""
    if how == "sample":
        assigned = assigned.orderBy(F.sha2(F.col("id").cast("string"), 256)).limit(sample)
    if how in ("exact", "sample"):
        return _all_pairs(assigned)
    stats = assigned.select("k", "y", F.expr("aggregate(y, 0D, (a, v) -> a + v * v)").alias("q"))
    d = stats.select(F.size("y")).first()[0]
    per = stats.groupBy("k").agg(F.count(F.lit(1)).alias("n"), F.sum("q").alias("q"), F.array(*[F.sum(F.col("y")[i]) for i in range(d)]).alias("s")).collect()  # K rows
    if len(per) < 2:
        return 0.0
    name = {r["k"]: i for i, r in enumerate(per)}
    n, q, s = np.array([r["n"] for r in per], float), np.array([r["q"] for r in per]), np.array([r["s"] for r in per])

    def linear(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if b.num_rows:
                x = b.column("y").flatten().to_numpy().reshape(b.num_rows, -1)
                own = np.array([name[v] for v in b.column("k").to_pylist()])
                total = n * (x * x).sum(1)[:, None] - 2 * x @ s.T + q
                yield pa.record_batch([pa.array(_from_totals(total, n, own))], names=["s"])

    return stats.select("k", "y").mapInArrow(linear, "s double").agg(F.avg("s")).first()[0]


def _from_totals(total: np.ndarray, n: np.ndarray, own: np.ndarray) -> np.ndarray:
    row = np.arange(len(own))
    inner = total[row, own] / np.maximum(n[own] - 1, 1)
    other = total / n
    other[row, own] = np.inf
    b = other.min(1)
    return np.where(n[own] > 1, (b - inner) / np.maximum(np.maximum(inner, b), 1e-300), 0.0)


def _segments(own: np.ndarray) -> list[tuple[int, slice]]:
    """Of clusters in order: pieces of at most TILE rows of one cluster each."""
    cuts = np.r_[np.flatnonzero(np.r_[True, own[1:] != own[:-1]]), len(own)]
    return [(int(own[lo]), slice(i, min(i + TILE, hi))) for lo, hi in zip(cuts[:-1], cuts[1:]) for i in range(lo, hi, TILE)]


def _add_distances(x: np.ndarray, own: np.ndarray, z: np.ndarray, other: np.ndarray, to_x: np.ndarray, to_z: np.ndarray | None) -> None:
    """Add the distances of two blocks' rows, each in the order of its clusters, to (cluster, row) totals: of x to the
    clusters of z and of z to those of x. A block with itself has no to_z."""
    middle = x.mean(0)
    x, z = x - middle, z - middle
    # squared distances as one product, in tiles that stay in the cache
    left = np.hstack([-2 * x, (x * x).sum(1)[:, None], np.ones((len(x), 1))])
    right = np.vstack([z.T, np.ones(len(z)), (z * z).sum(1)])
    right = [(c, s, np.ascontiguousarray(right[:, s])) for c, s in _segments(other)]
    ones = np.ones(TILE)
    for c, s in _segments(own):
        rows = left[s]
        for c2, s2, columns in right:
            d = rows @ columns
            if d.min() < 0:
                np.maximum(d, 0, out=d)
            np.sqrt(d, out=d)
            if to_z is not None:
                to_z[c, s2] += ones[: len(d)] @ d
            elif s == s2:
                np.fill_diagonal(d, 0)
            to_x[c2, s] += d @ ones[: d.shape[1]]


def _all_pairs(assigned: DataFrame) -> float:
    """Exact mean silhouette: rows are written in blocks, in the order of their clusters. A pair of blocks is gone over
    once, for the rows of both; a task adds up all its pairs and hands on one total for each row and cluster."""
    per = {r["k"]: r["n"] for r in assigned.groupBy("k").agg(F.count(F.lit(1)).alias("n")).orderBy("k").collect()}  # K rows
    if len(per) < 2:
        return 0.0
    name, n = {k: i for i, k in enumerate(per)}, np.array(list(per.values()), float)

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        task, at = TaskContext.get().partitionId(), 0
        held: list[tuple[np.ndarray, np.ndarray]] = []

        def block() -> pa.RecordBatch:
            own, y = (np.concatenate(parts) for parts in zip(*held))
            order = np.argsort(own, kind="stable")
            # the two colours of a block alternate over a task's blocks and over tasks
            return pa.record_batch([pa.array([(task << 32) + at]), pa.array([(task + at) % 2]), pa.array([own[order].tobytes()]), pa.array([y[order].tobytes()])], names=["b", "colour", "own", "y"])

        for whole in batches:
            i = 0
            while i < whole.num_rows:
                b = whole.slice(i, BLOCK - sum(len(own) for own, _ in held))
                held.append((np.array([name[v] for v in b.column("k").to_pylist()], np.int32), b.column("y").flatten().to_numpy(zero_copy_only=False).reshape(b.num_rows, -1)))
                i += b.num_rows
                if sum(len(own) for own, _ in held) == BLOCK:
                    yield block()
                    held, at = [], at + 1
        if held:
            yield block()

    def opened(own: bytes, y: bytes) -> tuple[np.ndarray, np.ndarray]:
        k = np.frombuffer(own, np.int32)
        return np.frombuffer(y).reshape(len(k), -1), k

    def pairs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        totals: dict[int, tuple[bytes, np.ndarray]] = {}

        def given() -> Iterator[pa.RecordBatch]:
            for b, (own, t) in totals.items():
                yield pa.record_batch([pa.array([b]), pa.array([own]), pa.array([t.tobytes()])], names=["b", "own", "t"])
            totals.clear()

        def total(b: int, own: bytes) -> np.ndarray:
            if b not in totals:
                totals[b] = own, np.zeros((len(n), len(own) // 4))
            return totals[b][1]

        for batch in batches:
            for i in range(batch.num_rows):
                r = batch.slice(i, 1).to_pylist()[0]
                same = r["b"] == r["b2"]
                _add_distances(*opened(r["own"], r["y"]), *opened(r["own2"], r["y2"]), total(r["b"], r["own"]), None if same else total(r["b2"], r["own2"]))
                if sum(t.nbytes for _, t in totals.values()) > HELD:
                    yield from given()
        yield from given()

    def widths(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Of totals in the order of their blocks: for each block, the sum of its rows' widths and their number."""
        now, own, t = None, None, None

        def scored() -> pa.RecordBatch:
            w = _from_totals(t.T, n, own)
            return pa.record_batch([pa.array([float(w.sum())]), pa.array([len(w)])], names=["w", "n"])

        for batch in batches:
            for i in range(batch.num_rows):
                r = batch.slice(i, 1).to_pylist()[0]
                more = np.frombuffer(r["t"]).reshape(len(n), -1)
                if r["b"] == now:
                    t = t + more
                    continue
                if now is not None:
                    yield scored()
                now, own, t = r["b"], np.frombuffer(r["own"], np.int32), more
        if now is not None:
            yield scored()

    left = settle(assigned.select("k", "y").mapInArrow(pack, "b long, colour long, own binary, y binary"), "silhouette")
    parts = int(min(-(-n.sum() // PART), MOST_PARTS))
    right = left.select(*[F.col(c).alias(f"{c}2") for c in left.columns])
    # of two blocks, which is the left one depends on their colours, so that all tasks get about as many pairs
    once = (F.col("b") == F.col("b2")) | ((F.col("b") != F.col("b2")) & ((F.col("b") < F.col("b2")) == (F.col("colour") == F.col("colour2"))))
    met = left.repartition(parts).join(right.repartition(parts).hint("shuffle_replicate_nl"), once).drop("colour", "colour2")
    summed = met.mapInArrow(pairs, "b long, own binary, t binary").repartition("b").sortWithinPartitions("b")
    out = summed.mapInArrow(widths, "w double, n long").agg(F.sum("w") / F.sum("n")).first()[0]
    discard(left)
    return out


def silhouettes(profiles: DataFrame, models: list[tuple[object, object]]) -> list[float]:
    """Mean squared-distance silhouette of each model's clusters over all rows, in two passes for all models
    together: rows join their nearest or likeliest cluster, and each cluster's count, sums and squares give
    the distances. A model whose rows share one cluster scores 0, as do empty tables."""
    d, widths = models[0][1].d, [m.k for _, m in models]
    starts = np.r_[0, np.cumsum(widths)]

    def own_clusters(y: np.ndarray) -> list[np.ndarray]:
        return [family.share(y, m).argmax(1) for family, m in models]

    def sums(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros((starts[-1], d + 2))
        for b in batches:
            y = b.column("y").flatten().to_numpy(zero_copy_only=False).reshape(-1, d)
            row = np.hstack([np.ones((len(y), 1)), (y * y).sum(1)[:, None], y])
            for at, own in zip(starts, own_clusters(y)):
                np.add.at(total, at + own, row)
        i = np.flatnonzero(total[:, 0])
        yield pa.record_batch([pa.array(np.repeat(i, d + 2)), pa.array(np.tile(np.arange(d + 2), len(i))), pa.array(total[i].ravel())], names=["c", "i", "v"])

    rows = profiles.where("y is not null").select("y")
    stats = np.zeros((starts[-1], d + 2))
    for r in rows.mapInArrow(sums, "c long, i long, v double").groupBy("c", "i").agg(F.sum("v").alias("v")).collect():  # models' sizes
        stats[r["c"], r["i"]] = r["v"]

    def score(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        got, n_rows = np.zeros(len(models)), 0
        for b in batches:
            y = b.column("y").flatten().to_numpy(zero_copy_only=False).reshape(-1, d)
            q = (y * y).sum(1)[:, None]
            n_rows += len(y)
            for j, own in enumerate(own_clusters(y)):
                part = stats[starts[j] : starts[j + 1]]
                there = np.flatnonzero(part[:, 0])
                if len(y) and len(there) > 1:
                    n, s = part[there, 0], part[there, 2:]
                    got[j] += _from_totals(n * q - 2 * y @ s.T + part[there, 1], n, np.searchsorted(there, own)).sum()
        yield pa.record_batch([pa.array(np.arange(len(models))), pa.array(got), pa.array(np.full(len(models), n_rows))], names=["j", "v", "n"])

    out = {r["j"]: r["v"] / max(r["n"], 1) for r in rows.mapInArrow(score, "j long, v double, n long").groupBy("j").agg(F.sum("v").alias("v"), F.sum("n").alias("n")).collect()}
    return [out.get(j, 0.0) for j in range(len(models))]


def centroid_gap(a: np.ndarray, b: np.ndarray) -> float:
    """Largest distance of a centroid of a from the nearest of b, either way."""
    d = np.sqrt(((a[:, None] - b) ** 2).sum(2))
    return float(max(d.min(1).max(), d.min(0).max()))


def missed(assigned: DataFrame, known: set[int]) -> DataFrame:
    """Rows whose cluster is not among the known ones."""
    return assigned.where(~F.col("k").isin(sorted(known)))


def patterns_known(local_mu: np.ndarray, union_mu: np.ndarray) -> set[int]:
    """Clusters of the union that are the nearest to some local pattern."""
    return set(((local_mu[:, None] - union_mu) ** 2).sum(2).argmin(1).tolist())


def parity(a: DataFrame, b: DataFrame) -> DataFrame:
    """One row: rows, and rows whose cluster is the same in both of (id, k)."""
    both = a.select("id", "k").join(b.select("id", F.col("k").alias("k2")), "id")
    return both.agg(F.count(F.lit(1)).alias("n"), F.sum((F.col("k") == F.col("k2")).cast("long")).alias("equal"))


def purity(assigned: DataFrame, label: str) -> DataFrame:
    """One row: the share of rows that carry their cluster's commonest label."""
    per = assigned.groupBy("k", label).agg(F.count(F.lit(1)).alias("n")).groupBy("k").agg(F.max("n").alias("top"), F.sum("n").alias("n"))
    return per.agg((F.sum("top") / F.sum("n")).alias("purity"))
