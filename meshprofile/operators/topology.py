"""Graphs of parties: mixing weights, spectrum, boost, exposure, connectivity."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from meshprofile.functions.hashing import uniform
from meshprofile.session import discard, settle

DRIVER_PARTIES = 5_000


def degrees(edges: DataFrame) -> DataFrame:
    return edges.groupBy("src").agg(F.count(F.lit(1)).cast("int").alias("d"))


def mixing(edges: DataFrame) -> DataFrame:
    """(src, dst, w): Metropolis weights 1 / (1 + the larger degree) on edges, the rest on the diagonal."""
    d = degrees(edges)
    off = edges.join(d, "src").join(d.select(F.col("src").alias("dst"), F.col("d").alias("d2")), "dst").select("src", "dst", (1 / (1 + F.greatest("d", "d2"))).alias("w"))
    return off.unionByName(off.groupBy("src").agg((1 - F.sum("w")).alias("w")).select("src", F.col("src").alias("dst"), "w"))


def boost(weights: DataFrame, a: float) -> DataFrame:
    """The two-term predictor folded into one matrix: (1 + a) w, less a on the diagonal."""
    return weights.withColumn("w", (1 + F.lit(a)) * F.col("w") - F.when(F.col("src") == F.col("dst"), F.lit(a)).otherwise(0.0))


def matrix(weights: DataFrame) -> np.ndarray:
    """Weights as a dense array on the driver; parties must be 0..M-1 and at most DRIVER_PARTIES."""
    m = weights.agg(F.max("src")).first()[0] + 1
    if m > DRIVER_PARTIES:
        raise ValueError(f"{m} parties: use spectrum_by_iteration and the edge engine")
    out = np.zeros((m, m))
    for r in weights.collect():
        out[r["src"], r["dst"]] = r["w"]
    return out


def mixing_matrix(pairs: list[tuple[int, int]], parties: int | None = None) -> np.ndarray:
    """The same matrix straight from undirected pairs, for small graphs."""
    m = parties or (max(max(p) for p in pairs) + 1 if pairs else 1)
    d = np.zeros(m)
    for a, b in pairs:
        d[[a, b]] += 1
    w = np.zeros((m, m))
    for a, b in pairs:
        w[a, b] = w[b, a] = 1 / (1 + max(d[a], d[b]))
    return w + np.diag(1 - w.sum(1))


def optimal_boost(w: np.ndarray) -> float:
    """The coefficient for which the boosted matrix forgets its start fastest; 0 where nothing can be gained."""
    e = np.sort(np.linalg.eigvalsh(w))
    if len(e) < 2:
        return 0.0
    low, second = e[0], e[-2]
    return float((second + low) / (2 - second - low))


def boosted_matrix(w: np.ndarray, a: float | None = None) -> np.ndarray:
    a = optimal_boost(w) if a is None else a
    return (1 + a) * w - a * np.eye(len(w))


def radius(w: np.ndarray) -> float:
    """Spectral radius of w less the averaging matrix: the factor by which a round shrinks the error."""
    m = len(w)
    return float(np.abs(np.linalg.eigvalsh(w - np.full((m, m), 1 / m))).max()) if m > 1 else 0.0


def spectrum(w: np.ndarray) -> dict[str, float]:
    e = np.sort(np.linalg.eigvalsh(w))
    a = optimal_boost(w)
    return {"lambda2": float(e[-2]) if len(e) > 1 else 0.0, "lambda_min": float(e[0]), "a": a, "rho_plain": radius(w), "rho_boosted": radius(boosted_matrix(w, a))}


def spectrum_by_iteration(weights: DataFrame, rounds: int = 80) -> dict[str, float]:
    """lambda2 and lambda_min for graphs too large for the driver: power iteration by joins on the
    weights, the constant vector deflated; each vector is written before the next."""

    def largest(sign: float) -> float:
        x = weights.select("src").distinct().select(F.col("src").alias("dst"), (uniform(F.col("src").cast("string")) - 0.5).alias("x"))
        norm, last = 1.0, None
        for t in range(rounds):
            about = x.agg(F.avg("x").alias("m"), F.sqrt(F.sum(F.col("x") * F.col("x"))).alias("n")).first()
            x = x.select("dst", ((F.col("x") - F.lit(about["m"])) / F.lit(about["n"])).alias("x"))
            moved = weights.join(x, "dst").groupBy("src").agg(F.sum(F.col("w") * F.col("x")).alias("ax"))
            x = moved.withColumnRenamed("src", "dst").join(x, "dst").select("dst", ((F.col("x") + sign * F.col("ax")) / 2).alias("x"))
            x = settle(x, "power")  # both halves of a round read it
            if last is not None:
                discard(last)
            last = x
            norm = x.agg(F.sqrt(F.sum(F.col("x") * F.col("x")))).first()[0] if t == rounds - 1 else norm
        return norm

    second, low = 2 * largest(1.0) - 1, 1 - 2 * largest(-1.0)
    return {"lambda2": second, "lambda_min": low, "a": (second + low) / (2 - second - low)}


def rounds_needed(rho: float, beta: float = 0.0, eps: float = 1e-6) -> int:
    """Rounds until the start or the masks, whichever lasts longer, have shrunk to eps."""
    rate = max(rho, beta)
    return 1 if rate <= 0 else max(1, math.ceil(math.log(eps) / math.log(rate)))


def closed_neighbourhoods(edges: DataFrame) -> DataFrame:
    return edges.groupBy("src").agg(F.array_union(F.collect_set("dst"), F.array(F.first("src"))).alias("near"))


def exposed(edges: DataFrame) -> DataFrame:
    """(watcher, watched): edges on which the watcher hears everything the watched hears and says."""
    n = closed_neighbourhoods(edges)
    both = edges.join(n, "src").join(n.select(F.col("src").alias("dst"), F.col("near").alias("near2")), "dst")
    return both.where(F.size(F.array_except("near2", "near")) == 0).select(F.col("src").alias("watcher"), F.col("dst").alias("watched"))


def exposed_pairs(pairs: list[tuple[int, int]]) -> list[tuple[int, int]]:
    near: dict[int, set[int]] = {}
    for a, b in pairs:
        near.setdefault(a, {a}).add(b)
        near.setdefault(b, {b}).add(a)
    return sorted((i, j) for a, b in pairs for i, j in ((a, b), (b, a)) if near[j] <= near[i])


def is_connected(pairs: list[tuple[int, int]], parties: int) -> bool:
    seen, todo = {0}, [0]
    near: dict[int, list[int]] = {}
    for a, b in pairs:
        near.setdefault(a, []).append(b)
        near.setdefault(b, []).append(a)
    while todo:
        for j in near.get(todo.pop(), []):
            if j not in seen:
                seen.add(j)
                todo.append(j)
    return len(seen) == parties


def prune_exposed(pairs: list[tuple[int, int]], parties: int) -> list[tuple[int, int]]:
    """Edges after refusals: the first exposed edge goes, again and again; raises if a party would be cut off."""
    left = sorted(pairs)
    while found := exposed_pairs(left):
        a, b = sorted(found[0])
        left.remove((a, b))
        if not is_connected(left, parties):
            raise ValueError(f"without the exposed edge {a}-{b} the graph falls apart")
    return left


def diameter(pairs: list[tuple[int, int]], parties: int) -> int:
    w = np.eye(parties, dtype=bool)
    for a, b in pairs:
        w[a, b] = w[b, a] = True
    reach, steps = np.eye(parties, dtype=bool), 0
    while not reach.all():
        new = (reach.astype(int) @ w) > 0
        if (new == reach).all():
            raise ValueError("the graph is not connected")
        reach, steps = new, steps + 1
    return steps


def connected_components(edges: DataFrame) -> DataFrame:
    """(src, component), component the least party reachable. Every round a party takes the least label around it,
    then its label's label; rounds grow with the logarithm of the diameter, so there is no bound on them.
    Each round's labels are written and the last ones deleted. Edges with a null end are left out."""
    edges = edges.where("src is not null and dst is not null").select("src", "dst")
    label = settle(edges.select("src").distinct().withColumn("component", F.col("src")), "labels")
    while True:
        near = edges.join(label.select(F.col("src").alias("dst"), "component"), "dst").groupBy("src").agg(F.min("component").alias("c"))
        hooked = settle(label.join(near, "src", "left").select("src", F.least("component", F.coalesce("c", "component")).alias("component"), F.col("component").alias("was")), "labels")
        up = hooked.select(F.col("src").alias("component"), F.col("component").alias("root"))
        new = settle(hooked.join(up, "component", "left").select("src", F.coalesce("root", "component").alias("component"), "was"), "labels")
        discard(label)
        done = new.where("component <> was").isEmpty()
        discard(hooked)
        label = new
        if done:
            return label.drop("was")


def degree_stats(edges: DataFrame) -> DataFrame:
    """One row: parties, edges, mean degree, mean degree + 1 (products a round), edges per party."""
    d = degrees(edges)
    return d.agg(
        F.count(F.lit(1)).alias("parties"),
        (F.sum("d") / 2).cast("long").alias("edges"),
        F.avg("d").alias("mean_degree"),
        (F.avg("d") + 1).alias("mean_extended"),
        (F.sum("d") / 2 / F.count(F.lit(1))).alias("edges_per_party"),
        F.max("d").cast("long").alias("max_degree"),
    )
