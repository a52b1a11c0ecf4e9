"""Fits: the distributed framework, its centralised and single-party baselines, prediction, choice of K."""

from __future__ import annotations

import time
from collections.abc import Callable, Iterator
from dataclasses import replace

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from meshprofile.functions.hashing import uniform_py
from meshprofile.functions.vectors import array_literal, l2sq
from meshprofile.operators import consensus as cs
from meshprofile.operators.families import FitReport, FuzzyCMeans, GaussianMixture, KMeans, Model
from meshprofile.session import discard, settle

BATCH_ROWS = 4096


def public_random(k: int, d: int, seed: str = "init", scale: float = 1.0, centre: np.ndarray | float = 0.0) -> np.ndarray:
    """Start centroids anyone can draw: hashed uniforms in centre + [0, scale)."""
    return np.array([[uniform_py(f"{seed}:{i}:{j}") for j in range(d)] for i in range(k)]) * scale + centre


def masked_start(profiles: DataFrame, k: int, s: cs.Setting, seed: str = "init") -> np.ndarray:
    """Start centroids around the global mean and spread, both obtained under masks."""
    mean, sd, _ = cs.masked_moments(profiles, s)
    return mean + (public_random(k, len(mean), seed) - 0.5) * 2 * sd


def public_peaks(k: int, d: int, phases: int = 4, width: float = 0.08) -> list[np.ndarray]:
    """Starts anyone can draw for daily profiles: a low base and one peak each, evenly spread over the day, for
    several shifts of the peaks."""
    at = np.arange(d)
    made = []
    for p in range(phases):
        centre = (np.arange(k) + (p + 0.5) / phases) * d / k
        made.append(0.1 + np.exp(-((at - centre[:, None]) ** 2) / (2 * (width * d) ** 2)))
    return made


def sample_rows(profiles: DataFrame, k: int) -> np.ndarray:
    """The k rows first by hash. For simulations only: it publishes raw profiles."""
    rows = profiles.orderBy(F.sha2(F.col("id").cast("string"), 256)).limit(k).select("y").collect()
    return np.array([r[0] for r in rows])


def _matrix(column: pa.Array, d: int | None = None) -> np.ndarray:
    """Rows of an array column of one length, in double precision; nulls inside become NaN."""
    if column.null_count:
        raise ValueError("a profile is null")
    n = np.diff(column.offsets.to_numpy())
    d = (int(n[0]) if len(n) else 0) if d is None else d
    if (n != d).any():
        raise ValueError(f"profiles of {int(n.min())} to {int(n.max())} values, not {d}")
    return column.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(len(column), d)


def usable(profiles: DataFrame) -> DataFrame:
    """(party, y) of the rows that take part in sums: party and profile are there, and hold no null or NaN."""
    return profiles.where("party is not null and y is not null and not exists(y, v -> v is null or isnan(v))").select("party", "y")


def checked(profiles: DataFrame, d: int, parties: int | None) -> int:
    """Number of rows, after a check in one pass that profiles have d values and parties are in the graph."""
    r = profiles.agg(F.count(F.lit(1)).alias("n"), F.min(F.size("y")).alias("a"), F.max(F.size("y")).alias("b"), F.min("party").alias("p"), F.max("party").alias("q")).first()
    if r["n"] and (r["a"] != d or r["b"] != d):
        raise ValueError(f"profiles have {r['a']} to {r['b']} values, the model {d}")
    if r["n"] and parties is not None and not 0 <= r["p"] <= r["q"] < parties:
        raise ValueError(f"parties run from 0 to {parties - 1}; the profiles have {r['p']} to {r['q']}")
    return r["n"]


def payloads(profiles: DataFrame, parts: list[tuple[object, Model]], pooled: bool = False) -> DataFrame:
    """(party, comp, x) sums of several models in one pass, their blocks end to end, and as comp -1 - i the seconds
    part i took: partial sums in numpy over Arrow batches, one row a party and component from each task, then a
    small aggregation. Rows never move by party. pooled sums parties as well (as party 0)."""
    widths = [family.floats(model) for family, model in parts]
    d = parts[0][1].d

    def partial(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums: dict[int, np.ndarray] = {}
        for batch in batches:
            for at in range(0, batch.num_rows, BATCH_ROWS):
                part = batch.slice(at, BATCH_ROWS)
                party, y = part.column("party").to_numpy(), _matrix(part.column("y"), d)
                for p in np.unique(party).tolist():
                    own, got, took = y[party == p], [], []
                    for family, model in parts:
                        began = time.perf_counter()
                        got.append(family.payload(own, model))
                        took.append(time.perf_counter() - began)
                    x = np.concatenate([*got, took])
                    sums[p] = sums[p] + x if p in sums else x
        comps = np.r_[np.arange(sum(widths)), -1 - np.arange(len(parts))].astype(np.int32)
        for p, x in sums.items():
            yield pa.record_batch([pa.array(np.full(len(comps), p, np.int32)), pa.array(comps), pa.array(x)], names=["party", "comp", "x"])

    rows = profiles.select("party", "y").mapInArrow(partial, "party int, comp int, x double")
    rows = rows.withColumn("party", F.lit(0)) if pooled else rows
    return rows.groupBy("party", "comp").agg(F.sum("x").alias("x"))


def _changed(old: Model, new: Model, history: list[float], stop: str, tol: float, moved: int | None) -> bool:
    if stop == "fixed":
        return True
    if stop == "shift":
        return old.gap(new) > tol
    if stop == "objective":
        return len(history) < 2 or abs(history[-1] - history[-2]) > tol * max(1.0, abs(history[-2]))
    return moved != 0


STOPS = ("fixed", "shift", "objective", "assignment")


def fit_many(
    profiles: DataFrame,
    parts: list[tuple[object, Model]],
    setting: cs.Setting | None = None,
    iterations: int = 50,
    stop: str = "shift",
    tol: float = 1e-6,
    engine: str = "auto",
    per_party: bool = False,
    ranges: tuple[float, float] | None = None,
    settled: bool = False,
) -> list[tuple[Model | list[Model], FitReport]]:
    """The framework for several models at once: local payloads, a consensus on them, the updates, until nothing
    moves. Every iteration is one scan and one exchange for all models that still move.

    Without a setting the sums are pooled (the centralised baseline). With one, every iteration ships only what
    the setting's consensus says; engine is consensus.run's, or auto: driver up to consensus.DRIVER_CELLS
    numbers, block beyond, where payloads stay on the executors and the driver gets one party's totals.
    Profiles are written once, unless `settled` says they come from a table, and deleted at the end. Lineage stays
    flat: only models are carried on. per_party gives each party's own model. ranges=(rows, value), public bounds
    on a party's rows and on a value, widens each component's mask to its own range. stop is fixed, shift,
    objective or assignment (no row changes its nearest or likeliest cluster).

    Rows without a party or profile, or with a null or NaN in it, take no part; profiles of another length than
    the models, and parties outside the graph, raise; without rows every model stays as it started.
    """
    if stop not in STOPS:
        raise ValueError(f"stop is one of {STOPS}, not {stop}")
    if engine not in ("auto", "driver") and per_party:
        raise ValueError("models of each party need the driver engine")
    parties = setting.parties if setting else 1
    reports = [FitReport(f.name, payload_floats=f.floats(m) - 1) for f, m in parts]
    models = [[m] * parties if per_party else [m] for _, m in parts]
    known = usable(profiles)
    rows = known if settled else settle(known, "profiles")
    old_scale = setting.scale if setting else None
    try:
        if not checked(rows, parts[0][1].d, setting.parties if setting else None):
            return [(m if per_party else m[0], r) for m, r in zip(models, reports)]
        active = list(range(len(parts)))
        for outer in range(iterations):
            now = [(parts[i][0], models[i][0]) for i in active]
            cuts = np.r_[0, np.cumsum([f.floats(m) for f, m in now])]
            if setting and ranges:
                setting.scale = np.concatenate([f.ranges(m, *ranges) for f, m in now])
            views, spread = _exchange(payloads(rows, now, pooled=setting is None), setting, engine, int(cuts[-1]), [reports[i] for i in active], per_party)
            before = [models[i] for i in active]
            for j, i in enumerate(active):
                family, report = parts[i][0], reports[i]
                own = views[:, cuts[j] : cuts[j + 1]]
                report.disagreement = max(report.disagreement, float(spread[cuts[j] : cuts[j + 1]].max()) if len(spread) else 0.0)
                report.objective.append(float(own[0, -1]))
                models[i] = [family.update(own[p], models[i][p]) for p in range(len(models[i]))]
                report.iterations = outer + 1
            moved = _moved_rows(rows, [(parts[i][0], b[0], models[i][0]) for i, b in zip(active, before)]) if stop == "assignment" else [None] * len(active)
            left = []
            for i, b, n in zip(active, before, moved):
                if _changed(b[0], models[i][0], reports[i].objective, stop, tol, n):
                    left.append(i)
                else:
                    reports[i].converged = True
            active = left
            if not active:
                break
        return [(m if per_party else m[0], r) for m, r in zip(models, reports)]
    finally:
        if setting:
            setting.scale = old_scale
        if not settled:
            discard(rows)


def _exchange(sums: DataFrame, setting: cs.Setting | None, engine: str, width: int, reports: list[FitReport], per_party: bool) -> tuple[np.ndarray, np.ndarray]:
    """Totals as seen by party 0 (or by all with per_party), and the largest disagreement of each component."""
    parties, comps = setting.parties if setting else 1, list(range(width))
    if engine == "auto":
        engine = "driver" if per_party or parties * (width + len(reports)) <= cs.DRIVER_CELLS else "block"
    if setting is None or engine == "driver":
        most = None if setting is None else max(cs.DRIVER_CELLS, 0)
        x, _ = cs.dense(sums, parties, [*range(-len(reports), 0), *comps], most)
        _note_seconds(reports, x[:, : len(reports)][:, ::-1])
        x = x[:, len(reports) :]
        if setting is None:
            return x, np.zeros(0)
        nonce = setting.nonce()
        if not setting.by_state:
            setting.prepare(nonce, comps)
        began = time.perf_counter()
        x, rounds = cs.run_counted(x, setting, nonce, comps)
        _note_consensus(reports, setting, rounds, time.perf_counter() - began)
        views = parties * x
        return views, views.max(0) - views.min(0)
    sums = settle(sums, "payloads")
    seconds, _ = cs.dense(sums.where("comp < 0"), parties, list(range(-len(reports), 0)))
    _note_seconds(reports, seconds[:, ::-1])
    began = time.perf_counter()
    seen = settle(cs.totals(sums.where("comp >= 0"), setting, engine), "totals")
    _note_consensus(reports, setting, setting.rounds, time.perf_counter() - began)
    got = seen.groupBy("comp").agg(F.max(F.when(F.col("party") == 0, F.col("total"))).alias("x"), (F.max("total") - F.min("total")).alias("spread")).toArrow()  # a model's numbers
    view, spread = np.zeros((1, width)), np.zeros(width)
    at = got.column("comp").to_numpy()
    view[0, at], spread[at] = got.column("x").to_numpy(), got.column("spread").to_numpy()
    discard(sums)
    discard(seen)
    return view, spread


def _note_seconds(reports: list[FitReport], seconds: np.ndarray) -> None:
    for i, r in enumerate(reports):
        for p, s in enumerate(seconds[:, i].tolist()):
            r.party_seconds[p] = r.party_seconds.get(p, 0.0) + s


def _note_consensus(reports: list[FitReport], s: cs.Setting, rounds: int, seconds: float) -> None:
    whole = sum(r.payload_floats + 1 for r in reports)
    for r in reports:  # an exchange of several models is shared by the size of their payloads
        r.rounds_per_iteration.append(rounds)
        r.messages += 2 * len(s.pairs) * rounds
        r.consensus_seconds += seconds * (r.payload_floats + 1) / whole


def _moved_rows(profiles: DataFrame, moves: list[tuple[object, Model, Model]]) -> list[int]:
    """How many rows each update has moved to another cluster."""

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        n = np.zeros(len(moves), np.int64)
        for batch in batches:
            y = _matrix(batch.column("y"))
            n += [(f.share(y, a).argmax(1) != f.share(y, b).argmax(1)).sum() if len(y) else 0 for f, a, b in moves]
        yield pa.record_batch([pa.array(np.arange(len(moves), dtype=np.int32)), pa.array(n)], names=["i", "n"])

    got = {r["i"]: r["n"] for r in profiles.select("y").mapInArrow(count, "i int, n long").groupBy("i").agg(F.sum("n").alias("n")).collect()}
    return [got.get(i, 0) for i in range(len(moves))]


def fit(profiles: DataFrame, family, start: Model, setting: cs.Setting | None = None, **how) -> tuple[Model | list[Model], FitReport]:
    """fit_many for one model."""
    return fit_many(profiles, [(family, start)], setting, **how)[0]


def best_of(profiles: DataFrame, family, starts: list[Model], setting: cs.Setting | None = None, **how) -> tuple[Model, FitReport]:
    """Fits from several starts in the same scans; the one with the best objective, which is a total like others."""
    got = fit_many(profiles, [(family, m) for m in starts], setting, **how)
    sign = 1 if family.lower_is_better() else -1
    return min(got, key=lambda g: sign * g[1].objective[-1] if g[1].objective else 0)


def fit_two_round(profiles: DataFrame, family: GaussianMixture, start: Model, setting: cs.Setting, iterations: int = 6) -> Model:
    """Mixtures with a second exchange for the scatter about the new means; equals the one-exchange shift."""
    model, rows = start, settle(usable(profiles), "profiles")
    try:
        if not checked(rows, start.d, setting.parties):
            return start
        comps = list(range(family.floats(start)))
        for _ in range(iterations):
            x, _ = cs.dense(payloads(rows, [(family, model)]).where("comp >= 0"), setting.parties, comps, cs.DRIVER_CELLS)
            moved = family.update(setting.parties * cs.run_numpy(x, setting, setting.nonce(), comps)[0], model)
            second = _AboutNewMean(family, model, moved.mu)
            x, _ = cs.dense(payloads(rows, [(second, model)]).where("comp >= 0"), setting.parties, comps, cs.DRIVER_CELLS)
            b = (setting.parties * cs.run_numpy(x, setting, setting.nonce(), comps)[0])[:-1].reshape(model.k, family.width(model.d))
            z = np.maximum(b[:, 0], 1e-12)
            sigma = family.covariance(b[:, 1 + model.d :] / z[:, None], np.zeros_like(model.mu), model, b[:, 0] > 1e-9)
            model = replace(moved, sigma=sigma)
        return model
    finally:
        discard(rows)


class _AboutNewMean:
    def __init__(self, family: GaussianMixture, old: Model, mu: np.ndarray):
        self.family, self.old, self.mu, self.name = family, old, mu, "gmm"

    def floats(self, m: Model) -> int:
        return self.family.floats(m)

    def payload(self, y: np.ndarray, m: Model) -> np.ndarray:
        q = self.family.share(y, self.old)
        return np.r_[np.hstack([q.sum(0)[:, None], q.T @ y, self.family.scatter(y, q, self.mu)]).ravel(), 0.0]


def fit_kmeans(profiles: DataFrame, mu: np.ndarray, setting: cs.Setting | None = None, on_empty: str = "keep", **how) -> tuple[Model, FitReport]:
    return fit(profiles, KMeans(on_empty), Model(mu), setting, **how)


def fit_fuzzy(profiles: DataFrame, mu: np.ndarray, setting: cs.Setting | None = None, m: float = 2.0, weighting: str = "classical", **how) -> tuple[Model, FitReport]:
    return fit(profiles, FuzzyCMeans(m, weighting), Model(mu), setting, **how)


def fit_gmm(profiles: DataFrame, mu: np.ndarray, setting: cs.Setting | None = None, cov: str = "full", cov_mode: str = "shift", reg: float = 1e-6, variance: float = 1.0, **how) -> tuple[Model, FitReport]:
    family = GaussianMixture(cov, cov_mode, reg)
    return fit(profiles, family, family.start(mu, variance), setting, **how)


def assign_hard(profiles: DataFrame, mu: np.ndarray) -> DataFrame:
    """profiles with k, the nearest centroid (lowest on ties), null for a null profile: SQL lambdas only, no shuffle."""
    df = profiles.withColumn("_d", F.expr(f"transform({array_literal(mu.tolist())}, mu -> {l2sq('y', 'mu')})"))
    return df.withColumn("k", (F.array_position("_d", F.array_min("_d")) - 1).cast("int")).drop("_d")


def assign_shares(profiles: DataFrame, family, model: Model) -> DataFrame:
    """profiles with u, the memberships or responsibilities, and k, their argmax (lowest on ties); null for a null profile."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if not batch.num_rows:
                continue
            there = batch.column("y").is_valid()
            u = family.share(_matrix(batch.column("y").filter(there), model.d), model)
            n = np.where(there.to_numpy(zero_copy_only=False), model.k, 0)
            k = np.full(batch.num_rows, -1, np.int32)
            k[n > 0] = u.argmax(1)
            lists = pa.ListArray.from_arrays(pa.array(np.r_[0, np.cumsum(n)].astype(np.int32)), pa.array(u.ravel()))
            lists = pc.if_else(there, lists, None)
            yield pa.record_batch([*batch.columns, lists, pa.array(k, mask=n == 0)], names=[*batch.schema.names, "u", "k"])

    fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in profiles.schema.fields if f.name not in ("u", "k"))
    return profiles.drop("u", "k").mapInArrow(run, f"{fields}, u array<double>, k int")


def predict(profiles: DataFrame, family, model: Model, soft: bool = False) -> DataFrame:
    if isinstance(family, KMeans) and not soft:
        return assign_hard(profiles, model.mu)
    return assign_shares(profiles, family, model)


def model_df(spark: SparkSession, model: Model) -> DataFrame:
    return spark.createDataFrame(model.rows(), "k int, weight double, mu array<double>, sigma array<double>")


def knee(ks: list[int], values: list[float], rule: str = "knee", threshold: float = 0.1) -> int:
    """The K after which the objective falls little: by distance to the chord, second difference or relative drop."""
    v = np.array(values, float)
    if len(ks) < 3:
        return ks[-1]
    if rule == "knee":
        x = (np.array(ks) - ks[0]) / (ks[-1] - ks[0])
        return ks[int(((1 - x) - (v - v[-1]) / max(v[0] - v[-1], 1e-300)).argmax())]
    if rule == "second_diff":
        return ks[1 + int((v[:-2] - 2 * v[1:-1] + v[2:]).argmax())]
    if rule == "rel_drop":
        drops = (v[:-1] - v[1:]) / np.maximum(v[:-1], 1e-300)
        below = np.flatnonzero(drops < threshold)
        return ks[int(below[0])] if len(below) else ks[-1]
    raise ValueError(f"rule is knee, second_diff or rel_drop, not {rule}")


def select_k(profiles: DataFrame, ks: list[int], starts: Callable[[int], list[np.ndarray]], setting: cs.Setting | None = None, rule: str = "knee", **how) -> tuple[int, list[float]]:
    """The chosen K and the least objective for each K over its starts, all fitted in the same scans."""
    own = [(k, mu) for k in ks for mu in starts(k)]
    got = fit_many(profiles, [(KMeans(), Model(mu)) for _, mu in own], setting, **how)
    values = [min(r.objective[-1] for (k2, _), (_, r) in zip(own, got) if k2 == k) for k in ks]
    return knee(ks, values, rule), values
