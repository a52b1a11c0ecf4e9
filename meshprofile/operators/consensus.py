"""Sums over parties by repeated mixing with neighbours, in four kinds and several engines.

Kinds: plain, boosted, masked_plain, masked_boosted. A round masks every party's state (masked kinds)
and replaces it by the weighted sum of what its neighbourhood said; the weights are the mixing matrix
(plain) or its boosted form, or with form="two_term" the plain mix plus a predictor term. All states tend
to the mean, and a total is the number of parties times it.

Stops: `spectral` (a number of rounds that anyone computes from the public weights), `fixed` (rounds as
given), and two that look at the states: `spread` (a simulator's view of all parties) and `max_consensus`
(parties pass on maxima and minima, exact after a diameter's worth of steps). The latter two run in the
engines that hold all parties of a component together (`driver`, `block`); the others refuse them.

Engines, all with the same result: `array` (SQL lambdas over one array of parties for each component),
`block` (numpy on blocks of components, each component mixing alone, so nothing moves between rounds),
`edge` (a join with the weights a round, for many parties or a message log), `closed` (one join with
matrix powers, no trace), `driver` (numpy on the driver for payloads of a model's size).

Nulls and odd input: a state row whose party, component or value is null adds nothing; a NaN or infinite
value spreads to that component's totals; absent cells are zero, so a party without rows takes part;
repeated rows of a cell add up; an empty state gives no totals; a party number outside the graph raises.
"""

from __future__ import annotations

import uuid
import warnings
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from meshprofile.functions.vectors import array_literal
from meshprofile.operators import masking, topology
from meshprofile.session import STATE, discard, require_schema, settle

KINDS = ("plain", "boosted", "masked_plain", "masked_boosted")
STOPS = ("spectral", "fixed", "spread", "max_consensus")
EPS, DRIVER_CELLS, BLOCK_CELLS, CLOSED_CELLS, BROADCAST_CELLS = 1e-6, 200_000, 100_000, 2_000_000, 200_000
MOST_ROUNDS = 10_000


@dataclass
class Setting:
    """A public graph with everything a run needs: kind, weights, rounds, masks.

    secrets holds one secret for each party (drawn afresh where none are given); every exchange takes a
    nonce of its own, so draws never repeat. scale widens the masks: one factor, or one for each component
    (see families' `ranges`), as plain masks are far narrower than counts. Edges on which one party hears
    everything another hears are dropped where masks are meant to protect (`exposed`: prune, raise, allow).
    """

    pairs: list[tuple[int, int]]
    parties: int
    kind: str = "masked_boosted"
    sigma: float = masking.SIGMA
    beta: float = masking.BETA
    secrets: tuple[str, ...] | None = None
    session: str | None = None
    a: float | None = None
    form: str = "matrix"
    stop: str = "spectral"
    rounds: int = 0
    eps: float = EPS
    exposed: str = "prune"
    scale: float | np.ndarray = 1.0
    w: np.ndarray = field(init=False)
    plain: np.ndarray = field(init=False)
    rho: float = field(init=False)
    exchanges: int = field(init=False, default=0)
    lookup: dict = field(init=False, default_factory=dict, repr=False)

    def __post_init__(self) -> None:
        if self.kind not in KINDS:
            raise ValueError(f"kind is one of {KINDS}, not {self.kind}")
        if self.stop not in STOPS:
            raise ValueError(f"stop is one of {STOPS}, not {self.stop}")
        if self.form not in ("matrix", "two_term"):
            raise ValueError(f"form is matrix or two_term, not {self.form}")
        if self.exposed not in ("prune", "raise", "allow"):
            raise ValueError(f"exposed is prune, raise or allow, not {self.exposed}")
        if self.parties < 1:
            raise ValueError("there must be a party")
        if self.stop == "fixed" and self.rounds < 1 and self.parties > 1:
            raise ValueError("a fixed stop needs a number of rounds")
        if self.parties > 1 and not topology.is_connected(self.pairs, self.parties):
            raise ValueError("the graph is not connected: no total can be reached")
        if self.parties == 2:
            warnings.warn("with two parties, the total less one's own value is the other's", stacklevel=3)
        if "masked" not in self.kind:
            self.sigma = 0.0
        elif self.parties > 2 and self.exposed != "allow":
            found = topology.exposed_pairs(self.pairs)
            if found and self.exposed == "raise":
                raise ValueError(f"exposed edges (watcher, watched): {found}")
            self.pairs = topology.prune_exposed(self.pairs, self.parties)
        if self.secrets is None:
            self.secrets = masking.fresh_secrets(self.parties)
        if len(self.secrets) != self.parties or len(set(self.secrets)) != self.parties:
            raise ValueError("every party needs a secret of its own")
        self.session = uuid.uuid4().hex + "." if self.session is None else self.session
        self.plain = topology.mixing_matrix(self.pairs, self.parties)
        if "boosted" in self.kind:
            self.a = topology.optimal_boost(self.plain) if self.a is None else self.a
        else:
            self.a = 0.0
        self.w = topology.boosted_matrix(self.plain, self.a)
        self.rho = topology.radius(self.w)
        if self.stop == "spectral":
            self.rounds = self.rounds or topology.rounds_needed(self.rho, self.beta if self.sigma else 0.0, self.eps)
        elif self.stop != "fixed":
            self.rounds = self.rounds or MOST_ROUNDS  # a bound; running into it raises
        if self.parties == 1:
            self.rounds = 0

    @property
    def by_state(self) -> bool:
        return self.stop in ("spread", "max_consensus") and self.parties > 1

    def nonce(self) -> str:
        """A name for the next exchange that none before it had."""
        self.exchanges += 1
        return f"{self.session}{self.exchanges - 1}"

    def width(self, comps: list[int]) -> np.ndarray | float:
        return self.scale if np.ndim(self.scale) == 0 else np.asarray(self.scale, float)[comps]

    def width_column(self) -> Column:
        if np.ndim(self.scale) == 0:
            return F.lit(float(self.scale))
        return F.element_at(F.expr(array_literal(np.asarray(self.scale, float).tolist())), F.col("comp") + 1)

    def delta(self, nonce: str, comps: list[int], t: int) -> np.ndarray:
        if t in self.lookup.get((nonce, tuple(comps)), {}):
            return self.lookup[nonce, tuple(comps)][t]
        return masking.delta_array(self.secrets, nonce, comps, t, self.sigma, self.beta) * self.width(comps)

    def theta(self, nonce: str, comps: list[int], t: int) -> np.ndarray:
        return self.delta(nonce, comps, t) - self.delta(nonce, comps, t - 1)

    def prepare(self, nonce: str, comps: list[int]) -> None:
        """A preset table of one exchange's draws for just these components, so that rounds only look them up; replaces the last one."""
        self.lookup = {}
        self.lookup = {(nonce, tuple(comps)): {t: self.delta(nonce, comps, t) for t in range(-1, min(self.rounds, 1000))}}

    def mix(self, said: np.ndarray) -> np.ndarray:
        if self.form == "two_term":
            return (1 + self.a) * (self.plain @ said) - self.a * said
        return self.w @ said


def run_numpy(x: np.ndarray, s: Setting, nonce: str = "0", comps: list[int] | None = None, rounds: int | None = None, trace: list | None = None) -> np.ndarray:
    """States (parties, comps) after all rounds; trace gets (t, shared, state before) each round."""
    return run_counted(x, s, nonce, comps, rounds, trace)[0]


def run_counted(x: np.ndarray, s: Setting, nonce: str = "0", comps: list[int] | None = None, rounds: int | None = None, trace: list | None = None) -> tuple[np.ndarray, int]:
    """The same, and how many rounds it took."""
    comps = list(range(x.shape[1])) if comps is None else comps
    by_state = s.by_state and rounds is None
    every = max(1, topology.diameter(s.pairs, s.parties)) if by_state and s.stop == "max_consensus" else 1
    t = 0
    while t < (s.rounds if rounds is None else rounds):
        shared = x + s.theta(nonce, comps, t) if s.sigma else x
        if trace is not None:
            trace.append((t, shared, x))
        x = s.mix(shared)
        t += 1
        if by_state and t % every == 0 and _agreed(x, s, every):
            return x, t
    if by_state and x.size:
        raise ValueError(f"parties do not agree after {t} rounds")
    return x, t


def _agreed(x: np.ndarray, s: Setting, steps: int) -> bool:
    """Whether the spread is small: seen from outside, or by maxima and minima passed on `steps` times."""
    high, low = x, x
    if s.stop == "max_consensus":
        near = (s.plain > 0) | np.eye(s.parties, dtype=bool)
        for _ in range(steps):
            high, low = np.stack([high[n].max(0) for n in near]), np.stack([low[n].min(0) for n in near])
        high, low = high[0], low[0]
    else:
        high, low = x.max(0), x.min(0)
    return not x.size or (high - low).max() <= s.eps * max(np.abs(high).max(), np.abs(low).max(), 1e-300)


def dense(state: DataFrame, parties: int, comps: list[int] | None = None, most: int | None = None) -> tuple[np.ndarray, list[int]]:
    """A small state on the driver; absent cells are zero (parties without rows take part)."""
    rows = state.select("party", "comp", "x").where("party is not null and comp is not null and x is not null")
    if most is not None:
        rows = rows.limit(most + 1)
    rows = rows.toArrow()
    if most is not None and rows.num_rows > most:
        raise ValueError("the payload is too large for the driver: use block or edge")
    party, comp, x = (rows.column(c).to_numpy() for c in ("party", "comp", "x"))
    if len(party) and not 0 <= party.min() <= party.max() < parties:
        raise ValueError(f"parties run from 0 to {parties - 1}; the state has {party.min()} to {party.max()}")
    comps = sorted(set(comp.tolist())) if comps is None else comps
    out = np.zeros((parties, len(comps)))
    np.add.at(out, (party, np.searchsorted(comps, comp)), x)
    return out, comps


def _to_state(spark: SparkSession, x: np.ndarray, comps: list[int]) -> DataFrame:
    return spark.createDataFrame([(i, c, float(x[i, k])) for i in range(len(x)) for k, c in enumerate(comps)], "party int, comp int, x double")


def _array(state: DataFrame, s: Setting, nonce: str, trace: bool) -> DataFrame:
    m, w = s.parties, array_literal(s.w.tolist() if s.form == "matrix" else s.plain.tolist())
    grid = state.where("comp is not null").groupBy("comp").agg(F.array(*[F.coalesce(F.sum(F.when(F.col("party") == i, F.col("x"))), F.lit(0.0)) for i in range(m)]).alias("x")).withColumn("width", s.width_column())
    keys = "array(" + ", ".join(f"'{k}'" for k in s.secrets) + ")"
    noise = masking.theta_sql(f"{keys}[i]", nonce, "i", "comp", "t", s.sigma, s.beta)
    said = f"transform(acc.x, (v, i) -> v + width * {noise})" if s.sigma else "acc.x"
    mixed = f"transform({w}, row -> aggregate(zip_with(row, shared, (p, q) -> p * q), 0D, (a, b) -> a + b))"
    if s.form == "two_term":
        mixed = f"zip_with({mixed}, shared, (m, v) -> {1 + s.a!r}D * m - {s.a!r}D * v)"
    entry = "concat(acc.log, array(named_struct('t', t, 'shared', shared, 'state', acc.x)))" if trace else "acc.log"
    # a transform over one element binds `shared` for the mix and the log
    step = f"transform(array({said}), shared -> named_struct('x', {mixed}, 'log', {entry}))[0]"
    log = "cast(array() as array<struct<t: int, shared: array<double>, state: array<double>>>)"
    done = f"aggregate(sequence(0, {s.rounds - 1}), named_struct('x', x, 'log', {log}), (acc, t) -> {step})" if s.rounds else f"named_struct('x', x, 'log', {log})"
    out = grid.withColumn("done", F.expr(done))
    if trace:
        rows = out.select("comp", F.explode("done.log").alias("r")).select("comp", "r.t", F.explode(F.arrays_zip(F.sequence(F.lit(0), F.lit(m - 1)).alias("party"), F.col("r.shared").alias("shared"), F.col("r.state").alias("state"))).alias("c"))
        return rows.select("t", F.col("c.party").alias("party"), "comp", F.col("c.shared").alias("shared"), F.col("c.state").alias("state"))
    return out.select("comp", F.posexplode("done.x").alias("party", "x")).select("party", "comp", "x")


def _block(state: DataFrame, s: Setting, nonce: str, trace: bool) -> DataFrame:
    size = max(1, BLOCK_CELLS // max(1, s.parties))

    def work(rows: pa.Table) -> pa.Table:
        party, comp, value = (rows.column(c).to_numpy() for c in ("party", "comp", "x"))
        comps, at = np.unique(comp, return_inverse=True)
        x = np.zeros((s.parties, len(comps)))
        np.add.at(x, (party, at), value)
        log: list | None = [] if trace else None
        end = run_numpy(x, s, nonce, comps.tolist(), trace=log)
        p, c = np.repeat(np.arange(s.parties), len(comps)).astype(np.int32), np.tile(comps, s.parties).astype(np.int32)
        if trace:
            return pa.concat_tables([pa.table({"t": np.full(len(p), t, np.int32), "party": p, "comp": c, "shared": a.ravel(), "state": b.ravel()}) for t, a, b in log])
        return pa.table({"party": p, "comp": c, "x": end.ravel()})

    schema = "t int, party int, comp int, shared double, state double" if trace else "party int, comp int, x double"
    known = state.where("party is not null and comp is not null and x is not null").select("party", "comp", "x")
    return known.withColumn("_b", F.floor(F.col("comp") / size)).groupBy("_b").applyInArrow(lambda rows: work(rows), schema)


def mix_by_join(state: DataFrame, weights: DataFrame, rounds: int, secrets: DataFrame | Column | None = None, nonce: str = "0", sigma: float = 0.0, beta: float = masking.BETA, width: Column | None = None, a: float = 0.0, trace: bool = False, keep_every: int = 5) -> DataFrame:
    """Rounds as joins of the state with weights (src, dst, w): for more parties than a driver's matrix
    holds, or for the log of what was said. secrets (see masking.mask) must be given where sigma is; a adds the
    predictor term to plain weights. The state is written out every few rounds, and what it replaces deleted."""
    if sigma and secrets is None:
        raise ValueError("masks need the parties' secrets")
    parties = weights.select(F.col("src").cast("int").alias("party")).distinct()
    known = state.where("party is not null and comp is not null and x is not null").groupBy("party", "comp").agg(F.sum("x").alias("x"))
    everyone = known.select("comp").distinct().crossJoin(parties)  # the payload itself: components are as many as a model's numbers
    x = everyone.join(known, ["party", "comp"], "left").select("party", "comp", F.coalesce("x", F.lit(0.0)).alias("x"))
    w, log, last = weights.select(F.col("src").cast("int").alias("party"), F.col("dst").cast("int").alias("dst"), "w"), [], None
    for t in range(rounds):
        said = masking.mask(x, t, secrets, nonce, sigma, beta, width) if sigma else x.withColumn("shared", F.col("x"))
        if trace:
            said = settle(said, "messages")
            log.append(said.select(F.lit(t).alias("t"), "party", "comp", "shared", F.col("x").alias("state")))
        x = said.join(w, "party").groupBy(F.col("dst").alias("party"), "comp").agg(F.sum(F.col("w") * F.col("shared")).alias("x"))
        if a:
            x = x.join(said.select("party", "comp", "shared"), ["party", "comp"]).select("party", "comp", ((1 + a) * F.col("x") - a * F.col("shared")).alias("x"))
        if t % keep_every == keep_every - 1:
            x = settle(x, "consensus")
            if last is not None:
                discard(last)
            last = x
    if not trace:
        return x
    out = log[0]
    for more in log[1:]:
        out = out.unionByName(more)
    return out


def _edge(state: DataFrame, s: Setting, nonce: str, trace: bool) -> DataFrame:
    spark, w = state.sparkSession, s.plain if s.form == "two_term" else s.w
    rows = [(i, j, float(w[j, i])) for i in range(s.parties) for j in range(s.parties) if w[j, i]]
    secrets = masking.secret_of(s.secrets) if s.parties <= 256 else masking.secrets_table(spark, s.secrets)
    weights = spark.createDataFrame(rows, "src int, dst int, w double")
    return mix_by_join(state, F.broadcast(weights) if len(rows) <= BROADCAST_CELLS else weights, s.rounds, secrets, nonce, s.sigma, s.beta, s.width_column(), s.a if s.form == "two_term" else 0.0, trace)


def _closed(state: DataFrame, s: Setting, nonce: str) -> DataFrame:
    spark, n = state.sparkSession, s.rounds
    cells = s.parties**2 * (n + 1 if s.sigma else 1)
    if cells > CLOSED_CELLS:
        raise ValueError(f"the closed form of {s.parties} parties and {n} rounds has {cells} weights: use edge")
    powers = [np.eye(s.parties)]
    for _ in range(n):
        powers.append(s.w @ powers[-1])

    def rows(p: np.ndarray, t: int) -> list:
        i, j = np.nonzero(p)
        return list(zip(i.tolist(), j.tolist(), [t] * len(i), p[i, j].tolist()))

    table = rows(powers[n], -1)
    if s.sigma:  # the differences of neighbouring powers carry each round's draw to the end
        table += [r for t in range(n) for r in rows(powers[n - t] - (powers[n - t - 1] if t < n - 1 else 0), t)]
    w = spark.createDataFrame(table, "dst int, party int, t int, w double")
    start = state.select("party", "comp", "x", F.lit(-1).alias("t"))
    if s.sigma:
        grid = state.select("comp").distinct().crossJoin(masking.secrets_table(spark, s.secrets)).withColumn("t", F.explode(F.sequence(F.lit(0), F.lit(n - 1))))
        draw = masking.delta(F.col("secret"), F.lit(nonce), F.col("party"), F.col("comp"), F.col("t"), s.sigma, s.beta) * s.width_column()
        start = start.unionByName(grid.select("party", "comp", draw.alias("x"), "t"))
    return start.join(F.broadcast(w) if len(table) <= BROADCAST_CELLS else w, ["party", "t"]).groupBy(F.col("dst").alias("party"), "comp").agg(F.sum(F.col("w") * F.col("x")).alias("x"))


def run(state: DataFrame, s: Setting, engine: str = "block", nonce: str | None = None, trace: bool = False) -> DataFrame:
    """state (party, comp, x) after s.rounds rounds, or with trace what each party said and held a round.

    Every call is an exchange with draws of its own; a nonce is given only to replay one."""
    require_schema(state, STATE)
    if s.by_state and engine not in ("block", "driver"):
        raise ValueError(f"engine {engine} cannot see when parties agree: use block or driver, or stop by spectral or fixed")
    if engine == "closed" and s.form == "two_term":
        raise ValueError("the closed engine has matrix powers only")
    nonce = s.nonce() if nonce is None else nonce
    if engine == "array":
        return _array(state, s, nonce, trace)
    if engine == "block":
        return _block(state, s, nonce, trace)
    if engine == "edge":
        return _edge(state, s, nonce, trace)
    if engine == "closed" and not trace:
        return _closed(state, s, nonce)
    if engine == "driver" and not trace:
        x, comps = dense(state, s.parties, most=DRIVER_CELLS)
        return _to_state(state.sparkSession, run_numpy(x, s, nonce, comps), comps)
    raise ValueError(f"no engine {engine}{' with a trace' if trace else ''}")


def totals(state: DataFrame, s: Setting, engine: str = "block", nonce: str | None = None) -> DataFrame:
    """(party, comp, total): each party's own view of the sum over parties."""
    return run(state, s, engine, nonce).select("party", "comp", (F.lit(float(s.parties)) * F.col("x")).alias("total"))


def direct_sum(state: DataFrame) -> DataFrame:
    """The same sums by pooling raw summaries: exact, and disclosing."""
    return state.groupBy("comp").agg(F.sum("x").alias("total"))


def masked_moments(profiles: DataFrame, s: Setting, engine: str = "driver") -> tuple[np.ndarray, np.ndarray, float]:
    """Mean, standard deviation and count over all rows, from one masked exchange of 1 + 2 D sums; rows
    without a profile are left out, and no rows give empty arrays and zero."""
    known = profiles.where("y is not null and party is not null")
    first = known.select(F.size("y")).first()
    if first is None:
        return np.zeros(0), np.zeros(0), 0
    d = first[0]
    sums = known.groupBy("party").agg(F.count(F.lit(1)).cast("double").alias("c0"), *[F.sum(F.col("y")[i]).alias(f"c{1 + i}") for i in range(d)], *[F.sum(F.col("y")[i] * F.col("y")[i]).alias(f"c{1 + d + i}") for i in range(d)])
    state = sums.select("party", F.posexplode(F.array(*[f"c{i}" for i in range(1 + 2 * d)])).alias("comp", "x"))
    got = {r["comp"]: r["total"] for r in totals(state, s, engine).where("party = 0").collect()}
    n = round(got[0])
    mean = np.array([got[1 + i] for i in range(d)]) / n
    return mean, np.sqrt(np.maximum(np.array([got[1 + d + i] for i in range(d)]) / n - mean**2, 0)), n
