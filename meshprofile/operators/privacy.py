"""What sharing discloses, and audits of the masks."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from meshprofile.operators import consensus as cs
from meshprofile.operators import masking


def disclose(summary: DataFrame) -> DataFrame:
    """(party, k, n, ratio, mu): what a raw summary (party, k, z, s) tells everyone who sees it."""
    whole = summary.groupBy("party").agg(F.sum("z").alias("n"))
    return summary.join(whole, "party").select("party", "k", "n", F.try_divide("z", "n").alias("ratio"), F.expr("transform(s, v -> try_divide(v, z))").alias("mu"))


def shared_trace(trace: DataFrame, party: int = 0, comp: int | None = None) -> DataFrame:
    out = trace.where(F.col("party") == party)
    return out if comp is None else out.where(F.col("comp") == comp)


def mask_gap(trace: DataFrame) -> DataFrame:
    """Distance between what each party said first and what it held."""
    return trace.where("t = 0").select("party", "comp", F.abs(F.col("shared") - F.col("state")).alias("gap"))


def messages(trace: DataFrame, edges: DataFrame, outer: int = 0) -> DataFrame:
    """The only table that may leave a party: (outer, t, src, dst, comp, x_plus), masked values alone."""
    return trace.join(edges, F.col("party") == F.col("src")).select(F.lit(outer).alias("outer"), "t", "src", "dst", "comp", F.col("shared").alias("x_plus"))


def count_rounding_attack(counts: np.ndarray, s: cs.Setting, scale: float = 1.0) -> float:
    """Share of whole-number starts that a listener finds by rounding the first message; masks times scale."""
    said = counts + scale * s.theta(s.nonce(), list(range(counts.shape[1])), 0)
    return float((np.round(said) == counts).mean())


def rebuild(x: np.ndarray, s: cs.Setting, watcher: int, watched: int, rounds: int = 30) -> np.ndarray:
    """A passive watcher's estimate of the watched party's start: its first message plus every later gap
    between what it said and what the weights predict from the messages the watcher hears. Exact where
    the watcher hears the whole neighbourhood, off where it does not."""
    heard = (s.w[watcher] != 0) | (np.arange(s.parties) == watcher)
    log: list = []
    cs.run_numpy(x, s, s.nonce(), rounds=rounds, trace=log)
    guess = log[0][1][watched].copy()
    for (_, before, _), (_, now, _) in zip(log, log[1:]):
        guess += now[watched] - (s.w[watched] * heard) @ before
    return guess


def repeated_draws(value: float, s: cs.Setting, outers: int) -> float:
    """Error of averaging a party's first messages over iterations in which its start stays the same."""
    said = [value + s.delta(s.nonce(), [0], 0)[0, 0] for _ in range(outers)]
    return abs(float(np.mean(said)) - value)


def guessed_masks(s: cs.Setting, knower: int, nonce: str = "0", comps: int = 16) -> float:
    """Share of the other parties' first draws that a party gets right by computing them with its own secret."""
    own = masking.delta_array((s.secrets[knower],) * s.parties, nonce, list(range(comps)), 0, s.sigma, s.beta)
    true = s.delta(nonce, list(range(comps)), 0)
    others = np.arange(s.parties) != knower
    return float((own[others] == true[others]).mean())


def shared_draws(s: cs.Setting, exchanges: int, comps: int = 16) -> int:
    """How many draws of the first round come back in another of the next exchanges."""
    seen = np.concatenate([s.delta(s.nonce(), list(range(comps)), 0).ravel() for _ in range(exchanges)])
    return len(seen) - len(np.unique(seen))


def audit(x: np.ndarray, counts: np.ndarray, s: cs.Setting) -> dict[str, object]:
    from meshprofile.operators.topology import exposed_pairs

    return {
        "exposed": exposed_pairs(s.pairs),
        "rounded_counts": count_rounding_attack(counts, s),
        "rounded_counts_scaled": count_rounding_attack(counts, s, 100.0),
        "first_gap": float(np.abs(s.theta(s.nonce(), list(range(x.shape[1])), 0)).max()),
        "guessed_masks": guessed_masks(s, 0),
        "shared_draws": shared_draws(s, 8),
    }
