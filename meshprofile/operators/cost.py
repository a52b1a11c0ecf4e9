"""Cost measures: payloads, messages, volumes, products, times."""

from __future__ import annotations

import time
from collections.abc import Callable

import numpy as np

from meshprofile.operators import consensus as cs

BYTES = {"float32": 4, "float64": 8}


def payload(family: str, k: int, d: int, triangle: bool = True) -> int:
    """Numbers in one message: counts and sums, for mixtures also scatters (upper triangle or whole)."""
    if family in ("kmeans", "fuzzy"):
        return k * (d + 1)
    if family == "gmm":
        return k * (1 + d + (d * (d + 1) // 2 if triangle else d * d))
    raise ValueError(f"no family {family}")


def message_bytes(floats: int, dtype: str = "float32") -> int:
    return floats * BYTES[dtype]


def upload_bytes(floats: int, degree: int, rounds: int, iterations: int, dtype: str = "float32") -> int:
    """What a party of that degree sends in a whole fit."""
    return message_bytes(floats, dtype) * degree * rounds * iterations


def link_seconds(size: float, mbit_s: float) -> float:
    """Seconds for so many bytes at so many megabits a second (bits, not bytes)."""
    return size * 8 / (mbit_s * 1e6)


def multiplications(n: int, n_i: int, k: int, d: int, degree: int, rounds: int, iterations: int, mode: str = "paper_formula", floats: int | None = None) -> dict[str, float]:
    """Products of the centralised fit and of one party; per_component counts dimensions and payload too."""
    dims, size = (1, 1) if mode == "paper_formula" else (d, floats or payload("kmeans", k, d))
    whole = n * k * dims * iterations
    return {"central": whole, "party_local": whole * n_i / n, "party_consensus": (degree + 1) * rounds * iterations * size}


def timed(work: Callable[[], object], repeat: int = 1) -> tuple[object, float]:
    """Result and median seconds."""
    took = []
    for _ in range(repeat):
        began = time.perf_counter()
        out = work()
        took.append(time.perf_counter() - began)
    return out, float(np.median(took))


def consensus_time(s: cs.Setting, floats: int = 294, seed: int = 0, repeat: int = 3) -> float:
    """Seconds a party spends on one consensus on average, without communication."""
    x = np.random.default_rng(seed).normal(size=(s.parties, floats))
    plain = cs.Setting(s.pairs, s.parties, "boosted", stop="fixed", rounds=s.rounds)
    return timed(lambda: cs.run_numpy(x, plain), repeat)[1] / s.parties
