"""Clusterings as one contract: a sum over rows in every party, a sum over parties, a closed-form update.

A family turns a block of rows and a model into weights z, weighted vector sums s and, for mixtures,
scatter sums h of each cluster, plus its objective; everything is additive over rows and parties, so a
party's payload is one array of K * width + 1 numbers: K blocks (z, s, h) and the objective last.
"""

from __future__ import annotations

from dataclasses import dataclass, field, replace

import numpy as np


@dataclass(frozen=True)
class Model:
    """Centroids mu (K, D); mixtures also weight (K) and sigma: (K, D, D), (K, D) or (K), by cov."""

    mu: np.ndarray
    weight: np.ndarray | None = None
    sigma: np.ndarray | None = None

    @property
    def k(self) -> int:
        return len(self.mu)

    @property
    def d(self) -> int:
        return self.mu.shape[1]

    def gap(self, other: Model) -> float:
        return float(np.abs(self.mu - other.mu).max())

    def rows(self) -> list[tuple]:
        """(k, weight, mu, sigma) rows of plain lists."""
        w = self.weight if self.weight is not None else [None] * self.k
        s = self.sigma if self.sigma is not None else [None] * self.k
        return [(k, None if w[k] is None else float(w[k]), self.mu[k].tolist(), None if s[k] is None else np.ravel(s[k]).tolist()) for k in range(self.k)]


def squared_distances(y: np.ndarray, mu: np.ndarray) -> np.ndarray:
    return ((y[:, None, :] - mu) ** 2).sum(2) if y.size * len(mu) < 1 << 22 else np.maximum((y * y).sum(1)[:, None] - 2 * y @ mu.T + (mu * mu).sum(1), 0)


@dataclass(frozen=True)
class KMeans:
    """Nearest centroid, lowest number on ties. An empty cluster keeps its centroid or, with `reseed`,
    moves to the largest cluster's centroid plus a small public offset."""

    on_empty: str = "keep"
    name: str = "kmeans"

    def width(self, d: int) -> int:
        return 1 + d

    def floats(self, m: Model) -> int:
        return m.k * self.width(m.d) + 1

    def ranges(self, m: Model, rows: float, value: float) -> np.ndarray:
        """Public bound of each number of a payload, from bounds on a party's rows and on a value's size."""
        return np.r_[np.tile(np.r_[rows, np.full(m.d, rows * value)], m.k), 4 * rows * m.d * value**2]

    def share(self, y: np.ndarray, m: Model) -> np.ndarray:
        d2 = squared_distances(y, m.mu)
        return (d2.argmin(1)[:, None] == np.arange(m.k)).astype(float)

    def payload(self, y: np.ndarray, m: Model) -> np.ndarray:
        u = self.share(y, m)
        return np.r_[np.hstack([u.sum(0)[:, None], u.T @ y]).ravel(), squared_distances(y, m.mu).min(1).sum()]

    def update(self, g: np.ndarray, m: Model) -> Model:
        b = g[:-1].reshape(m.k, 1 + m.d)
        z = np.round(b[:, 0])  # counts are whole: exchange error goes
        mu = np.where(z[:, None] >= 1, b[:, 1:] / np.maximum(z, 1)[:, None], m.mu)
        if self.on_empty == "reseed" and (z < 1).any():
            offset = 0.01 * (1 + np.arange(m.d) % 3)
            for k in np.flatnonzero(z < 1):
                mu[k] = mu[int(z.argmax())] + offset * (k + 1)
        return replace(m, mu=mu)

    def lower_is_better(self) -> bool:
        return True


@dataclass(frozen=True)
class FuzzyCMeans:
    """Memberships from distances with exponent m. classical weighs rows by u ** m, as_printed by u.
    A row on centroids shares itself evenly among those."""

    m: float = 2.0
    weighting: str = "classical"
    name: str = "fuzzy"

    def width(self, d: int) -> int:
        return 1 + d

    def floats(self, m: Model) -> int:
        return m.k * self.width(m.d) + 1

    def ranges(self, m: Model, rows: float, value: float) -> np.ndarray:
        return np.r_[np.tile(np.r_[rows, np.full(m.d, rows * value)], m.k), 4 * rows * m.d * value**2]

    def share(self, y: np.ndarray, m: Model) -> np.ndarray:
        d2 = squared_distances(y, m.mu)
        on = d2 <= 0
        with np.errstate(divide="ignore", invalid="ignore"):
            near = np.where(on.any(1), 1.0, d2.min(1))[:, None]
            v = (d2 / near) ** (-1 / (self.m - 1))
        v = np.where(on.any(1, keepdims=True), on, v)
        return v / v.sum(1, keepdims=True)

    def payload(self, y: np.ndarray, m: Model) -> np.ndarray:
        u = self.share(y, m)
        g = u**self.m if self.weighting == "classical" else u
        return np.r_[np.hstack([g.sum(0)[:, None], g.T @ y]).ravel(), (u**self.m * squared_distances(y, m.mu)).sum()]

    def update(self, g: np.ndarray, m: Model) -> Model:
        b = g[:-1].reshape(m.k, 1 + m.d)
        z = b[:, :1]
        return replace(m, mu=np.where(z > 1e-12, b[:, 1:] / np.where(z > 1e-12, z, 1), m.mu))

    def lower_is_better(self) -> bool:
        return True


@dataclass(frozen=True)
class GaussianMixture:
    """Expectation-maximisation. cov: full, diag or spherical. cov_mode: shift scatters about the old mean
    and corrects by the outer product of the move (exact, one exchange); old_mean leaves the correction
    out (inexact). Two exchanges (two_round) are offered by cluster.fit, and equal shift."""

    cov: str = "full"
    cov_mode: str = "shift"
    reg: float = 1e-6
    name: str = "gmm"

    def width(self, d: int) -> int:
        return 1 + d + {"full": d * (d + 1) // 2, "diag": d, "spherical": 1}[self.cov]

    def floats(self, m: Model) -> int:
        return m.k * self.width(m.d) + 1

    def ranges(self, m: Model, rows: float, value: float) -> np.ndarray:
        scatter = np.full(self.width(m.d) - 1 - m.d, 4 * rows * value**2)
        return np.r_[np.tile(np.r_[rows, np.full(m.d, rows * value), scatter], m.k), rows * m.d * 10.0]

    def log_parts(self, y: np.ndarray, m: Model) -> np.ndarray:
        out, d = np.empty((len(y), m.k)), m.d
        for k in range(m.k):
            x = y - m.mu[k]
            if self.cov == "full":
                low = np.linalg.cholesky(m.sigma[k])
                q, logdet = (np.linalg.solve(low, x.T) ** 2).sum(0), 2 * np.log(np.diag(low)).sum()
            else:
                var = np.broadcast_to(m.sigma[k], (d,))
                q, logdet = (x * x / var).sum(1), np.log(var).sum()
            out[:, k] = np.log(max(m.weight[k], 1e-300)) - 0.5 * (d * np.log(2 * np.pi) + logdet + q)
        return out

    def share(self, y: np.ndarray, m: Model) -> np.ndarray:
        p = self.log_parts(y, m)
        p = np.exp(p - p.max(1, keepdims=True))
        return p / p.sum(1, keepdims=True)

    def scatter(self, y: np.ndarray, q: np.ndarray, about: np.ndarray) -> np.ndarray:
        rows, (i, j) = [], np.triu_indices(y.shape[1])
        for k in range(len(about)):
            x = y - about[k]
            if self.cov == "full":
                rows.append(((x * q[:, k : k + 1]).T @ x)[i, j])  # the upper triangle only
            elif self.cov == "diag":
                rows.append(q[:, k] @ (x * x))
            else:
                rows.append([(q[:, k] @ (x * x)).sum() / y.shape[1]])
        return np.array(rows)

    def payload(self, y: np.ndarray, m: Model) -> np.ndarray:
        p = self.log_parts(y, m)
        top = p.max(1, keepdims=True)
        q = np.exp(p - top)
        norm = q.sum(1, keepdims=True)
        q /= norm
        blocks = np.hstack([q.sum(0)[:, None], q.T @ y, self.scatter(y, q, m.mu)])
        return np.r_[blocks.ravel(), (top + np.log(norm)).sum()]

    def update(self, g: np.ndarray, m: Model) -> Model:
        b, d = g[:-1].reshape(m.k, self.width(m.d)), m.d
        z = np.maximum(b[:, 0], 1e-12)
        alive = b[:, 0] > 1e-9
        mu = np.where(alive[:, None], b[:, 1 : 1 + d] / z[:, None], m.mu)
        move = mu - m.mu if self.cov_mode == "shift" else np.zeros_like(mu)
        return Model(mu, z / z.sum(), self.covariance(b[:, 1 + d :] / z[:, None], move, m, alive))

    def covariance(self, h: np.ndarray, move: np.ndarray, m: Model, alive: np.ndarray) -> np.ndarray:
        """Covariances from mean scatters h about the old means; a ridge keeps them positive definite."""
        d = m.d
        if self.cov == "full":
            i, j = np.triu_indices(d)
            out = np.zeros((m.k, d, d))
            out[:, i, j] = h
            out[:, j, i] = h
            out -= move[:, :, None] * move[:, None, :]
            for k in range(m.k):
                low = np.linalg.eigvalsh(out[k])[0]
                out[k] += (self.reg + max(0.0, self.reg - low)) * np.eye(d)
        elif self.cov == "diag":
            out = np.maximum(h - move**2, 0) + self.reg
        else:
            out = np.maximum(h[:, 0] - (move**2).mean(1), 0) + self.reg
        return np.where(alive.reshape(-1, *[1] * (out.ndim - 1)), out, m.sigma)

    def start(self, mu: np.ndarray, variance: float = 1.0) -> Model:
        k, d = mu.shape
        sigma = {"full": np.broadcast_to(np.eye(d) * variance, (k, d, d)), "diag": np.full((k, d), variance), "spherical": np.full(k, variance)}[self.cov]
        return Model(mu, np.full(k, 1 / k), np.array(sigma))

    def lower_is_better(self) -> bool:
        return False


@dataclass
class FitReport:
    family: str
    iterations: int = 0
    rounds_per_iteration: list[int] = field(default_factory=list)
    objective: list[float] = field(default_factory=list)
    disagreement: float = 0.0
    party_seconds: dict[int, float] = field(default_factory=dict)
    consensus_seconds: float = 0.0
    payload_floats: int = 0
    messages: int = 0
    converged: bool = False
