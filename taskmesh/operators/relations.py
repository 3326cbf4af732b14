"""How tasks relate: the regularizer, its map from shared vectors to weights, and updates of a learned relation.

A quadratic regularizer tr(W A W') with A = lam1 * Omega + lam2 * I has the weights w_t = sum_s K_ts v_s with
K = inverse(2 A). Only K's diagonal enters local subproblems: one number per task, ``kappa``. ``sigma`` bounds how far
joint curvature can exceed the tasks' own, so that all local changes may be added up.

Relations of a closed form (independent, mean, cluster) also mix as a DataFrame plan, for any number of tasks; dense ones
live on the driver and refuse more than ``MAX_DENSE_TASKS``.
"""

from __future__ import annotations

from dataclasses import dataclass, field, replace

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from taskmesh.operators.vector_aggregates import vector_mean

MAX_DENSE_TASKS = 2000


def largest_ratio(k: np.ndarray) -> float:
    """The largest eigenvalue of K after scaling its diagonal to one."""
    d = 1.0 / np.sqrt(np.diag(k))
    return float(np.linalg.eigvalsh(d[:, None] * k * d[None, :])[-1])


def gershgorin(k: np.ndarray) -> float:
    return float((np.abs(k).sum(axis=1) / np.diag(k)).max())


@dataclass(frozen=True)
class Relation:
    """m tasks, in the order the caller keeps. curvature: 'tight', or 'doubled', a valid and more careful choice."""

    lam1: float = 1.0
    lam2: float = 1.0
    curvature: str = "tight"

    def gram(self, m: int) -> np.ndarray:
        """A of the regularizer tr(W A W')."""
        raise NotImplementedError

    def kernel(self, m: int) -> np.ndarray:
        if m > MAX_DENSE_TASKS:
            raise ValueError(f"a dense relation of {m} tasks; at most {MAX_DENSE_TASKS}")
        return np.linalg.inv(2 * self.gram(m))

    def kappa(self, m: int) -> np.ndarray:
        return np.diag(self.kernel(m)) * (2.0 if self.curvature == "doubled" else 1.0)

    def mix(self, v: np.ndarray) -> np.ndarray:
        return self.kernel(len(v)) @ v

    def sigma(self, m: int, rule: str | float = "spectral", gamma: float = 1.0) -> float:
        """spectral <= gershgorin <= trace (the number of tasks); a number is taken as it is."""
        if isinstance(rule, float | int):
            return float(rule)
        if rule == "trace":
            return gamma * m
        k = self.kernel(m)
        return gamma * (largest_ratio(k) if rule == "spectral" else gershgorin(k))

    def penalty(self, w: np.ndarray) -> float:
        return float(np.sum(w * (self.gram(len(w)) @ w)))

    def conjugate(self, v: np.ndarray) -> float:
        return 0.5 * float(np.sum(v * self.mix(v)))

    def update(self, w: np.ndarray) -> Relation:
        """The relation that fits these weights best; a known relation stays."""
        return self


@dataclass(frozen=True)
class IndependentRelation(Relation):
    """No relation: every task by itself."""

    lam1: float = 0.0

    def gram(self, m):
        return self.lam2 * np.eye(m)

    def kappa(self, m):
        return np.full(m, 0.5 / self.lam2) * (2.0 if self.curvature == "doubled" else 1.0)

    def mix(self, v):
        return v / (2 * self.lam2)

    def sigma(self, m, rule="spectral", gamma=1.0):
        return float(rule) if isinstance(rule, float | int) else gamma * (m if rule == "trace" else 1.0)

    def penalty(self, w):
        return self.lam2 * float((w * w).sum())


class PooledRelation(IndependentRelation):
    """One model for all: the caller gives every point the same task."""


@dataclass(frozen=True)
class ClusterRelation(Relation):
    """Tasks pull towards the mean of their cluster. clusters: of each task; k: number to learn, None if they are known."""

    clusters: tuple[int, ...] = ()
    k: int | None = None
    starts: int = 6
    seed: int = 0

    def _ids(self, m: int) -> np.ndarray:
        return np.asarray(self.clusters if self.clusters else range(m))

    def gram(self, m):
        ids = self._ids(m)
        same = ids[:, None] == ids[None, :]
        return self.lam1 * (np.eye(m) - same / same.sum(axis=1)[:, None]) + self.lam2 * np.eye(m)

    def _means(self, v: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        _, at, size = np.unique(self._ids(len(v)), return_inverse=True, return_counts=True)
        total = np.zeros((len(size), v.shape[1]))
        np.add.at(total, at, v)
        return (total / size[:, None])[at], size[at]

    def kappa(self, m):
        _, at, size = np.unique(self._ids(m), return_inverse=True, return_counts=True)
        c = size[at]
        return 0.5 * ((1 - 1 / c) / (self.lam1 + self.lam2) + 1 / (c * self.lam2)) * (2.0 if self.curvature == "doubled" else 1.0)

    def mix(self, v):
        mean, _ = self._means(v)
        return 0.5 * ((v - mean) / (self.lam1 + self.lam2) + mean / self.lam2)

    def sigma(self, m, rule="spectral", gamma=1.0):
        if rule not in ("spectral", "gershgorin"):
            return super().sigma(m, rule, gamma)
        return gamma * self.largest_sigma(int(np.unique(self._ids(m), return_counts=True)[1].max()))

    def largest_sigma(self, c: int) -> float:
        """Of a largest cluster of c tasks, by both rules: its kernel has no negative entry, so the row sums are an eigenvalue."""
        return 1 / ((1 - 1 / c) * self.lam2 / (self.lam1 + self.lam2) + 1 / c)

    def penalty(self, w):
        mean, _ = self._means(w)
        return self.lam1 * float(((w - mean) ** 2).sum()) + self.lam2 * float((w * w).sum())

    def update(self, w):
        if self.k is None:
            return self
        return replace(self, clusters=tuple(int(c) for c in kmeans_tasks(w, self.k, self.starts, self.seed)))


def MeanRelation(m: int, lam1: float = 1.0, lam2: float = 1.0) -> ClusterRelation:
    """All tasks in one cluster."""
    return ClusterRelation(lam1=lam1, lam2=lam2, clusters=(0,) * m)


def kmeans_tasks(w: np.ndarray, k: int, starts: int = 6, seed: int = 0, rounds: int = 50) -> np.ndarray:
    """Clusters of the rows; the best of several seeded starts, numbered by their smallest member; an empty cluster takes the
    row that is farthest from its own."""
    best, best_cost = np.zeros(len(w), int), np.inf
    k = min(k, len(w))

    def distances(c: np.ndarray) -> np.ndarray:
        apart = w - c
        return np.einsum("ij,ij->i", apart, apart)

    squares, every = np.einsum("ij,ij->i", w, w), np.arange(k)
    for start in range(starts):
        rng = np.random.default_rng([seed, start])
        centres = [w[rng.integers(len(w))]]
        while len(centres) < k:
            d = np.min([distances(c) for c in centres], axis=0)
            centres.append(w[rng.choice(len(w), p=d / d.sum())] if d.sum() > 0 else w[rng.integers(len(w))])
        centres = np.array(centres)
        for _ in range(rounds):
            d = squares[:, None] - 2 * (w @ centres.T) + np.einsum("ij,ij->i", centres, centres)
            own = d.argmin(axis=1)
            for c in range(k):
                if not (own == c).any():
                    own[d[np.arange(len(w)), own].argmax()] = c
            members = (own[:, None] == every).astype(float)
            size = members.sum(axis=0)[:, None]
            new = np.where(size > 0, members.T @ w / np.maximum(size, 1), centres)
            if np.allclose(new, centres):
                break
            centres = new
        cost = float(((w - centres[own]) ** 2).sum())
        if cost < best_cost - 1e-12:
            best, best_cost = own, cost
    order = {c: r for r, c in enumerate(dict.fromkeys(best.tolist()))}
    return np.array([order[c] for c in best.tolist()])


@dataclass(frozen=True)
class DenseRelation(Relation):
    """Any positive semi-definite Omega, given."""

    omega: np.ndarray = field(default_factory=lambda: np.zeros((0, 0)))

    def gram(self, m):
        return self.lam1 * np.asarray(self.omega) + self.lam2 * np.eye(m)


def GraphRelation(edges: list[tuple[int, int, float]], m: int, lam1: float = 1.0, lam2: float = 1.0) -> DenseRelation:
    """A known graph: the weighted Laplacian."""
    omega = np.zeros((m, m))
    for i, j, w in edges:
        omega[i, i] += w
        omega[j, j] += w
        omega[i, j] -= w
        omega[j, i] -= w
    return DenseRelation(lam1=lam1, lam2=lam2, omega=omega)


@dataclass(frozen=True)
class SpectralClusterRelation(Relation):
    """Clusters relaxed to a projector on k directions: those of the tasks' Gram matrix with the largest eigenvalues."""

    k: int = 2
    projector: np.ndarray | None = None

    def gram(self, m):
        p = np.zeros((m, m)) if self.projector is None else self.projector
        omega = np.zeros((m, m)) if self.projector is None else np.eye(m) - p
        return self.lam1 * omega + self.lam2 * np.eye(m)

    def update(self, w):
        _, vectors = np.linalg.eigh(w @ w.T)
        top = vectors[:, -min(self.k, len(w)) :]
        return replace(self, projector=top @ top.T)


@dataclass(frozen=True)
class ConvexClusterRelation(Relation):
    """lam1 * tr(W inverse(eta I + S) W') with 0 <= S <= I and trace k: a jointly convex relaxation; S by water-filling."""

    k: int = 2
    eta: float = 0.1
    s: np.ndarray | None = None

    def gram(self, m):
        s = np.eye(m) * min(1.0, self.k / m) if self.s is None else self.s
        return self.lam1 * np.linalg.inv(self.eta * np.eye(m) + s)

    def update(self, w):
        values, vectors = np.linalg.eigh(w @ w.T)
        root = np.sqrt(np.maximum(values, 0))
        low, high = 1e-12, (root.max() + 1e-9) / self.eta
        k = min(self.k, len(w))
        for _ in range(200):  # s_i = clip(root_i / t - eta, 0, 1); the sum falls in t
            t = 0.5 * (low + high)
            low, high = (t, high) if np.clip(root / t - self.eta, 0, 1).sum() > k else (low, t)
        return replace(self, s=(vectors * np.clip(root / low - self.eta, 0, 1)) @ vectors.T)


@dataclass(frozen=True)
class CovarianceRelation(Relation):
    """lam1 * tr(W inverse(Omega) W') + lam2 * |W|^2 with trace one: Omega is the normalised root of the tasks' Gram matrix."""

    floor: float = 1e-3
    omega: np.ndarray | None = None

    def gram(self, m):
        omega = np.eye(m) / m if self.omega is None else self.omega
        return self.lam1 * np.linalg.inv(omega) + self.lam2 * np.eye(m)

    def update(self, w):
        values, vectors = np.linalg.eigh(w @ w.T)
        root = np.sqrt(np.maximum(values, 0))
        root = np.maximum(root / max(root.sum(), 1e-12), self.floor / len(w))
        return replace(self, omega=(vectors * (root / root.sum())) @ vectors.T)


@dataclass(frozen=True)
class SparsePrecisionRelation(Relation):
    """lam1 * tr(W Omega W') - lam_d * logdet(Omega) + lam_s * |Omega|_1: a sparse precision of tasks, by proximal steps."""

    lam_d: float = 1.0
    lam_s: float = 0.1
    steps: int = 100
    omega: np.ndarray | None = None

    def gram(self, m):
        return self.lam1 * (np.eye(m) if self.omega is None else self.omega) + self.lam2 * np.eye(m)

    def _cost(self, s: np.ndarray, omega: np.ndarray) -> float:
        sign, logdet = np.linalg.slogdet(omega)
        return np.inf if sign <= 0 else float((s * omega).sum() - self.lam_d * logdet + self.lam_s * np.abs(omega - np.diag(np.diag(omega))).sum())

    def update(self, w):
        m = len(w)
        s = self.lam1 * (w @ w.T)
        omega = np.eye(m) if self.omega is None else self.omega
        rate = 1.0
        for _ in range(self.steps):
            grad = s - self.lam_d * np.linalg.inv(omega)
            while rate > 1e-12:
                new = omega - rate * grad
                off = np.sign(new) * np.maximum(np.abs(new) - rate * self.lam_s, 0)
                np.fill_diagonal(off, np.diag(new))
                if np.linalg.eigvalsh(off)[0] > 1e-8 and self._cost(s, off) <= self._cost(s, omega) + 1e-12:
                    break
                rate /= 2
            else:
                break
            if np.abs(off - omega).max() < 1e-9:
                break
            omega, rate = off, rate * 1.5
        return replace(self, omega=omega)


def mix_frame(shared: DataFrame, clusters: DataFrame | None, lam1: float, lam2: float) -> DataFrame:
    """shared: task_id, v. clusters: task_id, cluster_id, or None for independent tasks. Weights for any number of tasks:
    one pre-aggregated shuffle for the means, one join by cluster; no task's vector meets another's."""
    if clusters is None:
        return shared.select("task_id", F.transform("v", lambda x: x / (2 * lam2)).alias("w"))
    joined = shared.join(clusters, "task_id")
    means = vector_mean(joined, ["cluster_id"], "v", "mean")
    own, common = 0.5 / (lam1 + lam2), 0.5 / lam2
    return joined.join(means, "cluster_id").select("task_id", F.zip_with("v", "mean", lambda x, c: (x - c) * own + c * common).alias("w"))
