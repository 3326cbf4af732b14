"""Convex losses, each with its conjugate and the exact minimiser of one coordinate of the local subproblem.

A loss has a NumPy form (scalars or arrays) for the Arrow pass and a Column form for plans inside the JVM; tests keep them
equal. Duals are kept as ``alpha``; for margin losses a = y * alpha is the bounded quantity. In ``step``, xu is the
product of the point with the running local model and q the curvature of the coordinate; q = 0 for a zero point.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

from taskmesh.functions.vectors import clip


@dataclass(frozen=True)
class Loss:
    """mu: 1 / mu is the smoothness of the loss (None: not smooth); lipschitz: its Lipschitz constant (None: none)."""

    name: str = ""
    mu: float | None = None
    lipschitz: float | None = None
    classification: bool = True

    def value(self, z, y):
        raise NotImplementedError

    def conjugate(self, alpha, y):
        """The conjugate at -alpha."""
        raise NotImplementedError

    def step(self, alpha: float, y: float, xu: float, q: float) -> float:
        """The coordinate's new dual."""
        raise NotImplementedError

    def steps(self, alpha: np.ndarray, y: float, xu: np.ndarray, q: np.ndarray) -> np.ndarray:
        """``step`` of one point under many models at once."""
        return np.array([self.step(float(a), y, float(z), float(c)) for a, z, c in zip(alpha, xu, q, strict=True)])

    def value_column(self, z: Column, y: Column) -> Column:
        raise NotImplementedError

    def conjugate_column(self, alpha: Column, y: Column) -> Column:
        raise NotImplementedError

    def step_column(self, alpha: Column, y: Column, xu: Column, q: Column) -> Column:
        raise NotImplementedError

    def subgradient(self, z: np.ndarray, y: np.ndarray) -> np.ndarray:
        """With respect to z."""
        raise NotImplementedError


@dataclass(frozen=True)
class Hinge(Loss):
    name: str = "hinge"
    lipschitz: float | None = 1.0

    def value(self, z, y):
        return np.maximum(0.0, 1.0 - y * z)

    def conjugate(self, alpha, y):
        return -y * alpha

    def step(self, alpha, y, xu, q):
        if q <= 0:
            return y
        return y * min(1.0, max(0.0, y * alpha + (1.0 - y * xu) / q))

    def steps(self, alpha, y, xu, q):
        return y * np.clip(y * alpha + (1.0 - y * xu) / np.maximum(q, 1e-300), 0.0, 1.0)

    def value_column(self, z, y):
        return F.greatest(F.lit(0.0), 1.0 - y * z)

    def conjugate_column(self, alpha, y):
        return -(y * alpha)

    def step_column(self, alpha, y, xu, q):
        return F.when(q <= 0, y).otherwise(y * clip(y * alpha + (1.0 - y * xu) / q, 0.0, 1.0))

    def subgradient(self, z, y):
        return np.where(y * z < 1.0, -y, 0.0)


@dataclass(frozen=True)
class SmoothHinge(Loss):
    """The hinge, quadratic over a stretch of length s before its kink."""

    s: float = 0.5
    name: str = "smooth_hinge"
    lipschitz: float | None = 1.0

    def __post_init__(self):
        object.__setattr__(self, "mu", self.s)

    def value(self, z, y):
        m = 1.0 - y * z
        return np.where(m <= 0, 0.0, np.where(m >= self.s, m - self.s / 2, m * m / (2 * self.s)))

    def conjugate(self, alpha, y):
        a = y * alpha
        return -a + self.s / 2 * a * a

    def step(self, alpha, y, xu, q):
        a = y * alpha
        return y * min(1.0, max(0.0, a + (1.0 - y * xu - self.s * a) / (q + self.s)))

    def steps(self, alpha, y, xu, q):
        a = y * alpha
        return y * np.clip(a + (1.0 - y * xu - self.s * a) / (q + self.s), 0.0, 1.0)

    def value_column(self, z, y):
        m = 1.0 - y * z
        return F.when(m <= 0, F.lit(0.0)).when(m >= self.s, m - self.s / 2).otherwise(m * m / (2 * self.s))

    def conjugate_column(self, alpha, y):
        a = y * alpha
        return -a + a * a * (self.s / 2)

    def step_column(self, alpha, y, xu, q):
        a = y * alpha
        return y * clip(a + (1.0 - y * xu - a * self.s) / (q + self.s), 0.0, 1.0)

    def subgradient(self, z, y):
        return -y * np.clip((1.0 - y * z) / self.s, 0.0, 1.0)


@dataclass(frozen=True)
class Squared(Loss):
    name: str = "squared"
    mu: float | None = 1.0
    classification: bool = False

    def value(self, z, y):
        return 0.5 * (z - y) ** 2

    def conjugate(self, alpha, y):
        return 0.5 * alpha * alpha - y * alpha

    def step(self, alpha, y, xu, q):
        return alpha + (y - xu - alpha) / (1.0 + q)

    def steps(self, alpha, y, xu, q):
        return self.step(alpha, y, xu, q)

    def value_column(self, z, y):
        return (z - y) * (z - y) * 0.5

    def conjugate_column(self, alpha, y):
        return alpha * alpha * 0.5 - y * alpha

    def step_column(self, alpha, y, xu, q):
        return alpha + (y - xu - alpha) / (q + 1.0)

    def subgradient(self, z, y):
        return z - y


@dataclass(frozen=True)
class Logistic(Loss):
    name: str = "logistic"
    mu: float | None = 4.0
    lipschitz: float | None = 1.0

    def value(self, z, y):
        return np.logaddexp(0.0, -y * z)

    def conjugate(self, alpha, y):
        a = np.clip(y * alpha, 0.0, 1.0)
        with np.errstate(divide="ignore", invalid="ignore"):
            return np.where(a > 0, a * np.log(a), 0.0) + np.where(a < 1, (1 - a) * np.log1p(-a), 0.0)

    def step(self, alpha, y, xu, q):
        """The root of ln(b / (1 - b)) + y * xu + q * (b - a), which rises in b: bisection, sped up by Newton steps inside the bracket."""
        a = min(1.0, max(0.0, y * alpha))
        low, high, b = 1e-15, 1.0 - 1e-15, min(max(a, 1e-3), 1.0 - 1e-3)
        for _ in range(60):
            g = np.log(b / (1.0 - b)) + y * xu + q * (b - a)
            if abs(g) < 1e-12:
                break
            low, high = (b, high) if g < 0 else (low, b)
            newton = b - g / (1.0 / (b * (1.0 - b)) + q)
            b = newton if low < newton < high else 0.5 * (low + high)
        return float(y * b)

    def value_column(self, z, y):
        m = -(y * z)
        return F.when(m > 0, m + F.log1p(F.exp(-m))).otherwise(F.log1p(F.exp(m)))

    def conjugate_column(self, alpha, y):
        a = clip(y * alpha, 0.0, 1.0)
        return F.when(a > 0, a * F.log(a)).otherwise(F.lit(0.0)) + F.when(a < 1, (1.0 - a) * F.log1p(-a)).otherwise(F.lit(0.0))

    def step_column(self, alpha, y, xu, q):
        raise NotImplementedError("the logistic step iterates; use the Arrow pass")

    def subgradient(self, z, y):
        return -y / (1.0 + np.exp(np.clip(y * z, -40, 40)))


@dataclass(frozen=True)
class Absolute(Loss):
    name: str = "absolute"
    lipschitz: float | None = 1.0
    classification: bool = False

    def value(self, z, y):
        return np.abs(z - y)

    def conjugate(self, alpha, y):
        return -y * alpha

    def step(self, alpha, y, xu, q):
        if q <= 0:
            return float(np.sign(y - xu))
        return min(1.0, max(-1.0, alpha + (y - xu) / q))

    def value_column(self, z, y):
        return F.abs(z - y)

    def conjugate_column(self, alpha, y):
        return -(y * alpha)

    def step_column(self, alpha, y, xu, q):
        return F.when(q <= 0, F.signum(y - xu)).otherwise(clip(alpha + (y - xu) / q, -1.0, 1.0))

    def subgradient(self, z, y):
        return np.sign(z - y)


LOSSES = {loss.name: loss for loss in (Hinge(), SmoothHinge(), Squared(), Logistic(), Absolute())}
