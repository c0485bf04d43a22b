"""Distributions of configurations and their refitting from observed losses."""

from __future__ import annotations

from dataclasses import dataclass, replace
from statistics import NormalDist

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

_N = NormalDist()
FLOOR = 1e-12


def midpoints(s: int) -> list[float]:
    """s fixed quantiles in the middle of equal shares."""
    return [(i + 0.5) / s for i in range(s)]


@dataclass(frozen=True)
class NormalPhi:
    """A normal distribution of the step, cut off to (lo, hi) by its inverse; `log` makes it one of the step's logarithm."""

    mu: float
    sigma: float
    lo: float = float("-inf")
    hi: float = float("inf")
    log: bool = False

    def __post_init__(self):
        for name in ("mu", "sigma", "lo", "hi"):  # numpy's numbers would not go into rows
            object.__setattr__(self, name, float(getattr(self, name)))

    def _at(self, v: float) -> float:
        return (v - self.mu) / max(self.sigma, FLOOR)

    def quantile(self, u: float) -> float:
        a = _N.cdf(self._at(self.lo)) if self.lo > float("-inf") else 0.0
        b = _N.cdf(self._at(self.hi)) if self.hi < float("inf") else 1.0
        v = self.mu + self.sigma * _N.inv_cdf(min(1 - 1e-12, max(1e-12, a + u * (b - a))))
        return float(np.exp(v)) if self.log else v

    def sample(self, s: int, seed: int | None = None) -> list[float]:
        """Fixed quantiles without a seed, else seeded draws."""
        us = midpoints(s) if seed is None else np.random.default_rng(seed).random(s).tolist()
        return [self.quantile(u) for u in us]


@dataclass(frozen=True)
class MixturePhi:
    """A mixture of normal distributions."""

    pi: tuple[float, ...]
    mu: tuple[float, ...]
    sigma: tuple[float, ...]

    def sample(self, s: int, seed: int = 0) -> list[float]:
        r = np.random.default_rng(seed)
        which = np.searchsorted(np.cumsum(self.pi) / sum(self.pi), r.random(s), side="right")
        return [float(self.mu[c] + self.sigma[c] * r.standard_normal()) for c in np.minimum(which, len(self.pi) - 1)]

    def log_likelihood(self, alphas, weights) -> float:
        a = np.asarray(alphas, dtype=float)[:, None]
        p = np.array(self.pi) * np.exp(-((a - self.mu) ** 2) / (2 * np.array(self.sigma) ** 2)) / np.array(self.sigma)
        return float(np.asarray(weights) @ np.log(p.sum(axis=1) + 1e-300))


@dataclass(frozen=True)
class BivariatePhi:
    """A normal distribution of step and batch size. Batch sizes are rounded and held between 1 and most."""

    mean: tuple[float, float] = (0.1, 1000.0)
    cov: tuple[tuple[float, float], tuple[float, float]] = ((0.1, 10.0), (10.0, 10000.0))
    least: float = 1e-6
    most: int = 1 << 31

    def sample(self, s: int, seed: int = 0) -> list[tuple[float, int]]:
        root = np.linalg.cholesky(_repaired(np.array(self.cov)))
        z = np.random.default_rng(seed).standard_normal((s, 2)) @ root.T + np.array(self.mean)
        return [(max(self.least, float(a)), int(min(self.most, max(1, round(b))))) for a, b in z]


def _repaired(cov: np.ndarray) -> np.ndarray:
    """The nearest usable covariance: symmetric, with positive eigenvalues."""
    value, vector = np.linalg.eigh((cov + cov.T) / 2)
    return (vector * np.maximum(value, FLOOR)) @ vector.T


def loss_weights(losses, kind: str = "gap", temperature: float = 1.0) -> np.ndarray:
    """Losses as probabilities: a lower loss weighs more, a non-finite one nothing, equal ones alike."""
    x = np.asarray(losses, dtype=float)
    ok = np.isfinite(x)
    if not ok.any():
        return np.full(len(x), 1 / max(1, len(x)))
    lo, hi = x[ok].min(), x[ok].max()
    if kind == "gap":
        p = np.where(ok, hi - np.where(ok, x, hi), 0.0)
    elif kind == "softmin":
        p = np.where(ok, np.exp(-(np.where(ok, x, lo) - lo) / temperature), 0.0)
    elif kind == "inverse":
        p = np.where(ok & (x > 0), 1 / np.where(ok & (x > 0), x, 1.0), 0.0)
    else:
        order = np.argsort(np.argsort(np.where(ok, x, np.inf), kind="stable"), kind="stable")
        p = np.where(ok, ok.sum() - order, 0).astype(float)
    return p / p.sum() if p.sum() > 0 else ok / ok.sum()


def update_normal(phi: NormalPhi, alphas, weights, kappa: float = 1.0, floor: float = 1e-9) -> NormalPhi:
    """Weighted maximum likelihood with the prior counting as kappa observations; 0 leaves it out."""
    a = np.log(np.asarray(alphas, dtype=float)) if phi.log else np.asarray(alphas, dtype=float)
    p = np.asarray(weights, dtype=float)
    keep = (p > 0) & np.isfinite(a)
    a, p, s = a[keep], p[keep], len(alphas)
    mean = float((kappa * phi.mu + s * (p @ a)) / (kappa + s))
    var = (kappa * phi.sigma**2 + kappa * (phi.mu - mean) ** 2 + s * float(p @ (a - mean) ** 2)) / (kappa + s)
    return replace(phi, mu=mean, sigma=max(floor, var**0.5))


def update_bivariate(phi: BivariatePhi, configs, weights, kappa: float = 1.0) -> BivariatePhi:
    x, p, s = np.asarray(configs, dtype=float), np.asarray(weights, dtype=float), len(configs)
    mean = (kappa * np.array(phi.mean) + s * (p @ x)) / (kappa + s)
    c, m = x - mean, np.array(phi.mean) - mean
    cov = _repaired((kappa * np.array(phi.cov) + kappa * np.outer(m, m) + s * (c.T * p) @ c) / (kappa + s))
    return replace(phi, mean=tuple(mean.tolist()), cov=tuple(map(tuple, cov.tolist())))


def em_mixture(phi: MixturePhi, alphas, weights, iterations: int = 50, tol: float = 1e-10, floor: float = 1e-6) -> tuple[MixturePhi, list[float]]:
    """Weighted expectation-maximisation; also the log likelihood after each step, which never falls."""
    a, w = np.asarray(alphas, dtype=float), np.asarray(weights, dtype=float)
    a, w = a[w > 0], w[w > 0]
    trace = [phi.log_likelihood(a, w)]
    for _ in range(iterations):
        pi, mu, sd = (np.array(v) for v in (phi.pi, phi.mu, phi.sigma))
        r = pi * np.exp(-((a[:, None] - mu) ** 2) / (2 * sd**2)) / sd + 1e-300
        r = r / r.sum(axis=1, keepdims=True) * w[:, None]
        n = np.maximum(r.sum(axis=0), 1e-300)
        mu = (r * a[:, None]).sum(axis=0) / n
        sd = np.sqrt(np.maximum((r * (a[:, None] - mu) ** 2).sum(axis=0) / n, floor**2))
        phi = MixturePhi(tuple((n / n.sum()).tolist()), tuple(mu.tolist()), tuple(sd.tolist()))
        trace.append(phi.log_likelihood(a, w))
        if abs(trace[-1] - trace[-2]) < tol:
            break
    return phi, trace


def phi_from_history(log: DataFrame) -> DataFrame:
    """mu and sigma of a prior from a log of best steps (alpha, weight)."""
    w, a = F.col("weight"), F.col("alpha")
    mean = F.sum(w * a) / F.sum(w)
    return log.agg(mean.alias("mu"), F.sqrt(F.greatest(F.lit(0.0), F.sum(w * a * a) / F.sum(w) - mean * mean)).alias("sigma"))


@dataclass
class StepCountController:
    """How many configurations the next iteration tries: it grows while time stays near the reference, then holds."""

    growth: int = 2
    theta: float = 0.1
    cut: float = 2.0
    most: int = 64
    s: int = 1
    reference: float | None = None
    settled: bool = False

    def next(self, seconds: float) -> int:
        if self.reference is None:
            self.reference = seconds
        if seconds > self.cut * self.reference and self.s > 1:  # the machine has slowed down: fewer, for good
            self.s, self.settled = max(1, self.s // self.growth), True
        elif self.settled:
            pass
        elif seconds <= (1 + self.theta) * self.reference:
            self.s = min(self.most, self.s * self.growth)
        else:
            self.s, self.settled = max(1, self.s // self.growth), True
        return self.s
