"""Losses f(w.x, y) with (sub)gradients, as Spark columns and as numpy, and regularisers."""

from __future__ import annotations

from collections.abc import Callable, Sequence
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Loss:
    """value and slope take (dot, y); slope is the derivative by dot, so that the gradient is slope * x."""

    name: str
    column: Callable[[Column, Column], Column]
    column_slope: Callable[[Column, Column], Column]
    value: Callable[[np.ndarray, np.ndarray], np.ndarray]
    slope: Callable[[np.ndarray, np.ndarray], np.ndarray]
    scalar: str | None = None  #: the slope as Python text, of dot m and label t, for loops over single examples


LOSSES: dict[str, Loss] = {}


def register_loss(name: str, column, column_slope, value, slope, scalar: str | None = None) -> Loss:
    """Makes a loss of the caller known to every trainer and plan."""
    LOSSES[name] = Loss(name, column, column_slope, value, slope, scalar)
    return LOSSES[name]


def _np_log_loss(dot, y):
    z = dot * y
    return np.maximum(-z, 0) + np.log1p(np.exp(-np.abs(z)))


def _np_log_slope(dot, y):
    return -y / (1 + np.exp(np.minimum(dot * y, 700.0)))


def _log_slope(dot, y):
    e = F.exp(-F.abs(dot * y))
    return -y * F.when(dot * y >= 0, e / (1 + e)).otherwise(1 / (1 + e))


register_loss(
    "svm",
    lambda dot, y: F.greatest(1 - y * dot, F.lit(0.0)),
    lambda dot, y: F.when(1 - y * dot > 0, -y).otherwise(0.0),
    lambda dot, y: np.maximum(1 - y * dot, 0),
    lambda dot, y: np.where(y * dot < 1, -y, 0.0),
    "-t if t * m < 1 else 0.0",
)
register_loss("lr", lambda dot, y: F.greatest(-dot * y, F.lit(0.0)) + F.log1p(F.exp(-F.abs(dot * y))), _log_slope, _np_log_loss, _np_log_slope, "-t / (1 + exp(700.0 if (z := t * m) > 700 else z))")
register_loss("squared", lambda dot, y: (dot - y) * (dot - y) / 2, lambda dot, y: dot - y, lambda dot, y: (dot - y) ** 2 / 2, lambda dot, y: dot - y, "m - t")


@dataclass(frozen=True)
class Spec:
    """What is minimised: the sum (or mean) of a loss plus mu times a regulariser. The regulariser is exact and never sampled."""

    loss: str = "svm"
    reg: str = "none"
    mu: float = 0.0
    scale: str = "sum"

    @property
    def f(self) -> Loss:
        return LOSSES[self.loss]

    def per(self, n: int) -> float:
        return 1.0 if self.scale == "sum" else 1.0 / max(1, n)

    def reg_value(self, w: np.ndarray) -> np.ndarray:
        """By row of w."""
        w = np.atleast_2d(w)
        if self.reg == "l1":
            return self.mu * np.abs(w).sum(axis=1)
        if self.reg == "l2":
            return self.mu * (w * w).sum(axis=1) / 2
        return np.zeros(len(w))

    def reg_grad(self, w: np.ndarray) -> np.ndarray:
        if self.reg == "l1":
            return self.mu * np.sign(w)
        if self.reg == "l2":
            return self.mu * w
        return np.zeros_like(w)


def dot_wide(xs: Sequence[str], w: Sequence[float]) -> Column:
    """w.x over columns, the model as literals."""
    out = F.lit(0.0)
    for k, (x, v) in enumerate(zip(xs, w)):
        term = F.col(x) * F.lit(float(v))
        out = term if k == 0 else out + term
    return out


def dot_array(x: str | Column, w) -> Column:
    """w.x over an array column; w is a Column or the model's numbers."""
    w = w if isinstance(w, Column) else F.array(*(F.lit(float(v)) for v in w))
    return F.aggregate(F.zip_with(x, w, lambda a, b: a * b), F.lit(0.0), lambda s, v: s + v)


def dot_sparse(values: Column, w: Column) -> Column:
    """w.x for a map from index to value and a map from index to weight; an index without weight counts nothing."""
    terms = F.map_zip_with(values, w, lambda _, v, u: F.coalesce(v * u, F.lit(0.0)))  # by a hash of the keys; a look-up in w would go through all of it
    return F.aggregate(F.map_values(terms), F.lit(0.0), lambda s, v: s + v)
