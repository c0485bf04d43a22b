"""Sampling and the estimators of SUMs from samples."""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from calib.plans.moments import Moments


@dataclass
class Estimate:
    """Estimated sums over all N examples with their deviations, by model: (s, 1 + d)."""

    est: np.ndarray
    std: np.ndarray

    def bounds(self, z: float = 1.0) -> tuple[np.ndarray, np.ndarray]:
        return self.est - z * self.std, self.est + z * self.std


def estimate(m: Moments, total: int) -> Estimate:
    """From n of N examples drawn without replacement: sums scaled up, deviations that vanish when all are read."""
    n = max(1, m.n)
    var = np.maximum(0.0, m.s2 - m.s1 * m.s1 / n) / max(1, n - 1)
    return Estimate(m.s1 * (total / n), total * np.sqrt(var / n * max(0.0, 1 - n / max(1, total))))


def estimate_bernoulli(s1: float, s2: float, q: float) -> tuple[float, float]:
    """The same for a sample of independent coin tosses with chance q."""
    return s1 / q, math.sqrt((1 - q) / q**2 * s2)


def estimate_columns(n: Column, s1: Column, s2: Column, total: Column, z: float = 1.0) -> dict[str, Column]:
    """est, std, low, high and rel_err as columns over running or grouped sums."""
    var = F.when(n > 1, F.greatest(F.lit(0.0), s2 - s1 * s1 / n) / (n - 1)).otherwise(0.0)
    est = total / n * s1
    std = total * F.sqrt(var / n * F.greatest(F.lit(0.0), 1 - n / total))
    return {"est": est, "std": std, "low": est - z * std, "high": est + z * std, "rel_err": F.when(std == 0, 0.0).when(est == 0, float("inf")).otherwise(2 * z * std / F.abs(est))}


def rel_error(est, std, z: float = 1.0) -> np.ndarray:
    """Width of the bounds against the estimate's size: 0 without deviation, infinite around zero."""
    est, std = np.asarray(est, dtype=float), np.asarray(std, dtype=float)
    with np.errstate(divide="ignore", invalid="ignore"):
        return np.where(std == 0, 0.0, np.where(est == 0, np.inf, 2 * z * std / np.abs(est)))


def required_n(variance: float, mean: float, total: int, eps: float, z: float = 1.0) -> int:
    """Examples after which the bounds of a sum are eps of it wide: from past variance and mean."""
    if mean == 0:
        return total
    n0 = (2 * z) ** 2 * variance / (eps * mean) ** 2
    return min(total, max(1, math.ceil(n0 / (1 + n0 / total) - 1e-9)))


def bernoulli(ex: DataFrame, q: float) -> DataFrame:
    """Each example by a coin that its random place decides."""
    return ex.where(F.col("ord") < int(q * 2**32))


def hash_sample(ex: DataFrame, q: float, columns: list[str]) -> DataFrame:
    """Examples by a hash of the whole tuple."""
    return ex.where(F.conv(F.substring(F.md5(F.concat_ws(":", *columns)), 1, 8), 16, 10).cast("long") < int(q * 2**32))


def feature_sample(ex: DataFrame, column: str, q: float) -> DataFrame:
    """What not to do: a sample that one feature decides, whose estimators are correlated with it."""
    return ex.where(F.pmod(F.xxhash64(column), F.lit(1 << 20)) < int(q * (1 << 20)))


def srs(ex: DataFrame, n: int, key: list[str]) -> DataFrame:
    """The first n examples in random order."""
    return ex.orderBy("ord", *key).limit(n)


def index_sample(ex: DataFrame, ids: DataFrame, key: str) -> DataFrame:
    """Examples looked up by id, as through an index; slower than a scan of blocks."""
    return ex.join(ids, key)
