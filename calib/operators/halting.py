"""When a scan may end: rules over estimates of gradients, losses and incremental losses."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

from calib.operators.estimators import rel_error


def stop_gradient(est, std, eps: float = 0.05, mode: str = "norm", share: float = 0.9, z: float = 1.0) -> bool:
    """Whether a gradient is known well enough.

    all: every coordinate's relative error is at most eps; share: a share of them; sum: their sum is at most
    eps for each coordinate; norm: the deviations together against the gradient's length, which coordinates near
    zero do not upset.
    """
    e = rel_error(est, std, z)
    if mode == "all":
        return bool((e <= eps).all())
    if mode == "share":
        return bool((e <= eps).mean() >= share)
    if mode == "sum":
        return bool(e.sum() <= eps * len(e))
    top, bottom = 2 * z * float(np.linalg.norm(std)), float(np.linalg.norm(est))
    return top == 0 or (bottom > 0 and top <= eps * bottom)


RULES = ("exact", "overlap", "inner_upper", "outer_lower")


@dataclass(frozen=True)
class LossDecision:
    survivors: list[int]
    done: bool
    best: int | None


def _slack(eps: float, mode: str, width: float) -> float:
    return eps * width if mode == "relative" else eps


def stop_loss(low, high, eps: float = 0.05, rules=RULES, mode: str = "relative", approximate: bool = True) -> list[int]:
    """The intervals that may still hold the least loss, by place.

    exact: an interval goes if another lies wholly below it. overlap: if it reaches only a little into one that
    begins and ends lower. inner_upper: if it sits inside another at that one's upper end. outer_lower: if
    another sits inside it at its lower end. An interval that has gone justifies no further removal, lower
    estimates are looked at first, and one always stays.
    """
    low, high = np.asarray(low, dtype=float), np.asarray(high, dtype=float)
    order = sorted(range(len(low)), key=lambda i: ((low[i] + high[i]) / 2, i))
    alive = set(order)
    if "exact" in rules and alive:
        least = min(high)
        keep = int(np.argmin(high))
        alive = {i for i in alive if low[i] < least or i == keep}
    if not approximate:
        return sorted(alive)

    def beaten(j: int, i: int) -> bool:
        """Whether interval i lets j go."""
        wide = high[j] - low[j]
        if "overlap" in rules and low[i] <= low[j] and high[i] <= high[j] and low[j] <= high[i]:
            if high[i] - low[j] <= _slack(eps, mode, wide) and (low[i], high[i]) != (low[j], high[j]):
                return True
        if "inner_upper" in rules and low[i] < low[j] and high[j] <= high[i] and high[i] - low[j] <= _slack(eps, mode, high[i] - low[i]):
            return True
        return "outer_lower" in rules and low[j] <= low[i] and high[i] < high[j] and high[i] - low[j] <= _slack(eps, mode, wide)

    for j in reversed(order):
        if len(alive) > 1 and j in alive and any(beaten(j, i) for i in order if i in alive and i != j):
            alive.discard(j)
    return sorted(alive)


def loss_decision(est, std, eps: float = 0.05, z: float = 1.0, rules=RULES, mode: str = "relative") -> LossDecision:
    """Who is left, and whether the scan may end for losses: one is left, or all that are left are accurate."""
    est, std = np.asarray(est, dtype=float), np.asarray(std, dtype=float)
    alive = stop_loss(est - z * std, est + z * std, eps, rules, mode)
    accurate = bool((rel_error(est[alive], std[alive], z) <= eps).all())
    best = min(alive, key=lambda i: (est[i], i))
    return LossDecision(alive, len(alive) == 1 or accurate, best)


def joint_halt(est: np.ndarray, std: np.ndarray, eps: float, z: float = 1.0, policy: str = "immediate", grad_mode: str = "norm", rules=RULES) -> LossDecision:
    """Losses and gradients together; rows are models, column 0 the loss.

    Exact pruning always drops a model with its gradient. Approximate pruning does so at once, or (deferred)
    only when the best model's gradient is accurate. Done: one is left and its gradient is accurate.
    """
    low, high = est[:, 0] - z * std[:, 0], est[:, 0] + z * std[:, 0]
    alive = stop_loss(low, high, eps, rules, approximate=False)
    best = min(alive, key=lambda i: (est[i, 0], i))
    good = stop_gradient(est[best, 1:], std[best, 1:], eps, grad_mode, z=z)
    if policy == "immediate" or good:
        left = stop_loss(low[alive], high[alive], eps, rules)
        alive = [alive[i] for i in left]
        best = min(alive, key=lambda i: (est[i, 0], i))
        good = stop_gradient(est[best, 1:], std[best, 1:], eps, grad_mode, z=z)
    accurate = bool((rel_error(est[alive, 0], std[alive, 0], z) <= eps).all())
    return LossDecision(alive, good and (len(alive) == 1 or accurate), best)


def stop_igd_loss(est, std, eps: float = 0.05, m: int = 2, beta: float = 0.01, z: float = 1.0) -> bool:
    """Whether incremental models have converged: at least m stable estimates, which differ by at most beta of the largest."""
    est = np.asarray(est, dtype=float)
    stable = est[rel_error(est, std, z) <= eps]
    return len(stable) >= m and (stable.max() - stable.min()) <= beta * abs(stable.max())


@dataclass
class CheckInterval:
    """How many examples pass until the next test: fewer once the loss is flat."""

    start: int = 10_000
    shrink: float = 0.5
    floor: int = 500
    flat_tol: float = 0.01
    size: int = 0

    def next(self, before: float | None, now: float) -> int:
        self.size = self.size or self.start
        if before is not None and abs(now - before) <= self.flat_tol * abs(before):
            self.size = max(self.floor, int(self.size * self.shrink))
        return self.size


@dataclass
class Trigger:
    """Calls for a test after so many rows or seconds, or when a callback says so."""

    every_rows: int | None = None
    every_secs: float | None = None
    callback: object = None
    rows: int = 0
    secs: float = 0.0

    def fires(self, rows: int, secs: float) -> bool:
        due = self.every_rows is not None and rows - self.rows >= self.every_rows
        due |= self.every_secs is not None and secs - self.secs >= self.every_secs
        due |= bool(self.callback and self.callback(rows, secs))
        if due:
            self.rows, self.secs = rows, secs
        return due
