"""Batch methods: gradient descent, line searches, averaging, coordinate descent and L-BFGS."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from calib.functions.losses import Spec, dot_wide
from calib.plans.moments import CostMeter, Moments, batch_matrix, full_gradient, multi_eval, objective
from calib.sources.views import wide


@dataclass
class Run:
    """A trained model with one trace row for each iteration and the costs."""

    w: np.ndarray
    trace: list[dict] = field(default_factory=list)
    cost: CostMeter = field(default_factory=CostMeter)


@dataclass(frozen=True)
class StopRule:
    """Stops after max_iter iterations, or once the loss has changed little `patience` times in a row."""

    max_iter: int = 20
    tol: float = 0.0
    rel_tol: float = 0.0
    patience: int = 1
    grad_tol: float = 0.0

    def done(self, losses: list[float], grad_norm: float | None = None) -> bool:
        if len(losses) > self.max_iter:
            return True
        if grad_norm is not None and grad_norm <= self.grad_tol:
            return True
        if len(losses) <= self.patience:
            return False
        last = losses[-self.patience - 1 :]
        return all(abs(b - a) <= max(self.tol, self.rel_tol * abs(a)) and (self.tol or self.rel_tol) for a, b in zip(last, last[1:]))


@dataclass(frozen=True)
class Step:
    """A step size that is constant or falls with the iteration k (from 0)."""

    kind: str = "const"
    a0: float = 1e-5
    gamma: float = 0.0

    def __call__(self, k: int) -> float:
        if self.kind == "inverse":
            return self.a0 / (1 + self.gamma * k)
        if self.kind == "exp":
            return self.a0 * self.gamma**k
        if self.kind == "sqrt":
            return self.a0 / (k + 1) ** 0.5
        return self.a0


def init_model(d: int, seed: int, scale: float = 0.01) -> np.ndarray:
    return np.random.default_rng(seed).standard_normal(d) * scale


def train_bgd(ex: DataFrame, spec: Spec, w0, step: Callable[[int], float], stop: StopRule = StopRule(), plan: str = "auto", fused: bool = True) -> Run:
    """Descent by full gradients. Fused, a pass gives loss and gradient together; otherwise each has a pass of its own."""
    w, run, losses = np.array(w0, dtype=float), Run(np.array(w0, dtype=float)), []
    for k in range(stop.max_iter + 1):
        m = multi_eval(ex, w, spec, plan, meter=run.cost)
        if not fused:
            multi_eval(ex, w, spec, plan, meter=run.cost)
        g = full_gradient(m, w, spec)[0]
        losses.append(float(objective(m, w, spec)[0]))
        run.trace.append({"k": k, "loss": losses[-1], "w": w.copy(), "alpha": step(k), "grad_norm": float(np.linalg.norm(g))})
        if stop.done(losses, float(np.linalg.norm(g))) or k == stop.max_iter:
            break
        w = w - step(k) * g
    run.w = w
    return run


def line_search(ex: DataFrame, spec: Spec, w: np.ndarray, loss: float, g: np.ndarray, direction: np.ndarray, a0: float = 1.0, rho: float = 0.5, c1: float = 1e-4, c2: float | None = None, max_tries: int = 30, plan: str = "auto", meter: CostMeter | None = None, speculative: bool = False) -> tuple[float, int, Moments]:
    """Shrinks the step until the loss falls enough (and, with c2, the slope too).

    One pass a trial, as the baseline has it; speculative, all trial steps share one pass and the first that
    qualifies is taken. Gives the step, how many trials it took, and the moments at the new model.
    """
    slope = float(g @ direction)
    alphas = [a0 * rho**t for t in range(max_tries)]
    together = multi_eval(ex, np.array([w + a * direction for a in alphas]), spec, plan, meter=meter) if speculative else None
    for t, a in enumerate(alphas):
        trial = w + a * direction
        m = together.pick([t]) if together is not None else multi_eval(ex, trial, spec, plan, meter=meter)
        ok = float(objective(m, trial, spec)[0]) <= loss + c1 * a * slope
        if ok and c2 is not None:
            ok = float(full_gradient(m, trial, spec)[0] @ direction) >= c2 * slope
        if ok:
            break
    return a, t + 1, m


def train_line_search(ex: DataFrame, spec: Spec, w0, iterations: int, a0: float = 1e-3, rho: float = 0.5, c1: float = 1e-4, c2: float | None = None, max_tries: int = 30, plan: str = "auto", speculative: bool = False) -> Run:
    run, w = Run(np.array(w0, dtype=float)), np.array(w0, dtype=float)
    m = multi_eval(ex, w, spec, plan, meter=run.cost)
    for k in range(iterations):
        loss, g = float(objective(m, w, spec)[0]), full_gradient(m, w, spec)[0]
        a, tries, m = line_search(ex, spec, w, loss, g, -g, a0, rho, c1, c2, max_tries, plan, run.cost, speculative)
        w = w - a * g
        run.trace.append({"k": k + 1, "tries": tries, "alpha": a, "loss": float(objective(m, w, spec)[0]), "w": w.copy()})
    run.w = w
    return run


def partial_gradient(ex: DataFrame, spec: Spec, w, finished: list[int], blocks: int, discard: bool = False, plan: str = "auto") -> Moments:
    """The gradient when some nodes are late: sums of the finished blocks, scaled up to all unless late ones are just left out."""
    m = multi_eval(ex.where(F.col("blk").isin(finished)), w, spec, plan)
    f = 1.0 if discard else blocks / max(1, len(finished))
    return Moments(m.n, m.s1 * f, m.s2 * f)


def train_bgd_oneshot(ex: DataFrame, spec: Spec, w0, step: float, iterations: int, part: str) -> DataFrame:
    """Each part (a column) descends alone to the end; gives part, n and w, to be averaged once. Groups see only sums per pass."""
    w0, d = np.array(w0, dtype=float), len(w0)
    cols = ["x"] if "x" in ex.columns else wide(d)

    def solve(table: pa.Table) -> pa.Table:
        parts = [batch_matrix(b, d) for b in table.to_batches()]
        w = w0.copy()
        n = sum(len(y) for _, y in parts)
        for _ in range(iterations):
            g = sum((spec.f.slope(x @ w, y) @ x for x, y in parts), np.zeros(d)) * spec.per(n)
            w = w - step * (g + spec.reg_grad(w))
        return pa.table({"part": table.column(part).slice(0, 1).cast(pa.int64()), "n": [n], "w": pa.array([w], pa.list_(pa.float64()))})

    return ex.select(part, *cols, "y").groupBy(part).applyInArrow(solve, "part long, n long, w array<double>")


def average(parts: DataFrame, d: int, weight: str = "uniform") -> np.ndarray:
    """The models of `parts` (n, w) averaged, each alike or by its number of examples."""
    u = F.lit(1.0) if weight == "uniform" else F.col("n").cast("double")
    row = parts.agg(F.sum(u).alias("u"), *(F.sum(u * F.element_at("w", j + 1)).alias(f"w{j}") for j in range(d))).first()
    return np.array([row[f"w{j}"] / row["u"] for j in range(d)])


def train_cd(ex: DataFrame, spec: Spec, w0, sweeps: int = 1, grid=(-0.5, -0.1, -0.02, 0.0, 0.02, 0.1, 0.5), block: int = 1) -> Run:
    """Coordinate descent: for one coordinate (or a block of them) after another the best of a grid of changes is taken.

    All trial values of a block share one scan; margins are not stored but recomputed from the model in it.
    """
    w, d, run = np.array(w0, dtype=float), len(w0), Run(np.array(w0, dtype=float))
    for sweep in range(sweeps):
        for first in range(0, d, block):
            coords = range(first, min(d, first + block))
            trials = [(j, v) for j in coords for v in grid]
            dots = dot_wide(wide(d), w)
            sums = [F.sum(spec.f.column(F.col("_dot") + F.col(f"x{j}") * float(v), F.col("y"))).alias(f"t{i}") for i, (j, v) in enumerate(trials)]
            row = ex.select(*wide(d), "y", dots.alias("_dot")).agg(F.count(F.lit(1)).alias("n"), *sums).first()
            run.cost.add(row["n"], len(trials), len(trials))
            moved = w.copy()
            for j in coords:
                losses = [(round(row[f"t{i}"] * spec.per(row["n"]) + float(spec.reg_value(np.where(np.arange(d) == j, w + v, w))[0]), 6), abs(v), v) for i, (jj, v) in enumerate(trials) if jj == j]
                moved[j] += min(losses)[2] / (1 if block == 1 else len(coords))
            w = moved
            run.trace.append({"sweep": sweep, "coord": first, "loss": min(losses)[0] if block == 1 else None, "w": w.copy()})
    run.w = w
    return run


def train_lbfgs(ex: DataFrame, spec: Spec, w0, iterations: int = 10, history: int = 10, speculative: bool = False, plan: str = "auto", a0: float = 1.0) -> Run:
    """Quasi-Newton steps from the last changes of model and gradient; the two-loop recursion runs on the driver."""
    w, run = np.array(w0, dtype=float), Run(np.array(w0, dtype=float))
    m = multi_eval(ex, w, spec, plan, meter=run.cost)
    loss, g = float(objective(m, w, spec)[0]), full_gradient(m, w, spec)[0]
    pairs: list[tuple[np.ndarray, np.ndarray]] = []
    for k in range(iterations):
        q, alphas = g.copy(), []
        for s, y in reversed(pairs):
            a = (s @ q) / (y @ s)
            alphas.append(a)
            q = q - a * y
        q = q * ((pairs[-1][0] @ pairs[-1][1]) / (pairs[-1][1] @ pairs[-1][1]) if pairs else 1 / max(1e-12, np.linalg.norm(g)))
        for (s, y), a in zip(pairs, reversed(alphas)):
            q = q + s * (a - (y @ q) / (y @ s))
        a, tries, m = line_search(ex, spec, w, loss, g, -q, a0, plan=plan, meter=run.cost, speculative=speculative, max_tries=12)
        new = w - a * q
        ng = full_gradient(m, new, spec)[0]
        if (new - w) @ (ng - g) > 1e-12:
            pairs = [*pairs, (new - w, ng - g)][-history:]
        w, g, loss = new, ng, float(objective(m, new, spec)[0])
        run.trace.append({"k": k + 1, "tries": tries, "alpha": a, "loss": loss, "w": w.copy()})
    run.w = w
    return run


def trace_frame(spark, run: Run, columns: dict[str, str], digits: dict[str, int] | None = None) -> DataFrame:
    """A run's trace as a frame; w becomes w0.. rounded to 6 digits, other floats to 4 or as told."""
    rows, digits = [], digits or {}
    fix = lambda v, n: None if v is None else round(float(v), n) + 0.0
    for r in run.trace:
        row = {}
        for c, kind in columns.items():
            if c == "w":
                row |= {f"w{j}": fix(v, 6) for j, v in enumerate(r["w"])}
            else:
                row[c] = fix(r[c], digits.get(c, 4)) if kind == "double" else r[c]
        rows.append(row)
    d = len(run.w)
    schema = ", ".join(", ".join(f"w{j} double" for j in range(d)) if c == "w" else f"{c} {t}" for c, t in columns.items())
    return spark.createDataFrame([tuple(r.values()) for r in rows], schema)


def states(frame: DataFrame) -> Iterator:
    """Rows of a small frame, one by one."""
    yield from frame.toLocalIterator()
