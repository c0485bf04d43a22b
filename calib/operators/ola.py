"""Online aggregation: a scan in waves of random blocks that ends when the estimates are good enough."""

from __future__ import annotations

import time
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from calib.functions.losses import Spec
from calib.operators.batch import Run
from calib.operators.estimators import Estimate, estimate
from calib.operators.halting import RULES, Trigger, joint_halt
from calib.operators.speculative import Grid, select_best, trial_models
from calib.operators.stepdist import NormalPhi, loss_weights, update_normal
from calib.plans.moments import CostMeter, Moments, multi_eval
from calib.sources.order import block_sequence


@dataclass(frozen=True)
class Schedule:
    """Blocks of each wave: always as many, ever more, or as many as the bounds' width asks for."""

    kind: str = "geometric"
    first: int = 1
    growth: float = 2.0

    def next(self, wave: int, done: int, blocks: int, rel_width: float | None = None, eps: float = 0.05) -> int:
        if self.kind == "linear":
            n = self.first
        elif self.kind == "width" and rel_width and done:  # the width falls with the root of the sample
            n = max(self.first, int(np.ceil(done * ((rel_width / eps) ** 2 - 1)))) if np.isfinite(rel_width) else done
        else:
            n = int(self.first * self.growth**wave)
        return max(1, min(n, blocks - done))


@dataclass
class Wave:
    """What is known after a wave: how many rows, the moments and estimates of the models that are left."""

    wave: int
    blocks: int
    n: int
    alive: list[int]
    moments: Moments
    estimate: Estimate


def ola_run(ex: DataFrame, models: np.ndarray, spec: Spec, total: int, blocks: list[int], schedule: Schedule = Schedule(), eps: float = 0.05, z: float = 1.0, policy: str = "immediate", grad_mode: str = "norm", rules=RULES, n_min: int = 0, halt: bool = True, plan: str = "auto", meter: CostMeter | None = None) -> list[Wave]:
    """Waves until one model is left and known, or all blocks are read, when results are exact.

    A wave is one job over its blocks alone (partitions or row groups of others are not read) and over the
    models that are left. Losses' regularisers are added to the estimates, which need no sampling.
    """
    alive, done, m, out, width = list(range(len(models))), 0, None, [], None
    while done < len(blocks):
        take = schedule.next(len(out), done, len(blocks), width, eps)
        new = multi_eval(ex.where(F.col("blk").isin(blocks[done : done + take])), models[alive], spec, plan, want_sq=True, meter=meter)
        m = new if m is None else m + new
        done += take
        e = estimate(m, total) if done < len(blocks) else Estimate(m.s1.copy(), np.zeros_like(m.s1))
        est = e.est * spec.per(total)
        std = e.std * spec.per(total)
        est[:, 0] += spec.reg_value(models[alive])
        est[:, 1:] += spec.reg_grad(models[alive])
        e = Estimate(est, std)
        out.append(Wave(len(out), done, m.n, list(alive), m, e))
        if not halt or m.n < n_min:
            continue
        d = joint_halt(est, std, eps, z, policy, grad_mode, rules)
        best = d.best
        width = 2 * z * float(np.linalg.norm(std[best, 1:])) / max(1e-300, float(np.linalg.norm(est[best, 1:])))
        keep = d.survivors if not d.done else [best]
        m, alive = m.pick(keep), [alive[i] for i in keep]
        out[-1].alive = list(alive)
        out[-1].moments, out[-1].estimate = m, Estimate(est[keep], std[keep])
        if d.done:
            break
    return out


def train_approx_bgd(ex: DataFrame, spec: Spec, w0, total: int, blocks: int, grid: Grid | None = None, phi: NormalPhi | None = None, s: int = 8, iterations: int = 5, eps: float = 0.05, z: float = 1.0, policy: str = "immediate", grad_mode: str = "norm", schedule: Schedule = Schedule(), n_min: int = 200, seed: int = 0, plan: str = "auto", kappa: float = 1.0) -> Run:
    """Speculative batch descent whose scans end early. With eps = 0 every scan is whole and the result exact."""
    w, run = np.array(w0, dtype=float), Run(np.array(w0, dtype=float))
    halt = eps > 0
    first = ola_run(ex, w[None, :], spec, total, block_sequence(blocks, 0, seed), schedule, eps, z, policy, grad_mode, n_min=n_min, halt=halt, plan=plan, meter=run.cost)[-1]
    g = first.estimate.est[0, 1:]
    for k in range(iterations):
        alphas = grid.at(k) if grid else phi.sample(s)
        models = trial_models(w, g, alphas)
        waves = ola_run(ex, models, spec, total, block_sequence(blocks, k + 1, seed), schedule, eps, z, policy, grad_mode, n_min=n_min, halt=halt, plan=plan, meter=run.cost)
        last = waves[-1]
        at = select_best(last.estimate.est[:, 0])
        best = last.alive[at]
        w, g = models[best], last.estimate.est[at, 1:]
        seen = {}
        for wave in waves:
            for i, m in enumerate(wave.alive):
                seen[m] = float(wave.estimate.est[i, 0])
        run.trace.append({"k": k + 1, "alpha": float(alphas[best]), "loss": float(last.estimate.est[at, 0]), "std": float(last.estimate.std[at, 0]), "n_read": last.n, "ratio": last.n / total, "waves": len(waves), "survivors": [len(v.alive) for v in waves], "w": w.copy(), "best": best})
        if phi is not None and grid is None:
            phi = update_normal(phi, [alphas[i] for i in seen], loss_weights([seen[i] for i in seen]), kappa)
    run.w = w
    return run


def ola_async(ex: DataFrame, models: np.ndarray, spec: Spec, total: int, every: int, stop: Callable[[Estimate, int], bool], trigger: Trigger | None = None) -> tuple[Estimate, int]:
    """Without waves: each task gives its sums after every so many rows, and the driver stops the job once it likes the estimate.

    trigger says when the estimate is judged; without one that is whenever sums arrive.
    """
    s, d = models.shape
    from calib.plans.moments import batch_matrix
    from calib.sources.views import wide

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        n, s1, s2 = 0, np.zeros((s, d + 1)), np.zeros((s, d + 1))

        def row() -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array([n]), pa.array([np.concatenate([s1.ravel(), s2.ravel()])], pa.list_(pa.float64()))], names=["n", "sums"])

        for b in batches:
            for at in range(0, b.num_rows, every):
                x, y = batch_matrix(b.slice(at, every), d)
                dot, yy = x @ models.T, y[:, None]
                v, g = spec.f.value(dot, yy), spec.f.slope(dot, yy)
                s1[:, 0] += v.sum(axis=0)
                s1[:, 1:] += g.T @ x
                s2[:, 0] += (v * v).sum(axis=0)
                s2[:, 1:] += (g * g).T @ (x * x)
                n += len(y)
                if n >= every:
                    yield row()
                    n = 0
                    s1[:], s2[:] = 0, 0
        if n:
            yield row()

    cols, began = ["x"] if "x" in ex.columns else wide(d), time.perf_counter()
    m = Moments(0, np.zeros((s, d + 1)), np.zeros((s, d + 1)))
    for r in ex.select(*cols, "y").mapInArrow(run, "n long, sums array<double>").toLocalIterator():
        flat = np.array(r["sums"]).reshape(2, s, d + 1)
        m = m + Moments(r["n"], flat[0], flat[1])
        if (trigger is None or trigger.fires(m.n, time.perf_counter() - began)) and stop(estimate(m, total), m.n):
            break
    return estimate(m, total), m.n


def train_subsample(ex: DataFrame, spec: Spec, w0, q: float, step: float, iterations: int, plan: str = "auto") -> Run:
    """The static rival: descent on one sample of a share q for ever; its last loss is that of all examples."""
    from calib.operators.estimators import bernoulli

    w, run, sample = np.array(w0, dtype=float), Run(np.array(w0, dtype=float)), bernoulli(ex, q)
    for k in range(iterations):
        m = multi_eval(sample, w, spec, plan, meter=run.cost)
        w = w - step * (m.grad[0] / q * 1.0 + spec.reg_grad(w))
        run.trace.append({"k": k + 1, "n_read": m.n, "w": w.copy()})
    run.w = w
    return run


def loss_probe(ex: DataFrame, w, spec: Spec, total: int, n: int, key: list[str]) -> float:
    """The loss from the next n examples in random order, scaled up; n = 1 is the crudest estimate."""
    m = multi_eval(ex.orderBy("ord", *key).limit(n), np.asarray(w, dtype=float), spec)
    return float(m.loss[0] * total / max(1, m.n))


def loss_ola(ex: DataFrame, w, spec: Spec, total: int, blocks: list[int], eps: float = 0.05, z: float = 1.0) -> tuple[float, int]:
    """The loss by online aggregation, and how many examples it took."""
    done, m = 0, None
    schedule = Schedule()
    for wave in range(len(blocks)):
        take = schedule.next(wave, done, len(blocks))
        if not take or done >= len(blocks):
            break
        new = multi_eval(ex.where(F.col("blk").isin(blocks[done : done + take])), np.asarray(w, dtype=float), spec, want_sq=True)
        m = new if m is None else m + new
        done += take
        e = estimate(m, total)
        if 2 * z * e.std[0, 0] <= eps * abs(e.est[0, 0]):
            break
    return float(estimate(m, total).est[0, 0]), m.n
