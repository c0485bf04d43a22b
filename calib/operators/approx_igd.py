"""Approximate incremental descent: speculative children, estimated parents, and snapshots that tell when to stop.

A pass is cut into waves of blocks. Within a wave each part moves its own children of every live parent and adds
up, for parents and for snapshots (a frozen copy of every moving model, by parent and step), sums of losses and of their squares.
Between waves the driver merges, prunes parents whose losses are clearly worse, and ends the pass once enough
snapshots' losses are known and agree.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from calib.functions.losses import Spec
from calib.operators.batch import Run
from calib.operators.estimators import estimate
from calib.operators.halting import RULES, CheckInterval, stop_igd_loss, stop_loss
from calib.operators.incremental import by_part, descend, margins, ordered
from calib.operators.speculative import select_best
from calib.plans.moments import Moments, multi_eval, objective
from calib.sources.order import block_sequence

WAVE = "part long, n long, w array<double>, s1 array<double>, s2 array<double>"


def wave_kernel(ex: DataFrame, spec: Spec, starts: dict[int, np.ndarray], shared: np.ndarray, alphas: np.ndarray, frozen: np.ndarray, key: list[str], part: str) -> DataFrame:
    """One wave. shared: (models, d) for parts that have no start of their own; frozen: models whose losses are summed."""
    d = shared.shape[1]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        states: dict[int, list] = {}
        for p, x, y in by_part(batches, d):
            if p not in states:
                states[p] = [0, starts.get(p, shared).copy(), np.zeros(len(frozen)), np.zeros(len(frozen))]
            st = states[p]
            v = spec.f.value(margins(x, frozen), y[:, None])
            st[2] += v.sum(axis=0)
            st[3] += (v * v).sum(axis=0)
            descend(st[1], x, y, alphas, spec)
            st[0] += len(y)
        cols = list(zip(*((p, n, w.ravel(), a, b) for p, (n, w, a, b) in states.items()))) or [()] * 5
        kinds = (pa.int64(), pa.int64(), pa.list_(pa.float64()), pa.list_(pa.float64()), pa.list_(pa.float64()))
        yield pa.RecordBatch.from_arrays([pa.array(list(c), t) for c, t in zip(cols, kinds)], names=["part", "n", "w", "s1", "s2"])

    return ordered(ex, part, key, d).mapInArrow(run, WAVE)


def resync(sync: str, local: dict[int, np.ndarray], counts: dict[int, int], merged: np.ndarray, stale: np.ndarray | None, stale_n: int) -> dict[int, np.ndarray]:
    """Models with which parts begin the next wave.

    none: their own. blocking: the average of all. stale: their own, with the average of the wave before folded
    in by counts, so that nobody waits for this one.
    """
    if sync == "none":
        return local
    if sync == "blocking" or stale is None:
        return {p: merged.copy() for p in local} if sync == "blocking" else local
    return {p: (stale_n * stale + counts[p] * w) / (stale_n + counts[p]) for p, w in local.items()}


def train_approx_igd(ex: DataFrame, spec: Spec, w0, alphas, total: int, blocks: int, key: list[str], part: str, iterations: int = 2, waves: int = 8, eps: float = 0.05, z: float = 1.0, m: int = 2, beta: float = 0.01, sync: str = "none", rules=RULES, seed: int = 0, check: CheckInterval | None = None) -> Run:
    """At most `iterations` passes, each of which may end after any wave. The number of parts must not change between waves."""
    alphas = np.asarray(alphas, dtype=float)
    s, run = len(alphas), Run(np.asarray(w0, dtype=float))
    parents, d = np.asarray(w0, dtype=float)[None, :], len(w0)
    objective_of = lambda loss, w: float(loss) * spec.per(total) + float(np.sum(spec.reg_value(w)))
    for k in range(iterations):
        order = block_sequence(blocks, k, seed)
        alive = list(range(len(parents)))
        shared = np.repeat(parents, s, axis=0)
        starts: dict[int, np.ndarray] = {}
        known = {("parent", i): Moments(0, np.zeros((1, 1)), np.zeros((1, 1))) for i in alive}
        frozen = {("parent", i): parents[i] for i in alive}
        stale, stale_n, read, halted, children = None, 0, 0, False, shared
        step = -(-blocks // waves)
        size = check or CheckInterval(step, 0.5, 1)
        before, wave, at = None, 0, 0
        while at < blocks:
            names = list(frozen)
            keep = np.array([i * s + c for i in alive for c in range(s)])
            rows = wave_kernel(ex.where(F.col("blk").isin(order[at : at + step])), spec, {p: w[keep] for p, w in starts.items()}, shared[keep], np.tile(alphas, len(alive)), np.array([frozen[n] for n in names]), key, part).collect()
            at += step
            counts = {r["part"]: r["n"] for r in rows}
            n = sum(counts.values())
            if not n:
                continue
            read += n
            local = {}
            for r in rows:
                w = starts.get(r["part"], shared).copy()
                w[keep] = np.array(r["w"]).reshape(-1, d)
                local[r["part"]] = w
            children = sum(counts[p] * w for p, w in local.items()) / n
            for j, name in enumerate(names):
                add = Moments(n, np.array([[sum(r["s1"][j] for r in rows)]]), np.array([[sum(r["s2"][j] for r in rows)]]))
                known[name] = known[name] + add
            run.cost.add(n, len(names), len(keep))
            # parents that are clearly worse go, with their children and snapshots
            e = [estimate(known["parent", i], total) for i in alive]
            low, high = ([objective_of(x.bounds(z)[side][0, 0], parents[i]) for i, x in zip(alive, e)] for side in (0, 1))
            alive = [alive[i] for i in stop_loss(low, high, eps, rules)]
            frozen = {n_: w for n_, w in frozen.items() if n_[1] in alive}
            best = alive[select_best([objective_of(estimate(known["parent", i], total).est[0, 0], parents[i]) for i in alive])]
            tracks = {c: [n_ for n_ in frozen if n_[:3] == ("snap", best, c) and known[n_].n > 1] for c in range(s)}
            if len(alive) == 1 and all(tracks.values()):
                # the child that is ahead by its newest snapshot decides whether the pass ends
                seen = {c: [estimate(known[n_], total) for n_ in names_] for c, names_ in tracks.items()}
                est = {c: [objective_of(x.est[0, 0], frozen[n_]) for n_, x in zip(tracks[c], seen[c])] for c in tracks}
                std = {c: [x.std[0, 0] * spec.per(total) for x in seen[c]] for c in tracks}
                ahead = select_best([est[c][-1] for c in range(s)])
                if stop_igd_loss(est[ahead], std[ahead], eps, m, beta, z):
                    halted = True
                    break
                for c in tracks:
                    stable = [n_ for n_, a, b in zip(tracks[c], est[c], std[c]) if 2 * z * b <= eps * abs(a)]
                    for n_ in stable[:-m] if len(stable) > m else []:  # a stable estimator need not be read on
                        frozen.pop(n_)
                step = min(step, size.next(before, est[ahead][-1]))
                before = est[ahead][-1]
            for i in alive:
                for c in range(s):
                    snap = ("snap", i, c, wave)
                    frozen[snap] = children[i * s + c].copy()
                    known[snap] = Moments(0, np.zeros((1, 1)), np.zeros((1, 1)))
            starts = resync(sync, local, counts, children, stale, stale_n)
            stale, stale_n, wave = children, n, wave + 1
        loss = objective_of(estimate(known["parent", best], total).est[0, 0], parents[best])
        run.trace.append({"k": k + 1, "parents": len(parents), "left": len(alive), "best": best, "loss": loss, "n_read": read, "ratio": read / total, "halted": halted, "waves": wave, "w": parents[best].copy()})
        parents = children[best * s : (best + 1) * s]
        if halted:
            break
    losses = objective(multi_eval(ex, parents, spec, meter=run.cost), parents, spec)
    best = select_best(losses)
    run.w = parents[best]
    run.trace.append({"k": len(run.trace) + 1, "parents": len(parents), "left": 1, "best": best, "loss": float(losses[best]), "n_read": total, "ratio": 1.0, "halted": False, "waves": 1, "w": run.w.copy()})
    return run
