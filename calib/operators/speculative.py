"""Speculative iterations: several configurations tried in one scan, from a distribution that learns from their losses."""

from __future__ import annotations

import pickle
import time
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from calib.functions.losses import Spec
from calib.operators.batch import Run, StopRule
from calib.operators.incremental import Lists, by_part, delayed, descend, in_order, in_turns, lists, margins, ordered, packed
from calib.operators.stepdist import BivariatePhi, NormalPhi, StepCountController, loss_weights, update_bivariate, update_normal
from calib.plans.moments import WIDE_SUMS, CostMeter, full_gradient, losses_of, multi_eval, objective
from calib.session import materialize


@dataclass(frozen=True)
class Grid:
    """Fixed steps, all multiplied by decay after every iteration."""

    values: tuple[float, ...]
    decay: float = 1.0

    def at(self, k: int) -> list[float]:
        return [v * self.decay**k for v in self.values]


def nested_grid(s: int, first: float = 1e-4, factor: float = 10.0) -> Grid:
    """s steps, of which the first s' are those of a smaller grid: one, then a larger, a smaller, and so on outwards."""
    return Grid(tuple(first * factor ** ((i + 1) // 2 * (1 if i % 2 else -1)) for i in range(s)))


def significant(v: float, digits: int = 9) -> float:
    return float(f"{v:.{digits - 1}e}") if np.isfinite(v) else float("inf")


def select_best(losses) -> int:
    """The least loss; equal ones (to 9 digits) by place, and non-finite ones never unless there is nothing else."""
    return min(range(len(losses)), key=lambda i: (significant(losses[i]), i))


def trial_models(w: np.ndarray, g: np.ndarray, alphas) -> np.ndarray:
    return np.array([w - a * g for a in alphas])


def train_spec_bgd(ex: DataFrame, spec: Spec, w0, grid: Grid | None = None, phi: NormalPhi | None = None, s: int = 4, iterations: int = 5, control: StepCountController | None = None, clock: Callable[[], float] = time.perf_counter, kappa: float = 1.0, weights: str = "gap", plan: str = "auto", overlap: bool = True, stop: StopRule | None = None, keep_best: bool = False, seed: int | None = None) -> Run:
    """Batch descent over s trial models an iteration.

    One scan gives every trial's loss and gradient; the best goes on. The steps come from a grid or from phi,
    which is refitted to the losses; control adapts s to the measured time. Without overlap a scan sums losses
    alone, and a second one the gradient of the best model. keep_best also keeps the old model as a candidate, so that losses never rise.
    """
    w, run, losses = np.array(w0, dtype=float), Run(np.array(w0, dtype=float)), []
    m = multi_eval(ex, w, spec, plan, meter=run.cost)
    loss, g = float(objective(m, w, spec)[0]), full_gradient(m, w, spec)[0]
    for k in range(iterations):
        s = control.s if control else s
        alphas = grid.at(k) if grid else phi.sample(s, None if seed is None else seed + k)
        began = clock()
        models = trial_models(w, g, alphas)
        m = multi_eval(ex, models, spec, plan, meter=run.cost) if overlap else losses_of(ex, models, spec, run.cost)
        found = objective(m, models, spec)
        best = select_best(found)
        if not (keep_best and not significant(found[best]) < significant(loss)):
            m = m.pick([best]) if overlap else multi_eval(ex, models[best], spec, plan, meter=run.cost)
            w, loss, g = models[best], float(found[best]), full_gradient(m, models[best], spec)[0]
        secs = clock() - began
        losses.append(loss)
        run.trace.append({"k": k + 1, "s": len(alphas), "best": best, "alpha": float(alphas[best]), "loss": loss, "w": w.copy(), "secs": secs, "phi": phi, "candidates": [(i, float(a), float(x)) for i, (a, x) in enumerate(zip(alphas, found))]})
        if phi is not None and grid is None:
            phi = update_normal(phi, alphas, loss_weights(found, weights), kappa)
        if control:
            control.next(secs)
        if stop is not None and stop.done(losses):
            break
    run.w = w
    return run


def train_spec_bgd_grids(ex: DataFrame, spec: Spec, w0, grids: list[Grid], iterations: int, plan: str = "auto") -> list[Run]:
    """What train_spec_bgd gives for each grid, all of them from the same scans."""
    w0, runs = np.array(w0, dtype=float), [Run(np.array(w0, dtype=float)) for _ in grids]
    m = multi_eval(ex, w0, spec, plan)
    for run in runs:
        run.cost.add(m.n, len(w0) + 1, 1)
    at = [(w0, full_gradient(m, w0, spec)[0])] * len(grids)
    for k in range(iterations):
        trials = [trial_models(w, g, grid.at(k)) for grid, (w, g) in zip(grids, at)]
        m, first = multi_eval(ex, np.concatenate(trials), spec, plan), 0
        for j, (run, grid, models) in enumerate(zip(runs, grids, trials)):
            own = m.pick(slice(first, first + len(models)))
            first += len(models)
            found = objective(own, models, spec)
            best = select_best(found)
            run.cost.add(m.n, len(models) * (len(w0) + 1), len(models))
            run.w = models[best]
            at[j] = (run.w, full_gradient(own.pick([best]), run.w, spec)[0])
            run.trace.append({"k": k + 1, "s": len(models), "best": best, "alpha": float(grid.at(k)[best]), "loss": float(found[best]), "w": run.w.copy()})
    return runs


def independent_runs(ex: DataFrame, spec: Spec, w, models: np.ndarray, plan: str = "auto") -> tuple[np.ndarray, CostMeter]:
    """The baseline without sharing: a scan for each configuration. Their losses and the cost."""
    meter = CostMeter()
    return np.array([objective(multi_eval(ex, m, spec, plan, meter=meter), m, spec)[0] for m in models]), meter


CHILDREN = "kind string, i int, l int, n long, w array<double>, loss double"


def advance(states: dict[int, list | bytes], runs: Iterator[tuple], spec: Spec, parents: np.ndarray, alphas: np.ndarray, batches_of: np.ndarray | None, late: int) -> None:
    """Moves the states of parts, which may be pickled or absent, over runs (part, X, y) of their examples."""
    s, d, c = len(parents), parents.shape[1], len(alphas)
    for p, x, y in runs:
        if p not in states:
            states[p] = [0, np.repeat(parents, c, axis=0), np.zeros(s), np.zeros((s * c, d)), np.zeros(s * c, dtype=int), delayed(np.repeat(parents, c, axis=0), late, x, spec)]
        elif isinstance(states[p], bytes):
            states[p] = pickle.loads(states[p])
        st = states[p]
        a = np.tile(alphas, s)
        st[2] += spec.f.value(margins(x, parents), y[:, None]).sum(axis=0)
        if batches_of is None:
            descend(st[1], x, y, a, spec, st[5])
        else:
            b = np.tile(batches_of, s)
            for m in range(s * c):
                at = 0
                while at < len(y):
                    take = min(int(b[m] - st[4][m]), len(y) - at)
                    xs, ys = x[at : at + take], y[at : at + take]
                    st[3][m] += spec.f.slope(xs @ st[1][m], ys) @ xs
                    st[4][m] += take
                    at += take
                    if st[4][m] == b[m]:
                        st[1][m] -= a[m] * (st[3][m] * spec.per(int(b[m])) + spec.reg_grad(st[1][m]))
                        st[3][m], st[4][m] = 0, 0
        st[0] += len(y)


def ended(states: dict[int, list], spec: Spec, s: int, alphas: np.ndarray, batches_of: np.ndarray | None) -> list[tuple]:
    """Rows (CHILDREN) of parts whose examples have all been seen."""
    out, c = [], len(alphas)
    for n, w, loss, g, held, _ in states.values():
        if batches_of is not None:
            for m in np.flatnonzero(held):
                w[m] -= np.tile(alphas, s)[m] * (g[m] * spec.per(int(held[m])) + spec.reg_grad(w[m]))
        out += [("loss", i, None, n, None, float(loss[i])) for i in range(s)]
        out += [("model", m // c, m % c, n, w[m].tolist(), None) for m in range(s * c)]
    return out


def igd_children(ex: DataFrame, spec: Spec, parents: np.ndarray, alphas: np.ndarray, key: list[str], part: str, batches_of: np.ndarray | None = None, late: int = 0) -> DataFrame:
    """One pass: every parent's loss, and its children's models after it, by part.

    Children of parent i start there and step with each of alphas; with batches_of, child l takes one step for
    each batches_of[l] examples. late: an update sees the models of late - 1 updates ago; 0: the newest. Rows: (loss, i) sums and (model, i, l) models with the part's count.
    """
    d = parents.shape[1]

    def run(rows: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        states: dict[int, list] = {}
        advance(states, by_part(rows, d), spec, parents, alphas, batches_of, late)
        cols = list(zip(*ended(states, spec, len(parents), alphas, batches_of))) or [()] * 6
        kinds = (pa.string(), pa.int32(), pa.int32(), pa.int64(), pa.list_(pa.float64()), pa.float64())
        yield pa.RecordBatch.from_arrays([pa.array(v, t) for v, t in zip(cols, kinds)], names=["kind", "i", "l", "n", "w", "loss"])

    return ordered(ex, part, key, d).mapInArrow(run, CHILDREN)


def children_of(stored: Lists, spec: Spec, parents: np.ndarray, alphas: np.ndarray, batches_of: np.ndarray | None = None, late: int = 0, turns: tuple[int, int] | None = None) -> dict[tuple, np.ndarray]:
    """What merge_children has of a pass of igd_children, by a chain of jobs: a part's state goes from one to the next.

    turns: (nodes, threads) whose threads, the parts of the lists, share their node's models.
    """
    d, states, out = parents.shape[1], {}, {}

    def job(rows: DataFrame, *ends: int) -> None:
        begun = dict(states)

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            own, seen = begun.copy(), in_order(batches, d, *ends) if ends else by_part(batches, d)
            advance(own, seen, spec, parents, alphas, batches_of, late)
            moved = {p: pickle.dumps(st) for p, st in own.items() if not isinstance(st, bytes)}
            yield pa.RecordBatch.from_arrays([pa.array(list(moved), pa.int64()), pa.array(list(moved.values()), pa.binary())], names=["part", "state"])

        states.update((r["part"], bytes(r["state"])) for r in rows.mapInArrow(run, "part long, state binary").collect())

    for v in stored.by_turn(*turns) if turns else stored.by_part():
        job(*(v if turns else (v,)))
    for kind, i, l, n, w, loss in ended({p: pickle.loads(st) for p, st in sorted(states.items())}, spec, len(parents), alphas, batches_of):
        if kind == "loss":
            out[(i,)] = out.get((i,), 0.0) + loss
            out[()] = out.get((), 0) + (n if not i else 0)
        else:
            out[(i, l)] = out.get((i, l), 0.0) + n * np.array(w)
    return {k: v / out[()] if len(k) == 2 else v for k, v in out.items()}


def merge_children(rows: DataFrame, d: int) -> dict[tuple, np.ndarray]:
    """Averages of models by count, and sums of losses, over parts: keys (i, l) and (i,); under () the number of examples."""
    if d > WIDE_SUMS:  # too many columns for generated code: a row for each place
        places = rows.select("kind", "i", "l", "n", "loss", F.posexplode_outer("w").alias("j", "v"))
        sums, out = places.groupBy("kind", "i", "l", "j").agg(F.sum("loss").alias("loss"), F.sum("n").alias("n"), F.sum(F.col("n") * F.col("v")).alias("v")), {}
        for r in sums.toLocalIterator():
            if r["kind"] == "loss":
                out[(r["i"],)], out[()] = r["loss"], r["n"]
            else:
                out.setdefault((r["i"], r["l"]), np.zeros(d))[r["j"]] = r["v"] / r["n"]
        return out
    agg = rows.groupBy("kind", "i", "l").agg(F.sum("loss").alias("loss"), F.sum("n").alias("n"), *(F.sum(F.col("n") * F.element_at("w", j + 1)).alias(f"w{j}") for j in range(d)))
    out = {}
    for r in agg.collect():
        if r["kind"] == "loss":
            out[(r["i"],)], out[()] = r["loss"], r["n"]
        else:
            out[(r["i"], r["l"])] = np.array([r[f"w{j}"] for j in range(d)]) / r["n"]
    return out


def train_spec_igd(ex: DataFrame, spec: Spec, w0, alphas, iterations: int, key: list[str], part: str, batches_of=None, final_eval: bool = True, variant: str = "merge", nodes: int = 1, threads: int = 4, phi: NormalPhi | None = None, s: int = 4, control: StepCountController | None = None, clock: Callable[[], float] = time.perf_counter, kappa: float = 1.0, weights: str = "gap", stop: StopRule | None = None, seed: int | None = None, stored: Lists | None = None) -> Run:
    """Incremental descent with s * s models: while children move on, their parents' losses are summed.

    After a pass only the children of the best parent stay, as the next parents. Losses are those of parents,
    so they lag one pass; the closing evaluation makes up for the last, unless stop ended the passes at the best parent.
    Steps are alphas or, with phi, draws from it; it is refitted to the steps of the pass before as soon as the losses
    of what they gave are known. control adapts s to the measured time of a pass; of alphas it takes the first s.
    variant: merge has models for each part; with lock and nolock the threads of a node share them, as in
    train_igd_shared, and part is not used. stored: the examples as lists, by part or, with lock and nolock, by
    ord % (nodes * threads); otherwise several passes over dense examples write them first.
    """
    if variant not in ("merge", "lock", "nolock"):
        raise ValueError(f"no variant is called {variant}")
    if batches_of is not None and (phi is not None or control is not None):
        raise ValueError("batches_of goes with fixed alphas")
    whole, turns, own = ex, None if variant == "merge" else (nodes, threads), None
    if stored is None and (iterations == 1 or "idx" in ex.columns):
        if turns:
            ex, part = in_turns(ex, key, nodes, threads), "node"
    elif stored is None:
        stored = own = lists(ex.withColumn("turn", F.col("ord") % (nodes * threads)) if turns else ex, "turn" if turns else part, key, len(w0))
    late = threads if variant == "nolock" else 0
    parents, run, d = np.array([np.asarray(w0, dtype=float)]), Run(np.asarray(w0, dtype=float)), len(w0)
    sizes = None if batches_of is None else np.asarray(batches_of, dtype=int)
    lowest, before = [], None
    for k in range(iterations):
        s = control.s if control else s
        tried = np.asarray(alphas if phi is None and control is None else alphas[:s] if phi is None else phi.sample(s, None if seed is None else seed + k), dtype=float)
        began = clock()
        found = children_of(stored, spec, parents, tried, sizes, late, turns) if stored else merge_children(igd_children(ex, spec, parents, tried, key, part, sizes, late), d)
        secs = clock() - began
        losses = [found[(i,)] * spec.per(found.get((), 0)) + float(np.sum(spec.reg_value(p))) for i, p in enumerate(parents)]
        run.cost.add(0, len(parents) + len(parents) * len(tried), len(parents) * len(tried))
        best = select_best(losses)
        lowest.append(float(losses[best]))
        run.trace.append({"k": k + 1, "s": len(tried), "parents": len(parents), "models": len(parents) * len(tried), "best": best, "loss": lowest[-1], "w": parents[best].copy(), "secs": secs, "phi": phi})
        if stop is not None and stop.done(lowest):
            run.w, final_eval = parents[best], False
            break
        if phi is not None and before is not None:
            phi = update_normal(phi, before, loss_weights(losses, weights), kappa)
        if control:
            control.next(secs)
        parents, before = np.array([found[(best, c)] for c in range(len(tried))]), tried
    else:
        run.w = parents[0]
    if own:
        own.drop()
    if final_eval:
        losses = objective(multi_eval(whole, parents, spec, meter=run.cost), parents, spec)
        best = select_best(losses)
        run.w = parents[best]
        run.trace.append({"k": iterations + 1, "s": len(parents), "parents": len(parents), "models": 0, "best": best, "loss": float(losses[best]), "w": run.w.copy(), "secs": 0.0, "phi": phi})
    return run


def train_spec_igd_grids(ex: DataFrame, spec: Spec, w0, grids: list[tuple[float, ...]], iterations: int, key: list[str], part: str) -> list[Run]:
    """What train_spec_igd gives for each grid of steps, all of them from the same passes: parents and steps that grids share move once."""
    w0 = np.asarray(w0, dtype=float)
    d, runs, parents = len(w0), [Run(w0) for _ in grids], [w0[None, :]] * len(grids)
    steps = np.array(list(dict.fromkeys(a for grid in grids for a in grid)))
    of = [[int(np.flatnonzero(steps == a)[0]) for a in grid] for grid in grids]
    moved = materialize(packed(ex, part, key, d), "packed") if iterations > 1 and "idx" not in ex.columns else ex

    def note(run: Run, k: int, own: np.ndarray, losses: list[float], models: int) -> int:
        best = select_best(losses)
        run.w = own[best]
        run.trace.append({"k": k, "s": models // len(own) if models else len(own), "parents": len(own), "models": models, "best": best, "loss": float(losses[best]), "w": own[best].copy()})
        return best

    for k in range(iterations):
        distinct, place = np.unique(np.concatenate(parents), axis=0, return_inverse=True)
        place = np.split(place.ravel(), np.cumsum([len(p) for p in parents])[:-1])
        found = merge_children(igd_children(moved, spec, distinct, steps, key, part), d)
        for j, run in enumerate(runs):
            losses = [found[(i,)] * spec.per(found.get((), 0)) + float(np.sum(spec.reg_value(distinct[i]))) for i in place[j]]
            best = note(run, k + 1, parents[j], losses, len(parents[j]) * len(of[j]))
            run.cost.add(0, len(place[j]) + len(place[j]) * len(of[j]), len(place[j]) * len(of[j]))
            parents[j] = np.array([found[(int(place[j][best]), c)] for c in of[j]])
    m, first = multi_eval(ex, np.concatenate(parents), spec), 0
    for run, own in zip(runs, parents):
        note(run, iterations + 1, own, objective(m.pick(slice(first, first + len(own))), own, spec).tolist(), 0)
        run.cost.add(m.n, len(own) * (d + 1), len(own))
        first += len(own)
    return runs


def train_spec_minibatch(ex: DataFrame, spec: Spec, w0, phi: BivariatePhi, s: int, iterations: int, key: list[str], part: str, kappa: float = 1.0, seed: int = 0) -> Run:
    """Mini-batch descent with configurations of step and batch size from a two-dimensional distribution, refitted every pass."""
    w, run, d = np.asarray(w0, dtype=float), Run(np.asarray(w0, dtype=float)), len(w0)
    for k in range(iterations):
        configs = phi.sample(s, seed + k)
        alphas, sizes = np.array([a for a, _ in configs]), np.array([b for _, b in configs])
        found = merge_children(igd_children(ex, spec, w[None, :], alphas, key, part, sizes), d)
        models = np.array([found[(0, c)] for c in range(s)])
        losses = objective(multi_eval(ex, models, spec, meter=run.cost), models, spec)
        best = select_best(losses)
        w = models[best]
        run.trace.append({"k": k + 1, "alpha": float(alphas[best]), "batch": int(sizes[best]), "loss": float(losses[best]), "w": w.copy(), "mean": phi.mean})
        phi = update_bivariate(phi, configs, loss_weights(losses), kappa)
    run.w = w
    return run
