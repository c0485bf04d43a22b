"""Many-SUM aggregate queries: the losses and gradients of several models from one scan, by four physical plans."""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from calib.functions.losses import Spec, dot_array, dot_wide
from calib.sources.views import wide

#: Sums up to which the columns of a code-generated plan are used, and model values up to which Arrow batches are.
WIDE_SUMS, ARROW_VALUES = 200, 10_000_000
#: Model values up to which sparse examples are multiplied in Arrow batches, each task with all models.
SPARSE_VALUES = 1_000_000


@dataclass
class CostMeter:
    """Deterministic costs, one row for each pass: passes, rows read, sums and models."""

    rows: list[dict] = field(default_factory=list)

    def add(self, n_rows: int, aggregates: int, models: int, passes: int = 1) -> None:
        self.rows.append({"passes": passes, "rows_read": n_rows, "aggregates": aggregates, "models": models})

    def total(self, key: str) -> int:
        return sum(r[key] for r in self.rows)


@dataclass
class Moments:
    """Sums of s models over n examples: loss and gradient, with the sums of their squares. Adding them merges samples."""

    n: int
    s1: np.ndarray  # (s, 1 + d): loss, gradient
    s2: np.ndarray

    def __add__(self, other: Moments) -> Moments:
        return Moments(self.n + other.n, self.s1 + other.s1, self.s2 + other.s2)

    @property
    def loss(self) -> np.ndarray:
        return self.s1[:, 0]

    @property
    def grad(self) -> np.ndarray:
        return self.s1[:, 1:]

    def pick(self, rows) -> Moments:
        return Moments(self.n, self.s1[rows], self.s2[rows])


def merge_stable(a: tuple[int, float, float], b: tuple[int, float, float]) -> tuple[int, float, float]:
    """(n, mean, sum of squared deviations) of two samples together, without the cancellation of plain squares."""
    n = a[0] + b[0]
    if not n:
        return (0, 0.0, 0.0)
    d = b[1] - a[1]
    return (n, a[1] + d * b[0] / n, a[2] + b[2] + d * d * a[0] * b[0] / n)


def model_bytes(s: int, d: int, kind: str = "batch", squares: bool = False) -> int:
    """Bytes of the models of an iteration: s of them, or s * s for incremental methods; twice with sums of squares."""
    return 8 * d * (s * s if kind == "incremental" else s) * (2 if squares else 1)


def choose_plan(s: int, d: int, squares: bool, sparse: bool = False) -> str:
    if sparse:
        return "sparse"
    if s * (d + 1) * (2 if squares else 1) <= WIDE_SUMS:
        return "wide"
    return "arrow" if s * d <= ARROW_VALUES else "long"


def sums(examples: DataFrame, columns: dict[str, Column]) -> dict[str, float]:
    """The abstract query: any number of SUMs of row functions in one pass."""
    row = examples.agg(*(F.sum(c).alias(k) for k, c in columns.items())).first()
    return {k: row[k] or 0.0 for k in columns}


def fuse_requests(examples: DataFrame, requests: list[dict[str, Column]]) -> list[dict[str, float]]:
    """Several such queries over one relation, answered by a single pass."""
    merged = {f"{i}|{k}": c for i, r in enumerate(requests) for k, c in r.items()}
    found = sums(examples, merged)
    return [{k: found[f"{i}|{k}"] for k in r} for i, r in enumerate(requests)]


def wide_columns(models: np.ndarray, spec: Spec, want_sq: bool = False) -> tuple[list[Column], list[Column]]:
    """Row columns that bind margins and slopes once, and the SUMs over them, by model: loss, gradient, squares."""
    s, d = models.shape
    bind, out = [], []
    for m in range(s):
        dot = dot_wide(wide(d), models[m])
        bind += [spec.f.column(dot, F.col("y")).alias(f"_f{m}"), spec.f.column_slope(dot, F.col("y")).alias(f"_g{m}")]
        terms = [F.col(f"_f{m}"), *(F.col(f"_g{m}") * F.col(x) for x in wide(d))]
        out += [F.sum(t).alias(f"s_{m}_{j}") for j, t in enumerate(terms)]
        if want_sq:
            out += [F.sum(t * t).alias(f"q_{m}_{j}") for j, t in enumerate(terms)]
    return bind, out


def _eval_wide(examples: DataFrame, models: np.ndarray, spec: Spec, want_sq: bool) -> Moments:
    s, d = models.shape
    bind, out = wide_columns(models, spec, want_sq)
    row = examples.select(*wide(d), *bind).agg(F.count(F.lit(1)).alias("n"), *out).first()
    get = lambda k: np.array([[row[f"{k}_{m}_{j}"] or 0.0 for j in range(d + 1)] for m in range(s)])
    return Moments(row["n"], get("s"), get("q") if want_sq else np.zeros((s, d + 1)))


def batch_matrix(b: pa.RecordBatch, d: int) -> tuple[np.ndarray, np.ndarray]:
    """(X, y) of an Arrow batch with wide columns or an array column x."""
    if "x" in b.schema.names:
        x = b.column("x").flatten().to_numpy(zero_copy_only=False).reshape(-1, d) if b.num_rows else np.zeros((0, d))
    else:
        x = np.column_stack([b.column(c).to_numpy(zero_copy_only=False) for c in wide(d)]) if b.num_rows else np.zeros((0, d))
    return x, b.column("y").to_numpy(zero_copy_only=False)


def _columns(examples: DataFrame, d: int) -> list[str]:
    return ["x"] if "x" in examples.columns else wide(d)


def partial_states(examples: DataFrame, models: np.ndarray, spec: Spec, want_sq: bool = False) -> DataFrame:
    """n and the flat sums of each task, by matrix products over Arrow batches."""
    s, d = models.shape
    f, sent = spec.f, examples.sparkSession.sparkContext.broadcast(models)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        w, n, s1, s2 = sent.value, 0, np.zeros((s, d + 1)), np.zeros((s, d + 1))
        for b in batches:
            x, y = batch_matrix(b, d)
            dot, yy = x @ w.T, y[:, None]
            v, g = f.value(dot, yy), f.slope(dot, yy)
            n += len(y)
            s1[:, 0] += v.sum(axis=0)
            s1[:, 1:] += g.T @ x
            if want_sq:
                s2[:, 0] += (v * v).sum(axis=0)
                s2[:, 1:] += (g * g).T @ (x * x)
        yield pa.RecordBatch.from_arrays([pa.array([n]), pa.array([np.concatenate([s1.ravel(), s2.ravel()])], pa.list_(pa.float64()))], names=["n", "sums"])

    return examples.select(*_columns(examples, d), "y").mapInArrow(run, "n long, sums array<double>")


def _eval_arrow(examples: DataFrame, models: np.ndarray, spec: Spec, want_sq: bool, merge: str = "central") -> Moments:
    s, d = models.shape
    states = (sparse_states if "idx" in examples.columns else partial_states)(examples, models, spec, want_sq)
    add = lambda rows: _add_states(rows, 2 * s * (d + 1))
    if merge == "tree":  # a first level of about the root of the number of tasks, then one
        parts = max(2, math.isqrt(states.rdd.getNumPartitions()))
        states = states.repartition(parts).mapInArrow(add, states.schema)
    states = states.repartition(1).sortWithinPartitions("n", "sums").mapInArrow(add, states.schema)  # a coalesce(1) would scan in one task; sorted, so that sums are the same in each run
    row = states.first()
    flat = np.array(row["sums"]).reshape(2, s, d + 1)
    return Moments(row["n"], flat[0], flat[1])


def _add_states(batches: Iterator[pa.RecordBatch], size: int) -> Iterator[pa.RecordBatch]:
    n, total = 0, np.zeros(size)
    for b in batches:
        if b.num_rows:
            n += int(np.sum(b.column("n").to_numpy(zero_copy_only=False)))
            total += b.column("sums").flatten().to_numpy(zero_copy_only=False).reshape(-1, size).sum(axis=0)
    yield pa.RecordBatch.from_arrays([pa.array([n]), pa.array([total], pa.list_(pa.float64()))], names=["n", "sums"])


def models_frame(examples: DataFrame, models: np.ndarray) -> DataFrame:
    rows = [(m, [float(v) for v in w]) for m, w in enumerate(models)]
    return examples.sparkSession.createDataFrame(rows, "m int, w array<double>")


def long_sums(examples: DataFrame, models: np.ndarray, spec: Spec) -> DataFrame:
    """m, n, loss and grad of every model: each row meets every model of a small broadcast table, then sums by model and place."""
    d = models.shape[1]
    x = F.col("x") if "x" in examples.columns else F.array(*wide(d))
    rows = examples.select(x.alias("x"), "y").join(F.broadcast(models_frame(examples, models)))
    dot = dot_array("x", F.col("w"))
    rows = rows.select("m", "x", spec.f.column(dot, F.col("y")).alias("f"), spec.f.column_slope(dot, F.col("y")).alias("g"))
    grads = [F.sum(F.col("g") * F.element_at("x", j + 1)) for j in range(d)]
    squares = [F.sum(F.pow(F.col("g") * F.element_at("x", j + 1), 2)) for j in range(d)]
    return rows.groupBy("m").agg(F.count(F.lit(1)).alias("n"), F.array(F.sum("f"), *grads).alias("s1"), F.array(F.sum(F.col("f") * F.col("f")), *squares).alias("s2"))


def _eval_long(examples: DataFrame, models: np.ndarray, spec: Spec) -> Moments:
    found = {r["m"]: r for r in long_sums(examples, models, spec).collect()}
    zero = [0.0] * (models.shape[1] + 1)
    get = lambda k: np.array([found[m][k] if m in found else zero for m in range(len(models))])
    return Moments(found[0]["n"] if found else 0, get("s1"), get("s2"))


def sparse_sums(examples: DataFrame, models: DataFrame, s: int, spec: Spec, want_sq: bool = False) -> tuple[DataFrame, DataFrame]:
    """Losses by model and gradients by feature of sparse examples (idx, val, y), with want_sq also sums of squares.

    models holds (j, ws): the weights of feature j in all s models, a table of any size that is joined by j, so
    that neither models nor gradients need fit anywhere as a whole; a frequent feature is a skewed key of that
    join, which adaptive execution splits. The entries of a row meet again by a number of its own, so rows may
    repeat in every column.
    """
    rows = examples.select("y", "idx", "val").withColumn("row", F.monotonically_increasing_id())  # numbered before entries are taken apart
    rows = rows.select("row", "y", F.explode_outer(F.arrays_zip("idx", "val")).alias("e"))
    entries = rows.select("row", "y", F.col("e.idx").alias("j"), F.col("e.val").alias("v"))
    whole = entries.join(models, "j", "left").groupBy("row", "y").agg(F.collect_list(F.struct("j", "v", "ws")).alias("es"))

    def dot(m: int) -> Column:
        return F.aggregate("es", F.lit(0.0), lambda a, e: a + F.coalesce(e["v"], F.lit(0.0)) * F.coalesce(F.get(e["ws"], F.lit(m)), F.lit(0.0)))

    dots = whole.select("y", F.transform("es", lambda e: F.struct(e["j"].alias("j"), e["v"].alias("v"))).alias("es"), *(dot(m).alias(f"d{m}") for m in range(s)))
    f = [spec.f.column(F.col(f"d{m}"), F.col("y")) for m in range(s)]
    squares = [F.sum(c * c).alias(f"square{m}") for m, c in enumerate(f)] if want_sq else []
    loss = dots.agg(F.count(F.lit(1)).alias("n"), *(F.sum(c).alias(f"loss{m}") for m, c in enumerate(f)), *squares)
    slopes = dots.select(F.explode("es").alias("e"), F.array(*(spec.f.column_slope(F.col(f"d{m}"), F.col("y")) for m in range(s))).alias("g"))
    terms = [F.col("e.v") * F.get("g", F.lit(m)) for m in range(s)]
    squares = [F.array(*(F.sum(t * t) for t in terms)).alias("qs")] if want_sq else []
    grad = slopes.where("e.j IS NOT NULL").groupBy(F.col("e.j").alias("j")).agg(F.array(*(F.sum(t) for t in terms)).alias("gs"), *squares)
    return loss, grad


def sparse_states(examples: DataFrame, models: np.ndarray, spec: Spec, want_sq: bool = False) -> DataFrame:
    """As partial_states, over sparse examples (idx, val, y) whose entries are summed by row and by feature."""
    s, d = models.shape
    f, sent = spec.f, examples.sparkSession.sparkContext.broadcast(models)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        w, n, s1, s2 = sent.value, 0, np.zeros((s, d + 1)), np.zeros((s, d + 1))
        for b in batches:
            size = b.column("idx").value_lengths().fill_null(0).to_numpy(zero_copy_only=False)
            j, v, y = (c.to_numpy(zero_copy_only=False) for c in (b.column("idx").flatten(), b.column("val").flatten(), b.column("y")))
            row = np.repeat(np.arange(len(y)), size)
            n += len(y)
            for m in range(s):
                dot = np.bincount(row, w[m, j] * v, len(y))
                value, g = f.value(dot, y), f.slope(dot, y)[row] * v
                s1[m, 0] += value.sum()
                s1[m, 1:] += np.bincount(j, g, d)
                if want_sq:
                    s2[m, 0] += (value * value).sum()
                    s2[m, 1:] += np.bincount(j, g * g, d)
        yield pa.RecordBatch.from_arrays([pa.array([n]), pa.array([np.concatenate([s1.ravel(), s2.ravel()])], pa.list_(pa.float64()))], names=["n", "sums"])

    entries = F.filter(F.arrays_zip("idx", "val"), lambda e: e["idx"].isNotNull())
    rows = examples.select(entries.alias("e"), "y").select(F.col("e.idx").alias("idx"), F.transform("e.val", lambda v: F.coalesce(v, F.lit(0.0))).alias("val"), "y")
    return rows.mapInArrow(run, "n long, sums array<double>")


def sparse_models(examples: DataFrame, models: np.ndarray) -> DataFrame:
    """(j, ws) of those features that some model uses."""
    used = np.flatnonzero(np.any(models != 0, axis=0))
    return examples.sparkSession.createDataFrame([(int(j), [float(v) for v in models[:, j]]) for j in used], "j long, ws array<double>")


def _eval_sparse(examples: DataFrame, models: np.ndarray, spec: Spec, want_sq: bool = False) -> Moments:
    s, d = models.shape
    loss, grad = sparse_sums(examples, sparse_models(examples, models), s, spec, want_sq)
    row, s1, s2 = loss.first(), np.zeros((s, d + 1)), np.zeros((s, d + 1))
    s1[:, 0] = [row[f"loss{m}"] or 0.0 for m in range(s)]
    if want_sq:
        s2[:, 0] = [row[f"square{m}"] or 0.0 for m in range(s)]
    for r in grad.toLocalIterator():
        s1[:, 1 + r["j"]] = r["gs"]
        if want_sq:
            s2[:, 1 + r["j"]] = r["qs"]
    return Moments(row["n"], s1, s2)


def multi_eval(examples: DataFrame, models: np.ndarray, spec: Spec, plan: str = "auto", want_sq: bool = False, merge: str = "central", meter: CostMeter | None = None) -> Moments:
    """Losses and gradients of all rows of `models` in one pass over the examples; sums without the regulariser."""
    models = np.atleast_2d(np.asarray(models, dtype=float))
    s, d = models.shape
    if plan == "auto":
        plan = choose_plan(s, d, want_sq, "idx" in examples.columns)
        plan = "arrow" if plan == "wide" and "x" in examples.columns else plan
    if plan == "sparse":
        plan = "arrow" if s * d <= SPARSE_VALUES else "joined"
    if plan == "wide":
        out = _eval_wide(examples, models, spec, want_sq)
    elif plan == "arrow":
        out = _eval_arrow(examples, models, spec, want_sq, merge)
    elif plan == "long":
        out = _eval_long(examples, models, spec)
    elif plan == "joined":
        out = _eval_sparse(examples, models, spec, want_sq)
    else:
        raise ValueError(f"no plan is called {plan}")
    if meter is not None:
        meter.add(out.n, s * (d + 1) * (2 if want_sq else 1), s)
    return out


def losses_of(examples: DataFrame, models: np.ndarray, spec: Spec, meter: CostMeter | None = None) -> Moments:
    """The losses alone of dense examples, s sums in one pass; the gradients of the result are zero."""
    models = np.atleast_2d(np.asarray(models, dtype=float))
    s, d = models.shape
    dot = (lambda w: dot_array("x", F.array(*map(F.lit, w.tolist())))) if "x" in examples.columns else (lambda w: dot_wide(wide(d), w))
    row = examples.agg(F.count(F.lit(1)).alias("n"), *(F.sum(spec.f.column(dot(w), F.col("y"))).alias(f"l{m}") for m, w in enumerate(models))).first()
    s1 = np.zeros((s, d + 1))
    s1[:, 0] = [row[f"l{m}"] or 0.0 for m in range(s)]
    if meter is not None:
        meter.add(row["n"], s, s)
    return Moments(row["n"], s1, np.zeros_like(s1))


def objective(m: Moments, models: np.ndarray, spec: Spec) -> np.ndarray:
    """The objective of each model, with its regulariser."""
    return m.loss * spec.per(m.n) + spec.reg_value(models)


def full_gradient(m: Moments, models: np.ndarray, spec: Spec) -> np.ndarray:
    return m.grad * spec.per(m.n) + spec.reg_grad(np.atleast_2d(models))


def scan_count(df: DataFrame) -> int:
    """How many file scans the plan of a frame has."""
    return df._jdf.queryExecution().optimizedPlan().toString().count("Relation [")
