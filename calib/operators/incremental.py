"""Incremental methods: one step for each example or small batch, in random order, alone or in parallel.

Examples of a part stream through a task in order; only models are kept. Spark tasks share no memory, so a
node with a shared model is one task that takes the examples of its threads in turn, and contention is a
fixed staleness: updates see the model as it was some updates ago.
"""

from __future__ import annotations

import math
from collections import deque
from collections.abc import Callable, Iterator
from dataclasses import dataclass
from functools import cache, reduce
from itertools import accumulate

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from calib.functions.losses import Loss, Spec
from calib.operators.batch import Run, Step, average, train_bgd, StopRule
from calib.plans.moments import batch_matrix, multi_eval, objective
from calib.session import drop_shuffles, drop_table, shared_dir
from calib.sources.order import digest, digits
from calib.sources.views import wide

STATE = "part long, n long, w array<double>"


#: Values of all models up to which a loop over Python numbers beats one over small arrays; examples whose products are taken together.
SCALAR_VALUES, BLOCK = 128, 32


def sgd(x: np.ndarray, y: np.ndarray, w: np.ndarray, alpha: np.ndarray, spec: Spec) -> None:
    """Steps of all rows of w (models) over the examples one by one; changes w. alpha: by model."""
    descend(w, x, y, alpha, spec)


@cache
def single(loss: Loss, d: int):
    """run(examples, w, alpha): one model's steps over rows (x0, .., label), as a loop over plain numbers that is written out for d."""
    xs, ws = ([f"{c}{j}" for j in range(d)] for c in "xw")
    lines = [f"{', '.join(ws)}, = w", f"for {', '.join(xs)}, t in examples:", f"  m = {' + '.join(f'{w} * {x}' for w, x in zip(ws, xs))}", f"  g = ({loss.scalar}) * alpha"]
    lines += [f"  {w} -= g * {x}" for w, x in zip(ws, xs)] + [f"return [{', '.join(ws)}]"]
    scope = {"exp": math.exp}
    exec("def run(examples, w, alpha):\n" + "".join(f" {v}\n" for v in lines), scope)
    return scope["run"]


class Late:
    """The last updates, which the next example does not see yet: their examples and each model's factors."""

    def __init__(self, depth: int, models: int, d: int):
        self.x, self.g = np.zeros((depth, d)), np.zeros((depth, models))


def descend_blocks(w: np.ndarray, x: np.ndarray, y: np.ndarray, alpha: np.ndarray, spec: Spec, late: Late | None = None) -> None:
    """As descend, for dense examples without a regulariser.

    A block's margins are taken from the models before it, and each is corrected by the updates since, which are
    known by their factors and the products of examples. The same steps as one by one, but for rounding.
    """
    slope, s = spec.f.slope, len(w)
    late = late or Late(0, s, w.shape[1])
    k = len(late.x)
    for at in range(0, len(y), BLOCK):
        xs, labels = np.ascontiguousarray(x[at : at + BLOCK]), y[at : at + BLOCK].tolist()
        seen = np.concatenate([late.x, xs])
        g = np.concatenate([late.g, np.empty((len(xs), s))])
        dots, products = xs @ (w + late.g.T @ late.x).T, xs @ seen.T
        for i, t in enumerate(labels):
            m = dots[i] - products[i, :i] @ g[:i] if i else dots[0]
            np.multiply(slope(m, t), alpha, out=g[k + i])
        w -= g[k:].T @ xs
        late.x, late.g = seen[len(seen) - k :], g[len(g) - k :]


class SparseRows:
    """Examples by the places and values of what is not zero."""

    def __init__(self, edges: np.ndarray, idx: np.ndarray, val: np.ndarray):
        self.edges, self.idx, self.val = edges, idx, val

    def row(self, i: int) -> tuple[np.ndarray, np.ndarray]:
        a, z = self.edges[i], self.edges[i + 1]
        return self.idx[a:z], self.val[a:z]

    def __getitem__(self, at: slice) -> SparseRows:
        a, z, _ = at.indices(len(self.edges) - 1)
        return SparseRows(self.edges[a : z + 1], self.idx, self.val)


def sparse_rows(b: pa.RecordBatch) -> SparseRows:
    idx = b.column("idx")
    edges = np.concatenate([[0], np.cumsum(idx.value_lengths().fill_null(0).to_numpy(zero_copy_only=False))]).astype(int)
    return SparseRows(edges, idx.flatten().to_numpy(zero_copy_only=False), b.column("val").flatten().to_numpy(zero_copy_only=False))


def margins(x: np.ndarray | SparseRows, models: np.ndarray) -> np.ndarray:
    """Dot products, (examples, models)."""
    if isinstance(x, SparseRows):
        return np.array([models[:, j] @ v for j, v in map(x.row, range(len(x.edges) - 1))])
    return x @ models.T


def descend(w: np.ndarray, x: np.ndarray | SparseRows, y: np.ndarray, alpha: np.ndarray, spec: Spec, late: Late | deque | None = None) -> None:
    """Steps of all rows of w (models) over dense or sparse examples one by one; changes w. late: what delayed() gave."""
    if not isinstance(x, SparseRows) and spec.reg == "none" and not isinstance(late, deque):
        if late is None and spec.f.scalar and w.size <= SCALAR_VALUES:
            run = single(spec.f, w.shape[1])
            for at in range(0, len(y), 4096):
                examples = np.column_stack([x[at : at + 4096], y[at : at + 4096]]).tolist()
                for m in range(len(w)):
                    w[m] = run(examples, w[m].tolist(), float(alpha[m]))
        else:
            descend_blocks(w, x, y, alpha, spec, late)
        return
    for i in range(len(y)):
        seen = w if late is None else late[0]
        shrink = None if spec.reg == "none" else alpha[:, None] * spec.reg_grad(seen)
        if isinstance(x, SparseRows):
            j, v = x.row(i)
            w[:, j] -= (spec.f.slope(seen[:, j] @ v, y[i]) * alpha)[:, None] * v
        else:
            w -= (spec.f.slope(seen @ x[i], y[i]) * alpha)[:, None] * x[i]
        if shrink is not None:
            w -= shrink
        if late is not None:
            late.append(w.copy())


def delayed(w: np.ndarray, late: int, x: np.ndarray | SparseRows, spec: Spec) -> Late | deque | None:
    """State by which updates of w see the models of late - 1 updates ago; 0: the newest. It goes with examples like x."""
    if not late:
        return None
    return deque([w.copy()] * late, maxlen=late) if spec.reg != "none" or isinstance(x, SparseRows) else Late(late - 1, *w.shape)


#: Numbers in a packed run of examples.
PACKED = 2048


def packed(ex: DataFrame, part: str | None, key: list[str], d: int) -> DataFrame:
    """(part, task, at, n, xy): dense examples in random order by part, sorted by all tasks; xy has the bytes of n examples with labels.

    The runs' order within a part is that of (task, at).
    """
    cols = ["x"] if "x" in ex.columns else wide(d)
    rows = ex.select((F.col(part).cast("long") if part else F.lit(0).cast("long")).alias("part"), "ord", *key, *cols, "y")
    rows = rows.repartitionByRange("part", "ord", *key).sortWithinPartitions("part", "ord", *key).select("part", *cols, "y")
    most = max(1, PACKED // (d + 1))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        task, at = TaskContext.get().partitionId(), 0
        for b in batches:
            out = []
            for p, x, y in by_part([b], d):
                xy = np.column_stack([x, y])
                for i in range(0, len(xy), most):
                    out.append((p, task, at, len(xy[i : i + most]), xy[i : i + most].tobytes()))
                    at += 1
            if out:
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out), (*[pa.int64()] * 4, pa.binary()))], names=["part", "task", "at", "n", "xy"])

    return rows.mapInArrow(run, "part long, task long, at long, n long, xy binary")


def unpacked(b: pa.RecordBatch, d: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(part, X, y) of packed runs."""
    xy = b.column("xy")
    ends = np.frombuffer(xy.buffers()[1], np.int32)[xy.offset : xy.offset + len(xy) + 1]
    xy = np.frombuffer(xy.buffers()[2], np.uint8)[ends[0] : ends[-1]].view(float).reshape(-1, d + 1)
    return np.repeat(b.column("part").to_numpy(), b.column("n").to_numpy()), xy[:, :d], xy[:, d]


def ordered(ex: DataFrame, part: str | None, key: list[str], d: int) -> DataFrame:
    """Each part whole in one partition and in random order: (part, idx, val, y), or packed runs of dense examples."""
    part_col = F.col(part).cast("long") if part else F.lit(0).cast("long")
    if "xy" in ex.columns:
        rows, order, cols = ex, ["part", "task", "at"], ["n", "xy"]
    elif "idx" in ex.columns:
        rows, order, cols = ex.select(part_col.alias("part"), "ord", *key, "idx", "val", "y"), ["part", "ord", *key], ["idx", "val", "y"]
    else:
        rows, order, cols = packed(ex, part, key, d), ["part", "task", "at"], ["n", "xy"]
    rows = rows.repartition("part") if part else rows.repartition(1)
    return rows.sortWithinPartitions(*order).select("part", *cols)


def by_part(batches: Iterator[pa.RecordBatch], d: int) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """Runs of one part: (part, X, y)."""
    for b in batches:
        if not b.num_rows:
            continue
        if "zip" in b.schema.names:
            for p, n, z in zip(b.column("part").to_pylist(), b.column("n").to_pylist(), b.column("zip")):
                yield (p, *unzipped(z.as_buffer(), n, d))
            continue
        if "xy" in b.schema.names:
            part, x, y = unpacked(b, d)
        else:
            part = b.column("part").to_numpy(zero_copy_only=False)
            x, y = (sparse_rows(b), b.column("y").to_numpy(zero_copy_only=False)) if "idx" in b.schema.names else batch_matrix(b, d)
        edges = np.flatnonzero(np.diff(part)) + 1
        for a, z in zip([0, *edges], [*edges, len(part)]):
            yield int(part[a]), x[a:z], y[a:z]


#: Of lists on disk: numbers in a run, examples of a bucket, and examples that a job of a pass reads.
RUN, BUCKET, JOB = 1 << 18, 1 << 17, 1 << 20
LISTS = "part long, at long, n long, zip binary, bucket int, grp int"


def zipped(xy: np.ndarray) -> bytes:
    """Examples with labels by column and byte place, compressed."""
    planes = np.ascontiguousarray(np.ascontiguousarray(xy.T).view(np.uint8).reshape(xy.shape[1], len(xy), 8).transpose(0, 2, 1))
    return pa.Codec("zstd", 1).compress(planes.reshape(-1), asbytes=True)


def unzipped(z: pa.Buffer, n: int, d: int) -> tuple[np.ndarray, np.ndarray]:
    """(X, y) of what zipped() made of n examples."""
    raw = pa.decompress(z, decompressed_size=n * (d + 1) * 8, codec="zstd")
    xy = np.ascontiguousarray(np.frombuffer(raw, np.uint8).reshape(d + 1, 8, n).transpose(0, 2, 1)).view(float).reshape(d + 1, n)
    return np.ascontiguousarray(xy[:d].T), xy[d].copy()


@dataclass
class Lists:
    """Dense examples on disk: a list for each part in random order, cut into buckets by ranges of ord.

    A pass is a chain of jobs that read a few buckets each, and no job moves or sorts more than it reads. Thus
    passes need no disk of their own, whatever the number of examples.
    """

    rows: DataFrame  #: LISTS; at: how many examples of the part and bucket come before the run
    counts: dict[int, list[int]]  #: examples of each part, by bucket
    groups: int
    path: str

    def by_part(self) -> Iterator[DataFrame]:
        """Jobs' rows (part, n, zip), each part's in order."""
        sizes, lo = [sum(b) for b in zip(*self.counts.values())], 0
        while lo < len(sizes):
            hi, n = lo + 1, sizes[lo]
            while hi < len(sizes) and n + sizes[hi] <= JOB:
                n, hi = n + sizes[hi], hi + 1
            if n:
                here = self.rows.where((F.col("bucket") >= lo) & (F.col("bucket") < hi))
                alone = (here.where(F.col("grp") == g).coalesce(1) for g in sorted({p % self.groups for p in self.counts}))
                yield reduce(DataFrame.unionAll, alone).sortWithinPartitions("part", "bucket", "at").select("part", "n", "zip")
            lo = hi

    def by_turn(self, nodes: int, threads: int) -> Iterator[tuple[DataFrame, int, int]]:
        """As in_turns() orders them, where part is ord % (nodes * threads): jobs' rows (part, thread, t, n, zip), part the node and t a run's first turn; and the turns that the job takes, from and before."""
        before = {p: [0, *accumulate(c)] for p, c in self.counts.items()}
        most, each = max((b[-1] for b in before.values()), default=0), max(1, JOB // (nodes * threads))
        for lo in range(0, most, each):
            hi, starts = min(most, lo + each), []
            for p, b in before.items():
                starts += [v for i, t in enumerate(b[:-1]) if t < hi and b[i + 1] > lo for v in (F.lit(f"{p},{i}"), F.lit(t))]
            place = F.concat_ws(",", "part", "bucket")
            here = self.rows.where(F.col("bucket").isin(sorted({i for b in before.values() for i, t in enumerate(b[:-1]) if t < hi and b[i + 1] > lo})))
            here = here.withColumn("t", F.element_at(F.create_map(*starts), place) + F.col("at")).where((F.col("t") < hi) & (F.col("t") + F.col("n") > lo))
            here = here.select((F.col("part") % nodes).alias("part"), F.floor(F.col("part") / nodes).alias("thread"), "t", "n", "zip")
            alone = (here.where(F.col("part") % min(nodes, 64) == g).coalesce(1) for g in range(min(nodes, 64)))
            yield reduce(DataFrame.unionAll, alone).sortWithinPartitions("part", "t", "thread"), lo, hi

    def drop(self) -> None:
        drop_table(self.rows.sparkSession, self.path)


def lists(ex: DataFrame, part: str, key: list[str], d: int, features: Callable[[DataFrame], DataFrame] | None = None) -> Lists:
    """Examples written once for all passes. features adds x to rows that have what it is made of, after they were moved."""
    spark, path = ex.sparkSession, shared_dir(ex.sparkSession, "lists")
    low, high, n = ex.agg(F.min("ord"), F.max("ord"), F.count(F.lit(1))).first()
    buckets = max(1, -(-n // BUCKET))
    cols = [c for c in ex.columns if c not in (part, "ord", "y", "blk", *key)] if features else ["x"] if "x" in ex.columns else wide(d)
    bucket = F.least(F.lit(buckets - 1), F.floor((F.col("ord") - (low or 0)) / ((high or 0) - (low or 0) + 1) * buckets)).cast("int")
    rows = ex.select(F.col(part).cast("long").alias("part"), bucket.alias("bucket"), "ord", *key, *cols, "y")
    rows = rows.repartitionById(buckets, "bucket").sortWithinPartitions("bucket", "part", "ord", *key)
    rows = features(rows) if features else rows
    most, groups = max(1, RUN // (d + 1)), max(1, spark.sparkContext.defaultParallelism)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, at, place = [], 0, None  # of one part in one bucket

        def out(xy: np.ndarray) -> Iterator[pa.RecordBatch]:
            nonlocal at
            for i in range(0, len(xy), most):
                v = xy[i : i + most]
                cols = ([place[1]], [at], [len(v)], [zipped(v)], [place[0]], [place[1] % groups])
                at += len(v)
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, (*[pa.int64()] * 3, pa.binary(), *[pa.int32()] * 2))], names=["part", "at", "n", "zip", "bucket", "grp"])

        for b in batches:
            if not b.num_rows:
                continue
            x, y = batch_matrix(b, d)
            xy, spot = np.column_stack([x, y]), np.column_stack([b.column("bucket").to_numpy(), b.column("part").to_numpy()])
            edges = np.flatnonzero(np.any(np.diff(spot, axis=0), axis=1)) + 1
            for a, z in zip([0, *edges], [*edges, len(y)]):
                now = (int(spot[a, 0]), int(spot[a, 1]))
                if now != place:
                    if held:
                        yield from out(np.concatenate(held))
                    held, at, place = [], 0, now
                held.append(xy[a:z])
                if sum(map(len, held)) >= most:
                    whole = np.concatenate(held)
                    full = len(whole) // most * most
                    yield from out(whole[:full])
                    held = [whole[full:]]
        if held:
            yield from out(np.concatenate(held))

    rows.select("bucket", "part", *(["x"] if "x" in rows.columns else wide(d)), "y").mapInArrow(run, LISTS).write.partitionBy("bucket", "grp").parquet(path)
    stored, counts = spark.read.schema(LISTS).parquet(path), {}
    for r in stored.groupBy("part", "bucket").agg(F.sum("n").alias("n")).collect():
        counts.setdefault(r["part"], [0] * buckets)[r["bucket"]] = r["n"]
    drop_shuffles(spark)
    return Lists(stored, counts, groups, path)


def in_order(batches: Iterator[pa.RecordBatch], d: int, lo: int, hi: int) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """As by_part, of rows of Lists.by_turn: the threads of a node take turns from lo on and before hi."""
    node, held = None, []

    def until(t: int) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
        nonlocal held
        taken, rest = [], []
        for first, thread, x, y in held:
            k = min(max(0, t - first), len(y))
            if k:
                taken.append((np.arange(first, first + k), np.full(k, thread), x[:k], y[:k]))
            if k < len(y):
                rest.append((first + k, thread, x[k:], y[k:]))
        held = rest
        if taken:
            turn, thread, x, y = (np.concatenate(v) for v in zip(*taken))
            order = np.lexsort((thread, turn))
            yield node, x[order], y[order]

    for b in batches:
        for p, thread, first, n, z in zip(*(b.column(c).to_pylist() for c in ("part", "thread", "t", "n")), b.column("zip")):
            if p != node:
                yield from until(hi)
                node = p
            first, skip = max(first, lo), max(0, lo - first)
            yield from until(first)
            x, y = unzipped(z.as_buffer(), n, d)
            x, y = x[skip:], y[skip:]
            held.append((first, thread, x[: hi - first], y[: hi - first]))
    yield from until(hi)


def _rows(states: dict[int, tuple[int, np.ndarray]]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(list(states), pa.int64()), pa.array([n for n, _ in states.values()], pa.int64()), pa.array([w.ravel() for _, w in states.values()], pa.list_(pa.float64()))], names=["part", "n", "w"])


def passes(ex: DataFrame, spec: Spec, w0, alpha, key: list[str], part: str | None = None) -> DataFrame:
    """STATE of each part after one pass. w0: (models, d) to start from; alpha: a step for each model."""
    w0 = np.atleast_2d(np.asarray(w0, dtype=float))
    d, alpha = w0.shape[1], np.broadcast_to(np.asarray(alpha, dtype=float), (len(w0),)).copy()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        states: dict[int, tuple[int, np.ndarray]] = {}
        for p, x, y in by_part(batches, d):
            n, w = states.get(p, (0, w0.copy()))
            sgd(x, y, w, alpha, spec)
            states[p] = (n + len(y), w)
        yield _rows(states)

    return ordered(ex, part, key, d).mapInArrow(run, STATE)


def train_igd(ex: DataFrame, spec: Spec, w0, step: Step, epochs: int, key: list[str], order: str = "reshuffle", hash_keys: list[str] | None = None) -> Run:
    """Serial descent. order: a new permutation each pass, one permutation for all, or the order of the key."""
    w, run = np.array(w0, dtype=float), Run(np.array(w0, dtype=float))
    for k in range(epochs):
        if order == "reshuffle":
            now = ex.withColumn("ord", digits(digest(hash_keys or key, k), 1))
        else:
            now = ex if order == "once" else ex.withColumn("ord", F.lit(0))
        w = np.array(passes(now, spec, w, step(k), key).first()["w"])
        m = multi_eval(ex, w, spec, meter=run.cost)
        run.trace.append({"k": k + 1, "alpha": step(k), "loss": float(objective(m, w, spec)[0]), "w": w.copy()})
    run.w = w
    return run


def train_igd_merge(ex: DataFrame, spec: Spec, w0, step: Step, epochs: int, key: list[str], part: str, weight: str = "count", evaluate: bool = True) -> Run:
    """A model for each part, averaged after every pass; all start again from the average."""
    w, run = np.array(w0, dtype=float), Run(np.array(w0, dtype=float))
    for k in range(epochs):
        w = average(passes(ex, spec, w, step(k), key, part), len(w), weight)
        row = {"k": k + 1, "alpha": step(k), "w": w.copy(), "loss": None}
        if evaluate:
            row["loss"] = float(objective(multi_eval(ex, w, spec, meter=run.cost), w, spec)[0])
        run.trace.append(row)
    run.w = w
    return run


def train_igd_oneshot(ex: DataFrame, spec: Spec, w0, step: Step, epochs: int, key: list[str], part: str, weight: str = "count") -> tuple[np.ndarray, DataFrame]:
    """Each part runs all its passes alone; one average at the end. A pass is a job, so that no part need fit in memory."""
    d, spark = len(w0), ex.sparkSession
    models: dict[int, np.ndarray] = {}
    for k in range(epochs):
        sent = spark.sparkContext.broadcast(models)

        def run(batches: Iterator[pa.RecordBatch], sent=sent, k=k) -> Iterator[pa.RecordBatch]:
            states: dict[int, tuple[int, np.ndarray]] = {}
            for p, x, y in by_part(batches, d):
                n, w = states.get(p, (0, np.atleast_2d(sent.value.get(p, w0)).astype(float).copy()))
                sgd(x, y, w, np.array([step(k)]), spec)
                states[p] = (n + len(y), w)
            yield _rows(states)

        rows = ordered(ex, part, key, d).mapInArrow(run, STATE).collect()
        models = {r["part"]: np.array(r["w"]) for r in rows}
    parts = spark.createDataFrame([(r["part"], r["n"], r["w"]) for r in rows], STATE)
    return average(parts, d, weight), parts


def partition_study(ex: DataFrame, spec: Spec, w0, step: Step, key: list[str], counts=(1, 2, 4, 8)) -> DataFrame:
    """How far the models of parts differ, and how good their average is, by the number of parts."""
    rows, d = [], len(w0)
    for m in counts:
        parts = passes(ex.withColumn("part", F.col("ord") % m), spec, w0, step(0), key, "part").collect()
        ws = np.array([r["w"] for r in sorted(parts)])
        n = np.array([r["n"] for r in sorted(parts)])
        w = (ws * n[:, None]).sum(axis=0) / n.sum()
        loss = float(objective(multi_eval(ex, w, spec), w, spec)[0])
        rows.append((m, float(ws.var(axis=0, ddof=1).sum()) if m > 1 else 0.0, loss))
    return ex.sparkSession.createDataFrame([(m, round(v, 6), round(x, 4)) for m, v, x in rows], "parts int, variance double, loss double")


def sgd_shared(x: np.ndarray, y: np.ndarray, w: np.ndarray, alpha: float, spec: Spec, late: deque | None) -> None:
    """One shared model. late: the models of the last updates, the oldest of which is what an update reads; None: it reads the newest."""
    slope = spec.f.slope
    for i in range(len(y)):
        seen = w if late is None else late[0]
        g = slope(seen @ x[i], y[i])
        w -= alpha * (g * x[i] + spec.reg_grad(seen))
        if late is not None:
            late.append(w.copy())


def in_turns(ex: DataFrame, key: list[str], nodes: int, threads: int) -> DataFrame:
    """Examples with their node, in the order in which its threads take turns."""
    from pyspark.sql import Window

    rows = ex.withColumn("node", F.col("ord") % nodes).withColumn("thread", F.floor(F.col("ord") / nodes) % threads)
    turn = F.row_number().over(Window.partitionBy("node", "thread").orderBy("ord", *key))
    return rows.withColumn("ord", turn * threads + F.col("thread"))


def train_igd_shared(ex: DataFrame, spec: Spec, w0, alpha: float, key: list[str], nodes: int = 1, threads: int = 4, mode: str = "lock") -> tuple[np.ndarray, DataFrame]:
    """One pass with a model for each node that its threads share; nodes are averaged by their counts.

    lock: updates are serial, each sees all before it. nolock: each sees the model of threads - 1 updates ago.
    The threads' examples, a residue of the random order each, are taken in turn.
    """
    d = len(w0)
    w0 = np.asarray(w0, dtype=float)
    rows = in_turns(ex, key, nodes, threads)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        states: dict[int, tuple[int, np.ndarray, deque | None]] = {}
        for p, x, y in by_part(batches, d):
            if p not in states:
                w = w0.copy()
                states[p] = (0, w, None if mode == "lock" else deque([w.copy()] * threads, maxlen=threads))
            n, w, late = states[p]
            sgd_shared(x, y, w, alpha, spec, late)
            states[p] = (n + len(y), w, late)
        yield _rows({p: (n, w) for p, (n, w, _) in states.items()})

    parts = ordered(rows, "node", key, d).mapInArrow(run, STATE)
    return average(parts, d, "count"), parts


def train_minibatch(ex: DataFrame, spec: Spec, w0, alpha: float, batch: int, epochs: int, key: list[str], evaluate: bool = True) -> Run:
    """Steps over groups of `batch` examples in random order, by the mean (or sum) of their gradients."""
    w, d, run = np.array(w0, dtype=float), len(w0), Run(np.array(w0, dtype=float))
    for k in range(epochs):
        start = w.copy()

        def once(batches: Iterator[pa.RecordBatch], start=start) -> Iterator[pa.RecordBatch]:
            w, n, g, inside = start.copy(), 0, np.zeros(d), 0
            for _, x, y in by_part(batches, d):
                at = 0
                while at < len(y):
                    take = min(batch - inside, len(y) - at)
                    xs, ys = x[at : at + take], y[at : at + take]
                    g += spec.f.slope(xs @ w, ys) @ xs
                    inside, at, n = inside + take, at + take, n + take
                    if inside == batch:
                        w = w - alpha * (g * spec.per(inside) + spec.reg_grad(w))
                        g, inside = np.zeros(d), 0
            if inside:
                w = w - alpha * (g * spec.per(inside) + spec.reg_grad(w))
            yield _rows({0: (n, w)})

        w = np.array(ordered(ex, None, key, d).mapInArrow(once, STATE).first()["w"])
        loss = float(objective(multi_eval(ex, w, spec, meter=run.cost), w, spec)[0]) if evaluate else None
        run.trace.append({"k": k + 1, "batch": batch, "alpha": alpha, "loss": loss, "w": w.copy()})
    run.w = w
    return run


def minibatch_steps(ex: DataFrame, spec: Spec, w0, alpha: float, batch: int, key: list[str]) -> DataFrame:
    """(step, n, w): the model after each step of one whole pass, and how many examples the step took."""
    d, w0 = len(w0), np.asarray(w0, dtype=float)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        w, step, g, inside = w0.copy(), 0, np.zeros(d), 0

        def row() -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array([step], pa.int64()), pa.array([inside], pa.int64()), pa.array([w], pa.list_(pa.float64()))], names=["step", "n", "w"])

        for _, x, y in by_part(batches, d):
            at = 0
            while at < len(y):
                take = min(batch - inside, len(y) - at)
                xs, ys = x[at : at + take], y[at : at + take]
                g += spec.f.slope(xs @ w, ys) @ xs
                inside, at = inside + take, at + take
                if inside == batch:
                    w, step = w - alpha * (g * spec.per(inside) + spec.reg_grad(w)), step + 1
                    yield row()
                    g, inside = np.zeros(d), 0
        if inside:
            w, step = w - alpha * (g * spec.per(inside) + spec.reg_grad(w)), step + 1
            yield row()

    return ordered(ex, None, key, d).mapInArrow(run, "step long, n long, w array<double>")


def train_hybrid(ex: DataFrame, spec: Spec, w0, igd_step: Step, bgd_step: Step, key: list[str], part: str, switch_tol: float = 0.01, max_igd: int = 5, max_bgd: int = 5) -> Run:
    """Incremental passes until they gain little, then batch descent."""
    w, run, before = np.array(w0, dtype=float), Run(np.array(w0, dtype=float)), None
    for k in range(max_igd):
        one = train_igd_merge(ex, spec, w, Step(igd_step.kind, igd_step(k), 0), 1, key, part)
        loss = one.trace[0]["loss"]
        if before is not None and loss > before * (1 - switch_tol):
            if loss < before:
                w = one.w
            break
        w, before = one.w, loss
        run.trace.append({"phase": "incremental", "k": len(run.trace) + 1, "loss": loss, "w": w.copy()})
    tail = train_bgd(ex, spec, w, bgd_step, StopRule(max_iter=max_bgd))
    for r in tail.trace[1:]:
        run.trace.append({"phase": "batch", "k": len(run.trace) + 1, "loss": r["loss"], "w": r["w"]})
    run.w = tail.w
    return run


def progressive_loss(ex: DataFrame, spec: Spec, w0, alpha: float, key: list[str], every: int = 1000) -> DataFrame:
    """(pos, mean loss so far): what an online learner reports, each example's loss taken before its own update."""
    d, w0 = len(w0), np.asarray(w0, dtype=float)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        w, n, total, out = w0.copy(), 0, 0.0, []
        for _, x, y in by_part(batches, d):
            for i in range(len(y)):
                dot = w @ x[i]
                total += float(spec.f.value(dot, y[i]))
                w -= alpha * (spec.f.slope(dot, y[i]) * x[i] + spec.reg_grad(w))
                n += 1
                if n % every == 0:
                    out.append((n, total / n))
        if n % every or not n:
            out.append((n, total / max(1, n)))
        yield pa.RecordBatch.from_arrays([pa.array([a for a, _ in out], pa.int64()), pa.array([b for _, b in out])], names=["pos", "mean_loss"])

    return ordered(ex, None, key, d).mapInArrow(run, "pos long, mean_loss double")
