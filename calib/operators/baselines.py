"""What the methods are compared with, and the measures of the comparison."""

from __future__ import annotations

import time
from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from calib.functions.losses import Spec
from calib.operators.batch import StopRule, Step, train_bgd
from calib.plans.moments import CostMeter, multi_eval, objective


def manual_tuning(ex: DataFrame, spec: Spec, w0, alphas, iterations: int) -> DataFrame:
    """A run of its own for each step, with the loss only at the end: (alpha, loss, passes)."""
    rows = []
    for a in alphas:
        run = train_bgd(ex, spec, w0, Step("const", a), StopRule(max_iter=iterations))
        rows.append((float(a), round(float(run.trace[-1]["loss"]), 4), iterations + 1))
    return ex.sparkSession.createDataFrame(rows, "alpha double, loss double, passes int")


def library_model(ex: DataFrame, kind: str, d: int, iterations: int = 20, mu: float = 0.0) -> tuple[np.ndarray, float]:
    """Spark's own linear models on the same examples (bias as a feature): weights and seconds."""
    from pyspark.ml.classification import LinearSVC, LogisticRegression
    from pyspark.ml.functions import array_to_vector

    x = F.col("x") if "x" in ex.columns else F.array(*(f"x{j}" for j in range(d)))
    data = ex.select(array_to_vector(x).alias("features"), ((F.col("y") + 1) / 2).alias("label"))
    began = time.perf_counter()
    est = LinearSVC(maxIter=iterations, regParam=mu, fitIntercept=False, standardization=False) if kind == "svm" else LogisticRegression(maxIter=iterations, regParam=mu, fitIntercept=False, standardization=False)
    return est.fit(data).coefficients.toArray(), time.perf_counter() - began


def library_minibatch(ex: DataFrame, spec: Spec, w0, step: float, fraction: float, iterations: int, seed: int = 0) -> np.ndarray:
    """Its older mini-batch descent: a new sample for every step, and a step that falls with the root of k."""
    w = np.array(w0, dtype=float)
    for k in range(iterations):
        m = multi_eval(ex.sample(fraction=fraction, seed=seed + k), w, spec)
        w = w - step / (k + 1) ** 0.5 * m.grad[0] / max(1, m.n)
    return w


def time_per_iteration(run: Callable[[], object], repeats: int = 3) -> float:
    """Mean seconds over `repeats` runs after a first one that does not count."""
    run()
    began = time.perf_counter()
    for _ in range(repeats):
        run()
    return (time.perf_counter() - began) / repeats


def overhead(times: DataFrame) -> DataFrame:
    """time(s) against time of the least s, by method: columns method, s, secs."""
    w = Window.partitionBy("method").orderBy("s")
    return times.withColumn("ratio", F.round(F.col("secs") / F.first("secs").over(w), 4))


def sample_ratio(trace: DataFrame, total: int) -> DataFrame:
    return trace.withColumn("ratio", F.round(F.col("n_read") / total, 6))


def speedup_to_loss(slow: DataFrame, fast: DataFrame) -> DataFrame:
    """How much sooner `fast` has a loss as good as slow's, for every row of slow: traces of (secs, loss)."""
    a = slow.select(F.col("secs").alias("slow_secs"), "loss")
    b = fast.select(F.col("secs").alias("fast_secs"), F.col("loss").alias("fast_loss"))
    hit = a.join(b, F.col("fast_loss") <= F.col("loss")).groupBy("slow_secs", "loss").agg(F.min("fast_secs").alias("fast_secs"))
    return hit.withColumn("speedup", F.round(F.col("slow_secs") / F.col("fast_secs"), 4))


def time_to_converge(trace: DataFrame, tau: float) -> DataFrame:
    """The first iteration whose loss is within tau of the least: traces of (run, k, loss)."""
    least = F.min("loss").over(Window.partitionBy("run"))
    return trace.withColumn("least", least).where(F.col("loss") <= F.col("least") * (1 + tau)).groupBy("run").agg(F.min("k").alias("k"))


def coverage(estimates: DataFrame, truth: float) -> DataFrame:
    """How often the bounds hold the truth, and how wide they are."""
    inside = ((F.col("low") <= truth) & (truth <= F.col("high"))).cast("double")
    return estimates.agg(F.avg(inside).alias("coverage"), F.avg("rel_err").alias("rel_err"))


def prune_hit_rate(pruned: DataFrame, exact: DataFrame) -> DataFrame:
    """How often the truly best configuration was kept: (k, survivors) against (k, best)."""
    return pruned.join(exact, "k").agg(F.avg(F.array_contains("survivors", F.col("best")).cast("double")).alias("hit_rate"))


def evaluate(ex: DataFrame, w, spec: Spec) -> DataFrame:
    """One row: confusion counts, accuracy and the area under the curve by ranks of the margins (ties share theirs)."""
    scored = score(ex, w, spec)
    groups = scored.groupBy("dot").agg(F.sum((F.col("y") > 0).cast("long")).alias("p"), F.sum((F.col("y") <= 0).cast("long")).alias("n"))
    # negatives below a score are a running sum over distinct scores, cut into ranges so that no task holds them all
    parts = 64
    cut = groups.stat.approxQuantile("dot", [i / parts for i in range(1, parts)], 0.01)
    bucket = sum(((F.col("dot") > c).cast("int") for c in sorted(set(cut))), F.lit(0))
    groups = groups.withColumn("bucket", bucket)
    below = groups.groupBy("bucket").agg(F.sum("n").alias("bn"))
    before = below.withColumn("base", F.coalesce(F.sum("bn").over(Window.orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))).select("bucket", "base")
    inside = F.coalesce(F.sum("n").over(Window.partitionBy("bucket").orderBy("dot").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    ranked = groups.withColumn("inside", inside).join(F.broadcast(before), "bucket")
    wins = F.sum(F.col("p") * (F.col("base") + F.col("inside") + F.col("n") / 2)).alias("wins")
    auc = ranked.agg(wins, F.sum("p").alias("p"), F.sum("n").alias("n")).select(F.when(F.col("p") * F.col("n") > 0, F.col("wins") / F.col("p") / F.col("n")).alias("auc"))
    hit = lambda a, b: F.sum(((F.col("pred") > 0) == a).cast("long") * ((F.col("y") > 0) == b).cast("long"))
    counts = scored.agg(hit(True, True).alias("tp"), hit(True, False).alias("fp"), hit(False, True).alias("fn"), hit(False, False).alias("tn"))
    return counts.crossJoin(auc).withColumn("accuracy", (F.col("tp") + F.col("tn")) / (F.col("tp") + F.col("tn") + F.col("fp") + F.col("fn")))


def score(ex: DataFrame, w, spec: Spec) -> DataFrame:
    """Examples with dot, margin, loss and predicted sign."""
    from calib.functions.losses import dot_array, dot_wide
    from calib.sources.views import wide

    dot = dot_array("x", list(w)) if "x" in ex.columns else dot_wide(wide(len(w)), w)
    rows = ex.withColumn("dot", dot)
    return rows.withColumns({"margin": F.col("y") * F.col("dot"), "loss": spec.f.column(F.col("dot"), F.col("y")), "pred": F.when(F.col("dot") > 0, 1.0).otherwise(-1.0)})


def update_plus_loss(ex: DataFrame, spec: Spec, w, plan: str = "auto") -> CostMeter:
    """One complete update and one complete loss, fused in one pass; the meter tells the cost."""
    meter = CostMeter()
    m = multi_eval(ex, w, spec, plan, meter=meter)
    objective(m, w, spec)
    return meter
