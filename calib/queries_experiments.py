"""The experiment workloads, re-expressed on the given tables. Traces are by iteration; seconds belong in the benchmarks."""

from __future__ import annotations

from functools import partial

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from calib import oracle as O
from calib.functions.losses import Spec
from calib.operators import baselines, incremental, ola, speculative, stepdist
from calib.operators.approx_igd import train_approx_igd
from calib.operators.batch import StopRule, trace_frame, train_line_search
from calib.plans.moments import model_bytes, multi_eval
from calib.queries_methods import BLOCKS, EX, GRID, KEY, N_SQL, SVM, LR, W, _n, _scaled, _spec_sql, approx_run, line, rows
from calib.registry import query
from calib.session import drop_shuffles, materialize, together
from calib.sources import views

S_VALUES = (1, 2, 4, 8, 16, 32)
ITERATIONS = 20
_tables: dict = {}


def star_rows(spark, sf_dir) -> DataFrame:
    """V2 in random blocks, with what its features are made of."""
    key = (spark.sparkContext.applicationId, sf_dir)
    if key not in _tables:
        ex, tasks = views.star_rows(spark, sf_dir), max(spark.sparkContext.defaultParallelism, min(BLOCKS, items(spark, sf_dir) >> 19))
        _tables[key] = materialize(ex.repartition(tasks, "blk").sortWithinPartitions("blk", "ord"), "star")
        drop_shuffles(spark)
    return _tables[key]


def star(spark, sf_dir) -> DataFrame:
    """V2 with its 54 features as an array, in random blocks."""
    return views.star_array(star_rows(spark, sf_dir))


def star_lists(spark, sf_dir, parts: int) -> incremental.Lists:
    """V2 for incremental passes, a list for each remainder of ord."""
    return incremental.lists(star_rows(spark, sf_dir).withColumn("part", F.col("ord") % parts), "part", KEY, views.STAR_D, views.star_array)


def items(spark, sf_dir) -> int:
    """How many line items there are, as _n has it, without writing V1."""
    return views.table(spark, sf_dir, "lineitem").count()


def nested(n: int, s: int) -> speculative.Grid:
    return speculative.Grid(tuple(v / n for v in speculative.nested_grid(s, 2.0, 2.0).values))


@query("SELECT count(*) AS n, true AS balanced FROM lineitem")
def view_star(spark, sf_dir):
    ex = star(spark, sf_dir)
    return ex.agg(F.count(F.lit(1)).alias("n"), F.avg((F.col("y") > 0).cast("double")).between(0.2, 0.8).alias("balanced"))


@query("SELECT (SELECT count(*) FROM embeddings) AS embed, (SELECT count(*) FROM documents JOIN labels USING (doc_id)) AS doc, (SELECT count(*) FROM documents) AS bow, (SELECT count(*) FROM pages) AS page, (SELECT count(*) FROM conversations WHERE role IN ('user', 'assistant')) AS conv, (SELECT count(*) FROM events) AS event")
def view_counts(spark, sf_dir):
    found = {
        "embed": views.v_embed(spark, sf_dir), "doc": views.v_doc(spark, sf_dir), "bow": views.v_bow(spark, sf_dir),
        "page": views.v_page(spark, sf_dir), "conv": views.v_conv(spark, sf_dir), "event": views.v_event(spark, sf_dir),
    }
    return rows(spark, [tuple(df.count() for df in found.values())], ", ".join(f"{k} long" for k in found))


def spec_and_search(ex: DataFrame, n: int, d: int, name: str = "") -> list:
    """Batch descent for each number of steps and line search, each a run of its own with its own scans: functions that give their rows."""
    w0 = [0.0] * d

    def steps(s: int) -> list[tuple]:
        run = speculative.train_spec_bgd(ex, SVM, w0, nested(n, s), iterations=ITERATIONS, plan="arrow")
        return [(f"{name}s={s}", t["k"], round(t["loss"], 3), t["k"] + 1) for t in run.trace]

    def search() -> list[tuple]:
        run, passes, out = train_line_search(ex, SVM, w0, ITERATIONS, 64.0 / n, plan="arrow", speculative=True), 1, []
        for t in run.trace:
            passes += t["tries"]
            out.append((f"{name}line_search", t["k"], round(t["loss"], 3), passes))
        return out

    return [*(partial(steps, s) for s in S_VALUES), search]


@query()
def fig3a_spec_bgd_svm(spark, sf_dir):
    """More concurrent steps lower the loss of every iteration; line search gets there with more passes. V2, then V3.

    No run shares a scan with another. passes is what a method needs by then; only the trials of a search's iteration, which count one each, share a scan here.
    """
    runs = spec_and_search(star(spark, sf_dir), items(spark, sf_dir), views.STAR_D)
    embed = materialize(views.v_embed(spark, sf_dir), "embed")
    n, d = embed.agg(F.count(F.lit(1)), F.max(F.size("x"))).first()
    runs += spec_and_search(embed, n, d, "embed ") if n else []
    return rows(spark, sum(together(lambda f: f(), runs), []), "method string, k int, loss double, passes int")


@query()
def fig3b_spec_igd_lr(spark, sf_dir):
    """Incremental descent with averaging of four parts: one to eight steps, each number a run of its own with its own passes."""
    ex, stored, out = star(spark, sf_dir), star_lists(spark, sf_dir, 4), []
    sizes = (1, 2, 4, 8)
    runs = together(lambda s: speculative.train_spec_igd(ex, LR, [0.0] * views.STAR_D, speculative.nested_grid(s, 0.005, 4.0).values, ITERATIONS, KEY, "part", stored=stored), sizes)
    stored.drop()
    for s, run in zip(sizes, runs):
        out += [(f"s={s}", t["k"], round(t["loss"], 3), t["models"]) for t in run.trace]
    return rows(spark, out, "method string, k int, loss double, models int")


@query()
def fig3c_methods_svm(spark, sf_dir):
    """Batch against the three incremental variants, each with 16 steps, by iteration."""
    ex, n, d, out = star(spark, sf_dir), items(spark, sf_dir), views.STAR_D, []
    run = speculative.train_spec_bgd(ex, SVM, [0.0] * d, nested(n, 16), iterations=2, plan="arrow")
    out += [("batch", t["k"], round(t["loss"], 3)) for t in run.trace]
    variants = ("merge", "lock", "nolock")
    stored = star_lists(spark, sf_dir, 4)  # merge has four parts, and lock and nolock have four threads of one node
    runs = together(lambda v: speculative.train_spec_igd(ex, SVM, [0.0] * d, speculative.nested_grid(16, 0.005, 2.0).values, 2, KEY, "part", variant=v, stored=stored), variants)
    stored.drop()
    for variant, run in zip(variants, runs):
        out += [(variant, t["k"] - 1, round(t["loss"], 3)) for t in run.trace[1:]]  # the first loss is that of the start
    return rows(spark, out, "method string, k int, loss double")


_COST = " UNION ALL ".join(
    f"SELECT '{view}' AS view, '{m}' AS method, {s} AS s, {d} AS d, {s if m == 'batch' else s * s} AS models, ({s * (d + 1)})::BIGINT AS aggregates, ({8 * d * (s if m == 'batch' else s * s)})::BIGINT AS bytes"
    for view, d in (("line", 5), ("star", 54), ("bow", 4096)) for m in ("batch", "incremental") for s in (S_VALUES if view != "bow" else (1, 2))
)


@query(_COST)
def table2_cost(spark, sf_dir):
    """What an iteration costs apart from time: models, SUMs and bytes of models."""
    out = []
    for view, d in (("line", 5), ("star", 54), ("bow", 4096)):
        for m in ("batch", "incremental"):
            for s in S_VALUES if view != "bow" else (1, 2):
                out.append((view, m, s, d, s if m == "batch" else s * s, s * (d + 1), model_bytes(s, d, m)))
    return rows(spark, out, "view string, method string, s int, d int, models int, aggregates long, bytes long")


@query(f"SELECT s, 4::BIGINT AS passes, 4 * {N_SQL} AS rows_read FROM (VALUES " + ", ".join(f"({s})" for s in S_VALUES) + ") t(s)")
def table2_passes(spark, sf_dir):
    """Passes and rows that speculative descent reads in three iterations do not grow with s."""
    ex, n, out = line(spark, sf_dir), _n(spark, sf_dir), []
    for s in S_VALUES:
        run = speculative.train_spec_bgd(ex, SVM, [0.0] * 5, nested(n, s), iterations=3, plan="arrow")
        out.append((s, run.cost.total("passes"), run.cost.total("rows_read")))
    return rows(spark, out, "s int, passes long, rows_read long")


@query()
def fig4a_approx_bgd(spark, sf_dir):
    """Exact against early-ending scans: loss by rows read."""
    n, out = _n(spark, sf_dir), []
    exact = speculative.train_spec_bgd(line(spark, sf_dir), SVM, [0.0] * 5, speculative.Grid(tuple(a / n for a in GRID)), iterations=4)
    out += [("exact", t["k"], (t["k"] + 1) * n, round(t["loss"], 2)) for t in exact.trace]
    run, read = approx_run(spark, sf_dir), 0
    for t in run.trace:
        read += t["n_read"]
        out.append(("approximate", t["k"], read, round(float(multi_eval(line(spark, sf_dir), t["w"], SVM).loss[0]), 2)))
    return rows(spark, out, "method string, k int, rows_read long, loss double")


@query()
def fig4b_approx_igd(spark, sf_dir):
    ex, out = line(spark, sf_dir).withColumn("part", F.col("ord") % 4), []
    alphas = speculative.nested_grid(4, 0.005, 4.0).values
    for name, run in (("exact", speculative.train_spec_igd(ex, LR, [0.0] * 5, alphas, 2, KEY, "part")), ("approximate", train_approx_igd(ex, LR, [0.0] * 5, alphas, _n(spark, sf_dir), BLOCKS, KEY, "part"))):
        out += [(name, t["k"], round(t["loss"], 2), round(t.get("ratio", 1.0), 6)) for t in run.trace]
    return rows(spark, out, "method string, k int, loss double, ratio double")


@query()
def fig4c_sparse(spark, sf_dir):
    """Sparse, high-dimensional documents: batch and incremental descent over all of them, exact and by online aggregation.

    ratio is the share of documents that an iteration read. Losses of approximate batch descent are those of its
    models over all documents; those of incremental descent are of the parents, of which the first is the start.
    """
    bits = 12
    bow = materialize(views.v_bow(spark, sf_dir, bits).withColumnRenamed("doc_id", "ex_id"), "bow")
    n, d, out = bow.count(), 1 << bits, []
    grid, alphas = speculative.Grid((2.0 / n, 20.0 / n)), speculative.nested_grid(2, 0.1, 4.0).values
    run = speculative.train_spec_bgd(bow, SVM, np.zeros(d), grid, iterations=2, plan="sparse")
    out += [("batch", t["k"], round(t["loss"], 4), 1.0) for t in run.trace]
    run = ola.train_approx_bgd(bow, SVM, np.zeros(d), n, BLOCKS, grid, iterations=2, plan="sparse")
    out += [("batch_online", t["k"], round(float(multi_eval(bow, t["w"], SVM, "sparse").loss[0]), 4), round(t["ratio"], 6)) for t in run.trace]
    parted = bow.withColumn("part", F.col("ord") % 4)
    for name, run in (("incremental", speculative.train_spec_igd(parted, SVM, np.zeros(d), alphas, 2, ["ex_id"], "part")), ("incremental_online", train_approx_igd(parted, SVM, np.zeros(d), alphas, n, BLOCKS, ["ex_id"], "part"))):
        out += [(name, t["k"], round(t["loss"], 4), round(t.get("ratio", 1.0), 6)) for t in run.trace]
    return rows(spark, out, "method string, k int, loss double, ratio double")


@query()
def subsample_vs_ola(spark, sf_dir):
    """Static samples, too small or too large, against online aggregation: final loss and rows read."""
    ex, n, out = line(spark, sf_dir), _n(spark, sf_dir), []
    for q in (0.01, 0.05, 0.2, 1.0):
        run = ola.train_subsample(ex, SVM, [0.0] * 5, q, 1.0 / n, 4)
        out.append((f"sample {q}", run.cost.total("rows_read"), round(float(multi_eval(ex, run.w, SVM).loss[0]), 3)))
    run = approx_run(spark, sf_dir)
    out.append(("online", run.cost.total("rows_read"), round(float(multi_eval(ex, run.w, SVM).loss[0]), 3)))
    return rows(spark, out, "method string, rows_read long, loss double")


def _batch_sizes_sql(alpha: float = 0.5, sizes=(100, 500, 1000, 5000), epochs: int = 2) -> str:
    """A recursion over the steps of all passes; s counts a size's steps, of which `steps` make a pass."""
    key = "ord, l_orderkey, l_linenumber, l_partkey, l_suppkey"
    ex = f"SELECT *, row_number() OVER (ORDER BY {key}) - 1 AS rk FROM {O.line()}"
    start = "SELECT b, 0::BIGINT AS s, steps, " + ", ".join(f"0.0::DOUBLE AS w{j}" for j in range(5)) + f" FROM (VALUES {', '.join(f'({b})' for b in sizes)}) z(b), (SELECT count(*) AS n FROM ex), LATERAL (SELECT (n + b - 1) // b AS steps)"
    moved = ", ".join(f"any_value(w{j}) - {O.num(alpha)} * sum({O.slope('lr', O.dot())} * x{j}) / count(*)" for j in range(5))
    step = f"SELECT b, s + 1, steps, {moved} FROM t JOIN ex ON rk // b = s % steps WHERE s < {epochs} * steps GROUP BY b, s, steps"
    return f"WITH RECURSIVE ex AS MATERIALIZED ({ex}), t AS ({start} UNION ALL {step}) SELECT b AS batch, (s // steps)::INT AS k, round(avg({O.loss('lr', O.dot())}), 6) + 0.0 AS loss FROM t, ex WHERE s > 0 AND s % steps = 0 GROUP BY b, s, steps"


@query(_batch_sizes_sql)
def fig6a_minibatch(spark, sf_dir):
    """A fixed step and several batch sizes."""
    ex, out = line(spark, sf_dir), []
    for b in (100, 500, 1000, 5000):
        run = incremental.train_minibatch(ex, Spec("lr", scale="mean"), [0.0] * 5, 0.5, b, 2, KEY)
        out += [(b, t["k"], round(t["loss"], 6)) for t in run.trace]
    return rows(spark, out, "batch int, k int, loss double")


@query()
def fig6b_two_param(spark, sf_dir):
    """Steps and batch sizes from the two-dimensional distribution, by the number of configurations."""
    ex, out = line(spark, sf_dir).withColumn("part", F.col("ord") % 2), []
    for s in (2, 8):
        run = speculative.train_spec_minibatch(ex, Spec("lr", scale="mean"), [0.0] * 5, stepdist.BivariatePhi(), s, 2, KEY, "part", seed=3)
        out += [(s, t["k"], round(t["alpha"], 6), t["batch"], round(t["loss"], 6)) for t in run.trace]
    return rows(spark, out, "s int, k int, alpha double, batch int, loss double")


def _manual_sql(alphas=(0.3, 1.0, 4.0), iterations: int = 3) -> str:
    parts = []
    for a in alphas:
        parts.append(f"SELECT {O.num(a)} AS alpha, loss, {iterations + 1} AS passes FROM ({_scaled(O.bgd('svm', [a] * iterations))}) WHERE k = {iterations}")
    return " UNION ALL ".join(parts)


@query(_manual_sql)
def manual_tuning(spark, sf_dir):
    n = _n(spark, sf_dir)
    t = baselines.manual_tuning(line(spark, sf_dir), SVM, [0.0] * 5, [a / n for a in (0.3, 1.0, 4.0)], 3)
    return t.select(F.round(F.col("alpha") * n, 6).alias("alpha"), "loss", "passes")


@query()
def table3_systems(spark, sf_dir):
    """One speculative run against Spark's own library and an online learner: passes of the data and final objective."""
    ex, n, out = line(spark, sf_dir), _n(spark, sf_dir), []
    at = lambda w, spec: float(multi_eval(ex, w, spec).loss[0])
    systems = {
        "ours": lambda kind, spec: speculative.train_spec_bgd(ex, spec, [0.0] * 5, nested(n, 8), iterations=5, plan="arrow").trace[-1]["loss"],
        "library": lambda kind, spec: at(baselines.library_model(ex, kind, 5, 20)[0], spec),
        "library_minibatch": lambda kind, spec: at(baselines.library_minibatch(ex, spec, [0.0] * 5, 1.0, 0.1, 10), spec),
        "online": lambda kind, spec: at(np.array(incremental.passes(ex, spec, [0.0] * 5, 0.001, KEY).first()["w"]), spec),
    }
    tasks = [(kind, spec, name) for kind, spec in (("svm", SVM), ("lr", LR)) for name in systems]
    losses = together(lambda t: systems[t[2]](t[0], t[1]), tasks)
    out += [(kind, name, round(loss, 2)) for (kind, _, name), loss in zip(tasks, losses)]
    return rows(spark, out, "task string, system string, loss double")


@query(f"{EX} SELECT 'ours' AS system, 1::BIGINT AS passes, count(*) AS rows_read, round(sum({O.loss('svm', O.dot_values(W))}), 4) AS loss FROM ex")
def update_plus_loss(spark, sf_dir):
    """One complete update and one complete loss: a single fused pass."""
    ex = line(spark, sf_dir)
    meter = baselines.update_plus_loss(ex, SVM, np.array(W))
    m = multi_eval(ex, np.array(W), SVM)
    return rows(spark, [("ours", meter.total("passes"), meter.total("rows_read"), round(float(m.loss[0]), 4))], "system string, passes long, rows_read long, loss double")


@query()
def spec_bgd_phi(spark, sf_dir):
    """Steps from a normal distribution that is refitted after every iteration; s adapts to a simulated clock."""
    n = _n(spark, sf_dir)
    ticks = iter(range(10_000))
    run = speculative.train_spec_bgd(line(spark, sf_dir), SVM, [0.0] * 5, None, stepdist.NormalPhi(np.log(1.0 / n), 1.0, log=True), iterations=5, control=stepdist.StepCountController(most=8), clock=lambda: float(next(ticks)))
    return rows(spark, [(t["k"], t["s"], round(t["alpha"] * n, 6), round(t["loss"], 4), round(t["phi"].mu, 6), round(t["phi"].sigma, 6)) for t in run.trace], "k int, s int, alpha double, loss double, mu double, sigma double")


@query()
def spec_igd_phi(spark, sf_dir):
    """Incremental descent whose steps come from a refitted distribution, with s by a simulated clock, until losses settle."""
    ex = line(spark, sf_dir).withColumn("part", F.col("ord") % 4)
    ticks = iter(range(10_000))
    run = speculative.train_spec_igd(ex, LR, [0.0] * 5, None, 5, KEY, "part", phi=stepdist.NormalPhi(np.log(0.005), 1.0, log=True), control=stepdist.StepCountController(most=4), clock=lambda: float(next(ticks)), stop=StopRule(rel_tol=1e-2))
    return rows(spark, [(t["k"], t["s"], t["parents"], t["models"], round(t["loss"], 4), round(t["phi"].mu, 6), round(t["phi"].sigma, 6)) for t in run.trace], "k int, s int, parents int, models int, loss double, mu double, sigma double")


@query(lambda: _spec_sql("trace", "lr", 3))
def spec_bgd_lr_trace(spark, sf_dir):
    n = _n(spark, sf_dir)
    run = speculative.train_spec_bgd(line(spark, sf_dir), LR, [0.0] * 5, speculative.Grid(tuple(a / n for a in GRID)), iterations=3)
    for t in run.trace:
        t["alpha"] = round(t["alpha"] * n, 6)
    return trace_frame(spark, run, {"k": "int", "s": "int", "best": "int", "alpha": "double", "loss": "double", "w": "w"}, {"alpha": 6})


@query()
def estimator_bias(spark, sf_dir):
    """Samples by hash of the key are unbiased; a sample that one feature decides is not: estimates against the truth."""
    from calib.functions.losses import dot_wide
    from calib.operators.estimators import bernoulli, feature_sample

    ex, q = line(spark, sf_dir), 0.1
    f = F.sum(SVM.f.column(dot_wide(views.wide(5), W), F.col("y")))
    truth = ex.agg(f.alias("f")).first()["f"]
    out = [(k, round((df.agg(f.alias("f")).first()["f"] or 0.0) / q / truth, 4)) for k, df in (("key", bernoulli(ex, q)), ("feature", feature_sample(ex, "x0", q)))]
    return rows(spark, out, "sample string, ratio double")


