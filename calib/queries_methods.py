"""Queries for losses, gradients, batch and incremental methods, speculation, distributions, sampling and halting."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from calib import oracle as O
from calib.functions.losses import Spec, dot_wide
from calib.operators import baselines, estimators, halting, incremental, ola, speculative, stepdist
from calib.operators.approx_igd import train_approx_igd
from calib.operators.batch import Step, StopRule, average, partial_gradient, trace_frame, train_bgd, train_bgd_oneshot, train_cd, train_lbfgs, train_line_search
from calib.plans.moments import multi_eval, wide_columns
from calib.registry import query
from calib.session import materialize, together
from calib.sources import views
from calib.sources.order import BLOCKS, block_sequence
from calib.sources.views import LINE_KEY, wide

W = [0.5, 0.2, -0.3, 0.1, 0.05]
X5 = wide(5)
SVM, LR, SQUARED = Spec("svm"), Spec("lr"), Spec("squared")
#: Steps for sums over any number of line items: they are divided by it.
GRID = (0.05, 0.3, 1.0, 4.0)
_tables: dict = {}


def line(spark: SparkSession, sf_dir: str, label: str = "planted") -> DataFrame:
    """The line-item view, put in random blocks once for a session: each pass then reads features and label alone."""
    key = (spark.sparkContext.applicationId, sf_dir, label)
    if key not in _tables:
        df = views.v_line(spark, sf_dir) if label == "planted" else views.v_noise(spark, sf_dir)
        _tables[key] = materialize(df.repartition(spark.sparkContext.defaultParallelism, "blk").sortWithinPartitions("blk", "ord"), "examples")
    return _tables[key]


def r(c, digits: int = 4):
    return F.round(c, digits) + F.lit(0.0)


def rows(spark: SparkSession, data: list[tuple], schema: str) -> DataFrame:
    return spark.createDataFrame(data, schema)


EX = f"WITH ex AS {O.line()}"
_Z = O.dot_values(W)


# losses and gradients


@query(f"{EX} SELECT count(*) AS n, round(sum({O.loss('svm', _Z)}), 4) AS loss FROM ex")
def loss_query(spark, sf_dir):
    ex = line(spark, sf_dir)
    return ex.agg(F.count(F.lit(1)).alias("n"), r(F.sum(SVM.f.column(dot_wide(X5, W), F.col("y")))).alias("loss"))


def _grads(kind: str) -> str:
    return ", ".join(f"round(sum({O.slope(kind, _Z)} * x{j}), 4) + 0.0 AS g{j}" for j in range(5))


@query(f"{EX} SELECT {_grads('svm')} FROM ex")
def gradient_query(spark, sf_dir):
    return line(spark, sf_dir).agg(*(r(F.sum(SVM.f.column_slope(dot_wide(X5, W), F.col("y")) * F.col(x))).alias(f"g{j}") for j, x in enumerate(X5)))


def _fused(spark, sf_dir, spec: Spec) -> DataFrame:
    """One pass in which margin and slope are bound once for loss and gradient."""
    bind, _ = wide_columns(np.array([W]), spec)
    b = line(spark, sf_dir).select(*X5, *bind)
    return b.agg(F.count(F.lit(1)).alias("n"), r(F.sum("_f0")).alias("loss"), *(r(F.sum(F.col("_g0") * F.col(x))).alias(f"g{j}") for j, x in enumerate(X5)))


@query(f"{EX} SELECT count(*) AS n, round(sum({O.loss('svm', _Z)}), 4) AS loss, {_grads('svm')} FROM ex")
def fused_loss_gradient(spark, sf_dir):
    return _fused(spark, sf_dir, SVM)


@query(f"{EX} SELECT count(*) AS n, round(sum({O.loss('lr', _Z)}), 4) AS loss, {_grads('lr')} FROM ex")
def lr_loss_gradient(spark, sf_dir):
    return _fused(spark, sf_dir, LR)


@query(f"{EX} SELECT count(*) AS n, round(sum({O.loss('squared', _Z)}), 4) AS loss, {_grads('squared')} FROM ex")
def squared_loss_gradient(spark, sf_dir):
    return _fused(spark, sf_dir, SQUARED)


def _reg_sql() -> str:
    l1, l2 = sum(map(abs, W)), sum(w * w for w in W) / 2
    out = [f"SELECT '{k}' AS reg, {O.num(mu)} AS mu, round(f + {O.num(mu)} * {O.num(v)}, 4) AS objective FROM s" for k, v in (("l1", l1), ("l2", l2)) for mu in (0.1, 10.0, 1000.0)]
    return f"{EX}, s AS (SELECT sum({O.loss('svm', _Z)}) AS f FROM ex) " + " UNION ALL ".join(out)


@query(_reg_sql)
def regularized_objective(spark, sf_dir):
    loss = float(multi_eval(line(spark, sf_dir), np.array(W), SVM).loss[0])
    return rows(spark, [(k, mu, round(loss + float(Spec("svm", k, mu).reg_value(np.array(W))[0]), 4)) for k in ("l1", "l2") for mu in (0.1, 10.0, 1000.0)], "reg string, mu double, objective double")


@query(f"{EX} SELECT l_orderkey, l_linenumber, l_partkey, l_suppkey, round(y * ({_Z}), 6) + 0.0 AS margin, round({O.loss('svm', _Z)}, 6) + 0.0 AS loss, CASE WHEN {_Z} > 0 THEN 1.0 ELSE -1.0 END::DOUBLE AS pred FROM ex")
def score_margins(spark, sf_dir):
    s = baselines.score(line(spark, sf_dir), W, SVM)
    return s.select(*LINE_KEY, r(F.col("margin"), 6).alias("margin"), r(F.col("loss"), 6).alias("loss"), "pred")


@query(
    f"""{EX}, s AS (SELECT {_Z} AS z, y FROM ex), u AS (SELECT z, count(*) FILTER (y > 0) AS p, count(*) FILTER (y <= 0) AS n FROM s GROUP BY z),
    b AS (SELECT p, n, coalesce(sum(n) OVER (ORDER BY z ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS below FROM u)
    SELECT count(*) FILTER (z > 0 AND y > 0) AS tp, count(*) FILTER (z > 0 AND y <= 0) AS fp, count(*) FILTER (z <= 0 AND y > 0) AS fn, count(*) FILTER (z <= 0 AND y <= 0) AS tn,
    round((SELECT sum(p * (below + n / 2.0::DOUBLE)) / sum(p) / sum(n) FROM b), 6) AS auc, round(count(*) FILTER ((z > 0) = (y > 0)) * 1.0::DOUBLE / count(*), 6) AS accuracy FROM s"""
)
def evaluate_model(spark, sf_dir):
    e = baselines.evaluate(line(spark, sf_dir), W, SVM)
    return e.select("tp", "fp", "fn", "tn", F.round("auc", 6).alias("auc"), F.round("accuracy", 6).alias("accuracy"))


# batch methods. Steps are for sums: they are divided by the number of examples, which SQL reads in a scalar subquery.

N_SQL = "(SELECT count(*) FROM lineitem)"


def _n(spark, sf_dir) -> int:
    return line(spark, sf_dir).count()


def _scaled(sql: str) -> str:
    """Steps written as multiples of 1/N become so in SQL."""
    return sql.replace("::DOUBLE) * g", f"::DOUBLE) / {N_SQL} * g")


TRACE = {"k": "int", "loss": "double", "w": "w"}


@query(lambda: _scaled(O.bgd("svm", [1.0] * 8)))
def bgd_svm_trace(spark, sf_dir):
    run = train_bgd(line(spark, sf_dir), SVM, [0.0] * 5, Step("const", 1.0 / _n(spark, sf_dir)), StopRule(max_iter=8))
    return trace_frame(spark, run, TRACE)


@query(lambda: _scaled(O.bgd("lr", [2.0] * 8)))
def bgd_lr_trace(spark, sf_dir):
    run = train_bgd(line(spark, sf_dir), LR, [0.0] * 5, Step("const", 2.0 / _n(spark, sf_dir)), StopRule(max_iter=8))
    return trace_frame(spark, run, TRACE)


DECAYS = [("inverse", 2.0, 1.0), ("exp", 2.0, 0.5), ("sqrt", 2.0, 0.0)]


def _decay_sql() -> str:
    parts = []
    for kind, a, g in DECAYS:
        sql = _scaled(O.bgd("svm", [Step(kind, a, g)(k) for k in range(4)], extra=f"'{kind}' AS rule, "))
        parts.append(f"SELECT * FROM ({sql})")
    return " UNION ALL ".join(parts)


@query(_decay_sql)
def bgd_decay_trace(spark, sf_dir):
    ex, n, out = line(spark, sf_dir), _n(spark, sf_dir), None
    for kind, a, g in DECAYS:
        run = train_bgd(ex, SVM, [0.0] * 5, lambda k, kind=kind, a=a, g=g: Step(kind, a, g)(k) / n, StopRule(max_iter=4))
        t = trace_frame(spark, run, TRACE).select(F.lit(kind).alias("rule"), "*")
        out = t if out is None else out.unionByName(t)
    return out


LS = dict(a0=32.0, rho=0.5, c1=1e-4)


def _line_search_sql(iterations: int = 4, tries: int = 10) -> str:
    """All trial steps up to a cap are evaluated; the first that qualifies is taken, else the last."""
    ctes = [f"ex AS {O.line()}", f"v0 AS {O.zeros()}", f"b0 AS (SELECT v0.*, m.f, {', '.join(f'm.g{j}' for j in range(5))} FROM v0, ({O.sums('svm', 'ex, v0')}) m)"]
    out = []
    for k in range(1, iterations + 1):
        values = ", ".join(f"({t + 1}, {O.num(LS['a0'] * LS['rho'] ** t)} / {N_SQL})" for t in range(tries))
        norm = " + ".join(f"b{k - 1}.g{j} * b{k - 1}.g{j}" for j in range(5))
        ctes.append(f"c{k} AS (SELECT t.t AS t, t.alpha AS alpha, b{k - 1}.f - {O.num(LS['c1'])} * t.alpha * ({norm}) AS bound, " + ", ".join(f"w{j} - t.alpha * g{j} AS w{j}" for j in range(5)) + f" FROM b{k - 1}, (VALUES {values}) t(t, alpha))")
        ctes.append(f"m{k} AS ({O.sums('svm', f'ex, c{k}', 't')})")
        ctes.append(f"b{k} AS (SELECT c{k}.*, m{k}.* EXCLUDE (t) FROM c{k} JOIN m{k} USING (t) ORDER BY CASE WHEN f <= bound THEN t ELSE 1000 - t END LIMIT 1)")
        out.append(f"SELECT {k} AS k, t::INT AS tries, round(alpha, 9) AS alpha, round(f, 4) AS loss FROM b{k}")
    return "WITH " + ",\n".join(ctes) + "\n" + " UNION ALL ".join(out)


@query(_line_search_sql)
def line_search_trace(spark, sf_dir):
    n = _n(spark, sf_dir)
    run = train_line_search(line(spark, sf_dir), SVM, [0.0] * 5, 4, LS["a0"] / n, LS["rho"], LS["c1"], max_tries=10)
    return trace_frame(spark, run, {"k": "int", "tries": "int", "alpha": "double", "loss": "double"}, {"alpha": 9})


@query(f"{EX}, s AS (SELECT round(sum({O.loss('svm', _Z)}), 4) AS loss, round(sum({O.slope('svm', _Z)} * x0), 4) + 0.0 AS g0 FROM ex) SELECT m::INT AS parts, merge, loss, g0 FROM s, (VALUES (1), (2), (4), (8)) t(m), (VALUES ('central'), ('tree')) u(merge)")
def bgd_partition_invariance(spark, sf_dir):
    out = []
    for parts in (1, 2, 4, 8):
        ex = line(spark, sf_dir).repartition(parts)
        for merge in ("central", "tree"):
            m = multi_eval(ex, np.array(W), SVM, plan="arrow", merge=merge)
            out.append((parts, merge, round(float(m.loss[0]), 4), round(float(m.grad[0, 0]), 4) + 0.0))
    return rows(spark, out, "parts int, merge string, loss double, g0 double")


def _oneshot_sql(iterations: int = 4) -> str:
    ctes = [f"ex AS (SELECT *, ord % 4 AS part FROM {O.line()})", f"v0 AS (SELECT part, z.* FROM (SELECT DISTINCT part FROM ex), {O.zeros()} z)"]
    for k in range(iterations):
        ctes.append(f"m{k} AS ({O.sums('svm', f'ex JOIN v{k} USING (part)', 'part')})")
        ctes.append(f"v{k + 1} AS (SELECT part, " + ", ".join(f"w{j} - {O.num(4.0)} / {N_SQL} * g{j} AS w{j}" for j in range(5)) + f" FROM v{k} JOIN m{k} USING (part))")
    return "WITH " + ",\n".join(ctes) + "\nSELECT " + ", ".join(f"round(avg(w{j}), 6) + 0.0 AS w{j}" for j in range(5)) + f" FROM v{iterations}"


def model_row(spark, w) -> DataFrame:
    return rows(spark, [tuple(round(float(v), 6) + 0.0 for v in w)], ", ".join(f"w{j} double" for j in range(len(w))))


@query(_oneshot_sql)
def bgd_oneshot_average(spark, sf_dir):
    ex = line(spark, sf_dir).withColumn("part", F.col("ord") % 4)
    return model_row(spark, average(train_bgd_oneshot(ex, SVM, [0.0] * 5, 4.0 / _n(spark, sf_dir), 4, "part"), 5))


FINISHED = list(range(0, BLOCKS, 2))


@query(f"{EX} SELECT policy, count(*) AS n, round(sum({O.loss('svm', _Z)}) * any_value(s), 4) AS loss, {', '.join(f'round(sum({O.slope("svm", _Z)} * x{j}) * any_value(s), 4) + 0.0 AS g{j}' for j in range(5))} FROM ex, (VALUES ('include', 2.0::DOUBLE), ('discard', 1.0::DOUBLE)) p(policy, s) WHERE blk % 2 = 0 GROUP BY policy")
def partial_gradient_timeout(spark, sf_dir):
    out = []
    for policy in ("include", "discard"):
        m = partial_gradient(line(spark, sf_dir), SVM, np.array(W), FINISHED, BLOCKS, policy == "discard")
        out.append((policy, m.n, round(float(m.loss[0]), 4), *(round(float(v), 4) + 0.0 for v in m.grad[0])))
    return rows(spark, out, "policy string, n long, loss double, " + ", ".join(f"g{j} double" for j in range(5)))


CD_GRID = (-0.5, -0.1, -0.02, 0.0, 0.02, 0.1, 0.5)


def _cd_sql() -> str:
    ctes, out = [f"ex AS {O.line()}", f"b0 AS {O.zeros()}"], []
    for j in range(5):
        values = ", ".join(f"({O.num(v)})" for v in CD_GRID)
        z = O.dot("w") + f" + x{j} * t.v"
        ctes.append(f"m{j} AS (SELECT t.v AS v, sum({O.loss('svm', z)}) AS f FROM ex, b{j}, (VALUES {values}) t(v) GROUP BY t.v)")
        ctes.append(f"p{j} AS (SELECT v, round(f, 6) AS f FROM m{j} ORDER BY round(f, 6), abs(v), v LIMIT 1)")
        ctes.append(f"b{j + 1} AS (SELECT " + ", ".join(f"w{i} + v AS w{i}" if i == j else f"w{i}" for i in range(5)) + f" FROM b{j}, p{j})")
        out.append(f"SELECT {j} AS coord, round(f, 4) AS loss, {O.ws()} FROM p{j}, b{j + 1}")
    return "WITH " + ",\n".join(ctes) + "\n" + " UNION ALL ".join(out)


@query(_cd_sql)
def coordinate_descent_trace(spark, sf_dir):
    run = train_cd(line(spark, sf_dir), SVM, [0.0] * 5, 1, CD_GRID)
    return trace_frame(spark, run, {"coord": "int", "loss": "double", "w": "w"})


@query()
def lbfgs_trace(spark, sf_dir):
    out = None
    for mode in (False, True):
        run = train_lbfgs(line(spark, sf_dir), LR, [0.0] * 5, 5, speculative=mode)
        t = trace_frame(spark, run, {"k": "int", "tries": "int", "loss": "double"}).withColumn("speculative", F.lit(mode))
        out = t if out is None else out.unionByName(t)
    return out


# incremental methods

ALPHA = 0.01
KEY = LINE_KEY


@query(lambda: f"{EX} SELECT n, {O.ws()} FROM ({O.fold(O.num(ALPHA), f'ex, {O.zeros()} z')})")
def igd_serial_sql(spark, sf_dir):
    found = incremental.passes(line(spark, sf_dir), SVM, [0.0] * 5, ALPHA, KEY)
    return found.select("n", *(r(F.element_at("w", j + 1), 6).alias(f"w{j}") for j in range(5)))


def _orders_sql(alpha: float = 0.001, epochs: int = 3) -> str:
    """Passes unrolled: a new permutation for each, the one of the view, or the order of the key."""
    fresh = "('0x' || substr(md5(concat_ws(':', l_orderkey, l_linenumber, l_partkey, l_suppkey, '{}')), 1, 8))::BIGINT"
    ctes, out = [f"ex AS {O.line()}", f"z AS {O.zeros()}"], []
    for policy, place in (("reshuffle", fresh), ("once", "ord"), ("cyclic", "0")):
        now = "z"
        for k in range(epochs):
            ctes.append(f"{policy}{k} AS ({O.fold(O.num(alpha), f'(SELECT * REPLACE ({place.format(k)} AS ord) FROM ex) e, {now}')})")
            now = f"{policy}{k}"
            out.append(f"SELECT '{policy}' AS policy, {k + 1} AS k, round(sum({O.loss('svm', O.dot())}), 4) AS loss FROM ex, {now}")
    return "WITH " + ",\n".join(ctes) + "\n" + " UNION ALL ".join(out)


@query(_orders_sql)
def igd_orders(spark, sf_dir):
    ex, orders = line(spark, sf_dir), ("reshuffle", "once", "cyclic")
    runs = together(lambda order: incremental.train_igd(ex, SVM, [0.0] * 5, Step("const", 0.001), 3, KEY, order, LINE_KEY), orders)
    out = [(order, t["k"], round(t["loss"], 4)) for order, run in zip(orders, runs) for t in run.trace]
    return rows(spark, out, "policy string, k int, loss double")


def _minibatch_sql(batch: int = 1000, alpha: float = 0.5, steps: int = 6) -> str:
    """The first steps of a pass: each group of examples in random order gives one step by its mean gradient."""
    ctes = [f"ex AS (SELECT * FROM (SELECT *, row_number() OVER (ORDER BY ord, l_orderkey, l_linenumber, l_partkey, l_suppkey) - 1 AS rk FROM {O.line()}) WHERE rk < {batch * steps})", f"v0 AS {O.zeros()}"]
    out = []
    for k in range(steps):
        ctes.append(f"m{k} AS ({O.sums('svm', f'(SELECT * FROM ex WHERE rk // {batch} = {k}) e, v{k}')})")
        ctes.append(f"v{k + 1} AS (SELECT " + ", ".join(f"w{j} - {O.num(alpha)} * g{j} / n AS w{j}" for j in range(5)) + f" FROM v{k}, m{k})")
        out.append(f"SELECT {k + 1} AS step, {O.ws()} FROM v{k + 1}")
    return "WITH " + ",\n".join(ctes) + "\n" + " UNION ALL ".join(out)


@query(_minibatch_sql)
def minibatch_trace(spark, sf_dir):
    """The models after each of the first six steps, by mini-batch passes over growing prefixes of the random order."""
    ex, out = line(spark, sf_dir), []
    for steps in range(1, 7):
        prefix = estimators.srs(ex, 1000 * steps, KEY)
        w = incremental.train_minibatch(prefix, Spec("svm", scale="mean"), [0.0] * 5, 0.5, 1000, 1, KEY, evaluate=False).w
        out.append((steps, *(round(float(v), 6) + 0.0 for v in w)))
    return rows(spark, out, "step int, " + ", ".join(f"w{j} double" for j in range(5)))


@query()
def minibatch_pass(spark, sf_dir):
    """The model after every step of a whole pass over all line items, of which minibatch_trace has the first six."""
    steps = incremental.minibatch_steps(line(spark, sf_dir), Spec("svm", scale="mean"), [0.0] * 5, 0.5, 1000, KEY)
    return steps.select("step", "n", *(r(F.element_at("w", j + 1), 6).alias(f"w{j}") for j in range(5)))


@query()
def hybrid_trace(spark, sf_dir):
    ex = line(spark, sf_dir).withColumn("part", F.col("ord") % 4)
    run = incremental.train_hybrid(ex, SVM, [0.0] * 5, Step("const", 0.01), Step("const", 0.2 / _n(spark, sf_dir)), KEY, "part", 0.01, 4, 4)
    return trace_frame(spark, run, {"phase": "string", "k": "int", "loss": "double"})


def _merge_sql(weight: str = "n") -> str:
    parts = O.fold(O.num(ALPHA), f"(SELECT *, ord % 4 AS part FROM ex) e, {O.zeros()} z", "part")
    return f"{EX}, p AS ({parts}) SELECT " + ", ".join(f"round(sum({weight} * w{j}) / sum({weight}), 6) + 0.0 AS w{j}" for j in range(5)) + " FROM p"


@query(_merge_sql)
def igd_merge_model(spark, sf_dir):
    ex = line(spark, sf_dir).withColumn("part", F.col("ord") % 4)
    return model_row(spark, incremental.train_igd_merge(ex, SVM, [0.0] * 5, Step("const", ALPHA), 1, KEY, "part", evaluate=False).w)


def _oneshot_igd_sql(epochs: int = 2) -> str:
    """Parts that go through all their passes alone."""
    ctes = [f"ex AS (SELECT *, ord % 4 AS part FROM {O.line()})", f"p0 AS (SELECT DISTINCT part, z.* FROM ex, {O.zeros()} z)"]
    ctes += [f"p{k + 1} AS ({O.fold(O.num(ALPHA), f'ex JOIN (SELECT part, {O.ws(digits=None)} FROM p{k}) v USING (part)', 'part')})" for k in range(epochs)]
    return "WITH " + ",\n".join(ctes) + " SELECT " + ", ".join(f"round(sum(n * w{j}) / sum(n), 6) + 0.0 AS w{j}" for j in range(5)) + f" FROM p{epochs}"


@query(_oneshot_igd_sql)
def igd_oneshot(spark, sf_dir):
    ex = line(spark, sf_dir).withColumn("part", F.col("ord") % 4)
    return model_row(spark, incremental.train_igd_oneshot(ex, SVM, [0.0] * 5, Step("const", ALPHA), 2, KEY, "part")[0])


def _study_sql(alpha: float = 0.001, counts=(1, 2, 4, 8)) -> str:
    ctes, out = [f"ex AS {O.line()}"], []
    for m in counts:
        ctes.append(f"p{m} AS ({O.fold(O.num(alpha), f'(SELECT *, ord % {m} AS part FROM ex) e, {O.zeros()} z', 'part')})")
        ctes.append(f"v{m} AS (SELECT " + " + ".join(f"coalesce(var_samp(w{j}), 0)" for j in range(5)) + " AS v, " + ", ".join(f"sum(n * w{j}) / sum(n) AS w{j}" for j in range(5)) + f" FROM p{m})")
        out.append(f"SELECT {m} AS parts, round(any_value(v), 6) + 0.0 AS variance, round(sum({O.loss('svm', O.dot())}), 4) AS loss FROM ex, v{m}")
    return "WITH " + ",\n".join(ctes) + "\n" + " UNION ALL ".join(out)


@query(_study_sql)
def igd_partition_study(spark, sf_dir):
    return incremental.partition_study(line(spark, sf_dir), SVM, [0.0] * 5, Step("const", 0.001), KEY)


def _turn_sql(nodes: int, threads: int) -> str:
    ranked = f"(SELECT *, ord % {nodes} AS node, (ord // {nodes}) % {threads} AS thread FROM ex)"
    return f"(SELECT * REPLACE (row_number() OVER (PARTITION BY node, thread ORDER BY ord, l_orderkey, l_linenumber, l_partkey, l_suppkey) * {threads} + thread AS ord) FROM {ranked})"


@query(lambda: f"{EX}, p AS ({O.fold(O.num(ALPHA), f'{_turn_sql(1, 4)} e, {O.zeros()} z', 'node')}) SELECT {O.ws()} FROM p")
def igd_lock_model(spark, sf_dir):
    return model_row(spark, incremental.train_igd_shared(line(spark, sf_dir), SVM, [0.0] * 5, ALPHA, KEY, 1, 4, "lock")[0])


@query(lambda: f"{EX} SELECT {O.ws()} FROM ({O.fold_late(O.num(ALPHA), f'{_turn_sql(1, 4)} e, {O.zeros()} z', 4)})")
def igd_nolock_model(spark, sf_dir):
    return model_row(spark, incremental.train_igd_shared(line(spark, sf_dir), SVM, [0.0] * 5, ALPHA, KEY, 1, 4, "nolock")[0])


@query(lambda: f"{EX}, p AS ({O.fold(O.num(ALPHA), f'{_turn_sql(2, 4)} e, {O.zeros()} z', 'node')}) SELECT " + ", ".join(f"round(sum(n * w{j}) / sum(n), 6) + 0.0 AS w{j}" for j in range(5)) + " FROM p")
def igd_node_hybrid(spark, sf_dir):
    return model_row(spark, incremental.train_igd_shared(line(spark, sf_dir), SVM, [0.0] * 5, ALPHA, KEY, 2, 4, "lock")[0])


def _progressive_sql(every: int = 1000) -> str:
    """A recursion over runs of `every` examples, each folded with the losses before its updates in the place of y."""
    key = "ord, l_orderkey, l_linenumber, l_partkey, l_suppkey"
    z = " + ".join(f"r.x{j} * a.x{j}" for j in range(5))
    f, g = (O.loss("svm", "@").replace("y", "r.y").replace("@", z), O.slope("svm", "@").replace("y", "r.y").replace("@", z))
    acc = ", ".join(f"'x{j}': a.x{j} - {O.num(ALPHA)} * ({g}) * r.x{j}" for j in range(5)) + f", 'y': a.y + {f}"
    row, start = ", ".join(f"'x{j}': x{j}" for j in range(5)) + ", 'y': y", ", ".join(f"'x{j}': 0.0::DOUBLE" for j in range(5)) + ", 'y': 0.0::DOUBLE"
    runs = f"SELECT rk // {every} AS c, count(*) AS n, list({{{row}}} ORDER BY rk) AS l FROM (SELECT *, row_number() OVER (ORDER BY {key}) - 1 AS rk FROM {O.line()}) GROUP BY c"
    step = f"SELECT t.c + 1, t.pos + runs.n, list_reduce(runs.l, lambda a, r: {{{acc}}}, t.s) FROM t JOIN runs ON runs.c = t.c"
    return f"WITH RECURSIVE runs AS MATERIALIZED ({runs}), t(c, pos, s) AS (SELECT 0::BIGINT, 0::BIGINT, {{{start}}} UNION ALL {step}) SELECT pos, round(s.y / pos, 6) + 0.0 AS mean_loss FROM t WHERE c > 0"


@query(_progressive_sql)
def progressive_loss(spark, sf_dir):
    return incremental.progressive_loss(line(spark, sf_dir), SVM, [0.0] * 5, ALPHA, KEY).select("pos", F.round("mean_loss", 6).alias("mean_loss"))


# speculation


def _spec_sql(what: str, kind: str = "svm", iterations: int = 4) -> str:
    return O.spec_bgd(kind, [list(GRID)] * iterations, what).replace("- t.alpha * g", f"- t.alpha / {N_SQL} * g")


def _spec_run(spark, sf_dir, iterations: int = 4, **more):
    n = _n(spark, sf_dir)
    return train_spec(spark, sf_dir, speculative.Grid(tuple(a / n for a in GRID)), iterations, **more), n


def train_spec(spark, sf_dir, grid, iterations, spec: Spec = SVM, **more):
    return speculative.train_spec_bgd(line(spark, sf_dir), spec, [0.0] * 5, grid, iterations=iterations, **more)


@query(lambda: _spec_sql("trace"))
def spec_bgd_trace(spark, sf_dir):
    run, n = _spec_run(spark, sf_dir)
    for t in run.trace:
        t["alpha"] = round(t["alpha"] * n, 6)
    return trace_frame(spark, run, {"k": "int", "s": "int", "best": "int", "alpha": "double", "loss": "double", "w": "w"}, {"alpha": 6})


@query(lambda: _spec_sql("candidates"))
def spec_bgd_candidates(spark, sf_dir):
    run, n = _spec_run(spark, sf_dir)
    return rows(spark, [(t["k"], i, round(a * n, 6), round(x, 4)) for t in run.trace for i, a, x in t["candidates"]], "k int, i int, alpha double, loss double")


MODELS = np.array([[0.1 * (m + 1), 0.05 * m, -0.1 * m, 0.02 * m, 0.01] for m in range(4)])


@query(lambda: f"{EX}, m AS (" + " UNION ALL ".join(f"SELECT {m} AS m, sum({O.loss('svm', O.dot_values(w))}) AS f, sum({O.slope('svm', O.dot_values(w))} * x1) AS g1 FROM ex" for m, w in enumerate(MODELS)) + ") SELECT plan, m, round(f, 4) AS loss, round(g1, 4) + 0.0 AS g1 FROM m, (VALUES ('wide'), ('arrow'), ('long'), ('sparse')) p(plan)")
def spec_plan_equivalence(spark, sf_dir):
    ex, out = line(spark, sf_dir), []
    sparse = ex.select(F.xxhash64(*LINE_KEY).alias("ex_id"), F.array(*(F.lit(j).cast("long") for j in range(5))).alias("idx"), F.array(*X5).alias("val"), "y")
    for plan in ("wide", "arrow", "long", "sparse"):
        m = multi_eval(sparse if plan == "sparse" else ex, MODELS, SVM, plan)
        out += [(plan, i, round(float(m.loss[i]), 4), round(float(m.grad[i, 1]), 4) + 0.0) for i in range(4)]
    return rows(spark, out, "plan string, m int, loss double, g1 double")


@query(f"SELECT mode, passes::BIGINT AS passes, passes * {N_SQL} AS rows_read, loss FROM (VALUES ('fused', 4), ('separate', 7)) t(mode, passes), (SELECT loss FROM ({_spec_sql('trace', iterations=3)}) WHERE k = 3) x")
def spec_overlap_ablation(spark, sf_dir):
    out = []
    for mode in ("fused", "separate"):
        run, _ = _spec_run(spark, sf_dir, 3, overlap=mode == "fused")
        out.append((mode, run.cost.total("passes"), run.cost.total("rows_read"), round(run.trace[-1]["loss"], 4)))
    return rows(spark, out, "mode string, passes long, rows_read long, loss double")


@query(lambda: f"{EX}, m AS (" + " UNION ALL ".join(f"SELECT {m} AS m, sum({O.loss('svm', O.dot_values(w))}) AS f FROM ex" for m, w in enumerate(MODELS)) + f") SELECT mode, passes::BIGINT AS passes, passes * {N_SQL} AS rows_read, m, round(f, 4) AS loss FROM m, (VALUES ('shared', 1), ('independent', 4)) t(mode, passes)")
def spec_vs_independent(spark, sf_dir):
    ex = line(spark, sf_dir)
    alone, meter = speculative.independent_runs(ex, SVM, None, MODELS)
    m = multi_eval(ex, MODELS, SVM)
    out = [("shared", 1, m.n, i, round(float(v), 4)) for i, v in enumerate(m.loss)]
    out += [("independent", meter.total("passes"), meter.total("rows_read"), i, round(float(v), 4)) for i, v in enumerate(alone)]
    return rows(spark, out, "mode string, passes long, rows_read long, m int, loss double")


@query(
    """WITH RECURSIVE e AS (SELECT count(*) AS n, count(*) FILTER (l_quantity > 40) AS m FROM lineitem),
    c AS (SELECT 1 AS k, 1 AS s, (50 * n + m) / 50.0::DOUBLE AS secs, (50 * n + m) / 50.0::DOUBLE AS ref, false AS settled, n, m FROM e
    UNION ALL SELECT k + 1, s2, (50 * n + s2 * m) / 50.0::DOUBLE, ref, done, n, m FROM (SELECT *, CASE WHEN secs > 2.0 * ref AND s > 1 THEN greatest(1, s // 2) WHEN settled THEN s
    WHEN secs <= 1.1 * ref THEN least(64, s * 2) ELSE greatest(1, s // 2) END AS s2, settled OR secs > 1.1 * ref AS done FROM c) WHERE k < 9)
    SELECT k, s, secs FROM c"""
)
def adaptive_steps_sim(spark, sf_dir):
    """The controller on a simulated clock: a line item takes one unit, and a large one a fiftieth more for each configuration."""
    n, m = views.table(spark, sf_dir, "lineitem").agg(F.count(F.lit(1)), F.count(F.when(F.col("l_quantity") > 40, 1))).first()
    c, out = stepdist.StepCountController(), []
    for k in range(1, 10):
        s, secs = c.s, (50 * n + c.s * m) / 50.0
        out.append((k, s, secs))
        c.next(secs)
    return rows(spark, out, "k int, s int, secs double")


@query()
def spec_igd_trace(spark, sf_dir):
    ex = line(spark, sf_dir).withColumn("part", F.col("ord") % 4)
    run = speculative.train_spec_igd(ex, LR, [0.0] * 5, (0.0005, 0.005, 0.05), 2, KEY, "part")
    return trace_frame(spark, run, {"k": "int", "parents": "int", "models": "int", "best": "int", "loss": "double"})


@query()
def spec_minibatch_trace(spark, sf_dir):
    ex = line(spark, sf_dir).withColumn("part", F.col("ord") % 4)
    run = speculative.train_spec_minibatch(ex, Spec("lr", scale="mean"), [0.0] * 5, stepdist.BivariatePhi(), 6, 2, KEY, "part")
    return trace_frame(spark, run, {"k": "int", "alpha": "double", "batch": "int", "loss": "double"})


# distributions, on steps whose losses are measured on the line items

#: Steps that are tried; the last one diverges, so that its loss is not a number.
TRIED, DIVERGED = (0.001, 0.01, 0.1, 1.0, 10.0), 5.0


def _tried_sql(alphas) -> str:
    values = ", ".join(f"({i}, {O.num(a)})" for i, a in enumerate(alphas))
    return f"(SELECT i, alpha, CASE WHEN alpha > {DIVERGED} THEN 'nan'::DOUBLE ELSE round(avg(abs(alpha * l_quantity - 1)), 6) END AS loss FROM lineitem, (VALUES {values}) v(i, alpha) GROUP BY i, alpha) t"


def measured(spark, sf_dir, alphas=TRIED) -> list[tuple[float, float]]:
    """Each step with the mean absolute loss of a model of one weight over all line items, in one scan."""
    loss = [F.round(F.avg(F.abs(F.lit(float(a)) * F.col("l_quantity") - 1)), 6) for a in alphas]
    found = views.table(spark, sf_dir, "lineitem").agg(*(f.alias(f"a{i}") for i, f in enumerate(loss))).first()
    return [(a, float("nan") if a > DIVERGED or v is None else v) for a, v in zip(alphas, found)]


_P = _tried_sql(TRIED)
_WEIGHTS = f"""p AS (SELECT i, alpha, loss, isfinite(loss) AS ok FROM {_P}), q AS (SELECT *, max(loss) FILTER (ok) OVER () AS hi, min(loss) FILTER (ok) OVER () AS lo,
    count(*) FILTER (ok) OVER () AS n, rank() OVER (ORDER BY CASE WHEN ok THEN loss ELSE 'inf'::DOUBLE END) - 1 AS rk FROM p),
    k AS (SELECT kind, i, alpha, CASE WHEN NOT ok THEN 0.0 WHEN kind = 'gap' THEN hi - loss WHEN kind = 'softmin' THEN exp(-(loss - lo) / 10.0) WHEN kind = 'inverse' THEN 1 / loss ELSE n - rk END AS v FROM q, (VALUES ('gap'), ('softmin'), ('inverse'), ('rank')) u(kind)),
    g AS (SELECT kind, i, alpha, v / sum(v) OVER (PARTITION BY kind) AS p FROM k)"""


@query(f"WITH {_WEIGHTS} SELECT kind, i, round(p, 9) + 0.0 AS p FROM g")
def loss_weights_kinds(spark, sf_dir):
    out, losses = [], [x for _, x in measured(spark, sf_dir)]
    for kind in ("gap", "softmin", "inverse", "rank"):
        out += [(kind, i, round(float(p), 9)) for i, p in enumerate(stepdist.loss_weights(losses, kind, 10.0))]
    return rows(spark, out, "kind string, i int, p double")


@query(
    f"""WITH {_WEIGHTS}, c AS (SELECT 5.0::DOUBLE AS s, kappa, 0.5::DOUBLE AS mu, 0.3::DOUBLE AS sigma FROM (VALUES (0.0::DOUBLE), (1.0), (5.0)) v(kappa)),
    m AS (SELECT kappa, any_value(mu) AS mu0, any_value(sigma) AS sg, any_value(s) AS s, (kappa * any_value(mu) + any_value(s) * sum(p * alpha)) / (kappa + any_value(s)) AS mu FROM g, c WHERE kind = 'gap' GROUP BY kappa)
    SELECT m.kappa AS kappa, round(any_value(m.mu), 9) AS mu, round(sqrt((m.kappa * any_value(sg) ** 2 + m.kappa * (any_value(mu0) - any_value(m.mu)) ** 2 + any_value(m.s) * sum(p * (alpha - m.mu) ** 2)) / (m.kappa + any_value(m.s))), 9) AS sigma
    FROM g, m WHERE kind = 'gap' GROUP BY m.kappa"""
)
def bayes_normal(spark, sf_dir):
    a, losses = zip(*measured(spark, sf_dir))
    p, out = stepdist.loss_weights(losses), []
    for kappa in (0.0, 1.0, 5.0):
        phi = stepdist.update_normal(stepdist.NormalPhi(0.5, 0.3), a, p, kappa)
        out.append((kappa, round(phi.mu, 9), round(phi.sigma, 9)))
    return rows(spark, out, "kappa double, mu double, sigma double")


#: Steps and batch sizes; what they weigh is measured.
CONFIGS = [(0.05, 500), (0.1, 1000), (0.2, 1500), (0.4, 800)]


@query(
    f"""WITH l AS (SELECT alpha AS a, b, max(loss) OVER () - loss AS gap FROM {_tried_sql([a for a, _ in CONFIGS])} JOIN (VALUES (0, 500.0::DOUBLE), (1, 1000), (2, 1500), (3, 800)) v(i, b) USING (i)),
    t AS (SELECT a, b, gap / sum(gap) OVER () AS p FROM l),
    m AS (SELECT (0.1 + 4 * sum(p * a)) / 5 AS ma, (1000.0 + 4 * sum(p * b)) / 5 AS mb FROM t)
    SELECT round(any_value(ma), 6) AS mean_a, round(any_value(mb), 6) AS mean_b, round((0.1 + (0.1 - any_value(ma)) ** 2 + 4 * sum(p * (a - ma) ** 2)) / 5, 6) AS var_a,
    round((10000 + (1000 - any_value(mb)) ** 2 + 4 * sum(p * (b - mb) ** 2)) / 5, 4) AS var_b, round((10 + (0.1 - any_value(ma)) * (1000 - any_value(mb)) + 4 * sum(p * (a - ma) * (b - mb))) / 5, 6) AS cov FROM t, m"""
)
def bayes_bivariate(spark, sf_dir):
    losses = [x for _, x in measured(spark, sf_dir, [a for a, _ in CONFIGS])]
    phi = stepdist.update_bivariate(stepdist.BivariatePhi(), CONFIGS, stepdist.loss_weights(losses), 1.0)
    c = phi.cov
    return rows(spark, [(round(phi.mean[0], 6), round(phi.mean[1], 6), round(c[0][0], 6), round(c[1][1], 4), round(c[0][1], 6))], "mean_a double, mean_b double, var_a double, var_b double, cov double")


@query()
def em_mixture(spark, sf_dir):
    prior = stepdist.MixturePhi((0.5, 0.5), (0.05, 2.0), (0.1, 1.0))
    a, losses = zip(*measured(spark, sf_dir))
    phi, trace = stepdist.em_mixture(prior, a, stepdist.loss_weights(losses))
    return rows(spark, [(i, round(phi.pi[i], 6), round(phi.mu[i], 6), round(phi.sigma[i], 6), round(trace[-1], 6)) for i in range(2)], "component int, pi double, mu double, sigma double, log_likelihood double")


@query(f"WITH {_WEIGHTS}, h AS (SELECT alpha, p AS weight FROM g WHERE kind = 'gap') SELECT round(sum(weight * alpha) / sum(weight), 9) AS mu, round(sqrt(sum(weight * alpha * alpha) / sum(weight) - (sum(weight * alpha) / sum(weight)) ** 2), 9) AS sigma FROM h")
def phi_from_history(spark, sf_dir):
    a, losses = zip(*measured(spark, sf_dir))
    log = rows(spark, [(x, float(w)) for x, w in zip(a, stepdist.loss_weights(losses))], "alpha double, weight double")
    return stepdist.phi_from_history(log).select(F.round("mu", 9).alias("mu"), F.round("sigma", 9).alias("sigma"))


# sampling and estimators

ID = ", ".join(LINE_KEY)


@query(f"{EX} SELECT {ID} FROM ex WHERE ord < {int(0.1 * 2**32)}")
def bernoulli_sample(spark, sf_dir):
    return estimators.bernoulli(line(spark, sf_dir), 0.1).select(*LINE_KEY)


@query(f"SELECT {ID} FROM lineitem WHERE ('0x' || substr(md5(concat_ws(':', l_orderkey, l_partkey, l_suppkey, l_linenumber, l_returnflag, l_linestatus)), 1, 8))::BIGINT < {int(0.1 * 2**32)}")
def hash_sample(spark, sf_dir):
    df = views.table(spark, sf_dir, "lineitem")
    return estimators.hash_sample(df, 0.1, ["l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_returnflag", "l_linestatus"]).select(*LINE_KEY)


@query(f"{EX} SELECT {ID} FROM ex ORDER BY ord, {ID} LIMIT 1000")
def srs_sample(spark, sf_dir):
    return estimators.srs(line(spark, sf_dir), 1000, LINE_KEY).select(*LINE_KEY)


@query(f"""{EX}, s AS (SELECT count(*) AS t, avg({O.loss('svm', _Z)}) AS m, var_samp({O.loss('svm', _Z)}) AS v FROM ex), n AS (SELECT eps, t, 4 * v / (eps * m) ** 2 AS n0 FROM s, (VALUES (0.01::DOUBLE), (0.05), (0.2)) e(eps))
    SELECT eps, least(t, greatest(1, ceil(n0 / (1 + n0 / t) - 1e-9)))::BIGINT AS n FROM n""")
def required_n(spark, sf_dir):
    f = SVM.f.column(dot_wide(X5, W), F.col("y"))
    s = line(spark, sf_dir).agg(F.count(F.lit(1)).alias("t"), F.avg(f).alias("m"), F.var_samp(f).alias("v")).first()
    return rows(spark, [(e, estimators.required_n(s["v"], s["m"], s["t"], e)) for e in (0.01, 0.05, 0.2)], "eps double, n long")


_PREFIX = f"""{EX}, f AS (SELECT blk, {O.loss('svm', _Z)} AS f FROM ex), b AS (SELECT blk, count(*) AS n, sum(f) AS s1, sum(f * f) AS s2 FROM f GROUP BY blk),
    c AS (SELECT blk, sum(n) OVER w AS n, sum(s1) OVER w AS s1, sum(s2) OVER w AS s2, sum(n) OVER () AS t FROM b WINDOW w AS (ORDER BY blk ROWS UNBOUNDED PRECEDING))"""
_EST = O.estimates("n", "s1", "s2", "t")


@query(f"{_PREFIX} SELECT blk, n::BIGINT AS n, " + ", ".join(f"round({v}, {6 if k == 'rel_err' else 3}) + 0.0 AS {k}" for k, v in _EST.items()) + " FROM c")
def estimate_loss_prefixes(spark, sf_dir):
    """The estimates after each block, from running sums over the blocks' sums: one query, one scan."""
    f = SVM.f.column(dot_wide(X5, W), F.col("y"))
    b = line(spark, sf_dir).select("blk", f.alias("f")).groupBy("blk").agg(F.count(F.lit(1)).alias("n"), F.sum("f").alias("s1"), F.sum(F.col("f") * F.col("f")).alias("s2"))
    w = Window.orderBy("blk").rowsBetween(Window.unboundedPreceding, 0)  # over one row for each block
    c = b.select("blk", *(F.sum(k).over(w).alias(k) for k in ("n", "s1", "s2")), F.sum("n").over(Window.partitionBy()).alias("t"))
    e = estimators.estimate_columns(F.col("n"), F.col("s1"), F.col("s2"), F.col("t"))
    return c.select("blk", "n", *(r(v, 6 if k == "rel_err" else 3).alias(k) for k, v in e.items()))


START = block_sequence(BLOCKS, 1, 0)


@query(lambda: f"{EX}, o AS (SELECT * FROM (VALUES " + ", ".join(f"({i}, {b})" for i, b in enumerate(START)) + ") t(pos, blk)) SELECT pos, blk, count(*) AS n FROM ex JOIN o USING (blk) GROUP BY pos, blk")
def block_sequence_scan(spark, sf_dir):
    pos = F.pmod(F.col("blk") - START[0], F.lit(BLOCKS)).cast("int").alias("pos")
    return line(spark, sf_dir).groupBy(pos, "blk").agg(F.count(F.lit(1)).alias("n"))


def _ola_sql(column: str) -> str:
    """Fixed waves of 1, 2, 4, .. blocks; all models go on to the end."""
    bounds, done, wave = [], 0, 0
    while done < BLOCKS:
        done = min(BLOCKS, done + 2**wave)
        bounds.append((wave, done))
        wave += 1
    models = MODELS[:2]
    part = lambda m, e: f"SELECT {m} AS m, pos, {e} AS f FROM ex JOIN o USING (blk)"
    expr = [O.loss("svm", O.dot_values(w)) if column == "loss" else f"{O.slope('svm', O.dot_values(w))} * x0" for w in models]
    body = " UNION ALL ".join(part(m, e) for m, e in enumerate(expr))
    est = O.estimates("n", "s1", "s2", "t")
    return f"""{EX}, o AS (SELECT * FROM (VALUES {", ".join(f"({i}, {b})" for i, b in enumerate(START))}) t(pos, blk)), f AS ({body}), v AS (SELECT * FROM (VALUES {", ".join(map(str, bounds))}) t(wave, upto)),
    c AS (SELECT wave, m, count(*) AS n, sum(f) AS s1, sum(f * f) AS s2, {N_SQL} AS t FROM f JOIN v ON pos < upto GROUP BY wave, m)
    SELECT wave, m, n, round({est['est']}, 3) + 0.0 AS est, round({est['std']}, 3) + 0.0 AS std FROM c"""


def _ola(spark, sf_dir, at: int) -> DataFrame:
    waves = ola.ola_run(line(spark, sf_dir), MODELS[:2], SVM, _n(spark, sf_dir), START, halt=False)
    return rows(spark, [(v.wave, m, v.n, round(float(v.estimate.est[m, at]), 3) + 0.0, round(float(v.estimate.std[m, at]), 3) + 0.0) for v in waves for m in range(2)], "wave int, m int, n long, est double, std double")


@query(lambda: _ola_sql("loss"))
def ola_rounds_loss(spark, sf_dir):
    return _ola(spark, sf_dir, 0)


@query(lambda: _ola_sql("gradient"))
def ola_rounds_gradient(spark, sf_dir):
    return _ola(spark, sf_dir, 1)


# halting rules, on literal rows

GRADIENTS = {"good": [(100.0, 1.0), (-80.0, 1.0)], "near_zero": [(100.0, 1.0), (-80.0, 1.0), (0.01, 1.0)], "zero": [(100.0, 1.0), (0.0, 0.0)], "zero_spread": [(100.0, 1.0), (0.0, 1.0)]}


def _gradient_sql() -> str:
    values = ", ".join(f"('{k}', {O.num(e)}, {O.num(s)})" for k, v in GRADIENTS.items() for e, s in v)
    return f"""WITH t AS (SELECT name, est, std, CASE WHEN std = 0 THEN 0.0 WHEN est = 0 THEN 'inf'::DOUBLE ELSE 2 * std / abs(est) END AS e FROM (VALUES {values}) v(name, est, std))
    SELECT name, bool_and(e <= 0.05) AS all_ok, avg((e <= 0.05)::INT) >= 0.9 AS share_ok, sum(e) <= 0.05 * count(*) AS sum_ok, sqrt(sum(std * std)) * 2 <= 0.05 * sqrt(sum(est * est)) AS norm_ok FROM t GROUP BY name"""


@query(_gradient_sql)
def stop_gradient_modes(spark, sf_dir):
    out = [(k, *(halting.stop_gradient([e for e, _ in v], [s for _, s in v], mode=m) for m in ("all", "share", "sum", "norm"))) for k, v in GRADIENTS.items()]
    return rows(spark, out, "name string, all_ok boolean, share_ok boolean, sum_ok boolean, norm_ok boolean")


INTERVALS = {"a": (6.92, 12.0), "b": (0.0, 10.0), "c": (11.0, 14.0), "d": (3.0, 7.0), "e": (6.85, 6.95)}
_I = "(VALUES " + ", ".join(f"('{k}', {O.num(lo)}, {O.num(hi)})" for k, (lo, hi) in INTERVALS.items()) + ") t(id, low, high)"
_RULES_SQL = f"""WITH i AS (SELECT * FROM {_I}), p AS (SELECT j.id AS j, i.id AS i, j.low AS jl, j.high AS jh, i.low AS il, i.high AS ih FROM i j JOIN i ON j.id <> i.id),
    u AS (SELECT j AS id, bool_or(ih <= jl) AS exact, bool_or(il <= jl AND ih <= jh AND jl <= ih AND ih - jl <= 0.05 * (jh - jl)) AS overlap,
    bool_or(il < jl AND jh <= ih AND ih - jl <= 0.05 * (ih - il)) AS inner_upper, bool_or(jl <= il AND ih < jh AND ih - jl <= 0.05 * (jh - jl)) AS outer_lower FROM p GROUP BY j)"""


@query(f"{_RULES_SQL} SELECT * FROM u")
def stop_loss_rules(spark, sf_dir):
    """Which rule lets each interval go, by a theta join of the intervals: a table of s rows, at most the models of one pass."""
    i = rows(spark, [(k, *v) for k, v in INTERVALS.items()], "id string, low double, high double")
    j, o = i.toDF("id", "jl", "jh"), i.toDF("oid", "il", "ih")
    p = j.join(F.broadcast(o), F.col("id") != F.col("oid"))
    jl, jh, il, ih = (F.col(c) for c in ("jl", "jh", "il", "ih"))
    return p.groupBy("id").agg(
        F.bool_or(ih <= jl).alias("exact"), F.bool_or((il <= jl) & (ih <= jh) & (jl <= ih) & (ih - jl <= 0.05 * (jh - jl))).alias("overlap"),
        F.bool_or((il < jl) & (jh <= ih) & (ih - jl <= 0.05 * (ih - il))).alias("inner_upper"), F.bool_or((jl <= il) & (ih < jh) & (ih - jl <= 0.05 * (jh - jl))).alias("outer_lower"),
    )


#: Steps whose losses over the line items make intervals: mean and half a standard deviation to either side.
CANDIDATES = {"a": 0.01, "b": 0.02, "c": 0.04, "d": 0.1, "e": 0.2}
MEASURED_SQL = "(SELECT id, round(avg(f) - stddev_samp(f) / 2, 6) AS low, round(avg(f) + stddev_samp(f) / 2, 6) AS high FROM (SELECT id, abs(alpha * l_quantity - 1) AS f FROM lineitem, (VALUES " + ", ".join(f"('{k}', {O.num(a)})" for k, a in CANDIDATES.items()) + ") v(id, alpha)) GROUP BY id)"


def measured_intervals(spark, sf_dir) -> DataFrame:
    """(id, low, high) of the candidates' losses, all from one scan."""
    f = {k: F.abs(F.lit(a) * F.col("l_quantity") - 1) for k, a in CANDIDATES.items()}
    ends = [F.struct(F.lit(k).alias("id"), F.round(F.avg(x) - F.stddev_samp(x) / 2, 6).alias("low"), F.round(F.avg(x) + F.stddev_samp(x) / 2, 6).alias("high")) for k, x in f.items()]
    return views.table(spark, sf_dir, "lineitem").agg(F.array(*ends).alias("found")).select(F.inline("found"))


@query(f"{_RULES_SQL.replace(_I, MEASURED_SQL)} SELECT id FROM u WHERE NOT (exact OR overlap OR inner_upper OR outer_lower)")
def fig2_stop_loss(spark, sf_dir):
    names, low, high = zip(*measured_intervals(spark, sf_dir).collect())
    left = halting.stop_loss(low, high)
    return rows(spark, [(names[i],) for i in left], "id string")


SNAPSHOTS = {"halts": [(100.0, 2.0), (100.5, 2.0), (140.0, 30.0)], "differs": [(100.0, 2.0), (103.0, 2.0), (140.0, 30.0)], "one": [(100.0, 2.0), (140.0, 30.0)]}


@query(lambda: "WITH t AS (SELECT * FROM (VALUES " + ", ".join(f"('{k}', {O.num(e)}, {O.num(s)})" for k, v in SNAPSHOTS.items() for e, s in v) + ") v(name, est, std)) SELECT name, coalesce(count(*) FILTER (2 * std / est <= 0.05) >= 2 AND (max(est) FILTER (2 * std / est <= 0.05) - min(est) FILTER (2 * std / est <= 0.05)) / max(est) FILTER (2 * std / est <= 0.05) <= 0.01, false) AS halt FROM t GROUP BY name")
def stop_igd_loss(spark, sf_dir):
    return rows(spark, [(k, bool(halting.stop_igd_loss([e for e, _ in v], [s for _, s in v]))) for k, v in SNAPSHOTS.items()], "name string, halt boolean")


# approximate methods


def approx_run(spark, sf_dir, label: str = "planted", iterations: int = 4, **more):
    n = _n(spark, sf_dir)
    grid = speculative.Grid(tuple(a / n for a in GRID))
    return ola.train_approx_bgd(line(spark, sf_dir, label), SVM, [0.0] * 5, n, BLOCKS, grid, iterations=iterations, **more)


@query()
def approx_bgd_trace(spark, sf_dir):
    run = approx_run(spark, sf_dir)
    return rows(spark, [(t["k"], t["best"], round(t["loss"], 3), t["n_read"], round(t["ratio"], 6), t["waves"], t["survivors"]) for t in run.trace], "k int, best int, loss double, n_read long, ratio double, waves int, survivors array<int>")


@query(lambda: _spec_sql("trace"))
def approx_bgd_exact(spark, sf_dir):
    """With eps = 0 the approximate method reads everything and is the exact one."""
    n, run = _n(spark, sf_dir), approx_run(spark, sf_dir, eps=0.0)
    for t in run.trace:
        t["alpha"], t["s"] = round(t["alpha"] * n, 6), len(GRID)
    return trace_frame(spark, run, {"k": "int", "s": "int", "best": "int", "alpha": "double", "loss": "double", "w": "w"}, {"alpha": 6})


@query()
def fig5_sample_ratio(spark, sf_dir):
    out = []
    for label in ("planted", "noise"):
        run = approx_run(spark, sf_dir, label, 5)
        out += [(label, t["k"], round(t["ratio"], 6)) for t in run.trace]
    return rows(spark, out, "view string, k int, ratio double")


@query()
def approx_igd_trace(spark, sf_dir):
    ex = line(spark, sf_dir).withColumn("part", F.col("ord") % 4)
    run = train_approx_igd(ex, LR, [0.0] * 5, (0.0005, 0.005, 0.05), _n(spark, sf_dir), BLOCKS, KEY, "part")
    return trace_frame(spark, run, {"k": "int", "parents": "int", "left": "int", "best": "int", "loss": "double", "ratio": "double", "halted": "boolean", "waves": "int"}, {"ratio": 6})


@query()
def igd_sync_modes(spark, sf_dir):
    out, ex = [], line(spark, sf_dir).withColumn("part", F.col("ord") % 4)
    for sync in ("none", "blocking", "stale"):
        run = train_approx_igd(ex, LR, [0.0] * 5, (0.005,), _n(spark, sf_dir), BLOCKS, KEY, "part", 1, 4, sync=sync)
        out += [(sync, t["k"], round(t["loss"], 4), round(t["ratio"], 6)) for t in run.trace]
    return rows(spark, out, "sync string, k int, loss double, ratio double")


@query(lambda: f"{EX}, o AS (SELECT {O.loss('svm', _Z)} AS f, row_number() OVER (ORDER BY ord, {ID}) AS rk FROM ex) SELECT kind, round(sum(f) * {N_SQL} / any_value(n), 3) AS loss, any_value(n)::BIGINT AS n FROM o, (VALUES ('single', 1), ('fixed', 500)) t(kind, n) WHERE rk <= n GROUP BY kind")
def loss_probe_kinds(spark, sf_dir):
    n = _n(spark, sf_dir)
    return rows(spark, [(k, round(ola.loss_probe(line(spark, sf_dir), W, SVM, n, c, LINE_KEY), 3), c) for k, c in (("single", 1), ("fixed", 500))], "kind string, loss double, n long")


@query()
def loss_probe_ola(spark, sf_dir):
    loss, n = ola.loss_ola(line(spark, sf_dir), W, SVM, _n(spark, sf_dir), START)
    return rows(spark, [(round(loss, 3), n)], "loss double, n long")


def _subsample_sql() -> str:
    parts = []
    for q in (0.01, 0.05, 0.2, 1.0):
        ctes = [f"ex AS {O.line()}", f"sm AS (SELECT * FROM ex WHERE ord < {int(q * 2**32)})", f"v0 AS {O.zeros()}"]
        for k in range(5):
            ctes.append(f"m{k} AS ({O.sums('svm', f'sm, v{k}')})")
            ctes.append(f"v{k + 1} AS (SELECT " + ", ".join(f"w{j} - {O.num(4.0)} / {N_SQL} * (g{j} / {O.num(q)}) AS w{j}" for j in range(5)) + f" FROM v{k}, m{k})")
        parts.append("SELECT * FROM (WITH " + ",\n".join(ctes) + f" SELECT {O.num(q)} AS q, (SELECT 5 * count(*) FROM sm)::BIGINT AS rows_read, round(f, 3) AS loss FROM ({O.sums('svm', 'ex, v5')}))")
    return " UNION ALL ".join(parts)


@query(_subsample_sql)
def subsample_static(spark, sf_dir):
    ex, n, out = line(spark, sf_dir), _n(spark, sf_dir), []
    for q in (0.01, 0.05, 0.2, 1.0):
        run = ola.train_subsample(ex, SVM, [0.0] * 5, q, 4.0 / n, 5)
        out.append((q, run.cost.total("rows_read"), round(float(multi_eval(ex, run.w, SVM).loss[0]), 3)))
    return rows(spark, out, "q double, rows_read long, loss double")
