import numpy as np
import pytest
from pyspark.sql import functions as F

from calib.functions.losses import LOSSES, Spec, register_loss
from calib.operators import halting, incremental, ola, speculative, stepdist
from calib.operators.approx_igd import resync, train_approx_igd
from calib.operators.batch import Step, StopRule, train_bgd, train_lbfgs, train_line_search
from calib.operators.estimators import Estimate, estimate, estimate_bernoulli, rel_error, required_n
from calib.plans import moments
from calib.queries_methods import INTERVALS, MODELS, line
from calib.session import materialize
from calib.sources.order import block_sequence
from calib.sources.views import LINE_KEY, wide

HAND = [((1.0, 1.0), 1.0), ((2.0, 1.0), -1.0), ((-1.0, 1.0), 1.0), ((0.0, 1.0), -1.0)]


@pytest.fixture(scope="module")
def hand(spark):
    return spark.createDataFrame([(*x, y) for x, y in HAND], "x0 double, x1 double, y double")


@pytest.fixture(scope="module")
def ex(spark, sf):
    return line(spark, sf)


@pytest.fixture(scope="module")
def xy(ex):
    p = ex.orderBy("ord", *LINE_KEY).select(*wide(5), "y", "ord", "blk").toPandas()
    return p[wide(5)].to_numpy(), p["y"].to_numpy(), p


def test_hand_example(hand):
    m = moments.multi_eval(hand, np.zeros(2), Spec("svm"), "wide")
    assert m.loss[0] == 4 and m.grad[0].tolist() == [2, 0]
    m = moments.multi_eval(hand, np.zeros(2), Spec("lr"), "arrow")
    assert m.loss[0] == pytest.approx(4 * np.log(2)) and m.grad[0].tolist() == pytest.approx([1, 0])


@pytest.mark.parametrize("name", ["svm", "lr", "squared"])
def test_slopes_are_derivatives(name):
    f, dot, y = LOSSES[name], np.array([-2.0, -0.5, 0.3, 1.7, 700.0]), np.array([1.0, -1.0, 1.0, -1.0, -1.0])
    h = 1e-6
    assert f.slope(dot, y) == pytest.approx((f.value(dot + h, y) - f.value(dot - h, y)) / (2 * h), abs=1e-3)


def test_plans_agree_with_numpy(ex, xy):
    x, y, _ = xy
    for spec in (Spec("svm"), Spec("lr")):
        dot = x @ MODELS.T
        loss, grad = spec.f.value(dot, y[:, None]).sum(axis=0), spec.f.slope(dot, y[:, None]).T @ x
        for plan in ("wide", "arrow", "long"):
            m = moments.multi_eval(ex, MODELS, spec, plan, want_sq=True)
            assert m.n == len(y) and m.loss == pytest.approx(loss) and m.grad == pytest.approx(grad, rel=1e-9, abs=1e-6)


def test_registered_loss(hand):
    register_loss("half", lambda d, y: F.abs(d - y) / 2, lambda d, y: F.signum(d - y) / 2, lambda d, y: np.abs(d - y) / 2, lambda d, y: np.sign(d - y) / 2)
    w = np.array([0.5, 0.0])
    a, b = (moments.multi_eval(hand, w, Spec("half"), p) for p in ("wide", "arrow"))
    assert a.loss == pytest.approx(b.loss) and a.grad == pytest.approx(b.grad)


def test_one_scan_for_all_models(ex):
    bind, out = moments.wide_columns(MODELS, Spec("svm"))
    assert moments.scan_count(ex.select(*wide(5), *bind).agg(*out)) == 1


def test_fused_requests_and_merging(ex):
    one, two = moments.fuse_requests(ex, [{"a": F.col("y")}, {"a": F.col("x0"), "b": F.lit(1)}])
    assert two["b"] == ex.count() and one["a"] == ex.agg(F.sum("y")).first()[0]
    a, b = np.arange(5.0), np.array([7.0, 9.0])
    s = lambda v: (len(v), v.mean(), ((v - v.mean()) ** 2).sum())
    assert moments.merge_stable(s(a), s(b)) == pytest.approx(s(np.concatenate([a, b])))


def test_speculation_with_one_step_is_plain_descent(ex):
    n = ex.count()
    a = train_bgd(ex, Spec("svm"), [0.0] * 5, Step("const", 1 / n), StopRule(max_iter=3))
    b = speculative.train_spec_bgd(ex, Spec("svm"), [0.0] * 5, speculative.Grid((1 / n,)), iterations=3)
    assert b.w == pytest.approx(a.w) and b.cost.total("passes") == 4


def test_nested_grids_do_not_hurt(ex):
    n, last = ex.count(), float("inf")
    for s in (1, 2, 4, 8):
        g = speculative.Grid(tuple(v / n for v in speculative.nested_grid(s, 1.0, 3.0).values))
        loss = speculative.train_spec_bgd(ex, Spec("svm"), [0.0] * 5, g, iterations=1).trace[0]["loss"]
        assert loss <= last + 1e-9
        last = loss


def test_line_search_lowers_enough(ex):
    n = ex.count()
    a = train_line_search(ex, Spec("lr"), [0.0] * 5, 3, 64 / n)
    b = train_line_search(ex, Spec("lr"), [0.0] * 5, 3, 64 / n, speculative=True)
    assert a.w == pytest.approx(b.w) and b.cost.total("passes") < a.cost.total("passes")
    losses = [t["loss"] for t in a.trace]
    assert losses == sorted(losses, reverse=True)


def test_lbfgs_against_library(ex):
    from calib.operators.baselines import library_model

    run = train_lbfgs(ex, Spec("lr"), [0.0] * 5, 15, speculative=True)
    w, _ = library_model(ex, "lr", 5, 50)
    best = float(moments.multi_eval(ex, w, Spec("lr")).loss[0])
    assert run.trace[-1]["loss"] <= best * 1.0001


def test_igd_against_numpy(ex, xy):
    x, y, p = xy
    w = np.zeros((1, 5))
    incremental.sgd(x, y, w, np.array([0.01]), Spec("svm"))
    got = incremental.passes(ex, Spec("svm"), [0.0] * 5, 0.01, LINE_KEY).first()
    assert got["n"] == len(y) and np.array(got["w"]) == pytest.approx(w[0])
    lock, _ = incremental.train_igd_shared(ex, Spec("svm"), [0.0] * 5, 0.01, LINE_KEY, 1, 1, "nolock")
    assert lock == pytest.approx(w[0])  # one thread reads the newest model


def test_spec_igd_is_merge_for_one_step(ex):
    parted = ex.withColumn("part", F.col("ord") % 3)
    a = incremental.train_igd_merge(parted, Spec("lr"), [0.0] * 5, Step("const", 0.01), 2, LINE_KEY, "part")
    b = speculative.train_spec_igd(parted, Spec("lr"), [0.0] * 5, (0.01,), 2, LINE_KEY, "part")
    assert b.w == pytest.approx(a.w) and b.trace[-1]["loss"] == pytest.approx(a.trace[-1]["loss"])


def test_minibatch_of_everything_is_a_batch_step(ex):
    n, spec = ex.count(), Spec("lr", scale="mean")
    a = incremental.train_minibatch(ex, spec, [0.0] * 5, 0.5, n, 1, LINE_KEY).w
    b = train_bgd(ex, spec, [0.0] * 5, Step("const", 0.5), StopRule(max_iter=1)).w
    assert a == pytest.approx(b)


def test_estimates_are_exact_at_the_end_and_unbiased_before(xy, ex):
    x, y, p = xy
    f = np.maximum(1 - y * (x @ MODELS[1]), 0)
    blocks = p["blk"].to_numpy()
    truth, ests, hits = f.sum(), [], []
    for start in range(64):
        inside = np.isin(blocks, [(start + i) % 64 for i in range(8)])
        m = moments.Moments(int(inside.sum()), np.array([[f[inside].sum()]]), np.array([[(f[inside] ** 2).sum()]]))
        e = estimate(m, len(f))
        ests.append(e.est[0, 0])
        hits.append(abs(e.est[0, 0] - truth) <= 1.96 * e.std[0, 0])
    assert np.mean(ests) == pytest.approx(truth, rel=0.02) and np.mean(hits) > 0.8
    whole = estimate(moments.Moments(len(f), np.array([[truth]]), np.array([[(f**2).sum()]])), len(f))
    assert whole.std[0, 0] == 0
    assert estimate_bernoulli(10.0, 30.0, 0.5) == pytest.approx((20.0, (0.5 / 0.25 * 30) ** 0.5))


def test_rel_error_and_required_n():
    assert rel_error([100, 0, 0, -50], [1, 0, 1, 1]).tolist() == [0.02, 0.0, np.inf, 0.04]
    assert required_n(4.0, 2.0, 10**6, 0.1) == 400 and required_n(4.0, 2.0, 300, 0.1) <= 300


def test_interval_rules():
    names = list(INTERVALS)
    low, high = zip(*INTERVALS.values())
    assert [names[i] for i in halting.stop_loss(low, high)] == ["b", "d"]
    r = np.random.default_rng(3)
    for _ in range(200):
        lo = r.random(6)
        hi = lo + r.random(6)
        assert int(np.argmin(hi)) in halting.stop_loss(lo, hi, approximate=False)
        assert halting.stop_loss(lo, hi, eps=5.0)
    assert halting.stop_loss([1.0, 1.0], [1.1, 1.1], eps=9.0) in ([0], [0, 1])


def test_joint_halt_policies():
    est, std = np.array([[10.0, 5.0], [10.0395, 5.0]]), np.array([[0.02, 4.0], [0.02, 4.0]])
    assert len(halting.joint_halt(est, std, 0.05, policy="deferred").survivors) == 2
    std[:, 1] = 0.01
    assert halting.joint_halt(est, std, 0.05).done


def test_ola_ends_early_and_keeps_the_best(ex):
    n = ex.count()
    models = np.array([[0.5, 0.25, -0.4, 0.1, 0.0], [-3.0, 0.0, 3.0, 0.0, 0.0], [0.0, 3.0, 0.0, 0.0, 3.0]])
    exact = moments.multi_eval(ex, models, Spec("svm")).loss
    waves = ola.ola_run(ex, models, Spec("svm"), n, block_sequence(64, 1), eps=0.2)
    assert waves[-1].alive == [int(np.argmin(exact))] and waves[-1].n < n
    waves = ola.ola_run(ex, models, Spec("svm"), n, block_sequence(64, 1), halt=False)
    assert waves[-1].estimate.est[:, 0] == pytest.approx(exact) and not waves[-1].estimate.std.any()


def test_async_sample(ex):
    n = ex.count()
    e, read = ola.ola_async(ex, MODELS, Spec("svm"), n, 500, lambda e, m: m >= 1500)
    assert 1500 <= read <= n and isinstance(e, Estimate)


def test_approx_igd_reads_less_and_learns(ex):
    parted, n = ex.withColumn("part", F.col("ord") % 2), ex.count()
    run = train_approx_igd(parted, Spec("lr"), [0.0] * 5, (0.001, 0.05), n, 64, LINE_KEY, "part", 2)
    start = n * np.log(2)
    assert run.trace[-1]["loss"] < 0.8 * start and all(t["ratio"] <= 1 for t in run.trace)


def test_resync():
    local, merged = {0: np.array([[1.0]]), 1: np.array([[3.0]])}, np.array([[2.0]])
    assert resync("blocking", local, {0: 1, 1: 1}, merged, None, 0)[1][0, 0] == 2
    assert resync("stale", local, {0: 1, 1: 3}, merged, np.array([[5.0]]), 1)[0][0, 0] == 3
    assert resync("stale", local, {0: 0, 1: 0}, merged, merged, 2)[0][0, 0] == 2  # no local rows: as blocking


def test_distributions():
    phi = stepdist.NormalPhi(0.1, 0.1**0.5, lo=0.0)
    assert min(phi.sample(50)) > 0
    p = stepdist.loss_weights([90, 60, 20, 45, float("nan")])
    assert p.sum() == pytest.approx(1) and p[4] == 0 and p.argmax() == 2
    assert stepdist.loss_weights([3, 3, 3]).tolist() == pytest.approx([1 / 3] * 3)
    _, trace = stepdist.em_mixture(stepdist.MixturePhi((0.5, 0.5), (0.0, 3.0), (1.0, 1.0)), [0.1, 0.2, 2.0, 2.5, 9.0], [0.2] * 5)
    assert all(b >= a - 1e-9 for a, b in zip(trace, trace[1:]))
    two = stepdist.update_bivariate(stepdist.BivariatePhi(), [(0.1, 900), (0.3, 1200)], [0.5, 0.5])
    assert np.linalg.eigvalsh(np.array(two.cov)).min() > 0 and all(b >= 1 for _, b in two.sample(20))


def test_best_ignores_bad_losses():
    assert speculative.select_best([float("nan"), 3.0, float("inf"), 3.0]) == 1


def test_controller():
    c, clock = stepdist.StepCountController(), {1: 1.0, 2: 1.02, 4: 1.05, 8: 1.08, 16: 1.6}
    seen = [c.s] + [c.next(clock[c.s]) for _ in range(6)]
    assert seen == [1, 2, 4, 8, 16, 8, 8]
    assert c.next(5.0) == 4


def test_triggers_and_intervals():
    t = halting.Trigger(every_rows=100)
    assert [t.fires(r, 0) for r in (50, 100, 150, 210)] == [False, True, False, True]
    i = halting.CheckInterval(1000, 0.5, 300)
    assert [i.next(None, 10), i.next(10, 10), i.next(10, 10), i.next(10, 5)] == [1000, 500, 300, 300]


def test_minibatch_pass_takes_every_line(spark, sf):
    from calib.queries_methods import minibatch_pass

    big = sf.replace("sf0.001", "sf0.01")  # more than six steps
    p = line(spark, big).orderBy("ord", *LINE_KEY).select(*wide(5), "y").toPandas()
    x, y, w, want = p[wide(5)].to_numpy(), p["y"].to_numpy(), np.zeros(5), []
    for at in range(0, len(y), 1000):
        xs, ys = x[at : at + 1000], y[at : at + 1000]
        w = w + 0.5 * ((ys * (xs @ w) < 1) * ys) @ xs / len(ys)
        want.append((len(ys), *w))
    got = minibatch_pass(spark, big).orderBy("step").toPandas()
    assert len(y) > 6000 and got["n"].sum() == len(y)
    assert got[["n", *(f"w{j}" for j in range(5))]].to_numpy() == pytest.approx(np.array(want), abs=1e-5)


def test_sparse_examples_give_what_dense_ones_do(ex):
    sparse = ex.where("blk < 8").select(F.monotonically_increasing_id().alias("ex_id"), "ord", "blk", *LINE_KEY, F.array(*(F.lit(j).cast("long") for j in range(5))).alias("idx"), F.array(*wide(5)).alias("val"), "y")
    sparse = materialize(sparse.withColumn("part", F.col("ord") % 2), "sparse")
    dense = sparse.select("ord", "blk", *LINE_KEY, "part", F.col("val").alias("x"), "y")
    models = np.array([[0.5, 0.2, -0.3, 0.1, 0.05], [0.0] * 5])
    a, b = (moments.multi_eval(f, models, Spec("svm"), plan, want_sq=True) for f, plan in ((sparse, "sparse"), (dense, "arrow")))
    assert a.n == b.n and a.s1 == pytest.approx(b.s1) and a.s2 == pytest.approx(b.s2) and a.s2[:, 0].all()
    a, b = (speculative.train_spec_igd(f, Spec("lr"), [0.0] * 5, (0.01, 0.1), 2, LINE_KEY, "part") for f in (sparse, dense))
    assert a.w == pytest.approx(b.w) and [t["loss"] for t in a.trace] == pytest.approx([t["loss"] for t in b.trace])
    a, b = (train_approx_igd(f, Spec("lr"), [0.0] * 5, (0.01, 0.1), sparse.count(), 8, LINE_KEY, "part") for f in (sparse, dense))
    assert a.w == pytest.approx(b.w) and [t["n_read"] for t in a.trace] == [t["n_read"] for t in b.trace]


def test_sparse_rows_may_repeat_and_be_empty(spark):
    rows = [(1, [0, 2], [1.0, 2.0], 1.0)] * 3 + [(1, [], [], -1.0), (2, [1], [0.5], -1.0), (None, None, None, 1.0)]
    sparse = spark.createDataFrame(rows, "ex_id long, idx array<long>, val array<double>, y double")
    x = np.array([[1.0, 0, 2.0]] * 3 + [[0, 0, 0], [0, 0.5, 0], [0, 0, 0]])
    y, w = np.array([r[3] for r in rows]), np.array([[0.1, 3.0, -0.2], [0, 0, 0]])
    m = moments.multi_eval(sparse, w, Spec("svm"), "sparse", want_sq=True)
    f, g = np.maximum(0, 1 - y[:, None] * (x @ w.T)), -y[:, None] * (y[:, None] * (x @ w.T) < 1)
    assert m.n == 6 and np.allclose(m.loss, f.sum(axis=0)) and np.allclose(m.grad, g.T @ x) and np.allclose(m.s2[:, 1:], (g**2).T @ x**2)


def test_regulariser_in_every_kernel(spark):
    """With L2: single steps, steps of small batches and approximate descent over one part, against plain loops."""
    r = np.random.default_rng(4)
    x, y = r.standard_normal((60, 3)), np.sign(r.standard_normal(60))
    t = spark.createDataFrame([(i, i, i % 4, 0, *map(float, x[i]), float(y[i])) for i in range(60)], "ex_id long, ord long, blk int, part int, x0 double, x1 double, x2 double, y double")
    spec, alphas = Spec("lr", reg="l2", mu=0.3), np.array([0.02, 0.1])
    one, many = [], []
    for a in alphas:
        w = np.zeros(3)
        for i in range(60):
            w = w - a * (spec.f.slope(w @ x[i], y[i]) * x[i] + spec.reg_grad(w))
        one.append(w)
        w = np.zeros(3)
        for i in range(0, 60, 25):
            w = w - a * (spec.f.slope(x[i : i + 25] @ w, y[i : i + 25]) @ x[i : i + 25] * spec.per(min(25, 60 - i)) + spec.reg_grad(w))
        many.append(w)
    for sizes, want in ((None, one), (np.array([25, 25]), many)):
        got = speculative.merge_children(speculative.igd_children(t, spec, np.zeros((1, 3)), alphas, ["ex_id"], "part", sizes), 3)
        assert got[()] == 60 and all(np.allclose(got[(0, c)], want[c]) for c in range(2))
    run = train_approx_igd(t, spec, [0.0] * 3, alphas, 60, 4, ["ex_id"], "part", iterations=1, eps=0.0, waves=1)
    best = min(one, key=lambda w: spec.f.value(x @ w, y).sum() * spec.per(60) + spec.reg_value(w))
    assert np.allclose(run.w, best)


def test_losses_alone(ex):
    models = np.random.default_rng(2).standard_normal((3, 5))
    assert np.allclose(moments.losses_of(ex, models, Spec("lr")).loss, moments.multi_eval(ex, models, Spec("lr")).loss)


def test_sparse_workload_compares_all_four(spark, sf):
    from calib.queries_experiments import fig4c_sparse

    got = fig4c_sparse(spark, sf).toPandas()
    print(got)
    assert set(got["method"]) == {"batch", "batch_online", "incremental", "incremental_online"}
    assert (got.groupby("method")["loss"].last() < spark.read.parquet(f"{sf}/documents.parquet").count()).all()


@pytest.mark.parametrize("variant", ["lock", "nolock"])
def test_spec_igd_with_shared_models(ex, variant):
    small, alphas = ex.where("blk < 8").localCheckpoint(), (0.01, 0.1, 0.001)
    alone = {a: incremental.train_igd_shared(small, Spec("lr"), [0.0] * 5, a, LINE_KEY, 2, 4, variant)[0] for a in alphas}
    run = speculative.train_spec_igd(small, Spec("lr"), [0.0] * 5, alphas, 1, LINE_KEY, "part", variant=variant, nodes=2)
    assert any(run.w == pytest.approx(w) for w in alone.values())
    run = speculative.train_spec_igd(small, Spec("lr"), [0.0] * 5, alphas, 2, LINE_KEY, "part", variant=variant, nodes=2)
    best = alone[min(alphas, key=lambda a: float(moments.multi_eval(small, alone[a], Spec("lr")).loss[0]))]
    assert run.trace[1]["models"] == 9 and run.trace[1]["w"] == pytest.approx(best)
    two = [incremental.train_igd_shared(small, Spec("lr"), best, a, LINE_KEY, 2, 4, variant)[0] for a in alphas]
    assert any(run.w == pytest.approx(w) for w in two)


def test_spec_igd_refits_its_steps(spark):
    """Against plain loops over one part: steps from the distribution, s by the clock, the best parent's children, refitting, and the stop."""
    r = np.random.default_rng(5)
    x, y = r.standard_normal((40, 3)), np.sign(r.standard_normal(40))
    t = spark.createDataFrame([(i, i, 0, *map(float, x[i]), float(y[i])) for i in range(40)], "ex_id long, ord long, part int, x0 double, x1 double, x2 double, y double")
    phi, ticks = stepdist.NormalPhi(np.log(0.05), 1.0, log=True), iter(range(100))
    run = speculative.train_spec_igd(t, Spec("lr"), [0.0] * 3, None, 4, ["ex_id"], "part", phi=phi, control=stepdist.StepCountController(most=4), clock=lambda: float(next(ticks)))

    def loss(w):
        return float(np.log1p(np.exp(-y * (x @ w))).sum())

    parents, before, expected = [np.zeros(3)], None, []
    for s in (1, 2, 4, 4):
        alphas, losses = phi.sample(s), [loss(w) for w in parents]
        best = int(np.argmin(losses))
        expected.append((s, len(parents), best, losses[best], phi.mu, phi.sigma))
        if before is not None:
            phi = stepdist.update_normal(phi, before, stepdist.loss_weights(losses))
        children = []
        for a in alphas:
            w = parents[best].copy()
            for i in range(40):
                w += a * y[i] * x[i] / (1 + np.exp(y[i] * (x[i] @ w)))
            children.append(w)
        parents, before = children, alphas
    got = [(v["s"], v["parents"], v["best"], v["loss"], v["phi"].mu, v["phi"].sigma) for v in run.trace[:-1]]
    assert got == [pytest.approx(e) for e in expected]
    assert run.w == pytest.approx(min(parents, key=loss))
    stopped = speculative.train_spec_igd(t, Spec("lr"), [0.0] * 3, (0.01,), 9, ["ex_id"], "part", stop=StopRule(rel_tol=0.9))
    assert len(stopped.trace) == 2 and stopped.trace[-1]["loss"] == pytest.approx(loss(stopped.w))


def test_async_sample_waits_for_its_trigger(ex):
    n, seen = ex.count(), []
    ola.ola_async(ex, MODELS, Spec("svm"), n, 200, lambda e, m: seen.append(m), trigger=halting.Trigger(every_rows=1000))
    assert seen and all(b - a >= 1000 for a, b in zip([0, *seen], seen))


def test_bags_of_long_documents(spark):
    """20000 distinct words: neither counts, norms nor the dot product may grow with their square."""
    import time

    from calib.functions.losses import dot_sparse
    from calib.sources.views import hashed_bag

    text = " ".join(f"w{i}" for i in range(20_000)) + " w7 w7"
    docs = spark.createDataFrame([(1, text), (2, None), (3, "a b a")], "doc_id long, text string")
    began = time.perf_counter()
    bag = hashed_bag(docs, ["doc_id"], F.col("text"), F.lit(1.0), 30).where(F.size("idx") > 0)
    dot = dot_sparse(F.map_from_arrays("idx", "val"), F.map_from_arrays("idx", F.transform("idx", lambda j: F.lit(2.0))))
    got = {r["doc_id"]: r for r in bag.select("doc_id", "idx", "val", dot.alias("dot")).collect()}
    assert time.perf_counter() - began < 20
    assert set(got) == {1, 3} and len(got[1]["idx"]) > 19_990 and got[1]["idx"] == sorted(set(got[1]["idx"]))
    assert max(got[1]["val"]) == pytest.approx(3 / np.sqrt(19_999 + 9), rel=1e-3)
    assert sorted(got[3]["val"]) == pytest.approx([1 / 5**0.5, 2 / 5**0.5]) and got[3]["dot"] == pytest.approx(6 / 5**0.5)


def test_sparse_sums_by_batches_are_those_of_the_join(spark):
    rows = [(i, [i % 7, 7 + i % 3, 7 + i % 3], [0.5, 1.0 + i, -2.0], float((-1) ** i)) for i in range(50)] + [(50, [], [], 1.0), (51, None, None, -1.0)]
    ex = spark.createDataFrame(rows, "ex_id long, idx array<long>, val array<double>, y double")
    models = np.random.default_rng(1).standard_normal((3, 12))
    for spec in (Spec("svm"), Spec("lr")):
        a, b = (moments.multi_eval(ex, models, spec, plan, want_sq=True) for plan in ("sparse", "joined"))
        assert a.n == b.n == 52 and np.allclose(a.s1, b.s1) and np.allclose(a.s2, b.s2)
    plan = moments.sparse_states(ex, models, Spec("svm"))._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan and "Join" not in plan


@pytest.mark.parametrize("loss", ["svm", "lr", "squared"])
@pytest.mark.parametrize("depth", [None, 0, 3])
def test_blocks_and_scalars_are_steps_one_by_one(loss, depth):
    r = np.random.default_rng(5)
    x, y, spec = r.standard_normal((150, 6)), np.sign(r.standard_normal(150)), Spec(loss)
    for models in (1, 40):  # below and above SCALAR_VALUES
        alpha, want = r.uniform(0.001, 0.02, models), np.repeat(r.standard_normal((1, 6)), models, axis=0)
        got, seen = want.copy(), [want.copy()] * ((depth or 0) + 1)
        for i in range(150):
            want = want - (spec.f.slope(seen[0] @ x[i], y[i]) * alpha)[:, None] * x[i]
            seen = [*seen[1:], want]
        late = None if depth is None else incremental.delayed(got, depth + 1, x, spec)
        for a, z in ((0, 1), (1, 70), (70, 150)):
            incremental.descend(got, x[a:z], y[a:z], alpha, spec, late)
        assert np.allclose(got, want, rtol=1e-9, atol=1e-12)


def test_serial_pass_is_not_sorted_in_one_task(ex):
    """Only packed runs of examples meet in the task that takes them all, in the order that one sort would give."""
    rows = incremental.ordered(ex, None, LINE_KEY, 5)
    assert set(rows.columns) == {"part", "n", "xy"}
    got = np.concatenate([np.frombuffer(r["xy"]).reshape(-1, 6) for r in rows.collect()])
    want = ex.orderBy("ord", *LINE_KEY).select(*wide(5), "y").toPandas().to_numpy()
    assert np.array_equal(got, want)


def test_grids_share_their_passes(ex, monkeypatch):
    grids = [speculative.nested_grid(s, 1e-4, 3.0) for s in (1, 2, 4)]
    alone = [speculative.train_spec_bgd(ex, Spec("svm"), [0.0] * 5, g, iterations=2, plan="arrow") for g in grids]
    scans, whole = [], speculative.multi_eval
    monkeypatch.setattr(speculative, "multi_eval", lambda *a, **k: scans.append(1) or whole(*a, **k))
    for a, b in zip(alone, speculative.train_spec_bgd_grids(ex, Spec("svm"), [0.0] * 5, grids, 2, "arrow")):
        assert [t["best"] for t in a.trace] == [t["best"] for t in b.trace] and np.allclose(a.w, b.w) and a.cost.rows == b.cost.rows
    assert len(scans) == 3
    parted = ex.where("blk < 16").withColumn("part", F.col("ord") % 2)
    steps = [speculative.nested_grid(s, 0.005, 4.0).values for s in (1, 2)]
    alone = [speculative.train_spec_igd(parted, Spec("lr"), [0.0] * 5, a, 2, LINE_KEY, "part") for a in steps]
    passes, children = [], speculative.igd_children
    monkeypatch.setattr(speculative, "igd_children", lambda *a, **k: passes.append(1) or children(*a, **k))
    for a, b in zip(alone, speculative.train_spec_igd_grids(parted, Spec("lr"), [0.0] * 5, steps, 2, LINE_KEY, "part")):
        assert np.allclose(a.w, b.w) and [t["models"] for t in a.trace] == [t["models"] for t in b.trace]
        assert [t["loss"] for t in a.trace] == pytest.approx([t["loss"] for t in b.trace])
    assert len(passes) == 2


def test_lists_have_the_order_of_parts_and_of_turns(ex, monkeypatch):
    for name, size in (("BUCKET", 500), ("JOB", 1700), ("RUN", 300)):
        monkeypatch.setattr(incremental, name, size)
    parted = ex.withColumn("part", F.col("ord") % 8)
    stored = incremental.lists(parted, "part", LINE_KEY, 5)
    jobs = [(rows, incremental.by_part) for rows in stored.by_part()]
    turns = [(rows, lambda b, d, lo=lo, hi=hi: incremental.in_order(b, d, lo, hi)) for rows, lo, hi in stored.by_turn(2, 4)]
    wants = (parted.orderBy("part", "ord", *LINE_KEY), incremental.in_turns(ex, LINE_KEY, 2, 4).withColumn("part", F.col("node")).orderBy("node", "ord"))
    for chain, want in zip((jobs, turns), wants):
        assert len(chain) > 2 and not any("Exchange" in rows._jdf.queryExecution().executedPlan().toString() for rows, _ in chain)  # passes shuffle nothing
        got = {}
        for rows, read in chain:
            for p, x, y in read(iter(rows.toArrow().to_batches()), 5):
                got.setdefault(p, []).append(np.column_stack([x, y]))
        want = want.select("part", *wide(5), "y").toPandas()
        assert sorted(got) == sorted(set(want["part"]))
        assert all(np.array_equal(np.concatenate(got[p]), v[[*wide(5), "y"]].to_numpy()) for p, v in want.groupby("part"))
    stored.drop()


@pytest.mark.parametrize("spec, late, sizes", [(Spec("svm"), 4, None), (Spec("lr", "l2", 0.1), 4, None), (Spec("lr", scale="mean"), 0, [7, 90])])
def test_passes_over_lists_are_those_over_rows(ex, monkeypatch, spec, late, sizes):
    small, parents = ex.where("blk < 16").withColumn("q", F.col("ord") % 4), np.array([[0.0] * 5, [0.1] * 5])
    args = (np.array([0.01, 0.1]), None if sizes is None else np.array(sizes), late)
    for name, size in (("BUCKET", 300), ("JOB", 400), ("RUN", 120)):
        monkeypatch.setattr(incremental, name, size)
    stored = incremental.lists(small, "q", LINE_KEY, 5)
    for frame, part, turns in ((small, "q", None), (incremental.in_turns(small, LINE_KEY, 1, 4), "node", (1, 4))):
        want = speculative.merge_children(speculative.igd_children(frame, spec, parents, args[0], LINE_KEY, part, *args[1:]), 5)
        got = speculative.children_of(stored, spec, parents, *args, turns)
        assert set(got) == set(want) and all(np.allclose(got[k], want[k], rtol=1e-10) for k in want)
    stored.drop()


def test_star_is_moved_and_kept_in_few_columns(spark, sf):
    from calib.sources import views

    slim = views.star_rows(spark, sf)
    assert len(slim.columns) < 30 < len(views.v_star(spark, sf).columns)
    a, b = (df.orderBy(*LINE_KEY).toPandas() for df in (views.as_array(views.v_star(spark, sf), views.STAR_D), views.star_array(slim)))
    assert list(a.columns) == list(b.columns) and np.array_equal(np.stack(a["x"]), np.stack(b["x"])) and a.drop(columns="x").equals(b.drop(columns="x"))


def test_scan_of_many_models_uses_all_tasks(ex, monkeypatch):
    plans, first = [], type(ex).first
    monkeypatch.setattr(type(ex), "first", lambda df: plans.append(df._jdf.queryExecution().executedPlan().toString()) or first(df))
    moments.multi_eval(ex, MODELS, Spec("svm"), "arrow")
    assert "Coalesce 1" not in plans[0]


def test_batch_experiment_makes_the_passes_it_reports(ex, monkeypatch):
    from calib import queries_experiments as E
    from calib.operators import batch
    from calib.plans.moments import multi_eval

    assert E.ITERATIONS == 20
    monkeypatch.setattr(E, "ITERATIONS", 2)
    small, scans = ex.where("blk < 4").localCheckpoint(), []
    for module in (speculative, batch):
        monkeypatch.setattr(module, "multi_eval", lambda *a, **k: scans.append(1) or multi_eval(*a, **k))
    *steps, search = E.spec_and_search(small, small.count(), 5)
    assert len(steps) == 6
    for f in steps:
        scans.clear()
        assert max(passes for _, _, _, passes in f()) == len(scans) == 3
    scans.clear()
    assert [k for _, k, _, _ in search()] == [1, 2] and len(scans) == 3


def test_incremental_experiment_runs_each_number_of_steps(spark, sf, monkeypatch):
    from calib import queries_experiments as E

    monkeypatch.setattr(E, "ITERATIONS", 2)
    tried, train = [], speculative.train_spec_igd
    monkeypatch.setattr(speculative, "train_spec_igd", lambda *a, **k: tried.append(len(a[3])) or train(*a, **k))
    got = [tuple(r) for r in E.fig3b_spec_igd_lr(spark, sf).collect()]
    assert sorted(tried) == [1, 2, 4, 8] and [(k, m) for s, k, _, m in got if s == "s=8"] == [(1, 8), (2, 64), (3, 0)]
