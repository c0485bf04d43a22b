"""Queries for what users need around the methods: sources, joins, aggregates, windows, sets, scalars, streams and functions."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from calib import oracle as O
from calib.functions import udx
from calib.functions.losses import Spec, dot_array, dot_sparse, dot_wide
from calib.operators import baselines
from calib.queries_methods import EX, ID, MEASURED_SQL, MODELS, N_SQL, START, W, X5, _Z, line, measured_intervals, r, rows
from calib.registry import query
from calib.session import shared_dir
from calib.sources import formats, views
from calib.sources.order import prepare
from calib.sources.views import LINE_KEY
from calib.streaming import online

SVM = Spec("svm")


@query(f"{EX} SELECT count(*) AS n, " + ", ".join(f"round(min(x{j}), 6) + 0.0 AS lo{j}, round(max(x{j}), 6) + 0.0 AS hi{j}" for j in range(5)) + " FROM ex")
def scan_parquet(spark, sf_dir):
    return line(spark, sf_dir).agg(F.count(F.lit(1)).alias("n"), *(c for j, x in enumerate(X5) for c in (r(F.min(x), 6).alias(f"lo{j}"), r(F.max(x), 6).alias(f"hi{j}"))))


def _bow_sql(bits: int = 12) -> str:
    return f"""tok AS (SELECT doc_id, lang, ('0x' || substr(md5(w), 1, 8))::BIGINT % {1 << bits} AS j FROM (SELECT doc_id, lang, unnest(regexp_split_to_array(lower(coalesce(text, '')), '[ \\t\\n\\x0B\\f\\r]+')) AS w FROM documents) WHERE w <> ''),
    cnt AS (SELECT doc_id, lang, j, count(*)::DOUBLE AS c FROM tok GROUP BY doc_id, lang, j), bow AS (SELECT doc_id, CASE WHEN lang = 'en' THEN 1.0 ELSE -1.0 END::DOUBLE AS y, j, c / sqrt(sum(c * c) OVER (PARTITION BY doc_id)) AS v FROM cnt)"""


@query(f"WITH {_bow_sql()} SELECT doc_id, any_value(y) AS y, count(*) AS nnz, min(j) AS first, max(j) AS last, round(sum(v), 6) AS total FROM bow GROUP BY doc_id")
def libsvm_roundtrip(spark, sf_dir):
    """Sparse documents written as text lines, an id in front, and parsed back."""
    bow = views.v_bow(spark, sf_dir).select("doc_id", "idx", "val", "y")
    pairs = F.transform(F.arrays_zip("idx", "val"), lambda e: F.concat((e["idx"] + 1).cast("string"), F.lit(":"), e["val"].cast("string")))
    path = shared_dir(spark, "libsvm")
    bow.select(F.concat_ws(" ", F.col("doc_id").cast("string"), F.col("y").cast("int").cast("string"), F.array_join(pairs, " ")).alias("value")).write.text(path)
    lines = spark.read.text(path)
    e = lines.select(F.substring_index("value", " ", 1).cast("long").alias("doc_id"), formats.parse_libsvm(F.expr("substring(value, locate(' ', value) + 1)")).alias("e"))
    idx, val = F.col("e.idx"), F.col("e.val")
    found = e.where(F.size(idx) > 0)
    return found.select("doc_id", F.col("e.y").alias("y"), F.size(idx).cast("long").alias("nnz"), F.array_min(idx).alias("first"), F.array_max(idx).alias("last"), F.round(F.aggregate(val, F.lit(0.0), lambda a, v: a + v), 6).alias("total"))


@query(f"{EX} SELECT blk, count(*) AS n, min(ord) AS lo, max(ord) AS hi FROM ex GROUP BY blk")
def prepare_blocks(spark, sf_dir):
    ex = prepare(views.v_line(spark, sf_dir), shared_dir(spark, "blocks"))
    return ex.groupBy("blk").agg(F.count(F.lit(1)).alias("n"), F.min("ord").alias("lo"), F.max("ord").alias("hi"))


@query(f"{EX} SELECT {ID}, round(1 - y * ({_Z}), 6) + 0.0 AS slack FROM ex WHERE 1 - y * ({_Z}) > 0")
def project_filter(spark, sf_dir):
    slack = 1 - F.col("y") * dot_wide(X5, W)
    return line(spark, sf_dir).where(slack > 0).select(*LINE_KEY, r(slack, 6).alias("slack"))


@query(f"{EX} SELECT count(*) AS n, round(sum({O.loss('svm', _Z)}), 4) AS loss FROM ex WHERE blk IN ({', '.join(map(str, START[:3]))})")
def block_prune(spark, sf_dir):
    ex = line(spark, sf_dir).where(F.col("blk").isin(START[:3]))
    return ex.agg(F.count(F.lit(1)).alias("n"), r(F.sum(SVM.f.column(dot_wide(X5, W), F.col("y")))).alias("loss"))


STAR_SQL = """FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey JOIN part ON l_partkey = p_partkey JOIN supplier ON l_suppkey = s_suppkey"""


@query(f"SELECT r_name, c_mktsegment, count(*) AS n, round(avg(l_quantity), 6) AS qty, round(avg(p_retailprice), 4) AS price, round(avg(s_acctbal), 4) AS bal {STAR_SQL} GROUP BY r_name, c_mktsegment")
def join_star(spark, sf_dir):
    df = views.star_joined(spark, sf_dir)
    return df.groupBy("r_name", "c_mktsegment").agg(F.count(F.lit(1)).alias("n"), F.round(F.avg("l_quantity"), 6).alias("qty"), F.round(F.avg("p_retailprice"), 4).alias("price"), F.round(F.avg("s_acctbal"), 4).alias("bal"))


def _labelled(spark, sf_dir, how: str) -> DataFrame:
    return views.table(spark, sf_dir, "documents").join(views.table(spark, sf_dir, "labels"), "doc_id", how).groupBy("lang").agg(F.count(F.lit(1)).alias("n"))


@query("SELECT lang, count(*) AS n FROM documents WHERE doc_id IN (SELECT doc_id FROM labels) GROUP BY lang")
def join_semi_labels(spark, sf_dir):
    return _labelled(spark, sf_dir, "left_semi")


@query("SELECT lang, count(*) AS n FROM documents WHERE doc_id NOT IN (SELECT doc_id FROM labels) GROUP BY lang")
def join_anti_labels(spark, sf_dir):
    return _labelled(spark, sf_dir, "left_anti")


@query(f"SELECT a.id AS a, b.id AS b, round(least(a.high, b.high) - greatest(a.low, b.low), 6) AS overlap FROM {MEASURED_SQL} a(id, low, high) JOIN {MEASURED_SQL} b(id, low, high) ON a.id < b.id AND a.low <= b.high AND b.low <= a.high")
def join_theta_overlap(spark, sf_dir):
    i = measured_intervals(spark, sf_dir)
    a, b = i.toDF("a", "al", "ah"), i.toDF("b", "bl", "bh")
    on = (F.col("a") < F.col("b")) & (F.col("al") <= F.col("bh")) & (F.col("bl") <= F.col("ah"))
    return a.join(F.broadcast(b), on).select("a", "b", F.round(F.least("ah", "bh") - F.greatest("al", "bl"), 6).alias("overlap"))


@query("SELECT w.id AS id, count(e.event_id) AS n, round(coalesce(sum(e.value), 0), 4) AS total FROM (SELECT event_id AS id, ts AS t FROM events WHERE event_type = (SELECT min(event_type) FROM events)) w LEFT JOIN events e ON e.ts >= w.t AND e.ts < w.t + INTERVAL 90 MINUTE GROUP BY w.id")
def range_join_blocks(spark, sf_dir):
    """Events inside check windows: both sides are cut into hours, joined by hour, and the rest is a filter."""
    e = views.table(spark, sf_dir, "events")
    least = e.agg(F.min("event_type").alias("least"))
    w = e.join(F.broadcast(least), F.col("event_type") == F.col("least")).select(F.col("event_id").alias("id"), F.unix_micros(F.col("ts").cast("timestamp")).alias("t"))
    hour, span = 3_600_000_000, 5_400_000_000
    cut = w.select("id", "t", F.explode(F.sequence(F.floor(F.col("t") / hour), F.floor((F.col("t") + span - 1) / hour))).alias("h"))
    ev = e.select(F.unix_micros(F.col("ts").cast("timestamp")).alias("ts"), "value", F.floor(F.unix_micros(F.col("ts").cast("timestamp")) / hour).alias("h"))
    hits = cut.join(ev, "h").where((F.col("ts") >= F.col("t")) & (F.col("ts") < F.col("t") + span)).groupBy("id").agg(F.count(F.lit(1)).alias("n"), F.sum("value").alias("v"))
    return w.select("id").join(hits, "id", "left").select("id", F.coalesce("n", F.lit(0)).cast("long").alias("n"), F.round(F.coalesce("v", F.lit(0.0)), 4).alias("total"))


TRACE_A = [(1.0, 50.0), (2.5, 30.0), (4.0, 22.0), (7.0, 20.0)]
TRACE_B = [(0.5, 60.0), (1.5, 28.0), (3.9, 21.0), (5.0, 19.0)]
_TRACES = ["(VALUES " + ", ".join(f"({O.num(a)}, {O.num(b)})" for a, b in t) + ") t(secs, loss)" for t in (TRACE_A, TRACE_B)]


@query(
    """SELECT a.event_id AS event_id, a.value AS loss, b.other AS other FROM (SELECT * FROM events WHERE event_type = 'click') a
    ASOF LEFT JOIN (SELECT user_id, ts, max(value) AS other FROM events WHERE event_type = 'view' AND value IS NOT NULL AND ts IS NOT NULL GROUP BY ALL) b ON a.user_id = b.user_id AND a.ts >= b.ts"""
)
def asof_trace(spark, sf_dir):
    """For each value of run A, a user's clicks, the last one of run B, the user's views: both in one order, and the last value that is not null."""
    e = views.table(spark, sf_dir, "events")
    nothing = F.lit(None)
    a = e.where("event_type = 'click'").select("user_id", "ts", "event_id", F.col("value").alias("loss"), nothing.cast("double").alias("other"), F.lit(1).alias("side"))
    b = e.where("event_type = 'view' AND value IS NOT NULL AND ts IS NOT NULL AND user_id IS NOT NULL").groupBy("user_id", "ts").agg(F.max("value").alias("other"))
    b = b.select("user_id", "ts", nothing.cast("long").alias("event_id"), nothing.cast("double").alias("loss"), "other", F.lit(0).alias("side"))
    w = Window.partitionBy("user_id").orderBy("ts", "side").rowsBetween(Window.unboundedPreceding, 0)
    return a.unionByName(b).withColumn("other", F.last("other", ignorenulls=True).over(w)).where("side = 1").select("event_id", "loss", "other")


@query(f"SELECT a.secs AS slow_secs, a.loss AS loss, min(b.secs) AS fast_secs, round(a.secs / min(b.secs), 4) AS speedup FROM {_TRACES[0].replace(' t(', ' a(')} JOIN {_TRACES[1].replace(' t(', ' b(')} ON b.loss <= a.loss GROUP BY a.secs, a.loss")
def speedup_measure(spark, sf_dir):
    return baselines.speedup_to_loss(rows(spark, TRACE_A, "secs double, loss double"), rows(spark, TRACE_B, "secs double, loss double"))


@query("SELECT * FROM (VALUES ('a', 4), ('b', 3)) t(run, k)")
def time_to_converge(spark, sf_dir):
    trace = [("a", k + 1, x) for k, (_, x) in enumerate(TRACE_A)] + [("b", k + 1, x) for k, (_, x) in enumerate([(0, 60.0), (0, 28.0), (0, 19.1), (0, 19.0)])]
    return baselines.time_to_converge(rows(spark, trace, "run string, k int, loss double"), 0.05)


@query("SELECT method, s, secs, round(secs / first_value(secs) OVER (PARTITION BY method ORDER BY s), 4) AS ratio FROM (SELECT l_returnflag AS method, l_linenumber AS s, sum(l_quantity) AS secs FROM lineitem GROUP BY ALL)")
def overhead_measure(spark, sf_dir):
    """The measure on line items: quantities stand for seconds, flags for methods and line numbers for s."""
    times = views.table(spark, sf_dir, "lineitem").groupBy(F.col("l_returnflag").alias("method"), F.col("l_linenumber").alias("s")).agg(F.sum("l_quantity").alias("secs"))
    return baselines.overhead(times)


@query(
    """WITH g AS (SELECT avg(l_quantity) AS m, stddev_samp(l_quantity) / sqrt(count(*)) AS d FROM lineitem GROUP BY l_orderkey % 64)
    SELECT round(avg((t BETWEEN m - d AND m + d)::INT), 6) AS coverage, round(avg(d / m), 6) AS rel_err FROM g, (SELECT avg(l_quantity) AS t FROM lineitem)"""
)
def coverage_measure(spark, sf_dir):
    """Estimates of the mean quantity from each of 64 groups of orders, one standard error to either side, against the mean of all."""
    li = views.table(spark, sf_dir, "lineitem")
    m, d = F.avg("l_quantity").alias("m"), (F.stddev_samp("l_quantity") / F.sqrt(F.count(F.lit(1)))).alias("d")
    e = li.groupBy(F.col("l_orderkey") % 64).agg(m, d).select((F.col("m") - F.col("d")).alias("low"), (F.col("m") + F.col("d")).alias("high"), (F.col("d") / F.col("m")).alias("rel_err"))
    found = baselines.coverage(e, li.agg(F.avg("l_quantity")).first()[0])
    return found.select(*(F.round(c, 6).alias(c) for c in ("coverage", "rel_err")))


#: Steps of which a tenth of the orders tells which ones stay: those whose loss is within KEPT of the least.
PRUNED, KEPT = (0.032, 0.033, 0.034, 0.035, 0.036), 1.00005


@query(
    f"""WITH l AS (SELECT l_suppkey % 16 AS k, i, round(avg(abs(alpha * l_quantity - 1)), 9) AS f, round(avg(abs(alpha * l_quantity - 1)) FILTER (l_orderkey % 10 = 0), 9) AS e
    FROM lineitem, (VALUES {", ".join(f"({i}, {O.num(a)})" for i, a in enumerate(PRUNED))}) v(i, alpha) GROUP BY ALL),
    m AS (SELECT k, f, i, coalesce(e <= {KEPT} * min(e) OVER (PARTITION BY k), false) AS stays, row_number() OVER (PARTITION BY k ORDER BY f, i) AS place FROM l)
    SELECT round(avg(stays::INT), 6) AS hit_rate FROM m WHERE place = 1"""
)
def prune_hit_rate(spark, sf_dir):
    """In each of 16 groups of suppliers: do the steps that a tenth of the orders lets stay hold the best one over all?"""
    f = [F.abs(F.lit(a) * F.col("l_quantity") - 1) for a in PRUNED]
    part = F.col("l_orderkey") % 10 == 0
    g = views.table(spark, sf_dir, "lineitem").groupBy((F.col("l_suppkey") % 16).alias("k"))
    g = g.agg(F.array(*(F.round(F.avg(x), 9) for x in f)).alias("f"), F.array(*(F.round(F.avg(F.when(part, x)), 9) for x in f)).alias("e"))
    stays = F.filter(F.transform("e", lambda v, i: F.when(v <= KEPT * F.array_min("e"), i)), lambda i: i.isNotNull())
    best = (F.array_position("f", F.array_min("f")) - 1).cast("int")
    return baselines.prune_hit_rate(g.select("k", stays.alias("survivors")), g.select("k", best.alias("best"))).select(F.round("hit_rate", 6).alias("hit_rate"))


@query(f"{EX} SELECT y, count(*) AS n, " + ", ".join(f"round(avg(x{j}), 6) + 0.0 AS m{j}, round(var_samp(x{j}), 6) AS v{j}" for j in range(5)) + ", round(corr(x0, x1), 6) + 0.0 AS c01 FROM ex GROUP BY y")
def agg_label_stats(spark, sf_dir):
    return line(spark, sf_dir).groupBy("y").agg(F.count(F.lit(1)).alias("n"), *(c for j, x in enumerate(X5) for c in (r(F.avg(x), 6).alias(f"m{j}"), F.round(F.var_samp(x), 6).alias(f"v{j}"))), r(F.corr("x0", "x1"), 6).alias("c01"))


def _loss_rows(spark, sf_dir) -> DataFrame:
    return line(spark, sf_dir).select("l_returnflag", "l_linestatus", SVM.f.column(dot_wide(X5, W), F.col("y")).alias("f"))


_CUBE = f"{EX} SELECT l_returnflag, l_linestatus, count(*) AS n, round(sum({O.loss('svm', _Z)}), 4) AS loss FROM ex GROUP BY "

def _summed(g) -> DataFrame:
    return g.agg(F.count(F.lit(1)).alias("n"), r(F.sum("f")).alias("loss"))


@query(_CUBE + "ROLLUP (l_returnflag, l_linestatus)")
def rollup_loss(spark, sf_dir):
    return _summed(_loss_rows(spark, sf_dir).rollup("l_returnflag", "l_linestatus"))


@query(_CUBE + "CUBE (l_returnflag, l_linestatus)")
def cube_loss(spark, sf_dir):
    return _summed(_loss_rows(spark, sf_dir).cube("l_returnflag", "l_linestatus"))


@query(_CUBE + "GROUPING SETS ((l_returnflag), (l_linestatus), ())")
def grouping_sets_loss(spark, sf_dir):
    return _summed(_loss_rows(spark, sf_dir).groupingSets([["l_returnflag"], ["l_linestatus"], []], "l_returnflag", "l_linestatus"))


@query(f"{EX} SELECT l_returnflag, " + ", ".join(f"round(sum({O.loss('svm', O.dot_values(w))}), 4) AS m{m}" for m, w in enumerate(MODELS)) + " FROM ex GROUP BY l_returnflag")
def pivot_config_loss(spark, sf_dir):
    ex = line(spark, sf_dir)
    losses = F.array(*(F.struct(F.lit(f"m{m}").alias("m"), SVM.f.column(dot_wide(X5, w), F.col("y")).alias("f")) for m, w in enumerate(MODELS)))
    long = ex.select("l_returnflag", F.explode(losses).alias("e")).select("l_returnflag", "e.m", "e.f")
    return long.groupBy("l_returnflag").pivot("m", ["m0", "m1", "m2", "m3"]).agg(r(F.sum("f")))


@query("SELECT lang, count(DISTINCT w) AS tokens, true AS near FROM (SELECT lang, unnest(regexp_split_to_array(lower(text), '[ \\t\\n\\x0B\\f\\r]+')) AS w FROM documents) WHERE w <> '' GROUP BY lang")
def approx_distinct_tokens(spark, sf_dir):
    """Exact and approximate distinct tokens; `near` tells whether the sketch was within 10 %."""
    w = views.table(spark, sf_dir, "documents").select("lang", F.explode(F.split(F.lower("text"), r"[ \t\n\x0B\f\r]+")).alias("w")).where("w <> ''")
    exact = w.distinct().groupBy("lang").agg(F.count(F.lit(1)).alias("tokens"))
    near = w.groupBy("lang").agg(F.approx_count_distinct("w", 0.02).alias("approx"))
    return exact.join(near, "lang").select("lang", "tokens", (F.abs(F.col("approx") - F.col("tokens")) <= 0.1 * F.col("tokens")).alias("near"))


@query(f"""{EX}, f AS (SELECT blk, {O.loss('svm', _Z)} AS f FROM ex), b AS (SELECT blk, count(*) AS n, sum(f) AS s FROM f GROUP BY blk)
    SELECT blk, sum(n) OVER w::BIGINT AS n, round({N_SQL} * sum(s) OVER w / sum(n) OVER w, 3) AS est FROM b WINDOW w AS (ORDER BY blk ROWS UNBOUNDED PRECEDING)""".replace("sum(n) OVER w::BIGINT", "(sum(n) OVER w)::BIGINT"))
def win_prefix_estimator(spark, sf_dir):
    b = line(spark, sf_dir).select("blk", SVM.f.column(dot_wide(X5, W), F.col("y")).alias("f")).groupBy("blk").agg(F.count(F.lit(1)).alias("n"), F.sum("f").alias("s"))
    w = Window.orderBy("blk").rowsBetween(Window.unboundedPreceding, 0)  # over one row for each block
    total = F.sum("n").over(Window.partitionBy())
    return b.select("blk", F.sum("n").over(w).alias("n"), r(total * F.sum("s").over(w) / F.sum("n").over(w), 3).alias("est"))


RUNS = [("a", k, x) for k, x in enumerate([50.0, 30.0, 30.0, 21.0])] + [("b", k, x) for k, x in enumerate([60.0, 28.0, 19.0])]
_RUNS = "(VALUES " + ", ".join(f"('{a}', {k}, {O.num(x)})" for a, k, x in RUNS) + ") t(run, k, loss)"


@query(f"SELECT run, k, round(loss - lag(loss) OVER w, 6) AS delta, round((loss - lag(loss) OVER w) / lag(loss) OVER w, 6) AS rel, rank() OVER (PARTITION BY run ORDER BY loss)::INT AS rank, ntile(2) OVER w::INT AS half FROM {_RUNS} WINDOW w AS (PARTITION BY run ORDER BY k)".replace("ntile(2) OVER w::INT", "(ntile(2) OVER w)::INT").replace("rank() OVER (PARTITION BY run ORDER BY loss)::INT", "(rank() OVER (PARTITION BY run ORDER BY loss))::INT"))
def win_loss_delta(spark, sf_dir):
    w = Window.partitionBy("run").orderBy("k")
    before = F.lag("loss").over(w)
    d = rows(spark, RUNS, "run string, k int, loss double")
    return d.select("run", "k", F.round(F.col("loss") - before, 6).alias("delta"), F.round((F.col("loss") - before) / before, 6).alias("rel"), F.rank().over(Window.partitionBy("run").orderBy("loss")).alias("rank"), F.ntile(2).over(w).alias("half"))


@query(f"SELECT run, k, loss FROM {_RUNS} QUALIFY row_number() OVER (PARTITION BY run ORDER BY loss, k) <= 2")
def win_topk_config(spark, sf_dir):
    d = rows(spark, RUNS, "run string, k int, loss double")
    return d.withColumn("rn", F.row_number().over(Window.partitionBy("run").orderBy("loss", "k"))).where("rn <= 2").drop("rn")


@query(f"SELECT run, k, loss FROM {_RUNS} ORDER BY loss, run, k LIMIT 3")
def topk_configs(spark, sf_dir):
    return rows(spark, RUNS, "run string, k int, loss double").orderBy("loss", "run", "k").limit(3)


@query(f"SELECT 'all' AS kind, count(*) AS n FROM (SELECT loss FROM {_RUNS} UNION ALL SELECT loss FROM {_RUNS}) UNION ALL SELECT 'distinct', count(*) FROM (SELECT loss FROM {_RUNS} UNION SELECT loss FROM {_RUNS})")
def set_union_traces(spark, sf_dir):
    d = rows(spark, RUNS, "run string, k int, loss double").select("loss")
    both = d.unionByName(d)
    n = lambda df, kind: df.agg(F.count(F.lit(1)).alias("n")).select(F.lit(kind).alias("kind"), "n")
    return n(both, "all").unionByName(n(both.distinct(), "distinct"))


@query(f"{EX} SELECT 0::BIGINT AS common, count(*) FILTER (blk <> {START[0]}) AS others, count(*) FILTER (blk = {START[0]}) AS mine FROM ex")
def set_blocks_disjoint(spark, sf_dir):
    ex = line(spark, sf_dir).select(*LINE_KEY, "blk")
    a, b = ex.where(F.col("blk") == START[0]).drop("blk"), ex.where(F.col("blk") == START[1]).drop("blk")
    rest = ex.drop("blk").exceptAll(a)
    kinds = a.intersect(b).select(F.lit("common").alias("k")).unionByName(rest.select(F.lit("others").alias("k"))).unionByName(a.select(F.lit("mine").alias("k")))
    return kinds.agg(*(F.count(F.when(F.col("k") == k, 1)).alias(k) for k in ("common", "others", "mine")))


@query(f"{EX} SELECT {ID}, round(ln(1 + exp(-abs({_Z}))), 6) AS softplus, round(1 / (1 + exp(-({_Z}))), 6) AS sigmoid, sign({_Z})::DOUBLE AS side FROM ex")
def scalar_math(spark, sf_dir):
    z = dot_wide(X5, W)
    return line(spark, sf_dir).select(*LINE_KEY, F.round(F.log1p(F.exp(-F.abs(z))), 6).alias("softplus"), F.round(1 / (1 + F.exp(-z)), 6).alias("sigmoid"), F.signum(z).alias("side"))


@query("SELECT vec_id, round(list_sum(list_transform(embedding, lambda v: v::DOUBLE * v::DOUBLE)), 5) AS norm FROM embeddings")
def array_dot(spark, sf_dir):
    e = views.table(spark, sf_dir, "embeddings").select("vec_id", F.transform("embedding", lambda v: v.cast("double")).alias("x"))
    return e.select("vec_id", F.round(dot_array("x", F.col("x")), 5).alias("norm"))


@query(f"WITH {_bow_sql()} SELECT doc_id, round(sum(v * (j % 7)), 5) AS dot FROM bow GROUP BY doc_id")
def map_sparse_dot(spark, sf_dir):
    bow = views.v_bow(spark, sf_dir).where(F.size("idx") > 0)
    m = F.map_from_arrays("idx", "val")
    weights = F.map_from_arrays("idx", F.transform("idx", lambda j: (j % 7).cast("double")))
    return bow.select("doc_id", F.round(dot_sparse(m, weights), 5).alias("dot"))


@query(
    """WITH t AS (SELECT doc_id, coalesce(text, '') AS t FROM documents), w AS (SELECT doc_id, t, list_filter(regexp_split_to_array(lower(t), '[ \\t\\n\\x0B\\f\\r]+'), lambda x: x <> '') AS w FROM t)
    SELECT doc_id, round(ln(greatest(length(t), 1) + 1), 6) AS x0, len(w) / 1000.0::DOUBLE AS x1, round(CASE WHEN len(w) > 0 THEN length(array_to_string(w, '')) * 1.0::DOUBLE / len(w) ELSE 0 END, 6) AS x2,
    round(CASE WHEN len(w) > 0 THEN len(list_distinct(w)) * 1.0::DOUBLE / len(w) ELSE 0 END, 6) AS x3, round(length(regexp_replace(t, '[^0-9]', '', 'g')) * 1.0::DOUBLE / greatest(length(t), 1), 6) AS x4 FROM w"""
)
def text_features(spark, sf_dir):
    f = views.text_features(F.col("text"))
    return views.table(spark, sf_dir, "documents").select("doc_id", F.round(f[0], 6).alias("x0"), f[1].alias("x1"), F.round(f[2], 6).alias("x2"), F.round(f[3], 6).alias("x3"), F.round(f[4], 6).alias("x4"))


@query("SELECT month(l_shipdate)::INT AS month, (dayofweek(l_shipdate) + 1)::INT AS dow, hour(l_shipdate)::INT AS hour, count(*) AS n FROM lineitem GROUP BY ALL")
def date_features(spark, sf_dir):
    t = views.table(spark, sf_dir, "lineitem")
    return t.groupBy(F.month("l_shipdate").alias("month"), F.dayofweek("l_shipdate").alias("dow"), F.hour("l_shipdate").alias("hour")).agg(F.count(F.lit(1)).alias("n"))


@query("SELECT event_type, (json_extract_string(props, '$.k')::BIGINT // 10)::BIGINT AS k10, count(*) AS n, round(sum(ln(1 + greatest(value, 0))), 4) AS x0 FROM events GROUP BY ALL")
def json_features(spark, sf_dir):
    k = F.get_json_object("props", "$.k").cast("long")
    return views.table(spark, sf_dir, "events").groupBy("event_type", F.floor(k / 10).alias("k10")).agg(F.count(F.lit(1)).alias("n"), F.round(F.sum(F.log1p(F.greatest("value", F.lit(0.0)))), 4).alias("x0"))


_W = "time_bucket(INTERVAL 6 HOUR, ts, TIMESTAMP '1970-01-01')"
_TOTAL = "count(*) AS n, round(sum(value::DECIMAL(38,12))::DOUBLE, 4) AS total"


@query(f"SELECT {_W} AS start, {_W} + INTERVAL 6 HOUR AS \"end\", {_TOTAL} FROM events GROUP BY 1, 2")
def win_tumbling(spark, sf_dir):
    return online.windowed(views.table(spark, sf_dir, "events"), "tumbling")


@query(f"SELECT s AS start, s + INTERVAL 12 HOUR AS \"end\", {_TOTAL} FROM (SELECT value, unnest([{_W}, {_W} - INTERVAL 6 HOUR]) AS s FROM events) GROUP BY s")
def win_sliding(spark, sf_dir):
    return online.windowed(views.table(spark, sf_dir, "events"), "sliding")


@query(
    f"""WITH g AS (SELECT user_id, ts, value, CASE WHEN ts - lag(ts) OVER w < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
    s AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS sid FROM g) SELECT min(ts) AS start, max(ts) + INTERVAL 6 HOUR AS "end", user_id, {_TOTAL} FROM s GROUP BY user_id, sid"""
)
def win_session(spark, sf_dir):
    return online.windowed(views.table(spark, sf_dir, "events"), "session")


@query(lambda: f"{EX} SELECT m, n, loss FROM (" + " UNION ALL ".join(f"SELECT {m} AS m, count(*) AS n, round(sum({O.loss('svm', O.dot_values(w))}), 4) AS loss FROM ex" for m, w in enumerate(MODELS[:2])) + ")")
def stream_ola_batch(spark, sf_dir):
    """Blocks written as files arrive one trigger after another; the moments at the end are those of a batch."""
    path = shared_dir(spark, "arriving")
    ex = views.v_line(spark, sf_dir, 8).select(*X5, "y", "blk")
    ex.repartition(8, "blk").write.parquet(path)
    m = online.ola_stream(spark, path, ex.schema, MODELS[:2], SVM, 0, files=2)
    return rows(spark, [(i, m.n, round(float(m.loss[i]), 4)) for i in range(2)], "m int, n long, loss double")


@query("WITH e AS (SELECT ts, event_id % 10 = 0 AS held FROM events) SELECT count(*) FILTER (NOT held OR ts > (SELECT max(ts) FROM e WHERE NOT held) - INTERVAL 1 HOUR) AS kept, count(*) AS sent FROM e")
def stream_late_rows(spark, sf_dir):
    """Events replayed in order of time, a tenth of them held back to the end, and then some sent twice: what is left after late rows and repeats go."""
    path, out = shared_dir(spark, "events"), shared_dir(spark, "kept")
    e = views.table(spark, sf_dir, "events")
    held = F.col("event_id") % 10 == 0
    lo, hi = (r for r in e.where(~held).agg(F.min(F.unix_micros(F.col("ts").cast("timestamp"))), F.max(F.unix_micros(F.col("ts").cast("timestamp")))).first())
    quarter = F.least(F.lit(3), F.floor(4 * (F.unix_micros(F.col("ts").cast("timestamp")) - lo) / F.lit(max(1, hi - lo))))
    for k in range(4):  # one file a trigger, in the order in which they are written
        e.where(~held & (quarter == k)).coalesce(1).write.mode("append").parquet(path)
    for more in (e.where(~held & (F.unix_micros(F.col("ts").cast("timestamp")) > hi - 1_800_000_000)), e.where(held)):  # late rows meet the watermark of the batch before the last
        more.coalesce(1).write.mode("append").parquet(path)
    s = spark.readStream.schema(e.schema).option("maxFilesPerTrigger", 1).parquet(path)
    q = online.watermarked(s).writeStream.format("parquet").option("path", out).option("checkpointLocation", shared_dir(spark, "stream")).trigger(availableNow=True).start()
    q.awaitTermination()
    kept = spark.read.parquet(out).agg(F.count(F.lit(1)).alias("kept"))
    return kept.join(e.agg(F.count(F.lit(1)).alias("sent")))


@query()
def stream_user_igd(spark, sf_dir):
    path, out = shared_dir(spark, "events"), shared_dir(spark, "models")
    e = views.event_features(views.table(spark, sf_dir, "events"))
    e.repartition(2).write.parquet(path)
    s = spark.readStream.schema(e.schema).parquet(path)

    def keep(df: DataFrame, batch: int) -> None:
        df.write.mode("append").parquet(out)

    q = online.user_models(s).writeStream.outputMode("update").foreachBatch(keep).option("checkpointLocation", shared_dir(spark, "stream")).trigger(availableNow=True).start()
    q.awaitTermination()
    last = spark.read.parquet(out).groupBy("user_id").agg(F.max("n").alias("n"), F.max_by("w", "n").alias("w"))
    return last.select("user_id", "n", *(F.round(F.col("w")[j], 6).alias(f"w{j}") for j in range(6)))


@query(f"{EX} SELECT {ID}, round(y * ({_Z}), 6) + 0.0 AS margin FROM ex")
def udf_margin(spark, sf_dir):
    return line(spark, sf_dir).select(*LINE_KEY, r(udx.margin_udf(W)("y", *X5), 6).alias("margin"))


@query("SELECT event_type, count(value) AS n, round(sum(value), 4) AS s1, round(sum(value * value), 3) AS s2 FROM events GROUP BY event_type")
def udaf_moments(spark, sf_dir):
    m = udx.moments_udaf(views.table(spark, sf_dir, "events"), "event_type", "value")
    return m.select("event_type", "n", F.round("s1", 4).alias("s1"), F.round("s2", 3).alias("s2"))


@query("SELECT * FROM (VALUES (0, 0.01::DOUBLE), (1, 0.1), (2, 0.001), (3, 1.0), (4, 0.0001)) t(i, alpha)")
def udtf_grid(spark, sf_dir):
    udx.register_udtf(spark)
    return spark.sql("SELECT i, round(alpha, 9) AS alpha FROM step_grid(5, 0.01D, 10.0D)")


@query(f"{EX} SELECT count(*) AS n, round(sum({O.loss('svm', _Z)}), 4) AS svm, round(sum({O.loss('lr', _Z)}), 4) AS lr FROM ex")
def sql_loss(spark, sf_dir):
    udx.register_sql(spark)
    line(spark, sf_dir).createOrReplaceTempView("calib_examples")
    dot = " + ".join(f"x{j} * {w!r}D" for j, w in enumerate(W))
    return spark.sql(f"SELECT count(*) AS n, round(sum(svm_loss({dot}, y)), 4) AS svm, round(sum(lr_loss({dot}, y)), 4) AS lr FROM calib_examples")


@query("SELECT 1000::BIGINT AS n, 125::BIGINT AS mine, 2::BIGINT AS labels")
def separable_source(spark, sf_dir):
    formats.register(spark)
    load = lambda: spark.read.format("separable").options(rows="1000", dims="6", blocks="8").load()
    df, mine = load(), load().where("blk = 3").agg(F.count(F.lit(1)).alias("mine"))
    return df.agg(F.count(F.lit(1)).alias("n"), F.countDistinct("y").alias("labels")).join(mine).select("n", "mine", "labels")


@query("SELECT count(*) AS rows, 0::BIGINT AS bad, 0::BIGINT AS labels FROM lineitem")
def view_check(spark, sf_dir):
    c = views.check(line(spark, sf_dir), 5)
    return rows(spark, [(c["rows"], c["bad"], c["labels"])], "rows long, bad long, labels long")


@query("SELECT count(DISTINCT md5(trim(regexp_replace(lower(coalesce(text, '')), '[ \\t\\n\\x0B\\f\\r]+', ' ', 'g')))) AS texts, count(*) AS n FROM documents")
def exact_dedup_texts(spark, sf_dir):
    """Cleaning of the text views: documents of one normalised text count once."""
    t = F.md5(F.trim(F.regexp_replace(F.lower(F.coalesce("text", F.lit(""))), r"[ \t\n\x0B\f\r]+", " ")))
    g = views.table(spark, sf_dir, "documents").groupBy(t.alias("t")).agg(F.count(F.lit(1)).alias("n"))
    return g.agg(F.count(F.lit(1)).alias("texts"), F.sum("n").alias("n"))
