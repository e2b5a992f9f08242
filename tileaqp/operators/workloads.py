"""The experiments as queries: per-query metrics and their summaries, at the size of the table they are given."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession, Window, functions as F

from ..functions import sqlapi
from ..plans import metrics
from ..plans.engine import evaluate
from ..plans.model import RESULT_SCHEMA, Agg, AxisSpec, SamplingPolicy, Viewport, ViewportQuery
from ..plans.workload import ExplorationSession, Setting, as_queries, centre_window, make_path, make_zooms, metrics_frame, run_workload, switch_attribute, workload_frame
from ..plans.index import domain_of
from ..sources.tables import load_table, wide_rows, with_uniform
from ..streaming import events as streams
from .methods import BOX, IDENTITY, OBJECTS_SQL, WINDOW, index, objects
from .registry import query

STEPS = 10


def setting(spark: SparkSession, sf: str, name: str = "uniform") -> Setting:
    """The tables that stand for the paper's files, at a tenth of the domain per window."""
    t = lambda n: load_table(spark, sf, n)
    rows = t("lineitem").count()
    small = dict(grid=(4, 4), side=0.5, split_min=40) if rows < 20_000 else dict(grid=(10, 10), side=0.316, split_min=40 if rows < 200_000 else 200)
    key = [*IDENTITY, "l_shipdate", "l_extendedprice"]
    if name == "uniform":
        return Setting(t("lineitem"), AxisSpec("l_extendedprice", "l_shipdate"), key, ["l_quantity"], **small)
    if name == "wide":
        return Setting(wide_rows(spark, sf), AxisSpec("l_extendedprice", "l_shipdate"), key, ["l_quantity"], **small)
    if name == "dense":
        return Setting(t("lineitem"), AxisSpec("l_extendedprice * l_discount", "l_quantity * l_tax"), key, ["l_quantity"], start=(0.2, 0.2), **small)
    if name == "low_variance":
        return Setting(t("part"), AxisSpec("p_partkey", "p_size"), ["p_partkey"], ["p_retailprice"], **small)
    if name == "heavy_tail":
        return Setting(t("events"), AxisSpec("ts", "user_id"), ["event_id"], ["value"], **small)
    if name == "lattice":
        return Setting(t("lineitem"), AxisSpec("l_discount", "l_tax"), key, ["l_extendedprice"], **small)
    if name == "clustered":
        e = t("embeddings").select("vec_id", *(F.element_at("embedding", i).cast("double").alias(f"e{i}") for i in (1, 2, 3)))
        return Setting(e, AxisSpec("e1", "e2"), ["vec_id"], ["e3"], **small)
    if name == "correlated":
        return Setting(t("documents").select("doc_id", "n_chars"), AxisSpec("doc_id", "ln(n_chars + 1)"), ["doc_id"], ["n_chars"], **small)
    if name == "negative":
        return Setting(t("customer"), AxisSpec("c_custkey", "c_nationkey"), ["c_custkey"], ["c_acctbal"], **small)
    if name == "medium":
        return Setting(t("orders"), AxisSpec("o_orderdate", "o_custkey"), ["o_orderkey"], ["o_totalprice"], **small)
    raise ValueError(name)


def path_queries(s: Setting, fn: str = "sum", eps: float = 0.05, steps: int = STEPS, **path) -> list[ViewportQuery]:
    domain = domain_of(s.df, s.axes, s.grid).box
    windows = make_path(domain, centre_window(domain, s.side, s.start), steps, **path)
    return as_queries(windows, (Agg(fn, s.attrs[0]),), eps)


def metrics_of(spark: SparkSession, sf: str, name: str = "uniform", fn: str = "sum", eps: float = 0.05, methods=("ATI", "ETI", "STI"), policy: SamplingPolicy | None = None, steps: int = STEPS, **path) -> DataFrame:
    s = setting(spark, sf, name)
    return metrics_frame(spark, run_workload(s, path_queries(s, fn, eps, steps, **path), methods, policy))


for _id, _name, _kw in (
    ("w01_uniform_path", "uniform", {"eps": 0.01}), ("w02_wide_rows", "wide", {"eps": 0.01}), ("w03_dense_spot", "dense", {}), ("w04_low_variance", "low_variance", {}),
    ("w08_mean", "uniform", {"fn": "mean"}), ("w14_heavy_tail", "heavy_tail", {}), ("w15_unseen_area", "uniform", {"jump_at": 5}),
    ("w01_lattice", "lattice", {}), ("w01_clustered_zero_mean", "clustered", {"fn": "mean", "eps": 0.1}), ("w01_correlated", "correlated", {}), ("w01_negative", "negative", {"fn": "mean", "eps": 0.1}), ("w01_medium", "medium", {}),
):
    query(_id)(lambda spark, sf, name=_name, kw=_kw: metrics_of(spark, sf, name, **kw))


@query("w05_bound_sweep")
def w05(spark, sf):
    out = None
    for eps in (0.10, 0.05, 0.02, 0.01):
        m = metrics.totals(metrics_of(spark, sf, eps=eps, steps=6))
        out = m if out is None else out.unionByName(m)
    return out


@query("w06_accuracy_sweep")
def w06(spark, sf):
    out = None
    for eps in (0.10, 0.05, 0.02, 0.01):
        m = metrics.bound_compliance(metrics_of(spark, sf, eps=eps, methods=("ATI",), steps=6))
        out = m if out is None else out.unionByName(m)
    return out


@query("w07_coverage")
def w07(spark, sf):
    return metrics.coverage(metrics_of(spark, sf, eps=0.01, methods=("ATI", "STI")))


@query("w09_region_with_zooms")
def w09(spark, sf):
    s = setting(spark, sf)
    domain = domain_of(s.df, s.axes, s.grid).box
    ops = make_zooms(domain, centre_window(domain, s.side / 1.5), 1)
    return metrics_frame(spark, run_workload(s, as_queries(ops, (Agg("sum", "l_quantity"),), 0.05), ("ATI", "STI")))


@query("w10_average_and_maximum")
def w10(spark, sf):
    """Two aggregates for each window, a loose bound first and then a tight one."""
    ix, _ = index(spark, sf)
    session = ExplorationSession(ix, WINDOW, (Agg("mean", "l_quantity"), Agg("max", "l_quantity")), 0.10)
    return session.run([("query",), ("pan", 0.1, 0.0), ("pan", 0.1, 0.1), ("bound", 0.01), ("query",)])


@query("w11_new_attribute")
def w11(spark, sf):
    ix, _ = index(spark, sf)
    qs = switch_attribute(as_queries(make_path(BOX, WINDOW, 6), (Agg("sum", "l_quantity"),), 0.05), 3, "l_tax")
    out = [evaluate(ix, q) for q in qs]
    return spark.createDataFrame([r for o in out for r in o.rows()], RESULT_SCHEMA)


@query("w12_ablations")
def w12(spark, sf):
    """Reads and rounds of the engine with parts of it off, over the same path."""
    s = setting(spark, sf)
    queries = path_queries(s, eps=0.02, steps=5)
    base = s.index_config()
    cases = {
        "full": (base, SamplingPolicy()), "no_splits": (replace(base, adapt=False), SamplingPolicy()), "no_reuse": (base, SamplingPolicy(reuse=False)), "flat": (replace(base, init="flat"), SamplingPolicy()),
        "one_pool": (replace(base, adapt=False), SamplingPolicy(reuse=False, strata="single")), "fixed_step": (base, SamplingPolicy(kind="fixed_step", cap=1.3)), "fpc_aware": (base, SamplingPolicy(kind="fpc_aware")),
        "all_overlapping": (replace(base, split_scope="all_overlapping"), SamplingPolicy()), "expected_reuse": (replace(base, gain="expected_reuse"), SamplingPolicy()), "two_levels": (replace(base, depth_per_query=2), SamplingPolicy()),
    }
    rows = []
    for name, (config, policy) in cases.items():
        got = run_workload(replace(s, config=config), queries, ("ATI",), policy)
        later = [r for r in got if r["query_id"]]
        rows.append((name, sum(r["io_ops"] for r in later), sum(r["rounds"] for r in later), max(r["rel_err"] or 0.0 for r in later)))
    return spark.createDataFrame(rows, "variant string, io_total long, rounds long, max_rel_err double")


@query("c10_speedup")
def c10(spark, sf):
    m = metrics_of(spark, sf, eps=0.02)
    return metrics.speedup(m, "STI").unionByName(metrics.speedup(m, "ETI"))


@query("m05_session")
def m05(spark, sf):
    ix, _ = index(spark, sf)
    return ExplorationSession(ix, WINDOW, (Agg("sum", "l_quantity"),), 0.05).run([("query",), ("pan", 0.1, 0.0), ("zoom", 0.5), ("pan", 0.0, 0.1), ("zoom", 2.0)])


@query("workload_rows", "SELECT i::INTEGER AS query_id, round(36500 + 3290 * i, 4)::DOUBLE AS x1 FROM range(5) g(i)")
def workload_rows(spark, sf):
    qs = as_queries([Viewport(36500.0 + 3290 * i, 69400.0 + 3290 * i, WINDOW.y1, WINDOW.y2) for i in range(5)], (Agg("count"),), 0.05)
    return workload_frame(spark, qs).select("query_id", F.round("x1", 4).alias("x1"))


@query("s10_generated_uniform")
def s10(spark, sf):
    """Three uniform attributes made up for every line item."""
    rows = with_uniform(load_table(spark, sf, "lineitem").select(*IDENTITY), IDENTITY, 3)
    return rows.agg(F.count("*").alias("n"), *(F.round(F.avg(f"a{i}"), 3).alias(f"mean{i}") for i in range(3)), F.max("a0").alias("top"))


@query("u01_sql_functions", f"WITH {OBJECTS_SQL} SELECT root, count(*) AS n FROM o GROUP BY root")
def u01(spark, sf):
    from ..plans.geometry import Domain

    sqlapi.register_functions(spark, Domain(BOX, 10, 10))
    objects(spark, sf).createOrReplaceTempView("_u01_objects")
    return spark.sql("SELECT tile_root(ax, ay) AS root, count(*) AS n FROM _u01_objects GROUP BY 1")


@query("u02_quantile_functions")
def u02(spark, sf):
    """Quantiles at the middle rank of every quantity, as a share of all line items."""
    sqlapi.register_functions(spark)
    counts = load_table(spark, sf, "lineitem").groupBy("l_quantity").agg(F.count("*").alias("n"))  # fifty quantities, whatever the scale
    below, every = Window.orderBy("l_quantity").rowsBetween(Window.unboundedPreceding, 0), Window.partitionBy()
    shares = counts.select("l_quantity", ((F.sum("n").over(below) - F.col("n") / 2) / F.sum("n").over(every)).alias("p"))
    return shares.select("l_quantity", "p", F.expr("norm_quantile(p)").alias("z"), F.expr("chi2_quantile(p, 10.0D)").alias("chi2"))


@query("u03_grouped_moments", f"WITH {OBJECTS_SQL} SELECT root, count(*) AS n, round(avg(l_quantity), 6) AS mean, round(var_pop(l_quantity) * count(*) + 0.00012345, 3) AS m2 FROM o GROUP BY root")
def u03(spark, sf):
    got = sqlapi.moments_by_group(objects(spark, sf), "root", "l_quantity")
    return got.select("root", "n", F.round("mean", 6).alias("mean"), F.round(F.col("m2") + 0.00012345, 3).alias("m2"))


@query("u04_table_functions")
def u04(spark, sf):
    ix, _ = index(spark, sf)
    sqlapi.register_index(spark, "lineitem", ix)
    w = WINDOW
    return spark.sql(f"SELECT * FROM lineitem_window({w.x1}D, {w.x2}D, {w.y1}D, {w.y2}D, 'l_quantity', 0.95D)")


@query("u05_window_statement")
def u05(spark, sf):
    ix, _ = index(spark, sf)
    w = WINDOW
    return sqlapi.sql(ix, f"SELECT sum(l_quantity), avg(l_quantity), count(*) WINDOW X BETWEEN {w.x1} AND {w.x2} Y BETWEEN {w.y1} AND {w.y2} ERROR 5% CONFIDENCE 95%")


def _events(spark: SparkSession, sf: str) -> DataFrame:
    return load_table(spark, sf, "events").withColumn("ts", F.col("ts").cast("timestamp"))


@query("t03_tumbling_windows", "SELECT epoch(time_bucket(INTERVAL 1 HOUR, ts))::BIGINT AS start, event_type, count(*) AS n, round(sum(value), 2) AS total FROM events GROUP BY ALL")
def t03(spark, sf):
    got = streams.windowed_counts(_events(spark, sf), "tumbling")
    return got.select(F.unix_seconds("start").alias("start"), "event_type", "n", F.round("total", 2).alias("total"))


@query("t03_sliding_windows", "SELECT (epoch(time_bucket(INTERVAL 15 MINUTE, ts))::BIGINT - 900 * i)::BIGINT AS start, event_type, count(*) AS n FROM events, range(4) g(i) GROUP BY ALL")
def t03b(spark, sf):
    got = streams.windowed_counts(_events(spark, sf), "sliding")
    return got.select(F.unix_seconds("start").alias("start"), "event_type", "n")


@query("t03_session_windows", "WITH g AS (SELECT *, CASE WHEN lag(ts) OVER w IS NULL OR ts - lag(ts) OVER w > INTERVAL 30 MINUTE THEN 1 ELSE 0 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), s AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g) SELECT user_id, floor(epoch(min(ts)))::BIGINT AS start, count(*) AS n FROM s GROUP BY user_id, k")
def t03c(spark, sf):
    got = streams.windowed_counts(_events(spark, sf), "session")
    return got.select("user_id", F.unix_seconds("start").alias("start"), "n")


@query("t06_interval_join", "SELECT v.user_id AS user_id, v.event_id AS view_id, c.event_id AS click_id FROM events v JOIN events c ON v.user_id = c.user_id AND c.ts BETWEEN v.ts AND v.ts + INTERVAL 10 MINUTE WHERE v.event_type = 'view' AND c.event_type = 'click'")
def t06(spark, sf):
    return streams.views_then_clicks(_events(spark, sf))


@query("t06_stream_static_join", "SELECT event_id, c_mktsegment FROM events LEFT JOIN customer ON user_id = c_custkey")
def t06b(spark, sf):
    return streams.with_customer(_events(spark, sf), load_table(spark, sf, "customer")).select("event_id", "c_mktsegment")


def smoke(spark: SparkSession, folder: str) -> DataFrame:
    """Ten steps of the path over uniform objects, with the bound of 5%."""
    s = setting(spark, folder)
    return metrics_frame(spark, run_workload(s, path_queries(s, steps=10), ("ATI",)))
