"""The methods, baselines and measures as queries over the given tables.

The objects are line items placed by price and shipping day on a grid of ten by ten over
a fixed domain; draws use the portable key, so that SQL can make them as well.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window, functions as F

from ..functions.quantiles import two_sided_z
from ..plans.baselines import ExactTileIndex, SampleOnlyIndex, StaticGrid, full_scan, strata_frame
from ..plans.engine import count_window, evaluate, evaluate_progressive, next_rate, plan_strata, window_objects
from ..plans.estimators import estimates
from ..plans.geometry import CELL_BITS, Domain, classify_columns
from ..plans.index import bind_objects, build_index, status_column
from ..plans.model import LEVELS, Agg, AxisSpec, IndexConfig, SamplingPolicy, Viewport, ViewportQuery
from ..sources.tables import load_table
from .registry import query

AXES = AxisSpec("l_extendedprice", "l_shipdate")
IDENTITY = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey"]
BOX = Viewport(900.0, 105000.0, 9132.0, 11631.0)
GRID = (10, 10)
WINDOW = Viewport(36500.0, 69400.0, 9986.0, 10776.0)
RATE_KEY = 115292150460684697  # a tenth of the key space
Z95 = two_sided_z(0.95)


def objects(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bind_objects(load_table(spark, sf_dir, "lineitem"), AXES, IDENTITY, ["l_quantity", "l_tax"], Domain(BOX, *GRID), 7, True)


def index(spark: SparkSession, sf_dir: str, attrs: tuple[str, ...] = ("l_quantity",), config: IndexConfig | None = None, q0: ViewportQuery | None = None):
    config = config or IndexConfig(grid=GRID, split_min=40, portable_key=True)
    rows = objects(spark, sf_dir)
    return build_index(rows, AxisSpec("ax", "ay"), [], list(attrs), config, q0, Domain(BOX, *GRID), objects=rows)


def the_query(fn: str = "sum", eps: float = 0.05, attr: str = "l_quantity") -> ViewportQuery:
    return ViewportQuery(WINDOW, (Agg(fn, None if fn == "count" else attr),), eps)


def _cell(v: str, lo: float, hi: float, n: int) -> str:
    """SQL of the integer coordinate of a value, set right against the bounds."""
    edge = lambda k: f"({lo!r}::DOUBLE + {hi - lo!r}::DOUBLE * (({k})::DOUBLE / {float(n)!r}::DOUBLE))"
    j = f"least({n - 1}, greatest(0, floor(({v} - {lo!r}::DOUBLE) / {hi - lo!r}::DOUBLE * {float(n)!r}::DOUBLE)::BIGINT))"
    return f"(CASE WHEN {v} < {edge(j)} AND {j} > 0 THEN {j} - 1 WHEN {v} >= {edge(f'{j} + 1')} AND {j} < {n - 1} THEN {j} + 1 ELSE {j} END)"


_N = GRID[0] << LEVELS
_BITS = lambda j, at: " + ".join(f"((({j} >> {i}) & 1) << {2 * i + at})" for i in range(LEVELS))
OBJECTS_SQL = f"""
  raw AS (SELECT *, l_extendedprice::DOUBLE AS ax, epoch_us(l_shipdate) / 8.64e10 AS ay FROM lineitem),
  placed AS (SELECT *, {_cell("ax", BOX.x1, BOX.x2, _N)} AS jx, {_cell("ay", BOX.y1, BOX.y2, _N)} AS jy FROM raw
             WHERE ax BETWEEN {BOX.x1} AND {BOX.x2} AND ay BETWEEN {BOX.y1} AND {BOX.y2}),
  o AS (SELECT *, ((jy >> {LEVELS}) * {GRID[0]} + (jx >> {LEVELS}))::INTEGER AS root,
               ({_BITS(f"(jx & {(1 << LEVELS) - 1})", 0)} + {_BITS(f"(jy & {(1 << LEVELS) - 1})", 1)})::BIGINT AS zcode,
               ('0x' || substr(md5('s7|' || l_orderkey || '|' || l_linenumber || '|' || l_partkey || '|' || l_suppkey), 1, 15))::BIGINT AS rkey
        FROM placed)"""
IN_WINDOW = f"ax BETWEEN {WINDOW.x1} AND {WINDOW.x2} AND ay BETWEEN {WINDOW.y1} AND {WINDOW.y2}"
_W, _H = BOX.width / GRID[0], BOX.height / GRID[1]
TILES_SQL = f"""
  t AS (SELECT r::INTEGER AS root, {BOX.x1} + {BOX.width} * ((r % {GRID[0]}) * {1 << LEVELS}.0 / {_N}.0) AS x_lo, {BOX.x1} + {BOX.width} * ((r % {GRID[0]} + 1) * {1 << LEVELS}.0 / {_N}.0) AS x_hi,
               {BOX.y1} + {BOX.height} * ((r // {GRID[0]}) * {1 << LEVELS}.0 / {_N}.0) AS y_lo, {BOX.y1} + {BOX.height} * ((r // {GRID[0]} + 1) * {1 << LEVELS}.0 / {_N}.0) AS y_hi
        FROM range({GRID[0] * GRID[1]}) AS g(r))"""
STRATA_SQL = f"""
  strata AS (SELECT root, count(*) AS pop, count(*) FILTER (rkey < {RATE_KEY}) AS n, avg(l_quantity) FILTER (rkey < {RATE_KEY}) AS mean, var_samp(l_quantity) FILTER (rkey < {RATE_KEY}) AS s2
             FROM o WHERE {IN_WINDOW} GROUP BY root)"""
EST_SQL = f"""
  est AS (SELECT sum(pop)::BIGINT AS pop, sum(n)::BIGINT AS n, sum(pop * mean) AS sum_est, sum(CASE WHEN n < pop THEN pop::DOUBLE * pop * s2 / n * (1 - n::DOUBLE / pop) ELSE 0 END) AS sum_var FROM strata)"""


def strata(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A stratum per cell of the window: population, and the sample at a tenth."""
    drawn = lambda f: f(F.when(F.col("rkey") < RATE_KEY, F.col("l_quantity")))
    rows = objects(spark, sf_dir).filter(WINDOW.condition())
    return rows.groupBy("root").agg(F.count("*").alias("pop"), drawn(F.count).alias("n"), drawn(F.avg).alias("mean"), drawn(F.var_samp).alias("s2"))


def _estimates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return estimates(strata(spark, sf_dir), [], Z95)


@query("m01_axis_binding", f"WITH {OBJECTS_SQL} SELECT l_orderkey, l_linenumber, l_partkey, l_suppkey, ax, ay FROM raw")
def m01(spark, sf):
    df = load_table(spark, sf, "lineitem")
    x, y = AXES.columns(df)
    return df.select(*IDENTITY, x.alias("ax"), y.alias("ay"))


@query("m02_viewport_pixels", f"WITH {OBJECTS_SQL} SELECT floor((ax - {WINDOW.x1}) * (800 / {WINDOW.width}::DOUBLE))::BIGINT AS px, floor(({WINDOW.y2} - ay) * (600 / {WINDOW.height}::DOUBLE))::BIGINT AS py, count(*) AS n FROM raw WHERE {IN_WINDOW} GROUP BY ALL")
def m02(spark, sf):
    px, py = WINDOW.to_pixels(F.col("ax"), F.col("ay"), 800, 600)
    return objects(spark, sf).filter(WINDOW.condition()).groupBy(F.floor(px).alias("px"), F.floor(py).alias("py")).agg(F.count("*").alias("n"))


#: The window around the line items of each order.
ORDER_WINDOWS_SQL = """
  w AS (SELECT l_orderkey AS query_id, min(l_extendedprice)::DOUBLE AS x1, max(l_extendedprice)::DOUBLE AS x2, min(epoch_us(l_shipdate) / 8.64e10)::DOUBLE AS y1, max(epoch_us(l_shipdate) / 8.64e10)::DOUBLE AS y2
        FROM lineitem WHERE l_orderkey IS NOT NULL AND l_extendedprice IS NOT NULL AND l_shipdate IS NOT NULL GROUP BY l_orderkey)"""
SIDES = ("x1", "x2", "y1", "y2")


def order_windows(spark: SparkSession, sf_dir: str) -> DataFrame:
    df = load_table(spark, sf_dir, "lineitem")
    x, y = AXES.columns(df)
    placed = df.select(F.col("l_orderkey").alias("query_id"), x.alias("x"), y.alias("y")).dropna()
    return placed.groupBy("query_id").agg(F.min("x").alias("x1"), F.max("x").alias("x2"), F.min("y").alias("y1"), F.max("y").alias("y2"))


def _moved(windows: DataFrame, move) -> DataFrame:
    v = move(Viewport(*(F.col(c) for c in SIDES)))
    return windows.select("query_id", *(getattr(v, c).alias(c) for c in SIDES))


@query("m03_pan", f"WITH {ORDER_WINDOWS_SQL} SELECT query_id, x1 + 0.1::DOUBLE * (x2 - x1) AS x1, x2 + 0.1::DOUBLE * (x2 - x1) AS x2, y1 + -0.05::DOUBLE * (y2 - y1) AS y1, y2 + -0.05::DOUBLE * (y2 - y1) AS y2 FROM w")
def m03(spark, sf):
    """The window of every order, moved by shares of its sides."""
    return _moved(order_windows(spark, sf), lambda v: v.pan(0.1, -0.05))


_ZOOMED = lambda a, b, c: f"({a} + {b}) / 2.0::DOUBLE + ({c} - ({a} + {b}) / 2.0::DOUBLE) * 0.5::DOUBLE AS {c}"


@query("m04_zoom", f"WITH {ORDER_WINDOWS_SQL} SELECT query_id, {_ZOOMED('x1', 'x2', 'x1')}, {_ZOOMED('x1', 'x2', 'x2')}, {_ZOOMED('y1', 'y2', 'y1')}, {_ZOOMED('y1', 'y2', 'y2')} FROM w")
def m04(spark, sf):
    """The window of every order, half as wide around its centre."""
    return _moved(order_windows(spark, sf), lambda v: v.zoom(0.5))


@query("m06_window_selection", f"WITH {OBJECTS_SQL} SELECT ax, ay, rkey FROM o WHERE {IN_WINDOW}")
def m06(spark, sf):
    return objects(spark, sf).filter(WINDOW.condition()).select("ax", "ay", "rkey")


_METADATA_SQL = f"WITH {OBJECTS_SQL} SELECT root, count(*) AS n_objects, sum(l_quantity)::BIGINT AS total, min(l_quantity)::BIGINT AS low, max(l_quantity)::BIGINT AS high, round(avg(l_quantity), 6) AS mean, round(var_pop(l_quantity) * count(*) + 0.00012345, 3) AS m2 FROM o GROUP BY root"


@query("m07_flat_metadata", _METADATA_SQL)
def m07(spark, sf):
    ix, _ = index(spark, sf)
    t, s = ix.tiles_frame(), ix.stats_frame()
    rows = t.join(s, "tile_id").filter("n_objects > 0")
    return rows.select("root", "n_objects", F.round("sum").cast("long").alias("total"), F.col("min").cast("long").alias("low"), F.col("max").cast("long").alias("high"), F.round("mean", 6).alias("mean"), F.round(F.col("m2") + 0.00012345, 3).alias("m2"))


_EXACT_SQL = f"WITH {OBJECTS_SQL} SELECT sum(l_quantity)::BIGINT AS total, count(*) AS pop FROM o WHERE {IN_WINDOW}"


def _exact(spark, r) -> DataFrame:
    return spark.createDataFrame([(round(r.answers[0].estimate), r.pop)], "total long, pop long")


@query("m08_first_query_in_the_pass", _EXACT_SQL)
def m08(spark, sf):
    return _exact(spark, index(spark, sf, q0=the_query())[1])


@query("m09_query_driven_layout", f"WITH {OBJECTS_SQL} SELECT sum(l_quantity)::BIGINT AS total, count(*) AS pop, 18::BIGINT AS extra_tiles FROM o WHERE {IN_WINDOW}")
def m09(spark, sf):
    """A fifth more tiles around the first window, which is then answered exactly from them."""
    ix, _ = index(spark, sf, config=IndexConfig(grid=GRID, init="query_driven", split_min=40), q0=the_query())
    extra = len(ix.leaves()) - GRID[0] * GRID[1]
    r = evaluate(ix, the_query(eps=0.0))
    return _exact(spark, r).withColumn("extra_tiles", F.lit(extra).cast("long"))


@query("m10_leaf_of_each_object", f"WITH {OBJECTS_SQL} SELECT root, zcode, count(*) AS n FROM o GROUP BY ALL")
def m10(spark, sf):
    return objects(spark, sf).groupBy("root", "zcode").agg(F.count("*").alias("n"))


_CONTAIN = f"CASE WHEN x_lo >= {WINDOW.x1} AND x_hi <= {WINDOW.x2} AND y_lo >= {WINDOW.y1} AND y_hi <= {WINDOW.y2} THEN 'full' WHEN x_lo <= {WINDOW.x2} AND x_hi >= {WINDOW.x1} AND y_lo <= {WINDOW.y2} AND y_hi >= {WINDOW.y1} THEN 'partial' ELSE 'disjoint' END"


@query("m11_containment", f"WITH {TILES_SQL} SELECT root, {_CONTAIN} AS kind FROM t")
def m11(spark, sf):
    ix, _ = index(spark, sf)
    return ix.tiles_frame().select("root", classify_columns(WINDOW).alias("kind"))


@query("m12_pruned_leaves", f"WITH {OBJECTS_SQL}, {TILES_SQL} SELECT root, {_CONTAIN} AS kind, n AS pop FROM t JOIN (SELECT root, count(*) AS n FROM o WHERE {IN_WINDOW} GROUP BY root) USING (root) WHERE n > 0")
def m12(spark, sf):
    ix, _ = index(spark, sf, config=IndexConfig(grid=GRID, adapt=False, portable_key=True))
    s = plan_strata(ix, the_query(), SamplingPolicy())
    return spark.createDataFrame([(ix.tiles[x.tile_id].root, x.kind, x.pop) for x in s], "root int, kind string, pop long")


@query("m13_status", f"WITH {OBJECTS_SQL}, {STRATA_SQL} SELECT root, CASE WHEN n = pop THEN 'exact' WHEN n > 0 THEN 'approximate' ELSE 'not_available' END AS status FROM strata")
def m13(spark, sf):
    return strata(spark, sf).select("root", status_column(F.col("n"), F.col("pop")).alias("status"))


@query("m14_m17_cases", None)
def m14(spark, sf):
    """Cases of all strata on three following windows."""
    ix, _ = index(spark, sf)
    rows = []
    for i in range(3):
        q = ViewportQuery(WINDOW.pan(0.1 * i, 0), (Agg("sum", "l_quantity"),), 0.05, query_id=i)
        rows += [(i, s.tile_id, s.kind, s.case, s.pop) for s in plan_strata(ix, q, SamplingPolicy())]
        evaluate(ix, q)
    return spark.createDataFrame(rows, "query_id int, tile_id long, kind string, `case` int, pop long")


@query("m18_count_window", f"WITH {OBJECTS_SQL} SELECT count(*) AS n FROM o WHERE {IN_WINDOW}")
def m18(spark, sf):
    return spark.createDataFrame([(count_window(index(spark, sf)[0], WINDOW),)], "n long")


@query("m19_incremental_draw", f"WITH {OBJECTS_SQL} SELECT root, count(*) AS n, sum(l_quantity)::BIGINT AS total FROM o WHERE rkey >= {RATE_KEY} AND rkey < {2 * RATE_KEY} GROUP BY root")
def m19(spark, sf):
    rows = objects(spark, sf).filter(F.col("rkey").between(RATE_KEY, 2 * RATE_KEY - 1))
    return rows.groupBy("root").agg(F.count("*").alias("n"), F.sum("l_quantity").cast("long").alias("total"))


@query("m20_bitmaps", f"WITH {OBJECTS_SQL} SELECT root, count(*) FILTER (rkey < {RATE_KEY})::BIGINT AS n_read, count(*) AS n_objects FROM o GROUP BY root")
def m20(spark, sf):
    w = Window.partitionBy("root").orderBy("rkey")
    rows = objects(spark, sf).withColumn("pos", F.row_number().over(w).cast("long"))
    bits = rows.groupBy("root", F.bitmap_bucket_number("pos").alias("b")).agg(F.bitmap_construct_agg(F.when(F.col("rkey") < RATE_KEY, F.bitmap_bit_position("pos"))).alias("m"), F.count("*").alias("n"))
    return bits.groupBy("root").agg(F.sum(F.bitmap_count("m")).alias("n_read"), F.sum("n").alias("n_objects"))


@query("m22_merged_moments", f"WITH {OBJECTS_SQL} SELECT root, count(*) AS n, round(avg(l_quantity), 6) AS mean, round(var_pop(l_quantity) * count(*) + 0.00012345, 3) AS m2 FROM o GROUP BY root")
def m22(spark, sf):
    """Two batches of draws merged by the pairwise formula."""
    batch = F.when(F.col("rkey") < 3 * RATE_KEY, "a").otherwise("b")
    rows = objects(spark, sf).groupBy("root", batch.alias("batch")).agg(F.count("*").alias("n"), F.avg("l_quantity").alias("mean"), (F.var_pop("l_quantity") * F.count("*")).alias("m2"))
    v = rows.groupBy("root").pivot("batch", ["a", "b"]).agg(F.first("n").alias("n"), F.first("mean").alias("mean"), F.first("m2").alias("m2")).na.fill(0)
    n, d = F.col("a_n") + F.col("b_n"), F.col("b_mean") - F.col("a_mean")
    mean = F.when(F.col("a_n") == 0, F.col("b_mean")).when(F.col("b_n") == 0, F.col("a_mean")).otherwise(F.col("a_mean") + d * F.col("b_n") / n)
    m2 = F.col("a_m2") + F.col("b_m2") + F.when((F.col("a_n") > 0) & (F.col("b_n") > 0), d * d * F.col("a_n") * F.col("b_n") / n).otherwise(0.0)
    return v.select("root", n.alias("n"), F.round(mean, 6).alias("mean"), F.round(m2 + 0.00012345, 3).alias("m2"))


@query("m24_sum_fixed_rate", f"WITH {OBJECTS_SQL}, {STRATA_SQL}, {EST_SQL} SELECT pop, n, round(sum_est, 4) AS sum_est FROM est")
def m24(spark, sf):
    return _estimates(spark, sf).select("pop", F.col("n_sampled").alias("n"), F.round("sum_est", 4).alias("sum_est"))


@query("m25_mean_fixed_rate", f"WITH {OBJECTS_SQL}, {STRATA_SQL}, {EST_SQL} SELECT round(sum_est / pop, 6) AS mean_est FROM est")
def m25(spark, sf):
    return _estimates(spark, sf).select(F.round("mean_est", 6).alias("mean_est"))


@query("m26_count_exact", f"WITH {OBJECTS_SQL}, {STRATA_SQL} SELECT sum(pop)::BIGINT AS pop FROM strata")
def m26(spark, sf):
    return strata(spark, sf).agg(F.sum("pop").alias("pop"))


@query("m27_stratum_variance", f"WITH {OBJECTS_SQL}, {STRATA_SQL} SELECT root, n, round(s2, 6) AS s2 FROM strata")
def m27(spark, sf):
    return strata(spark, sf).select("root", "n", F.round("s2", 6).alias("s2"))


@query("m28_variance_of_sum", f"WITH {OBJECTS_SQL}, {STRATA_SQL}, {EST_SQL} SELECT round(sum_var, 2) AS sum_var FROM est")
def m28(spark, sf):
    return _estimates(spark, sf).select(F.round("sum_var", 2).alias("sum_var"))


@query("m29_variance_of_mean", f"WITH {OBJECTS_SQL}, {STRATA_SQL}, {EST_SQL} SELECT round(sum_var / (pop::DOUBLE * pop), 8) AS mean_var FROM est")
def m29(spark, sf):
    return _estimates(spark, sf).select(F.round("mean_var", 8).alias("mean_var"))


@query("m30_finite_population", f"WITH {OBJECTS_SQL}, {STRATA_SQL} SELECT root, round(CASE WHEN pop > 0 THEN 1 - n::DOUBLE / pop ELSE 0 END, 8) AS fpc FROM strata")
def m30(spark, sf):
    from ..plans.estimators import fpc_column

    return strata(spark, sf).select("root", F.round(fpc_column(F.col("n"), F.col("pop")), 8).alias("fpc"))


@query("m31_clt_interval", f"WITH {OBJECTS_SQL}, {STRATA_SQL}, {EST_SQL} SELECT round(sum_est - {Z95!r} * sqrt(sum_var), 4) AS sum_low, round(sum_est + {Z95!r} * sqrt(sum_var), 4) AS sum_high FROM est")
def m31(spark, sf):
    return _estimates(spark, sf).select(F.round("sum_low", 4).alias("sum_low"), F.round("sum_high", 4).alias("sum_high"))


_VAR_SQL = f"WITH {OBJECTS_SQL} SELECT round(var_samp(l_quantity), 6) AS variance, round(stddev_samp(l_quantity), 6) AS stddev FROM o WHERE {IN_WINDOW}"


@query("m32_variance_and_stddev", _VAR_SQL)
def m32(spark, sf):
    ix, _ = index(spark, sf)
    r = evaluate(ix, ViewportQuery(WINDOW, (Agg("variance", "l_quantity"), Agg("stddev", "l_quantity")), 0.0))
    return spark.createDataFrame([tuple(a.estimate for a in r.answers)], "variance double, stddev double").select(F.round("variance", 6).alias("variance"), F.round("stddev", 6).alias("stddev"))


@query("m33_extremes", f"WITH {OBJECTS_SQL} SELECT min(l_tax) AS low, max(l_tax) AS high FROM o WHERE {IN_WINDOW}")
def m33(spark, sf):
    ix, _ = index(spark, sf)
    r = evaluate(ix, ViewportQuery(WINDOW, (Agg("min", "l_tax"), Agg("max", "l_tax")), 0.5))
    return spark.createDataFrame([tuple(a.estimate for a in r.answers)], "low double, high double")


@query("m34_estimated_error", f"WITH {OBJECTS_SQL}, {STRATA_SQL}, {EST_SQL} SELECT round({Z95!r} * sqrt(sum_var) / abs(sum_est), 8) AS eps_est FROM est")
def m34(spark, sf):
    return _estimates(spark, sf).select(F.round("eps_est", 8).alias("eps_est"))


@query("m35_several_aggregates", None)
def m35(spark, sf):
    ix, _ = index(spark, sf)
    return evaluate(ix, ViewportQuery(WINDOW, (Agg("sum", "l_quantity"), Agg("mean", "l_tax"), Agg("count")), 0.02)).to_df(spark)


_CELL_EPS = f"{Z95!r}::DOUBLE * sqrt(s2 / n * (1 - n::DOUBLE / pop)) / abs(mean)"


@query("m36_next_rate", f"WITH {OBJECTS_SQL}, {STRATA_SQL}, c AS (SELECT root, {_CELL_EPS} AS e FROM strata WHERE n >= 2 AND mean <> 0) SELECT root, round(e, 9)::DOUBLE AS eps, round(least(1.0, 0.1 * least(2.0, greatest(1.1, (e / 0.02) * (e / 0.02)))), 9)::DOUBLE AS rate FROM c")
def m36(spark, sf):
    """The rate that each cell of the window would be read at next, after a tenth of it and for a bound of 2%; at most a hundred cells."""
    eps = F.lit(Z95) * F.sqrt(F.col("s2") / F.col("n") * (1 - F.col("n") / F.col("pop"))) / F.abs("mean")
    cells = strata(spark, sf).filter("n >= 2 AND mean <> 0").select("root", eps.alias("eps")).collect()
    return spark.createDataFrame([(r.root, round(r.eps, 9), round(next_rate(0.1, r.eps, 0.02), 9)) for r in cells], "root int, eps double, rate double")


@query("m37_sampling_loop", None)
def m37(spark, sf):
    ix, _ = index(spark, sf, config=IndexConfig(grid=GRID, split_min=40, portable_key=True))
    r = evaluate(ix, the_query(eps=0.02))
    return spark.createDataFrame([(0, x["round"], float(x["rate"]), x["new_reads"], float(x["eps_est"])) for x in r.round_log], "query_id int, round int, rate double, new_reads long, eps_est double")


_CHILD = f"(zcode >> {CELL_BITS - 2}) & 3"


@query("m39_split_counts", f"WITH {OBJECTS_SQL} SELECT root, ({_CHILD})::INTEGER AS part, count(*) AS n FROM o GROUP BY ALL")
def m39(spark, sf):
    """Four quarters of every cell, by two bits of the path code."""
    return objects(spark, sf).groupBy("root", F.shiftright("zcode", CELL_BITS - 2).bitwiseAND(F.lit(3)).cast("int").alias("part")).agg(F.count("*").alias("n"))


@query("m40_enrichment_by_new_attribute", f"WITH {OBJECTS_SQL} SELECT round(sum(l_tax), 4) AS total, count(*) AS pop FROM o WHERE {IN_WINDOW}")
def m40(spark, sf):
    ix, _ = index(spark, sf)
    evaluate(ix, the_query(attr="l_tax"))
    r = evaluate(ix, the_query(eps=0.0, attr="l_tax"))
    return spark.createDataFrame([(r.answers[0].estimate, r.pop)], "total double, pop long").withColumn("total", F.round("total", 4))


@query("m43_exact_mode", _EXACT_SQL)
def m43(spark, sf):
    ix, _ = index(spark, sf)
    evaluate(ix, the_query(eps=0.1))
    return _exact(spark, evaluate(ix, the_query(eps=0.0)))


@query("m44_tighter_bound", None)
def m44(spark, sf):
    ix, _ = index(spark, sf)
    out = [evaluate(ix, ViewportQuery(WINDOW, (Agg("mean", "l_quantity"),), e, query_id=i)) for i, e in enumerate((0.1, 0.05, 0.02))]
    return out[0].to_df(spark).unionByName(out[1].to_df(spark)).unionByName(out[2].to_df(spark))


@query("m45_result_rows", None)
def m45(spark, sf):
    return evaluate(index(spark, sf)[0], the_query()).to_df(spark)


@query("m46_window_objects", f"WITH {OBJECTS_SQL} SELECT ax, ay, rkey FROM o WHERE {IN_WINDOW}")
def m46(spark, sf):
    return window_objects(index(spark, sf)[0], WINDOW).select("ax", "ay", "rkey")


@query("b01_exact_tile_index", _EXACT_SQL)
def b01(spark, sf):
    return _exact(spark, ExactTileIndex(index(spark, sf)[0]).evaluate(the_query(eps=0.05)))


@query("b02_sample_only_index", None)
def b02(spark, sf):
    return SampleOnlyIndex(index(spark, sf)[0]).evaluate(the_query()).to_df(spark)


_FIVE = [WINDOW.pan(0.1 * i, 0.05 * i) for i in range(5)]
_FIVE_SQL = "w(query_id, x1, x2, y1, y2) AS (VALUES " + ", ".join(f"({i}, {v.x1!r}::DOUBLE, {v.x2!r}::DOUBLE, {v.y1!r}::DOUBLE, {v.y2!r}::DOUBLE)" for i, v in enumerate(_FIVE)) + ")"


def five_windows(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame([(i, v.x1, v.x2, v.y1, v.y2) for i, v in enumerate(_FIVE)], "query_id int, x1 double, x2 double, y1 double, y2 double")


_SCAN_SQL = f"WITH {OBJECTS_SQL}, {_FIVE_SQL} SELECT query_id, count(*) AS pop, sum(l_quantity)::BIGINT AS total, round(avg(l_quantity), 6) AS mean, min(l_quantity)::BIGINT AS low, max(l_quantity)::BIGINT AS high FROM w JOIN o ON ax BETWEEN x1 AND x2 AND ay BETWEEN y1 AND y2 GROUP BY query_id"


@query("b03_full_scan", _SCAN_SQL)
def b03(spark, sf):
    got = full_scan(objects(spark, sf), five_windows(spark), [Agg(f, "l_quantity") for f in ("sum", "mean", "min", "max")])
    return got.select("query_id", "pop", F.col("sum_l_quantity").cast("long").alias("total"), F.round("mean_l_quantity", 6).alias("mean"), F.col("min_l_quantity").cast("long").alias("low"), F.col("max_l_quantity").cast("long").alias("high"))


@query("b04_uniform_sample", f"WITH {OBJECTS_SQL} SELECT count(*) AS n, round(sum(l_quantity) * 10.0, 4)::DOUBLE AS sum_est FROM o WHERE {IN_WINDOW} AND rkey < {RATE_KEY}")
def b04(spark, sf):
    """One draw at a tenth of all objects, scaled up without strata."""
    s = objects(spark, sf).filter((F.col("rkey") < RATE_KEY) & WINDOW.condition())
    return s.agg(F.count("*").alias("n"), F.round(F.sum("l_quantity") * 10.0, 4).alias("sum_est"))


_SHARE = f"greatest(0, least(x_hi, {WINDOW.x2}) - greatest(x_lo, {WINDOW.x1})) * greatest(0, least(y_hi, {WINDOW.y2}) - greatest(y_lo, {WINDOW.y1})) / ((x_hi - x_lo) * (y_hi - y_lo))"


@query("b05_static_grid", f"WITH {OBJECTS_SQL}, {TILES_SQL} SELECT round(sum({_SHARE} * s), 2) AS sum_est FROM t JOIN (SELECT root, sum(l_quantity) AS s FROM o GROUP BY root) USING (root)")
def b05(spark, sf):
    r = StaticGrid(index(spark, sf)[0]).evaluate(the_query())
    return spark.createDataFrame([(r.answers[0].estimate,)], "sum_est double").select(F.round("sum_est", 2).alias("sum_est"))


@query("t01_progressive_answers", None)
def t01(spark, sf):
    rows = [(i, r.answers[0].estimate, r.answers[0].ci_low, r.answers[0].ci_high, r.io_ops) for i, r in enumerate(evaluate_progressive(index(spark, sf)[0], the_query(eps=0.01)))]
    return spark.createDataFrame(rows, "round int, estimate double, ci_low double, ci_high double, io_ops long")


@query("c06_relative_error", f"WITH {OBJECTS_SQL}, {_FIVE_SQL}, e AS (SELECT query_id, sum(l_quantity) AS exact_value, 10.0 * sum(l_quantity) FILTER (rkey < {RATE_KEY}) AS estimate FROM w JOIN o ON ax BETWEEN x1 AND x2 AND ay BETWEEN y1 AND y2 GROUP BY query_id) SELECT query_id, round(abs(estimate - exact_value) / abs(exact_value), 8)::DOUBLE AS rel_err FROM e")
def c06(spark, sf):
    from ..plans.metrics import relative_error

    rows = objects(spark, sf).join(F.broadcast(five_windows(spark)), F.col("ax").between(F.col("x1"), F.col("x2")) & F.col("ay").between(F.col("y1"), F.col("y2")))
    name = [F.lit("sum").alias("agg"), F.lit("l_quantity").alias("attr")]
    got = rows.groupBy("query_id").agg((10.0 * F.sum(F.when(F.col("rkey") < RATE_KEY, F.col("l_quantity")))).alias("estimate"), F.sum("l_quantity").alias("exact_value"))
    err = relative_error(got.select("query_id", *name, "estimate"), got.select("query_id", *name, "exact_value"))
    return err.select("query_id", F.round("rel_err", 8).alias("rel_err"))


_COVER_SQL = f"""WITH {OBJECTS_SQL}, {_FIVE_SQL},
  st AS (SELECT query_id, root, count(*) AS pop, count(*) FILTER (rkey < {RATE_KEY}) AS n, avg(l_quantity) FILTER (rkey < {RATE_KEY}) AS mean, var_samp(l_quantity) FILTER (rkey < {RATE_KEY}) AS s2, sum(l_quantity) AS truth
         FROM w JOIN o ON ax BETWEEN x1 AND x2 AND ay BETWEEN y1 AND y2 GROUP BY ALL),
  e AS (SELECT query_id, sum(truth) AS truth, sum(pop * mean) AS est, {Z95!r} * sqrt(sum(CASE WHEN n < pop THEN pop::DOUBLE * pop * s2 / n * (1 - n::DOUBLE / pop) ELSE 0 END)) AS half FROM st GROUP BY query_id)
  SELECT avg(CASE WHEN truth BETWEEN est - half AND est + half THEN 1.0 ELSE 0.0 END)::DOUBLE AS coverage, count(*) AS n FROM e"""


@query("c08_coverage_fixed_rate", _COVER_SQL)
def c08(spark, sf):
    rows = objects(spark, sf).join(F.broadcast(five_windows(spark)), F.col("ax").between(F.col("x1"), F.col("x2")) & F.col("ay").between(F.col("y1"), F.col("y2")))
    drawn = lambda f: f(F.when(F.col("rkey") < RATE_KEY, F.col("l_quantity")))
    st = rows.groupBy("query_id", "root").agg(F.count("*").alias("pop"), drawn(F.count).alias("n"), drawn(F.avg).alias("mean"), drawn(F.var_samp).alias("s2"), F.sum("l_quantity").alias("truth"))
    e = estimates(st, ["query_id"], Z95).join(st.groupBy("query_id").agg(F.sum("truth").alias("truth")), "query_id")
    return e.agg(F.avg(F.col("truth").between(F.col("sum_low"), F.col("sum_high")).cast("double")).alias("coverage"), F.count("*").alias("n"))


@query("c13_index_size", None)
def c13(spark, sf):
    ix, _ = index(spark, sf)
    evaluate(ix, the_query())
    s = ix.size()
    return spark.createDataFrame([tuple(s.values())], ", ".join(f"{k} long" for k in s))


@query("strata_of_a_query", None)
def strata_rows(spark, sf):
    ix, _ = index(spark, sf)
    return strata_frame(ix, plan_strata(ix, the_query(), SamplingPolicy()), "l_quantity")

