"""Relational operators and functions that a user of the methods needs, over the given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window, functions as F

from ..sources.tables import load_table
from .methods import IN_WINDOW, OBJECTS_SQL, ORDER_WINDOWS_SQL, RATE_KEY, SIDES, TILES_SQL, WINDOW, five_windows, index, objects, order_windows
from .methods import _FIVE_SQL as FIVE_SQL
from .registry import query


def t(spark: SparkSession, sf: str, name: str) -> DataFrame:
    return load_table(spark, sf, name)


@query("r01_projection", "SELECT l_orderkey, round(l_extendedprice * l_discount, 4) AS px, round(l_quantity * l_tax, 4) AS py FROM lineitem")
def r01(spark, sf):
    return t(spark, sf, "lineitem").selectExpr("l_orderkey", "round(l_extendedprice * l_discount, 4) AS px", "round(l_quantity * l_tax, 4) AS py")


@query("r02_filters", "SELECT l_orderkey, l_linenumber, l_returnflag FROM lineitem WHERE (l_quantity BETWEEN 5 AND 10 OR (l_extendedprice >= 50000 AND l_extendedprice < 60000)) AND l_returnflag IN ('A', 'R') AND l_linestatus IS NOT NULL AND l_returnflag LIKE '_' AND regexp_matches(l_linestatus, '^[OF]$')")
def r02(spark, sf):
    c = F.col
    two = c("l_quantity").between(5, 10) | ((c("l_extendedprice") >= 50000) & (c("l_extendedprice") < 60000))
    rows = t(spark, sf, "lineitem").filter(two & c("l_returnflag").isin("A", "R") & c("l_linestatus").isNotNull() & c("l_returnflag").like("_") & c("l_linestatus").rlike("^[OF]$"))
    return rows.select("l_orderkey", "l_linenumber", "l_returnflag")


@query("r03_equi_joins", "SELECT r_name, n_name, c_mktsegment, count(*) AS n, sum(l_quantity)::BIGINT AS quantity FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ALL")
def r03(spark, sf):
    l, o, c, n, r = (t(spark, sf, x) for x in ("lineitem", "orders", "customer", "nation", "region"))
    places = n.join(F.broadcast(r), n.n_regionkey == r.r_regionkey)  # 25 nations in 5 regions, whatever the scale
    per_order = l.groupBy("l_orderkey").agg(F.count("*").alias("n"), F.sum("l_quantity").alias("q"))  # aggregated before the joins
    joined = per_order.join(o, per_order.l_orderkey == o.o_orderkey).join(c, o.o_custkey == c.c_custkey).join(F.broadcast(places), c.c_nationkey == places.n_nationkey)
    return joined.groupBy("r_name", "n_name", "c_mktsegment").agg(F.sum("n").alias("n"), F.sum("q").cast("long").alias("quantity"))


@query("r03_join_strategies", "SELECT 'broadcast' AS strategy, count(*) AS n FROM lineitem JOIN supplier ON l_suppkey = s_suppkey UNION ALL SELECT 'merge', count(*) FROM lineitem JOIN supplier ON l_suppkey = s_suppkey UNION ALL SELECT 'shuffle_hash', count(*) FROM lineitem JOIN supplier ON l_suppkey = s_suppkey")
def r03b(spark, sf):
    l, s = t(spark, sf, "lineitem").select("l_suppkey"), t(spark, sf, "supplier").select("s_suppkey")
    one = lambda h: l.join(s.hint(h), l.l_suppkey == s.s_suppkey).agg(F.lit(h).alias("strategy"), F.count("*").alias("n"))
    return one("broadcast").union(one("merge")).union(one("shuffle_hash"))


_TILE_N = f"a AS (SELECT root, count(*) AS n_all FROM o GROUP BY root), b AS (SELECT root, count(*) AS n_in FROM o WHERE {IN_WINDOW} GROUP BY root)"


@query("r04_outer_joins", f"WITH {OBJECTS_SQL}, {_TILE_N} SELECT a.root AS root, n_all, coalesce(n_in, 0) AS n_in, n_in IS NULL AS missing FROM a LEFT JOIN b ON a.root = b.root UNION ALL SELECT b.root + 1000, n_in, 0, false FROM b FULL JOIN (SELECT root FROM a WHERE root < 50) h ON b.root = h.root WHERE h.root IS NULL")
def r04(spark, sf):
    o = objects(spark, sf)
    a = o.groupBy("root").agg(F.count("*").alias("n_all"))
    b = o.filter(WINDOW.condition()).groupBy("root").agg(F.count("*").alias("n_in"))
    left = a.join(b, "root", "left").select("root", "n_all", F.coalesce("n_in", F.lit(0)).alias("n_in"), F.col("n_in").isNull().alias("missing"))
    half = a.filter("root < 50").select(F.col("root").alias("h"))
    full = b.join(half, b.root == half.h, "full").filter("h IS NULL").select((F.col("root") + 1000).alias("root"), F.col("n_in").alias("n_all"), F.lit(0).cast("long").alias("n_in"), F.lit(False).alias("missing"))
    return left.unionByName(full)


@query("r05_semi_join", f"WITH {OBJECTS_SQL} SELECT root, count(*) AS n FROM o WHERE root IN (SELECT root FROM o WHERE {IN_WINDOW}) GROUP BY root")
def r05(spark, sf):
    o = objects(spark, sf)
    return o.select("root").join(o.filter(WINDOW.condition()).select("root").distinct(), "root", "left_semi").groupBy("root").agg(F.count("*").alias("n"))


@query("r05_anti_join_unread", f"WITH {OBJECTS_SQL} SELECT root, count(*) AS n FROM o WHERE NOT EXISTS (SELECT 1 FROM o r WHERE r.rkey = o.rkey AND r.rkey < {RATE_KEY}) GROUP BY root")
def r05b(spark, sf):
    o = objects(spark, sf).select("root", "rkey")
    return o.join(o.filter(F.col("rkey") < RATE_KEY).select("rkey"), "rkey", "left_anti").groupBy("root").agg(F.count("*").alias("n"))


@query("r06_range_join", f"WITH {OBJECTS_SQL}, {TILES_SQL} SELECT t.root AS root, count(*) AS n FROM o JOIN t ON ax >= x_lo AND (ax < x_hi OR t.root % 10 = 9) AND ay >= y_lo AND (ay < y_hi OR t.root // 10 = 9) GROUP BY t.root")
def r06(spark, sf):
    """The naive assignment: four inequalities against a hundred tiles of fixed number."""
    tiles = index(spark, sf)[0].tiles_frame().select(F.col("root").alias("tile"), "x_lo", "x_hi", "y_lo", "y_hi")
    o = objects(spark, sf).select("ax", "ay")
    inside = (F.col("ax") >= F.col("x_lo")) & ((F.col("ax") < F.col("x_hi")) | (F.col("tile") % 10 == 9)) & (F.col("ay") >= F.col("y_lo")) & ((F.col("ay") < F.col("y_hi")) | (F.floor(F.col("tile") / 10) == 9))
    return o.join(F.broadcast(tiles), inside).groupBy(F.col("tile").alias("root")).agg(F.count("*").alias("n"))


@query("r07_theta_join", f"WITH {TILES_SQL}, {FIVE_SQL} SELECT query_id, root FROM w JOIN t ON x_lo <= x2 AND x1 <= x_hi AND y_lo <= y2 AND y1 <= y_hi")
def r07(spark, sf):
    tiles = index(spark, sf)[0].tiles_frame()
    meets = (F.col("x_lo") <= F.col("x2")) & (F.col("x1") <= F.col("x_hi")) & (F.col("y_lo") <= F.col("y2")) & (F.col("y1") <= F.col("y_hi"))
    return tiles.join(F.broadcast(five_windows(spark)), meets).select("query_id", "root")


_OWNED_SQL = f"{ORDER_WINDOWS_SQL}, owned AS (SELECT o_custkey, w.* FROM w JOIN orders ON query_id = o_orderkey)"


def owned_windows(spark: SparkSession, sf: str) -> DataFrame:
    """The window of every order, with its customer."""
    return order_windows(spark, sf).join(t(spark, sf, "orders").select("o_custkey", F.col("o_orderkey").alias("query_id")), "query_id").select("o_custkey", "query_id", *SIDES)


@query("r08_interval_join", f"WITH {_OWNED_SQL} SELECT a.query_id AS a, b.query_id AS b, ((least(a.x2, b.x2) - greatest(a.x1, b.x1)) * (least(a.y2, b.y2) - greatest(a.y1, b.y1))) / nullif((a.x2 - a.x1) * (a.y2 - a.y1), 0) AS share FROM owned a JOIN owned b ON a.o_custkey = b.o_custkey AND a.query_id < b.query_id AND a.x1 <= b.x2 AND b.x1 <= a.x2 AND a.y1 <= b.y2 AND b.y1 <= a.y2")
def r08(spark, sf):
    """Windows of a customer's orders that overlap, and the share of the first that they have in common (none where it has no area)."""
    a = owned_windows(spark, sf)
    b = a.select(*(F.col(c).alias(f"b_{c}") for c in a.columns))
    c = F.col
    near = (c("o_custkey") == c("b_o_custkey")) & (c("query_id") < c("b_query_id")) & (c("x1") <= c("b_x2")) & (c("b_x1") <= c("x2")) & (c("y1") <= c("b_y2")) & (c("b_y1") <= c("y2"))
    common = (F.least("x2", "b_x2") - F.greatest("x1", "b_x1")) * (F.least("y2", "b_y2") - F.greatest("y1", "b_y1"))
    area = (c("x2") - c("x1")) * (c("y2") - c("y1"))
    return a.join(b, near).select(c("query_id").alias("a"), c("b_query_id").alias("b"), (common / F.nullif(area, F.lit(0.0))).alias("share"))


@query("r09_as_of_join", "SELECT o_orderkey, e.event_id AS event_id FROM (SELECT o_orderkey, o_custkey, o_orderdate FROM orders) o ASOF LEFT JOIN (SELECT user_id, ts - INTERVAL 10000 DAY AS at, max(event_id) AS event_id FROM events GROUP BY ALL) e ON o.o_custkey = e.user_id AND o.o_orderdate >= e.at")
def r09(spark, sf):
    """The last event of a user before each order (events moved back in time to meet the orders): one sort of both, no range join."""
    e = t(spark, sf, "events").select(F.col("user_id").alias("k"), (F.col("ts") - F.expr("INTERVAL '10000' DAY")).alias("at"), "event_id", F.lit(None).cast("long").alias("o_orderkey"))
    o = t(spark, sf, "orders").select(F.col("o_custkey").alias("k"), F.col("o_orderdate").alias("at"), F.lit(None).cast("long").alias("event_id"), "o_orderkey")
    w = Window.partitionBy("k").orderBy("at", F.col("o_orderkey").asc_nulls_first(), "event_id").rowsBetween(Window.unboundedPreceding, 0)
    return e.unionByName(o).withColumn("event_id", F.last("event_id", ignorenulls=True).over(w)).filter("o_orderkey IS NOT NULL").select("o_orderkey", "event_id")


@query("r10_hash_aggregation", f"WITH {OBJECTS_SQL} SELECT root, count(*) AS n, sum(l_quantity)::BIGINT AS total, round(avg(l_quantity), 6) AS mean, round(var_samp(l_quantity), 4) AS var FROM o GROUP BY root")
def r10(spark, sf):
    return objects(spark, sf).groupBy("root").agg(F.count("*").alias("n"), F.sum("l_quantity").cast("long").alias("total"), F.round(F.avg("l_quantity"), 6).alias("mean"), F.round(F.var_samp("l_quantity"), 4).alias("var"))


@query("r11_sort_aggregation", "SELECT n_regionkey, string_agg(n_name, ',' ORDER BY n_name) AS names, count(*) AS n FROM nation GROUP BY n_regionkey")
def r11(spark, sf):
    return t(spark, sf, "nation").groupBy("n_regionkey").agg(F.array_join(F.array_sort(F.collect_list("n_name")), ",").alias("names"), F.count("*").alias("n"))


@query("r12_distinct_aggregates", f"WITH {OBJECTS_SQL} SELECT root, count(DISTINCT l_quantity) AS d FROM o GROUP BY root")
def r12(spark, sf):
    return objects(spark, sf).groupBy("root").agg(F.count_distinct("l_quantity").alias("d"))


@query("r12_approximate_distinct", None)
def r12b(spark, sf):
    o = t(spark, sf, "lineitem")
    return o.groupBy("l_returnflag").agg(F.approx_count_distinct("l_partkey").alias("hash_based"), F.hll_sketch_estimate(F.hll_sketch_agg("l_partkey")).alias("sketch"), F.count_distinct("l_partkey").alias("exact"))


@query("r13_pyramid_rollup", f"WITH {OBJECTS_SQL} SELECT root, ((zcode >> 28) & 3)::INTEGER AS q1, ((zcode >> 26) & 3)::INTEGER AS q2, count(*) AS n, grouping(root, q1, q2)::INTEGER AS level FROM o GROUP BY ROLLUP (root, q1, q2)")
def r13(spark, sf):
    o = objects(spark, sf).withColumns({"q1": F.shiftright("zcode", 28).bitwiseAND(F.lit(3)).cast("int"), "q2": F.shiftright("zcode", 26).bitwiseAND(F.lit(3)).cast("int")})
    return o.rollup("root", "q1", "q2").agg(F.count("*").alias("n"), F.grouping_id().cast("int").alias("level"))


@query("r13_cube", "SELECT l_returnflag, l_linestatus, count(*) AS n, sum(l_quantity)::BIGINT AS total FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)")
def r13b(spark, sf):
    return t(spark, sf, "lineitem").cube("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.sum("l_quantity").cast("long").alias("total"))


@query("r13_grouping_sets", "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY GROUPING SETS ((l_returnflag), (l_linestatus), ())")
def r13c(spark, sf):
    rows = t(spark, sf, "lineitem")
    return rows.groupingSets([["l_returnflag"], ["l_linestatus"], []], "l_returnflag", "l_linestatus").agg(F.count("*").alias("n"))


@query("r14_quantiles", f"WITH {OBJECTS_SQL} SELECT root, quantile_cont(l_quantity, 0.5) AS median, quantile_cont(l_quantity, 0.9) AS p90 FROM o GROUP BY root")
def r14(spark, sf):
    return objects(spark, sf).groupBy("root").agg(F.percentile("l_quantity", 0.5).alias("median"), F.percentile("l_quantity", 0.9).alias("p90"))


@query("r14_quantile_sketches", None)
def r14b(spark, sf):
    rows = t(spark, sf, "lineitem").groupBy("l_returnflag")
    return rows.agg(F.percentile_approx("l_extendedprice", 0.5, 1000).alias("approx"), F.expr("kll_sketch_get_quantile_double(kll_sketch_agg_double(l_extendedprice), 0.5)").alias("sketch"), F.percentile("l_extendedprice", 0.5).alias("exact"))


@query("r15_pivot", "SELECT l_returnflag, count(*) FILTER (l_linestatus = 'F') AS F, count(*) FILTER (l_linestatus = 'O') AS O FROM lineitem GROUP BY l_returnflag")
def r15(spark, sf):
    return t(spark, sf, "lineitem").groupBy("l_returnflag").pivot("l_linestatus", ["F", "O"]).agg(F.count(F.lit(1))).na.fill(0)


@query("r15_unpivot", f"WITH {OBJECTS_SQL}, a AS (SELECT root, sum(l_quantity)::DOUBLE AS l_quantity, round(sum(l_tax), 4)::DOUBLE AS l_tax FROM o GROUP BY root) SELECT root, 'l_quantity' AS attr, l_quantity AS total FROM a UNION ALL SELECT root, 'l_tax', l_tax FROM a")
def r15b(spark, sf):
    a = objects(spark, sf).groupBy("root").agg(F.sum("l_quantity").alias("l_quantity"), F.round(F.sum("l_tax"), 4).alias("l_tax"))
    return a.unpivot("root", ["l_quantity", "l_tax"], "attr", "total")


@query("r16_ranking", f"WITH {OBJECTS_SQL}, c AS (SELECT root, count(*) AS n FROM o GROUP BY root) SELECT root, n, row_number() OVER (ORDER BY n DESC, root) AS rn, rank() OVER (ORDER BY n DESC) AS rk, dense_rank() OVER (ORDER BY n DESC) AS dr, ntile(4) OVER (ORDER BY n DESC, root) AS nt, round(percent_rank() OVER (ORDER BY n DESC), 6) AS pr, round(cume_dist() OVER (ORDER BY n DESC), 6) AS cd FROM c")
def r16(spark, sf):
    """Ranks of the hundred cells; one partition holds them all, as there are never more."""
    c = objects(spark, sf).groupBy("root").agg(F.count("*").alias("n"))
    w, total = Window.orderBy(F.desc("n")), Window.orderBy(F.desc("n"), "root")
    long = lambda x: x.cast("long")
    return c.select("root", "n", long(F.row_number().over(total)).alias("rn"), long(F.rank().over(w)).alias("rk"), long(F.dense_rank().over(w)).alias("dr"), long(F.ntile(4).over(total)).alias("nt"), F.round(F.percent_rank().over(w), 6).alias("pr"), F.round(F.cume_dist().over(w), 6).alias("cd"))


@query("r17_analytic_windows", f"WITH {_OWNED_SQL} SELECT query_id, x1 - lag(x1) OVER v AS dx, lead(y1) OVER v - y1 AS dy, first_value(x1) OVER v AS first_x, last_value(x1) OVER (PARTITION BY o_custkey ORDER BY query_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS last_x, nth_value(x1, 2) OVER v AS second_x FROM owned WINDOW v AS (PARTITION BY o_custkey ORDER BY query_id)")
def r17(spark, sf):
    """How the windows of a customer's orders follow one another."""
    v = Window.partitionBy("o_custkey").orderBy("query_id")
    whole = v.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return owned_windows(spark, sf).select("query_id", (F.col("x1") - F.lag("x1").over(v)).alias("dx"), (F.lead("y1").over(v) - F.col("y1")).alias("dy"), F.first("x1").over(v).alias("first_x"), F.last("x1").over(whole).alias("last_x"), F.nth_value("x1", 2).over(v).alias("second_x"))


@query("r18_frames", "SELECT event_id, sum(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING)::BIGINT AS running, count(*) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 9 PRECEDING AND CURRENT ROW) AS last_ten, count(*) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 7 DAY PRECEDING AND CURRENT ROW) AS last_week FROM events")
def r18(spark, sf):
    by = Window.partitionBy("user_id")
    rows = by.orderBy("ts", "event_id")
    week = by.orderBy("micros").rangeBetween(-7 * 86_400_000_000, 0)
    e = t(spark, sf, "events").withColumn("micros", F.unix_micros(F.col("ts").cast("timestamp")))
    return e.select("event_id", F.sum("event_id").over(rows.rowsBetween(Window.unboundedPreceding, 0)).alias("running"), F.count("*").over(rows.rowsBetween(-9, 0)).alias("last_ten"), F.count("*").over(week).alias("last_week"))


@query("r19_top_k", f"WITH {OBJECTS_SQL} SELECT root, count(*) AS n FROM o GROUP BY root ORDER BY n DESC, root LIMIT 10")
def r19(spark, sf):
    return objects(spark, sf).groupBy("root").agg(F.count("*").alias("n")).orderBy(F.desc("n"), "root").limit(10)


@query("r20_top_k_per_group", f"WITH {OBJECTS_SQL} SELECT root, rkey FROM (SELECT root, rkey, row_number() OVER (PARTITION BY root ORDER BY rkey) AS r FROM o) WHERE r <= 5")
def r20(spark, sf):
    """The first five drawn of each cell."""
    w = Window.partitionBy("root").orderBy("rkey")
    return objects(spark, sf).select("root", "rkey", F.row_number().over(w).alias("r")).filter("r <= 5").select("root", "rkey")


@query("r20_best_per_group", "SELECT l_returnflag, max(l_extendedprice) AS price, arg_max(l_orderkey, (l_extendedprice, l_orderkey)) AS l_orderkey FROM lineitem GROUP BY l_returnflag")
def r20b(spark, sf):
    return t(spark, sf, "lineitem").groupBy("l_returnflag").agg(F.max("l_extendedprice").alias("price"), F.max_by("l_orderkey", F.struct("l_extendedprice", "l_orderkey")).alias("l_orderkey"))


_A, _B = "SELECT l_suppkey AS k FROM lineitem WHERE l_quantity < 3", "SELECT l_suppkey AS k FROM lineitem WHERE l_quantity > 48"


def _sets(spark, sf):
    rows = t(spark, sf, "lineitem")
    return rows.filter("l_quantity < 3").select(F.col("l_suppkey").alias("k")), rows.filter("l_quantity > 48").select(F.col("l_suppkey").alias("k"))


@query("r21_union", f"SELECT k, count(*) AS n FROM ({_A} UNION ALL {_B}) GROUP BY k")
def r21(spark, sf):
    a, b = _sets(spark, sf)
    return a.unionByName(b).groupBy("k").agg(F.count("*").alias("n"))


@query("r21_intersect", f"{_A} INTERSECT {_B}")
def r21b(spark, sf):
    a, b = _sets(spark, sf)
    return a.intersect(b)


@query("r21_intersect_all", f"SELECT k, count(*) AS n FROM ({_A} INTERSECT ALL {_B}) GROUP BY k")
def r21c(spark, sf):
    a, b = _sets(spark, sf)
    return a.intersectAll(b).groupBy("k").agg(F.count("*").alias("n"))


@query("r21_except_all", f"SELECT k, count(*) AS n FROM ({_A} EXCEPT ALL {_B}) GROUP BY k")
def r21d(spark, sf):
    a, b = _sets(spark, sf)
    return a.exceptAll(b).groupBy("k").agg(F.count("*").alias("n"))


@query("r21_subtract", f"{_A} EXCEPT SELECT l_suppkey FROM lineitem WHERE l_quantity > 49 AND l_tax > 0.07")
def r21e(spark, sf):
    a, _ = _sets(spark, sf)
    return a.subtract(t(spark, sf, "lineitem").filter("l_quantity > 49 AND l_tax > 0.07").select(F.col("l_suppkey").alias("k")))


@query("r22_scalar_subquery", f"WITH {OBJECTS_SQL} SELECT root, round(count(*)::DOUBLE / (SELECT count(*) FROM o), 8) AS share FROM o GROUP BY root")
def r22(spark, sf):
    o = objects(spark, sf)
    o.createOrReplaceTempView("_r22_objects")
    return spark.sql("SELECT root, round(count(*) / (SELECT count(*) FROM _r22_objects), 8) AS share FROM _r22_objects GROUP BY root")


@query("r22_exists_and_correlated", "SELECT o_orderkey FROM orders WHERE EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey AND l_quantity > 49) AND o_totalprice > (SELECT avg(o2.o_totalprice) FROM orders o2 WHERE o2.o_orderpriority = orders.o_orderpriority)")
def r22b(spark, sf):
    t(spark, sf, "orders").createOrReplaceTempView("_r22_orders")
    t(spark, sf, "lineitem").createOrReplaceTempView("_r22_lineitem")
    return spark.sql("SELECT o_orderkey FROM _r22_orders o WHERE EXISTS (SELECT 1 FROM _r22_lineitem WHERE l_orderkey = o_orderkey AND l_quantity > 49) AND o_totalprice > (SELECT avg(p.o_totalprice) FROM _r22_orders p WHERE p.o_orderpriority = o.o_orderpriority)")


@query("r22_lateral", "SELECT n_nationkey, s_suppkey FROM (SELECT n_nationkey, s_suppkey, row_number() OVER (PARTITION BY n_nationkey ORDER BY s_acctbal DESC, s_suppkey) AS r FROM nation JOIN supplier ON s_nationkey = n_nationkey) WHERE r <= 2")
def r22c(spark, sf):
    t(spark, sf, "nation").createOrReplaceTempView("_r22_nation")
    t(spark, sf, "supplier").createOrReplaceTempView("_r22_supplier")
    return spark.sql("SELECT n_nationkey, s_suppkey FROM _r22_nation, LATERAL (SELECT s_suppkey FROM _r22_supplier WHERE s_nationkey = n_nationkey ORDER BY s_acctbal DESC, s_suppkey LIMIT 2)")


_QUADTREE_SQL = "WITH RECURSIVE {objects}q(depth, zlo, zhi) AS (SELECT 0, {zero}, {top} UNION ALL SELECT depth + 1, zlo + i * ((zhi - zlo) {div} 4), zlo + (i + 1) * ((zhi - zlo) {div} 4) FROM q JOIN (VALUES (0), (1), (2), (3)) v(i) ON depth < 3)"


@query("r23_recursive_quadtree", _QUADTREE_SQL.format(objects=f"{OBJECTS_SQL}, ", zero="0::BIGINT", top="1073741824::BIGINT", div="//") + ", leaf AS (SELECT zcode >> 24 AS leaf, count(*) AS n, sum(l_quantity)::BIGINT AS total FROM o GROUP BY 1) SELECT depth, zlo, zhi, coalesce(sum(n), 0)::BIGINT AS n, coalesce(sum(total), 0)::BIGINT AS total FROM q LEFT JOIN leaf ON leaf << 24 >= zlo AND leaf << 24 < zhi GROUP BY depth, zlo, zhi")
def r23(spark, sf):
    """Three levels of quarters, made by recursion, and what lies in each over all cells. The objects are counted by the 64 last ones first."""
    objects(spark, sf).groupBy(F.shiftright("zcode", 24).alias("leaf")).agg(F.count("*").alias("n"), F.sum("l_quantity").cast("long").alias("total")).createOrReplaceTempView("_r23_leaf")
    tree = _QUADTREE_SQL.format(objects="", zero="0L", top="1073741824L", div="DIV")
    return spark.sql(f"{tree} SELECT depth, zlo, zhi, coalesce(sum(n), 0L) AS n, coalesce(sum(total), 0L) AS total FROM q LEFT JOIN _r23_leaf ON shiftleft(leaf, 24) >= zlo AND shiftleft(leaf, 24) < zhi GROUP BY depth, zlo, zhi")


@query("r24_sample_by_key", f"WITH {OBJECTS_SQL} SELECT root, count(*) AS n FROM o WHERE rkey < {RATE_KEY} GROUP BY root")
def r24(spark, sf):
    return objects(spark, sf).filter(F.col("rkey") < RATE_KEY).groupBy("root").agg(F.count("*").alias("n"))


@query("r24_bernoulli_and_stratified", None)
def r24b(spark, sf):
    rows = t(spark, sf, "lineitem")
    a = rows.sample(0.1, seed=7).groupBy("l_returnflag").agg(F.count("*").alias("n")).withColumn("kind", F.lit("bernoulli"))
    b = rows.sampleBy("l_returnflag", {"A": 0.1, "N": 0.05, "R": 0.2}, seed=7).groupBy("l_returnflag").agg(F.count("*").alias("n")).withColumn("kind", F.lit("stratified"))
    return a.unionByName(b)


@query("r24_fixed_size_per_stratum", f"WITH {OBJECTS_SQL} SELECT root, count(*) AS n, sum(l_quantity)::BIGINT AS total FROM (SELECT *, row_number() OVER (PARTITION BY root ORDER BY rkey) AS r, count(*) OVER (PARTITION BY root) AS pop FROM o) WHERE r <= ceil(0.1::DOUBLE * pop) GROUP BY root")
def r24c(spark, sf):
    """The smallest keys of each cell, a tenth of it rounded up."""
    by = Window.partitionBy("root")
    rows = objects(spark, sf).withColumns({"r": F.row_number().over(by.orderBy("rkey")), "pop": F.count("*").over(by)})
    return rows.filter(F.col("r") <= F.ceil(F.lit(0.1) * F.col("pop"))).groupBy("root").agg(F.count("*").alias("n"), F.sum("l_quantity").cast("long").alias("total"))


@query("r25_dedup", "SELECT DISTINCT l_orderkey, l_linenumber FROM lineitem")
def r25(spark, sf):
    return t(spark, sf, "lineitem").select("l_orderkey", "l_linenumber").dropDuplicates()


@query("r26_null_handling", "SELECT doc_id, coalesce(toxic, -1) AS toxic, CASE WHEN quality = 0 THEN NULL ELSE 1.0 / quality END::DOUBLE AS inverse FROM documents LEFT JOIN labels USING (doc_id)")
def r26(spark, sf):
    d = t(spark, sf, "documents").select("doc_id").join(t(spark, sf, "labels"), "doc_id", "left")
    return d.withColumn("inverse", F.try_divide(F.lit(1.0), F.nullif("quality", F.lit(0)))).na.fill({"toxic": -1}).select("doc_id", "toxic", "inverse")


@query("r27_checkpointed", f"WITH {OBJECTS_SQL} SELECT root, count(*) AS n FROM o GROUP BY root")
def r27(spark, sf):
    """Lineage cut by a table in the shared folder, which outlives executors."""
    from ..runtime import durable

    return durable(objects(spark, sf).select("root"), "objects").groupBy("root").agg(F.count("*").alias("n"))


@query("f01_math", "SELECT l_orderkey, l_linenumber, l_partkey, floor(l_extendedprice / 1000)::BIGINT AS f, round(sqrt(l_extendedprice), 6) AS s, round(ln(l_extendedprice), 6) AS l, round(log2(l_quantity), 6) AS l2, sign(l_quantity - 25)::DOUBLE AS g, greatest(l_discount, l_tax) AS hi, least(l_discount, l_tax) AS lo, (l_orderkey % 7)::BIGINT AS m, least(11, greatest(0, floor((l_quantity) / 5) + 1))::BIGINT AS b FROM lineitem")
def f01(spark, sf):
    c = F.col
    return t(spark, sf, "lineitem").select(
        "l_orderkey", "l_linenumber", "l_partkey", F.floor(c("l_extendedprice") / 1000).alias("f"), F.round(F.sqrt("l_extendedprice"), 6).alias("s"), F.round(F.ln("l_extendedprice"), 6).alias("l"), F.round(F.log2("l_quantity"), 6).alias("l2"),
        F.signum(c("l_quantity") - 25).alias("g"), F.greatest("l_discount", "l_tax").alias("hi"), F.least("l_discount", "l_tax").alias("lo"), F.pmod("l_orderkey", F.lit(7)).alias("m"), F.width_bucket("l_quantity", F.lit(0), F.lit(50), F.lit(10)).alias("b"),
    )


@query("f02_bits", "SELECT o_orderkey, (o_orderkey >> 3)::BIGINT AS r, (o_orderkey << 2)::BIGINT AS l, (o_orderkey & 255)::BIGINT AS a, (o_orderkey | 1)::BIGINT AS o, xor(o_orderkey, 85)::BIGINT AS x, bit_count(o_orderkey)::INTEGER AS n FROM orders")
def f02(spark, sf):
    c = F.col("o_orderkey")
    return t(spark, sf, "orders").select("o_orderkey", F.shiftright(c, 3).alias("r"), F.shiftleft(c, 2).alias("l"), c.bitwiseAND(F.lit(255)).alias("a"), c.bitwiseOR(F.lit(1)).alias("o"), c.bitwiseXOR(F.lit(85)).alias("x"), F.bit_count(c).alias("n"))


@query("f03_hashes", "SELECT doc_id, md5(text) AS m, sha256(text) AS s, ('0x' || substr(md5(text), 1, 15))::BIGINT AS k FROM documents")
def f03(spark, sf):
    b = F.col("text").cast("binary")
    return t(spark, sf, "documents").select("doc_id", F.md5(b).alias("m"), F.sha2(b, 256).alias("s"), F.conv(F.substring(F.md5(b), 1, 15), 16, 10).cast("long").alias("k"))


@query("f04_strings", "SELECT page_id, regexp_extract(url, '^https?://([^/]+)', 1) AS host, length(url)::INTEGER AS n, upper(substr(url, 1, 8)) AS head, len(string_split(url, '/'))::INTEGER AS parts, lpad(page_id::VARCHAR, 8, '0') AS padded, trim('  ' || url || ' ') AS trimmed FROM pages")
def f04(spark, sf):
    c = F.col("url")
    return t(spark, sf, "pages").select("page_id", F.regexp_extract(c, "^https?://([^/]+)", 1).alias("host"), F.length(c).alias("n"), F.upper(F.substring(c, 1, 8)).alias("head"), F.size(F.split(c, "/")).alias("parts"), F.lpad(F.col("page_id").cast("string"), 8, "0").alias("padded"), F.trim(F.concat(F.lit("  "), c, F.lit(" "))).alias("trimmed"))


@query("f05_dates", "SELECT o_orderkey, epoch_us(o_orderdate)::BIGINT AS us, date_diff('day', DATE '1992-01-01', o_orderdate::DATE)::INTEGER AS d, date_trunc('month', o_orderdate)::DATE::VARCHAR AS m, year(o_orderdate)::INTEGER AS y, (o_orderdate + INTERVAL 30 DAY)::DATE::VARCHAR AS due FROM orders")
def f05(spark, sf):
    c = F.col("o_orderdate")
    return t(spark, sf, "orders").select("o_orderkey", F.unix_micros(c.cast("timestamp")).alias("us"), F.datediff(c, F.lit("1992-01-01").cast("date")).alias("d"), F.trunc(c.cast("date"), "month").cast("string").alias("m"), F.year(c).alias("y"), (c + F.expr("INTERVAL '30' DAY")).cast("date").cast("string").alias("due"))


@query("f06_arrays", "SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE)), 4)::DOUBLE AS squares, len(list_filter(embedding, lambda x: x > 0))::INTEGER AS above, embedding[1]::DOUBLE AS first, round(list_aggregate(embedding, 'max')::DOUBLE, 6) AS top FROM embeddings")
def f06(spark, sf):
    e = F.col("embedding")
    squares = F.aggregate(F.transform(e, lambda x: x.cast("double") * x.cast("double")), F.lit(0.0), lambda a, x: a + x)
    return t(spark, sf, "embeddings").select("vec_id", F.round(squares, 4).alias("squares"), F.size(F.filter(e, lambda x: x > 0)).alias("above"), F.element_at(e, 1).cast("double").alias("first"), F.round(F.array_max(e).cast("double"), 6).alias("top"))


@query("f06_exploded", "SELECT i::INTEGER AS i, round(avg(v::DOUBLE), 6) AS mean, count(*) AS n FROM (SELECT unnest(embedding) AS v, generate_subscripts(embedding, 1) - 1 AS i FROM embeddings) GROUP BY i")
def f06b(spark, sf):
    return t(spark, sf, "embeddings").select(F.posexplode("embedding").alias("i", "v")).groupBy("i").agg(F.round(F.avg(F.col("v").cast("double")), 6).alias("mean"), F.count("*").alias("n"))


@query("f07_maps", f"WITH {OBJECTS_SQL} SELECT root, sum(l_quantity)::DOUBLE AS q, 2 AS n, round(2 * sum(l_tax), 4)::DOUBLE AS twice FROM o GROUP BY root")
def f07(spark, sf):
    """Measure to statistic as a map."""
    a = objects(spark, sf).groupBy("root").agg(F.map_from_arrays(F.array(F.lit("l_quantity"), F.lit("l_tax")), F.array(F.sum("l_quantity"), F.sum("l_tax"))).alias("m"))
    return a.select("root", F.col("m")["l_quantity"].alias("q"), F.size(F.map_keys("m")).alias("n"), F.round(F.transform_values("m", lambda k, v: v * 2)["l_tax"], 4).alias("twice"))


@query("f08_json", "SELECT event_id, (props->>'$.k')::INTEGER AS k FROM events")
def f08(spark, sf):
    return t(spark, sf, "events").select("event_id", F.get_json_object("props", "$.k").cast("int").alias("k"))


@query("f08_parsed_json", "SELECT event_id, (props->>'$.k')::INTEGER AS k, (props->>'$.k')::INTEGER AS v FROM events")
def f08b(spark, sf):
    return t(spark, sf, "events").select("event_id", F.from_json("props", "k int")["k"].alias("k"), F.variant_get(F.parse_json("props"), "$.k", "int").alias("v"))


@query("f09_structs", "SELECT n_nationkey, n_name || '/' || n_regionkey AS label FROM nation")
def f09(spark, sf):
    s = F.struct(F.col("n_name").alias("name"), F.col("n_regionkey").alias("region"))
    return t(spark, sf, "nation").select("n_nationkey", s.alias("s")).withColumn("s", F.col("s").withField("label", F.concat_ws("/", "s.name", "s.region"))).select("n_nationkey", F.col("s.label").alias("label"))


@query("f10_statistics", "SELECT l_returnflag, round(stddev_samp(l_quantity), 6) AS sd, round(var_pop(l_quantity), 6) AS vp, round(skewness(l_extendedprice), 3) AS skew, round(corr(l_quantity, l_extendedprice), 6) AS c, round(regr_slope(l_extendedprice, l_quantity), 4) AS slope FROM lineitem GROUP BY l_returnflag")
def f10(spark, sf):
    """Skewness here is of the whole population; SQL's is of a sample, so its factor is put on."""
    n = F.count("*")
    sample = F.skewness("l_extendedprice") * F.sqrt(n * (n - 1)) / (n - 2)
    return t(spark, sf, "lineitem").groupBy("l_returnflag").agg(F.round(F.stddev_samp("l_quantity"), 6).alias("sd"), F.round(F.var_pop("l_quantity"), 6).alias("vp"), F.round(sample, 3).alias("skew"), F.round(F.corr("l_quantity", "l_extendedprice"), 6).alias("c"), F.round(F.regr_slope("l_extendedprice", "l_quantity"), 4).alias("slope"))


