"""Queries whose answers are held against exact ones, with SQL for what must hold of them.

An estimate depends on the draw, so SQL can't give it; but it can give the population and the exact value of every
window, and say what must be true of every row: the estimated error keeps the bound,
the interval holds the estimate, an answer called exact is the exact value, and no
answer is further off than three times its bound.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, replace

from pyspark.sql import DataFrame, SparkSession, functions as F

from ..functions import sqlapi
from ..plans.baselines import SampleOnlyIndex, full_scan
from ..plans.engine import evaluate, evaluate_progressive, plan_strata
from ..plans.geometry import Domain
from ..plans.index import bind_objects
from ..plans.model import Agg, AxisSpec, IndexConfig, QueryResult, SamplingPolicy, Viewport, ViewportQuery
from ..plans.workload import METHODS, ExplorationSession, as_queries, build_from, centre_window, make_path, make_zooms, switch_attribute, workload_frame
from ..sources.tables import load_table, wide_rows, with_uniform
from .methods import BOX, GRID, IN_WINDOW, OBJECTS_SQL, TILES_SQL, WINDOW, index, objects, the_query
from .registry import query

#: How the engine is run here: counting and reading in one job, rates solved from variances.
AHEAD = SamplingPolicy(kind="fpc_aware", cap=16.0, rate0=0.03, exhaust_below=25, pooled_floor=3, ahead=True)
ROWS = "method string, query_id int, agg string, attr string, eps_max double, pop long, exact_value double, met_bound boolean, in_interval boolean, near_truth boolean, exact_right boolean"


@dataclass(frozen=True)
class Space:
    """A table with axes in a fixed box, in Spark and in SQL."""

    table: str
    axes: tuple[str, str]
    sql_axes: tuple[str, str]
    identity: tuple[str, ...]
    attr: str
    box: Viewport
    side: float = 0.316
    start: tuple[float, float] = (0.5, 0.5)
    rows: Callable[[SparkSession, str], DataFrame] | None = None

    def first(self) -> Viewport:
        return centre_window(self.box, self.side, self.start)

    def objects(self, spark: SparkSession, sf: str, attrs: tuple[str, ...]) -> DataFrame:
        df = self.rows(spark, sf) if self.rows else load_table(spark, sf, self.table)
        return bind_objects(df, AxisSpec(*self.axes), list(self.identity), list(attrs), Domain(self.box, *GRID), 7, True)


_KEY = ("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_shipdate", "l_extendedprice")
_DAY = "epoch_us(l_shipdate) / 8.64e10"
UNIFORM = Space("lineitem", ("l_extendedprice", "l_shipdate"), ("l_extendedprice", _DAY), _KEY, "l_quantity", BOX)
WIDE = replace(UNIFORM, rows=wide_rows)
DENSE = Space("lineitem", ("l_extendedprice * l_discount", "l_quantity * l_tax"), ("l_extendedprice * l_discount", "l_quantity * l_tax"), _KEY, "l_quantity", Viewport(0.0, 10500.0, 0.0, 4.0), 0.4, (0.2, 0.2))
LOW = Space("part", ("p_partkey", "p_size"), ("p_partkey::DOUBLE", "p_size::DOUBLE"), ("p_partkey",), "p_retailprice", Viewport(1.0, 2000.0, 1.0, 50.0), 0.5)
HEAVY = Space("events", ("event_id", "user_id"), ("event_id::DOUBLE", "user_id::DOUBLE"), ("event_id",), "value", Viewport(0.0, 10000.0, 0.0, 1500.0), 0.5)
LATTICE = Space("lineitem", ("l_discount", "l_tax"), ("l_discount", "l_tax"), _KEY, "l_extendedprice", Viewport(0.0, 0.1001, 0.0, 0.0803), 0.45)


def verified(spark: SparkSession, rows: DataFrame, answered: list[tuple[str, QueryResult]]) -> DataFrame:
    """``ROWS`` of answered queries, in their order; exact values come from one scan for all."""
    asked = [replace(r.query, query_id=i) for i, (_, r) in enumerate(answered)]
    aggs = list(dict.fromkeys(a for q in asked for a in q.aggs))
    truth = {r.query_id: r.asDict() for r in full_scan(rows, workload_frame(spark, asked), aggs).collect()}  # a row per query
    out = []
    for i, (method, r) in enumerate(answered):
        for a in r.answers:
            exact = truth[i][f"{a.agg}_{a.attr}" if a.attr else "count"] if r.pop else None
            slack = 1e-9 * abs(exact or 0.0)
            off = abs((a.estimate or 0.0) - (exact or 0.0))
            held = a.ci_low is None or a.ci_low - slack <= a.estimate <= a.ci_high + slack
            out.append((method, r.query.query_id, a.agg, a.attr, r.query.eps_max, r.pop, None if exact is None else float(exact), a.exact or a.eps_est <= r.query.eps_max, held, off <= 3 * r.query.eps_max * abs(exact or 0.0) + slack, not a.exact or off <= slack))
    return spark.createDataFrame(out, ROWS).withColumn("exact_value", F.round("exact_value", 2))


def verified_sql(space: Space, queries: list[ViewportQuery], methods: tuple[str, ...]) -> str:
    """The same rows: populations and exact values of the windows, and true for all that must hold."""
    values = ", ".join(f"({q.query_id}, '{a.fn}', {'NULL' if a.attr is None else repr(a.attr)}, {q.eps_max!r}::DOUBLE, {q.window.x1!r}::DOUBLE, {q.window.x2!r}::DOUBLE, {q.window.y1!r}::DOUBLE, {q.window.y2!r}::DOUBLE)" for q in queries for a in q.aggs)
    attrs = sorted({a.attr for q in queries for a in q.aggs if a.attr})
    cases = " ".join(f"WHEN fn = '{fn}' AND attr = '{a}' THEN {sql}({a})::DOUBLE" for a in attrs for fn, sql in (("sum", "sum"), ("mean", "avg"), ("min", "min"), ("max", "max")))
    ways = ", ".join(f"('{m}')" for m in methods)
    b = space.box
    return f"""
    WITH o AS (SELECT {space.sql_axes[0]} AS ax, {space.sql_axes[1]} AS ay, * FROM {space.table}),
         w(query_id, fn, attr, eps_max, x1, x2, y1, y2) AS (VALUES {values}),
         e AS (SELECT query_id, fn, attr, eps_max, count(ax) AS pop, CASE WHEN count(ax) = 0 THEN NULL {cases} ELSE count(ax)::DOUBLE END AS exact_value
               FROM w LEFT JOIN o ON ax BETWEEN greatest(x1, {b.x1}) AND least(x2, {b.x2}) AND ay BETWEEN greatest(y1, {b.y1}) AND least(y2, {b.y2}) GROUP BY query_id, fn, attr, eps_max)
    SELECT m.method, e.query_id::INTEGER AS query_id, e.fn AS agg, e.attr, e.eps_max, e.pop, round(e.exact_value, 2) AS exact_value,
           true AS met_bound, true AS in_interval, true AS near_truth, true AS exact_right
    FROM e, (VALUES {ways}) m(method)"""


@dataclass(frozen=True)
class Workload:
    """Queries over a space, answered by some methods on an index of each method's own."""

    space: Space
    queries: tuple[ViewportQuery, ...]
    methods: tuple[str, ...] = ("ATI", "ETI", "STI")

    def shorter(self, n: int) -> Workload:
        return replace(self, queries=self.queries[:n])

    def sql(self) -> str:
        return verified_sql(self.space, list(self.queries), self.methods)

    def run(self, spark: SparkSession, sf: str) -> DataFrame:
        attrs = tuple(sorted({a.attr for q in self.queries for a in q.aggs if a.attr} | {self.space.attr}))
        rows = self.space.objects(spark, sf, attrs).persist()
        config = IndexConfig(grid=GRID, split_min=40, init="query_driven", portable_key=True)
        answered = []
        for name in self.methods:
            bounds = dict.fromkeys(q.eps_max for q in self.queries)
            for eps in bounds:  # each bound explores on an index of its own
                own = [q for q in self.queries if q.eps_max == eps]
                ix, first = build_from(rows, Domain(self.space.box, *GRID), config, [self.space.attr], own[0])
                method = METHODS[name](ix, AHEAD)
                answered += [(name, first), *((name, method.evaluate(q)) for q in own[1:])]
        out = verified(spark, rows, answered)
        rows.unpersist()
        return out


def _path(space: Space, steps: int, eps: float, *aggs: Agg, start: int = 0, **path) -> tuple[ViewportQuery, ...]:
    qs = as_queries(make_path(space.box, space.first(), steps, **path), aggs or (Agg("sum", space.attr),), eps)
    return tuple(replace(q, query_id=q.query_id + start) for q in qs)


def _bounds(space: Space, steps: int) -> tuple[ViewportQuery, ...]:
    return tuple(q for i, eps in enumerate((0.10, 0.05, 0.02, 0.01)) for q in _path(space, steps, eps, start=1000 * i))


#: The experiments: a hundred queries along a path where one path is the experiment, fewer where several are compared.
WORKLOADS = {
    "w01_uniform_path": Workload(UNIFORM, _path(UNIFORM, 100, 0.01), ("ATI",)),
    "w01_uniform_path_baselines": Workload(UNIFORM, _path(UNIFORM, 25, 0.01), ("ETI", "STI")),
    "w02_wide_rows": Workload(WIDE, _path(WIDE, 20, 0.01)),
    "w03_dense_spot": Workload(DENSE, _path(DENSE, 20, 0.05)),
    "w04_low_variance": Workload(LOW, _bounds(LOW, 10)),
    "w05_bound_sweep": Workload(UNIFORM, _bounds(UNIFORM, 10)),
    "w06_accuracy_sweep": Workload(UNIFORM, _bounds(UNIFORM, 25), ("ATI",)),
    "w08_mean": Workload(UNIFORM, _path(UNIFORM, 20, 0.02, Agg("mean", "l_quantity"))),
    "w09_region_with_zooms": Workload(UNIFORM, tuple(as_queries(make_zooms(BOX, centre_window(BOX, 0.2), 2), (Agg("sum", "l_quantity"),), 0.05)), ("ATI", "STI")),
    "w10_average_and_maximum": Workload(UNIFORM, (*_path(UNIFORM, 4, 0.10, Agg("mean", "l_extendedprice"), Agg("max", "l_extendedprice")), *_path(UNIFORM, 4, 0.01, Agg("mean", "l_extendedprice"), Agg("max", "l_extendedprice"), start=1000)), ("ATI",)),
    "w11_new_attribute": Workload(UNIFORM, tuple(switch_attribute(list(_path(UNIFORM, 10, 0.05)), 5, "l_tax")), ("ATI",)),
    "w14_heavy_tail": Workload(HEAVY, _path(HEAVY, 20, 0.05)),
    "w15_unseen_area": Workload(UNIFORM, _path(UNIFORM, 100, 0.02, jump_at=50), ("ATI",)),
    "w01_lattice": Workload(LATTICE, _path(LATTICE, 10, 0.05)),
}
for _name, _workload in WORKLOADS.items():
    query(f"{_name}_checked", _workload.sql())(lambda spark, sf, w=_workload: w.run(spark, sf))

_FIRST = as_queries([WINDOW], (Agg("sum", "l_quantity"),), 0.05)[0]


def _sql(queries: list[ViewportQuery], *methods: str) -> str:
    return verified_sql(UNIFORM, queries, methods or ("ATI",))


def _answer(spark: SparkSession, sf: str, queries: list[ViewportQuery], attrs: tuple[str, ...] = ("l_quantity",)) -> DataFrame:
    """One index for all the queries, in order."""
    ix, _ = index(spark, sf, attrs)
    return verified(spark, ix.objects, [("ATI", evaluate(ix, q)) for q in queries])


_SEVERAL = [replace(_FIRST, aggs=(Agg("sum", "l_quantity"), Agg("mean", "l_tax"), Agg("count")), eps_max=0.02)]
_TIGHTER = [ViewportQuery(WINDOW, (Agg("mean", "l_quantity"),), e, query_id=i) for i, e in enumerate((0.1, 0.05, 0.02))]


@query("m35_several_aggregates_checked", _sql(_SEVERAL))
def m35(spark, sf):
    return _answer(spark, sf, _SEVERAL)


@query("m42_aggregates_of_two_measures", _sql(_SEVERAL))
def m42(spark, sf):
    """Both measures known to the index before, sampled by one draw."""
    return _answer(spark, sf, _SEVERAL, ("l_quantity", "l_tax"))


@query("m44_tighter_bound_checked", _sql(_TIGHTER))
def m44(spark, sf):
    return _answer(spark, sf, _TIGHTER)


@query("m45_result_rows_checked", _sql([_FIRST]))
def m45(spark, sf):
    return _answer(spark, sf, [_FIRST])


@query("m41_sampling_along_a_pan", _sql([replace(_FIRST, window=WINDOW.pan(0.1 * i, 0.0), query_id=i, eps_max=0.02) for i in range(4)]))
def m41(spark, sf):
    return _answer(spark, sf, [replace(_FIRST, window=WINDOW.pan(0.1 * i, 0.0), query_id=i, eps_max=0.02) for i in range(4)])


@query("b02_sample_only_checked", _sql([_FIRST], "STI"))
def b02(spark, sf):
    ix, _ = index(spark, sf)
    return verified(spark, ix.objects, [("STI", SampleOnlyIndex(ix).evaluate(_FIRST))])


_OPS = [("query",), ("pan", 0.1, 0.0), ("zoom", 0.5), ("pan", 0.0, 0.1), ("zoom", 2.0)]


def _session_queries() -> list[ViewportQuery]:
    w, out = WINDOW, []
    for i, (op, *args) in enumerate(_OPS):
        w = w.pan(*args) if op == "pan" else w.zoom(args[0], None, BOX) if op == "zoom" else w
        out.append(replace(_FIRST, window=w, query_id=i))
    return out


@query("m05_session_checked", _sql(_session_queries()))
def m05(spark, sf):
    ix, _ = index(spark, sf)
    session = ExplorationSession(ix, WINDOW, (Agg("sum", "l_quantity"),), 0.05)
    session.run(_OPS)
    return verified(spark, ix.objects, [("ATI", r) for r in session.results])


@query("t01_progressive_checked", _sql([replace(_FIRST, eps_max=0.01)]))
def t01(spark, sf):
    """The last of the answers that come round by round."""
    ix, _ = index(spark, sf)
    *_, last = evaluate_progressive(ix, replace(_FIRST, eps_max=0.01))
    return verified(spark, ix.objects, [("ATI", last)])


_SPLIT = f"""k AS (SELECT count(*) AS k FROM t JOIN (SELECT root, count(*) AS n, count(*) FILTER ({IN_WINDOW}) AS w FROM o GROUP BY root) USING (root)
      WHERE NOT (x_lo >= {WINDOW.x1} AND x_hi <= {WINDOW.x2} AND y_lo >= {WINDOW.y1} AND y_hi <= {WINDOW.y2}) AND n > 40 AND w > 0)"""


@query("m38_split_decision", f"WITH {OBJECTS_SQL}, {TILES_SQL}, {_SPLIT} SELECT k AS divided, (100 + 4 * k)::BIGINT AS tiles, (100 + 3 * k)::BIGINT AS leaves, (SELECT count(*) FROM o)::BIGINT AS bitmap_bits FROM k")
def m38(spark, sf):
    """Cells on the window's border with enough objects are divided once; what that makes of the index's size."""
    ix, _ = index(spark, sf)
    evaluate(ix, the_query())
    size = ix.size()
    divided = sum(t.depth == 0 and not t.is_leaf for t in ix.tiles.values())
    return spark.createDataFrame([(divided, size["tiles"], size["leaves"], size["bitmap_bits"])], "divided long, tiles long, leaves long, bitmap_bits long")


@query("m14_cases_by_cell", f"WITH {OBJECTS_SQL}, {TILES_SQL} SELECT root, count(*) AS pop, bool_and(x_lo >= {WINDOW.x1} AND x_hi <= {WINDOW.x2} AND y_lo >= {WINDOW.y1} AND y_hi <= {WINDOW.y2}) AS inside, true AS case_right FROM o JOIN t USING (root) WHERE {IN_WINDOW} GROUP BY root")
def m14(spark, sf):
    """Strata by root cell, with what their cases must be: known cells inside are exact, the rest has no valid sample yet."""
    ix, _ = index(spark, sf)
    got: dict[int, list] = {}
    for s in plan_strata(ix, the_query(), SamplingPolicy()):
        got.setdefault(ix.tiles[s.tile_id].root, []).append(s)
    rows = [(root, sum(s.pop for s in strata), all(s.case == 1 for s in strata), all(s.case == (1 if s.kind == "full" and ix.tiles[s.tile_id].depth == 0 else 4) or s.case in (1, 3) for s in strata)) for root, strata in got.items()]
    return spark.createDataFrame(rows, "root int, pop long, inside boolean, case_right boolean")


@query("m23_storage_rule", f"WITH {OBJECTS_SQL}, c AS (SELECT root, {IN_WINDOW} AS i FROM o) SELECT count(DISTINCT root) AS cells, 0::BIGINT AS stored_of_partial, true AS keys_match FROM c WHERE i")
def m23(spark, sf):
    """After a query only tiles inside the window have new statistics, and a kept sample is all objects below its key."""
    ix, _ = index(spark, sf)
    evaluate(ix, the_query(eps=0.02))
    fresh = [(t, s) for (t, _), s in ix.stats.items() if ix.tiles[t].depth]
    outside = sum(ix.leaves_overlapping(WINDOW) is not None and (ix.tiles[t], "full") not in ix.leaves_overlapping(WINDOW) for t, _ in fresh)
    right = all(ix.with_tile(ix.objects, [ix.tiles[t]]).filter(F.col("rkey") < s.theta).count() == s.moments.n for t, s in fresh[:3])
    cells = len({ix.tiles[s.tile_id].root for s in plan_strata(ix, the_query(), SamplingPolicy())})
    return spark.createDataFrame([(cells, outside, right)], "cells long, stored_of_partial long, keys_match boolean")


@query("u05_window_statement_checked", f"WITH {OBJECTS_SQL} SELECT count(*) AS pop, round(sum(l_quantity)::DOUBLE, 2) AS total, true AS near FROM o WHERE {IN_WINDOW}")
def u05(spark, sf):
    ix, _ = index(spark, sf)
    w = WINDOW
    got = sqlapi.sql(ix, f"SELECT sum(l_quantity), count(*) WINDOW X BETWEEN {w.x1} AND {w.x2} Y BETWEEN {w.y1} AND {w.y2} ERROR 5% CONFIDENCE 95%").filter("agg = 'sum'")
    exact = ix.objects.filter(w.condition()).agg(F.round(F.sum("l_quantity"), 2).alias("total"))
    return got.join(exact).select("pop", "total", (F.abs(F.col("estimate") - F.col("total")) <= 0.15 * F.col("total")).alias("near"))


@query("w07_coverage_checked", "SELECT 99::BIGINT AS n, true AS covered_enough, true AS bound_kept")
def w07(spark, sf):
    """Of a hundred queries at 1% and a confidence of 95% at least nine tenths of the intervals hold the exact value."""
    rows = UNIFORM.objects(spark, sf, ("l_quantity",)).persist()
    qs = list(_path(UNIFORM, 100, 0.01))
    ix, _ = build_from(rows, Domain(BOX, *GRID), IndexConfig(grid=GRID, split_min=40, init="query_driven", portable_key=True), ["l_quantity"], qs[0])
    truth = {r.query_id: r.sum_l_quantity for r in full_scan(rows, workload_frame(spark, qs), [Agg("sum", "l_quantity")]).collect()}
    got = [evaluate(ix, q, AHEAD) for q in qs[1:]]
    rows.unpersist()
    hits = sum(r.answers[0].ci_low - 1e-6 <= truth[r.query.query_id] <= r.answers[0].ci_high + 1e-6 for r in got)
    return spark.createDataFrame([(len(got), hits >= 0.9 * len(got), all(r.answers[0].eps_est <= 0.01 for r in got))], "n long, covered_enough boolean, bound_kept boolean")


_QUANTILES = "(0.01, -2.326348, 2.558212), (0.02, -2.053749, 3.059051), (0.03, -1.880794, 3.412069), (0.04, -1.750686, 3.696541), (0.05, -1.644854, 3.940299), (0.06, -1.554774, 4.156724), (0.07, -1.475791, 4.353392), (0.08, -1.405072, 4.53505), (0.09, -1.340755, 4.704892), (0.1, -1.281552, 4.865182)"


@query("u02_quantiles_checked", f"SELECT p::DOUBLE AS p, count(*) AS n, z::DOUBLE AS z, c::DOUBLE AS chi2 FROM lineitem JOIN (VALUES {_QUANTILES}) v(p, z, c) ON round(l_discount, 2) = p::DOUBLE GROUP BY ALL")
def u02(spark, sf):
    """Quantiles at every discount that is given, as a probability; there are ten."""
    sqlapi.register_functions(spark)
    given = load_table(spark, sf, "lineitem").groupBy(F.round("l_discount", 2).alias("p")).agg(F.count("*").alias("n")).filter("p > 0 AND p < 1")
    return given.select("p", "n", F.expr("round(norm_quantile(p), 6) + 0D").alias("z"), F.expr("round(chi2_quantile(p, 10.0D), 6)").alias("chi2"))


@query("s10_generated_uniform_checked", "SELECT count(*) AS n, true AS means_right, true AS range_right, true AS independent FROM lineitem")
def s10(spark, sf):
    """Two attributes made up for every line item: means within five standard errors, values in range, columns uncorrelated."""
    key = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_shipdate", "l_extendedprice"]
    n, a0, a1 = F.count("*"), F.col("a0"), F.col("a1")
    near = lambda a: F.abs(F.avg(a) - 500) < 5 * 288.7 / F.sqrt(n)
    got = with_uniform(load_table(spark, sf, "lineitem").select(*key), key, 2)
    return got.agg(n.alias("n"), (near(a0) & near(a1)).alias("means_right"), ((F.min(a0) >= 0) & (F.max(a0) < 1000)).alias("range_right"), (F.abs(F.corr(a0, a1)) < 7 / F.sqrt(n)).alias("independent"))
