"""Invariants of tiles, samples and answers on the given tables."""

from __future__ import annotations

import math

import pytest
from hypothesis import HealthCheck, given, settings, strategies as st
from pyspark.sql import functions as F

from tileaqp.functions.quantiles import chi2_quantile, normal_quantile
from tileaqp.plans.baselines import ExactTileIndex, SampleOnlyIndex, full_scan
from tileaqp.plans.engine import count_window, evaluate, exact_extreme, next_rate
from tileaqp.plans.estimators import Moments, Stratum, answer, clt_interval, estimate_mean, estimate_sum
from tileaqp.plans.geometry import Domain, Tile, classify, gather_int, spread_int, with_codes
from tileaqp.plans.index import TileIndex, bind_objects, build_index, domain_of, write_objects
from tileaqp.plans.model import KEY_SPACE, LEVELS, Agg, AxisSpec, IndexConfig, SamplingPolicy, Viewport, ViewportQuery
from tileaqp.plans.workload import ExplorationSession, Setting, as_queries, centre_window, make_path, make_zooms, run_workload, workload_frame
from tileaqp.operators.workloads import setting

KEY = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_shipdate", "l_extendedprice"]
AXES = AxisSpec("l_extendedprice", "l_shipdate")


@pytest.fixture(scope="module")
def lineitem(spark, sf):
    return spark.read.parquet(f"{sf}/lineitem.parquet").persist()


@pytest.fixture(scope="module")
def bound(spark, lineitem):
    domain = domain_of(lineitem, AXES, (4, 4))
    return domain, bind_objects(lineitem, AXES, KEY, ["l_quantity", "l_tax"], domain).persist()


def fresh(bound, **config) -> TileIndex:
    domain, objects = bound
    config = {"grid": (4, 4), "split_min": 40, **config}
    return build_index(objects, AxisSpec("ax", "ay"), [], ["l_quantity"], IndexConfig(**config), domain=domain, objects=objects)[0]


def truth(bound, w: Viewport) -> dict:
    r = bound[1].filter(w.condition()).agg(F.count("*").alias("count"), F.sum("l_quantity").alias("sum"), F.avg("l_quantity").alias("mean"), F.var_samp("l_quantity").alias("variance"), F.stddev_samp("l_quantity").alias("stddev"), F.min("l_quantity").alias("min"), F.max("l_quantity").alias("max"))
    return r.first().asDict()


def q(w: Viewport, *fns: str, eps: float = 0.05) -> ViewportQuery:
    return ViewportQuery(w, tuple(Agg(f, None if f == "count" else "l_quantity") for f in fns), eps)


@pytest.mark.parametrize("name", ["uniform", "dense", "low_variance", "heavy_tail", "lattice", "clustered", "correlated", "negative", "medium"])
def test_codes_agree_with_bounds(spark, sf, name):
    s = setting(spark, sf, name)
    domain = domain_of(s.df, s.axes, s.grid)
    for r in bind_objects(s.df, s.axes, s.identity, s.attrs, domain).limit(300).collect():
        for depth in (0, 3, LEVELS):
            step = 4 ** (LEVELS - depth)
            lo = r.zcode // step * step
            b = Tile(0, None, depth, r.root, lo, lo + step, 1).bounds(domain)
            assert b.x1 <= r.ax and (r.ax < b.x2 or b.x2 >= domain.box.x2 * (1 - 1e-15))
            assert b.y1 <= r.ay and (r.ay < b.y2 or b.y2 >= domain.box.y2 * (1 - 1e-15))


@given(st.integers(0, (1 << LEVELS) - 1))
def test_interleaving_goes_back(v):
    assert gather_int(spread_int(v)) == v


def test_borders_null_and_nan(spark):
    d = Domain(Viewport(0.0, 3.0, 0.0, 3.0), 3, 3)
    rows = spark.createDataFrame([(0.0, 0.0), (1.0, 1.0), (3.0, 3.0), (2.0, 0.9999999999)], "ax double, ay double")
    assert [r.root for r in with_codes(rows, d).collect()] == [0, 4, 8, 2]
    bad = spark.createDataFrame([(1, None, 1.0, 5.0), (2, float("nan"), 1.0, 5.0), (3, 1.0, 1.0, None), (4, 2.0, 9.0, 1.0)], "id long, x double, y double, v double")
    assert bind_objects(bad, AxisSpec("x", "y"), ["id"], ["v"], d).count() == 1
    with pytest.raises(TypeError):
        AxisSpec("l_returnflag", "y").columns(spark.createDataFrame([("a", 1.0)], "l_returnflag string, y double"))


def test_leaves_cover_after_splits(bound):
    ix = fresh(bound)
    box = ix.domain.box
    for w in make_path(box, centre_window(box, 0.5), 4):
        evaluate(ix, q(w, "sum", eps=0.02))
    leaves = sorted(ix.leaves(), key=lambda t: t.start)
    assert len(leaves) > 16 and all(a.end <= b.start for a, b in zip(leaves, leaves[1:], strict=False))
    assert sum(t.n_objects for t in leaves) == bound[1].count()
    counts = {r.tile_id: r["count"] for r in ix.with_tile(bound[1], leaves).groupBy("tile_id").count().collect()}
    assert all(counts.get(t.tile_id, 0) == t.n_objects for t in leaves)
    for t in ix.tiles.values():
        if t.children:
            assert sum(ix.tiles[c].n_objects for c in t.children) == t.n_objects
    for (tile, attr), s in ix.stats.items():
        got = ix.with_tile(bound[1], [ix.tiles[tile]]).filter(F.col("rkey") < s.theta).agg(F.count("*"), F.sum(attr)).first()
        assert got[0] == s.moments.n and (got[1] or 0) == pytest.approx(s.moments.total)


@pytest.mark.parametrize("w", [(0.5, (0.5, 0.5)), (0.1, (0.0, 0.0)), (1.0, (0.5, 0.5)), (0.25, (0.99, 0.2))])
def test_exact_answers(bound, w):
    ix = fresh(bound)
    window = centre_window(ix.domain.box, *w)
    want = truth(bound, window)
    assert count_window(ix, window) == want["count"]
    fns = ("count", "sum", "mean", "variance", "stddev", "min", "max")
    r = evaluate(ix, q(window, *fns, eps=0.0))
    for a in r.answers:
        assert a.exact and a.estimate == pytest.approx(want[a.agg], rel=1e-9) and a.ci_low == a.ci_high
    assert ExactTileIndex(fresh(bound)).evaluate(q(window, "sum")).io_ops == evaluate(fresh(bound), q(window, "sum", eps=0.0)).io_ops
    for fn in ("min", "max"):
        assert exact_extreme(fresh(bound), window, "l_quantity", fn)[0] == want[fn]


def test_edges(bound):
    ix = fresh(bound)
    b = ix.domain.box
    outside = Viewport(b.x2 + 1, b.x2 + 2, b.y1, b.y2)
    r = evaluate(ix, q(outside, "sum", "count", "mean"))
    assert r.pop == 0 and r.io_ops == 0 and [a.estimate for a in r.answers] == [0.0, 0.0, None]
    line = Viewport(b.x1, b.x1, b.y1, b.y2)
    assert evaluate(ix, q(line, "count")).pop == truth(bound, line)["count"]
    with pytest.raises(ValueError):
        Viewport(2, 1, 0, 1)
    with pytest.raises(ValueError):
        ViewportQuery(b, (Agg("sum", "v"),), 1.0)


def test_bound_is_met_or_all_is_read_and_reuse_costs_nothing(bound):
    ix = fresh(bound)
    window = centre_window(ix.domain.box, 0.5)
    for policy in (SamplingPolicy(), SamplingPolicy(kind="fpc_aware", cap=16.0), SamplingPolicy(kind="fixed_step")):
        r = evaluate(fresh(bound), q(window, "sum", "mean", eps=0.03), policy)
        assert all(a.exact or a.eps_est <= 0.03 for a in r.answers)
        assert sum(x["new_reads"] for x in r.round_log) == r.io_ops
    whole = q(ix.domain.box, "sum", eps=0.1)
    ix2 = fresh(bound)
    ix2.stats.clear()
    first, again = evaluate(ix2, whole), evaluate(ix2, whole)
    assert first.io_ops > 0 and again.io_ops == 0 and again.answers[0].estimate == first.answers[0].estimate
    tighter = evaluate(ix2, whole.with_bound(0.01))
    assert tighter.io_ops <= ix2.domain.gx * 10_000 and tighter.answers[0].eps_est <= 0.01


def test_no_reuse_and_no_splits_is_the_sample_only_method(bound):
    window = centre_window(bound[0].box, 0.4)
    a = SampleOnlyIndex(fresh(bound)).evaluate(q(window, "sum"))
    b = evaluate(fresh(bound, adapt=False), q(window, "sum"), SamplingPolicy(reuse=False))
    assert (a.io_ops, a.rounds, a.answers[0].estimate) == (b.io_ops, b.rounds, b.answers[0].estimate)


def test_answers_dont_depend_on_partitions(bound):
    domain, objects = bound
    window = centre_window(domain.box, 0.4)
    got = []
    for n in (1, 5):
        o = objects.repartition(n)
        ix = build_index(o, AxisSpec("ax", "ay"), [], ["l_quantity"], IndexConfig(grid=(4, 4), split_min=40), domain=domain, objects=o)[0]
        r = evaluate(ix, q(window, "sum", eps=0.02))
        got.append((r.io_ops, round(r.answers[0].estimate, 6)))
    assert got[0] == got[1]


def test_unbiased_and_covered_over_seeds(lineitem, bound):
    domain = bound[0]
    window = centre_window(domain.box, 0.5)
    want = truth(bound, window)["sum"]
    keys = [F.xxhash64(*KEY, F.lit(s)).bitwiseAND(F.lit(KEY_SPACE - 1)).alias(f"k{s}") for s in range(200)]
    x, y = AXES.columns(lineitem)
    rows = with_codes(lineitem.select(x.alias("ax"), y.alias("ay"), "l_quantity", *keys), domain).filter(window.condition()).toPandas()
    estimates, inside = [], 0
    for s in range(200):
        strata = []
        for root, g in rows.groupby("root"):
            d = g[g[f"k{s}"] < KEY_SPACE // 5].l_quantity
            strata.append(Stratum(root, "partial", len(g), 3, {}, {"v": Moments(len(d), d.mean(), ((d - d.mean()) ** 2).sum(), d.min(), d.max(), len(d))}))
        a = answer(strata, Agg("sum", "v"), 0.95)
        estimates.append(a.estimate)
        inside += a.ci_low <= want <= a.ci_high
    mean = sum(estimates) / 200
    se = (sum((e - mean) ** 2 for e in estimates) / 199 / 200) ** 0.5
    assert abs(mean - want) <= 3 * se and 0.90 <= inside / 200 <= 0.99


@settings(suppress_health_check=[HealthCheck.too_slow], deadline=None)
@given(st.lists(st.floats(-1e3, 1e3), min_size=2, max_size=40), st.integers(1, 39))
def test_moments_merge(values, cut):
    def of(v):
        n = len(v)
        m = sum(v) / n if n else 0.0
        p = [sum((x - m) ** k for x in v) for k in (2, 3, 4)]
        return Moments(n, m, p[0], min(v, default=math.inf), max(v, default=-math.inf), n, p[1], p[2])

    whole, both = of(values), of(values[:cut]).merge(of(values[cut:]))
    assert both.n == whole.n and both.mean == pytest.approx(whole.mean, abs=1e-8) and both.m2 == pytest.approx(whole.m2, abs=1e-5)
    assert both.m3 == pytest.approx(whole.m3, abs=1e-1, rel=1e-6) and both.m4 == pytest.approx(whole.m4, abs=10, rel=1e-6)


def test_estimators_by_hand():
    s = [Stratum(1, "full", 3, 1, {}, {"v": Moments(3, 12, 8, filled=3)}), Stratum(2, "partial", 4, 3, {}, {"v": Moments(2, 6, 2, filled=2)})]
    assert estimate_sum(s, "v") == (60, 8.0) and estimate_mean(s, "v") == (60 / 7, 8 / 49)
    low, high = clt_interval(60, 4.0, 0.95)
    assert high - low == pytest.approx(2 * 1.959964 * 2, abs=1e-5)
    nulls = [Stratum(1, "full", 4, 1, {}, {"v": Moments(4, 1.5, 0, filled=3)})]
    assert estimate_mean(nulls, "v")[0] == 2.0
    zero = [Stratum(1, "partial", 10, 3, {}, {"v": Moments(2, 0.0, 2.0, filled=2)})]
    assert answer(zero, Agg("sum", "v"), 0.95).eps_est == math.inf


@pytest.mark.parametrize(("p", "df", "want"), [(0.95, 1, 3.841458820694124), (0.025, 10, 3.2469727802368413), (0.975, 10, 20.483177350807388), (0.5, 100, 99.33412923598846), (0.05, 2, 0.10258658877510107)])
def test_chi2_quantiles(p, df, want):
    assert chi2_quantile(p, df) == pytest.approx(want, rel=1e-6)


def test_normal_quantile_and_rates():
    assert normal_quantile(0.975) == pytest.approx(1.959963984540054)
    assert [next_rate(0.1, e, 0.02) for e in (0.0201, 0.025, 0.2)] == [pytest.approx(0.11), pytest.approx(0.15625), 0.2]
    assert next_rate(0.8, 1.0, 0.01) == 1.0


def test_query_driven_layout_adds_tiles_near_the_window(bound):
    domain, objects = bound
    window = centre_window(domain.box, 0.25, (0.2, 0.2))
    ix, first = build_index(objects, AxisSpec("ax", "ay"), [], ["l_quantity"], IndexConfig(grid=(4, 4), init="query_driven", extra=0.5), q(window, "sum"), domain, objects=objects)
    assert 16 < len(ix.leaves()) <= 24 and first.answers[0].estimate == pytest.approx(truth(bound, window)["sum"])
    assert sum(t.n_objects for t in ix.leaves()) == objects.count()
    near = min(ix.leaves(), key=lambda t: math.dist((t.bounds(domain).x1 / domain.box.width, t.bounds(domain).y1 / domain.box.height), (window.x1 / domain.box.width, window.y1 / domain.box.height)))
    assert near.depth > 0 and ix.size()["tiles"] > len(ix.leaves())


def test_save_and_load(spark, bound, tmp_path):
    ix = fresh(bound)
    window = centre_window(ix.domain.box, 0.5)
    evaluate(ix, q(window, "sum", eps=0.03))
    ix.save(f"{tmp_path}/index")
    back = TileIndex.load(spark, f"{tmp_path}/index")
    assert back.size() == ix.size()
    a, b = evaluate(ix, q(window, "sum", eps=0.02)), evaluate(back, q(window, "sum", eps=0.02))
    assert (a.io_ops, a.answers[0].estimate) == (b.io_ops, pytest.approx(b.answers[0].estimate))
    plan = back.objects.filter((F.col("rkey") < 100) & F.col("root").isin([1, 2]))._jdf.queryExecution().executedPlan().toString()
    assert "LessThan(rkey,100)" in plan and "In(root" in plan


def test_bitmaps(bound):
    ix = fresh(bound)
    ix.stats.clear()
    evaluate(ix, q(ix.domain.box, "sum", eps=0.1))
    tile = max(ix.leaves(), key=lambda t: t.n_objects)
    one = ix.bitmap(tile, "l_quantity").agg(F.sum("n_objects"), F.sum("n_read")).first()
    n = ix.stat(tile.tile_id, "l_quantity").moments.n
    assert tuple(one) == (tile.n_objects, n)
    rows = {r.tile_id: (r.n_read, r.n_objects) for r in ix.bitmap_frame("l_quantity").collect()}
    assert rows[tile.tile_id] == (n, tile.n_objects)


AHEAD = SamplingPolicy(kind="fpc_aware", cap=16.0, rate0=0.03, exhaust_below=25, pooled_floor=3, ahead=True)


def test_counting_and_reading_in_one_job(spark, bound):
    """The same populations and exact answers as in two steps; parts keep what was read of them and nothing else."""
    domain, objects = bound
    path = as_queries(make_path(domain.box, centre_window(domain.box, 0.5), 8), (Agg("sum", "l_quantity"), Agg("mean", "l_quantity"), Agg("count")), 0.05)
    ix, met = fresh(bound), 0
    exact = {r.query_id: r for r in full_scan(objects, workload_frame(spark, path), [Agg("sum", "l_quantity")]).collect()}
    for query in path:
        r = evaluate(ix, query, AHEAD)
        truth = exact[query.query_id]
        assert r.pop == truth.pop == r.answers[2].estimate and all(a.eps_est <= 0.05 for a in r.answers)
        met += r.answers[0].ci_low <= truth.sum_l_quantity <= r.answers[0].ci_high
        whole = evaluate(fresh(bound), query.with_bound(0.0), AHEAD)
        assert whole.rounds == 1 and whole.answers[0].estimate == pytest.approx(truth.sum_l_quantity)
    assert met >= 6 and len(ix.leaves()) > 16
    checked = 0
    for (tile_id, attr), stat in ix.stats.items():
        t = ix.tiles[tile_id]
        rows = ix.with_tile(objects, [t]).filter(F.col("rkey") < stat.theta)
        if t.depth and stat.moments.n and checked < 12:
            checked += 1
            got = rows.agg(F.count("*").alias("n"), F.avg(attr).alias("m")).first()
            assert got.n == stat.moments.n and got.m == pytest.approx(stat.moments.mean)
    assert checked


def test_reading_from_clustered_files(spark, bound, tmp_path):
    """Answers from files equal those from memory, and cells and keys reach the scan."""
    domain, objects = bound
    write_objects(objects, f"{tmp_path}/objects", 4)
    ix = build_index(objects, AxisSpec("ax", "ay"), [], ["l_quantity"], IndexConfig(grid=(4, 4), split_min=40), domain=domain, objects=spark.read.parquet(f"{tmp_path}/objects"))[0]
    memory = fresh(bound)
    for query in as_queries(make_path(domain.box, centre_window(domain.box, 0.4), 4), (Agg("sum", "l_quantity"),), 0.02):
        a, b = evaluate(ix, query, AHEAD), evaluate(memory, query, AHEAD)
        assert (a.io_ops, a.pop, a.rounds) == (b.io_ops, b.pop, b.rounds) and a.answers[0].estimate == pytest.approx(b.answers[0].estimate)


def test_session_and_workload(spark, lineitem, bound):
    s = ExplorationSession(fresh(bound), centre_window(bound[0].box, 0.5), (Agg("sum", "l_quantity"),), 0.1)
    rows = s.run([("query",), ("pan", 0.1, 0.0), ("zoom", 0.5), ("bound", 0.02), ("query",), ("aggs", Agg("mean", "l_tax")), ("query",)]).collect()
    assert len(rows) == 5 and rows[3].eps_max == 0.02 and rows[4].attr == "l_tax" and all(r.met_bound for r in rows)
    setting_ = Setting(lineitem, AXES, KEY, ["l_quantity"], (4, 4), 0.5, 40)
    box = bound[0].box
    got = run_workload(setting_, as_queries(make_path(box, centre_window(box, 0.5), 5), (Agg("sum", "l_quantity"),), 0.05))
    io = {m: sum(r["io_ops"] for r in got if r["method"] == m and r["query_id"]) for m in ("ATI", "ETI", "STI")}
    assert io["ATI"] < io["ETI"] and all(r["rel_err"] < 1e-9 for r in got if r["method"] == "ETI")
    assert sum(r["rel_err"] <= 0.05 for r in got if r["method"] == "ATI") >= 4


def test_paths_stay_inside(bound):
    box = bound[0].box
    for w in make_path(box, centre_window(box, 0.3), 100, jump_at=50) + [w for _, w in make_zooms(box, centre_window(box, 0.3))]:
        assert box.x1 - 1e-6 <= w.x1 <= w.x2 <= box.x2 + 1e-6 and box.y1 - 1e-6 <= w.y1 <= w.y2 <= box.y2 + 1e-6
    assert make_path(box, centre_window(box, 0.3), 9) == make_path(box, centre_window(box, 0.3), 9)


def test_full_scan_answers_a_workload_in_one_pass(spark, bound):
    box = bound[0].box
    qs = as_queries(make_path(box, centre_window(box, 0.4), 3), (Agg("sum", "l_quantity"),), 0.05)
    got = {r.query_id: r for r in full_scan(bound[1], workload_frame(spark, qs), [Agg("sum", "l_quantity"), Agg("count")]).collect()}
    for x in qs:
        assert got[x.query_id].sum_l_quantity == pytest.approx(truth(bound, x.window)["sum"])


def test_containment():
    t = Viewport(0, 1, 0, 1)
    assert [classify(t, Viewport(*w)) for w in ((0, 1, 0, 1), (0.5, 2, 0, 1), (2, 3, 0, 1), (1, 2, 0, 1), (0.2, 0.3, 0.2, 0.3))] == ["full", "partial", "disjoint", "partial", "partial"]
    assert Viewport(0, 10, 0, 10).zoom(0.5) == Viewport(2.5, 7.5, 2.5, 7.5) and Viewport(0, 10, 0, 10).pan(0.1, 0) == Viewport(1, 11, 0, 10)
    px = Viewport(0, 10, 0, 10).to_pixels(5, 5, 100, 50)
    assert px == (50, 25) and Viewport(0, 10, 0, 10).from_pixels(*px, 100, 50) == (5, 5)


def test_written_objects_are_clustered(spark, bound, tmp_path):
    write_objects(bound[1], f"{tmp_path}/o", 2)
    assert spark.read.parquet(f"{tmp_path}/o").count() == bound[1].count()


def test_fixed_sizes_per_stratum(bound):
    ix = fresh(bound, adapt=False)
    ix.stats.clear()
    policy = SamplingPolicy(rate0=0.2, draw="fixed_n", floor=2, exhaust_below=2)
    r = evaluate(ix, q(ix.domain.box, "sum", eps=0.2), policy)
    want = sum(math.ceil(int(0.2 * KEY_SPACE) / KEY_SPACE * t.n_objects) for t in ix.leaves())
    assert r.rounds == 1 and r.io_ops == want


def test_divided_tiles_can_keep_what_they_knew(bound):
    window = centre_window(bound[0].box, 0.3, (0.4, 0.4))
    around = centre_window(bound[0].box, 0.9)
    io = {}
    for keep in (False, True):
        ix = fresh(bound, reuse_parent=keep)
        evaluate(ix, q(window, "sum", eps=0.02))
        r = evaluate(ix, q(around, "sum", eps=0.0))
        io[keep] = r.io_ops
        assert r.answers[0].estimate == pytest.approx(truth(bound, around)["sum"])
    assert io[True] < io[False]
