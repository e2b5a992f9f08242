"""Every option of the engine over two windows of one path, and the sources, sinks and streams, held against SQL.

Each option's queries return, for each of its values (in the column ``method``), the
population and exact value of each window and whether the answer kept what was promised. Text
copies of tables are written to the session's shared folder.
"""

from __future__ import annotations

import uuid
from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession, functions as F, types as T

from ..plans.engine import evaluate
from ..plans.geometry import Domain
from ..plans.index import TileIndex, bind_objects, build_index, write_objects
from ..plans.metrics import bound_compliance, coverage, engine_io, per_query, speedup, totals
from ..plans.model import KEY_SPACE, Agg, AxisSpec, IndexConfig, QueryResult, SamplingPolicy, Viewport, ViewportQuery
from ..plans.workload import Setting, as_queries, metrics_frame, run_workload
from ..runtime import durable, shared_root
from ..sources import csv_offsets
from ..sources.tables import load_csv, load_json, load_table, write_rows, write_wide_csv
from ..streaming import events as streams
from .checked import UNIFORM, verified, verified_sql
from .methods import AXES, BOX, GRID, IDENTITY, IN_WINDOW, OBJECTS_SQL, TILES_SQL, WINDOW, index, objects
from .registry import query

BASE = IndexConfig(grid=GRID, split_min=40, portable_key=True)
POLICY = SamplingPolicy()
SUM = (Agg("sum", "l_quantity"),)
#: The second window overlaps the first by nine tenths, so that it meets what the first one divided and kept.
WINDOWS = (WINDOW, WINDOW.pan(0.1, 0.0))
TWO = tuple(as_queries(WINDOWS, SUM, 0.02))
TIGHT = tuple(replace(q, eps_max=0.01) for q in TWO)

#: Each option: its values as (layout, policy), over the same queries.
OPTIONS: dict[str, tuple[tuple[ViewportQuery, ...], dict[str, tuple[IndexConfig, SamplingPolicy]]]] = {
    "v01_initialization": (TWO, {k: (replace(BASE, init=k), POLICY) for k in ("flat", "query_driven")}),
    "v02_grid_size": (TWO, {f"grid_{n}": (replace(BASE, grid=(n, n)), POLICY) for n in (5, 10, 20)}),
    "v03_split_threshold": (TWO, {f"over_{n}": (replace(BASE, split_min=n), POLICY) for n in (20, 200)}),
    "v04_fan_out": (TWO, {f"parts_{n}": (replace(BASE, fan_out=n), POLICY) for n in (4, 16, 64)}),
    "v05_split_depth": (TWO, {f"levels_{n}": (replace(BASE, depth_per_query=n), POLICY) for n in (1, 2)}),
    "v06_split_scope": (TWO, {k: (replace(BASE, split_scope=k), POLICY) for k in ("partial", "all_overlapping")}),
    "v07_split_gain": (TWO, {k: (replace(BASE, gain=k), POLICY) for k in ("count_threshold", "expected_reuse")}),
    "v08_adaptation": (TWO, {f"adapt_{k}".lower(): (replace(BASE, adapt=k), POLICY) for k in (True, False)}),
    "v09_reuse": (TWO, {f"reuse_{k}".lower(): (BASE, replace(POLICY, reuse=k)) for k in (True, False)}),
    "v10_sample_sizes": (TIGHT, {k: (BASE, replace(POLICY, draw=k)) for k in ("threshold", "fixed_n", "neyman")}),
    "v11_strata_of_samples": (TWO, {k: (replace(BASE, adapt=False), replace(POLICY, reuse=False, strata=k)) for k in ("tiles", "single")}),
    "v12_rate_policy": (TIGHT, {k: (BASE, replace(POLICY, kind=k, cap=1.3 if k == "fixed_step" else 2.0)) for k in ("error_ratio", "fixed_step")}),
    "v13_cap": (TIGHT, {f"cap_{c:g}": (BASE, replace(POLICY, cap=c)) for c in (1.5, 2.0, 16.0)}),
    "v14_minimum_growth": (TIGHT, {f"step_{c:g}": (BASE, replace(POLICY, min_step=c)) for c in (1.1, 1.5)}),
    "v15_first_rate": (TWO, {f"rate_{r:g}": (BASE, replace(POLICY, rate0=r)) for r in (0.005, 0.01, 0.1)}),
    "v21_reuse_of_parents": (TWO, {f"parents_{k}".lower(): (replace(BASE, reuse_parent=k), POLICY) for k in (True, False)}),
    "v22_kept_rows": (TWO, {f"kept_{r:g}": (replace(BASE, keep_rows=r), POLICY) for r in (0.0, 0.1, 1.0)}),
    "v23_small_strata": (TWO, {f"whole_up_to_{n}": (BASE, replace(POLICY, exhaust_below=n)) for n in (0, 10, 100)}),
    "v24_rate_from_variances": (TIGHT, {k: (BASE, replace(POLICY, kind="fpc_aware", cap=16.0, ahead=k == "ahead")) for k in ("in_steps", "ahead")}),
}


def explore(spark: SparkSession, rows: DataFrame, config: IndexConfig, policy: SamplingPolicy, queries: tuple[ViewportQuery, ...]) -> list[QueryResult]:
    """The queries in order on a new index; the grid may be another than that of ``rows``, which then are placed anew."""
    domain = Domain(BOX, *config.grid)
    first = queries[0] if config.init == "query_driven" else None
    ix, _ = build_index(rows, AxisSpec("ax", "ay"), [], ["l_quantity"], config, first, domain, objects=rows)
    return [evaluate(ix, q, policy) for q in queries]


def option(spark: SparkSession, sf: str, queries: tuple[ViewportQuery, ...], cases: dict[str, tuple[IndexConfig, SamplingPolicy]]) -> DataFrame:
    base = objects(spark, sf).persist()
    answered = []
    for name, (config, policy) in cases.items():
        rows = base if config.grid == GRID else bind_objects(load_table(spark, sf, "lineitem"), AXES, IDENTITY, ["l_quantity"], Domain(BOX, *config.grid), 7, True)
        answered += [(name, r) for r in explore(spark, rows, config, policy, queries)]
    out = verified(spark, base, answered)
    base.unpersist()
    return out


for _name, (_queries, _cases) in OPTIONS.items():
    query(_name, verified_sql(UNIFORM, list(_queries), tuple(_cases)))(lambda spark, sf, q=_queries, c=_cases: option(spark, sf, q, c))

_BOUNDS = [replace(TWO[0], eps_max=e, query_id=i) for i, e in enumerate((0.10, 0.05, 0.02, 0.01, 0.0))]


@query("v17_bounds", verified_sql(UNIFORM, _BOUNDS, ("ATI",)))
def v17(spark, sf):
    """The same window on an index that learns, the bound ever tighter, at last exact."""
    rows = objects(spark, sf)
    return verified(spark, rows, [("ATI", r) for r in explore(spark, rows, BASE, POLICY, tuple(_BOUNDS))])


_KINDS = [replace(TWO[0], aggs=tuple(Agg(f, None if f == "count" else "l_quantity") for f in ("count", "sum", "mean", "min", "max")))]


@query("v18_aggregates", verified_sql(UNIFORM, _KINDS, ("ATI",)))
def v18(spark, sf):
    rows = objects(spark, sf)
    return verified(spark, rows, [("ATI", r) for r in explore(spark, rows, BASE, POLICY, tuple(_KINDS))])


@query("v18_spread", f"WITH {OBJECTS_SQL} SELECT count(*) AS pop, round(var_samp(l_quantity), 4) AS variance, round(stddev_samp(l_quantity), 4) AS stddev FROM o WHERE {IN_WINDOW}")
def v18b(spark, sf):
    """Variance and standard deviation in exact mode."""
    q = replace(TWO[0], aggs=(Agg("variance", "l_quantity"), Agg("stddev", "l_quantity")), eps_max=0.0)
    r = explore(spark, objects(spark, sf), BASE, POLICY, (q,))[0]
    return spark.createDataFrame([(r.pop, *(a.estimate for a in r.answers))], "pop long, variance double, stddev double").select("pop", F.round("variance", 4).alias("variance"), F.round("stddev", 4).alias("stddev"))


@query("v16_confidence", "SELECT gamma::DOUBLE AS gamma, true AS width_in_order, true AS met_bound FROM (VALUES (0.9), (0.95), (0.99)) v(gamma)")
def v16(spark, sf):
    """One sample, three confidences: the interval widens with each, by the quotient of the normal quantiles."""
    from ..functions.quantiles import two_sided_z

    rows, out, widths = objects(spark, sf).persist(), [], {}
    for gamma in (0.9, 0.95, 0.99):
        r = explore(spark, rows, replace(BASE, adapt=False), replace(POLICY, rate0=0.05, strata="tiles", reuse=False), (replace(TWO[0], eps_max=0.5, gamma=gamma),))[0].answers[0]
        widths[gamma] = (r.ci_high - r.ci_low) / two_sided_z(gamma)
        out.append((gamma, abs(widths[gamma] - widths[0.9]) <= 1e-6 * widths[0.9], r.eps_est <= 0.5))
    rows.unpersist()
    return spark.createDataFrame(out, "gamma double, width_in_order boolean, met_bound boolean")


@query("v22_reads_of_kept_rows", "SELECT true AS fewer, true AS samples_match")
def v22(spark, sf):
    """What divided tiles pass on is not read again, and is the sample that reading would give."""
    rows = objects(spark, sf).persist()
    reads, right = {}, True
    for kept in (0.0, 1.0):
        ix, _ = build_index(rows, AxisSpec("ax", "ay"), [], ["l_quantity"], replace(BASE, keep_rows=kept), None, Domain(BOX, *GRID), objects=rows)
        reads[kept] = sum(evaluate(ix, q).io_ops for q in TWO)
        for (t, a), s in list(ix.stats.items())[-3:]:
            right = right and ix.with_tile(rows, [ix.tiles[t]]).filter(F.col("rkey") < s.theta).count() == s.moments.n
    rows.unpersist()
    return spark.createDataFrame([(reads[1.0] <= reads[0.0], right)], "fewer boolean, samples_match boolean")


# ---- measures -------------------------------------------------------------------------


def _metrics(spark: SparkSession, sf: str) -> DataFrame:
    """Three windows by all three methods, with Spark's own reading."""
    s = Setting(load_table(spark, sf, "lineitem"), AXES, [*IDENTITY, "l_shipdate", "l_extendedprice"], ["l_quantity"], (4, 4), 0.5, 40)
    qs = as_queries([WINDOW, *(WINDOW.pan(0.1 * i, 0.05 * i) for i in (1, 2))], SUM, 0.05)
    return metrics_frame(spark, run_workload(s, qs, cache=False))


_METHODS = "(VALUES ('ATI'), ('ETI'), ('STI')) m(method)"


@query("c01_c05_cost_measures", f"SELECT method, 2::BIGINT AS queries, true AS timed, true AS sums_right, true AS rounds_right FROM {_METHODS}")
def c01(spark, sf):
    """Time, reads and rounds of each query add up to the workload's, the first query apart."""
    m = durable(_metrics(spark, sf), "metrics")
    each = per_query(m).filter("query_id > 0").groupBy("method").agg(F.count("*").alias("queries"), (F.min("wall_ms") > 0).alias("timed"), F.sum("io_ops").alias("io"), F.avg("rounds").alias("mean"))
    t = totals(m).select("method", "io_total", "mean_rounds")
    return each.join(t, "method").select("method", "queries", "timed", (F.col("io") == F.col("io_total")).alias("sums_right"), (F.abs(F.col("mean") - F.col("mean_rounds")) < 1e-9).alias("rounds_right"))


@query("c07_c12_accuracy_measures", f"SELECT method, 2::BIGINT AS n, true AS width_right, true AS compliance_right, true AS estimated_kept FROM {_METHODS}")
def c07(spark, sf):
    """Estimated error within the bound, interval width of nought for the exact method alone, actual error within thrice the bound."""
    m = durable(_metrics(spark, sf), "metrics")
    kept = m.filter("query_id > 0").groupBy("method").agg((F.max("eps_est") <= 0.05).alias("estimated_kept"))
    rows = coverage(m).join(bound_compliance(m), ["method", "eps_max"]).join(kept, "method")
    return rows.select("method", "n", F.when(F.col("method") == "ETI", F.abs("mean_width") < 1e-3).otherwise(F.col("mean_width") >= 0).alias("width_right"), (F.col("max_rel_err") <= 0.15).alias("compliance_right"), "estimated_kept")


@query("c10_speedup_checked", "SELECT base, true AS positive FROM (VALUES ('STI'), ('ETI')) v(base)")
def c10(spark, sf):
    m = durable(_metrics(spark, sf), "metrics")
    return speedup(m, "STI").unionByName(speedup(m, "ETI")).select("base", ((F.col("time_ratio") > 0) & (F.col("io_ratio") > 0)).alias("positive"))


@query("c14_physical_reads", f"SELECT method, true AS bytes_known FROM {_METHODS}")
def c14(spark, sf):
    """Bytes that Spark read from files for each later query, where it read any objects."""
    m = _metrics(spark, sf).filter("query_id > 0")
    return m.groupBy("method").agg(F.min((F.col("bytes_read") > 0) | (F.col("io_ops") == 0)).alias("bytes_known"))


# ---- sources and sinks ----------------------------------------------------------------

LINES_SCHEMA = T.StructType([T.StructField(n, k) for n, k in (("l_orderkey", T.LongType()), ("l_linenumber", T.LongType()), ("l_quantity", T.DoubleType()), ("l_extendedprice", T.DoubleType()), ("l_returnflag", T.StringType()))])
PLACED_SCHEMA = T.StructType([*LINES_SCHEMA.fields, T.StructField("file", T.StringType()), T.StructField("pos", T.LongType())])
BY_FLAG = "SELECT l_returnflag, count(*) AS n, round(sum(l_quantity), 2) AS total FROM lineitem GROUP BY l_returnflag"


def _folder(spark: SparkSession, name: str) -> str:
    return f"{shared_root(spark)}/{name}-{uuid.uuid4().hex}"


def _lines(spark: SparkSession, sf: str) -> DataFrame:
    return load_table(spark, sf, "lineitem").select(*(F.col(f.name).cast(f.dataType) for f in LINES_SCHEMA))


def _copy(spark: SparkSession, sf: str, kind: str) -> str:
    path = _folder(spark, kind)
    write_rows(_lines(spark, sf), path, kind)
    return path


def _by_flag(rows: DataFrame) -> DataFrame:
    return rows.groupBy("l_returnflag").agg(F.count("*").alias("n"), F.round(F.sum("l_quantity"), 2).alias("total"))


@query("s01_positions", "SELECT count(*) AS n, count(*) AS places, 0::BIGINT AS first_pos FROM lineitem")
def s01(spark, sf):
    """Every row has a place of its own: its file and its number in it."""
    return load_table(spark, sf, "lineitem", positions=True).agg(F.count("*").alias("n"), F.count_distinct("file", "pos").alias("places"), F.min("pos").alias("first_pos"))


@query("s02_csv_with_schema", BY_FLAG)
def s02(spark, sf):
    return _by_flag(load_csv(spark, _copy(spark, sf, "csv"), LINES_SCHEMA))


@query("s03_json_lines", BY_FLAG)
def s03(spark, sf):
    return _by_flag(load_json(spark, _copy(spark, sf, "json"), LINES_SCHEMA))


@query("s04_csv_with_offsets", BY_FLAG.replace("count(*) AS n,", "count(*) AS n, count(*) AS places,"))
def s04(spark, sf):
    """The byte of each row's start is its place; ranges of numbers reach the reader."""
    csv_offsets.register(spark)
    rows = spark.read.format("csv_offsets").schema(PLACED_SCHEMA).load(_copy(spark, sf, "csv"))
    return rows.groupBy("l_returnflag").agg(F.count("*").alias("n"), F.count_distinct("file", "pos").alias("places"), F.round(F.sum("l_quantity"), 2).alias("total"))


def _fetched(spark: SparkSession, sf: str, order: str) -> DataFrame:
    csv_offsets.register(spark)
    path = _copy(spark, sf, "csv")
    chosen = spark.read.format("csv_offsets").schema(PLACED_SCHEMA).load(path).filter("l_quantity >= 49")
    return csv_offsets.fetch(spark, path, LINES_SCHEMA, chosen, order).select("l_orderkey", "l_linenumber", "l_quantity")


_FETCHED = "SELECT l_orderkey::BIGINT AS l_orderkey, l_linenumber::BIGINT AS l_linenumber, l_quantity::DOUBLE AS l_quantity FROM lineitem WHERE l_quantity >= 49"


@query("m21_offset_ordered_reads", _FETCHED)
def m21(spark, sf):
    """Rows at given bytes, in the order of the file."""
    return _fetched(spark, sf, "offset")


@query("s05_point_reads", _FETCHED)
def s05(spark, sf):
    return _fetched(spark, sf, "none")


@query("v19_read_order", "SELECT count(*) AS n, true AS forward, true AS shorter_way FROM lineitem WHERE l_quantity >= 49")
def v19(spark, sf):
    """The way of the reading head over the chosen rows, by place and by draw key: bytes passed over between one row and the next."""
    csv_offsets.register(spark)
    path = _copy(spark, sf, "csv")
    rows = spark.read.format("csv_offsets").schema(PLACED_SCHEMA).load(path).filter("l_quantity >= 49")
    rows = durable(rows.select("file", "pos", F.xxhash64("l_orderkey", "l_linenumber", F.lit(7)).alias("key")), "places")
    from pyspark.sql import Window

    step = lambda by: F.col("pos") - F.lag("pos").over(Window.partitionBy("file").orderBy(by))
    moves = rows.select(step("pos").alias("sorted"), step("key").alias("drawn"))
    return moves.agg(F.count("*").alias("n"), (F.coalesce(F.min("sorted"), F.lit(0)) >= 0).alias("forward"), (F.coalesce(F.sum(F.abs("sorted")), F.lit(0)) <= F.coalesce(F.sum(F.abs("drawn")), F.lit(0))).alias("shorter_way"))


@query("v20_file_kinds", f"SELECT kind, l_returnflag, n, total FROM ({BY_FLAG}), (VALUES ('csv'), ('json'), ('parquet')) k(kind)")
def v20(spark, sf):
    load = {"csv": load_csv, "json": load_json, "parquet": lambda spark, path, schema: spark.read.schema(schema).parquet(path)}
    out = None
    for kind, read in load.items():
        rows = _by_flag(read(spark, _copy(spark, sf, kind), LINES_SCHEMA)).select(F.lit(kind).alias("kind"), "l_returnflag", "n", "total")
        out = rows if out is None else out.unionByName(rows)
    return out


@query("s06_saved_index", verified_sql(UNIFORM, list(TWO), ("saved", "loaded")))
def s06(spark, sf):
    """An index that has learned, and the same written and read again: both answer the next window."""
    rows = objects(spark, sf)
    ix, _ = build_index(rows, AxisSpec("ax", "ay"), [], ["l_quantity"], BASE, None, Domain(BOX, *GRID), objects=rows)
    answered = [("saved", evaluate(ix, TWO[0]))]
    path = _folder(spark, "index")
    ix.save(path)
    again = TileIndex.load(spark, path)
    answered += [("loaded", evaluate(again, TWO[0])), ("saved", evaluate(ix, TWO[1])), ("loaded", evaluate(again, TWO[1]))]
    return verified(spark, rows, answered)


@query("s07_sinks", "SELECT kind, n, true AS same FROM (VALUES ('csv', 2::BIGINT), ('json', 2::BIGINT), ('parquet', 2::BIGINT)) v(kind, n)")
def s07(spark, sf):
    """Result rows written as each kind and read again."""
    ix, _ = index(spark, sf)
    result = durable(evaluate(ix, replace(TWO[0], aggs=(Agg("sum", "l_quantity"), Agg("count")))).to_df(spark), "result")
    out = []
    for kind in ("csv", "json", "parquet"):
        path = _folder(spark, kind)
        write_rows(result, path, kind)
        reader = spark.read.schema(result.schema)
        back = (reader.option("header", True) if kind == "csv" else reader).format(kind).load(path)
        out.append((kind, back.count(), back.exceptAll(result).isEmpty()))
    return spark.createDataFrame(out, "kind string, n long, same boolean")


@query("s08_clustered_objects", f"WITH {OBJECTS_SQL} SELECT count(*) AS pop, round(sum(l_quantity)::DOUBLE, 2) AS total, true AS reads_less FROM o WHERE {IN_WINDOW}")
def s08(spark, sf):
    """Objects in files by cell and draw key: a window's exact sum, from fewer rows than there are where files have several row groups."""
    path = _folder(spark, "objects")
    rows = objects(spark, sf)
    write_objects(rows, path, 16)
    stored = spark.read.parquet(path)
    ix, _ = build_index(stored, AxisSpec("ax", "ay"), [], [], BASE, None, Domain(BOX, *GRID), objects=stored)
    got: list[QueryResult] = []
    read = engine_io(spark, lambda: got.append(evaluate(ix, replace(TWO[0], eps_max=0.0))))
    n = sum(t.n_objects for t in ix.leaves())
    return spark.createDataFrame([(got[0].pop, got[0].answers[0].estimate, read["input_records"] < 2 * n)], "pop long, total double, reads_less boolean").withColumn("total", F.round("total", 2))


@query("s09_wide_file", "SELECT count(*) AS n, round(sum(o_totalprice), 2) AS total, count(c_name) AS customers FROM lineitem LEFT JOIN orders ON l_orderkey = o_orderkey LEFT JOIN customer ON o_custkey = c_custkey")
def s09(spark, sf):
    """The wide rows as text, read again with their schema."""
    path = _folder(spark, "wide")
    wide = write_wide_csv(spark, sf, path)
    back = spark.read.schema(wide.schema).option("header", True).option("timestampFormat", "yyyy-MM-dd HH:mm:ss").csv(path)
    return back.agg(F.count("*").alias("n"), F.round(F.sum("o_totalprice"), 2).alias("total"), F.count("c_name").alias("customers"))


# ---- streams --------------------------------------------------------------------------

_EVENT_AXES = AxisSpec("event_id", "user_id")
_EVENT_BOX = Domain(Viewport(0.0, 1e9, 0.0, 1e9), 4, 4)


def _event_stream(spark: SparkSession, sf: str) -> tuple[DataFrame, DataFrame]:
    """The events, and the same as a stream of several files."""
    rows = load_table(spark, sf, "events")
    path = _folder(spark, "events")
    rows.repartitionByRange(4, "ts").write.parquet(path)
    return rows, streams.stream_of(spark, path, rows.schema)


@query("t02_stream_into_tiles", "SELECT count(*) AS n, round(sum(value), 2) AS total, true AS exact FROM events WHERE event_id IS NOT NULL AND user_id IS NOT NULL")
def t02(spark, sf):
    """Tiles made of half the events take up the rest as a stream; the whole domain is then answered exactly."""
    rows, stream = _event_stream(spark, sf)
    bind = lambda d: bind_objects(d, _EVENT_AXES, ["event_id"], ["value"], _EVENT_BOX)
    first = bind(rows.filter("event_id % 2 = 0"))
    ix, _ = build_index(first, AxisSpec("ax", "ay"), [], ["value"], IndexConfig(grid=(4, 4), split_min=10), None, _EVENT_BOX, objects=first)
    streams.stream_into_index(stream.filter("event_id % 2 = 1"), ix, bind, _folder(spark, "progress")).awaitTermination()
    r = evaluate(ix, ViewportQuery(_EVENT_BOX.box, (Agg("sum", "value"),), 0.0))
    return spark.createDataFrame([(r.pop, r.answers[0].estimate, r.answers[0].exact)], "n long, total double, exact boolean").withColumn("total", F.round("total", 2))


def _drain(frame: DataFrame, spark: SparkSession, mode: str) -> DataFrame:
    """All that a stream gives until its input ends, by batches into one table."""
    path, taken = _folder(spark, "drained"), set()

    def take(batch: DataFrame, number: int) -> None:
        if number not in taken:
            batch.withColumn("batch", F.lit(number)).write.mode("append").parquet(path)
            taken.add(number)

    frame.writeStream.foreachBatch(take).outputMode(mode).option("checkpointLocation", _folder(spark, "progress")).trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(T.StructType([*frame.schema.fields, T.StructField("batch", T.IntegerType())])).parquet(path)


@query("t04_watermark", "SELECT count(*) > 0 AS closed_some, true AS closed_are_right FROM events")
def t04(spark, sf):
    """Hours that the watermark closed have all their events; later rows change none of them."""
    rows, stream = _event_stream(spark, sf)
    closed = _drain(streams.windowed_counts(stream, "tumbling"), spark, "append")
    whole = streams.windowed_counts(rows.withColumn("ts", F.col("ts").cast("timestamp")), "tumbling")
    both = closed.join(whole.select("start", "event_type", F.col("n").alias("want")), ["start", "event_type"], "left")
    return both.agg((F.count("*") > 0).alias("closed_some"), F.coalesce(F.min(F.col("n") <= F.col("want")), F.lit(True)).alias("closed_are_right"))


@query("t05_repeated_events", "SELECT count(DISTINCT event_id) AS n, true AS once FROM events")
def t05(spark, sf):
    """Each event once, from a stream in which files repeat."""
    rows = load_table(spark, sf, "events")
    path = _folder(spark, "events")
    rows.coalesce(1).write.parquet(path)
    rows.limit(0).write.mode("append").parquet(path)
    rows.coalesce(1).write.mode("append").parquet(path)
    got = _drain(streams.without_repeats(streams.stream_of(spark, path, rows.schema), "20000 days").select("event_id"), spark, "append")
    return got.groupBy("event_id").agg(F.count("*").alias("k")).agg(F.count("*").alias("n"), (F.max("k") == 1).alias("once"))


@query("t05_bounded_state", "SELECT event_type AS cell, count(*) AS n, least(count(*), 32) AS sampled FROM events GROUP BY event_type")
def t05b(spark, sf):
    """Count and a sample of at most 32 values per kind of event, in state that doesn't grow."""
    _, stream = _event_stream(spark, sf)
    got = _drain(streams.sampled_cells(stream), spark, "update")
    return got.groupBy("cell").agg(F.max("n").alias("n"), F.max("sampled").cast("long").alias("sampled"))


@query("w13_walk_through", f"WITH {OBJECTS_SQL}, {TILES_SQL}, c AS (SELECT root, count(*) AS n, count(*) FILTER ({IN_WINDOW}) AS w FROM o GROUP BY root) SELECT count(*) FILTER (w > 0) AS cells, sum(w)::BIGINT AS pop, true AS right FROM c")
def w13(spark, sf):
    """One query step by step: cells met, objects counted, samples kept only of tiles inside the window and equal to all objects below their key."""
    rows = objects(spark, sf)
    ix, _ = build_index(rows, AxisSpec("ax", "ay"), [], ["l_quantity"], BASE, None, Domain(BOX, *GRID), objects=rows)
    before = set(ix.stats)
    r = evaluate(ix, TWO[0])
    cells = rows.filter(WINDOW.condition()).select("root").distinct().count()
    full = {t.tile_id for t, kind in ix.leaves_overlapping(WINDOW) if kind == "full"}
    fresh = [k for k in ix.stats if k not in before]
    right = all(t in full for t, _ in fresh) and all(ix.stats[k].theta <= KEY_SPACE for k in fresh) and r.answers[0].eps_est <= 0.02
    return spark.createDataFrame([(cells, r.pop, right)], "cells long, pop long, right boolean")
