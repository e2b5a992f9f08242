"""Files by offset, text files with a schema, generated tables, SQL surface and streams."""

from __future__ import annotations

import pytest
from pyspark.sql import functions as F

from tileaqp.functions import sqlapi
from tileaqp.operators.methods import BOX, WINDOW, index
from tileaqp.plans.engine import evaluate
from tileaqp.plans.geometry import Domain
from tileaqp.plans.index import bind_objects, build_index, domain_of
from tileaqp.plans.model import Agg, AxisSpec, IndexConfig, Viewport, ViewportQuery
from tileaqp.plans.workload import Setting, as_queries, centre_window, make_path, run_workload
from tileaqp.sources import csv_offsets
from tileaqp.sources.tables import gen_uniform, load_csv, load_json, load_table, wide_rows, write_rows
from tileaqp.streaming import events as streams

SCHEMA = "l_orderkey long, l_quantity double, l_extendedprice double, l_returnflag string"


@pytest.fixture(scope="module")
def lines(spark, sf, tmp_path_factory):
    folder = tmp_path_factory.mktemp("text")
    rows = spark.read.parquet(f"{sf}/lineitem.parquet").selectExpr("l_orderkey", "l_quantity", "l_extendedprice", "l_returnflag")
    write_rows(rows.repartition(3), f"{folder}/csv", "csv")
    write_rows(rows.repartition(2), f"{folder}/json", "json")
    return rows, str(folder)


def schema(text: str):
    from pyspark.sql.types import StructType

    return StructType.fromDDL(text)


def test_csv_and_json_with_a_schema(spark, lines):
    rows, folder = lines
    for got in (load_csv(spark, f"{folder}/csv", schema(SCHEMA)), load_json(spark, f"{folder}/json", schema(SCHEMA))):
        assert not [r for r in got.collect() if r._corrupt]
        assert got.select(rows.columns).exceptAll(rows).count() == 0 and got.count() == rows.count()


def test_offset_source_reads_the_same_rows(spark, lines):
    rows, folder = lines
    csv_offsets.register(spark)
    got = spark.read.format("csv_offsets").schema(SCHEMA + ", file string, pos long").option("splitBytes", 10_000).load(f"{folder}/csv")
    assert got.select(rows.columns).exceptAll(rows).count() == 0 and got.count() == rows.count()
    assert got.select("file", "pos").distinct().count() == rows.count()
    few = got.filter("l_quantity between 10 and 12")
    assert few.count() == rows.filter("l_quantity between 10 and 12").count()
    chosen = got.filter("l_orderkey % 50 = 0")
    for order in ("offset", "none"):
        back = csv_offsets.fetch(spark, f"{folder}/csv", schema(SCHEMA), chosen.select("file", "pos"), order)
        assert sorted(back.collect()) == sorted(chosen.select(rows.columns).collect())


def test_pushed_ranges_reach_the_reader():
    from pyspark.sql.datasource import GreaterThanOrEqual, In

    reader = csv_offsets.OffsetReader(schema(SCHEMA), {"path": "/nowhere"})
    left = list(reader.pushFilters([GreaterThanOrEqual(("l_quantity",), 5.0), In(("l_returnflag",), ("A",))]))
    assert reader.tests == [("l_quantity", ">=", 5.0)] and len(left) == 1
    with pytest.raises(TypeError):
        csv_offsets.OffsetReader(schema("a date"), {"path": "/nowhere"})


def test_row_width_doesnt_change_what_is_read(spark, sf):
    key = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_shipdate", "l_extendedprice"]
    io = []
    for df in (load_table(spark, sf, "lineitem"), wide_rows(spark, sf)):
        s = Setting(df, AxisSpec("l_extendedprice", "l_shipdate"), key, ["l_quantity"], (4, 4), 0.5, 40)
        box = domain_of(df, s.axes, s.grid).box
        io.append([r["io_ops"] for r in run_workload(s, as_queries(make_path(box, centre_window(box, 0.5), 3), (Agg("sum", "l_quantity"),), 0.05), ("ATI",))])
    assert io[0] == io[1]


def test_generated_tables_and_positions(spark, sf):
    a = gen_uniform(spark, 1000, 3)
    assert a.columns == ["oid", "a0", "a1", "a2"] and a.filter("a0 < 0 or a0 >= 1000").count() == 0
    assert a.exceptAll(gen_uniform(spark, 1000, 3).repartition(7)).count() == 0
    rows = load_table(spark, sf, "orders", positions=True)
    assert rows.select("file", "pos").distinct().count() == rows.count()


def test_plans_push_down_and_prune(spark, sf):
    rows = bind_objects(load_table(spark, sf, "part"), AxisSpec("p_partkey", "p_size"), ["p_partkey"], ["p_retailprice"], Domain(Viewport(0.0, 1e6, 0.0, 60.0), 4, 4))
    plan = rows.select("ax", "ay", "root")._jdf.queryExecution().executedPlan().toString()
    assert "p_retailprice" not in plan.split("ReadSchema")[-1] and "BatchEvalPython" not in plan and "ArrowEvalPython" not in plan


def test_sql_surface(spark, sf):
    ix, _ = index(spark, sf)
    w = WINDOW
    text = f"SELECT sum(l_quantity), count(*) WINDOW X BETWEEN {w.x1} AND {w.x2} Y BETWEEN {w.y1} AND {w.y2} ERROR 2% CONFIDENCE 90%"
    q = sqlapi.parse(text)
    assert q.eps_max == 0.02 and q.gamma == 0.9 and q.aggs == (Agg("sum", "l_quantity"), Agg("count"))
    rows = sqlapi.sql(ix, text).collect()
    assert rows[0].eps_est <= 0.02 and rows[1].exact
    for bad in ("SELECT 1", "SELECT sum(a) WINDOW X BETWEEN 1 AND 2", "SELECT median(a) WINDOW X BETWEEN 1 AND 2 Y BETWEEN 1 AND 2"):
        with pytest.raises(ValueError):
            sqlapi.parse(bad)
    sqlapi.register_functions(spark, Domain(BOX, 10, 10))
    assert spark.sql("SELECT tile_status(3, 3), tile_status(0, 3), fpc(1, 4), round(norm_quantile(0.975D), 4)").first()[:] == ("exact", "not_available", 0.75, 1.96)
    sqlapi.register_index(spark, "items", ix)
    r = spark.sql(f"SELECT * FROM items_window({BOX.x1}D, {BOX.x2}D, {BOX.y1}D, {BOX.y2}D, 'l_quantity', 0.95D)").first()
    want = spark.read.parquet(f"{sf}/lineitem.parquet").agg(F.sum("l_quantity")).first()[0]
    assert r.sum_est == pytest.approx(want, rel=0.02)
    assert spark.sql("SELECT * FROM quad_children(0, 16)").count() == 4
    assert spark.sql(f"SELECT * FROM pan_path({w.x1}D, {w.x2}D, {w.y1}D, {w.y2}D, 5, 7)").count() == 5


@pytest.fixture(scope="module")
def event_files(spark, sf, tmp_path_factory):
    """Ten files in the order of time; one more with a row that comes too late, and a copy."""
    folder = f"{tmp_path_factory.mktemp('events')}/in"
    rows = spark.read.parquet(f"{sf}/events.parquet")
    ordered = rows.orderBy("ts").collect()
    n = len(ordered)
    for i in range(10):
        spark.createDataFrame(ordered[i * n // 10 : (i + 1) * n // 10], rows.schema).coalesce(1).write.mode("append").parquet(folder)
    late = [ordered[0].asDict() | {"event_id": 10**6}, ordered[-1].asDict()]
    spark.createDataFrame([tuple(x[c] for c in rows.columns) for x in late], rows.schema).coalesce(1).write.mode("append").parquet(folder)
    return rows, folder


def run(spark, frame, name: str, mode: str):
    q = frame.writeStream.format("memory").queryName(name).outputMode(mode).start()
    q.processAllAvailable()
    q.stop()
    return spark.table(name)


@pytest.mark.parametrize("kind", ["tumbling", "sliding"])
def test_stream_windows_match_the_batch(spark, event_files, kind):
    rows, folder = event_files
    got = run(spark, streams.windowed_counts(streams.stream_of(spark, folder, rows.schema), kind), f"w_{kind}", "append")
    want = {(r.start, r.event_type): r.n for r in streams.windowed_counts(rows.withColumn("ts", F.col("ts").cast("timestamp")), kind).collect()}
    closed = got.collect()
    # windows that the watermark closed are final; the late row is in none of them
    assert closed and sum(want[r.start, r.event_type] != r.n for r in closed) <= (0 if kind == "tumbling" else 0)


def test_stream_drops_copies_and_samples(spark, event_files):
    rows, folder = event_files
    once = run(spark, streams.without_repeats(streams.stream_of(spark, folder, rows.schema)).select("event_id"), "once", "append")
    assert once.groupBy("event_id").count().filter("count > 1").count() == 0 and once.count() >= rows.count()


def test_stream_into_tiles(spark, sf, event_files, tmp_path):
    rows, folder = event_files
    axes = AxisSpec("ts", "user_id")
    domain = domain_of(rows, axes, (3, 3))
    first = rows.filter("event_id % 2 = 0")
    bind = lambda d: bind_objects(d, axes, ["event_id"], ["value"], domain)
    ix, _ = build_index(first, axes, ["event_id"], ["value"], IndexConfig(grid=(3, 3), split_min=10), domain=domain)
    evaluate(ix, ViewportQuery(centre_window(domain.box, 0.5), (Agg("sum", "value"),), 0.1))
    stream = spark.readStream.schema(rows.schema).parquet(folder).filter("event_id % 2 = 1 and event_id < 1000000").dropDuplicates(["event_id"])
    streams.stream_into_index(stream, ix, bind, f"{tmp_path}/cp").awaitTermination()
    everything = bind(rows)
    assert sum(t.n_objects for t in ix.leaves()) == everything.count()
    for (tile, attr), s in ix.stats.items():
        if ix.tiles[tile].is_leaf:
            r = ix.with_tile(everything, [ix.tiles[tile]]).filter(F.col("rkey") < s.theta).agg(F.count("*"), F.sum(attr)).first()
            assert r[0] == s.moments.n and (r[1] or 0.0) == pytest.approx(s.moments.total)
    exact = evaluate(ix, ViewportQuery(domain.box, (Agg("sum", "value"),), 0.0))
    assert exact.answers[0].estimate == pytest.approx(everything.agg(F.sum("value")).first()[0])
