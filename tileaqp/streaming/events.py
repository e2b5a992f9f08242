"""Streams: windowed counts, joins, bounded state per cell, and objects that arrive while tiles are in use."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, functions as F
from pyspark.sql.streaming import StatefulProcessor, StatefulProcessorHandle

from ..plans.estimators import Moments, moment_columns, moments_of
from ..plans.index import Stats, TileIndex
from ..plans.model import KEY_SPACE
from ..runtime import ship

LATE = "2 hours"


def stream_of(spark: SparkSession, path: str, schema, files_per_trigger: int = 1) -> DataFrame:
    """A folder of Parquet files as a stream; times without zone become times."""
    rows = spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(path)
    return rows.withColumn("ts", F.col("ts").cast("timestamp"))


def windowed_counts(events: DataFrame, kind: str = "tumbling", late: str | None = LATE) -> DataFrame:
    """(start, end, event_type, n, total) per hour, per sliding hour, or per session of a user; works on tables as well."""
    rows = events.withWatermark("ts", late) if late and events.isStreaming else events
    if kind == "session":
        keys = [F.session_window("ts", "30 minutes").alias("w"), F.col("user_id")]
    elif kind in ("tumbling", "sliding"):
        keys = [(F.window("ts", "1 hour") if kind == "tumbling" else F.window("ts", "1 hour", "15 minutes")).alias("w"), F.col("event_type")]
    else:
        raise ValueError(f"no window {kind}")
    got = rows.groupBy(*keys).agg(F.count("*").alias("n"), F.round(F.sum("value"), 4).alias("total"))
    return got.select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), *got.columns[1:])


def without_repeats(events: DataFrame, late: str = LATE) -> DataFrame:
    """Each event once, as long as its copies come within the watermark."""
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"]) if events.isStreaming else events.dropDuplicates(["event_id"])


def views_then_clicks(events: DataFrame, minutes: int = 10, late: str = LATE) -> DataFrame:
    """Clicks of a user within ``minutes`` after a view: an interval join whose state the watermark bounds."""
    mark = (lambda d: d.withWatermark("ts", late)) if events.isStreaming else (lambda d: d)
    v = mark(events).filter("event_type = 'view'").select(F.col("user_id").alias("v_user"), F.col("ts").alias("v_ts"), F.col("event_id").alias("view_id"))
    c = mark(events).filter("event_type = 'click'").select("user_id", F.col("ts").alias("c_ts"), F.col("event_id").alias("click_id"))
    near = F.expr(f"user_id = v_user AND c_ts >= v_ts AND c_ts <= v_ts + INTERVAL {minutes} MINUTES")
    return v.join(c, near).select("user_id", "view_id", "click_id")


def with_customer(events: DataFrame, customers: DataFrame) -> DataFrame:
    """A stream met with a table."""
    return events.join(customers.select(F.col("c_custkey").alias("user_id"), "c_mktsegment"), "user_id", "left")


class CellSample(StatefulProcessor):
    """Count, and the sum of the ``size`` values with the smallest keys: a uniform sample in bounded state."""

    size = 32

    def init(self, handle: StatefulProcessorHandle) -> None:
        self.state = handle.getValueState("sample", "n long, keys array<long>, vals array<double>")

    def handleInputRows(self, key, rows: Iterator[pd.DataFrame], timerValues) -> Iterator[pd.DataFrame]:
        n, held = 0, []
        if self.state.exists():
            n, keys, values = self.state.get()
            held = list(zip(keys, values, strict=True))
        for pdf in rows:
            n += len(pdf)
            held += list(zip(pdf["rkey"].tolist(), pdf["value"].tolist(), strict=True))
        held = sorted(held)[: self.size]
        self.state.update((n, [k for k, _ in held], [v for _, v in held]))
        mean = sum(v for _, v in held) / len(held) if held else 0.0
        yield pd.DataFrame({"cell": [key[0]], "n": [n], "sampled": [len(held)], "sum_est": [n * mean]})

    def close(self) -> None:
        pass


def sampled_cells(events: DataFrame, seed: int = 7) -> DataFrame:
    """(cell, n, sampled, sum_est) per event type, updated with every batch."""
    ship(events.sparkSession)
    # the default provider keeps one table of state; a stream reads this when it starts
    events.sparkSession.conf.set("spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    rows = events.select(F.col("event_type").alias("cell"), "value", F.xxhash64("event_id", F.lit(seed)).bitwiseAND(F.lit(KEY_SPACE - 1)).alias("rkey"))
    return rows.groupBy("cell").transformWithStateInPandas(CellSample(), "cell string, n long, sampled long, sum_est double", "Update", "None")


def absorb(index: TileIndex, objects: DataFrame) -> int:
    """New bound objects enter the tiles: counts grow, and each statistic takes those with keys below its limit, so samples stay uniform and exact tiles exact."""
    leaves = index.leaves()
    attrs = sorted({a for _, a in index.stats})
    cut = {f"_cut{i}": [index.stat(t.tile_id, a).theta for t in leaves] for i, a in enumerate(attrs)}
    rows = index.with_tile(objects, leaves, **cut)
    columns = [c for i, a in enumerate(attrs) for c in moment_columns(a, F.col("rkey") < F.col(f"_cut{i}"))]
    got = rows.groupBy("tile_id").agg(F.count("*").alias("_n"), *columns).collect()  # a row per leaf
    for r in got:
        t = index.tiles[r.tile_id]
        while t is not None:  # the parents' counts too
            t.n_objects += r._n
            t = index.tiles[t.parent_id] if t.parent_id is not None else None
        for a in attrs:
            s = index.stat(r.tile_id, a)
            if s.theta:
                m: Moments = s.moments.merge(moments_of(r.asDict(), a))
                index.stats[r.tile_id, a] = Stats(s.theta, m)
    # leaves without objects were exact and unknown at once; they stay exact for what they get
    index.objects = index.objects.unionByName(objects)
    index._kept = None
    index.version += 1
    return sum(r._n for r in got)


def stream_into_index(stream: DataFrame, index: TileIndex, bind, checkpoint: str):
    """A running query whose batches ``absorb`` takes up; ``bind`` makes OBJECTS of a batch. Batches seen before a restart are skipped."""
    from ..runtime import durable

    done: set[int] = set()

    def take(batch: DataFrame, number: int) -> None:
        if number not in done:
            absorb(index, durable(bind(batch), "batch"))
            done.add(number)

    return stream.writeStream.foreachBatch(take).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
