"""Cost and accuracy of a workload's METRICS rows."""

from __future__ import annotations

import time
import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, functions as F


def timed(fn: Callable):
    """What a call returns, and its milliseconds."""
    began = time.time()
    out = fn()
    return out, (time.time() - began) * 1000


def per_query(metrics: DataFrame) -> DataFrame:
    """One row per method, bound and query: time and reads don't repeat for several aggregates."""
    return metrics.groupBy("method", "eps_max", "query_id").agg(F.max("wall_ms").alias("wall_ms"), F.max("io_ops").alias("io_ops"), F.max("rounds").alias("rounds"))


def totals(metrics: DataFrame) -> DataFrame:
    """Time, reads and rounds of whole workloads, with and without the first query (which is part of building)."""
    later = F.col("query_id") > 0
    return per_query(metrics).groupBy("method", "eps_max").agg(
        F.sum(F.when(later, F.col("wall_ms"))).alias("total_ms"), F.sum("wall_ms").alias("total_ms_with_first"), F.sum(F.when(later, F.col("io_ops"))).alias("io_total"),
        F.max(F.when(~later, F.col("io_ops"))).alias("io_init"), F.avg(F.when(later, F.col("rounds"))).alias("mean_rounds"),
    )


def relative_error(results: DataFrame, exact: DataFrame) -> DataFrame:
    """RESULT rows with the exact value of the same query, aggregate and measure, and the error over its size (null where it is 0)."""
    keys = ["query_id", "agg", "attr"]
    joined = results.join(exact.select(*keys, "exact_value"), keys)
    return joined.withColumn("rel_err", F.abs(F.col("estimate") - F.col("exact_value")) / F.nullif(F.abs("exact_value"), F.lit(0.0)))


def coverage(metrics: DataFrame) -> DataFrame:
    """Share of queries whose interval holds the exact value, and mean width."""
    return metrics.filter("query_id > 0").groupBy("method", "eps_max").agg(F.avg(F.col("covered").cast("double")).alias("coverage"), F.avg(F.col("ci_high") - F.col("ci_low")).alias("mean_width"), F.count("*").alias("n"))


def bound_compliance(metrics: DataFrame) -> DataFrame:
    """Share of queries whose actual error is within the bound."""
    return metrics.filter("query_id > 0").groupBy("method", "eps_max").agg(F.avg((F.col("rel_err") <= F.col("eps_max") + 1e-12).cast("double")).alias("compliance"), F.avg("rel_err").alias("mean_rel_err"), F.max("rel_err").alias("max_rel_err"))


def speedup(metrics: DataFrame, base: str, method: str = "ATI") -> DataFrame:
    """Per bound the base's time and reads over the method's."""
    t = totals(metrics)
    a = t.filter(F.col("method") == method).select("eps_max", F.col("total_ms").alias("ms"), F.col("io_total").alias("io"))
    b = t.filter(F.col("method") == base).select("eps_max", (F.col("total_ms")).alias("base_ms"), F.col("io_total").alias("base_io"))
    return a.join(b, "eps_max").select("eps_max", F.lit(base).alias("base"), (F.col("base_ms") / F.col("ms")).alias("time_ratio"), (F.col("base_io") / F.greatest("io", F.lit(1))).alias("io_ratio"))


def engine_io(spark: SparkSession, run: Callable) -> dict[str, int]:
    """Spark's own reading of the jobs that ``run`` starts: bytes, records and shuffle bytes of their stages."""
    sc = spark.sparkContext
    group, before = f"tileaqp-{uuid.uuid4().hex}", sc.getLocalProperty("spark.jobGroup.id")
    sc.setLocalProperty("spark.jobGroup.id", group)
    try:
        run()
    finally:
        sc.setLocalProperty("spark.jobGroup.id", before)
    sc._jsc.sc().listenerBus().waitUntilEmpty(10_000)
    tracker, store = sc.statusTracker(), sc._jsc.sc().statusStore()
    stages = {i for job in tracker.getJobIdsForGroup(group) if (info := tracker.getJobInfo(job)) for i in info.stageIds}
    new = [s for i in stages if tracker.getStageInfo(i) and (s := store.lastStageAttempt(i)).numCompleteTasks()]
    return {"stages": len(new), "input_bytes": sum(s.inputBytes() for s in new), "input_records": sum(s.inputRecords() for s in new), "shuffle_bytes": sum(s.shuffleWriteBytes() for s in new)}
