"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line."""

from __future__ import annotations

import json
import os
import sys
import time

from pyspark.sql import SparkSession

FOLDER = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")
STEPS = int(os.environ.get("BENCH_STEPS", "20"))


def main() -> None:
    spark = (
        SparkSession.builder.master(f"local[{CPUS}]").appName("bench").config("spark.sql.shuffle.partitions", CPUS).config("spark.driver.memory", "12g")
        .config("spark.sql.session.timeZone", "UTC").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    from tileaqp.operators import library
    from tileaqp.operators.workloads import path_queries, setting
    from tileaqp.plans.model import SamplingPolicy
    from tileaqp.plans.workload import run_workload

    policy = SamplingPolicy(kind="fpc_aware", cap=16.0, rate0=0.03, exhaust_below=25, pooled_floor=3, ahead=True)  # few large rounds: a round costs a job
    seconds: dict[str, float] = {}
    reads: dict[str, int] = {}
    accuracy: dict[str, float] = {}
    warm = setting(spark, FOLDER)
    run_workload(warm, path_queries(warm, eps=0.01, steps=12), policy=policy)
    for name, table, eps in (("uniform_1pct", "uniform", 0.01), ("uniform_5pct", "uniform", 0.05), ("dense_1pct", "dense", 0.01), ("low_variance_1pct", "low_variance", 0.01)):
        s = setting(spark, FOLDER, table)
        got = run_workload(s, path_queries(s, eps=eps, steps=STEPS), policy=policy)
        for method in ("ATI", "STI", "ETI"):
            later = [r for r in got if r["method"] == method and r["query_id"]]
            seconds[f"{name}_{method.lower()}"] = round(sum(r["wall_ms"] for r in later) / 1000, 3)
            reads[f"{name}_{method.lower()}"] = sum(r["io_ops"] for r in later)
            accuracy[f"{name}_{method.lower()}_covered"] = round(sum(r["covered"] for r in later) / len(later), 3)
            accuracy[f"{name}_{method.lower()}_max_rel_err"] = round(max(r["rel_err"] or 0.0 for r in later), 5)
    for name in ("b03_full_scan", "m07_flat_metadata", "m24_sum_fixed_rate", "r03_equi_joins", "r13_pyramid_rollup", "r18_frames", "t03_session_windows"):
        began = time.time()
        library.QUERIES[name](spark, FOLDER).write.format("noop").mode("overwrite").save()
        seconds[name] = round(time.time() - began, 3)
    ratio = lambda d, base: round(sum(d[f"{n}_{base}"] / max(d[f"{n}_ati"], 1e-9) for n in ("uniform_1pct", "uniform_5pct", "dense_1pct", "low_variance_1pct")) / 4, 3)
    print(json.dumps({
        "metric": "seconds of all headline queries", "value": round(sum(seconds.values()), 3), "unit": "sec", "queries": seconds, "sf": FOLDER.rsplit("sf", 1)[-1], "steps": STEPS, "io_ops": reads, "accuracy": accuracy,
        "speedup": {"time_over_sti": ratio(seconds, "sti"), "time_over_eti": ratio(seconds, "eti"), "io_over_sti": ratio(reads, "sti"), "io_over_eti": ratio(reads, "eti")},
    }))
    sys.stdout.flush()
    spark.stop()


if __name__ == "__main__":
    main()
