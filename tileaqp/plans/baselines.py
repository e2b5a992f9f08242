"""What the engine is compared with: exact tiles, samples alone, a full scan, one uniform sample, fixed totals."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame, functions as F

from .engine import evaluate
from .estimators import Stratum
from .geometry import classify
from .index import TileIndex
from .model import Agg, Answer, QueryResult, SamplingPolicy, Viewport, ViewportQuery


class ApproximateTileIndex:
    """The engine itself, under the contract of the baselines."""

    name = "ATI"

    def __init__(self, index: TileIndex, policy: SamplingPolicy | None = None):
        self.index, self.policy = index, policy or SamplingPolicy()

    def evaluate(self, q: ViewportQuery) -> QueryResult:
        return evaluate(self.index, q, self.policy)


class ExactTileIndex(ApproximateTileIndex):
    """The same tiles and splits; whatever isn't known exactly is read whole, whatever the bound."""

    name = "ETI"

    def evaluate(self, q: ViewportQuery) -> QueryResult:
        r = evaluate(self.index, q.with_bound(0.0), self.policy)
        return replace(r, query=q)


class SampleOnlyIndex(ApproximateTileIndex):
    """Tiles only locate objects: every query samples anew, nothing is kept or split."""

    name = "STI"

    def __init__(self, index: TileIndex, policy: SamplingPolicy | None = None):
        super().__init__(index, replace(policy or SamplingPolicy(), reuse=False))


_SCAN = {"count": lambda c: F.count(F.lit(1)), "sum": F.sum, "mean": F.avg, "variance": F.var_samp, "stddev": F.stddev_samp, "min": F.min, "max": F.max}


def full_scan(objects: DataFrame, workload: DataFrame, aggs: list[Agg]) -> DataFrame:
    """(query_id, pop, one column per aggregate): exact answers of all windows of a workload in one pass.

    ``workload`` has a row per query (query_id, x1, x2, y1, y2) and is broadcast; it is
    made by hand or by a path and doesn't grow with the objects.
    """
    w = workload.select("query_id", "x1", "x2", "y1", "y2")
    rows = objects.join(F.broadcast(w), F.col("ax").between(F.col("x1"), F.col("x2")) & F.col("ay").between(F.col("y1"), F.col("y2")))
    values = [_SCAN[a.fn](F.col(a.attr).cast("double") if a.attr else None).alias(f"{a.fn}_{a.attr}" if a.attr else "count") for a in aggs]
    got = rows.groupBy("query_id").agg(F.count("*").alias("pop"), *values)
    return w.select("query_id").join(got, "query_id", "left").withColumn("pop", F.coalesce("pop", F.lit(0)))


def uniform_sample(objects: DataFrame, window: Viewport, attr: str, rate: float, seed: int = 7) -> DataFrame:
    """(n, sum_est, mean_est): one Bernoulli sample of all objects, scaled up."""
    s = objects.sample(rate, seed).filter(window.condition())
    return s.agg(F.count("*").alias("n"), (F.sum(attr) / rate).alias("sum_est"), F.avg(attr).alias("mean_est"))


class StaticGrid:
    """Totals per root cell, made once; cells on the border count by the share of their area. No reads, and no guarantee."""

    name = "GRID"

    def __init__(self, index: TileIndex):
        self.index = index

    def evaluate(self, q: ViewportQuery) -> QueryResult:
        total: dict[str | None, float] = {}
        for r in self.index.roots.values():
            t = self.index.tiles[r]
            b = t.bounds(self.index.domain)
            if classify(b, q.window) == "disjoint":
                continue
            w = max(0.0, min(b.x2, q.window.x2) - max(b.x1, q.window.x1)) * max(0.0, min(b.y2, q.window.y2) - max(b.y1, q.window.y1))
            share = w / ((b.width or 1) * (b.height or 1))
            total[None] = total.get(None, 0.0) + share * t.n_objects
            for a in q.attrs():
                if (r, a) not in self.index.stats:
                    raise ValueError("the grid's totals are made before its cells are split")
                total[a] = total.get(a, 0.0) + share * self.index.stats[r, a].moments.total
        answers = []
        for a in q.aggs:
            if a.fn not in ("count", "sum", "mean"):
                raise ValueError(f"totals don't give {a.fn}")
            v = total.get(a.attr, 0.0)
            if a.fn == "mean":
                v = v / total[None] if total.get(None) else float("nan")
            answers.append(Answer(a.fn, a.attr, v, None, None, float("inf"), False))
        return QueryResult(q, answers, round(total.get(None, 0.0)), 0, 0, 0)


def strata_frame(index: TileIndex, strata: list[Stratum], attr: str) -> DataFrame:
    """Strata as rows, for estimates in Spark."""
    rows = [(s.tile_id, attr, s.kind, s.pop, s.moments(attr).n, s.moments(attr).mean, None if s.moments(attr).n < 2 else s.moments(attr).s2, s.exact(attr)) for s in strata]
    return index.spark.createDataFrame(rows, "tile_id long, attr string, kind string, pop long, n long, mean double, s2 double, exact boolean")
