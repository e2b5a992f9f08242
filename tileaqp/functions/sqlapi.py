"""The engine from SQL: scalar and table functions, vectorised quantiles, and a small statement for windows."""

from __future__ import annotations

import re

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, functions as F

from ..plans.engine import evaluate
from ..plans.geometry import CELL_BITS, Domain
from ..plans.index import TileIndex
from ..plans.model import RESULT_SCHEMA, Agg, SamplingPolicy, Viewport, ViewportQuery
from ..runtime import ship
from .quantiles import chi2_quantile, normal_quantile


def register_functions(spark: SparkSession, domain: Domain | None = None) -> None:
    """tile_status, fpc, quad_prefix and, for a domain, tile_root as SQL functions; norm_quantile and chi2_quantile for columns of levels."""
    run = lambda s: spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {s}")
    run("tile_status(n BIGINT, pop BIGINT) RETURNS STRING RETURN CASE WHEN n = pop THEN 'exact' WHEN n > 0 THEN 'approximate' ELSE 'not_available' END")
    run("fpc(n BIGINT, pop BIGINT) RETURNS DOUBLE RETURN CASE WHEN pop > 0 THEN 1 - n / pop ELSE 0.0D END")
    run(f"quad_prefix(zcode BIGINT, depth INT) RETURNS BIGINT RETURN shiftright(zcode, {CELL_BITS} - 2 * depth)")
    if domain:
        b = domain.box
        axis = lambda v, lo, w, n: f"CAST(least({n - 1}, greatest(0, floor(({v} - {lo!r}D) / {w!r}D * {n}))) AS INT)"
        run(f"tile_root(x DOUBLE, y DOUBLE) RETURNS INT RETURN {axis('y', b.y1, b.height, domain.gy)} * {domain.gx} + {axis('x', b.x1, b.width, domain.gx)}")
    ship(spark)

    @F.pandas_udf("double")
    def norm_quantile(p: pd.Series) -> pd.Series:
        return p.map(normal_quantile, na_action="ignore")

    @F.pandas_udf("double")
    def chi2(p: pd.Series, df: pd.Series) -> pd.Series:
        return pd.Series([chi2_quantile(a, b) for a, b in zip(p, df, strict=True)])

    spark.udf.register("norm_quantile", norm_quantile)
    spark.udf.register("chi2_quantile", chi2)


def moments_by_group(rows: DataFrame, by: str, value: str) -> DataFrame:
    """(by, n, mean, m2) from whole groups in pandas: a check on the built-in aggregates, not for large groups."""
    kind = rows.schema[by].dataType.simpleString()

    def of(pdf: pd.DataFrame) -> pd.DataFrame:
        v = pdf[value].astype(float)
        return pd.DataFrame({by: [pdf[by].iloc[0]], "n": [len(v)], "mean": [v.mean()], "m2": [((v - v.mean()) ** 2).sum()]})

    return rows.select(by, value).groupBy(by).applyInPandas(of, f"{by} {kind}, n long, mean double, m2 double")


def register_index(spark: SparkSession, name: str, index: TileIndex) -> None:
    """Table functions ``<name>_window`` (a count and totals from what is stored of whole tiles), ``quad_children`` and ``pan_path``.

    The window function works on the snapshot taken here: exact and sampled whole tiles
    answer, tiles on the border count by their share of area; it reads no objects.
    """
    ship(spark)
    d = index.domain
    attrs = sorted({a for _, a in index.stats})
    tiles = []
    for t in index.leaves():
        b = t.bounds(d)
        for attr in attrs:
            m = index.stat(t.tile_id, attr).moments
            tiles.append((b.x1, b.x2, b.y1, b.y2, attr, t.n_objects, m.n, m.mean, m.m2))

    @F.udtf(returnType="attr string, pop double, sum_est double, ci_low double, ci_high double")
    class StoredWindow:
        def eval(self, x1: float, x2: float, y1: float, y2: float, attr: str, gamma: float):
            pop = total = var = unknown = 0.0
            for a, b, c, e, name, count, n, mean, m2 in tiles:
                if name != attr:
                    continue
                w, h = min(b, x2) - max(a, x1), min(e, y2) - max(c, y1)
                if w < 0 or h < 0:
                    continue
                share = (w / (b - a) if b > a else 1.0) * (h / (e - c) if e > c else 1.0)
                pop += share * count
                if not n:
                    unknown += share * count
                    continue
                total += share * count * mean
                if 1 < n < count:
                    var += (share * count) ** 2 * m2 / (n - 1) / n * (1 - n / count)
            # tiles of which nothing was read are taken to be like the others
            total *= pop / (pop - unknown) if pop > unknown else 1.0
            half = normal_quantile((1 + gamma) / 2) * var**0.5
            yield attr, pop, total, total - half, total + half

    @F.udtf(returnType="part int, zlo long, zhi long")
    class QuadChildren:
        def eval(self, zlo: int, zhi: int):
            step = (zhi - zlo) // 4
            for i in range(4):
                yield i, zlo + i * step, zlo + (i + 1) * step

    @F.udtf(returnType="query_id int, x1 double, x2 double, y1 double, y2 double")
    class PanPath:
        def eval(self, x1: float, x2: float, y1: float, y2: float, steps: int, seed: int):
            from tileaqp.plans.workload import make_path

            for i, v in enumerate(make_path(d.box, Viewport(x1, x2, y1, y2), steps, seed=seed)):
                yield i, v.x1, v.x2, v.y1, v.y2

    spark.udtf.register(f"{name}_window", StoredWindow)
    spark.udtf.register("quad_children", QuadChildren)
    spark.udtf.register("pan_path", PanPath)


_NUMBER = r"([-+]?[0-9.]+(?:[eE][-+]?[0-9]+)?)"
_STATEMENT = re.compile(
    rf"\s*select\s+(?P<aggs>.+?)\s+window\s+x\s+between\s+{_NUMBER}\s+and\s+{_NUMBER}\s+y\s+between\s+{_NUMBER}\s+and\s+{_NUMBER}(?:\s+error\s+{_NUMBER}\s*(?P<percent>%)?)?(?:\s+confidence\s+{_NUMBER}\s*(?P<sure>%)?)?\s*;?\s*", re.IGNORECASE | re.DOTALL
)
_AGG = re.compile(r"\s*(count|sum|avg|mean|variance|stddev|min|max)\s*\(\s*([\w]+|\*)\s*\)\s*", re.IGNORECASE)


def parse(text: str) -> ViewportQuery:
    """SELECT sum(a), avg(b) WINDOW X BETWEEN .. AND .. Y BETWEEN .. AND .. [ERROR 5%] [CONFIDENCE 95%]"""
    m = _STATEMENT.fullmatch(text)
    if not m:
        raise ValueError(f"not a window statement: {text}")
    aggs = []
    for part in m["aggs"].split(","):
        a = _AGG.fullmatch(part)
        if not a:
            raise ValueError(f"not an aggregate: {part}")
        fn = {"avg": "mean"}.get(a[1].lower(), a[1].lower())
        aggs.append(Agg(fn, None if fn == "count" else a[2]))
    numbers = [m[i] for i in range(2, 6)]
    eps, gamma = m[6], m[8]
    eps_max = 0.05 if eps is None else float(eps) / (100 if m["percent"] else 1)
    sure = 0.95 if gamma is None else float(gamma) / (100 if m["sure"] else 1)
    x1, x2, y1, y2 = map(float, numbers)
    return ViewportQuery(Viewport(x1, x2, y1, y2), tuple(aggs), eps_max, sure)


def sql(index: TileIndex, text: str, policy: SamplingPolicy | None = None) -> DataFrame:
    """The RESULT rows of a window statement; the index learns from it."""
    return index.spark.createDataFrame(evaluate(index, parse(text), policy).rows(), RESULT_SCHEMA)
