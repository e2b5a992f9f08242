"""Sequences of windows, sessions over them, and the runner that compares methods."""

from __future__ import annotations

import hashlib
import math
from collections.abc import Iterable
from dataclasses import dataclass, replace

from pyspark.sql import DataFrame, SparkSession

from .baselines import ApproximateTileIndex, ExactTileIndex, SampleOnlyIndex, full_scan
from .engine import evaluate
from .index import TileIndex, build_index
from .metrics import engine_io, timed
from .model import Agg, AxisSpec, IndexConfig, QueryResult, SamplingPolicy, Viewport, ViewportQuery

WORKLOAD_SCHEMA = "query_id int, op string, x1 double, x2 double, y1 double, y2 double, aggs array<struct<fn: string, attr: string>>, eps_max double, gamma double"
METRICS_SCHEMA = "method string, query_id int, wall_ms double, io_ops long, rounds int, bytes_read long, agg string, attr string, eps_max double, estimate double, ci_low double, ci_high double, eps_est double, exact_value double, rel_err double, covered boolean"


def _unit(seed: int, step: int) -> float:
    """A number in [-1, 1) from a digest: the same on every machine."""
    return int(hashlib.md5(f"{seed}|{step}".encode()).hexdigest()[:12], 16) / 2**47 - 1


def centre_window(domain: Viewport, side: float, at: tuple[float, float] = (0.5, 0.5)) -> Viewport:
    """A window whose sides are a share of the domain's, around a place given in shares."""
    w, h = side * domain.width, side * domain.height
    cx, cy = domain.x1 + at[0] * domain.width, domain.y1 + at[1] * domain.height
    x1 = min(max(domain.x1, cx - w / 2), domain.x2 - w)
    y1 = min(max(domain.y1, cy - h / 2), domain.y2 - h)
    return Viewport(x1, x1 + w, y1, y1 + h)


def make_path(domain: Viewport, first: Viewport, steps: int = 100, shift: float = 0.1, heading: float = 30.0, spread: float = 60.0, seed: int = 7, jump_at: int | None = None) -> list[Viewport]:
    """Windows that follow a direction, each turned by up to ``spread`` degrees, and turn back at the border; ``jump_at`` moves to unseen parts."""
    w, h = first.width, first.height
    x, y, angle = first.x1, first.y1, math.radians(heading)
    out = [first]
    for step in range(1, steps):
        if step == jump_at:
            x, y = domain.x1 + domain.x2 - w - x, domain.y1 + domain.y2 - h - y
        turn = angle + math.radians(spread) * _unit(seed, step)
        x, y = x + shift * w * math.cos(turn), y + shift * h * math.sin(turn)
        if not domain.x1 <= x <= domain.x2 - w:
            x = min(max(x, domain.x1), domain.x2 - w)
            angle = math.pi - angle
        if not domain.y1 <= y <= domain.y2 - h:
            y = min(max(y, domain.y1), domain.y2 - h)
            angle = -angle
        out.append(Viewport(x, x + w, y, y + h))
    return out


def make_zooms(domain: Viewport, first: Viewport, rounds: int = 2, shift: float = 0.1) -> list[tuple[str, Viewport]]:
    """Pan three times, look closer, pan three times, step back; again and again."""
    out, v = [("start", first)], first
    for _ in range(rounds):
        for op in ("pan", "pan", "pan", "zoom_in", "pan", "pan", "pan", "zoom_out"):
            v = v.pan(shift, shift / 2).clip(domain) if op == "pan" else v.zoom(0.5 if op == "zoom_in" else 2.0, within=domain)
            out.append((op, v))
    return out


def as_queries(windows: Iterable[Viewport | tuple[str, Viewport]], aggs: tuple[Agg, ...], eps_max: float, gamma: float = 0.95) -> list[ViewportQuery]:
    pairs = [("pan", w) if isinstance(w, Viewport) else w for w in windows]
    return [ViewportQuery(w, aggs, eps_max, gamma, i, op) for i, (op, w) in enumerate(pairs)]


def workload_frame(spark: SparkSession, queries: list[ViewportQuery]) -> DataFrame:
    rows = [(q.query_id, q.op, q.window.x1, q.window.x2, q.window.y1, q.window.y2, [(a.fn, a.attr) for a in q.aggs], q.eps_max, q.gamma) for q in queries]
    return spark.createDataFrame(rows, WORKLOAD_SCHEMA)


class ExplorationSession:
    """Operations of one user: the window and the index carry over from one to the next."""

    def __init__(self, index: TileIndex, first: Viewport, aggs: tuple[Agg, ...], eps_max: float = 0.05, gamma: float = 0.95, policy: SamplingPolicy | None = None, method: type = ApproximateTileIndex):
        self.index, self.window, self.aggs, self.eps_max, self.gamma = index, first, aggs, eps_max, gamma
        self.method = method(index, policy or SamplingPolicy())
        self.results: list[QueryResult] = []

    def set_bound(self, eps_max: float) -> ExplorationSession:
        self.eps_max = eps_max
        return self

    def set_aggregates(self, *aggs: Agg) -> ExplorationSession:
        self.aggs = aggs
        return self

    def query(self, op: str = "query") -> QueryResult:
        r = self.method.evaluate(ViewportQuery(self.window, self.aggs, self.eps_max, self.gamma, len(self.results), op))
        self.results.append(r)
        return r

    def pan(self, dx: float, dy: float) -> QueryResult:
        self.window = self.window.pan(dx, dy)
        return self.query("pan")

    def zoom(self, factor: float, focus: tuple[float, float] | None = None) -> QueryResult:
        self.window = self.window.zoom(factor, focus, self.index.domain.box)
        return self.query("zoom")

    def run(self, ops: Iterable[tuple]) -> DataFrame:
        """('pan', dx, dy), ('zoom', factor), ('bound', eps), ('aggs', ...), ('query',) in order; the results as rows."""
        for name, *args in ops:
            {"pan": self.pan, "zoom": self.zoom, "bound": self.set_bound, "aggs": self.set_aggregates, "query": self.query}[name](*args)
        return self.frame()

    def frame(self) -> DataFrame:
        from .model import RESULT_SCHEMA

        return self.index.spark.createDataFrame([r for q in self.results for r in q.rows()], RESULT_SCHEMA)


METHODS = {"ATI": ApproximateTileIndex, "ETI": ExactTileIndex, "STI": SampleOnlyIndex}


@dataclass
class Setting:
    """A table bound to axes, and how its workload looks at scale."""

    df: DataFrame
    axes: AxisSpec
    identity: list[str]
    attrs: list[str]
    grid: tuple[int, int] = (10, 10)
    side: float = 0.316
    split_min: int = 200
    start: tuple[float, float] = (0.5, 0.5)
    init: str = "query_driven"
    config: IndexConfig | None = None

    def index_config(self) -> IndexConfig:
        return self.config or IndexConfig(grid=self.grid, init=self.init, split_min=self.split_min)


def run_workload(setting: Setting, queries: list[ViewportQuery], methods: Iterable[str] = ("ATI", "ETI", "STI"), policy: SamplingPolicy | None = None, cache: bool = True) -> list[dict]:
    """METRICS rows: every method answers the same queries on an index of its own, built with the first one.

    Methods take turns query by query, and another one begins each time, so that none bears the
    warming up of the others.
    """
    from .index import bind_objects, domain_of

    policy = policy or SamplingPolicy()
    config = setting.index_config()
    domain = domain_of(setting.df, setting.axes, config.grid)
    objects = bind_objects(setting.df, setting.axes, setting.identity, setting.attrs, domain, config.seed, config.portable_key)
    if cache:
        objects = objects.persist()
    aggs = list(queries[0].aggs)
    exact = {r.query_id: r.asDict() for r in full_scan(objects, workload_frame(objects.sparkSession, queries), aggs).collect()}  # a row per query
    out = []
    built = {name: build_from(objects, domain, config, setting.attrs, queries[0]) for name in methods}
    running = {name: METHODS[name](index, policy) for name, (index, _) in built.items()}
    names = list(running)
    for i, q in enumerate(queries):
        for name in names[i % len(names):] + names[: i % len(names)]:
            if q is queries[0]:
                r, physical = built[name][1], None
            else:
                got: list[tuple[QueryResult, float]] = []
                physical = engine_io(objects.sparkSession, lambda m=running[name], q=q, got=got: got.append(timed(lambda: m.evaluate(q))))["input_bytes"]
                r, r.wall_ms = got[0][0], got[0][1]
            for a in r.answers:
                truth = exact[q.query_id][f"{a.agg}_{a.attr}" if a.attr else "count"]
                err = None if truth is None or a.estimate is None or not truth else abs(a.estimate - truth) / abs(truth)
                low, high = (a.ci_low, a.ci_high) if a.ci_low is not None else (-math.inf, math.inf)
                slack = 1e-9 * abs(truth or 0.0)  # sums in another order differ in the last digits
                out.append({
                    "method": name, "query_id": q.query_id, "wall_ms": r.wall_ms, "io_ops": r.io_ops, "rounds": r.rounds, "bytes_read": physical, "agg": a.agg, "attr": a.attr, "eps_max": q.eps_max, "estimate": a.estimate,
                    "ci_low": a.ci_low, "ci_high": a.ci_high, "eps_est": a.eps_est, "exact_value": None if truth is None else float(truth), "rel_err": err, "covered": None if truth is None else low - slack <= truth <= high + slack,
                })
    if cache:
        objects.unpersist()
    return out


def build_from(objects: DataFrame, domain, config: IndexConfig, attrs: list[str], q0: ViewportQuery):
    """An index over objects that are bound already."""
    return build_index(objects, AxisSpec("ax", "ay"), [], attrs, config, q0, domain, objects=objects)


def metrics_frame(spark: SparkSession, rows: list[dict]) -> DataFrame:
    return spark.createDataFrame([tuple(r[c.split()[0]] for c in METRICS_SCHEMA.split(", ")) for r in rows], METRICS_SCHEMA)


def switch_attribute(queries: list[ViewportQuery], at: int, attr: str) -> list[ViewportQuery]:
    """From the query ``at`` on, the same aggregates of another measure."""
    return [q if q.query_id < at else replace(q, aggs=tuple(replace(a, attr=attr) for a in q.aggs)) for q in queries]


def answer_all(index: TileIndex, queries: list[ViewportQuery], policy: SamplingPolicy | None = None) -> list[QueryResult]:
    return [evaluate(index, q, policy) for q in queries]
