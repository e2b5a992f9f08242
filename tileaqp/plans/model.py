"""The engine's value types: axes, queries, options, results."""

from __future__ import annotations

from dataclasses import dataclass, field, replace

from pyspark.sql import Column, DataFrame, SparkSession, functions as F, types as T

#: Draw keys are numbers below this; a sample at rate p holds the keys below p times it.
KEY_SPACE = 1 << 60
#: Levels of splits that a path code resolves, per axis.
LEVELS = 15

AGGREGATES = ("count", "sum", "mean", "variance", "stddev", "min", "max")


@dataclass(frozen=True)
class AxisSpec:
    """Two numeric expressions that place an object in the plane."""

    x: str
    y: str

    @staticmethod
    def number(expression: str, kind: T.DataType) -> Column:
        """An axis or measure as a double: dates and times in days, intervals in seconds."""
        c = F.expr(expression)
        if isinstance(kind, (T.TimestampType, T.TimestampNTZType)):
            return F.unix_micros(c.cast("timestamp")) / F.lit(8.64e10)
        if isinstance(kind, T.DateType):
            return F.unix_date(c).cast("double")
        if isinstance(kind, T.DayTimeIntervalType):
            return c.cast("interval second").cast("decimal(18,6)").cast("double")
        if isinstance(kind, T.NumericType):
            return c.cast("double")
        raise TypeError(f"{expression}: {kind.simpleString()} is no axis or measure; cast it first")

    def columns(self, df: DataFrame) -> tuple[Column, Column]:
        kinds = df.select(F.expr(self.x).alias("x"), F.expr(self.y).alias("y")).schema
        return self.number(self.x, kinds["x"].dataType), self.number(self.y, kinds["y"].dataType)


@dataclass(frozen=True)
class Viewport:
    """A window: two closed intervals. Sides may be columns, which aren't checked."""

    x1: float
    x2: float
    y1: float
    y2: float

    def __post_init__(self):
        if not isinstance(self.x1, Column) and (self.x1 > self.x2 or self.y1 > self.y2):
            raise ValueError("an interval ends before it starts")

    @property
    def width(self) -> float:
        return self.x2 - self.x1

    @property
    def height(self) -> float:
        return self.y2 - self.y1

    def to_pixels(self, x, y, width: int, height: int):
        """Screen place of data (numbers or columns), rows counted from the top."""
        return (x - self.x1) * (width / self.width), (self.y2 - y) * (height / self.height)

    def from_pixels(self, px, py, width: int, height: int):
        return self.x1 + px * (self.width / width), self.y2 - py * (self.height / height)

    def pan(self, dx: float, dy: float) -> Viewport:
        """Shifted by shares of its own sides."""
        return Viewport(self.x1 + dx * self.width, self.x2 + dx * self.width, self.y1 + dy * self.height, self.y2 + dy * self.height)

    def zoom(self, factor: float, focus: tuple[float, float] | None = None, within: Viewport | None = None) -> Viewport:
        """Scaled around the focus (its centre unless given); below one looks closer."""
        fx, fy = focus or ((self.x1 + self.x2) / 2, (self.y1 + self.y2) / 2)
        out = Viewport(fx + (self.x1 - fx) * factor, fx + (self.x2 - fx) * factor, fy + (self.y1 - fy) * factor, fy + (self.y2 - fy) * factor)
        return out.clip(within) if within else out

    def clip(self, d: Viewport) -> Viewport:
        x1, y1 = min(max(self.x1, d.x1), d.x2), min(max(self.y1, d.y1), d.y2)
        return Viewport(x1, max(x1, min(self.x2, d.x2)), y1, max(y1, min(self.y2, d.y2)))

    def condition(self, x: str | Column = "ax", y: str | Column = "ay") -> Column:
        x, y = (F.col(c) if isinstance(c, str) else c for c in (x, y))
        return x.between(self.x1, self.x2) & y.between(self.y1, self.y2)


@dataclass(frozen=True)
class Agg:
    """An aggregate of a measure; ``ci`` chooses the interval of variance and stddev: chi2 or delta."""

    fn: str
    attr: str | None = None
    ci: str = "chi2"

    def __post_init__(self):
        if self.fn not in AGGREGATES or (self.attr is None) != (self.fn == "count"):
            raise ValueError(f"no aggregate {self.fn}({self.attr})")


@dataclass(frozen=True)
class ViewportQuery:
    """Aggregates of the objects in a window, with the largest relative error accepted (0: exact) and a confidence."""

    window: Viewport
    aggs: tuple[Agg, ...]
    eps_max: float = 0.05
    gamma: float = 0.95
    query_id: int = 0
    op: str = "query"

    def __post_init__(self):
        if not 0 <= self.eps_max < 1 or not 0 < self.gamma < 1 or not self.aggs:
            raise ValueError("0 <= eps_max < 1, 0 < gamma < 1, and an aggregate are needed")

    def attrs(self) -> tuple[str, ...]:
        return tuple(dict.fromkeys(a.attr for a in self.aggs if a.attr))

    def with_bound(self, eps_max: float) -> ViewportQuery:
        return replace(self, eps_max=eps_max)


@dataclass(frozen=True)
class IndexConfig:
    """Layout and adaptation of tiles."""

    grid: tuple[int, int] = (100, 100)
    init: str = "flat"  # or query_driven: smaller tiles near the first query
    extra: float = 0.2  # share of the grid's tiles that query_driven adds
    split_min: int = 200
    depth_per_query: int = 1
    split_scope: str = "partial"  # or all_overlapping
    gain: str = "count_threshold"  # or expected_reuse
    gain_min: float = 0.0
    adapt: bool = True
    max_depth: int = LEVELS
    reuse_parent: bool = False
    fan_out: int = 4  # parts of a divided tile: 4, 16 or 64
    keep_rows: float = 0.0  # share of the draw keys whose rows are kept, so that parts inherit the sample of their tile
    seed: int = 7
    portable_key: bool = False

    @property
    def split_levels(self) -> int:
        """Levels of quarters that one division goes down."""
        return (self.fan_out.bit_length() - 1) // 2

    def __post_init__(self):
        if self.fan_out not in (4, 16, 64) or not 0 <= self.keep_rows <= 1:
            raise ValueError("a tile has 4, 16 or 64 parts, and kept rows are a share")
        if self.init not in ("flat", "query_driven") or self.split_scope not in ("partial", "all_overlapping") or self.gain not in ("count_threshold", "expected_reuse"):
            raise ValueError("unknown option")
        if not 0 <= self.max_depth <= LEVELS or min(self.grid) < 1:
            raise ValueError("a grid of at least one cell, and no more levels than codes have")


@dataclass(frozen=True)
class SamplingPolicy:
    """How samples start and grow."""

    rate0: float = 0.01
    cap: float = 2.0
    min_step: float = 1.1
    kind: str = "error_ratio"  # or fixed_step, fpc_aware
    draw: str = "threshold"  # or fixed_n, neyman
    floor: int = 10
    pooled_floor: int = 2  # floor once the strata together hold a hundred
    exhaust_below: int = 10
    strata: str = "tiles"  # or single, for the sample-only method
    reuse: bool = True
    max_rounds: int = 64  # then everything left is read: a bound that no sample meets still ends
    ahead: bool = False  # border counts and the first draw in one job, at the rate that known variances suggest

    def __post_init__(self):
        if self.kind not in ("error_ratio", "fixed_step", "fpc_aware") or self.draw not in ("threshold", "fixed_n", "neyman") or self.strata not in ("tiles", "single"):
            raise ValueError("unknown option")


RESULT_SCHEMA = "query_id int, agg string, attr string, estimate double, ci_low double, ci_high double, eps_est double, eps_max double, gamma double, exact boolean, met_bound boolean, pop long, n_sampled long, io_ops long, rounds int"


@dataclass
class Answer:
    agg: str
    attr: str | None
    estimate: float | None
    ci_low: float | None
    ci_high: float | None
    eps_est: float
    exact: bool


@dataclass
class QueryResult:
    """Answers of one query and what they cost."""

    query: ViewportQuery
    answers: list[Answer]
    pop: int
    n_sampled: int
    io_ops: int
    rounds: int
    round_log: list[dict] = field(default_factory=list)
    wall_ms: float = 0.0

    def rows(self) -> list[tuple]:
        q = self.query
        return [
            (q.query_id, a.agg, a.attr, a.estimate, a.ci_low, a.ci_high, a.eps_est, q.eps_max, q.gamma, a.exact, a.exact or a.eps_est <= q.eps_max, self.pop, self.n_sampled, self.io_ops, self.rounds)
            for a in self.answers
        ]

    def to_df(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame(self.rows(), RESULT_SCHEMA)
