"""Stratified estimates and intervals from per-tile samples, on the driver and as column expressions."""

from __future__ import annotations

import math
from collections.abc import Iterable
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, functions as F

from ..functions.quantiles import chi2_quantile, two_sided_z
from .model import Agg, Answer


@dataclass(frozen=True)
class Moments:
    """What is kept of a sample: size, sizes without nulls, mean, squared deviations, fourth powers, extremes."""

    n: int = 0
    mean: float = 0.0
    m2: float = 0.0
    low: float = math.inf
    high: float = -math.inf
    filled: int = 0
    m3: float = 0.0
    m4: float = 0.0

    def merge(self, o: Moments) -> Moments:
        """Moments of both samples together."""
        if not self.n or not o.n:
            return o if not self.n else self
        n, d = self.n + o.n, o.mean - self.mean
        a, b = self.n / n, o.n / n
        return Moments(
            n,
            self.mean + d * b,
            self.m2 + o.m2 + d * d * self.n * b,
            min(self.low, o.low),
            max(self.high, o.high),
            self.filled + o.filled,
            self.m3 + o.m3 + d**3 * self.n * b * (a - b) + 3 * d * (a * o.m2 - b * self.m2),
            self.m4 + o.m4 + d**4 * self.n * b * (a * a - a * b + b * b) + 6 * d * d * (a * a * o.m2 + b * b * self.m2) + 4 * d * (a * o.m3 - b * self.m3),
        )

    @property
    def total(self) -> float:
        return self.n * self.mean

    @property
    def s2(self) -> float:
        """Sample variance; unknown below two objects."""
        return self.m2 / (self.n - 1) if self.n > 1 else math.inf


def moment_columns(attr: str, only: Column | None = None, prefix: str | None = None, high: bool = False) -> list[Column]:
    """Aggregates that make the Moments of a measure; a null counts as 0 in sums. ``high`` adds the third and fourth."""
    v = F.coalesce(F.col(attr).cast("double"), F.lit(0.0))
    keep = (lambda c: F.when(only, c)) if only is not None else (lambda c: c)
    p = prefix or attr
    x = keep(v)
    out = [F.count(x).alias(f"{p}__n"), F.avg(x).alias(f"{p}__mean"), F.var_pop(x).alias(f"{p}__var"), F.min(x).alias(f"{p}__low"), F.max(x).alias(f"{p}__high"), F.count(keep(F.col(attr))).alias(f"{p}__filled")]
    return out + [F.skewness(x).alias(f"{p}__skew"), F.kurtosis(x).alias(f"{p}__kurt")] if high else out


def moments_of(row: dict, p: str) -> Moments:
    n = row[f"{p}__n"]
    if not n:
        return Moments()
    var = row[f"{p}__var"]
    skew, kurt = row.get(f"{p}__skew"), row.get(f"{p}__kurt")
    m3 = 0.0 if skew is None or math.isnan(skew) else skew * var**1.5 * n
    m4 = 0.0 if kurt is None or math.isnan(kurt) else (kurt + 3) * var * var * n
    return Moments(n, row[f"{p}__mean"], var * n, row[f"{p}__low"], row[f"{p}__high"], row[f"{p}__filled"], m3, m4)


def fpc(n: float, pop: float) -> float:
    """What sampling without replacement leaves of the variance: nothing once all are drawn."""
    return 1 - n / pop if pop else 0.0


@dataclass
class Stratum:
    """A tile's part of the window: its population, and the sample so far of every measure."""

    tile_id: int
    kind: str  # full or partial
    pop: int
    case: int = 0
    theta: dict[str, int] = field(default_factory=dict)
    sample: dict[str, Moments] = field(default_factory=dict)

    def exact(self, attr: str) -> bool:
        return self.sample.get(attr, Moments()).n == self.pop

    def moments(self, attr: str) -> Moments:
        return self.sample.get(attr, Moments())


def _sum(strata: Iterable[Stratum], attr: str) -> tuple[float, float, float]:
    """Estimated sum, its variance, estimated objects that aren't null."""
    total = var = filled = 0.0
    for s in strata:
        m = s.moments(attr)
        if m.n == s.pop:
            total, filled = total + m.total, filled + m.filled
        elif not m.n:
            return math.nan, math.inf, math.nan
        else:
            total += s.pop * m.mean
            filled += s.pop * m.filled / m.n
            var += s.pop**2 * m.s2 / m.n * fpc(m.n, s.pop)
    return total, var, filled


def estimate_count(strata: Iterable[Stratum]) -> int:
    return sum(s.pop for s in strata)


def estimate_sum(strata: list[Stratum], attr: str) -> tuple[float, float]:
    return _sum(strata, attr)[:2]


def estimate_mean(strata: list[Stratum], attr: str) -> tuple[float, float]:
    total, var, filled = _sum(strata, attr)
    return (total / filled, var / filled**2) if filled else (math.nan, 0.0 if not estimate_count(strata) else math.inf)


def estimate_variance(strata: list[Stratum], attr: str) -> tuple[float, float, float]:
    """Sample variance of all objects in the window, degrees of freedom, and the variance of the estimate from fourth powers."""
    n = estimate_count(strata)
    drawn = [s for s in strata if s.moments(attr).n != s.pop]
    if n < 2 or any(s.moments(attr).n < 2 for s in drawn):
        return (math.nan, math.inf, 0.0) if n < 2 else (math.nan, 0.0, math.inf)
    mean = sum(s.pop * s.moments(attr).mean for s in strata) / n
    squares = sum(s.pop * ((s.moments(attr).s2 if s in drawn else s.moments(attr).m2 / s.pop) * ((s.pop - 1) / s.pop if s in drawn else 1) + (s.moments(attr).mean - mean) ** 2) for s in strata)
    value = squares / (n - 1)
    # degrees of freedom that match mean and variance of the weighted sum of stratum variances
    parts = [(s.pop * s.moments(attr).s2, s.moments(attr).n - 1) for s in drawn]
    top, bottom = sum(p for p, _ in parts) ** 2, sum(p * p / k for p, k in parts)
    df = top / bottom if bottom else math.inf
    var = 0.0
    for s in drawn:
        m = s.moments(attr)
        # squared deviations from the common mean, as a measure of their own
        d = m.mean - mean
        spread = max(0.0, (m.m4 + 4 * d * m.m3 + 4 * d * d * m.m2) / m.n - (m.m2 / m.n) ** 2) * m.n / (m.n - 1)
        var += s.pop**2 * spread / m.n * fpc(m.n, s.pop)
    return value, df, var / (n - 1) ** 2


def clt_interval(estimate: float, var: float, gamma: float) -> tuple[float, float]:
    half = two_sided_z(gamma) * math.sqrt(var) if var else 0.0
    return estimate - half, estimate + half


def chi2_interval(value: float, df: float, share: float, gamma: float) -> tuple[float, float]:
    """Interval of a variance; its distance from the estimate shrinks as the sample's ``share`` of the objects grows."""
    if math.isinf(df) or share >= 1:
        return value, value
    shrink = math.sqrt(1 - share)
    low = df * value / chi2_quantile((1 + gamma) / 2, df)
    high = df * value / chi2_quantile((1 - gamma) / 2, df)
    return value - (value - low) * shrink, value + (high - value) * shrink


def eps_est(low: float, high: float, estimate: float) -> float:
    """Half the interval over the estimate's size; 0 for a point, infinite around an estimate of 0."""
    if math.isnan(estimate) or math.isinf(high - low):
        return math.inf
    half = (high - low) / 2
    return 0.0 if not half else half / abs(estimate) if estimate else math.inf


def answer(strata: list[Stratum], agg: Agg, gamma: float) -> Answer:
    """Estimate and interval of one aggregate over all strata."""
    if agg.fn == "count":
        n = float(estimate_count(strata))
        return Answer(agg.fn, None, n, n, n, 0.0, True)
    attr = agg.attr
    exact = all(s.exact(attr) for s in strata)
    if not estimate_count(strata):
        value = 0.0 if agg.fn == "sum" else None
        return Answer(agg.fn, attr, value, value, value, 0.0, True)
    if agg.fn in ("min", "max"):
        if not exact:
            return Answer(agg.fn, attr, None, None, None, math.inf, False)
        value = min(s.moments(attr).low for s in strata) if agg.fn == "min" else max(s.moments(attr).high for s in strata)
        return Answer(agg.fn, attr, value, value, value, 0.0, True)
    if agg.fn in ("sum", "mean"):
        value, var = (estimate_sum if agg.fn == "sum" else estimate_mean)(strata, attr)
        low, high = clt_interval(value, var, gamma)
    else:
        value, df, var = estimate_variance(strata, attr)
        share = sum(s.moments(attr).n for s in strata) / estimate_count(strata)
        if math.isnan(value):
            if exact:
                return Answer(agg.fn, attr, None, None, None, 0.0, True)
            low = high = math.inf
        elif exact:
            low = high = value
        elif agg.ci == "delta":
            low, high = clt_interval(value, var, gamma)
            low = max(0.0, low)
        else:
            low, high = chi2_interval(value, df, share, gamma)
        if agg.fn == "stddev":
            value, low, high = (math.sqrt(v) if 0 <= v < math.inf else v for v in (value, low, high))
    return Answer(agg.fn, attr, value, low, high, 0.0 if exact else eps_est(low, high, value), exact)


# The same over rows of strata: pop, n, mean, s2. For workloads with more strata than a driver should hold.


def fpc_column(n: Column, pop: Column) -> Column:
    return F.when(pop > 0, 1 - n / pop).otherwise(0.0)


def estimates(strata: DataFrame, by: list[str], z: float) -> DataFrame:
    """Sum and mean with variances and intervals; a stratum drawn wholly has no variance."""
    part = F.when(F.col("n") < F.col("pop"), F.col("pop") * F.col("pop") * F.col("s2") / F.col("n") * fpc_column(F.col("n"), F.col("pop"))).otherwise(0.0)
    out = strata.groupBy(*by).agg(F.sum("pop").alias("pop"), F.sum("n").alias("n_sampled"), F.sum(F.col("pop") * F.col("mean")).alias("sum_est"), F.sum(part).alias("sum_var"))
    half = z * F.sqrt("sum_var")
    return out.withColumns({
        "sum_low": F.col("sum_est") - half, "sum_high": F.col("sum_est") + half,
        "mean_est": F.col("sum_est") / F.col("pop"), "mean_var": F.col("sum_var") / (F.col("pop") * F.col("pop")),
        "eps_est": half / F.abs("sum_est"),
    })
