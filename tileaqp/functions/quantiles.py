"""Quantiles of the normal and chi-square distributions, in plain Python."""

from __future__ import annotations

import math
from functools import lru_cache
from statistics import NormalDist


@lru_cache(1024)
def normal_quantile(p: float) -> float:
    return NormalDist().inv_cdf(p)


def two_sided_z(gamma: float) -> float:
    return normal_quantile((1 + gamma) / 2)


def gamma_p(a: float, x: float) -> float:
    """Regularised lower incomplete gamma function: by its series below a + 1, by the continued fraction above."""
    if x <= 0:
        return 0.0
    scale = math.exp(a * math.log(x) - x - math.lgamma(a))
    if x < a + 1:
        term = total = 1 / a
        n = a
        while abs(term) > abs(total) * 1e-16:
            n += 1
            term *= x / n
            total += term
        return min(1.0, scale * total)
    tiny = 1e-300
    b = x + 1 - a
    c, d = 1 / tiny, 1 / b
    h = d
    for i in range(1, 10_000):
        an = -i * (i - a)
        b += 2
        d = 1 / (an * d + b or tiny)
        c = b + an / c or tiny
        h *= (step := c * d)
        if abs(step - 1) < 1e-16:
            break
    return max(0.0, 1 - scale * h)


@lru_cache(4096)
def chi2_quantile(p: float, df: float) -> float:
    """Start from the cube-root normal approximation, then Newton steps kept inside a bracket."""
    if not 0 < p < 1 or df <= 0:
        raise ValueError("0 < p < 1 and positive degrees of freedom")
    z = normal_quantile(p)
    x = max(df * (1 - 2 / (9 * df) + z * math.sqrt(2 / (9 * df))) ** 3, 1e-8)
    low, high = 0.0, math.inf
    a = df / 2
    for _ in range(200):
        err = gamma_p(a, x / 2) - p
        low, high = (x, high) if err < 0 else (low, x)
        slope = math.exp((a - 1) * math.log(x / 2) - x / 2 - math.lgamma(a)) / 2
        new = x - err / slope if slope > 0 else math.inf
        if not low < new < high:
            new = (low + high) / 2 if high < math.inf else 2 * x
        if abs(new - x) <= 1e-13 * x:
            return new
        x = new
    return x
