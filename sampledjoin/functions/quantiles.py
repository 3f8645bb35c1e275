"""Quantiles of the normal and of Student's t distribution, on the driver and as columns."""

from __future__ import annotations

import math
from statistics import NormalDist

from pyspark.sql import Column
from pyspark.sql import functions as F


def z_quantile(confidence: float) -> float:
    """Half-width of the two-sided normal interval, in standard deviations."""
    return NormalDist().inv_cdf(0.5 + confidence / 2)


def _beta_fraction(a: float, b: float, x: float) -> float:
    """Continued fraction of the incomplete beta function (modified Lentz)."""
    tiny, c, d = 1e-300, 1.0, 1 - (a + b) * x / (a + 1)
    d = 1 / (d if abs(d) > tiny else tiny)
    out = d
    for m in range(1, 300):
        for top in (m * (b - m) * x / ((a + 2 * m - 1) * (a + 2 * m)), -(a + m) * (a + b + m) * x / ((a + 2 * m) * (a + 2 * m + 1))):
            d = 1 + top * d
            c = 1 + top / c
            d, c = 1 / (d if abs(d) > tiny else tiny), c if abs(c) > tiny else tiny
            out *= d * c
        if abs(d * c - 1) < 1e-14:
            break
    return out


def t_cdf(t: float, f: float) -> float:
    x = f / (f + t * t)
    if x >= 1:
        return 0.5
    a, b = f / 2, 0.5
    front = math.exp(math.lgamma(a + b) - math.lgamma(a) - math.lgamma(b) + a * math.log(x) + b * math.log1p(-x))
    tail = front * _beta_fraction(a, b, x) / a if x < (a + 1) / (a + b + 2) else 1 - front * _beta_fraction(b, a, 1 - x) / b
    return 1 - tail / 2 if t > 0 else tail / 2


def t_quantile(p: float, f: float) -> float:
    """By bisection."""
    lo, hi = -1e4, 1e4
    for _ in range(200):
        mid = (lo + hi) / 2
        lo, hi = (mid, hi) if t_cdf(mid, f) < p else (lo, mid)
    return (lo + hi) / 2


def t_column(confidence: float, f: Column) -> Column:
    """A series in 1/f around the normal quantile; good from about f = 30 on. The normal quantile where f is not positive."""
    z = z_quantile(confidence)
    series = F.lit(z) + F.lit((z**3 + z) / 4) / f + F.lit((5 * z**5 + 16 * z**3 + 3 * z) / 96) / (f * f)
    return F.when(f > 0, series).otherwise(F.lit(z))


def t_sql(confidence: float, f: str) -> str:
    """The same series as SQL text."""
    z = z_quantile(confidence)
    return f"(CASE WHEN {f} > 0 THEN {z!r} + {(z**3 + z) / 4!r} / ({f}) + {(5 * z**5 + 16 * z**3 + 3 * z) / 96!r} / (CAST({f} AS DOUBLE) * ({f})) ELSE {z!r} END)"
