"""Paired comparisons over seeds."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def _beta_fraction(a: float, b: float, x: float) -> float:
    """Continued fraction of the incomplete beta function."""
    tiny = 1e-300
    c, d = 1.0, 1 - (a + b) * x / (a + 1)
    d = 1 / (d if abs(d) > tiny else tiny)
    out = d
    for m in range(1, 500):
        for num in (m * (b - m) * x / ((a + 2 * m - 1) * (a + 2 * m)), -(a + m) * (a + b + m) * x / ((a + 2 * m) * (a + 2 * m + 1))):
            d = 1 + num * d
            c = 1 + num / c
            d, c = 1 / (d if abs(d) > tiny else tiny), c if abs(c) > tiny else tiny
            out *= d * c
        if abs(d * c - 1) < 1e-15:
            break
    return out


def beta_inc(a: float, b: float, x: float) -> float:
    """Regularised incomplete beta function."""
    if x <= 0 or x >= 1:
        return float(x >= 1)
    front = math.exp(math.lgamma(a + b) - math.lgamma(a) - math.lgamma(b) + a * math.log(x) + b * math.log1p(-x))
    return front * _beta_fraction(a, b, x) / a if x < (a + 1) / (a + b + 2) else 1 - front * _beta_fraction(b, a, 1 - x) / b


def t_p(t: float, dof: int) -> float:
    """Two-sided p-value of Student's t."""
    if math.isinf(t):
        return 0.0
    return beta_inc(dof / 2, 0.5, dof / (dof + t * t))


def t_quantile(dof: int, level: float = 0.95) -> float:
    lo, hi = 0.0, 1e4
    for _ in range(200):
        mid = (lo + hi) / 2
        lo, hi = (mid, hi) if t_p(mid, dof) > 1 - level else (lo, mid)
    return (lo + hi) / 2


def interval(values: list[float], level: float = 0.95) -> tuple[float, float]:
    """(mean, half width) of the mean's confidence interval."""
    n = len(values)
    m = sum(values) / n
    sd = math.sqrt(sum((v - m) ** 2 for v in values) / (n - 1)) if n > 1 else 0.0
    return m, t_quantile(n - 1, level) * sd / math.sqrt(n) if n > 1 else 0.0


def paired_t(a: list[float], b: list[float]) -> tuple[float, float, float]:
    """(mean of a - b, half width of its 95 % interval, two-sided p)."""
    diff = [x - y for x, y in zip(a, b, strict=True)]
    m, half = interval(diff)
    if half == 0:
        return m, 0.0, 1.0 if m == 0 else 0.0
    return m, half, t_p(m / (half / t_quantile(len(diff) - 1)), len(diff) - 1)


#: Student's 97.5 % quantile for three seeds.
T_TWO = 4.302652729749464


def p_of_two(mean: Column, half: Column) -> Column:
    """p of three paired differences from their mean and half width: closed form for two degrees of freedom."""
    t = F.abs(mean) / (half / F.lit(T_TWO))
    return 1 - t / F.sqrt(t * t + 2)


def summarise(runs: DataFrame, by: list[str], value: str = "value") -> DataFrame:
    """(by, n, mean, half): confidence intervals over three seeds a group."""
    agg = runs.groupBy(*by).agg(F.count(value).alias("n"), F.avg(value).alias("mean"), F.stddev_samp(value).alias("sd"))
    return agg.select(*by, "n", "mean", (F.lit(T_TWO) * F.col("sd") / F.sqrt("n")).alias("half"))
