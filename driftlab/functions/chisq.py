"""The chi-square distribution and two-sample statistics, as columns and in NumPy.

Upper tails are finite sums: for an even number of degrees of freedom Poisson terms; for an odd one half-integer
terms on top of erfc, which is a series below 1.5 and a continued fraction above. All terms
are positive, so nothing cancels, and all are taken in log space, so nothing overflows.
"""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

_ROOT_PI = math.sqrt(math.pi)


# ------------------------------------------------------------------ NumPy


def chi2_sf(x: float, dof: int) -> float:
    """P(X >= x) for a chi-square variable."""
    if dof <= 0 or not x > 0:
        return 1.0
    z = x / 2
    if dof % 2 == 0:
        logs = [i * math.log(z) - math.lgamma(i + 1) - z for i in range(dof // 2)]
        return min(1.0, math.fsum(math.exp(t) for t in logs))
    logs = [(i - 0.5) * math.log(z) - math.lgamma(i + 0.5) - z for i in range(1, (dof + 1) // 2)]
    return min(1.0, math.erfc(math.sqrt(z)) + math.fsum(math.exp(t) for t in logs))


def chi2_ppf(p: float, dof: int) -> float:
    """The value below which a chi-square variable lies with probability p, by bisection."""
    if not 0 <= p < 1:
        raise ValueError("p must be in [0, 1)")
    if dof <= 0 or p == 0:
        return 0.0
    lo, hi = 0.0, max(1.0, float(dof))
    while 1 - chi2_sf(hi, dof) < p:
        hi *= 2
    for _ in range(200):
        mid = (lo + hi) / 2
        if 1 - chi2_sf(mid, dof) < p:
            lo = mid
        else:
            hi = mid
    return (lo + hi) / 2


def normal_cdf(z: float) -> float:
    return 0.5 * math.erfc(-z / math.sqrt(2))


def table_stat(o: np.ndarray, t: np.ndarray, yates: bool = False) -> tuple[np.ndarray, np.ndarray]:
    """(statistic, degrees of freedom) of the 2 x K table of counts o (K) and each row of t (tests x K)."""
    o, t = np.asarray(o, float), np.atleast_2d(np.asarray(t, float))
    n, q, c = o.sum(), t.sum(axis=1, keepdims=True), o + t
    with np.errstate(divide="ignore", invalid="ignore"):
        gap = np.abs(q * o - n * t)
        if yates:
            gap = np.maximum(gap - (n + q) / 2, 0)
        stat = np.where(c > 0, gap**2 / c, 0.0).sum(axis=1) / (n * q[:, 0])
    return np.nan_to_num(stat), (c > 0).sum(axis=1) - 1


def gof_stat(o: np.ndarray, t: np.ndarray) -> np.ndarray:
    """One-way statistic of each row of t against the shares of o."""
    o, t = np.asarray(o, float), np.atleast_2d(np.asarray(t, float))
    expect = t.sum(axis=1, keepdims=True) * o / o.sum()
    with np.errstate(divide="ignore", invalid="ignore"):
        return np.where(expect > 0, (t - expect) ** 2 / expect, np.where(t > 0, np.inf, 0.0)).sum(axis=1)


# ------------------------------------------------------------------ columns


def _sum(items: Column, term) -> Column:
    return F.aggregate(items, F.lit(0.0), lambda acc, i: acc + term(i))


def log_gamma_half(k: Column) -> Column:
    """ln Gamma(k / 2) for a whole k >= 1."""
    half = F.floor(k / 2).cast("int")
    whole = F.when(half > 1, _sum(F.sequence(F.lit(1), F.greatest(half - 1, F.lit(1))), lambda i: F.log(i.cast("double")))).otherwise(F.lit(0.0))
    odd = F.lit(math.log(_ROOT_PI)) + F.when(half > 0, _sum(F.sequence(F.lit(1), F.greatest(half, F.lit(1))), lambda i: F.log(i.cast("double") - 0.5))).otherwise(F.lit(0.0))
    return F.when(k % 2 == 0, whole).otherwise(odd)


def erfc_col(x: Column) -> Column:
    """Complementary error function of a column that is not negative."""
    series = F.aggregate(
        F.sequence(F.lit(1), F.lit(60)),
        F.struct(F.lit(1.0).alias("term"), F.lit(1.0).alias("total")),
        lambda s, i: F.struct((s["term"] * 2 * x * x / (2 * i + 1)).alias("term"), (s["total"] + s["term"] * 2 * x * x / (2 * i + 1)).alias("total")),
    )["total"]
    low = 1 - 2 / _ROOT_PI * x * F.exp(-x * x) * series
    tail = F.aggregate(F.sequence(F.lit(80), F.lit(1)), x, lambda t, i: x + i / 2.0 / t)
    return F.when(x < 1.5, low).otherwise(F.exp(-x * x) / (_ROOT_PI * tail))


def chi2_sf_col(x: Column, dof: Column) -> Column:
    """Upper tail as a column expression; 1 for no degrees of freedom."""
    z, k = (x / 2).cast("double"), dof.cast("int")
    terms = F.greatest(F.floor(k / 2).cast("int"), F.lit(1))
    even = F.aggregate(
        F.sequence(F.lit(1), terms),
        F.struct((-z).alias("log"), F.lit(0.0).alias("total")),
        lambda s, i: F.struct((s["log"] + F.log(z) - F.log(i.cast("double"))).alias("log"), (s["total"] + F.exp(s["log"])).alias("total")),
    )["total"]
    odd = F.aggregate(
        F.sequence(F.lit(1), terms),
        F.struct((0.5 * F.log(z) - math.log(_ROOT_PI / 2) - z).alias("log"), F.lit(0.0).alias("total")),
        lambda s, i: F.struct((s["log"] + F.log(z) - F.log(i.cast("double") + 0.5)).alias("log"), (s["total"] + F.exp(s["log"])).alias("total")),
    )["total"]
    tail = F.when(k % 2 == 0, even).otherwise(erfc_col(F.sqrt(z)) + F.when(k > 1, odd).otherwise(0.0))
    return F.when((k <= 0) | ~(x > 0), F.lit(1.0)).otherwise(F.least(F.lit(1.0), tail))


def table_stat_col(o: Column, t: Column) -> Column:
    """Statistic of two arrays of counts."""
    n, q = (F.aggregate(a, F.lit(0.0), lambda s, v: s + v) for a in (o, t))
    cells = F.zip_with(o, t, lambda a, b: F.when(a + b > 0, (q * a - n * b) * (q * a - n * b) / (a + b)).otherwise(0.0))
    return F.aggregate(cells, F.lit(0.0), lambda s, v: s + v) / (n * q)


def table_dof_col(o: Column, t: Column) -> Column:
    return F.size(F.filter(F.zip_with(o, t, lambda a, b: a + b), lambda c: c > 0)) - 1


# ------------------------------------------------------------------ the same tail in DuckDB


def sf_sql(x: str, dof: str) -> str:
    """SQL for the upper tail: one less the lower series, with lgamma."""
    series = f"list_sum(list_transform(range(0, 800), lambda i: exp(-({x}) / 2.0 + (({dof}) / 2.0 + i) * ln(({x}) / 2.0) - lgamma(({dof}) / 2.0 + i + 1))))"
    return f"(CASE WHEN ({dof}) <= 0 OR NOT ({x}) > 1e-12 THEN 1.0 ELSE greatest(0.0, 1.0 - {series}) END)"
