"""Accuracy of the estimators: limit laws, variances, expectations, storage and time.

The arithmetic works on numbers and on Columns alike.  ``p0`` and ``p1`` are the shares
of unseen and once-seen values, ``l`` the sample's length, ``u`` the subsample's, ``m`` the
counter's storage units, ``are`` its relative efficiency.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Relative efficiencies of counters, as published.
ARE = {"bottom_m": 1.00, "max_term": 0.93, "hll": 1 / 1.08}
#: The published relative variance of HyperLogLog is this over m.
HLL_CONSTANT = 1.08


def product_law(mx, vx, my, vy, exact: bool = False):
    """Mean and variance of a product of uncorrelated normal variables."""
    return mx * my, my * my * vx + mx * mx * vy + (vx * vy if exact else 0)


def delta_law(variance, derivative):
    """Variance of a smooth function of an estimator."""
    return variance * derivative * derivative


def inverse_law(variance, p):
    """Variance of 1 / (1 - p)."""
    a = 1 - p
    return delta_law(variance, 1 / (a * a))


def coverage_var(e1, e2, l):  # noqa: E741
    """Variance of e1 / l from the spectrum of the sample."""
    return ((e1 + 2 * e2) / l - (e1 / l) * (e1 / l)) / l


def p0_var_sampled(p0, p1, l):  # noqa: E741
    """Its limit."""
    return (p0 * (1 - p0) + p1) / l


def indicator_var(e1, l, u):  # noqa: E741
    """Variance of the share of once-seen draws among ``u``, given the sample."""
    return (e1 / l) * (1 - e1 / l) / u


def p0_var_subsampled(p0, p1, u, l=None, form: str = "paper"):  # noqa: E741
    """Variance of the subsampled share: as published, or as the sum of both stages."""
    if form == "paper":
        return (2 * p0 * (1 - p0) + p1) / u
    if form == "two_term":
        return (p0 * (1 - p0) + p1) / l + p0 * (1 - p0) / u
    raise ValueError(form)


def ratio_var_sampled(p0, p1, l):  # noqa: E741
    return p0_var_sampled(p0, p1, l) / ((1 - p0) * (1 - p0))


def ratio_var_subsampled(p0, p1, u, l=None, form: str = "paper"):  # noqa: E741
    return p0_var_subsampled(p0, p1, u, l, form) / ((1 - p0) * (1 - p0))


def rel_var_sampled(p0, p1, l, m, are=1.0):  # noqa: E741
    """Relative variance of the coverage estimator."""
    return ratio_var_sampled(p0, p1, l) + 1 / (are * m)


def rel_var_subsampled(p0, p1, u, m, are=1.0, l=None, form: str = "paper"):  # noqa: E741
    """Relative variance of the subsampled coverage estimator."""
    return ratio_var_subsampled(p0, p1, u, l, form) + 1 / (are * m)


def var_before_substitution(ns, p0, p1, size, m, coefficient=1.0):
    """The absolute variance before n_s = n (1 - p0) is put in; coefficient 2 for the subsample."""
    mean, var = product_law(ns, ns * ns / m, 1 / (1 - p0), inverse_law((coefficient * p0 * (1 - p0) + p1) / size, p0))
    return var


def efficiency(n, m, variance):
    """Relative efficiency of a counter from the variance of its estimates."""
    return n * n / m / variance


def _survive(f: Column, rate: float | Column, form: str) -> Column:
    return F.exp(-rate * f) if form == "exp" else F.pow(F.lit(1.0) - rate, f)


def moments_at(freqs: DataFrame, rates: list[float], form: str = "exact") -> DataFrame:
    """``moments`` at several rates, from one pass over the frequencies."""
    rows = freqs.select("f", F.explode(F.array(*[F.lit(float(r)) for r in rates])).alias("rate"))
    return moments(rows, F.col("rate"), ["rate"], form)


def moments(freqs: DataFrame, rate: float | Column, group_by: list[str] | None = None, form: str = "exact") -> DataFrame:
    """Expected p0, p1 over values and, weighted by frequency, over occurrences.

    ``freqs`` has one row per value with its frequency ``f``; one aggregate."""
    f = F.col("f").cast("double")
    once = rate * f * F.exp(-rate * f) if form == "exp" else f * rate * F.pow(F.lit(1.0) - rate, f - 1)
    none = _survive(f, rate, form)
    return freqs.groupBy(*(group_by or [])).agg(
        F.count(F.lit(1)).alias("n"), F.sum("f").cast("long").alias("length"),
        F.avg(none).alias("p0"), F.avg(once).alias("p1"),
        (F.sum(f * none) / F.sum(f)).alias("p0_mass"), (F.sum(f * once) / F.sum(f)).alias("p1_mass"))


def expected_estimate(n, p0, p0_mass):
    """The mean of the coverage estimator to first order: the once-seen share estimates
    unseen occurrences, the scale-up needs unseen values."""
    return n * (1 - p0) / (1 - p0_mass)


def expected_subsampled(n, p0, p0_mass, u, square=None):
    """The mean of the subsampled estimator to second order in 1 / u.  The share of once-seen
    draws has the sample's share as its mean and, with uniform draws that are looked up in the
    sample, the variance p (1 - p) / u.  With draws that keep the copies of a value together, each
    value of k copies adds (1[k = 1] - p k)^2: ``square`` is the sum of k^2 over the sample's length."""
    p = p0_mass
    var = (p * (1 - p) if square is None else p * (1 - 2 * p) + p * p * square) / u
    return expected_estimate(n, p0, p) * (1 + var / ((1 - p) * (1 - p)))


def storage(method: str, m: int, l=0, u=0, ns=None):  # noqa: E741
    """Storage units; with ``ns`` what is really held (one counter per sampled value)."""
    if method == "sampled":
        return m + (l if ns is None else ns)
    if method == "subsampled":
        return m + u
    return m


def reservoir_insertions(u: int, l: int) -> float:  # noqa: E741
    """Expected insertions of a bottom-u reservoir over ``l`` elements in random order."""
    return float(l) if l <= u else u * (1 + math.log(l / u))


def alpha(m: int) -> float:
    """The constant of the harmonic mean of ``m`` registers: published for 16, 32, 64 and
    from 128 on, the defining integral otherwise."""
    if m in (16, 32, 64):
        return {16: 0.673, 32: 0.697, 64: 0.709}[m]
    if m >= 128:
        return 0.7213 / (1 + 1.079 / m)
    # u = t / (1 - t), Simpson's rule
    def g(t: float) -> float:
        if t >= 1:
            return 0.0
        u = t / (1 - t)
        return math.log2((2 + u) / (1 + u)) ** m / (1 - t) ** 2

    k = 20_000
    total = g(0) + g(1) + sum((4 if i % 2 else 2) * g(i / k) for i in range(1, k))
    return 1 / (m * total / (3 * k))
