"""Splitting a storage budget B between counter (m) and subsample (u).

The variance is c / u + k / m with m + u = B, k = 1 / efficiency and
c = (2 P0 (1 - P0) + P1) / (1 - P0)^2, so the best shares are as the square roots.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import theory


def coefficient(p0, p1):
    """c, on numbers and Columns."""
    return (2 * p0 * (1 - p0) + p1) / ((1 - p0) * (1 - p0))


def variance(m: float, u: float, c: float, are: float = 1.0) -> float:
    return c / u + 1 / (are * m)


def best_split(budget: int, p0: float, p1: float, are: float = 1.0) -> tuple[int, int]:
    """``(m, u)`` with the least variance, 2 <= m and 1 <= u; integer neighbours are compared."""
    if budget < 3:
        raise ValueError("a budget is 3 units at least")
    c, k = max(coefficient(p0, p1), 0.0), 1 / are
    ideal = budget * math.sqrt(c) / (math.sqrt(c) + math.sqrt(k))
    tries = {min(max(int(math.floor(ideal)) + d, 1), budget - 2) for d in (-1, 0, 1, 2)}
    u = min(tries, key=lambda x: (variance(budget - x, x, c, are), x))
    return budget - u, u


def best_u(budget: Column, c: Column, are: Column) -> Column:
    """The same in the plan: floor and ceiling of the ideal share, whichever varies less."""
    ideal = budget * F.sqrt(c) / (F.sqrt(c) + F.sqrt(1 / are))
    fit = lambda x: F.least(F.greatest(x, F.lit(1.0)), budget - 2)
    low, high = fit(F.floor(ideal).cast("double")), fit(F.ceil(ideal).cast("double"))
    var = lambda u: c / u + 1 / (are * (budget - u))
    return F.when(var(high) < var(low), high).otherwise(low).cast("long")


def best_split_sampled(budget: int, length: int, ns: int | None = None) -> int:
    """For the first method the variance falls with m alone: all beyond the singleton count's storage."""
    return max(budget - (length if ns is None else ns), 0)


def split_sampled(budget: Column, held: Column) -> Column:
    """The same in the plan: null where the budget does not hold the singleton count and two registers."""
    return F.when(budget - held >= 2, budget - held).cast("long")


def best_u_sql(b: str, c: str, are: str) -> str:
    """``best_u`` as SQL text, for functions whose bodies are put in line."""
    ideal = f"{b} * sqrt({c}) / (sqrt({c}) + sqrt(1 / {are}))"
    low, high = (f"least(greatest(CAST({f}({ideal}) AS DOUBLE), 1), {b} - 2)" for f in ("floor", "ceil"))
    var = "{c} / ({u}) + 1 / ({are} * ({b} - ({u})))"
    return f"CAST(CASE WHEN {var.format(c=c, u=high, are=are, b=b)} < {var.format(c=c, u=low, are=are, b=b)} THEN {high} ELSE {low} END AS BIGINT)"


def budget_for(target: float, p0: float, p1: float, are: float = 1.0) -> int:
    """The least budget whose best split reaches the target variance."""
    return int(math.ceil((math.sqrt(coefficient(p0, p1)) + math.sqrt(1 / are)) ** 2 / target))


def budget_column(target: Column, c: Column, are: Column) -> Column:
    return F.ceil(F.pow(F.sqrt(c) + F.sqrt(1 / are), 2) / target).cast("long")


def pilot_moments(sample: DataFrame) -> DataFrame:
    """p0, p1 of a (small) sample: what the planner needs, from one pass."""
    from .spectrum import heads
    length = F.col("l").cast("double")
    return heads(sample).select("l", "ns", "e1", "e2", F.try_divide(F.col("e1"), length).alias("p0"), F.try_divide(2 * F.col("e2"), length).alias("p1"))


def estimate_budgeted(sample: DataFrame, budget: int, pilot: DataFrame | None = None, moments: tuple[float, float] | None = None,
                      mode: str = "value_hash", rate: float | None = None, seed: int = 42, are: float = 1.0) -> DataFrame:
    """Split the budget by the pilot's moments (one row to the driver), or by given ones,
    then estimate by subsample.  Adds budget and predicted_var."""
    from .counters import HyperLogLog
    from .estimators import estimate_subsampled

    if moments is None:
        row = pilot_moments(pilot if pilot is not None else sample).first()
        p0 = min(row["p0"] if row["p0"] is not None else 0.0, 0.999)
        moments = (p0, row["p1"] or 0.0)
    m, u = best_split(budget, *moments, are)
    out = estimate_subsampled(sample, u, HyperLogLog(m), mode, rate=rate, seed=seed)
    return out.withColumn("budget", F.lit(budget)).withColumn("predicted_var", F.lit(theory.rel_var_subsampled(*moments, u, m, are)))
