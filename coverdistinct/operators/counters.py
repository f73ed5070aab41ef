"""Distinct counters for the sample: any of them can be the estimators' first step.

A counter has ``state`` (a mergeable DataFrame), ``merge``, ``estimate`` (one row per group
with ``ns_hat``), ``are`` (relative efficiency) and ``storage_units``.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions import theory
from ..functions.hashing import SPAN, bucket, hash60, rank


def _one(df: DataFrame, group_by: list[str], *aggs: Column) -> DataFrame:
    return df.groupBy(*group_by).agg(*aggs)


@dataclass(frozen=True)
class Exact:
    """Every value is kept: exact, and as large as the number of values."""

    name = "exact"
    are = float("inf")
    storage_units = None

    def state(self, sample, group_by=()):
        return sample.select(*group_by, "element").distinct()

    def merge(self, a, b):
        return a.union(b).distinct()

    def estimate(self, state, group_by=()):
        return _one(state, list(group_by), F.count("element").cast("double").alias("ns_hat"))


@dataclass(frozen=True)
class HyperLogLog:
    """Registers of maximal ranks, for any m >= 2: one partial aggregate, at most m rows per
    task and group, and mergeable by maximum."""

    m: int = 200
    seed: int = 42
    fast: bool = False
    name = "hll"
    are = theory.ARE["hll"]

    @property
    def storage_units(self):
        return self.m

    def registers(self, element: Column) -> tuple[Column, Column]:
        return bucket(element, self.m, self.seed, self.fast), rank(element, self.seed, self.fast)

    def state(self, sample, group_by=()):
        b, r = self.registers(F.col("element"))
        # both in one projection, so that the digest they share is computed once
        return sample.select(*group_by, b.alias("bucket"), r.alias("rank")).groupBy(*group_by, "bucket").agg(F.max("rank").alias("rank"))

    def merge(self, a, b):
        keys = [c for c in a.columns if c != "rank"]
        return a.unionByName(b).groupBy(*keys).agg(F.max("rank").alias("rank"))

    def formula(self, used: Column, power_sum: Column) -> Column:
        """The estimate from the number of used registers and the sum of 2^-rank over them."""
        m = float(self.m)
        empty = m - used
        raw = theory.alpha(self.m) * m * m / (power_sum + empty)
        small = (raw <= 2.5 * m) & (empty > 0)
        return F.when(small, m * F.log(F.lit(m) / F.when(empty > 0, empty))).otherwise(raw)

    def estimate(self, state, group_by=()):
        g = list(group_by)
        sums = _one(state, g, F.count("rank").alias("used"), F.coalesce(F.sum(F.pow(F.lit(2.0), -F.col("rank"))), F.lit(0.0)).alias("power_sum"))
        return sums.select(*g, self.formula(F.col("used"), F.col("power_sum")).alias("ns_hat"))


@dataclass(frozen=True)
class BuiltinHll:
    """The engine's HyperLogLog++."""

    rsd: float = 0.05
    name = "hll_builtin"
    are = theory.ARE["hll"]

    @property
    def storage_units(self):
        return 1 << math.ceil(2 * math.log2(1.106 / self.rsd))

    def state(self, sample, group_by=()):
        return sample

    def estimate(self, state, group_by=()):
        return _one(state, list(group_by), F.approx_count_distinct("element", self.rsd).cast("double").alias("ns_hat"))


@dataclass(frozen=True)
class HllSketch:
    """A storable binary HyperLogLog sketch."""

    lg_m: int = 10
    name = "hll_sketch"
    are = theory.ARE["hll"]

    @property
    def storage_units(self):
        return 1 << self.lg_m

    def state(self, sample, group_by=()):
        return _one(sample, list(group_by), F.hll_sketch_agg("element", F.lit(self.lg_m)).alias("sketch"))

    def merge(self, a, b):
        keys = [c for c in a.columns if c != "sketch"]
        return _one(a.unionByName(b), keys, F.hll_union_agg("sketch").alias("sketch"))

    def estimate(self, state, group_by=()):
        return state.select(*group_by, F.hll_sketch_estimate("sketch").cast("double").alias("ns_hat"))


@dataclass(frozen=True)
class BottomM:
    """The m smallest hashes: (m - 1) / the largest of them, exact below m values."""

    m: int = 200
    seed: int = 42
    fast: bool = False
    name = "bottom_m"
    are = theory.ARE["bottom_m"]

    @property
    def storage_units(self):
        return self.m

    def _lowest(self, hashes, group_by, near=None):
        """The m lowest distinct hashes; ``near`` is a rough count of them, one row: with it
        only about 2 m + 100 of the lowest go on, and no task sends more to the merge (that fewer
        than m of them are there has odds below 1e-12)."""
        if not group_by:
            if near is not None:
                bound = near.select(((2.0 * self.m + 100) * float(SPAN) / F.greatest("near", F.lit(1))).alias("bound"))
                hashes = hashes.crossJoin(F.broadcast(bound)).where(F.col("hash") < F.col("bound")).select("hash")
            return hashes.distinct().orderBy("hash").limit(self.m)
        order = W.partitionBy(*group_by).orderBy("hash")
        return hashes.distinct().withColumn("k", F.row_number().over(order)).where(F.col("k") <= self.m).drop("k")

    def state(self, sample, group_by=()):
        hashes = sample.select(*group_by, hash60(F.col("element"), "v", self.seed, self.fast).alias("hash"))
        return self._lowest(hashes, list(group_by), None if group_by else sample.agg(F.approx_count_distinct("element").alias("near")))

    def merge(self, a, b):
        return self._lowest(a.unionByName(b), [c for c in a.columns if c != "hash"])

    def estimate(self, state, group_by=()):
        n = F.count("hash")
        full = (self.m - 1) / (F.max("hash").cast("double") / float(SPAN))
        return _one(state, list(group_by), F.when(n < self.m, n.cast("double")).otherwise(full).alias("ns_hat"))


@dataclass(frozen=True)
class Theta:
    """The engine's theta sketch: storable, with set operations."""

    lg_m: int = 12
    name = "theta"
    are = theory.ARE["bottom_m"]

    @property
    def storage_units(self):
        return 1 << self.lg_m

    def state(self, sample, group_by=()):
        return _one(sample, list(group_by), F.theta_sketch_agg("element", self.lg_m).alias("sketch"))

    def merge(self, a, b):
        keys = [c for c in a.columns if c != "sketch"]
        return _one(a.unionByName(b), keys, F.theta_union_agg("sketch", self.lg_m).alias("sketch"))

    def estimate(self, state, group_by=()):
        return state.select(*group_by, F.theta_sketch_estimate("sketch").cast("double").alias("ns_hat"))


def max_term_likelihood(histogram: dict[int, int], m: int) -> float:
    """n that makes the register maxima likeliest, P(max <= k) = exp(-(n/m) 2^-k), by
    bisection on the derivative; ``histogram``: registers by maximum, 0 for empty ones."""
    used = {k: c for k, c in histogram.items() if k > 0}
    if not used:
        return 0.0
    empty = m - sum(used.values())

    def slope(x: float) -> float:
        """d log likelihood / d x at n = m x."""
        s = -float(empty)
        for k, c in used.items():
            b = 2.0 ** -k
            z = b * x  # register in (k-1, k]: exp(-b x) - exp(-2 b x), its log's slope
            s += c * (-b + b / math.expm1(z)) if z < 700 else -c * b
        return s

    lo, hi = 1e-9, 1.0
    while slope(hi) > 0 and hi < 1e18:
        hi *= 2
    for _ in range(200):
        mid = (lo + hi) / 2
        lo, hi = (mid, hi) if slope(mid) > 0 else (lo, mid)
    return m * (lo + hi) / 2


@dataclass(frozen=True)
class MaxTerm(HyperLogLog):
    """The same registers, read by maximum likelihood.  Per group the estimate sees a
    histogram of at most 62 rows."""

    name = "max_term"
    are = theory.ARE["max_term"]

    def histogram(self, state, group_by=()):
        return state.groupBy(*group_by, "rank").agg(F.count(F.lit(1)).alias("registers"))

    def estimate(self, state, group_by=()):
        m = self.m

        @F.pandas_udf("double")
        def invert(ranks: pd.Series, registers: pd.Series) -> float:
            return max_term_likelihood(dict(zip(ranks.tolist(), registers.tolist())), m)

        return _one(self.histogram(state, group_by), list(group_by), invert("rank", "registers").alias("ns_hat"))


@dataclass(frozen=True)
class Linear:
    """Occupied buckets of m: good while n is not much above m; null when all are taken."""

    m: int = 4096
    seed: int = 42
    fast: bool = False
    name = "linear"
    are = 1.0

    @property
    def storage_units(self):
        return self.m

    def state(self, sample, group_by=()):
        return sample.select(*group_by, bucket(F.col("element"), self.m, self.seed, self.fast).alias("bucket")).distinct()

    def merge(self, a, b):
        return a.unionByName(b).distinct()

    def estimate(self, state, group_by=()):
        free = self.m - F.count("bucket")
        return _one(state, list(group_by), F.when(free > 0, self.m * F.log(F.lit(float(self.m)) / free)).alias("ns_hat"))


REGISTRY = {c.name: c for c in (Exact, HyperLogLog, BuiltinHll, HllSketch, BottomM, Theta, MaxTerm, Linear)}


def counter(name: str, **options):
    return REGISTRY[name](**options)
