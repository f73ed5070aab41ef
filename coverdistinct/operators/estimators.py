"""The coverage estimators and what they are compared with.

The coverage estimator scales the sample's distinct count by 1 / (1 - P0), where P0 is
the share of once-seen values among the sample's occurrences; the subsampled one takes
P0 from a probe.  Both give one ``EstimateRow`` per group, lazily.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import theory
from .counters import HyperLogLog
from .probe import probe
from .sampling import bernoulli
from .spectrum import counts, heads

Z = 1.96
ROW = ["method", "procedure", "rate", "m", "u", "l", "e1", "e2", "p0", "p1", "ns_hat", "ratio", "n_hat", "rel_var",
       "ci_lo", "ci_hi", "storage_units", "storage_actual", "status"]


def _are(counter) -> float:
    return counter.are


def finish(df: DataFrame, method: str, counter, rate: float | None, group_by: list[str], are: float | None = None) -> DataFrame:
    """Columns l, ns (or null), e1, e2, u, p0, p1, ns_hat -> the estimate row."""
    are = _are(counter) if are is None else are
    whole = rate == 1
    p0 = F.lit(0.0) if whole else F.col("p0")
    p1 = F.lit(0.0) if whole else F.col("p1")
    status = (F.when(F.col("l") == 0, "empty_sample").when(F.lit(False) if whole else F.col("p0") >= 1, "all_singletons").otherwise("ok"))
    ratio = F.when(F.col("l") > 0, F.try_divide(F.lit(1.0), 1 - p0))
    m = counter.storage_units
    sketch = F.lit(0.0) if are == float("inf") or m is None else F.lit(1 / (are * m))
    size = F.col("l") if method == "sampled" else F.col("u")
    cover = (p0 * (1 - p0) + p1) if method == "sampled" else (2 * p0 * (1 - p0) + p1)
    noise = F.lit(0.0) if whole else F.try_divide(F.try_divide(cover, size.cast("double")), (1 - p0) * (1 - p0))
    n_hat = F.col("ns_hat") * F.col("ratio")
    df = df.withColumn("status", status).withColumn("ratio", ratio).withColumn("rel_var", F.when(F.col("status") == "ok", noise + sketch))
    half = Z * F.sqrt("rel_var")
    units = F.lit(m).cast("long") if m is not None else F.col("ns_hat").cast("long")
    extra = F.lit(0) if whole else (F.col("l") if method == "sampled" else F.col("u"))
    actual = F.lit(0) if whole else (F.coalesce("ns", "l") if method == "sampled" else F.col("u"))
    return df.select(
        *group_by, F.lit(method).alias("method"), F.lit(counter.name).alias("procedure"), F.lit(rate).cast("double").alias("rate"),
        F.lit(m).cast("long").alias("m"), F.col("u").cast("long").alias("u"), F.col("l").cast("long").alias("l"), F.col("e1").cast("long").alias("e1"), F.col("e2").cast("long").alias("e2"),
        p0.alias("p0"), p1.alias("p1"), F.when(F.col("l") > 0, F.col("ns_hat")).alias("ns_hat"), "ratio",
        F.when(F.col("status") == "ok", n_hat).alias("n_hat"), "rel_var",
        F.when(F.col("status") == "ok", F.greatest(n_hat * (1 - half), F.coalesce("ns", F.lit(0)).cast("double"))).alias("ci_lo"),
        F.when(F.col("status") == "ok", n_hat * (1 + half)).alias("ci_hi"),
        (units + extra).cast("long").alias("storage_units"), (units + actual).cast("long").alias("storage_actual"), "status")


def _fused(sample: DataFrame, hll: HyperLogLog, g: list[str]) -> DataFrame:
    """Registers and spectrum heads from one scan and one shuffle by element: registers do
    not mind duplicates, so they are fed by the per-value counts."""
    b, r = hll.registers(F.col("element"))
    per_value = counts(sample, g).select(*g, "f", b.alias("bucket"), r.alias("rank"))
    per_bucket = per_value.groupBy(*g, "bucket").agg(
        F.max("rank").alias("rank"), F.sum("f").alias("l"), F.count(F.lit(1)).alias("ns"),
        F.count_if(F.col("f") == 1).alias("e1"), F.count_if(F.col("f") == 2).alias("e2"))
    out = per_bucket.groupBy(*g).agg(
        F.count("bucket").alias("used"), F.coalesce(F.sum(F.pow(F.lit(2.0), -F.col("rank"))), F.lit(0.0)).alias("power_sum"),
        *[F.coalesce(F.sum(c), F.lit(0)).alias(c) for c in ("l", "ns", "e1", "e2")])
    return out.withColumn("ns_hat", hll.formula(F.col("used"), F.col("power_sum")))


def _registers_and_length(sample: DataFrame, hll: HyperLogLog, g: list[str]) -> DataFrame:
    """The count and the sample's length from one scan: registers carry how many rows fed
    them, so a task shuffles m rows.  (The lowest u of a probe are another scan: the engine has
    no aggregate that keeps them; ``fused`` folds both in one, in Python workers.)"""
    b, r = hll.registers(F.col("element"))
    regs = sample.select(*g, b.alias("bucket"), r.alias("rank")).groupBy(*g, "bucket").agg(F.max("rank").alias("rank"), F.count(F.lit(1)).alias("rows"))
    out = regs.groupBy(*g).agg(F.count("bucket").alias("used"), F.coalesce(F.sum(F.pow(F.lit(2.0), -F.col("rank"))), F.lit(0.0)).alias("power_sum"), F.coalesce(F.sum("rows"), F.lit(0)).alias("l"))
    return out.select(*g, hll.formula(F.col("used"), F.col("power_sum")).alias("ns_hat"), "l")


def _combine(a: DataFrame, b: DataFrame, g: list[str]) -> DataFrame:
    """Two frames of one row, or of one row per group."""
    if not g:
        return a.crossJoin(F.broadcast(b))
    named = b.withColumnsRenamed({c: f"__{c}" for c in g})
    condition = None
    for c in g:
        eq = F.col(c).eqNullSafe(F.col(f"__{c}"))
        condition = eq if condition is None else condition & eq
    return a.join(named, condition).drop(*[f"__{c}" for c in g])


def estimate_sampled(sample: DataFrame, counter=None, group_by: list[str] | None = None, rate: float | None = None, are: float | None = None) -> DataFrame:
    """The coverage estimator on a sample (element, occ, groups)."""
    counter = counter or HyperLogLog()
    g = group_by or []
    if type(counter) is HyperLogLog:
        parts = _fused(sample, counter, g)
    else:
        parts = _combine(heads(sample, g), counter.estimate(counter.state(sample, g), g), g)
    length = F.col("l").cast("double")
    parts = parts.withColumn("u", F.lit(0)).withColumn("p0", F.try_divide(F.col("e1"), length)).withColumn("p1", F.try_divide(2 * F.col("e2"), length))
    return finish(parts, "sampled", counter, rate, g, are)


def estimate_from(stream: DataFrame, rate: float, counter=None, group_by: list[str] | None = None, seed: int = 42, fast: bool = False) -> DataFrame:
    """Sample and estimate in one plan."""
    return estimate_sampled(bernoulli(stream, rate, seed, fast), counter, group_by, rate)


def estimate_subsampled(sample: DataFrame, u: int, counter=None, mode: str = "value_hash", group_by: list[str] | None = None,
                        rate: float | None = None, seed: int = 42, fast: bool = False, boundary: str = "keep", are: float | None = None) -> DataFrame:
    """The subsampled coverage estimator: the counter sees the whole sample, the singleton
    share comes from u occurrences; no shuffle by element."""
    counter = counter or HyperLogLog()
    g = group_by or []
    found = probe(sample, u, mode, seed, g, fast, boundary)
    if type(counter) is HyperLogLog:
        counted = _registers_and_length(sample, counter, g)
    else:
        counted = _combine(counter.estimate(counter.state(sample, g), g), sample.groupBy(*g).agg(F.count(F.lit(1)).alias("l")), g)
    parts = _combine(counted, found, g)
    parts = parts.withColumn("ns", F.lit(None).cast("long")).withColumn("e1", F.lit(None).cast("long")).withColumn("e2", F.lit(None).cast("long"))
    return finish(parts, "subsampled", counter, rate, g, are)


def naive(sample: DataFrame, counter=None, group_by: list[str] | None = None) -> DataFrame:
    """The sample's distinct count taken for the stream's."""
    counter = counter or HyperLogLog()
    return counter.estimate(counter.state(sample, group_by or []), group_by or []).withColumnRenamed("ns_hat", "n_hat")


def full(stream: DataFrame, counter=None, group_by: list[str] | None = None) -> DataFrame:
    """The counter on the whole stream."""
    return naive(stream, counter, group_by)


def exact(stream: DataFrame, group_by: list[str] | None = None) -> DataFrame:
    return stream.groupBy(*(group_by or [])).agg(F.count_distinct("element").alias("n"), F.count(F.lit(1)).alias("length"))


def scale_up(sample: DataFrame, rate: float, group_by: list[str] | None = None) -> DataFrame:
    """The strawman n_s / rate."""
    return heads(sample, group_by).select(*(group_by or []), "ns", (F.col("ns") / rate).alias("n_hat"))


def oracle_ratio(stream: DataFrame, sample: DataFrame) -> DataFrame:
    """n_s / (1 - true unseen share of values): the identity behind the scale-up."""
    from .spectrum import unseen_truth
    ns = sample.agg(F.count_distinct("element").alias("ns"))
    return unseen_truth(stream, sample).crossJoin(ns).select("n", "ns", "p0_distinct", F.try_divide(F.col("ns").cast("double"), 1 - F.col("p0_distinct")).alias("n_hat"))


def skew_aware(sample: DataFrame) -> DataFrame:
    """Published comparators that are not part of the methods above: the lower bound
    n_s + e1^2 / (2 e2), and coverage with a squared-variation correction."""
    c = counts(sample)
    h = c.agg(F.sum("f").alias("l"), F.count(F.lit(1)).alias("ns"), F.count_if(F.col("f") == 1).alias("e1"), F.count_if(F.col("f") == 2).alias("e2"),
              F.sum(F.col("f") * (F.col("f") - 1)).alias("pairs"))
    share = 1 - F.col("e1") / F.col("l")
    base = F.try_divide(F.col("ns").cast("double"), share)
    cv2 = F.greatest(base * F.col("pairs") / (F.col("l").cast("double") * (F.col("l") - 1)) - 1, F.lit(0.0))
    return h.select("ns", "e1", "e2", (F.col("ns") + F.try_divide(F.col("e1").cast("double") * F.col("e1"), 2.0 * F.col("e2"))).alias("lower_bound"),
                    base.alias("coverage"), cv2.alias("cv2"), (base + F.try_divide(F.col("l") * (1 - share), share) * cv2).alias("coverage_cv"))


def expected(freqs: DataFrame, rate: float) -> DataFrame:
    """The mean that the coverage estimator has on a stream with these frequencies."""
    m = theory.moments(freqs, rate)
    return m.withColumn("expected_n_hat", theory.expected_estimate(F.col("n"), F.col("p0"), F.col("p0_mass")))
