"""Frequencies of frequencies and Good-Turing estimates."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F


def counts(sample: DataFrame, group_by: list[str] | None = None) -> DataFrame:
    """One row per value: the only shuffle by element, after a partial count, so a hot
    value sends one row per task."""
    return sample.groupBy(*(group_by or []), "element").agg(F.count(F.lit(1)).alias("f"))


def spectrum(sample: DataFrame, group_by: list[str] | None = None) -> DataFrame:
    """``(i, e_i)``: how many values occur i times."""
    g = group_by or []
    return counts(sample, g).groupBy(*g, F.col("f").alias("i")).agg(F.count(F.lit(1)).alias("e_i"))


def heads(sample: DataFrame, group_by: list[str] | None = None) -> DataFrame:
    """l, ns, e1, e2 in one job: length, distinct values, values seen once and twice."""
    return counts(sample, group_by).groupBy(*(group_by or [])).agg(
        F.coalesce(F.sum("f"), F.lit(0)).alias("l"), F.count(F.lit(1)).alias("ns"),
        F.count_if(F.col("f") == 1).alias("e1"), F.count_if(F.col("f") == 2).alias("e2"))


def good_turing(spec: DataFrame, group_by: list[str] | None = None) -> DataFrame:
    """``(i, e_next, p_i)``: the probability that an element of the stream occurs i times in
    the sample, (i + 1) e_{i+1} / l, for every i that has a positive estimate."""
    over = W.partitionBy(*(group_by or [F.lit(0)]))
    total = F.sum(F.col("i") * F.col("e_i")).over(over)
    return spec.select(*(group_by or []), (F.col("i") - 1).alias("i"), F.col("e_i").alias("e_next"),
                       (F.col("i") * F.col("e_i") / total).alias("p_i"))


def empirical_prob(sample: DataFrame) -> DataFrame:
    """The plain relative frequency of each sampled value: 0 for all others."""
    c = counts(sample)
    total = c.agg(F.sum("f").alias("l"))
    return c.crossJoin(F.broadcast(total)).select("element", "f", (F.col("f") / F.col("l")).alias("prob"))


def unseen_truth(stream: DataFrame, sample: DataFrame) -> DataFrame:
    """Diagnostics that need the whole stream: unseen share of occurrences and of values."""
    full = counts(stream)
    seen = sample.select("element").distinct()
    unseen = full.join(seen, "element", "left_anti").agg(F.count(F.lit(1)).alias("unseen_values"), F.coalesce(F.sum("f"), F.lit(0)).alias("unseen_rows"))
    total = full.agg(F.count(F.lit(1)).alias("n"), F.sum("f").alias("length"))
    return total.crossJoin(unseen).select("n", "length", "unseen_values", "unseen_rows",
                                          F.try_divide("unseen_rows", "length").alias("p0_mass"), F.try_divide("unseen_values", "n").alias("p0_distinct"))
