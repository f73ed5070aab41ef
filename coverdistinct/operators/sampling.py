"""Samplers of a stream: which occurrences are kept."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.hashing import hash60, threshold


def bernoulli(stream: DataFrame, rate: float, seed: int = 42, fast: bool = False) -> DataFrame:
    """Keeps each occurrence with probability ``rate``, by the hash of its identity: the
    same rows whatever the partitioning, no shuffle, no state.  Rate 1 is no filter."""
    limit = threshold(rate)
    return stream if rate == 1 else stream.where(hash60(F.col("occ"), "s", seed, fast) < limit)


def native(stream: DataFrame, rate: float, seed: int = 42) -> DataFrame:
    """The engine's own sampler; its rows depend on the partitioning."""
    return stream.sample(False, rate, seed)


def fixed_size(stream: DataFrame, size: int, seed: int = 42, fast: bool = False) -> DataFrame:
    """``size`` occurrences without replacement: the lowest hashes, a bounded heap per task."""
    return stream.withColumn("__h", hash60(F.col("occ"), "s", seed, fast)).orderBy("__h", "occ").limit(size).drop("__h")


def by_group(stream: DataFrame, group: str, rates: dict[str, float], seed: int = 42, fast: bool = False) -> DataFrame:
    """A rate of its own for each group; a group without one is left out.  ``rates`` is a
    literal of the plan, no join."""
    limit = F.create_map(*[x for k, r in rates.items() for x in (F.lit(k), F.lit(threshold(r)))])
    return stream.where(hash60(F.col("occ"), "s", seed, fast) < F.try_element_at(limit, F.col(group)))


def with_replacement(stream: DataFrame, rate: float, seed: int = 42) -> DataFrame:
    """For sensitivity only: the analysis samples without replacement."""
    return stream.sample(True, rate, seed)
