"""Probes of the singleton share on a subsample of ``u`` occurrences.

``in_sub``      u occurrences in uniform order, values that are unique among them (the
                procedure read literally: diverges when u is below the number of values)
``in_sample``   the same occurrences, but "once" means once in the whole sample
``value_hash``  the u lowest by value hash, then occurrence hash: copies of a value stay
                together, one pass, and the default

Each gives ``(group.., u, u1, u2, p0, p1)``.  Ungrouped, the lowest u come from a bounded heap
per task; grouped, from a limit per group before and after the shuffle.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.hashing import hash60

MODES = ("in_sub", "in_sample", "value_hash")


def _lowest(df: DataFrame, order: list[str], u: int, group_by: list[str]) -> DataFrame:
    if not group_by:
        return df.orderBy(*order).limit(u)
    return df.withColumn("__k", F.row_number().over(W.partitionBy(*group_by).orderBy(*order))).where(F.col("__k") <= u).drop("__k")


def subsample(sample: DataFrame, u: int, mode: str = "value_hash", seed: int = 42, group_by: list[str] | None = None, fast: bool = False) -> DataFrame:
    """The u occurrences: ``(group.., element, occ_hash, value_hash)``."""
    g = group_by or []
    rows = sample.select(*g, "element", hash60(F.col("occ"), "u", seed, fast).alias("occ_hash"), hash60(F.col("element"), "v", seed, fast).alias("value_hash"))
    order = ["value_hash", "occ_hash"] if mode == "value_hash" else ["occ_hash", "value_hash"]
    return _lowest(rows, order, u, g)


def _heads(values: DataFrame, g: list[str]) -> DataFrame:
    """``values``: one row per value with its count ``f`` in the subsample."""
    out = values.groupBy(*g).agg(F.coalesce(F.sum("f"), F.lit(0)).alias("u"), F.count_if(F.col("f") == 1).alias("u1"), F.count_if(F.col("f") == 2).alias("u2"))
    return out.select(*g, "u", "u1", "u2", F.try_divide("u1", "u").alias("p0"), F.try_divide(2 * F.col("u2"), F.col("u")).alias("p1"))


def probe(sample: DataFrame, u: int, mode: str = "value_hash", seed: int = 42, group_by: list[str] | None = None, fast: bool = False, boundary: str = "keep") -> DataFrame:
    """``boundary``: 'keep' counts the last value of a value-hash probe, which may be cut
    off; 'drop' leaves it out."""
    if mode not in MODES:
        raise ValueError(mode)
    g = group_by or []
    sub = subsample(sample, u, mode, seed, g, fast)
    if mode == "in_sample":
        wanted = sub.groupBy(*g, "element").agg(F.count(F.lit(1)).alias("in_sub"))
        # at most u values a group: broadcast to a second pass over the sample
        hits = sample.join(F.broadcast(wanted) if not g and u <= 1_000_000 else wanted, [*g, "element"])
        full = hits.groupBy(*g, "element").agg(F.count(F.lit(1)).alias("f"), F.first("in_sub").alias("in_sub"))
        out = full.groupBy(*g).agg(F.coalesce(F.sum("in_sub"), F.lit(0)).alias("u"),
                                   F.coalesce(F.sum(F.when(F.col("f") == 1, F.col("in_sub"))), F.lit(0)).alias("u1"),
                                   F.coalesce(F.sum(F.when(F.col("f") == 2, F.col("in_sub"))), F.lit(0)).alias("u2"))
        return out.select(*g, "u", "u1", "u2", F.try_divide("u1", "u").alias("p0"), F.try_divide("u2", "u").alias("p1"))
    if mode == "value_hash" and boundary == "drop":
        last = F.max("value_hash").over(W.partitionBy(*(g or [F.lit(0)])))
        taken = F.count(F.lit(1)).over(W.partitionBy(*(g or [F.lit(0)])))
        sub = sub.withColumn("__last", last).withColumn("__n", taken).where((F.col("__n") < u) | (F.col("value_hash") < F.col("__last")))
    return _heads(sub.groupBy(*g, "element").agg(F.count(F.lit(1)).alias("f")), g)


_HELD = "element string, key long, occ_hash long, value_hash long, seen long, insertions long"


def reservoir_parts(sample: DataFrame, u: int, keys: str = "value", seed: int = 42) -> DataFrame:
    """One pass per task over its rows in order, with u places: an element whose key is below
    the highest one held takes that one's place.  Keys: ``value`` or ``occ`` hashes, or ``random``
    draws (the classic reservoir; not the same under repartitioning).  At most u rows a task,
    each with how many rows the task saw and how many of them were inserted."""
    if keys not in ("value", "occ", "random"):
        raise ValueError(keys)
    rows = sample.select(F.col("element").cast("string").alias("element"), hash60(F.col("occ"), "u", seed).alias("occ_hash"), hash60(F.col("element"), "v", seed).alias("value_hash"))

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        from pyspark import TaskContext

        rng = np.random.default_rng([seed, TaskContext.get().partitionId()])
        held: list[tuple] = []  # a heap of what is held, the highest key on top
        seen = inserted = 0
        for b in batches:
            key = b["value_hash"].to_numpy() if keys == "value" else b["occ_hash"].to_numpy() if keys == "occ" else rng.integers(0, 1 << 60, len(b))
            seen += len(b)
            free = max(u - len(held), 0)
            # what is not below the top now will not be later
            some = np.arange(len(b)) if free else np.flatnonzero(key <= -held[0][0])
            for i in some.tolist():
                x = (-int(key[i]), -int(b["occ_hash"].iat[i]), int(b["value_hash"].iat[i]), b["element"].iat[i])
                if len(held) < u:
                    heapq.heappush(held, x)
                elif x > held[0]:
                    heapq.heapreplace(held, x)
                else:
                    continue
                inserted += 1
        if seen:
            yield pd.DataFrame([(e, -k, -o, v, seen, inserted) for k, o, v, e in held], columns=["element", "key", "occ_hash", "value_hash", "seen", "insertions"])

    return rows.mapInPandas(run, _HELD)


def reservoir(sample: DataFrame, u: int, keys: str = "value", seed: int = 42) -> DataFrame:
    """The subsample U of u occurrences, merged from the reservoirs of all tasks: (element,
    occ_hash, value_hash).  Reservoirs of parts of a stream merge the same way."""
    return merge_reservoirs(reservoir_parts(sample, u, keys, seed), u).select("element", "occ_hash", "value_hash")


def merge_reservoirs(parts: DataFrame, u: int) -> DataFrame:
    return parts.orderBy("key", "occ_hash").limit(u)


def reservoir_cost(sample: DataFrame, u: int, seed: int = 42) -> DataFrame:
    """Per task the rows seen, the insertions measured and u (1 + ln(l / u)), what they are in
    random order."""
    parts = reservoir_parts(sample, u, "occ", seed).withColumn("task", F.spark_partition_id())
    seen = F.col("seen").cast("double")
    expected = F.when(seen <= u, seen).otherwise(u * (1 + F.log(seen / u)))
    return parts.groupBy("task").agg(F.first("seen").alias("seen"), F.first("insertions").alias("insertions")).withColumn("expected", expected)
