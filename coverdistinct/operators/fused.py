"""The subsampled estimator in a single scan, and a layout that saves input.

``fused`` reads a sample once: each task folds its rows into m registers, the u lowest
(value hash, occurrence hash) pairs and a count, so at most tasks x (m + u + 1) rows are
shuffled, whatever the data.  Hashes are computed in the JVM; Python sees four numbers a row.

``write_hashed`` stores a table by the leading bits of its occurrence hash.  A sample
at rate P is then the leading P of the partitions: it reads P of the bytes, and stays
a row sample (unlike whole files of an unhashed table).
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.hashing import BITS, hash60, threshold
from .counters import HyperLogLog
from .estimators import finish

LEADING = 8  # bits of the stored partition number


def _lowest(v: np.ndarray, o: np.ndarray, u: int) -> tuple[np.ndarray, np.ndarray]:
    order = np.lexsort((o, v))[:u]
    return v[order], o[order]


def fused(sample: DataFrame, u: int, counter: HyperLogLog | None = None, rate: float | None = None, seed: int = 42, fast: bool = True) -> DataFrame:
    """The same row as ``estimate_subsampled`` with the value-hash probe."""
    hll = counter or HyperLogLog(fast=fast)
    m = hll.m
    b, r = hll.registers(F.col("element"))
    rows = sample.select(b.alias("b"), r.alias("r"), hash60(F.col("element"), "v", seed, fast).alias("v"), hash60(F.col("occ"), "u", seed, fast).alias("o"))

    def fold(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        registers, n = np.zeros(m, np.int64), 0
        v = o = np.zeros(0, np.int64)
        for batch in batches:
            np.maximum.at(registers, np.asarray(batch.column("b")), np.asarray(batch.column("r")))
            v, o = _lowest(np.concatenate([v, np.asarray(batch.column("v"))]), np.concatenate([o, np.asarray(batch.column("o"))]), u)
            n += len(batch)
        used = np.flatnonzero(registers)
        kind = np.concatenate([np.zeros(len(used), np.int32), np.ones(len(v), np.int32), [np.int32(2)]])
        yield pa.RecordBatch.from_arrays([pa.array(kind, pa.int32()), pa.array(np.concatenate([used, v, [0]]), pa.int64()), pa.array(np.concatenate([registers[used], o, [n]]), pa.int64())], ["kind", "k", "x"])

    parts = rows.mapInArrow(fold, "kind int, k long, x long")
    registers = parts.where("kind = 0").groupBy("k").agg(F.max("x").alias("x")).agg(F.count("x").alias("used"), F.coalesce(F.sum(F.pow(F.lit(2.0), -F.col("x"))), F.lit(0.0)).alias("z"))
    probe = parts.where("kind = 1").orderBy("k", "x").limit(u).groupBy("k").agg(F.count(F.lit(1)).alias("f")).agg(
        F.coalesce(F.sum("f"), F.lit(0)).alias("u"), F.count_if(F.col("f") == 1).alias("u1"), F.count_if(F.col("f") == 2).alias("u2"))
    length = parts.where("kind = 2").agg(F.coalesce(F.sum("x"), F.lit(0)).alias("l"))
    null = F.lit(None).cast("long")
    out = length.crossJoin(F.broadcast(registers)).crossJoin(F.broadcast(probe))
    out = out.select("l", "u", F.try_divide("u1", "u").alias("p0"), F.try_divide(2 * F.col("u2"), F.col("u")).alias("p1"), hll.formula(F.col("used"), F.col("z")).alias("ns_hat"), null.alias("ns"), null.alias("e1"), null.alias("e2"))
    return finish(out, "subsampled", hll, rate, [])


def write_hashed(df: DataFrame, occ: Column, path: str, seed: int = 42, fast: bool = True) -> None:
    """One folder per leading value of the occurrence hash; the hash itself is stored."""
    h = df.withColumn("occ_hash", hash60(occ, "s", seed, fast)).withColumn("occ_part", F.shiftright("occ_hash", BITS - LEADING).cast("int"))
    h.repartition("occ_part").sortWithinPartitions("occ_hash").write.partitionBy("occ_part").parquet(path)


def read_sample(spark: SparkSession, path: str, rate: float) -> DataFrame:
    """The rows that ``bernoulli`` would keep, from the partitions that can hold them."""
    limit = threshold(rate)
    last = (limit - 1) >> (BITS - LEADING)
    return spark.read.parquet(path).where((F.col("occ_part") <= last) & (F.col("occ_hash") < limit)).drop("occ_part")


def estimate_until(batches: Iterator[DataFrame], width: float, counter: HyperLogLog | None = None) -> tuple[DataFrame, int]:
    """Adds parts of a sample until the confidence interval is narrow enough: the estimate
    and the number of parts used.  One row per step comes to the driver."""
    from .estimators import estimate_sampled

    sample, used, out = None, 0, None
    for part in batches:
        sample = part if sample is None else sample.unionByName(part)
        used += 1
        out = estimate_sampled(sample, counter)
        row = out.first()
        if row["status"] == "ok" and row["ci_hi"] - row["ci_lo"] <= width * row["n_hat"]:
            break
    return out, used
