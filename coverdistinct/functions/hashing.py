"""Hashes of elements and occurrences.

``portable`` hashes are slices of MD5, which any SQL engine can replay; ``fast`` ones are
xxHash64.  Both give 60 bits, so a hash is a non-negative long and a rate is a
threshold on it.
"""

from __future__ import annotations

import math

from pyspark.sql import Column
from pyspark.sql import functions as F

BITS = 60
SPAN = 1 << BITS


def encode(*columns: Column) -> Column:
    """One string for a composite key: every part with its length, nulls marked, so that
    ('a', 'bc') and ('ab', 'c') differ.  A single column is its own string."""
    if len(columns) == 1:
        return columns[0].cast("string")
    parts = [F.coalesce(F.concat(F.length(c.cast("string")).cast("string"), F.lit(":"), c.cast("string")), F.lit("~")) for c in columns]
    return F.concat_ws(",", *parts)


def normal_double(c: Column) -> Column:
    """-0.0 is 0.0, and NaN is one value."""
    return F.when(F.isnan(c), F.lit(float("nan"))).when(c == 0, F.lit(0.0)).otherwise(c)


def _digest(c: Column, purpose: str, seed: int | Column) -> Column:
    if isinstance(seed, Column):
        return F.md5(F.concat(c.cast("string"), F.lit(f"|{purpose}"), seed.cast("string")))
    return F.md5(F.concat(c.cast("string"), F.lit(f"|{purpose}{seed}")))


def _hex(digest: Column, first: int, n: int) -> Column:
    return F.conv(F.substring(digest, first, n), 16, 10).cast("long")


def hash60(c: Column, purpose: str, seed: int | Column, fast: bool = False) -> Column:
    """60 bits of the hash of ``c``; ``purpose`` keeps occurrence and value hashes apart.
    The seed may be a column, for replicated runs in one plan."""
    if fast:
        return F.shiftrightunsigned(F.xxhash64(c, F.lit(purpose), seed if isinstance(seed, Column) else F.lit(seed)), 64 - BITS)
    return _hex(_digest(c, purpose, seed), 9, 15)


def bucket_hash(c: Column, seed: int | Column, fast: bool = False) -> Column:
    """What ``bucket`` reduces by the number of registers: the same for any number."""
    if fast:
        return F.xxhash64(c, F.lit("bucket"), seed if isinstance(seed, Column) else F.lit(seed))
    return _hex(_digest(c, "v", seed), 1, 8)


def bucket(c: Column, m: int | Column, seed: int | Column, fast: bool = False) -> Column:
    """One of ``m`` registers, from bits that the rank does not use."""
    return bucket_of(bucket_hash(c, seed, fast), m)


def bucket_of(h: Column, m: int | Column) -> Column:
    return F.pmod(h, m if isinstance(m, Column) else F.lit(m)).cast("int")


def below(c: Column, purpose: str, seed: int | Column, rate: float) -> Column:
    """``hash60(c, purpose, seed) < threshold(rate)``, by the digits themselves: no number is parsed."""
    if threshold(rate) == SPAN:
        return F.lit(True)
    return F.substring(_digest(c, purpose, seed), 9, 15) < f"{threshold(rate):015x}"


def rank(c: Column, seed: int | Column, fast: bool = False) -> Column:
    """Leading zeros of the 60-bit value hash, plus one (61 for zero)."""
    h = hash60(c, "v", seed, fast)
    return F.when(h == 0, F.lit(BITS + 1)).otherwise(BITS + 1 - F.length(F.bin(h))).cast("int")


def threshold(rate: float) -> int:
    """Hashes below it are kept at ``rate``."""
    if not 0 < rate <= 1:
        raise ValueError("a rate is in (0, 1], the probability to keep an occurrence")
    return SPAN if rate == 1 else int(math.floor(rate * SPAN))
