"""Element streams: a column or key of a table, with an identity for each occurrence.

A stream is a DataFrame ``(group columns.., element, occ)``.  The element is what is
counted; ``occ`` names the occurrence, and is what sampling hashes, never the
element.  Only the columns that the two need are read.
"""

from __future__ import annotations

import os
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..functions.hashing import encode


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def element_stream(df: DataFrame, element: list[Column], occ: list[Column], group_by: dict[str, Column] | None = None, null_policy: str = "skip", native: bool = False) -> DataFrame:
    """``null_policy``: 'skip' leaves null elements out, as SQL's distinct count does;
    'as_value' counts them as one value.  A composite key is null when all its parts are.
    ``native`` keeps a single element in its own type and makes the occurrence a 64-bit
    hash of its columns: no strings are built, for the fast hashes."""
    if null_policy not in ("skip", "as_value"):
        raise ValueError(null_policy)
    null = element[0].isNull()
    for c in element[1:]:
        null = null & c.isNull()
    rows = df.where(~null) if null_policy == "skip" else df
    if native and null_policy == "skip":
        value = element[0] if len(element) == 1 else encode(*element)
        return rows.select(*[c.alias(k) for k, c in (group_by or {}).items()], value.alias("element"), F.xxhash64(*occ).alias("occ"))
    value = encode(*element)
    if null_policy == "as_value":
        value = F.coalesce(value, F.lit("~null"))
    return rows.select(*[c.alias(k) for k, c in (group_by or {}).items()], value.alias("element"), encode(*occ).alias("occ"))


@dataclass(frozen=True)
class Stream:
    """A named stream of the test tables, with the same definition in SQL."""

    name: str
    table: str
    element: tuple[str, ...]
    occ: tuple[str, ...]
    tokens: bool = False

    def load(self, spark: SparkSession, sf_dir: str, group_by: dict[str, str] | None = None, null_policy: str = "skip", native: bool = False) -> DataFrame:
        df = table(spark, sf_dir, self.table)
        if self.tokens:
            df = tokens(df)
        groups = {k: F.expr(v) for k, v in (group_by or {}).items()}
        return element_stream(df, [F.expr(e) for e in self.element], [F.expr(o) for o in self.occ], groups, null_policy, native)


def tokens(df: DataFrame, text: str = "text") -> DataFrame:
    """Lower-case runs of letters, with their place in the split text."""
    parts = F.split(F.lower(F.col(text)), r"[^\p{L}]+")
    return df.select("*", F.posexplode(parts).alias("pos", "token")).where("token <> ''").drop(text)


_LINE = ("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "cast(l_quantity as int)", "cast(l_shipdate as date)")
STREAMS = {s.name: s for s in (
    Stream("part_key", "lineitem", ("l_partkey",), _LINE),
    Stream("order_key", "lineitem", ("l_orderkey",), _LINE),
    Stream("supp_key", "lineitem", ("l_suppkey",), _LINE),
    Stream("ship_date", "lineitem", ("cast(l_shipdate as date)",), _LINE),
    Stream("part_supp", "lineitem", ("l_partkey", "l_suppkey"), _LINE),
    Stream("cust_key", "orders", ("o_custkey",), ("o_orderkey",)),
    Stream("user", "events", ("user_id",), ("event_id",)),
    Stream("flow", "events", ("user_id", "event_type"), ("event_id",)),
    Stream("value", "events", ("cast(round(value * 100) as bigint)",), ("event_id",)),
    Stream("props", "events", ("props",), ("event_id",)),
    Stream("event_type", "events", ("event_type",), ("event_id",)),
    Stream("host", "pages", ("host",), ("page_id",)),
    Stream("doc_text", "documents", ("text",), ("doc_id",)),
    Stream("doc_source", "documents", ("source",), ("doc_id",)),
    Stream("word", "documents", ("token",), ("doc_id", "pos"), tokens=True),
    Stream("talk_word", "conversations", ("token",), ("conv_id", "turn", "pos"), tokens=True),
)}


def load(spark: SparkSession, sf_dir: str, name: str, group_by: dict[str, str] | None = None, null_policy: str = "skip", native: bool = False) -> DataFrame:
    s = STREAMS[name]
    if name == "host":
        df = table(spark, sf_dir, "pages").select("page_id", F.regexp_extract("url", "^[a-z]+://([^/?#]+)", 1).alias("host"))
        return element_stream(df, [F.col("host")], [F.col("page_id")], {k: F.expr(v) for k, v in (group_by or {}).items()}, null_policy)
    return s.load(spark, sf_dir, group_by, null_policy, native)


#: Column kinds that can be elements; a map is hashed as its sorted entries.
def hashable(df: DataFrame, name: str) -> Column:
    kind = df.schema[name].dataType
    if isinstance(kind, T.MapType):
        return F.to_json(F.array_sort(F.map_entries(name)))
    if isinstance(kind, (T.ArrayType, T.StructType)):
        return F.to_json(name)
    if isinstance(kind, T.BinaryType):
        return F.hex(name)
    if isinstance(kind, (T.FloatType, T.DoubleType)):
        from ..functions.hashing import normal_double
        return normal_double(F.col(name).cast("double"))
    return F.col(name)


FORMATS = ("parquet", "orc", "json", "csv", "text")


def read(spark: SparkSession, path: str, fmt: str, schema: T.StructType | None = None) -> DataFrame:
    """A table in any of the supported formats; a given schema is not inferred again."""
    if fmt not in FORMATS:
        raise ValueError(fmt)
    r = spark.read.schema(schema) if schema is not None and fmt != "text" else spark.read
    return r.option("header", True).csv(path) if fmt == "csv" else r.format(fmt).load(path)


def write(df: DataFrame, path: str, fmt: str, partition_by: list[str] | None = None) -> None:
    if fmt not in FORMATS:
        raise ValueError(fmt)
    w = df.write.partitionBy(*(partition_by or []))
    w.option("header", True).csv(path) if fmt == "csv" else w.format(fmt).save(path)


def block_sample(spark: SparkSession, path: str, rate: float, seed: int = 42) -> DataFrame:
    """A sample of whole files: reads ``rate`` of the bytes, but rows of a file go
    together, so the independence of the analysis does not hold (``design`` = cluster).
    The files are listed by Spark, so any store that it reads will do."""
    files = sorted(spark.read.parquet(path).inputFiles())
    chosen = spark.createDataFrame([(f, os.path.basename(f)) for f in files], "path string, name string")
    from ..functions.hashing import hash60, threshold
    keep = [r["path"] for r in chosen.where(hash60(F.col("name"), "block", seed) < threshold(rate)).collect()] if rate < 1 else files
    if not keep:
        return spark.read.parquet(path).where("false").withColumn("design", F.lit("cluster"))
    return spark.read.parquet(*keep).withColumn("design", F.lit("cluster"))
