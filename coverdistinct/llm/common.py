"""Shared helpers: table paths, durable intermediate tables, ASCII lower case."""

from __future__ import annotations

import atexit
import functools
import shutil
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

UPPER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
LOWER = UPPER.lower()
#: Six ASCII white-space characters: the separators of the word contract.
SPACE = " \t\n\x0b\x0c\r"
#: Characters of scripts written without spaces (Thai, Lao, Myanmar, Khmer, kana, Han), for a class of ``re``.
UNSPACED = "\u0e00-\u0eff\u1000-\u109f\u1780-\u17ff\u3005-\u3007\u3040-\u30ff\u31f0-\u31ff\u3400-\u4dbf\u4e00-\u9fff\uf900-\ufaff\uff66-\uff9f\U00020000-\U0003ffff"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


@functools.cache
def _own_dir() -> str:
    """A folder for sessions without a shared one (tests on one machine); gone at exit."""
    place = f"/tmp/checkpoints/coverdistinct-{uuid.uuid4().hex}"
    atexit.register(shutil.rmtree, place, ignore_errors=True)
    return f"file://{place}"


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors share, from the session; one of our own only where it is
    unset and driver and executors are one process.  A cluster without one is refused: tables
    in a machine's own folder would be lost."""
    place = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir", None)
    if not place and not one_process(spark.sparkContext.master):
        raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
    return place or _own_dir()


def one_process(master: str) -> bool:
    return master == "local" or master.startswith("local[")


def settle(df: DataFrame, name: str) -> DataFrame:
    """Write ``df`` as a table in the shared folder and read it back: lineage ends
    there, and a lost executor costs a reread, not a recomputation.  The shuffle
    files of the write are given back as soon as the table stands."""
    spark = df.sparkSession
    path = f"{shared_dir(spark).rstrip('/')}/{name}-{uuid.uuid4().hex}"
    key = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
    before = spark.conf.get(key, "false")
    spark.conf.set(key, "true")
    try:
        df.write.parquet(path)
    finally:
        spark.conf.set(key, before)
    return spark.read.schema(df.schema).parquet(path)


def shuffle_partitions(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions", "200"))


def ascii_lower(col: Column) -> Column:
    """Lower-case A-Z alone."""
    return F.translate(col, UPPER, LOWER)


def words(col: Column) -> Column:
    """Maximal runs of characters other than the six ASCII white-space ones; a
    null or blank text gives an empty array."""
    plain = F.trim(F.translate(F.coalesce(col, F.lit("")), SPACE, " " * len(SPACE)))
    return F.when(plain == "", F.array().cast("array<string>")).otherwise(F.split(plain, " +"))


def unit(*cols: Column) -> Column:
    """A hash draw in (0, 1), 53 bits, never 0 or 1."""
    return (F.shiftrightunsigned(F.xxhash64(*cols), 11).cast("double") + 0.5) / F.lit(float(1 << 53))
