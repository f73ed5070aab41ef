"""A corpus from language identification to shards, each stage on all its predecessor kept.

``STAGES`` lists the stages in order; each takes ``(spark, docs, sf_dir)`` and returns a
DataFrame, which is written and reread as the next stage's ``docs``.  All but the last
return the columns of ``documents``.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from coverdistinct.llm import decontam, langid, mixing, neardup, sharding
from coverdistinct.llm.common import settle, table

#: Share of the tokens that mixing keeps.
MIX_SHARE = 0.9


def language_id(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops documents without a letter, and those in no language that the labels teach."""
    return langid.keep_identified(docs)


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps the first document of each group (five-word shingles, similarity 0.8)."""
    return neardup.keep_one_of_each(docs)


def decontamination(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops documents that cover a test item."""
    return decontam.keep_uncontaminated(docs, table(spark, sf_dir, "benchmark"))


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps what the token budgets select in one epoch at most."""
    return mixing.keep_mixed(docs, MIX_SHARE)


def shard(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Places the documents: doc_id, size, text_crc32, law, shard, slot, grown_shard."""
    return sharding.shard_documents(docs)


STAGES = [
    ("language id", language_id),
    ("near-duplicates", near_dedup),
    ("decontamination", decontamination),
    ("mixing", mix_sources),
    ("sharding", shard),
]

ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = settle(stage(spark, docs, sf_dir), f"stage-{name.replace(' ', '-')}")
    return STAGES[-1][1](spark, docs, sf_dir)
