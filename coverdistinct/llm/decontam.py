"""Benchmark decontamination by greedy string tiling.

Seeds: runs of ``LEAST`` tokens that a document shares with a test item.  A document
with a seed is tiled against the item: of the matches between unmarked tokens the
longest are marked again and again, found by running Karp-Rabin hashes, until none of
``LEAST`` tokens is left.  An item too short to hold a seed is found where a text is
that item and nothing else.  The share of the item's tokens under tiles does not depend on
the order of the tiles, so passages that were cut up and reordered are caught too.

The seeds of the test items are broadcast in blocks of bounded size; a larger
benchmark takes more blocks, each a pass over the documents, whose hits are merged
by a key of the row.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass
from functools import reduce

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import UNSPACED, settle

LEAST, COVERAGE = 5, 0.5
#: Tokens of test items that one broadcast may hold.
BLOCK_TOKENS = 1_000_000
_WORD, _NO_SPACES = re.compile(r"\w+"), re.compile(f"[{UNSPACED}]")
_WORD_OR_SIGN = re.compile(f"[^\\W{UNSPACED}]+|(?=\\w)[{UNSPACED}]")
_BASE, _MOD = 1_000_003, (1 << 61) - 1


def tokens(text: str | None) -> list[str]:
    """Lower-cased words; in scripts without spaces each character is one."""
    text = (text or "").lower()
    return (_WORD if text.isascii() or not _NO_SPACES.search(text) else _WORD_OR_SIGN).findall(text)


def _running(ids: list[int], size: int, free: list[bool]) -> Iterator[tuple[int, int]]:
    """``(hash, start)`` of all windows of ``size`` unmarked tokens, each hash from the last."""
    top = pow(_BASE, size - 1, _MOD)
    h = run = 0
    for i, x in enumerate(ids):
        if not free[i]:
            h = run = 0
            continue
        if run >= size:
            h = (h - ids[i - size] * top) % _MOD
        h = (h * _BASE + x) % _MOD
        run += 1
        if run >= size:
            yield h, i - size + 1


def tiles(doc: list[str], item: list[str], least: int = LEAST) -> list[tuple[int, int, int]]:
    """Greedy tiles ``(start in doc, start in item, length)``, longest first; ties go to
    the earlier place in the item, then in the document."""
    names: dict[str, int] = {}
    b = [names.setdefault(t, len(names) + 1) for t in item]
    a = [names.get(t, 0) for t in doc]
    free_a, free_b = [x != 0 for x in a], [True] * len(b)
    out = []
    while True:
        starts: dict[int, list[int]] = {}
        for h, j in _running(b, least, free_b):
            starts.setdefault(h, []).append(j)
        best: list[tuple[int, int, int]] = []
        longest = least
        for h, i in _running(a, least, free_a):
            for j in starts.get(h, ()):
                if i and j and free_a[i - 1] and free_b[j - 1] and a[i - 1] == b[j - 1]:
                    continue  # part of a match that starts earlier
                n = 0
                while i + n < len(a) and j + n < len(b) and free_a[i + n] and free_b[j + n] and a[i + n] == b[j + n]:
                    n += 1
                if n > longest:
                    best, longest = [], n
                if n == longest:
                    best.append((j, i, n))
        if not best:
            return out
        for j, i, n in sorted(best):
            if all(free_a[i: i + n]) and all(free_b[j: j + n]):
                out.append((i, j, n))
                free_a[i: i + n] = [False] * n
                free_b[j: j + n] = [False] * n


@dataclass
class Benchmark:
    items: list[tuple[int | None, list[str]]]
    pairs: frozenset
    seeds: dict[tuple[str, ...], tuple[int, ...]]  # places in items
    short: dict[tuple[str, ...], list[int | None]]  # items without a seed

    @classmethod
    def build(cls, rows: list[tuple[int | None, str]], least: int = LEAST) -> Benchmark:
        """Each row is an item, whatever its id; one without tokens is none."""
        items, short = [], {}
        for i, text in dict.fromkeys(rows):
            t = tokens(text)
            if len(t) >= least:
                items.append((i, t))
            elif t and i not in short.setdefault(tuple(t), []):
                short[tuple(t)].append(i)
        seeds: dict[tuple[str, ...], set[int]] = {}
        for at, (_, t) in enumerate(items):
            for k in range(len(t) - least + 1):
                seeds.setdefault(tuple(t[k: k + least]), set()).add(at)
        return cls(items, frozenset(p for _, t in items for p in zip(t, t[1:])), {k: tuple(sorted(v)) for k, v in seeds.items()}, short)

    def hits(self, text: str | None, coverage: float = COVERAGE, least: int = LEAST) -> list[tuple[int | None, float, int, int]]:
        """``(item, share covered, tiles, tokens)`` of the items covered enough, best
        first, null ids last among equals; each id once, with its best row."""
        t = tokens(text)
        if len(t) < least:
            same = self.short.get(tuple(t), ())
            return [(i, 1.0, 1, len(t)) for i in sorted(same, key=lambda i: (i is None, i or 0))]
        # a seed has least - 1 pairs, counted by place, as they may be equal
        if sum(map(self.pairs.__contains__, zip(t, t[1:]))) < least - 1:
            return []
        seen = self.seeds.keys() & set(zip(*[t[k:] for k in range(least)]))
        out = []
        for at in {at for s in seen for at in self.seeds[s]}:
            i, item = self.items[at]
            found = tiles(t, item, least)
            n = sum(x[2] for x in found)
            if n >= coverage * len(item):
                out.append((i, n / len(item), len(found), n))
        best: dict[int | None, tuple[int | None, float, int, int]] = {}
        for x in sorted(out, key=lambda x: (-x[1], x[0] is None, x[0] or 0, x[2], x[3])):
            best.setdefault(x[0], x)
        return list(best.values())


_HIT = pa.struct([("item_id", pa.int64()), ("coverage", pa.float64()), ("n_tiles", pa.int64()), ("n_tokens", pa.int64())])
_SCHEMA = "key long, hits array<struct<item_id:long,coverage:double,n_tiles:long,n_tokens:long>>"


def _n_blocks(benchmark: DataFrame) -> int:
    size = benchmark.agg(F.coalesce(F.sum(F.octet_length("text")), F.lit(0)).alias("n")).first()["n"] // 2
    return int(size // BLOCK_TOKENS) + 1


def _blocks(benchmark: DataFrame, n: int) -> Iterator[Benchmark]:
    """``n`` indices of at most about BLOCK_TOKENS tokens each."""
    for k in range(n):
        part = benchmark.where(F.pmod(F.xxhash64("item_id", "text"), F.lit(n)) == k).select("item_id", "text")
        yield Benchmark.build([(r["item_id"], r["text"]) for r in part.collect()])


def decontaminate(docs: DataFrame, benchmark: DataFrame, coverage: float = COVERAGE) -> DataFrame:
    """Per row of ``docs`` (doc_id, text): doc_id, kept, and of the best covered item
    item_id, coverage, n_tiles and n_tokens (null or 0 if kept), items (all covered enough).

    Null and empty texts are kept; whole texts are tiled; without test items all is kept.
    Rows of ``benchmark`` with a null or repeated item_id are items of their own; those
    under LEAST tokens are found where they are the whole text."""
    spark, rows = docs.sparkSession, docs.select("doc_id", "text")

    def found(index: Benchmark, rows: DataFrame, key: str) -> DataFrame:
        shared = spark.sparkContext.broadcast(index)

        def tile(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                hits = [[dict(zip(("item_id", "coverage", "n_tiles", "n_tokens"), h)) for h in shared.value.hits(t, coverage)] for t in batch.column("text").to_pylist()]
                yield pa.RecordBatch.from_arrays([batch.column(key), pa.array(hits, pa.list_(_HIT))], ["key", "hits"])

        return rows.select(key, "text").mapInArrow(tile, _SCHEMA)

    n = _n_blocks(benchmark)
    if n == 1:
        hits = found(next(_blocks(benchmark, n)), rows, "doc_id").withColumnRenamed("key", "doc_id")
    else:
        # a row's own key, so that rows that repeat an id stay rows of their own; it is fixed by the table
        rows = settle(rows.withColumn("row", F.monotonically_increasing_id()), "documents")
        parts = [found(index, rows, "row").where(F.size("hits") > 0) for index in _blocks(benchmark, n)]
        merged = reduce(DataFrame.union, parts).groupBy("key").agg(F.flatten(F.collect_list("hits")).alias("hits"))
        hits = rows.select("doc_id", F.col("row").alias("key")).join(merged.hint("merge"), "key", "left")
    # best first, as in one block; an id whose rows are in several blocks is listed once
    order = F.transform(F.coalesce("hits", F.array()), lambda h: F.struct((-h["coverage"]).alias("c"), h["item_id"].isNull().alias("u"), h["item_id"].alias("item_id"), h["n_tiles"].alias("n_tiles"), h["n_tokens"].alias("n_tokens")))
    best = F.get("hits", F.lit(0))
    return hits.select("doc_id", F.array_sort(order).alias("hits")).select(
        "doc_id", (F.size("hits") == 0).alias("kept"), best["item_id"].alias("item_id"), F.coalesce(-best["c"], F.lit(0.0)).alias("coverage"),
        *(F.coalesce(best[c], F.lit(0)).cast("long").alias(c) for c in ("n_tiles", "n_tokens")), F.array_distinct(F.transform("hits", lambda h: h["item_id"])).alias("items"))


def keep_uncontaminated(docs: DataFrame, benchmark: DataFrame, coverage: float = COVERAGE) -> DataFrame:
    """``docs`` without the rows that cover a test item."""
    out, columns = docs, docs.columns
    for index in _blocks(benchmark, _n_blocks(benchmark)):
        shared = docs.sparkSession.sparkContext.broadcast(index)

        @F.udf("boolean", useArrow=True)
        def clean(text: str, shared=shared) -> bool:
            return not shared.value.hits(text, coverage)

        out = out.where(clean("text"))
    return out.select(*columns)
