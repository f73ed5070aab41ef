"""Mixing sources to target weights by hierarchical budgeting.

The sources form a tree: domain, language, source.  A token budget flows down by
weight.  No node may get more than its leaves hold in the allowed epochs; what a node
cannot take is shared among its siblings by weight, and leaves its parent only when
the parent is full.  Each level is one pass of window functions: children in the
order in which they fill up, running capacity before and weight after them.

A leaf's budget is whole epochs plus a token-prefix of one more, in a seeded order of
that epoch.  The prefix needs no sorted leaf: a first pass sums tokens by the order's
leading digits, a second by the next digits within the cell where the budget ends,
and only the places of the last cell are ordered; rows that share a place (a repeated
or null id with equal tokens) are one counted place, of which some copies fit.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import settle, words

NONE = "(none)"
#: Production weights of the nodes by name; a node not listed has weight 1.  Fixed values.
WEIGHTS = {
    "domain": {"web": 5.0, "books": 3.0, "forum": 2.0},
    "language": {"en": 5.0, "de": 2.0, "fr": 2.0, "es": 1.0},
    "source": {},
}
SHARE, EPOCHS, SEED = 0.6, 3, 8
LEVELS = ["domain", "language", "source"]
DIGITS = 3  # hexadecimal digits of the order per cell
#: Leaves up to this number are broadcast to the documents.
MAX_BROADCAST_LEAVES = 100_000


def domain(source: Column) -> Column:
    """The domain of a source, by its number: 0-9 web, 10-14 books, 15-19 forum."""
    n = F.try_to_number(F.regexp_extract(source, r"^src(\d{1,9})$", 1), F.lit("999999999")).cast("int")
    return F.when(n < 10, "web").when(n < 15, "books").when(n < 20, "forum").otherwise("other")


def _weight(level: str, weights: dict) -> Column:
    out = F.lit(1.0)
    for name, w in weights.get(level, {}).items():
        out = F.when(F.col(level) == name, F.lit(float(w))).otherwise(out)
    return out


def fill(children: DataFrame, parent: list[str], level: str, weights: dict) -> DataFrame:
    """``budget`` of each child from its parent's ``given``, in proportion to weight up to ``room``."""
    c = children.withColumn("weight", _weight(level, weights)).withColumn("full_at", F.col("room") / F.col("weight"))
    w = W.partitionBy(*parent).orderBy("full_at", level) if parent else W.partitionBy(F.lit(0)).orderBy("full_at", level)
    c = c.withColumn("before", F.coalesce(F.sum("room").over(w.rowsBetween(W.unboundedPreceding, -1)), F.lit(0.0)))
    c = c.withColumn("after", F.sum("weight").over(w.rowsBetween(W.currentRow, W.unboundedFollowing)))
    c = c.withColumn("is_full", F.col("before") + F.col("full_at") * F.col("after") <= F.col("given"))
    every = W.partitionBy(*parent) if parent else W.partitionBy(F.lit(0))
    taken = F.coalesce(F.sum(F.when(F.col("is_full"), F.col("room"))).over(every), F.lit(0.0))
    heavy = F.sum(F.when(~F.col("is_full"), F.col("weight"))).over(every)
    budget = F.when(F.col("is_full"), F.col("room")).otherwise(F.floor((F.col("given") - taken) * F.col("weight") / heavy).cast("double"))
    return c.withColumn("budget", F.greatest(budget, F.lit(0.0))).drop("weight", "full_at", "before", "after", "is_full")


def budgets(leaves: DataFrame, share: float, epochs: int, weights: dict = WEIGHTS) -> DataFrame:
    """Per leaf (domain, language, source, tokens): ``budget`` and of it ``epochs`` whole ones and ``rest``."""
    room = (F.col("tokens") * epochs).cast("double")
    rows = leaves.withColumn("room", room)
    total = leaves.agg(F.floor(F.coalesce(F.sum("tokens"), F.lit(0)) * F.lit(share)).cast("double").alias("given"))
    top = fill(rows.groupBy("domain").agg(F.sum("room").alias("room")).crossJoin(F.broadcast(total)), [], "domain", weights)
    middle = rows.groupBy("domain", "language").agg(F.sum("room").alias("room")).join(top.select("domain", F.col("budget").alias("given")), "domain")
    middle = fill(middle, ["domain"], "language", weights)
    low = rows.join(middle.select("domain", "language", F.col("budget").alias("given")), ["domain", "language"])
    low = fill(low, ["domain", "language"], "source", weights)
    whole = F.when(F.col("tokens") > 0, F.floor(F.col("budget") / F.greatest("tokens", F.lit(1)))).otherwise(F.lit(0)).cast("long")
    return low.withColumn("epochs", whole).select(*LEVELS, "tokens", F.col("budget").cast("long").alias("budget"), "epochs",
                                                  (F.col("budget").cast("long") - F.col("epochs") * F.col("tokens")).alias("rest"))


def _sized(docs: DataFrame) -> DataFrame:
    source = F.coalesce(F.col("source"), F.lit(NONE))
    return docs.select("doc_id", domain(source).alias("domain"), F.coalesce(F.col("lang"), F.lit(NONE)).alias("language"),
                       source.alias("source"), F.size(words(F.col("text"))).cast("long").alias("n_tokens"))


def _order(seed: int) -> Column:
    """The place of a row in the epoch that its leaf takes a part of."""
    return F.md5(F.concat_ws("|", F.coalesce(F.col("doc_id").cast("string"), F.lit(NONE)), F.col("n_tokens"), F.col("epochs"), F.lit(str(seed))))


def _last_cell(rows: DataFrame, cell: Column) -> DataFrame:
    """Of each leaf the first cell that does not fit in ``rest``, and the tokens before it."""
    sums = rows.withColumn("cell", cell).groupBy(*LEVELS, "rest", "cell").agg(F.sum("n_tokens").alias("in_cell"))
    upto = F.sum("in_cell").over(W.partitionBy(*LEVELS).orderBy("cell"))
    over = sums.withColumn("upto", upto).where(F.col("upto") > F.col("rest"))
    return over.groupBy(*LEVELS).agg(F.min(F.struct("cell", (F.col("upto") - F.col("in_cell")).alias("before"))).alias("x")).select(*LEVELS, "x.cell", "x.before")


def mix(docs: DataFrame, share: float = SHARE, epochs: int = EPOCHS, weights: dict = WEIGHTS, seed: int = SEED) -> DataFrame:
    """The selected copies of ``docs`` (doc_id, text, lang, source): doc_id, domain, language,
    source, n_tokens, epoch (from 0), one row per copy.

    The budget is ``share`` of all tokens, and a leaf gives at most ``epochs`` times its
    own.  Null languages and sources are a node of their own; texts without tokens
    cost nothing and go with whole epochs or the prefix they fall in; repeated rows are selected alike
    or, at the very end of a prefix, as many of them as fit."""
    sized = settle(_sized(docs), "sized")
    leaves = sized.groupBy(*LEVELS).agg(F.sum("n_tokens").alias("tokens"))
    plan = settle(budgets(leaves, share, epochs, weights), "budgets")
    small = F.broadcast if plan.count() <= MAX_BROADCAST_LEAVES else (lambda x: x)
    rows = sized.join(small(plan.drop("budget", "tokens")), LEVELS).withColumn("place", _order(seed))
    first, second = F.substring("place", 1, DIGITS), F.substring("place", DIGITS + 1, DIGITS)
    end1 = settle(_last_cell(rows, first), "cells").withColumnsRenamed({"cell": "cell1", "before": "before1"})
    near = rows.join(small(end1), LEVELS, "left")
    inside = near.where(first == F.col("cell1")).withColumn("rest", F.col("rest") - F.col("before1"))
    end2 = settle(_last_cell(inside, second), "cells").withColumnsRenamed({"cell": "cell2", "before": "before2"})
    near = near.join(small(end2), LEVELS, "left")
    # the prefix: leading digits below the first cell, or within it below the second, or early in the second
    last = (first == F.col("cell1")) & (second == F.col("cell2"))
    columns = ["doc_id", *LEVELS, "n_tokens"]
    tail = near.where(last).groupBy(*columns, "epochs", "rest", "before1", "before2", "place").agg(F.count(F.lit(1)).alias("n"))
    tail = tail.withColumn("left", F.col("rest") - F.col("before1") - F.col("before2") - F.coalesce(F.sum(F.col("n_tokens") * F.col("n")).over(
        W.partitionBy(*LEVELS).orderBy("place", "doc_id", "n_tokens").rowsBetween(W.unboundedPreceding, -1)), F.lit(0)))
    fit = F.when((F.col("rest") <= 0) | (F.col("left") < 0), 0).when(F.col("n_tokens") == 0, F.col("n")).otherwise(F.least("n", F.floor(F.col("left") / F.greatest("n_tokens", F.lit(1)))))
    tail = tail.withColumn("fit", fit.cast("long"))
    more = F.col("cell1").isNull() | (first < F.col("cell1")) | ((first == F.col("cell1")) & (F.col("cell2").isNull() | (second < F.col("cell2"))))
    more = more & (F.col("rest") > 0)
    body = near.where(~F.coalesce(last, F.lit(False))).select(*columns, (F.col("epochs") + F.coalesce(more, F.lit(False)).cast("long")).alias("copies"))
    each = F.array(F.struct((F.col("epochs") + 1).alias("copies"), F.col("fit").alias("n")), F.struct(F.col("epochs").alias("copies"), (F.col("n") - F.col("fit")).alias("n")))
    tail = tail.select(*columns, F.explode(F.filter(each, lambda x: (x["n"] > 0) & (x["copies"] > 0))).alias("x"))
    tail = tail.select(*columns, "x.copies", F.explode(F.sequence(F.lit(1).cast("long"), "x.n"))).drop("col")
    both = body.union(tail).where("copies > 0")
    return both.select(*columns, F.explode(F.sequence(F.lit(0), (F.col("copies") - 1).cast("int"))).alias("epoch"))


def keep_mixed(docs: DataFrame, share: float, weights: dict = WEIGHTS, seed: int = SEED) -> DataFrame:
    """The rows of ``docs`` that one epoch at most selects, with their own columns."""
    chosen = mix(docs, share, 1, weights, seed).select(F.col("doc_id").alias("__id")).distinct()
    return docs.join(chosen, docs["doc_id"].eqNullSafe(chosen["__id"]), "left_semi")
