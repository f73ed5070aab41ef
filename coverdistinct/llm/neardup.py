"""Near-duplicate groups from bottom-k sketches of one hash function.

1. A document's set holds the 64-bit hashes of its distinct word shingles, its
   sketch the ``K`` smallest.  Documents with equal sets become one class, and
   only its first document goes on.
2. Inverted lists of the retained values generate candidates.  A linked pair shares
   at least ``least_shared(n)`` retained values (but for odds of about 1e-10), so each
   document enters only the lists of its rarest ``size - least_shared + 1`` values:
   a passage that a third of all documents share fills no list unless it is
   most of a document.
3. Of a short list all pairs are candidates.  The members of long lists are listed
   again by their full sets, where the least number of shared shingles is certain and
   the lists hold true relatives alone.  A list that is still long (a large group
   of near copies) gets a reference set, what most of some of its members hold, and each
   member the *difference* of its set from it.  By the triangle inequality all members
   with a small difference are linked to the one with the smallest; of the other pairs one
   member is far, and then the two can be linked only if they share a known part of their
   differences.  Differences are small and rare, so lists of their rarest shingles give few
   candidates and miss none.  Where one of these lists has many far members (a family
   within the family), it gets a reference of its own, and so on: the work grows with the
   members, not with their pairs.  No list is capped.
4. The union sketch of a pair estimates its similarity and drops hopeless pairs;
   the rest is confirmed on full sets, which only documents of the rest and of long lists get.  Components of the confirmed links follow by
   minimum labels and pointer jumping.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from .common import ascii_lower, settle, unit, words

K = 64
#: A list up to this length is compared in full at once; a longer one by differences from a reference set.
SHORT = 48
#: Members, about so many by their draws, whose majority makes a reference (any set would be right, a good one makes small differences); turns in
#: which lists with a common member share one; turns after which the lists that are left are compared in full.
VOTERS, MERGED_TURNS, TURNS = 31, 3, 12
#: A list of differences with up to so many far members is compared, these with all: some numbers a pair, against
#: hundreds of shingles a member for a reference of its own.
FARS = 128
#: Values before its own that a list remembers of each member, so that a pair comes from one list alone.
REMEMBERED = 64
#: What moves texts, sketch values or full sets goes in up to so many rounds, one more for each so many rows: the disk holds the shuffle of one at a time.
ROUNDS, ROUND_ROWS = 4, 1 << 16


def with_sets(docs: DataFrame, n: int) -> DataFrame:
    """``(doc_id, s)``: the sorted distinct hashes of the ``n``-word shingles; of fewer
    words the whole sequence as one; of none an empty array."""
    chain = lambda x, i: F.xxhash64(x, *[F.get("w", i + k) for k in range(1, n)])
    shingles = F.slice(F.transform("w", chain), 1, F.greatest(F.size("w") - (n - 1), F.lit(1)))
    return (docs.select("doc_id", words(ascii_lower(F.col("text"))).alias("w"))
                .select("doc_id", F.sort_array(F.array_distinct(shingles)).alias("s")))


def least_shared(n: Column, similarity: float) -> Column:
    """Retained values that a document of ``n`` shingles shares with any linked one."""
    whole = F.ceil(similarity * n - 1e-9)
    spread = 7.5 * (K * similarity * (1 - similarity)) ** 0.5
    large = F.floor(similarity * K - spread * F.sqrt(1 - similarity * K / n))
    middle = F.floor((similarity - 0.23) * F.least(n, F.lit(K)))
    return F.greatest(F.when(n <= similarity * K, whole).when(n < 110, middle).otherwise(large), F.lit(1)).cast("int")


def _sketch_passes(a: Column, b: Column, na: Column, nb: Column, similarity: float) -> Column:
    """The union sketch: of the K smallest values of both, how many are in both."""
    union = F.slice(F.sort_array(F.array_union(a, b)), 1, K)
    return F.size(F.array_intersect(F.array_intersect(a, b), union)) >= least_shared(F.greatest(na, nb), similarity)


def components(links: DataFrame) -> DataFrame:
    """``(id, component)`` of all ids in ``links`` (a, b): the smallest id reachable."""
    both = settle(links.select("a", "b").union(links.select("b", "a")).distinct(), "links")
    labels = settle(both.groupBy("a").agg(F.least(F.col("a"), F.min("b")).alias("component")).withColumnRenamed("a", "id"), "labels")
    while True:
        near = (both.join(labels.hint("merge"), both["b"] == labels["id"]).groupBy("a").agg(F.min("component").alias("m")))
        hooked = labels.join(near.hint("merge"), labels["id"] == near["a"]).select("id", F.least("component", "m").alias("c"), F.col("component").alias("was"))
        up = labels.select(F.col("id").alias("c"), F.col("component").alias("top"))
        new = settle(hooked.join(up.hint("merge"), "c").select("id", F.least("c", "top").alias("component"), "was"), "labels")
        if new.where("component <> was").isEmpty():
            return new.select("id", "component")
        labels = new.select("id", "component")


def _ranked(hits: DataFrame, owner: list[str]) -> DataFrame:
    """Adds ``rank``, the place of a value among all ``size`` values of its owner from the
    rarest on; values that no other owner has are not in ``hits`` and come first."""
    own = W.partitionBy(*owner)
    place = F.row_number().over(own.orderBy("df", "value"))
    return hits.withColumn("rank", F.col("size") - F.count(F.lit(1)).over(own) + place.cast("long"))


def _at(x: str) -> list[Column]:
    return [F.col(c).alias(f"{c}_{x}") for c in ("size", "rank")]


def _most_shared(x: str, y: str) -> Column:
    """Values that two owners can share if this is the first one: it and what both have
    after it.  Every pair passes at the first value that it shares, so no other list need give it."""
    return 1 + F.least(F.col(f"size_{x}") - F.col(f"rank_{x}"), F.col(f"size_{y}") - F.col(f"rank_{y}"))


def _rounds(rows: int) -> int:
    return min(ROUNDS, 1 + rows // ROUND_ROWS)


def _turn(c: Column, k: int, rounds: int) -> Column:
    """Whether ``c`` belongs to round ``k``."""
    return F.pmod(F.xxhash64(c), F.lit(rounds)) == k if rounds > 1 else F.lit(True)


def _all(parts: list[DataFrame]) -> DataFrame:
    out = parts[0]
    for p in parts[1:]:
        out = out.union(p)
    return out


class NearDuplicates:
    """One run over ``docs`` (doc_id, text); ``percent``: the least similarity, in hundredths."""

    def __init__(self, docs: DataFrame, n: int = 3, percent: int = 85):
        self.docs, self.n, self.percent, self.sets = docs.select("doc_id", "text"), n, percent, None
        self.similarity = percent / 100

    def _confirm(self, pairs: DataFrame) -> DataFrame:
        """Of candidate ``pairs`` (a, b) those that the sketches do not rule out and the full sets confirm."""
        k = self.sketches
        side = lambda t, x, cols: t.select(F.col("id").alias(x), *[F.col(c).alias(f"{c}_{x}") for c in cols])
        hopeful = (pairs.distinct()
                   .join(side(k, "a", ["n", "sketch"]), "a").join(side(k, "b", ["n", "sketch"]), "b")
                   .where(_sketch_passes(F.col("sketch_a"), F.col("sketch_b"), F.col("n_a"), F.col("n_b"), self.similarity))
                   .select("a", "b"))
        hopeful = settle(hopeful, "hopeful")
        if self.sets is None:
            self._build_sets(settle(hopeful.select(F.col("a").alias("id")).union(hopeful.select("b")).union(self.long).distinct(), "compared"))
        return self._measure(hopeful).where(self._linked()).select("a", "b")

    def _alike_sizes(self, x: str, y: str) -> Column:
        return 100 * F.least(x, y) >= self.percent * F.greatest(x, y)

    def _prepare(self) -> None:
        base = with_sets(self.docs, self.n).select(
            "doc_id", F.size("s").cast("long").alias("n"), F.xxhash64("s").alias("u"), F.xxhash64(F.lit("second"), "s").alias("v"), F.slice("s", 1, K).alias("sketch"))
        self.base = settle(base, "sketches")
        self.classes = settle(self.base.where("n > 0").groupBy("n", "u", "v").agg(F.min("doc_id").alias("id")), "classes")
        firsts = self.classes.select("id", "n", "u", "v").where("id IS NOT NULL")
        reps = self.base.select("doc_id", "n", "u", "v", "sketch").join(
            firsts.select(F.col("id").alias("doc_id"), "n", "u", "v").hint("merge"), ["doc_id", "n", "u", "v"], "left_semi")
        reps = settle(reps.dropDuplicates(["doc_id", "n", "u", "v"]).select(F.col("doc_id").alias("id"), "n", "sketch"), "reps")
        self.rounds = _rounds(self.base.count())
        size = F.least("n", F.lit(K))
        hits = _all([self._hits(reps, k) for k in range(self.rounds)])
        lists = _ranked(hits.withColumn("size", size), ["id", "n"]).where(F.col("rank") <= size - least_shared(F.col("n"), self.similarity) + 1)
        lists = lists.select("value", "id", "n", "size", "rank")
        lengths = lists.groupBy("value").agg(F.count(F.lit(1)).alias("m")).where("m > 1")
        self.lists = settle(lists.join(lengths.hint("merge"), "value"), "lists")
        members = settle(self.lists.select("id").distinct(), "members")
        self.sketches = settle(reps.join(members.hint("merge"), "id", "left_semi"), "member-sketches")
        self.long = settle(self.lists.where(F.col("m") > SHORT).select("id").distinct(), "long")

    def _hits(self, reps: DataFrame, k: int) -> DataFrame:
        """Retained values of round ``k`` that several documents have, with how many (``df``)."""
        mine = F.col("sketch") if self.rounds == 1 else F.filter("sketch", lambda v: _turn(v, k, self.rounds))
        entries = reps.select("id", "n", F.explode(mine).alias("value"))
        shared = entries.groupBy("value").agg(F.count(F.lit(1)).alias("df")).where("df > 1")
        hits = entries.join(shared.hint("merge"), "value")
        return settle(hits, "hits") if self.rounds > 1 else hits

    def _build_sets(self, ids: DataFrame) -> None:
        """The full sets of ``ids`` alone; the texts are read once a round, and meet the ids of that round."""
        parts = []
        for k in range(self.rounds):
            mine = _turn(F.col("doc_id"), k, self.rounds)
            texts = self.docs.where(mine).join(ids.withColumnRenamed("id", "doc_id").where(mine).hint("merge"), "doc_id", "left_semi")
            parts.append(settle(with_sets(texts, self.n).withColumnRenamed("doc_id", "id"), "sets"))
        self.sets = _all(parts)

    def _measure(self, pairs: DataFrame) -> DataFrame:
        """``(a, b, n_a, n_b, both)``: shared shingles of distinct settled ``pairs`` on the full sets, a part of all shingles in each round."""
        rounds, parts = _rounds(pairs.count()), []
        for k in range(rounds):
            mine = F.col("s") if rounds == 1 else F.filter("s", lambda v: _turn(v, k, rounds))
            side = lambda x: self.sets.select(F.col("id").alias(x), F.size("s").cast("long").alias(f"n_{x}"), mine.alias(f"s_{x}"))  # noqa: B023, E731
            parts.append(pairs.join(side("a"), "a").join(side("b"), "b")
                         .select("a", "b", "n_a", "n_b", F.size(F.array_intersect("s_a", "s_b")).cast("long").alias("both")))
        if rounds == 1:
            return parts[0]
        return _all([settle(p, "measured") for p in parts]).groupBy("a", "b", "n_a", "n_b").agg(F.sum("both").alias("both"))

    def _linked(self) -> Column:
        return 100 * F.col("both") >= self.percent * (F.col("n_a") + F.col("n_b") - F.col("both"))

    def _short_pairs(self, lists: DataFrame, sketches: bool) -> DataFrame:
        x = lists.where(F.col("m") <= SHORT)
        y = x.select("value", F.col("id").alias("b"), F.col("n").alias("nb"), *_at("b"))
        need = least_shared(F.greatest("na", "nb"), self.similarity) if sketches else F.ceil(self.similarity / (1 + self.similarity) * (F.col("na") + F.col("nb")) - 1e-9)
        return (x.select("value", F.col("id").alias("a"), F.col("n").alias("na"), *_at("a")).join(y, "value")
                 .where((F.col("a") < F.col("b")) & self._alike_sizes("na", "nb") & (_most_shared("a", "b") >= need)).select("a", "b"))

    def _full_lists(self, ids: DataFrame) -> DataFrame:
        """Lists of the rarest shingles of the full sets of ``ids``."""
        entries = self.sets.join(ids, "id", "left_semi").select("id", F.size("s").cast("long").alias("n"), F.explode("s").alias("value"))
        shared = entries.groupBy("value").agg(F.count(F.lit(1)).alias("df")).where("df > 1")
        prefix = F.col("n") - F.ceil(self.similarity * F.col("n") - 1e-9) + 1
        lists = _ranked(entries.join(shared.hint("merge"), "value").withColumn("size", F.col("n")), ["id", "n"]).where(F.col("rank") <= prefix)
        lists = lists.select("value", "id", "n", "size", "rank")
        lengths = lists.groupBy("value").agg(F.count(F.lit(1)).alias("m")).where("m > 1")
        return lists.join(lengths.hint("merge"), "value")

    def _gather(self, lists: DataFrame, merged: bool) -> DataFrame:
        """Clusters of members from long ``lists`` (cluster, value, id, has): a list each, or
        one for all lists of a cluster that have the same most listed member."""
        if merged:
            often = lists.groupBy("cluster", "id").agg(F.count(F.lit(1)).alias("often"))
            top = lists.join(often.hint("merge"), ["cluster", "id"]).groupBy("cluster", "value").agg(F.max(F.struct("often", (-F.col("id")).alias("low"))).alias("p"))
            lists = lists.join(top.select("cluster", "value", F.xxhash64("cluster", F.lit("member"), "p.low").alias("next")).hint("merge"), ["cluster", "value"])
        else:
            lists = lists.withColumn("next", F.xxhash64("cluster", F.lit("value"), "value"))
        return settle(lists.select(F.col("next").alias("cluster"), "id", "value", "has"), "clusters")

    def _references(self, clusters: DataFrame, members: DataFrame) -> DataFrame:
        """``(cluster, ref)``: what most voters hold; it agrees with every list that made the cluster."""
        sizes = members.groupBy("cluster").agg(F.count(F.lit(1)).alias("m"))
        voters = members.join(sizes.hint("merge"), "cluster").where(F.col("m") * unit(F.col("cluster"), F.col("id")) < VOTERS).select("cluster", "id")
        voters = voters.join(voters.groupBy("cluster").agg(F.count(F.lit(1)).alias("voters")).hint("merge"), "cluster")
        votes = voters.join(self.sets, "id").select("cluster", "voters", F.explode("s").alias("value")).groupBy("cluster", "voters", "value").agg(F.count(F.lit(1)).alias("votes"))
        voted = votes.where("2 * votes > voters").select("cluster", "value", F.lit(False).alias("firm"), F.lit(True).alias("has"))
        firm = clusters.select("cluster", "value", F.lit(True).alias("firm"), "has").distinct()
        held = voted.union(firm).groupBy("cluster", "value").agg(F.max(F.struct("firm", "has")).alias("x")).where("x.has")
        return held.groupBy("cluster").agg(F.collect_list("value").alias("ref"))

    def _differences(self, clusters: DataFrame) -> DataFrame:
        """``(cluster, id, n, delta, size, slack)``: for every member what its set has more or
        less than the reference.  Two members with slacks of sum 0 or more are linked: with
        X and Y the differences, (100 + p) (|X| + |Y|) <= (100 - p) (nx + ny)."""
        members = clusters.select("cluster", "id").distinct()
        own = self.sets.select("id", F.size("s").cast("long").alias("n"), "s")
        rows = members.join(own, "id").join(self._references(clusters, members), "cluster", "left").withColumn("ref", F.coalesce("ref", F.array().cast("array<bigint>")))
        mark = lambda a, b, has: F.transform(F.array_except(a, b), lambda v: F.struct(v.alias("value"), F.lit(has).alias("has")))
        rows = rows.select("cluster", "id", "n", F.concat(mark("s", "ref", True), mark("ref", "s", False)).alias("delta")).withColumn("size", F.size("delta").cast("long"))
        return settle(rows.withColumn("slack", (100 - self.percent) * F.col("n") - (100 + self.percent) * F.col("size")), "differences")

    def _related(self, told: DataFrame) -> tuple[DataFrame, DataFrame]:
        """The sure links, from the member with the most slack to all it reaches, and lists
        ``(cluster, value, has, id, ..)`` for pairs with a member out of its reach (a *far* one).

        With slack z, x and y are linked if they share at least -(zx + zy) / 2 (100 + p) of their
        differences.  No partner has more slack than the best, and a far one has less than minus the best."""
        best = told.groupBy("cluster").agg(F.max(F.struct("slack", (-F.col("id")).alias("low"))).alias("best"))
        rows = told.join(best.hint("merge"), "cluster").withColumn("top", F.col("best.slack")).withColumn("far", F.col("slack") + F.col("top") < 0)
        star = rows.where("NOT far").select((-F.col("best.low")).alias("hub"), "id").where("hub <> id").select(F.least("hub", "id").alias("a"), F.greatest("hub", "id").alias("b"))
        lack = F.when(F.col("far"), -F.col("slack") - F.col("top")).otherwise(F.col("top") + 1 - F.col("slack"))
        need = F.greatest(F.ceil(lack / (2 * (100 + self.percent)) - 1e-9), F.lit(1))
        rows = rows.withColumn("room", F.col("size") - need + 1)
        entries = rows.select("cluster", "id", "n", "size", "slack", "far", "room", F.explode("delta").alias("d")).select("*", "d.*").drop("d")
        # a value that no far member has, or no other member, ranks as the rarest
        shared = entries.groupBy("cluster", "value").agg(F.count(F.lit(1)).alias("df"), F.max("far").alias("any_far")).where("df > 1 AND any_far").drop("any_far")
        lists = _ranked(entries.join(shared.hint("merge"), ["cluster", "value"]), ["cluster", "id"]).where(F.col("rank") <= F.col("room"))
        lengths = lists.groupBy("cluster", "value").agg(F.count(F.lit(1)).alias("m"), F.count_if("far").alias("fars")).where("m > 1 AND fars > 0")
        lists = lists.join(lengths.hint("merge"), ["cluster", "value"])
        before = W.partitionBy("cluster", "id").orderBy("rank").rowsBetween(-REMEMBERED, -1)
        lists = lists.withColumn("earlier", F.collect_list("value").over(before))
        return star, settle(lists.select("cluster", "value", "has", "id", "n", "size", "slack", "far", "rank", "fars", "earlier"), "difference-lists")

    def _far_pairs(self, lists: DataFrame) -> DataFrame:
        """Each far member of a list with all others, but for those that an earlier list gives."""
        x = lists.where("far").select("cluster", "value", F.col("id").alias("x"), F.col("n").alias("nx"), F.col("slack").alias("slack_x"), F.col("earlier").alias("earlier_x"), *_at("x"))
        y = lists.select("cluster", "value", "id", "n", "far", "slack", "earlier", *_at("y"))
        once = ~F.col("far") | (F.col("x") < F.col("id"))
        enough = 2 * (100 + self.percent) * _most_shared("x", "y") >= -(F.col("slack_x") + F.col("slack"))
        both = y.join(x, (y["cluster"] == x["cluster"]) & (y["value"] == x["value"]) & (F.col("id") != F.col("x")) & once & self._alike_sizes("n", "nx") & enough & ~F.arrays_overlap("earlier", "earlier_x"))
        return both.select(F.least("x", "id").alias("a"), F.greatest("x", "id").alias("b"))

    def run(self) -> DataFrame:
        """``(doc_id, n_shingles, component_id, kept)``, one row per row of ``docs``."""
        self._prepare()
        links = settle(self._confirm(self._short_pairs(self.lists, True)), "confirmed")
        if not self.long.isEmpty():
            full = settle(self._full_lists(self.long), "full-lists")
            links = links.union(settle(self._confirm(self._short_pairs(full, False)), "confirmed"))
            rest, turn = full.where(F.col("m") > SHORT).select(F.lit(0).cast("long").alias("cluster"), "value", "id", F.lit(True).alias("has")), 0
            while not rest.isEmpty():
                star, lists = self._related(self._differences(self._gather(rest, turn < MERGED_TURNS)))
                few = (F.col("fars") <= FARS) | F.lit(turn == TURNS)
                links = links.union(star).union(settle(self._confirm(self._far_pairs(lists.where(few))), "confirmed"))
                rest, turn = lists.where(~few).select("cluster", "value", "id", "has"), turn + 1
        labels = None if links.isEmpty() else components(links)
        named = self.classes if labels is None else self.classes.join(labels, "id", "left")
        named = named.select("n", "u", "v", F.coalesce("component", "id").alias("component_id") if labels is not None else F.col("id").alias("component_id"))
        out = self.base.select("doc_id", "n", "u", "v").join(named.hint("merge"), ["n", "u", "v"], "left")
        component = F.coalesce("component_id", "doc_id")
        return out.select("doc_id", F.col("n").alias("n_shingles"), component.alias("component_id"), F.col("doc_id").eqNullSafe(component).alias("kept"))


def near_duplicates(docs: DataFrame, n: int = 3, percent: int = 85) -> DataFrame:
    """Per row of ``docs`` (doc_id, text): doc_id, n_shingles, component_id, kept.

    Links hold where ``100 * |A and B| >= percent * |A or B|`` on the distinct
    ``n``-word shingles of the lower-cased (A-Z) whole texts.  A text of fewer words is
    one shingle; null, empty and blank texts have none and are linked with
    nothing.  Rows that repeat a doc_id are one node; a null id is its own."""
    return NearDuplicates(docs, n, percent).run()


def keep_one_of_each(docs: DataFrame, n: int = 5, percent: int = 80) -> DataFrame:
    """``docs`` without all but the first document of each near-duplicate group."""
    kept = near_duplicates(docs, n, percent).where("kept").select(F.col("doc_id").alias("__id")).distinct()
    return docs.join(kept, docs["doc_id"].eqNullSafe(kept["__id"]), "left_semi")
