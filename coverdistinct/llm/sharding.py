"""Sharding by a hierarchical weighted hash tree, in DataFrame expressions only.

Each inner node of the tree holds a draw among its children: child ``c`` of
weight ``w`` gets the score ``-ln(u(key, c)) / w`` and the lowest score wins, so a
child wins in proportion to its weight and a change of one weight moves rows
only into or out of that child's subtree.  A row costs
``regions + racks of one region + shards of one rack`` draws, not one per shard.

Capacity is added as a subtree of its own under the root (``grow``); its score
is one more number in the root's draw, so a row either keeps its whole path or
goes to the new subtree.  Weights inside a rack may also be changed; movement is
then confined to the region, rack and shard whose weights changed.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import shuffle_partitions, unit


@dataclass(frozen=True)
class Shard:
    region: str
    rack: str
    shard: int
    weight: float = 1.0


@dataclass(frozen=True)
class Topology:
    """A weighted tree of regions, racks and shards; bounded by its author, never by data."""

    shards: tuple[Shard, ...]

    @classmethod
    def regular(cls, regions: int, racks: int, per_rack: int) -> Topology:
        return cls(tuple(
            Shard(f"r{r}", f"r{r}k{k}", (r * racks + k) * per_rack + s)
            for r in range(regions) for k in range(racks) for s in range(per_rack)
        ))

    def grow(self, weight: float = 1.0) -> Topology:
        """One more shard, in a region of its own: it takes rows only into itself."""
        n = max((s.shard for s in self.shards), default=-1) + 1
        return Topology((*self.shards, Shard(f"r+{n}", f"r+{n}k0", n, weight)))

    def tree(self) -> dict[str, dict[str, dict[int, float]]]:
        out: dict[str, dict[str, dict[int, float]]] = {}
        for s in self.shards:
            if s.weight <= 0:
                raise ValueError("weights are positive; leave a drained shard out")
            out.setdefault(s.region, {}).setdefault(s.rack, {})[s.shard] = float(s.weight)
        if not out:
            raise ValueError("a topology has one shard at least")
        return out


def _children(nodes: list[list[tuple[str, float, int]]]) -> Column:
    """A constant: for each node its children as (name, weight, index below)."""
    return F.array(*[F.array(*[F.struct(F.lit(n).alias("name"), F.lit(w).alias("weight"), F.lit(i).alias("below")) for n, w, i in x]) for x in nodes])


def _draw(key: Column, children: Column) -> Column:
    """The index of the child that wins the weighted draw."""
    score = lambda c: F.struct((-F.log(unit(key, c["name"])) / c["weight"]).alias("score"), c["below"].alias("below"))
    return F.array_min(F.transform(children, score))["below"]


def _pick(df: DataFrame, key: Column, topology: Topology, out: str) -> DataFrame:
    """Adds ``out``: three narrow projections, one per level."""
    tree = topology.tree()
    regions, racks = [], []
    leaves: list[list[tuple[str, float, int]]] = []
    for region, below in tree.items():
        regions.append((f"region:{region}", sum(sum(x.values()) for x in below.values()), 0))
        racks.append([])
        for rack, shards in below.items():
            racks[-1].append((f"rack:{rack}", sum(shards.values()), len(leaves)))
            leaves.append([(f"shard:{s}", w, s) for s, w in shards.items()])
    return (df.withColumn("__region", _draw(key, _children([[(n, w, i) for i, (n, w, _) in enumerate(regions)]])[0]))
              .withColumn("__rack", _draw(key, _children(racks)[F.col("__region")]))
              .withColumn(out, _draw(key, _children(leaves)[F.col("__rack")]))
              .drop("__region", "__rack"))


def assign(df: DataFrame, key: str, topology: Topology, out: str = "shard") -> DataFrame:
    """Adds the shard of each row's ``key`` (a null key is a key like any other)."""
    return _pick(df, F.coalesce(F.col(key).cast("string"), F.lit("\x00null")), topology, out)


def number(df: DataFrame, shard: str, order: list[str], out: str = "slot") -> DataFrame:
    """Adds a gapless position from 0 within each shard.

    A shard's rows never meet in one task: rows are dealt to ``(shard, cell)``
    pairs by a hash of the order columns, cells are counted after a partial
    aggregate, and a row's slot is its cell's offset plus its rank in the cell.
    The offsets table has shards x cells rows, whatever the data.
    """
    from pyspark.sql import Window as W

    cells = 4 * shuffle_partitions(df.sparkSession)
    dealt = df.withColumn("__cell", F.pmod(F.xxhash64(*order, F.lit("cell")), F.lit(cells)).cast("int"))
    counts = dealt.groupBy(shard, "__cell").agg(F.count(F.lit(1)).alias("__n"))
    before = W.partitionBy(shard).orderBy("__cell").rowsBetween(W.unboundedPreceding, -1)
    offsets = counts.select(shard, "__cell", F.coalesce(F.sum("__n").over(before), F.lit(0)).alias("__offset"))
    ranked = dealt.withColumn("__rank", F.row_number().over(W.partitionBy(shard, "__cell").orderBy(*order)) - 1)
    joined = ranked.join(offsets, [shard, "__cell"])
    return joined.withColumn(out, (F.col("__offset") + F.col("__rank")).cast("long")).drop("__cell", "__rank", "__offset")


BASE = Topology.regular(regions=2, racks=5, per_rack=4)


def shard_documents(docs: DataFrame, topology: Topology = BASE) -> DataFrame:
    """Every row of ``docs`` (doc_id, text) with its shard, slot and the shard it
    would have with one shard more.  Null texts have size 16 and the CRC of no
    bytes; repeated rows get the same shard and slots of their own; null ids are
    a key.  Of other columns none is read."""
    small = docs.select(
        "doc_id",
        (F.coalesce(F.octet_length("text"), F.lit(0)) + 16).cast("long").alias("size"),
        F.crc32(F.coalesce("text", F.lit(""))).alias("text_crc32"),
    )
    placed = assign(assign(small, "doc_id", topology), "doc_id", topology.grow(), "grown_shard")
    return number(placed, "shard", ["doc_id", "text_crc32", "size"]).select(
        "doc_id", "size", "text_crc32", F.lit("key").alias("law"), "shard", "slot", "grown_shard")


def shard_table(docs: DataFrame, path: str, topology: Topology = BASE) -> None:
    """Write ``docs`` (with ``doc_id``) as one folder per shard; a null id is a key like any
    other, and a column of docs may have the name ``shard``, which is replaced.  The rows are
    rebalanced by shard: as many tasks, and so files, as the bytes of each shard need."""
    assign(docs.drop("shard"), "doc_id", topology).hint("rebalance", "shard").write.partitionBy("shard").parquet(path)
