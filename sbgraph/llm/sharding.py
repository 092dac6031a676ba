"""Sharding by a hierarchical weighted hash tree (DataFrame functions only).

Shards are the leaves of a region / rack / shard tree.  A row descends one level
at a time: every child of the current node draws ``-ln(u) / weight`` with ``u``
hashed from the key, the level and the child's own name, and the least draw wins.
A child's chance is its share of the weight, and changing one child's weight moves
rows only into or out of that child's subtree.

``standard_tree`` fills racks of four and regions of two racks, so one more shard
after a full region is a region of its own: its draw is the only new one, and rows
move only into it.  Inside an unfinished region the movement is confined to that
region's subtree.

Defined cases: a null key is drawn as the text ``null``; a null text has 0 bytes
and counts as the empty text; repeated rows go to the same shard and get slots of
their own; an empty table gives an empty result.  Slots are gapless per shard:
a shard's rows are ordered inside hash bins, and a bin starts after the rows of
the bins before it, so that no task has to sort a whole shard.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

RACK, REGION = 4, 2


@dataclass(frozen=True)
class Node:
    """A node of the tree; leaves carry a shard number and their own weight."""

    name: str
    children: tuple[Node, ...] = ()
    shard: int | None = None
    own: float = 1.0
    weight: float = field(init=False)

    def __post_init__(self) -> None:
        object.__setattr__(self, "weight", self.own if self.shard is not None else sum(c.weight for c in self.children))


def standard_tree(shards: int, weights: dict[int, float] | None = None) -> Node:
    """The tree of ``shards`` leaves; ``weights`` overrides single leaves (default 1)."""
    weights = weights or {}
    leaves = [Node(f"shard{k}", (), k, weights.get(k, 1.0)) for k in range(shards)]
    racks = [Node(f"rack{k // RACK}", tuple(leaves[k : k + RACK])) for k in range(0, shards, RACK)]
    regions = [Node(f"region{k // REGION}", tuple(racks[k : k + REGION])) for k in range(0, len(racks), REGION)]
    return Node("root", tuple(regions))


def _draw(key: Column, child: Node) -> Column:
    u = (F.shiftrightunsigned(F.xxhash64(key, F.lit(child.name)), 11) + F.lit(0.5)) / F.lit(float(1 << 53))
    return -F.log(u) / F.lit(child.weight)


def place(key: Column, node: Node) -> Column:
    """The shard a key descends to below ``node``."""
    if node.shard is not None:
        return F.lit(node.shard)
    live = [c for c in node.children if c.weight > 0]
    if len(live) == 1:
        return place(key, live[0])
    choice = F.array_min(F.array(*[F.struct(_draw(key, c).alias("draw"), F.lit(k).alias("k")) for k, c in enumerate(live)]))["k"]
    picked = F.transform(F.array(choice), lambda k: F.coalesce(*[F.when(k == i, place(key, c)) for i, c in enumerate(live)]))
    return picked[0]


def shards_of(rows: DataFrame, shards: int, key: str = "doc_id", out: str = "shard", tree: Node | None = None) -> DataFrame:
    """Adds the shard of every row."""
    text = F.coalesce(F.col(f"`{key}`").cast("string"), F.lit("null"))
    return rows.withColumn(out, place(text, tree or standard_tree(shards)).cast("int"))


def with_slots(rows: DataFrame, order: list[str], shard: str = "shard", bins: int = 256) -> DataFrame:
    """Adds ``slot``: gapless from 0 in every shard.

    ``order`` must settle the order of different rows.  Bins per shard are the
    unit of work: their counts (shards x bins rows) give each bin's first slot.
    """
    binned = rows.withColumn("__bin", F.pmod(F.xxhash64(F.lit("slot"), *[F.col(c) for c in order]), F.lit(bins)).cast("int"))
    counts = binned.groupBy(shard, "__bin").agg(F.count(F.lit(1)).alias("__n"))
    before = Window.partitionBy(shard).orderBy("__bin").rowsBetween(Window.unboundedPreceding, -1)
    first = counts.select(F.col(shard).alias("__shard"), F.col("__bin").alias("__b"), F.coalesce(F.sum("__n").over(before), F.lit(0)).alias("__first"))
    within = Window.partitionBy(shard, "__bin").orderBy(*order)
    ranked = binned.withColumn("__rank", F.row_number().over(within) - 1)
    # At most shards x bins rows: a proven bound.
    joined = ranked.join(F.broadcast(first), (F.col(shard) == F.col("__shard")) & (F.col("__bin") == F.col("__b")))
    return joined.withColumn("slot", (F.col("__first") + F.col("__rank")).cast("long")).drop("__bin", "__b", "__shard", "__first", "__rank")


def assign(docs: DataFrame, shards: int = 24, bins: int = 256, key: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id, size, text_crc32, law, shard, slot and grown_shard of every row."""
    size = F.coalesce(F.octet_length(F.col(f"`{text}`")), F.lit(0)).cast("long") + 8
    rows = docs.select(F.col(f"`{key}`").alias("doc_id"), size.alias("size"), F.crc32(F.coalesce(F.col(f"`{text}`"), F.lit("")).cast("binary")).alias("text_crc32"))
    rows = shards_of(shards_of(rows, shards), shards + 1, out="grown_shard")
    slotted = with_slots(rows, ["doc_id", "text_crc32", "size"], bins=bins)
    return slotted.select("doc_id", "size", "text_crc32", F.lit("key").alias("law"), "shard", "slot", "grown_shard")
