"""Assignment of pivots to bins."""

from __future__ import annotations

import heapq

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import owner
from .index import in_order

#: Pivots that the exact greedy assigner may hold on the driver.
DRIVER_PIVOTS = 5_000_000
ASSIGNMENT = "pivot long, bin int, load long"


def greedy(loads: list[tuple[int, int]], bins: int) -> list[tuple[int, int, int]]:
    """(id, bin, load): heaviest first, each to the least loaded bin (ties: id, bin)."""
    heap = [(0, b) for b in range(bins)]
    out = []
    for key, load in sorted(loads, key=lambda x: (-x[1], x[0])):
        total, b = heapq.heappop(heap)
        out.append((key, b, load))
        heapq.heappush(heap, (total + load, b))
    return out


def assign_lpt(work: DataFrame, bins: int, cap: int = DRIVER_PIVOTS) -> DataFrame:
    """Exact greedy bin packing on the driver; refuses more than ``cap`` pivots."""
    if (n := work.count()) > cap:
        raise ValueError(f"{n} pivots are more than {cap}; use lpt_scalable")
    return work.sparkSession.createDataFrame(greedy([(r["pivot"], r["load"]) for r in work.toLocalIterator()], bins), ASSIGNMENT)


def assign_lpt_scalable(work: DataFrame, bins: int, buckets: int | None = None, share: float = 0.25) -> DataFrame:
    """Greedy over heavy pivots and over hash buckets of the others.

    A pivot above ``share`` of a bin's mean load is heavy; there are at most
    ``bins / share`` of them.  All others fall into ``buckets`` buckets whose sums are
    packed.  The driver holds the heavy pivots and the buckets only.
    """
    buckets = buckets or 64 * bins
    spark, mean = work.sparkSession, (work.agg(F.sum("load")).first()[0] or 0) / bins
    heavy, slot = F.col("load") > F.lit(share * mean), owner(F.col("pivot"), buckets)
    units = work.withColumn("unit", F.when(heavy, F.col("pivot")).otherwise(-1 - slot.cast("long")))
    sums = units.groupBy("unit").agg(F.sum("load").cast("long").alias("load")).collect()  # bins / share + buckets rows at most
    packed = greedy([(r["unit"], r["load"]) for r in sums], bins)
    side = F.broadcast(spark.createDataFrame([(k, b) for k, b, _ in packed], "unit long, bin int"))
    return units.join(side, "unit").select("pivot", "bin", "load")


def assign_blocks(work: DataFrame, bins: int) -> DataFrame:
    """Consecutive pivots in blocks of equal size; loads are ignored."""
    placed = in_order(work.select("pivot", "load"), ["pivot"])
    n = placed.agg(F.count(F.lit(1)).alias("n"))  # one row
    return placed.crossJoin(F.broadcast(n)).select("pivot", F.floor(F.col("place") * bins / F.col("n")).cast("int").alias("bin"), "load")


def assign_hash(work: DataFrame, bins: int) -> DataFrame:
    return work.select("pivot", owner(F.col("pivot"), bins).alias("bin"), "load")


def assign_snake(work: DataFrame, bins: int) -> DataFrame:
    """Bins in turn, back and forth, by falling load."""
    turn, at = F.floor(F.col("place") / bins), F.pmod(F.col("place"), F.lit(bins))
    placed = in_order(work.select("pivot", "load"), ["load", "pivot"], descending=("load",))
    return placed.select("pivot", F.when(turn % 2 == 0, at).otherwise(bins - 1 - at).cast("int").alias("bin"), "load")


ASSIGNERS = {"lpt": assign_lpt, "lpt_scalable": assign_lpt_scalable, "blocks": assign_blocks, "hash": assign_hash, "snake": assign_snake}


def split_hot(assignment: DataFrame, bins: int, max_load: int) -> DataFrame:
    """pivot, bin, load, shard, shards: a pivot above ``max_load`` is cut by end vertex.

    Counters are per end, so the shards' counts add up without a merge.  A pivot may have more
    shards than there are bins; a bin then holds several of them.
    """
    shards = F.greatest(F.lit(1), F.ceil(F.col("load") / F.lit(max_load))).cast("int")
    cut = assignment.withColumn("shards", shards).withColumn("shard", F.explode(F.sequence(F.lit(0), F.col("shards") - 1)))
    return cut.select("pivot", F.pmod(F.col("bin") + F.col("shard"), F.lit(bins)).cast("int").alias("bin"), (F.col("load") / F.col("shards")).cast("long").alias("load"), "shard", "shards")


def assignment_stats(assignment: DataFrame, bins: int) -> DataFrame:
    """One row: least and greatest bin load and their ratio (null when a bin is empty)."""
    held = assignment.groupBy("bin").agg(F.sum("load").cast("long").alias("load"))
    all_bins = assignment.sparkSession.range(bins).select(F.col("id").cast("int").alias("bin"))
    loads = all_bins.join(held, "bin", "left").select(F.coalesce("load", F.lit(0)).alias("load"))
    low, high = F.min("load"), F.max("load")
    return loads.agg(low.alias("least"), high.alias("greatest"), F.round(high / F.nullif(low, F.lit(0)), 6).alias("ratio"))
