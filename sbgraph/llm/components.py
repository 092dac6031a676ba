"""Connected components of a distributed link table (large-star / small-star rounds)."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .store import Store


#: Parts into which a node's larger neighbours are dealt, so that a hub is no single key.
SALTS = 16


def _stars(edges: DataFrame, large: bool) -> DataFrame:
    """One star step over edges (a, b) with a > b.

    large: every node links its larger neighbours to its least neighbour;
    small: every node links itself and its smaller neighbours to the least one.
    """
    if large:
        both = edges.unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
        least = both.groupBy("a").agg(F.least(F.min("b"), F.first("a")).alias("m"))
        least = least.withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
        salted = both.where("b > a").withColumn("salt", F.pmod(F.xxhash64("b"), F.lit(SALTS)).cast("int"))
        linked = salted.join(least, ["a", "salt"]).select(F.col("b").alias("a"), F.col("m").alias("b"))
    else:
        least = edges.groupBy("a").agg(F.min("b").alias("m"))
        joined = edges.join(least, "a")
        linked = joined.select(F.col("b").alias("a"), F.col("m").alias("b")).unionByName(least.select("a", F.col("m").alias("b")))
    return linked.where("a <> b").distinct()


def components(edges: DataFrame, store: Store, rounds: int = 100) -> DataFrame:
    """(node, component) of every node with a link; the component is its least node."""
    state = lambda t: t.agg(F.count(F.lit(1)), F.sum(F.hash("a", "b").cast("long"))).first()
    now = store.put("links0", edges.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).where("a <> b").distinct())
    seen = state(now)
    for k in range(1, rounds + 1):
        now = store.put(f"links{k}", _stars(_stars(now, True), False))
        store.drop(f"links{k - 1}")
        seen, was = state(now), seen
        if seen == was:
            break
    else:
        raise RuntimeError("components did not settle")
    return now.select(F.col("a").alias("node"), F.col("b").alias("component")).unionByName(now.select(F.col("b").alias("node"), F.col("b").alias("component")).distinct())
