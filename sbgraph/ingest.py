"""From interactions to simple signed edges."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .model import SignedGraph


def sign_from_predicate(rows: DataFrame, condition: Column) -> DataFrame:
    """A native sign: 1 where the condition holds, else 0."""
    return rows.withColumn("sign", F.when(condition, 1).otherwise(0).cast("byte"))


def sign_from_rating(rows: DataFrame, rating: str, threshold: str = "fixed", value: float = 0.0, user: str = "u") -> DataFrame:
    """A rating at or above a threshold is positive.

    threshold: ``fixed`` (``value``), ``mean`` or ``median`` of the graph, ``user_mean``.
    """
    r = F.col(rating)
    if threshold == "fixed":
        return sign_from_predicate(rows, r >= F.lit(value))
    if threshold == "user_mean":
        means = rows.groupBy(F.col(user).alias("__u")).agg(F.avg(rating).alias("__cut"))
        return sign_from_predicate(rows.join(means, F.col(user) == F.col("__u")), r >= F.col("__cut")).drop("__u", "__cut")
    cut = rows.agg((F.avg(rating) if threshold == "mean" else F.percentile(rating, F.lit(0.5))).alias("__cut"))
    return sign_from_predicate(rows.crossJoin(F.broadcast(cut)), r >= F.col("__cut")).drop("__cut")  # one row


def random_bucket(seed: int) -> Column:
    """A number from 0 to 99 that depends on the pair and the seed only."""
    return F.conv(F.substring(F.md5(F.concat_ws("|", F.col("u").cast("string"), F.col("v").cast("string"), F.lit(str(seed)))), 1, 8), 16, 10).cast("long") % 100


def sign_random(edges: DataFrame, neg_pct: int = 30, seed: int = 42) -> DataFrame:
    """Each pair negative with a fixed probability; negative sets of one seed are nested."""
    return edges.withColumn("sign", (random_bucket(seed) >= neg_pct).cast("byte"))


def sign_sweep(graph: SignedGraph, neg_pcts: tuple[int, ...] = (10, 30, 50, 70, 90), seed: int = 42) -> dict[int, SignedGraph]:
    """The same topology at several shares of negative edges."""
    return {p: SignedGraph(sign_random(graph.edges, p, seed).select("u", "v", "sign"), f"{graph.name}_neg{p}") for p in neg_pcts}


POLICIES = ("latest", "earliest", "majority", "sum", "drop_conflicts")


def resolve_conflicts(rows: DataFrame, policy: str = "latest") -> DataFrame:
    """One edge per pair.

    ``latest`` keeps the sign of the greatest (ts, k1, k2, sign), ``earliest`` of the
    least, ``majority`` the more frequent sign (positive on a tie), ``sum`` the sign of
    the sum of +1 / -1 (pairs that cancel out are dropped), ``drop_conflicts`` only
    pairs without a conflict.  All are partial aggregates; none sorts.
    """
    order = F.struct("ts", "k1", "k2", "sign")
    by = rows.groupBy("u", "v")
    if policy == "latest":
        return by.agg(F.max_by("sign", order).cast("byte").alias("sign"))
    if policy == "earliest":
        return by.agg(F.min_by("sign", order).cast("byte").alias("sign"))
    counts = by.agg(F.sum(F.col("sign").cast("long")).alias("pos"), F.count(F.lit(1)).alias("n"))
    neg = F.col("n") - F.col("pos")
    if policy == "majority":
        return counts.select("u", "v", (F.col("pos") >= neg).cast("byte").alias("sign"))
    if policy == "sum":
        return counts.where(F.col("pos") != neg).select("u", "v", (F.col("pos") > neg).cast("byte").alias("sign"))
    if policy == "drop_conflicts":
        return counts.where((F.col("pos") == 0) | (neg == 0)).select("u", "v", (F.col("pos") > 0).cast("byte").alias("sign"))
    raise ValueError(f"policy must be one of {POLICIES}")


def duplicate_profile(rows: DataFrame) -> DataFrame:
    """One row: interactions, pairs, repeated pairs, conflicting pairs, pairs whose conflict ties in time."""
    pairs = rows.groupBy("u", "v").agg(F.count(F.lit(1)).alias("n"), F.min("sign").alias("a"), F.max("sign").alias("b"), F.max(F.when(F.col("sign") == 1, F.col("ts"))).alias("p"), F.max(F.when(F.col("sign") == 0, F.col("ts"))).alias("q"))
    count = lambda c: F.coalesce(F.sum(F.when(c, 1).otherwise(0)), F.lit(0)).cast("long")
    return pairs.agg(
        F.coalesce(F.sum("n"), F.lit(0)).cast("long").alias("interactions"),
        F.count(F.lit(1)).alias("pairs"),
        count(F.col("n") > 1).alias("repeated"),
        count(F.col("a") != F.col("b")).alias("conflicting"),
        count((F.col("a") != F.col("b")) & (F.col("p") == F.col("q"))).alias("tied"),
    )


def as_unsigned(graph: SignedGraph) -> DataFrame:
    return graph.edges.select("u", "v")


def sign_flips(rows: DataFrame) -> DataFrame:
    """u, v, flips: how often a pair's sign changed over its interactions."""
    w = Window.partitionBy("u", "v").orderBy("ts", "k1", "k2", "sign")
    return rows.withColumn("was", F.lag("sign").over(w)).groupBy("u", "v").agg(F.sum(F.when(F.col("was") != F.col("sign"), 1).otherwise(0)).cast("long").alias("flips"))


def sign_as_of(rows: DataFrame, when: Column) -> DataFrame:
    """Edges as they stood at a time: the latest sign up to it."""
    return resolve_conflicts(rows.where(F.col("ts") <= when))
