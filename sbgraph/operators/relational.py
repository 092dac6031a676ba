"""Relational operators around signed graphs: snapshots, validity, ranks, frames, rollups."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..model import SignedGraph
from . import measures
from .index import in_order


def lost_edges(old: SignedGraph, new: SignedGraph) -> DataFrame:
    """Pairs of the old graph that the new one has not (left anti join)."""
    return old.edges.join(new.edges.select("u", "v"), ["u", "v"], "left_anti").select("u", "v")


def kept_edges(old: SignedGraph, new: SignedGraph) -> DataFrame:
    """Edges with the same sign in both."""
    return old.edges.intersect(new.edges)


def changed_edges(old: SignedGraph, new: SignedGraph) -> DataFrame:
    """Edges of the new graph that are new or have another sign."""
    return new.edges.exceptAll(old.edges)


def degree_ranks(graph: SignedGraph, tiles: int = 4) -> DataFrame:
    """gid, deg, rank, dense_rank, tile within each side, by falling degree.

    Ranks come from the table of distinct degrees (of a side with E edges, no more than the
    root of 2 E), tiles from places in the whole order.
    """
    v = graph.vertices.select("gid", "side", "deg")
    held = v.groupBy("side", "deg").agg(F.count(F.lit(1)).alias("n"))
    down = Window.partitionBy("side").orderBy(F.desc("deg"))
    ranks = held.select(F.col("side").alias("__side"), F.col("deg").alias("__deg"), (F.sum("n").over(down.rowsBetween(Window.unboundedPreceding, 0)) - F.col("n") + 1).cast("int").alias("rank"), F.row_number().over(down).alias("dense_rank"))
    sides = held.groupBy(F.col("side").alias("__s")).agg(F.sum("n").alias("size"))  # two rows
    sides = sides.select("__s", "size", F.coalesce(F.sum("size").over(Window.orderBy("__s").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("first"))
    placed = in_order(v, ["side", "deg", "gid"], descending=("deg",)).join(F.broadcast(sides), F.col("side") == F.col("__s"))
    at, small, wide = F.col("place") - F.col("first"), F.floor(F.col("size") / tiles), F.pmod(F.col("size"), F.lit(tiles))
    tile = F.when(at < wide * (small + 1), F.floor(at / (small + 1))).otherwise(wide + F.floor((at - wide * (small + 1)) / F.greatest(small, F.lit(1)))) + 1
    return placed.join(ranks, (F.col("side") == F.col("__side")) & (F.col("deg") == F.col("__deg"))).select("gid", "deg", "rank", "dense_rank", tile.cast("int").alias("tile"))


def work_cdf(work: DataFrame) -> DataFrame:
    """pivot, load, running: loads summed up from the heaviest pivot on."""
    placed = in_order(work.select("pivot", "load"), ["load", "pivot"], ("load",), ("load",))
    return placed.select("pivot", "load", F.col("sum_load").alias("running"))


def degree_quantiles(graph: SignedGraph) -> DataFrame:
    """side, median, p90, greatest degree."""
    return graph.vertices.groupBy(F.col("side").cast("int").alias("side")).agg(F.percentile("deg", F.lit(0.5)).alias("median"), F.percentile("deg", F.lit(0.9)).alias("p90"), F.max("deg").alias("greatest"))


def moving_positive(rows: DataFrame, seconds: int = 86_400) -> DataFrame:
    """u, k1, positive, n: interactions of a vertex over the time before each of them."""
    at = F.col("ts").cast("long")
    w = Window.partitionBy("u").orderBy("__at").rangeBetween(-seconds, 0)
    held = rows.withColumn("__at", at)
    return held.select("u", "k1", F.sum(F.col("sign").cast("long")).over(w).alias("positive"), F.count(F.lit(1)).over(w).alias("n"))


def as_of_join(probes: DataFrame, rows: DataFrame) -> DataFrame:
    """u, v, at, sign: the sign a pair had at a time (null before its first interaction).

    Probes and interactions are merged into one sorted run per pair, so no pair of rows
    is formed; the last sign seen is carried along.
    """
    told = rows.select("u", "v", F.col("ts").alias("at"), F.struct("k1", "k2", "sign").alias("k"), F.col("sign").cast("int").alias("s"), F.lit(0).alias("probe"))
    asked = probes.select("u", "v", "at", F.lit(None).cast("struct<k1: bigint, k2: bigint, sign: tinyint>").alias("k"), F.lit(None).cast("int").alias("s"), F.lit(1).alias("probe"))
    w = Window.partitionBy("u", "v").orderBy("at", "probe", "k").rowsBetween(Window.unboundedPreceding, 0)
    both = told.unionByName(asked).withColumn("sign", F.last("s", ignorenulls=True).over(w))
    return both.where("probe = 1").select("u", "v", "at", "sign")


def validity(rows: DataFrame) -> DataFrame:
    """u, v, sign, start, stop: the interval in which each interaction's sign held."""
    w = Window.partitionBy("u", "v").orderBy("ts", "k1", "k2", "sign")
    return rows.select("u", "v", "sign", F.col("ts").alias("start"), F.lead("ts").over(w).alias("stop")).where("stop IS NULL OR stop > start")


def interval_join(spans: DataFrame, points: DataFrame, bucket: str = "month") -> DataFrame:
    """label, edges, positive: edges whose validity holds at each point (label, at).

    Closed spans are filed under every bucket they touch and met by equality of the
    bucket; open ones are met from their start on by a running count.
    """
    cut = lambda c: F.date_trunc(bucket, c)
    step = F.expr(f"INTERVAL 1 {bucket}")
    closed = spans.where("stop IS NOT NULL").withColumn("b", F.explode(F.sequence(cut("start"), cut("stop"), step)))
    asked = points.withColumn("b", cut("at"))
    inside = asked.join(closed, "b").where("start <= at AND at < stop").groupBy("label").agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("sign").cast("long")).alias("p"))
    started = spans.where("stop IS NULL").select(F.col("start").alias("t"), F.lit(None).cast("string").alias("label"), F.lit(1).alias("one"), F.col("sign").cast("long").alias("p"))
    marks = started.unionByName(points.select(F.col("at").alias("t"), "label", F.lit(0).alias("one"), F.lit(0).cast("long").alias("p")))
    days = marks.groupBy("t", "label").agg(F.sum("one").cast("long").alias("one"), F.sum("p").cast("long").alias("p")).withColumn("asks", F.col("label").isNotNull())
    open_ = in_order(days, ["t", "asks", "label"], ("one", "p")).where("asks").select("label", F.col("sum_one").alias("n2"), F.col("sum_p").alias("p2"))
    zero = lambda c: F.coalesce(F.col(c), F.lit(0))
    return open_.join(inside, "label", "left").select("label", (zero("n2") + zero("n")).cast("long").alias("edges"), (zero("p2") + zero("p")).cast("long").alias("positive"))


def rollup_degree(edges: DataFrame, attributes: DataFrame, keys: list[str]) -> DataFrame:
    """Edges and positive edges by prefixes of the keys, with their grouping level."""
    rows = edges.join(attributes, "u")
    return rows.rollup(*keys).agg(F.count(F.lit(1)).alias("edges"), F.sum(F.col("sign").cast("long")).alias("positive"), F.grouping_id().cast("int").alias("level"))


def census_map(graph: SignedGraph, ends: str = "U") -> DataFrame:
    """One row ``shapes``: the pattern census as a map."""
    rows = measures.pattern_census(graph, ends)
    return rows.select(F.map_from_entries(F.array(*[F.struct(F.lit(c), F.col(c)) for c in rows.columns])).alias("shapes"))


def merge_census(a: Column, b: Column) -> Column:
    """The sum of two census maps."""
    return F.map_zip_with(a, b, lambda _, x, y: F.coalesce(x, F.lit(0)) + F.coalesce(y, F.lit(0)))


def sign_pivot(rows: DataFrame, key: str) -> DataFrame:
    """key, negative, positive: edges by sign as columns."""
    return rows.groupBy(key).pivot("sign", [0, 1]).count().select(key, F.coalesce(F.col("0"), F.lit(0)).alias("negative"), F.coalesce(F.col("1"), F.lit(0)).alias("positive"))
