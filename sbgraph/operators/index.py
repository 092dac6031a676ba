"""Degrees, priority, compact ids, orientation and workloads."""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import higher, owner
from ..model import SignedGraph
from ..sources import cut


def degrees(graph: SignedGraph) -> DataFrame:
    """gid, deg.  Partial counts per task, summed at the hash owner of the id."""
    return graph.directed.groupBy(F.col("mid").alias("gid")).agg(F.count(F.lit(1)).alias("deg"))


def attach_degrees(graph: SignedGraph, deg: DataFrame | None = None) -> DataFrame:
    """gu, gv, sign, du, dv: the index returned to the edges that refer to it."""
    deg = degrees(graph) if deg is None else deg
    left = deg.select(F.col("gid").alias("gu"), F.col("deg").alias("du"))
    right = deg.select(F.col("gid").alias("gv"), F.col("deg").alias("dv"))
    return graph.tagged.join(left, "gu").join(right, "gv")


def orient(graph: SignedGraph, deg: DataFrame | None = None) -> DataFrame:
    """Edges from the end of higher priority to the lower one: hi, hi_deg, lo, lo_deg, sign."""
    e = attach_degrees(graph, deg)
    up = higher(F.col("du"), F.col("gu"), F.col("dv"), F.col("gv"))
    pick = lambda a, b: F.when(up, F.col(a)).otherwise(F.col(b))
    return e.select(pick("gu", "gv").alias("hi"), pick("du", "dv").alias("hi_deg"), pick("gv", "gu").alias("lo"), pick("dv", "du").alias("lo_deg"), "sign")


def in_order(rows: DataFrame, keys: list[str], values: tuple[str, ...] = (), descending: tuple[str, ...] = (), parts: int | None = None, held: list[DataFrame] | None = None) -> DataFrame:
    """Rows with ``place`` (from 0) in the order of the keys, and ``sum_<value>`` up to each row.

    Rows are dealt by ranges and sorted there; ``parts`` counts and sums put the ranges behind
    one another, so no task sees all rows.  Ranges are drawn once and kept: behind a checkpoint,
    or, with ``held``, as a cached table that is put into that list for the caller to release.
    """
    parts = parts or int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    by = [F.desc(k) if k in descending else F.asc(k) for k in keys]
    dealt = rows.repartitionByRange(parts, *by).sortWithinPartitions(*by)
    schema = ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in rows.schema.fields), "part int, place long", *(f"sum_{v} long" for v in values)])

    def number(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        part, at, sums = TaskContext.get().partitionId(), 0, dict.fromkeys(values, 0)
        for b in batches:
            if not b.num_rows:
                continue
            running = [pc.add(pc.cumulative_sum(b.column(v).cast(pa.int64())), sums[v]) for v in values]
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array([part] * b.num_rows, pa.int32()), pa.array(range(at, at + b.num_rows), pa.int64()), *running], names=[*b.schema.names, "part", "place", *(f"sum_{v}" for v in values)])
            at += b.num_rows
            sums = {v: r[-1].as_py() for v, r in zip(values, running, strict=True)}

    numbered = dealt.mapInArrow(number, schema)
    if held is None:
        numbered = cut(numbered)
    else:
        held.append(numbered := numbered.persist())
    ends = numbered.groupBy("part").agg(F.count(F.lit(1)).alias("n"), *(F.max_by(f"sum_{v}", "place").alias(f"all_{v}") for v in values))
    before = Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    first = ends.select("part", *(F.coalesce(F.sum(c).over(before), F.lit(0)).alias(f"__{c}") for c in ("n", *(f"all_{v}" for v in values))))
    met = numbered.join(F.broadcast(first), "part")  # ``parts`` rows
    return met.select(*rows.columns, (F.col("__n") + F.col("place")).alias("place"), *((F.col(f"__all_{v}") + F.col(f"sum_{v}")).alias(f"sum_{v}") for v in values))


def compact_ids(vertices: DataFrame, order: str = "priority", parts: int | None = None, held: list[DataFrame] | None = None) -> DataFrame:
    """gid, deg, rank_id: dense ids from 0.

    ``priority`` orders by (deg, gid) so that ids compare as priorities; ``hash`` keeps
    the ids of each of ``parts`` owners together.
    """
    rows = vertices.select("gid", "deg")
    if order == "priority":
        return in_order(rows, ["deg", "gid"], parts=parts, held=held).select("gid", "deg", F.col("place").alias("rank_id"))
    owned = rows.withColumn("owner", owner(F.col("gid"), parts or int(rows.sparkSession.conf.get("spark.sql.shuffle.partitions"))))
    return in_order(owned, ["owner", "gid"], parts=parts, held=held).select("gid", "deg", F.col("place").alias("rank_id"))


def ranked(graph: SignedGraph, ids: DataFrame | None = None) -> DataFrame:
    """Edges by rank: hi, hi_deg, lo, lo_deg, sign; a greater rank is a higher priority."""
    ids = compact_ids(degrees(graph)) if ids is None else ids
    ends = lambda g, r, d: ids.select(F.col("gid").alias(g), F.col("rank_id").alias(r), F.col("deg").alias(d))
    e = graph.tagged.join(ends("gu", "ru", "du"), "gu").join(ends("gv", "rv", "dv"), "gv")
    up = F.col("ru") > F.col("rv")
    pick = lambda a, b: F.when(up, F.col(a)).otherwise(F.col(b))
    return e.select(pick("ru", "rv").alias("hi"), pick("du", "dv").alias("hi_deg"), pick("rv", "ru").alias("lo"), pick("dv", "du").alias("lo_deg"), F.col("sign").cast("long").alias("sign"))


KINDS = ("full", "restricted", "exact")


def rank_workload(ranked: DataFrame, kind: str = "full") -> DataFrame:
    """pivot, load from oriented edges, for vertices with any load."""
    if kind == "full":
        both = ranked.select(F.col("hi").alias("pivot"), F.col("lo_deg").alias("d")).unionByName(ranked.select(F.col("lo").alias("pivot"), F.col("hi_deg").alias("d")))
        return both.groupBy("pivot").agg(F.sum("d").cast("long").alias("load"))
    if kind == "restricted":
        return ranked.groupBy(F.col("hi").alias("pivot")).agg(F.sum("lo_deg").cast("long").alias("load"))
    if kind == "exact":
        return _below(ranked).groupBy("pivot").agg(F.sum("below").cast("long").alias("load"))
    raise ValueError(f"kind must be one of {KINDS}")


def workload(graph: SignedGraph, kind: str = "full") -> DataFrame:
    """pivot, load of every vertex.

    ``full``: the degrees of all neighbours; ``restricted``: of neighbours below the
    pivot; ``exact``: the wedges that survive both priority tests.
    """
    deg = degrees(graph)
    own = rank_workload(orient(graph, deg), kind)
    return deg.select(F.col("gid").alias("pivot")).join(own, "pivot", "left").select("pivot", F.coalesce("load", F.lit(0)).cast("long").alias("load"))


def _below(oriented: DataFrame) -> DataFrame:
    """pivot, below: for every edge, the neighbours of its lower end that the pivot outranks.

    All lists are put in order together by ranges, so that a hub's list is cut like any other.
    """
    both = oriented.select(F.col("lo").alias("mid"), F.col("hi").alias("end"), F.col("hi_deg").alias("end_deg"), F.lit(True).alias("above")).unionByName(oriented.select(F.col("hi").alias("mid"), F.col("lo").alias("end"), F.col("lo_deg").alias("end_deg"), F.lit(False).alias("above")))
    placed = in_order(both, ["mid", "end_deg", "end"])
    first = placed.groupBy("mid").agg(F.min("place").alias("first"))
    return placed.where("above").join(first, "mid").select(F.col("end").alias("pivot"), (F.col("place") - F.col("first")).alias("below"))


def work_bounds(graph: SignedGraph) -> DataFrame:
    """One row: edges, sum of smaller degrees, full workload, surviving wedges."""
    o = orient(graph)
    return o.agg(F.count(F.lit(1)).alias("edges"), F.coalesce(F.sum("lo_deg"), F.lit(0)).cast("long").alias("sum_min"), F.coalesce(F.sum(F.col("hi_deg") + F.col("lo_deg")), F.lit(0)).cast("long").alias("sum_full")).crossJoin(workload(graph, "exact").agg(F.coalesce(F.sum("load"), F.lit(0)).cast("long").alias("wedges")))  # one row each


def prune_core(graph: SignedGraph, rounds: int = 2) -> SignedGraph:
    """Drops vertices of degree 1, round by round; the count does not change."""
    edges = graph.edges
    for _ in range(rounds):
        for side in ("u", "v"):
            keep = edges.groupBy(side).agg(F.count(F.lit(1)).alias("__n")).where("__n > 1").select(side)
            edges = edges.join(keep, side, "left_semi").select("u", "v", "sign")
    return SignedGraph(edges, graph.name)
