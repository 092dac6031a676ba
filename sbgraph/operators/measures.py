"""Measures derived from balanced butterflies."""

from __future__ import annotations

import itertools

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import choose2, gid, total
from ..model import SignedGraph
from ..schemas import TOTAL
from ..sources import cut
from . import count, index, tiles

SIDES = {"U": ("gu", "gv"), "V": ("gv", "gu")}


def balance_summary(graph: SignedGraph, order: str = "priority") -> DataFrame:
    """One row: total, balanced, unbalanced, ratio."""
    b1, b2 = F.col("b1"), F.col("b2")
    rows = count.pairs(graph, order).agg(total(choose2(b1 + b2)).alias("total"), total(choose2(b1) + choose2(b2)).alias("balanced"), total(b1 * b2).alias("unbalanced"))
    return rows.withColumn("ratio", F.round(F.col("balanced").cast("double") / F.nullif(F.col("total").cast("double"), F.lit(0.0)), 6))


def four_counters(graph: SignedGraph, ends: str = "U") -> DataFrame:
    """low, high, pp, nn, pn, np: wedges between two ends of one side by their two signs."""
    end, mid = SIDES[ends]
    t = graph.tagged
    a = t.select(F.col(mid).alias("mid"), F.col(end).alias("low"), F.col("sign").alias("s1"))
    b = t.select(F.col(mid).alias("mid"), F.col(end).alias("high"), F.col("sign").alias("s2"))
    n = lambda x, y: F.sum(F.when((F.col("s1") == x) & (F.col("s2") == y), 1).otherwise(0)).cast("long")
    return a.join(b, "mid").where("low < high").groupBy("low", "high").agg(n(1, 1).alias("pp"), n(0, 0).alias("nn"), n(1, 0).alias("pn"), n(0, 1).alias("np"))


def pattern_census(graph: SignedGraph, ends: str = "U") -> DataFrame:
    """One row: the seven shapes of a butterfly by its negative edges.

    Two negatives sit on the middle vertex, on one end, or on opposite corners.
    """
    pp, nn, pn, np_ = (F.col(c) for c in ("pp", "nn", "pn", "np"))
    on_mid, on_end = ("two_on_v", "two_on_u") if ends == "U" else ("two_on_u", "two_on_v")
    shapes = {"none": choose2(pp), "four": choose2(nn), on_mid: pp * nn, on_end: choose2(pn) + choose2(np_), "two_diagonal": pn * np_, "one": pp * (pn + np_), "three": nn * (pn + np_)}
    rows = four_counters(graph, ends).agg(*[total(v).alias(k) for k, v in shapes.items()])
    return rows.select("none", "four", "two_on_v", "two_on_u", "two_diagonal", "one", "three")


def class_split(graph: SignedGraph, ends: str = "U") -> DataFrame:
    """One row: balanced butterflies closed by symmetric and by asymmetric wedges, for one end side.

    Wedges are formed on the side that has fewer.  Seen from the other one, a butterfly of symmetric
    wedges has two mids whose signs to both ends agree (the wedges' two signs are the same pair),
    one of asymmetric wedges has mids whose signs are opposite at both ends.
    """
    other = "V" if ends == "U" else "U"
    if tiles.wedges_of(graph, ends) <= tiles.wedges_of(graph, other):
        return count.pairs(graph, ends).agg(total(choose2(F.col("b1"))).alias("symmetric"), total(choose2(F.col("b2"))).alias("asymmetric"))
    pp, nn, pn, np_ = (F.col(c) for c in ("pp", "nn", "pn", "np"))
    same = choose2(pp) + choose2(nn) + choose2(pn) + choose2(np_)
    return four_counters(graph, other).agg(total(same).alias("symmetric"), total(pp * nn + pn * np_).alias("asymmetric"))


def vertex_counts(graph: SignedGraph, side: str = "U") -> DataFrame:
    """key, balanced of every vertex of a side."""
    n = choose2(F.col("b1")) + choose2(F.col("b2"))
    own = count.pairs(graph, side).withColumn("n", n)
    held = own.select(F.col("pivot").alias("g"), "n").unionByName(own.select(F.col("end").alias("g"), "n")).groupBy("g").agg(total(F.col("n")).alias("balanced"))
    keys = graph.edges.select(F.col(side.lower()).alias("key")).distinct()
    return keys.join(held.select(F.shiftright("g", 1).alias("key"), "balanced"), "key", "left").select("key", F.coalesce("balanced", F.lit(0)).cast(TOTAL).alias("balanced"))


def edge_counts(graph: SignedGraph, side: str = "U") -> DataFrame:
    """u, v, balanced of every edge: over its wedges, the other wedges of their class.

    The joins move every wedge thrice; where those are many, tiles count them where they are formed.
    """
    if 3 * tiles.wedges_of(graph, side) > tiles.FAR:
        held = tiles.edge_counts(graph.cached(), side)
    else:
        w = count.wedges(graph, side)
        met = w.join(count.pairs(graph, side), ["pivot", "end"]).withColumn("n", F.when(F.col("pos") != 1, F.col("b1")).otherwise(F.col("b2")) - 1)
        both = met.select(F.col("pivot").alias("g"), "mid", "n").unionByName(met.select(F.col("end").alias("g"), "mid", "n"))
        held = both.groupBy("g", "mid").agg(F.sum("n").cast("long").alias("balanced"))
    e = graph.edges.select("u", "v", gid(F.col("u"), 0).alias("gu"), gid(F.col("v"), 1).alias("gv"))
    end, mid = SIDES[side]
    return e.join(held, (e[end] == held["g"]) & (e[mid] == held["mid"]), "left").select("u", "v", F.coalesce("balanced", F.lit(0)).cast("long").alias("balanced"))


def top_pairs(graph: SignedGraph, k: int = 10, side: str = "U") -> DataFrame:
    """a, b, balanced: the pairs of one side that share the most balanced butterflies."""
    rows = count.pairs(graph, side).select(F.shiftright("end", 1).alias("a"), F.shiftright("pivot", 1).alias("b"), (choose2(F.col("b1")) + choose2(F.col("b2"))).alias("balanced"))
    return rows.orderBy(F.desc("balanced"), "a", "b").limit(k)


def clustering(graph: SignedGraph) -> DataFrame:
    """One row: butterflies per path of three edges, all and balanced."""
    paths = index.attach_degrees(graph).agg(total((F.col("du") - 1) * (F.col("dv") - 1)).alias("paths"))
    rows = balance_summary(graph).crossJoin(paths)  # one row each
    share = lambda c: F.round(4 * F.col(c).cast("double") / F.nullif(F.col("paths").cast("double"), F.lit(0.0)), 6)
    return rows.select("paths", "total", "balanced", share("total").alias("coefficient"), share("balanced").alias("balanced_coefficient"))


def is_biclique(graph: SignedGraph, us: list[int], vs: list[int]) -> bool:
    """Whether every pair of the two sets is an edge."""
    return graph.edges.where(F.col("u").isin(us) & F.col("v").isin(vs)).count() == len(set(us)) * len(set(vs))


def _gather(done: DataFrame | None, named: DataFrame, turn: int) -> DataFrame:
    """What is peeled so far, cut now and then so that the plan stays short."""
    both = named if done is None else done.unionByName(named)
    return cut(both) if turn % 50 == 0 else both


def tip_decomposition(graph: SignedGraph, side: str = "U") -> DataFrame:
    """key, tip: the greatest k such that the vertex is in a set of one side whose members
    each have k balanced butterflies inside the set.

    The butterflies of two vertices of a side do not change while others of that side go,
    so this is a weighted core decomposition of the pair graph.  Every vertex starts at all its
    butterflies and falls to the greatest k for which those shared with vertices at k or
    above are k at least, until none falls: far fewer rounds than there are tip numbers.
    """
    w = count.pairs(graph, side).select(F.col("end").alias("a"), F.col("pivot").alias("b"), (choose2(F.col("b1")) + choose2(F.col("b2"))).alias("n")).where("n > 0")
    near = cut(w.unionByName(w.select(F.col("b").alias("a"), F.col("a").alias("b"), "n")))
    everyone = graph.edges.select(gid(F.col(side.lower()), 0 if side == "U" else 1).alias("a")).distinct()
    now = cut(everyone.join(near.groupBy("a").agg(F.sum("n").alias("tip")), "a", "left").select("a", F.coalesce("tip", F.lit(0)).cast("long").alias("tip")))
    falling = Window.partitionBy("a").orderBy(F.desc("at")).rowsBetween(Window.unboundedPreceding, 0)
    while True:  # tips only fall, so this ends
        levels = near.join(now.select(F.col("a").alias("b"), F.col("tip").alias("at")), "b").groupBy("a", "at").agg(F.sum("n").alias("n"))
        held = levels.select("a", F.least("at", F.sum("n").over(falling)).alias("k")).groupBy("a").agg(F.max("k").alias("k"))
        fresh = cut(now.join(held, "a", "left").select("a", F.coalesce("k", F.lit(0)).cast("long").alias("tip"), (F.col("tip") != F.coalesce("k", F.lit(0))).alias("fell")))
        now = fresh.select("a", "tip")
        if fresh.where("fell").isEmpty():
            return now.select(F.shiftright("a", 1).alias("key"), "tip")


def wing_decomposition(graph: SignedGraph) -> DataFrame:
    """u, v, wing: the greatest k such that the edge is in a subgraph whose edges each have k
    balanced butterflies inside it."""
    left, done, level = cut(graph.edges), None, 0
    for turn in itertools.count(1):  # ends with the last edge
        held = cut(edge_counts(SignedGraph(left)))
        least = held.agg(F.min("balanced")).first()[0]
        if least is None:
            break
        level = max(level, int(least))
        gone = held.where(F.col("balanced") <= level)
        named = gone.select("u", "v", F.lit(level).cast("long").alias("wing"))
        done = _gather(done, named, turn)
        left = cut(left.join(gone.select("u", "v"), ["u", "v"], "left_anti"))
    return graph.edges.select("u", "v", F.lit(0).cast("long").alias("wing")) if done is None else done


def graph_profile(graph: SignedGraph, approx: bool = False) -> DataFrame:
    """One row: sides, edges, density, negatives, greatest degrees, wedges by end side, balanced."""
    e = graph.edges
    n = (lambda c: F.approx_count_distinct(c)) if approx else (lambda c: F.count_distinct(F.col(c)))
    base = e.agg(n("u").alias("n_u"), n("v").alias("n_v"), F.count(F.lit(1)).alias("n_e"), F.coalesce(F.sum(1 - F.col("sign")), F.lit(0)).cast("long").alias("negatives"))
    du, dv = (e.groupBy(c).agg(F.count(F.lit(1)).alias("d")).agg(F.max("d").cast("long").alias(f"max_deg_{c}"), total(choose2(F.col("d"))).alias(w)) for c, w in (("u", "wedges_v_ends"), ("v", "wedges_u_ends")))
    rows = base.crossJoin(du).crossJoin(dv).crossJoin(count.count_wedge_agg(graph))  # one row each
    density = F.round(F.col("n_e") / (F.col("n_u") * F.col("n_v")), 6)
    return rows.select("n_u", "n_v", "n_e", density.alias("density"), "negatives", "max_deg_u", "max_deg_v", "wedges_u_ends", "wedges_v_ends", "balanced")
