"""Choice of a counting plan from degree sums."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import choose2, total
from ..model import SignedGraph
from ..operators import count, index
from ..schemas import TOTAL

#: Bytes that a plan may shuffle before it is refused.
SHUFFLE_BUDGET = 100 * 10**12
#: Bytes of a combined pair row, of an edge through all shuffles of the index, and of a list entry.
PAIR_BYTES, EDGE_BYTES, ENTRY_BYTES = 24, 100, 8
#: What the index's further stages cost before any row moves, as bytes (measured: about two
#: seconds against wedges at some 10**9 bytes a second).
STAGES = 2 * 10**9
#: Wedges per edge from which the priority rule is looked at: only hubs on both sides bring it down.
HUBS = 64


@dataclass(frozen=True)
class PlanChoice:
    method: str
    order: str
    wedges: int
    bins: int
    bytes: int


def plan_costs(graph: SignedGraph) -> DataFrame:
    """One row: edges, vertices, wedges with ends on U and with ends on V; degree sums only."""
    n, pairs = F.count(F.lit(1)), total(choose2(F.col("d")))
    side = lambda mid, *what: graph.edges.groupBy(mid).agg(n.alias("d")).agg(*what)
    us = side("u", n.alias("n_u"), F.coalesce(F.sum("d"), F.lit(0)).alias("edges"), pairs.alias("v_ends"))
    return us.crossJoin(side("v", n.alias("n_v"), pairs.alias("u_ends")))  # one row each


def choose_plan(graph: SignedGraph, per_task: int = 200_000_000, budget: int = SHUFFLE_BUDGET, tasks: int | None = None) -> PlanChoice:
    """The method and order that move the fewest bytes; raises beyond the shuffle budget.

    Ends on one side need no index, so they win ties against the priority rule, whose wedges
    are at most the sum of the smaller degrees over the edges.  Wedges combine by pair of ends
    in every task before they move; the pivot-partitioned counter moves lists instead, behind
    an index.
    """
    c = {k: int(v) for k, v in plan_costs(graph).first().asDict().items()}
    tasks = tasks or int(graph.spark.conf.get("spark.sql.shuffle.partitions"))
    order, wedges, ends = min((("V", c["v_ends"], c["n_v"]), ("U", c["u_ends"], c["n_u"])), key=lambda x: x[1])
    if wedges > HUBS * max(1, c["edges"]):
        least = int(index.orient(graph).agg(F.coalesce(F.sum("lo_deg"), F.lit(0))).first()[0])
        if least < wedges:
            order, wedges, ends = "priority", least, max(c["n_u"], c["n_v"])
    bins = max(8, -(-wedges // per_task))
    combined = PAIR_BYTES * min(wedges, tasks * (ends * (ends - 1) // 2)) + (EDGE_BYTES * c["edges"] if order == "priority" else 0)
    local = STAGES + EDGE_BYTES * c["edges"] + ENTRY_BYTES * min(wedges, 2 * bins * c["edges"])
    method, moved = ("wedge_agg", combined) if combined <= local else ("pivot_local", local)
    if moved > budget:
        raise ValueError(f"the cheapest plan moves {moved} bytes, more than the budget of {budget}")
    return PlanChoice(method, order if method == "wedge_agg" else "priority", wedges, bins, moved)


def count_auto(graph: SignedGraph) -> DataFrame:
    """The balanced total by the chosen plan, run at once."""
    held = graph.cached()  # the costs and the count both read the edges
    plan = choose_plan(held)
    rows = count.count_wedge_agg(held, plan.order) if plan.method == "wedge_agg" else count.count_pivot_local(held, bins=plan.bins, workload="restricted", form="arrow")
    found = rows.first()["balanced"]
    held.edges.unpersist()
    return graph.spark.createDataFrame([(found,)], f"balanced {TOTAL}")
