"""SQL surface: views and query texts."""

from __future__ import annotations

from .functions import register
from .model import SignedGraph
from .operators import count, index


def create_views(graph: SignedGraph, prefix: str = "") -> None:
    """Views ``edges``, ``oriented`` and ``pairs`` of a graph, and the functions."""
    register(graph.spark)
    graph.edges.createOrReplaceTempView(f"{prefix}edges")
    index.orient(graph).createOrReplaceTempView(f"{prefix}oriented")
    count.pairs(graph).createOrReplaceTempView(f"{prefix}pairs")


def balanced_count_sql(view: str = "edges") -> str:
    """A query for the balanced total of a view with u, v, sign."""
    return f"""
        SELECT CAST(coalesce(sum(CAST(b1 * (b1 - 1) / 2 + b2 * (b2 - 1) / 2 AS DECIMAL(38, 0))), 0) AS BIGINT) AS balanced
        FROM (SELECT sum(CASE WHEN a.sign = b.sign THEN 1 ELSE 0 END) AS b1, sum(CASE WHEN a.sign <> b.sign THEN 1 ELSE 0 END) AS b2
              FROM {view} a JOIN {view} b ON a.u = b.u AND a.v < b.v GROUP BY a.v, b.v) AS p"""
