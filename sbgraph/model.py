"""The signed bipartite graph: a lazy edge table and what follows from it."""

from __future__ import annotations

from dataclasses import dataclass
from functools import cached_property

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .functions import gid
from .schemas import EDGES, MAX_KEY


@dataclass(frozen=True)
class SignedGraph:
    """``edges`` has u, v, sign (0 negative, 1 positive), one row per pair."""

    edges: DataFrame
    name: str = "graph"

    @property
    def spark(self) -> SparkSession:
        return self.edges.sparkSession

    @cached_property
    def tagged(self) -> DataFrame:
        """Edges in the common id space: gu, gv, sign."""
        return self.edges.select(gid(F.col("u"), 0).alias("gu"), gid(F.col("v"), 1).alias("gv"), F.col("sign").cast("byte").alias("sign"))

    @cached_property
    def directed(self) -> DataFrame:
        """Every edge from both ends: mid, end, sign."""
        t = self.tagged
        return t.select(F.col("gu").alias("mid"), F.col("gv").alias("end"), "sign").unionByName(t.select(F.col("gv").alias("mid"), F.col("gu").alias("end"), "sign"))

    @cached_property
    def vertices(self) -> DataFrame:
        """gid, side, key, deg of every vertex."""
        deg = self.directed.groupBy(F.col("mid").alias("gid")).agg(F.count(F.lit(1)).alias("deg"))
        return deg.select("gid", F.col("gid").bitwiseAND(F.lit(1).cast("long")).cast("byte").alias("side"), F.shiftright("gid", 1).alias("key"), "deg")

    def swapped(self) -> SignedGraph:
        """Sides exchanged."""
        return SignedGraph(self.edges.select(F.col("v").alias("u"), F.col("u").alias("v"), "sign"), f"{self.name}_swapped")

    def filtered(self, condition: str) -> SignedGraph:
        return SignedGraph(self.edges.where(condition), self.name)

    def cached(self) -> SignedGraph:
        return SignedGraph(self.edges.persist(), self.name)


def from_rows(spark: SparkSession, rows: list[tuple[int, int, int]], name: str = "rows") -> SignedGraph:
    """A small graph given inline."""
    return SignedGraph(spark.createDataFrame(rows, EDGES), name)


def validate(edges: DataFrame) -> dict[str, int]:
    """Counts of rows that no builder may hand on (all must be 0)."""
    bad = lambda c: F.coalesce(F.sum(F.when(c, 1).otherwise(0)), F.lit(0))
    pairs = edges.groupBy("u", "v").agg(F.count(F.lit(1)).alias("n"))
    row = edges.agg(
        bad(F.col("u").isNull() | F.col("v").isNull() | F.col("sign").isNull()).alias("nulls"),
        bad(~F.col("sign").isin(0, 1)).alias("signs"),
        bad((F.col("u") < 0) | (F.col("v") < 0) | (F.col("u") >= MAX_KEY) | (F.col("v") >= MAX_KEY)).alias("keys"),
    ).first()
    return row.asDict() | {"duplicates": pairs.where("n > 1").count()}
