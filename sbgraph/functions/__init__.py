"""Column functions of the engine, and their registration for SQL."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.functions import pandas_udf, udtf

from ..schemas import EDGES, TOTAL


def choose2(n: Column) -> Column:
    """n over 2 as a long; exact for n below 4.2e9."""
    n = n.cast("long")
    return F.shiftright(n * (n - 1), 1)


def total(value: Column) -> Column:
    """An exact sum as a decimal."""
    return F.coalesce(F.sum(value.cast(TOTAL)), F.lit(0).cast(TOTAL))


def gid(key: Column, side: int) -> Column:
    """One id space for both sides (U = 0, V = 1); keeps the order of keys within a side."""
    return F.shiftleft(key.cast("long"), 1) + F.lit(side).cast("long")


def higher(a_deg: Column, a_gid: Column, b_deg: Column, b_gid: Column) -> Column:
    """Priority: the larger degree, then the larger id."""
    return (a_deg > b_deg) | ((a_deg == b_deg) & (a_gid > b_gid))


#: Modulus and multiplier of the owner hash (a prime, and its golden section).
PRIME, GOLDEN = 2_147_483_647, 1_327_217_885


def owner(value: Column, parts: int | Column) -> Column:
    """The owner of an id among ``parts``: a multiplicative hash, by its high part."""
    mixed = F.pmod(F.pmod(value.cast("long"), F.lit(PRIME)) * F.lit(GOLDEN), F.lit(PRIME))
    n = parts if isinstance(parts, Column) else F.lit(parts)
    return F.floor(mixed * n / F.lit(PRIME)).cast("int")


def packed(rank: Column, sign: Column) -> Column:
    """An adjacency entry: the rank above one bit of sign."""
    return F.shiftleft(rank, 1) + sign.cast("long")


@pandas_udf(T.LongType())
def balanced_pairs(sign_sum: pd.Series) -> int:
    """Balanced pairs of a list of wedge sign sums (grouped aggregate)."""
    odd = int((sign_sum == 1).sum())
    even = len(sign_sum) - odd
    return odd * (odd - 1) // 2 + even * (even - 1) // 2


@udtf(returnType=T.StructType([T.StructField("left_end", T.LongType()), T.StructField("right_end", T.LongType()), T.StructField("symmetric", T.BooleanType())]))
class WedgesOf:
    """Wedges of one middle vertex from its packed adjacency."""

    def eval(self, adjacency: list[int]):
        for i, a in enumerate(adjacency or []):
            for b in adjacency[i + 1 :]:
                yield min(a >> 1, b >> 1), max(a >> 1, b >> 1), (a & 1) == (b & 1)


@udtf(returnType=EDGES)
class ParseEdge:
    """Edges of a text line ``u v sign``; comments and malformed lines give none."""

    def eval(self, line: str):
        parts = (line or "").replace(",", " ").replace("\t", " ").split()
        if len(parts) >= 3 and not parts[0].startswith(("#", "%")):
            try:
                yield int(parts[0]), int(parts[1]), 1 if float(parts[2]) > 0 else 0
            except ValueError:
                return


def register(spark: SparkSession) -> None:
    """Makes the functions known to SQL."""
    spark.udf.register("balanced_pairs", balanced_pairs)
    spark.udtf.register("wedges_of", WedgesOf)
    spark.udtf.register("parse_edge", ParseEdge)
