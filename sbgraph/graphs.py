"""Signed graphs on the given tables, and the worked graphs."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .ingest import resolve_conflicts, sign_from_predicate, sign_from_rating, sign_random
from .model import SignedGraph, from_rows
from .sources import table

NAMES = {"g1": "part_supp_returns", "g2": "cust_supp_returns", "g3": "cust_part_qty", "g4": "cust_brand_qty", "g5": "user_type_value", "g6": "user_propkey_err", "g7": "vec_dim_sign", "g8": "doc_token_quality"}
#: Codes of event types.
TYPE_CODES = {"click": 1, "error": 2, "purchase": 3, "signup": 4, "view": 5}
KEEP = ["u", "v", "sign", "ts", "k1", "k2"]


def _lines(spark: SparkSession, sf: str) -> DataFrame:
    return table(spark, sf, "lineitem").select("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_quantity", "l_returnflag", F.col("l_shipdate").alias("ts"), F.col("l_orderkey").cast("long").alias("k1"), F.col("l_linenumber").cast("long").alias("k2"))


def _with_customer(spark: SparkSession, sf: str) -> DataFrame:
    orders = table(spark, sf, "orders").select("o_orderkey", F.col("o_custkey").alias("u"))
    return _lines(spark, sf).join(orders, F.col("l_orderkey") == F.col("o_orderkey"))


def interactions(spark: SparkSession, sf: str, graph: str) -> DataFrame:
    """u, v, sign, ts, k1, k2 of a graph before conflicts are resolved (g1 to g6)."""
    returned = F.col("l_returnflag") != "R"
    if graph == "g1":
        rows = sign_from_predicate(_lines(spark, sf).withColumn("u", F.col("l_partkey")).withColumn("v", F.col("l_suppkey")), returned)
    elif graph == "g2":
        rows = sign_from_predicate(_with_customer(spark, sf).withColumn("v", F.col("l_suppkey")), returned)
    elif graph == "g3":
        rows = sign_from_rating(_with_customer(spark, sf).withColumn("v", F.col("l_partkey")), "l_quantity", value=25)
    elif graph == "g4":
        part = table(spark, sf, "part").select("p_partkey", F.regexp_extract("p_brand", "([0-9]+)", 1).cast("long").alias("v"))
        rows = sign_from_rating(_with_customer(spark, sf).join(part, F.col("l_partkey") == F.col("p_partkey")), "l_quantity", value=25)
    elif graph in ("g5", "g6"):
        events = table(spark, sf, "events").select(F.col("user_id").alias("u"), "event_type", "value", "props", F.col("ts").cast("timestamp").alias("ts"), F.col("event_id").cast("long").alias("k1"), F.lit(0).cast("long").alias("k2"))
        if graph == "g5":
            code = F.coalesce(*[F.when(F.col("event_type") == k, F.lit(c)) for k, c in TYPE_CODES.items()]).cast("long")
            rows = sign_from_rating(events.withColumn("v", code), "value", value=10)
        else:
            rows = sign_from_predicate(events.withColumn("v", F.get_json_object("props", "$.k").cast("long")), F.col("event_type") != "error")
    else:
        raise ValueError(f"no interactions for {graph}")
    return rows.select(F.col("u").cast("long"), F.col("v").cast("long"), "sign", "ts", "k1", "k2").where("u IS NOT NULL AND v IS NOT NULL")


def vector_signs(spark: SparkSession, sf: str) -> DataFrame:
    """Complete graph of vectors and dimensions, signed by the coordinate."""
    rows = table(spark, sf, "embeddings").select(F.col("vec_id").cast("long").alias("u"), F.posexplode("embedding").alias("v", "x"))
    return rows.select("u", F.col("v").cast("long").alias("v"), (F.col("x") >= 0).cast("byte").alias("sign"))


def document_tokens(spark: SparkSession, sf: str) -> DataFrame:
    """doc_id, token, sign: tokens of labelled documents; the sign is the label's."""
    labels = table(spark, sf, "labels").select("doc_id", "quality")
    docs = table(spark, sf, "documents").select("doc_id", "text").join(labels, "doc_id")
    words = docs.select(F.col("doc_id").alias("u"), F.explode(F.array_distinct(F.regexp_extract_all(F.lower("text"), F.lit("([a-zà-ÿ]+)"), F.lit(1)))).alias("token"), (F.col("quality") == 1).cast("byte").alias("sign"))
    return words.groupBy("u", "token").agg(F.max("sign").alias("sign"))


def build(spark: SparkSession, sf: str, graph: str) -> SignedGraph:
    """One of g1 to g8.  The token key of g8 is a hash; only equality of tokens matters."""
    if graph == "g7":
        edges = vector_signs(spark, sf)
    elif graph == "g8":
        edges = document_tokens(spark, sf).select("u", F.shiftrightunsigned(F.xxhash64("token"), 2).alias("v"), "sign")
    else:
        edges = resolve_conflicts(interactions(spark, sf, graph))
    return SignedGraph(edges, NAMES[graph])


def lines_of(spark: SparkSession, sf: str, quantity: int) -> SignedGraph:
    """The part of g1 whose lines are of one quantity: a sparse graph with few butterflies."""
    rows = _lines(spark, sf).where(F.col("l_quantity") == quantity)
    rows = sign_from_predicate(rows.withColumn("u", F.col("l_partkey")).withColumn("v", F.col("l_suppkey")), F.col("l_returnflag") != "R")
    return SignedGraph(resolve_conflicts(rows.select(*KEEP).where("u IS NOT NULL AND v IS NOT NULL")), f"{NAMES['g1']}_of_{quantity}")


def quantity_loads(spark: SparkSession, sf: str) -> DataFrame:
    """pivot, load: the lines of each quantity."""
    return table(spark, sf, "lineitem").where("l_quantity IS NOT NULL").groupBy(F.col("l_quantity").cast("long").alias("pivot")).agg(F.count(F.lit(1)).alias("load"))


def random_signs(graph: SignedGraph, neg_pct: int = 30, seed: int = 42) -> SignedGraph:
    return SignedGraph(sign_random(graph.edges, neg_pct, seed).select("u", "v", "sign"), f"{graph.name}_neg{neg_pct}")


#: The edges of the worked graph of tips and wings.
W2 = [(ord(e[0]) - 96, int(e[1]), int(e[2] == "+")) for e in "a1- a2+ b1- b2+ c1- c2+ c3- c4- d3- d4- d5+ d6- e5+ e6- f5+ f6- g6+".split()]


def worked(spark: SparkSession, name: str) -> SignedGraph:
    """Worked graphs w1 (users and products), w2 (tips and wings), w3 (one butterfly), w4, w5 (single butterflies side by side)."""
    if name == "w1":
        signs = ["+++-", "++++", "-+++", "--++"]
        rows = [(u, v, int(c == "+")) for u, line in enumerate(signs, 1) for v, c in enumerate(line, 1)]
    elif name == "w2":
        rows = W2
    elif name == "w3":
        rows = [(2, 5, 0), (2, 8, 0), (7, 5, 0), (7, 8, 0)]
    else:
        blocks = {"w4": ["++++", "+-+-", "----", "-++-"], "w5": ["++++", "----", "-++-", "--++", "-+-+", "-+++", "---+"]}[name]
        rows = [(2 * k + p // 2, 2 * k + p % 2, int(c == "+")) for k, b in enumerate(blocks) for p, c in enumerate(b)]
    return from_rows(spark, rows, name)
