"""Cost and accuracy measures of a run."""

from __future__ import annotations

import resource
import time
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..model import SignedGraph
from ..sources import noop
from . import count, index


class PhaseTimer:
    """Seconds per named phase."""

    def __init__(self) -> None:
        self.seconds: dict[str, float] = {}

    @contextmanager
    def phase(self, name: str):
        began = time.perf_counter()
        yield
        self.seconds[name] = self.seconds.get(name, 0.0) + time.perf_counter() - began

    def frame(self, spark: SparkSession, run: str = "run") -> DataFrame:
        return spark.createDataFrame([(run, k, v) for k, v in self.seconds.items()], "run string, phase string, seconds double")


def run_with_breakdown(graph: SignedGraph, bins: int, threads: int, assigner: str = "lpt_scalable", workload: str = "full") -> tuple[int, PhaseTimer, DataFrame]:
    """The pivot-partitioned counter phase by phase: total, timer, per-bin rows."""
    timer = PhaseTimer()
    with timer.phase("io"):
        edges = graph.edges.persist()
        noop(edges)
    with timer.phase("index"):
        ready = count.prepare(SignedGraph(edges, graph.name), bins, assigner, workload)
        assignment = ready.assignment.persist()
        noop(ready.ranked)
        noop(assignment)
    with timer.phase("exchange"):
        routed = [x.repartitionById(bins, F.col("bin")).persist() for x in count.route_two_hop(ready.ranked, assignment)]
        for x in routed:
            noop(x)
    with timer.phase("count"):
        per = count.bins_arrow(*routed, bins, threads).persist()
        noop(per)
    with timer.phase("reduce"):
        found = int(per.agg(F.coalesce(F.sum("balanced"), F.lit(0))).first()[0])
    every = graph.spark.range(bins).select(F.col("id").cast("int").alias("bin")).join(per, "bin", "left").fillna(0)
    kept = graph.spark.createDataFrame(every.collect(), every.schema)  # ``bins`` rows
    ready.release()
    for x in (per, *routed, assignment, edges):
        x.unpersist()
    return found, timer, kept


def straggler_ratio(per_bin: DataFrame, column: str = "nanos") -> float | None:
    """Greatest over least value of the bins; None when a bin is empty."""
    low, high = per_bin.agg(F.min(column), F.max(column)).first()
    return high / low if low else None


def improvement_pct(naive: float, aware: float) -> float:
    return (naive - aware) / naive * 100


def speedup(times: DataFrame, base: str) -> DataFrame:
    """graph, config, value: seconds of the base configuration over those of each."""
    first = times.where(F.col("config") == base).select("graph", F.col("value").alias("base"))
    return times.join(first, "graph").select("graph", "config", (F.col("base") / F.col("value")).alias("value"))


def exchange_volume(graph: SignedGraph, assignment: DataFrame) -> DataFrame:
    """bin, edges, entries, bytes: what the counter's two exchanges send to a bin.

    The rows are those that the counter routes: an edge is 17 bytes (two ids and a sign), a list
    entry 8, and a list goes to a bin once.
    """
    ids = index.compact_ids(index.degrees(graph)).select(F.col("gid").alias("__gid"), "rank_id", F.col("gid"), F.col("deg"))
    by_rank = assignment.join(ids.select("__gid", "rank_id"), F.col("pivot") == F.col("__gid")).drop("pivot", "__gid").withColumnRenamed("rank_id", "pivot")
    edges, lists = count.route_two_hop(index.ranked(graph, ids.select("gid", "deg", "rank_id")), by_rank)
    hop = edges.groupBy("bin").agg(F.count(F.lit(1)).alias("edges"))
    sent = lists.groupBy("bin").agg(F.sum(F.size("codes")).cast("long").alias("entries"))
    rows = hop.join(sent, "bin", "full").select("bin", F.coalesce("edges", F.lit(0)).cast("long").alias("edges"), F.coalesce("entries", F.lit(0)).cast("long").alias("entries"))
    return rows.withColumn("bytes", F.col("edges") * 17 + F.col("entries") * 8)


def peak_memory() -> int:
    """Peak resident KB of this process."""
    return resource.getrusage(resource.RUSAGE_SELF).ru_maxrss


def _stages(spark: SparkSession) -> list:
    """What the status store knows of all stages so far."""
    store = spark.sparkContext._jsc.sc().statusStore()
    gateway = spark.sparkContext._gateway
    none = spark.sparkContext._jvm.java.util.ArrayList()
    stages = store.stageList(none, False, False, gateway.new_array(gateway.jvm.double, 0), none)
    return [stages.apply(k) for k in range(stages.size())]


def shuffle_bytes(spark: SparkSession) -> int:
    """Shuffle bytes written by all stages so far."""
    return sum(x.shuffleWriteBytes() for x in _stages(spark))


def jvm_peak_bytes(spark: SparkSession) -> int:
    """The greatest execution memory that the tasks of one stage took in the JVM (never added to Python's)."""
    return max((x.peakExecutionMemory() for x in _stages(spark)), default=0)


def assert_exact(found: int, expected: int) -> None:
    if found != expected:
        raise AssertionError(f"{found} balanced butterflies, expected {expected}")


def throughput(work: int, seconds: float) -> float:
    return work / seconds if seconds else float("inf")
