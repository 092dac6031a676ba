"""The experiment workloads; each returns experiment, graph, config, metric, value."""

from __future__ import annotations

import math
import os
import subprocess
import sys
import time
from collections.abc import Iterable
from pathlib import Path

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .. import graphs
from ..ingest import sign_sweep
from ..model import SignedGraph
from ..operators import assign, count, index, measures, metrics
from ..schemas import RESULT

#: Bins of the twelve configurations; bins times threads stay near one number.
CONFIGS = (1, 2, 3, 4, 6, 8, 12, 16, 24, 32, 48, 64)
UNITS = 12
ALL_GRAPHS = ("g1", "g2", "g3", "g4", "g5", "g6", "g7", "g8")
#: Metrics that do not depend on the machine or the moment.
DETERMINISTIC = ("balanced", "total", "wasted", "sum_min", "over_limit", "straggler_wedges", "bytes", "ratio", "symmetric", "asymmetric", "max_tip", "max_wing")
#: No pivot is split: per-bin work is that of the assignment alone.
WHOLE = 1 << 62


class Rows:
    """Collects result rows."""

    def __init__(self, spark: SparkSession, experiment: str) -> None:
        self.spark, self.experiment, self.rows = spark, experiment, []

    def add(self, graph: str, config: str, metric: str, value: float | None) -> None:
        self.rows.append((self.experiment, graph, config, metric, None if value is None else float(value)))

    def frame(self) -> DataFrame:
        return self.spark.createDataFrame(self.rows, RESULT)


def _held(spark: SparkSession, sf: str, names: Iterable[str]) -> Iterable[tuple[str, SignedGraph]]:
    for name in names:
        graph = graphs.build(spark, sf, name).cached()
        graph.edges.count()
        yield name, graph
        graph.edges.unpersist()


def _timed(rows: DataFrame) -> tuple[tuple, float]:
    began = time.perf_counter()
    found = rows.first()
    return found, time.perf_counter() - began


def profile_table(spark: SparkSession, sf: str, names=ALL_GRAPHS) -> DataFrame:
    """The dataset table."""
    out = Rows(spark, "profile_table")
    for name, graph in _held(spark, sf, names):
        for metric, value in measures.graph_profile(graph).first().asDict().items():
            out.add(name, "-", metric, value)
    return out.frame()


def compare_counters(spark: SparkSession, sf: str, names=ALL_GRAPHS[:7], threads: int = 8, serial_limit: int = 30_000_000) -> DataFrame:
    """Serial, shared-memory and pivot-partitioned counters: count seconds and speed-ups."""
    out = Rows(spark, "compare_counters")
    for name, graph in _held(spark, sf, names):
        work = index.work_bounds(graph).first()["sum_min"]
        secs, found = {}, {}
        if work <= serial_limit:
            found["serial"], secs["serial"] = _timed(count.count_serial(graph))
        else:
            out.add(name, "serial", "over_limit", work)
        found["shared"], secs["shared"] = _timed(count.count_shared(graph, threads))
        found["pivot_local"], timer, _ = metrics.run_with_breakdown(graph, threads, 1, workload="restricted")
        secs["pivot_local"] = timer.seconds["count"]
        for method, n in found.items():
            out.add(name, method, "balanced", n if method == "pivot_local" else n["balanced"])
        for method, s in secs.items():
            out.add(name, method, "seconds", s)
            out.add(name, method, "speedup", s / secs["pivot_local"])
        out.add(name, "all", "sum_min", work)
    return out.frame()


def compare_baseline(spark: SparkSession, sf: str, names=("g1", "g2", "g3", "g5", "g6")) -> DataFrame:
    """Pivot-partitioned against the sign-blind counter."""
    out = Rows(spark, "compare_baseline")
    for name, graph in _held(spark, sf, names):
        began = time.perf_counter()
        found, timer, _ = metrics.run_with_breakdown(graph, 8, 1, workload="restricted")
        out.add(name, "pivot_local", "count_seconds", timer.seconds["count"])
        out.add(name, "pivot_local", "total_seconds", time.perf_counter() - began)
        out.add(name, "pivot_local", "balanced", found)
        row, seconds = _timed(count.count_signblind(graph))
        out.add(name, "signblind", "count_seconds", seconds)  # the edges are held, as they are for the other
        for metric in ("total", "balanced", "wasted"):
            out.add(name, "signblind", metric, row[metric])
    return out.frame()


def phase_breakdown(spark: SparkSession, sf: str, names=("g1", "g3", "g6"), configs=CONFIGS) -> DataFrame:
    """Seconds per phase, straggler ratios, volume and memory over the configurations, with speed-ups over the first."""
    out = Rows(spark, "phase_breakdown")
    for name, graph in _held(spark, sf, names):
        base = None
        for bins in configs:
            threads = max(1, UNITS // bins)
            found, timer, per = metrics.run_with_breakdown(graph, bins, threads)
            config, total = f"{bins}x{threads}", sum(timer.seconds.values())
            base = base or total
            for phase, s in timer.seconds.items():
                out.add(name, config, phase, s)
            out.add(name, config, "speedup", base / total)
            out.add(name, config, "balanced", found)
            out.add(name, config, "straggler_time", metrics.straggler_ratio(per, "nanos"))
            out.add(name, config, "straggler_wedges", metrics.straggler_ratio(per, "wedges"))
            out.add(name, config, "peak_kb", per.agg({"peak_kb": "max"}).first()[0])
            out.add(name, config, "jvm_peak_bytes", metrics.jvm_peak_bytes(spark))
    return out.frame()


def straggler_grid(spark: SparkSession, sf: str, names=("g1", "g3", "g6"), configs=CONFIGS, workload: str = "full") -> DataFrame:
    """Greatest over least wedges per bin, a work count that does not depend on the machine."""
    out = Rows(spark, "straggler_grid")
    for name, graph in _held(spark, sf, names):
        for bins in configs:
            per = count.count_pivot_local(graph, bins, 1, workload=workload, return_="bins", max_load=WHOLE)
            out.add(name, str(bins), "straggler_wedges", metrics.straggler_ratio(per, "wedges"))
    return out.frame()


def volume_vs_bins(spark: SparkSession, sf: str, names=("g1", "g6"), configs=CONFIGS) -> DataFrame:
    """Bytes that the counter sends to all bins, and the shuffle bytes of a run; both grow with the bins."""
    out = Rows(spark, "volume_vs_bins")
    for name, graph in _held(spark, sf, names):
        for bins in configs:
            held = assign.assign_lpt(index.workload(graph), bins)
            out.add(name, str(bins), "bytes", metrics.exchange_volume(graph, held).agg({"bytes": "sum"}).first()[0])
            before = metrics.shuffle_bytes(spark)
            count.count_pivot_local(graph, bins, 1, "lpt", form="arrow", max_load=WHOLE)
            out.add(name, str(bins), "shuffle_bytes", metrics.shuffle_bytes(spark) - before)
    return out.frame()


def executor_scaling(spark: SparkSession, sf: str, name: str = "g1", executors=(1, 2, 4), memory_mb: int = 1024, limit_s: int = 900) -> DataFrame:
    """Count seconds on local clusters of one-core executors (one host: loopback network only)."""
    out = Rows(spark, "executor_scaling")
    code = (
        "import sys,tempfile\nfrom pyspark.sql import SparkSession\n"
        "k,sf,name,mb=int(sys.argv[1]),sys.argv[2],sys.argv[3],sys.argv[4]\n"
        "s=SparkSession.builder.master(f'local-cluster[{k},1,{mb}]').config('spark.executor.memory',mb+'m').config('spark.ui.enabled','false').config('spark.sql.shuffle.partitions','8').config('spark.checkpoint.dir',tempfile.mkdtemp()).getOrCreate()\n"
        "from sbgraph import graphs\nfrom sbgraph.operators import metrics\n"
        "found,timer,per=metrics.run_with_breakdown(graphs.build(s,sf,name),8,1)\n"
        "print('RESULT',found,timer.seconds['exchange'],timer.seconds['count'],metrics.shuffle_bytes(s),per.agg({'peak_kb':'max'}).first()[0],metrics.jvm_peak_bytes(s))\n"
    )
    root = str(Path(__file__).resolve().parents[2])
    names = ("balanced", "exchange_seconds", "count_seconds", "shuffle_bytes", "peak_kb", "jvm_peak_bytes")
    for k in executors:
        try:
            run = subprocess.run([sys.executable, "-c", code, str(k), sf, name, str(memory_mb)], capture_output=True, text=True, timeout=limit_s, check=False, env=os.environ | {"PYTHONPATH": os.pathsep.join([root, os.environ.get("PYTHONPATH", "")])})
            line = next((x for x in run.stdout.splitlines() if x.startswith("RESULT")), None)
        except subprocess.TimeoutExpired:
            line = None
        if line is None:  # the run stays in the table
            out.add(name, f"loopback_{k}", "failed", None)
            continue
        for metric, value in zip(names, line.split()[1:], strict=True):
            out.add(name, f"loopback_{k}", metric, float(value))
    return out.frame()


def flat_vs_hybrid(spark: SparkSession, sf: str, names=("g1", "g3"), bins: int = 4, threads: int = 3) -> DataFrame:
    """Bins with sub-bins against as many bins of one thread."""
    out = Rows(spark, "flat_vs_hybrid")
    for name, graph in _held(spark, sf, names):
        for config, b, t in (("hybrid", bins, threads), ("flat", bins * threads, 1)):
            found, timer, _ = metrics.run_with_breakdown(graph, b, t)
            out.add(name, config, "count_seconds", timer.seconds["count"])
            out.add(name, config, "exchange_seconds", timer.seconds["exchange"])
            out.add(name, config, "balanced", found)
    return out.frame()


def partitioning_ablation(spark: SparkSession, sf: str, names=("g1", "g3", "g6"), bins: int = 8) -> DataFrame:
    """Straggler ratio by wedges of blocks and of load-aware assignment, by workload estimate."""
    out = Rows(spark, "partitioning_ablation")
    for name, graph in _held(spark, sf, names):
        ratios = {}
        for config, assigner, work in (("blocks", "blocks", "full"), ("lpt_full", "lpt", "full"), ("lpt_restricted", "lpt", "restricted"), ("lpt_exact", "lpt", "exact")):
            per = count.count_pivot_local(graph, bins, 1, assigner, work, return_="bins", max_load=WHOLE)
            ratios[config] = metrics.straggler_ratio(per, "wedges") or math.inf
            out.add(name, config, "straggler_wedges", ratios[config])
            if math.isfinite(ratios["blocks"]):
                out.add(name, config, "improvement_pct", metrics.improvement_pct(ratios["blocks"], ratios[config]))
    return out.frame()


def deterministic(rows: DataFrame) -> DataFrame:
    """What of an experiment's result does not depend on the machine."""
    return rows.where(F.col("metric").isin(*DETERMINISTIC))


def sign_distribution(spark: SparkSession, sf: str, names=("g1", "g3"), neg_pcts=(10, 30, 50, 70, 90)) -> DataFrame:
    """Seconds and counts over the share of negative edges; time stays flat, counts vary."""
    out = Rows(spark, "sign_distribution")
    for name, graph in _held(spark, sf, names):
        for pct, signed in sign_sweep(graph, neg_pcts).items():
            found, timer, _ = metrics.run_with_breakdown(signed, 8, 1, workload="restricted")
            out.add(name, f"neg{pct}", "balanced", found)
            out.add(name, f"neg{pct}", "count_seconds", timer.seconds["count"])
            out.add(name, f"neg{pct}", "exchange_seconds", timer.seconds["exchange"])
    return out.frame()


def class_separation(spark: SparkSession, sf: str, names=("g5", "g6")) -> DataFrame:
    """Two-class counters against pairing all wedges."""
    out = Rows(spark, "class_separation")
    for name, graph in _held(spark, sf, names):
        for config, run in (("separated", count.count_wedge_agg), ("not_separated", count.count_no_separation)):
            row, seconds = _timed(run(graph))
            out.add(name, config, "seconds", seconds)
            out.add(name, config, "balanced", row["balanced"])
    return out.frame()


def worked_examples(spark: SparkSession, sf: str) -> DataFrame:
    """Small graphs of the lines of one quantity, and assignments of the quantities' loads."""
    out = Rows(spark, "worked_examples")
    for q in (1, 2, 3, 4, 5):
        row = measures.balance_summary(graphs.lines_of(spark, sf, q)).first()
        out.add(f"lines_of_{q}", "-", "balanced", row["balanced"])
        out.add(f"lines_of_{q}", "-", "total", row["total"])
    loads = graphs.quantity_loads(spark, sf)
    for name, assigner in (("greedy", assign.assign_lpt), ("blocks", assign.assign_blocks)):
        row = assign.assignment_stats(assigner(loads, 3), 3).first()
        out.add("loads", name, "ratio", row["greatest"] / row["least"] if row["least"] else None)
    return out.frame()


def applications(spark: SparkSession, sf: str, names=("g5", "g6")) -> DataFrame:
    """Class splits by end side, and the greatest tip and wing numbers."""
    out = Rows(spark, "applications")
    chosen = [("w2", graphs.worked(spark, "w2")), *_held(spark, sf, names)]
    for name, graph in chosen:
        for ends in ("U", "V"):
            for metric, value in measures.class_split(graph, ends).first().asDict().items():
                out.add(name, f"ends_{ends}", metric, value)
        out.add(name, "U", "max_tip", measures.tip_decomposition(graph).agg({"tip": "max"}).first()[0])
    out.add("w2", "-", "max_wing", measures.wing_decomposition(graphs.worked(spark, "w2")).agg({"wing": "max"}).first()[0])
    return out.frame()


ALL = (profile_table, compare_counters, compare_baseline, phase_breakdown, straggler_grid, volume_vs_bins, executor_scaling, flat_vs_hybrid, partitioning_ablation, sign_distribution, class_separation, worked_examples, applications)
