"""Assignment, ingest rules, metrics, SQL and streaming."""

from __future__ import annotations

import datetime as dt
import subprocess
import sys
from pathlib import Path

import pytest
from pyspark.sql import functions as F

from sbgraph import experiments, functions, graphs, ingest, sources, sql, streaming
from sbgraph.model import SignedGraph, from_rows
from sbgraph.operators import assign, count, index, metrics
from sbgraph.schemas import INTERACTIONS


def test_assignment_example():
    got = assign.greedy(list(enumerate((15, 12, 9, 7, 6, 4))), 3)
    sums = [sum(w for _, b, w in got if b == k) for k in range(3)]
    assert sorted(sums) == [16, 18, 19] and round(max(sums) / min(sums), 2) == 1.19


def test_assigners_cover_all_pivots(spark):
    work = spark.createDataFrame([(k, k % 7) for k in range(50)], "pivot long, load long")
    for f in assign.ASSIGNERS.values():
        rows = f(work, 4).collect()
        assert sorted(r["pivot"] for r in rows) == list(range(50)) and {r["bin"] for r in rows} <= set(range(4))
    assert assign.assignment_stats(assign.assign_lpt(work, 4), 4).first()["ratio"] < 1.1
    with pytest.raises(ValueError, match="lpt_scalable"):
        assign.assign_lpt(work, 4, cap=10)
    hot = assign.split_hot(spark.createDataFrame([(1, 0, 100)], assign.ASSIGNMENT), 4, 10)
    assert hot.count() == 10 and hot.agg(F.max("load")).first()[0] <= 10 and {r["bin"] for r in hot.collect()} == {0, 1, 2, 3}
    cut = assign.split_hot(work.withColumn("bin", F.lit(1)).select("pivot", "bin", "load"), 4, 2)
    assert cut.groupBy("pivot").agg(F.count(F.lit(1)).alias("n"), F.max("shards").alias("s")).where("n <> s").count() == 0


def rows(spark):
    t = dt.datetime(2020, 1, 1)
    day = dt.timedelta(days=1)
    data = [(1, 1, 1, t, 1, 0), (1, 1, 0, t + day, 2, 0), (1, 2, 0, t, 1, 0), (1, 2, 1, t, 1, 0), (2, 1, 1, t, 5, 0), (2, 1, 1, t + day, 6, 0), (2, 1, 0, t + 2 * day, 7, 0)]
    return spark.createDataFrame(data, INTERACTIONS)


@pytest.mark.parametrize(("policy", "expected"), [("latest", {(1, 1): 0, (1, 2): 1, (2, 1): 0}), ("earliest", {(1, 1): 1, (1, 2): 0, (2, 1): 1}), ("majority", {(1, 1): 1, (1, 2): 1, (2, 1): 1}), ("sum", {(2, 1): 1}), ("drop_conflicts", {})])
def test_conflict_policies(spark, policy, expected):
    assert {(r["u"], r["v"]): r["sign"] for r in ingest.resolve_conflicts(rows(spark), policy).collect()} == expected


def test_duplicates_flips_and_as_of(spark):
    assert tuple(ingest.duplicate_profile(rows(spark)).first()) == (7, 3, 3, 3, 1)
    assert {(r["u"], r["v"]): r["flips"] for r in ingest.sign_flips(rows(spark)).collect()} == {(1, 1): 1, (1, 2): 1, (2, 1): 1}
    as_of = ingest.sign_as_of(rows(spark), F.lit("2020-01-02").cast("timestamp"))
    assert {(r["u"], r["v"]): r["sign"] for r in as_of.collect()}[2, 1] == 1


def test_ratings(spark):
    data = spark.createDataFrame([(1, 1.0), (1, 3.0), (2, 10.0), (2, 2.0)], "u long, r double")
    positive = lambda **kw: sum(r["sign"] for r in ingest.sign_from_rating(data, "r", **kw).collect())
    assert [positive(threshold="fixed", value=2), positive(threshold="mean"), positive(threshold="median"), positive(threshold="user_mean")] == [3, 1, 2, 2]


def test_sign_sets_are_nested(spark, sf):
    g = graphs.build(spark, sf, "g5")
    swept = {p: {(r["u"], r["v"]) for r in s.edges.where("sign = 0").collect()} for p, s in ingest.sign_sweep(g).items()}
    assert swept[10] <= swept[30] <= swept[50] <= swept[70] <= swept[90]


@pytest.mark.parametrize("fmt", ["parquet", "orc", "json", "csv"])
def test_sources_round_trip(spark, tmp_path, fmt):
    g = from_rows(spark, [(1, 2, 1), (3, 4, 0)])
    sources.write_edges(g.edges, str(tmp_path / "e"), fmt)
    assert sorted(map(tuple, sources.read_edges(spark, str(tmp_path / "e"), fmt).collect())) == [(1, 2, 1), (3, 4, 0)]


def test_text_source_and_audit(spark, tmp_path):
    (tmp_path / "e.txt").write_text("# c\n% c\n1 2 1\n3\t4 0\n\n")
    e = sources.read_edges(spark, str(tmp_path / "e.txt"), "text")
    assert sorted(map(tuple, e.collect())) == [(1, 2, 1), (3, 4, 0)]
    audit = sources.ingest_audit(e).first()
    assert (audit["n_rows"], audit["files"]) == (2, 1)
    assert audit["checksum"] == sources.ingest_audit(e.repartition(3)).first()["checksum"] != sources.ingest_audit(e.limit(1)).first()["checksum"]


def test_bucketed_table(spark):
    sources.save_bucketed(from_rows(spark, [(1, 2, 1)]).edges, "bucketed_edges", "v", 2)
    assert sources.read_catalog(spark, "bucketed_edges").count() == 1
    spark.sql("DROP TABLE bucketed_edges")


def test_compact_ids_are_priorities(spark, sf):
    g = graphs.build(spark, sf, "g6")
    got = index.compact_ids(index.degrees(g)).orderBy("rank_id").collect()
    assert [r["rank_id"] for r in got] == list(range(len(got)))
    assert [(r["deg"], r["gid"]) for r in got] == sorted((r["deg"], r["gid"]) for r in got)
    assert sorted(r["rank_id"] for r in index.compact_ids(index.degrees(g), "hash").collect()) == list(range(len(got)))


def test_volume_grows_with_bins(spark, sf):
    g = graphs.build(spark, sf, "g6").cached()
    sizes = [metrics.exchange_volume(g, assign.assign_lpt(index.workload(g), b)).agg(F.sum("bytes")).first()[0] for b in (1, 2, 4, 8)]
    assert sizes == sorted(sizes) and sizes[0] < sizes[-1]


def test_breakdown_and_scalars(spark, sf):
    found, timer, per = metrics.run_with_breakdown(graphs.build(spark, sf, "g5"), 2, 2)
    assert found == 690 and set(timer.seconds) == {"io", "index", "exchange", "count", "reduce"}
    assert per.agg(F.sum("balanced")).first()[0] == 690
    assert round(metrics.improvement_pct(5.673, 2.895), 2) == 48.97
    assert metrics.peak_memory() > 0 and metrics.throughput(10, 2) == 5
    assert metrics.shuffle_bytes(spark) > 0 and metrics.jvm_peak_bytes(spark) >= 0


def test_order_by_ranges(spark):
    rows = spark.createDataFrame([((7 * k) % 101, k % 5) for k in range(101)], "k long, x long").repartition(7)
    got = index.in_order(rows, ["x", "k"], ("k",), ("x",), 6).collect()
    wanted, running = sorted(((r["k"], r["x"]) for r in got), key=lambda r: (-r[1], r[0])), 0
    by_place = {r["place"]: r for r in got}
    for place, (k, x) in enumerate(wanted):
        running += k
        assert (by_place[place]["k"], by_place[place]["x"], by_place[place]["sum_k"]) == (k, x, running)
    assert index.in_order(rows.limit(0), ["k"]).count() == 0


def test_sql_surface(spark):
    g = graphs.worked(spark, "w1")
    sql.create_views(g, "w1_")
    assert spark.sql(sql.balanced_count_sql("w1_edges")).first()["balanced"] == 16
    assert spark.sql("SELECT sum(b1 * (b1 - 1) DIV 2 + b2 * (b2 - 1) DIV 2) FROM w1_pairs").first()[0] == 16
    assert [tuple(r) for r in spark.sql("SELECT * FROM parse_edge('7,8,-1')").collect()] == [(7, 8, 0)]
    assert spark.sql("SELECT count(*) FROM wedges_of(array(2L, 5L, 7L))").first()[0] == 3
    lists = count.wedges(g, "U").groupBy("pivot", "end").agg(functions.balanced_pairs("pos").alias("n"))
    assert lists.agg(F.sum("n")).first()[0] == 16


def test_stream_equals_batch(spark, sf):
    events = sources.table(spark, sf, "events")
    batch = streaming.resolve_stream_batch(streaming.event_edges(events))
    live = streaming.replay(spark, f"{sf}/events.parquet*", streaming.latest_signs)
    assert sorted(map(tuple, live.collect())) == sorted(map(tuple, batch.collect()))
    assert streaming.without_replays(streaming.event_edges(events.unionByName(events))).count() == events.count()
    assert streaming.session_graphs(streaming.event_edges(events)).agg(F.sum("edges")).first()[0] == events.count()


def test_incremental_total(spark):
    start = [(u, v, (u + v) % 2) for u in range(5) for v in range(4)]
    live = streaming.IncrementalTotal(from_rows(spark, start), fold=2)
    schema = "u long, v long, sign byte"
    for batch in ([(0, 0, 1), (7, 1, 0), (7, 2, 1)], [(1, 1, None), (2, 3, 1)], [(1, 1, 0), (0, 0, None)]):
        live.apply(spark.createDataFrame(batch, schema))
        assert live.total == count.count_wedge_agg(SignedGraph(live.edges)).first()["balanced"]
    with pytest.raises(ValueError, match="twice"):
        live.apply(spark.createDataFrame([(1, 1, 1), (1, 1, 0)], schema))


def test_incremental_total_by_time(spark):
    """A late row of an earlier time changes nothing, and the order inside a batch is (ts, k1, k2, sign)."""
    t, hour = dt.datetime(2020, 1, 1), dt.timedelta(hours=1)
    live = streaming.IncrementalTotal(from_rows(spark, []))
    schema = "u long, v long, sign byte, ts timestamp, k1 long, k2 long"
    square = [(u, v, 1, t + hour, 1, 0) for u in (1, 2) for v in (1, 2)]
    for batch, wanted in ((square, 1), ([(1, 1, 0, t, 1, 0)], 1), ([(1, 1, 1, t + 2 * hour, 1, 0), (1, 1, 0, t + 2 * hour, 2, 0)], 0), ([(2, 1, 0, t + 3 * hour, 1, 0)], 1)):
        assert live.apply(spark.createDataFrame(batch, schema)) == wanted


def test_stream_state_drops_late_rows(spark, tmp_path):
    """Update mode over three files: an older row inside the lateness changes nothing, one behind it is dropped."""
    t, minute = dt.datetime(2020, 1, 1, 12), dt.timedelta(minutes=1)
    files = [[(1, t, "view"), (2, t, "view")], [(1, t - 30 * minute, "error"), (3, t + 300 * minute, "view")], [(4, t - 200 * minute, "error"), (2, t + 301 * minute, "error")]]
    for k, rows in enumerate(files):
        data = [(10 * k + i, when, user, kind, 1.0, '{"k": 5}') for i, (user, when, kind) in enumerate(rows)]
        spark.createDataFrame(data, "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string").coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    got = streaming.replay(spark, str(tmp_path / "in"), streaming.latest_signs_state, "update").collect()
    last = {r["u"]: r["sign"] for r in sorted(got, key=lambda r: r["batch"])}
    assert last == {1: 1, 2: 0, 3: 1} or last == {1: 1, 2: 0, 3: 1, 4: 0}  # the order in which files are read decides about 4
    table = streaming.LatestTable(spark, str(tmp_path / "latest"), 4)
    schema = "u long, v long, sign byte, ts timestamp, k1 long, k2 long"
    for number, rows in enumerate([[(1, 1, 1, t, 1, 0), (2, 1, 1, t, 2, 0)], [(1, 1, 0, t + minute, 3, 0)], [(2, 1, 0, t - minute, 4, 0)]]):
        for _ in range(2):  # replayed batches replace themselves
            table.merge(spark.createDataFrame(rows, schema), number)
    assert sorted(map(tuple, table.edges().collect())) == [(1, 1, 0), (2, 1, 1)]


def test_stream_replays_are_dropped(spark, sf, tmp_path):
    events = sources.table(spark, sf, "events").limit(200)
    for _ in range(2):
        events.coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
    kept = streaming.replay(spark, str(tmp_path / "in"), lambda e: streaming.without_replays(e).select("event_id", "u"), "append")
    assert kept.count() == 200 == kept.select("event_id").distinct().count()


def test_stream_beside_a_static_table(spark, sf):
    users = spark.createDataFrame([(k, f"user{k}") for k in range(5)], "u long, name string")
    got = streaming.replay(spark, f"{sf}/events.parquet*", lambda e: streaming.with_attributes(e, users).groupBy("name").count())
    batch = streaming.with_attributes(streaming.event_edges(sources.table(spark, sf, "events")), users).groupBy("name").count()
    assert sorted(map(str, got.collect())) == sorted(map(str, batch.collect()))


def test_times_and_ratios(spark):
    times = spark.createDataFrame([("g", "a", 4.0), ("g", "b", 2.0)], "graph string, config string, value double")
    assert {r["config"]: r["value"] for r in metrics.speedup(times, "a").collect()} == {"a": 1.0, "b": 2.0}
    bins = spark.createDataFrame([(0, 10), (1, 5)], "bin int, nanos long")
    assert metrics.straggler_ratio(bins) == 2 and metrics.straggler_ratio(bins.withColumn("nanos", F.col("bin"))) is None


def test_failed_runs_stay_in_the_table(spark, sf):
    got = {r["config"]: r for r in experiments.executor_scaling(spark, sf, "g5", (1,)).collect() if r["metric"] in ("balanced", "failed")}
    assert got["loopback_1"]["value"] == 690
    late = experiments.executor_scaling(spark, sf, "g5", (1,), limit_s=1).collect()
    assert [(r["metric"], r["value"]) for r in late] == [("failed", None)]


def test_queries_are_registered_without_a_session():
    """In a process of its own: names and SQL are there before a session is."""
    code = "import __spark_entry__ as e; q, o = e.queries(), e.oracle_sql(); assert len(q) > 200 and set(o) <= set(q)"
    root = Path(__file__).resolve().parent.parent
    subprocess.run([sys.executable, "-c", code], check=True, cwd=root)
