"""Counters against the definition, against each other and against worked graphs."""

from __future__ import annotations

import itertools
import random
from collections import Counter

import numpy as np
import pytest

from sbgraph import experiments, graphs, plans
from sbgraph.model import SignedGraph, from_rows, validate
from sbgraph.operators import assign, count, index, measures


def brute(rows):
    e = {(u, v): s for u, v, s in rows}
    us, vs = sorted({u for u, _ in e}), sorted({v for _, v in e})
    total = balanced = 0
    for a, b in itertools.combinations(us, 2):
        for c, d in itertools.combinations(vs, 2):
            if all(k in e for k in ((a, c), (a, d), (b, c), (b, d))):
                total += 1
                balanced += (e[a, c] + e[a, d] + e[b, c] + e[b, d]) % 2 == 0
    return total, balanced


def random_rows(seed, nu=9, nv=7, density=0.6, neg=0.4):
    r = random.Random(seed)
    return [(u, v, int(r.random() >= neg)) for u in range(nu) for v in range(nv) if r.random() < density] or [(0, 0, 1)]


CASES = {
    "random1": random_rows(1),
    "random2": random_rows(2, 12, 4, 0.8),
    "one_edge": [(0, 0, 1)],
    "star": [(u, 0, u % 2) for u in range(6)],
    "path": [(0, 0, 1), (1, 0, 0), (1, 1, 1)],
    "complete_negative": [(u, v, 0) for u in range(4) for v in range(5)],
    "product_signs": [(u, v, int((u % 2) == (v % 3 == 0))) for u in range(4) for v in range(4)],
    "hub": [(0, v, v % 2) for v in range(12)] + [(u, v, (u + v) % 2) for u in range(1, 4) for v in range(0, 12, u)],
}


@pytest.mark.parametrize("name", CASES)
def test_counters_agree_with_the_definition(spark, name):
    rows = CASES[name]
    total, balanced = brute(rows)
    g = from_rows(spark, rows).cached()
    answers = {
        "wedge_priority": count.count_wedge_agg(g),
        "wedge_u": count.count_wedge_agg(g, "U"),
        "wedge_v": count.count_wedge_agg(g, "V"),
        "sql": count.count_pivot_local(g, 3, 2),
        "arrow": count.count_pivot_local(g, 3, 2, form="arrow", workload="restricted"),
        "serial": count.count_serial(g),
        "nosep": count.count_no_separation(g),
    }
    assert {k: d.first()["balanced"] for k, d in answers.items()} == dict.fromkeys(answers, balanced)
    blind = count.count_signblind(g).first()
    assert (blind["total"], blind["balanced"], blind["wasted"]) == (total, balanced, total - balanced)
    s = measures.balance_summary(g).first()
    assert (s["total"], s["balanced"], s["unbalanced"]) == (total, balanced, total - balanced)


@pytest.mark.parametrize("assigner", sorted(assign.ASSIGNERS))
def test_any_assignment_gives_the_total(spark, assigner):
    rows = CASES["random1"]
    g = from_rows(spark, rows).cached()
    for kw in ({"max_load": 5}, {"workload": "exact"}):
        per = count.count_pivot_local(g, 4, 1, assigner, return_="bins", **kw)
        assert sum(r["balanced"] for r in per.collect()) == brute(rows)[1]


def test_empty_graph(spark):
    g = from_rows(spark, [])
    assert count.count_wedge_agg(g).first()["balanced"] == 0
    assert count.count_pivot_local(g, 2).first()["balanced"] == 0
    assert measures.balance_summary(g).first()["ratio"] is None


@pytest.mark.parametrize(("name", "balanced", "total"), [("w1", 16, 36), ("w2", 7, 7), ("w3", 1, 1), ("w4", 4, 4), ("w5", 5, 7)])
def test_worked_graphs(spark, name, balanced, total):
    row = measures.balance_summary(graphs.worked(spark, name)).first()
    assert (row["balanced"], row["total"]) == (balanced, total)


def test_worked_measures(spark):
    w1, w2 = graphs.worked(spark, "w1"), graphs.worked(spark, "w2")
    assert tuple(measures.pattern_census(w1).first()) == (9, 0, 2, 2, 3, 19, 1)
    assert {r["balanced"] for s in "UV" for r in measures.vertex_counts(w1, s).collect()} == {8}
    assert {r["key"]: r["balanced"] for r in measures.vertex_counts(w2).collect()} == {1: 2, 2: 2, 3: 3, 4: 3, 5: 2, 6: 2, 7: 0}
    edges = {(r["u"], r["v"]): r["balanced"] for r in measures.edge_counts(w2).collect()}
    assert sum(edges.values()) == 28 and edges[3, 3] == 1 and edges[7, 6] == 0
    assert tuple(measures.class_split(w2, "U").first()) == (7, 0) and tuple(measures.class_split(w2, "V").first()) == (1, 6)
    assert {r["key"]: r["tip"] for r in measures.tip_decomposition(w2).collect()} == {**dict.fromkeys(range(1, 7), 2), 7: 0}
    wings = sorted(r["wing"] for r in measures.wing_decomposition(w2).collect())
    assert wings == [0] + [1] * 4 + [2] * 12
    assert tuple(measures.pattern_census(graphs.worked(spark, "w5")).first()) == (1,) * 7
    assert measures.is_biclique(w1, [1, 2], [1, 2, 3, 4]) and not measures.is_biclique(w2, [1, 7], [1])


def test_pivot_of_the_trace(spark):
    rows = index.workload(graphs.worked(spark, "w3"), "exact").collect()
    assert sorted(r["load"] for r in rows)[-1] == 2
    per = count.count_pivot_local(graphs.worked(spark, "w3"), 4, 1, return_="bins").collect()
    assert sorted(r["balanced"] for r in per) == [0, 0, 0, 1]


def test_invariants(spark):
    rows = CASES["random2"]
    base = brute(rows)
    flip_all = [(u, v, 1 - s) for u, v, s in rows]
    switch = [(u, v, 1 - s if u == 0 else s) for u, v, s in rows]
    for changed in (flip_all, switch):
        assert count.count_wedge_agg(from_rows(spark, changed)).first()["balanced"] == base[1]
    g = from_rows(spark, rows)
    assert count.count_wedge_agg(g.swapped()).first()["balanced"] == base[1]
    assert sum(r["balanced"] for r in measures.vertex_counts(g).collect()) == 2 * base[1]
    assert sum(r["balanced"] for r in measures.edge_counts(g).collect()) == 4 * base[1]
    assert sum(measures.pattern_census(g).first()) == base[0]
    assert count.count_wedge_agg(index.prune_core(g)).first()["balanced"] == base[1]
    assert count.enumerate_butterflies(g).count() == base[1]
    assert count.enumerate_butterflies(g, balanced=None).count() == base[0]
    assert plans.count_auto(g).first()["balanced"] == base[1]


def test_goldens(spark, sf):
    for name, balanced in (("g1", 374_269), ("g3", 136_706), ("g5", 690), ("g6", 16_767), ("g7", 125_743_247), ("g8", 2_606_902)):
        g = graphs.build(spark, sf, name)
        assert count.count_wedge_agg(g, "U" if name == "g8" else "V").first()["balanced"] == balanced


def test_validation(spark):
    g = from_rows(spark, [(1, 1, 1), (1, 1, 0)])
    assert validate(g.edges)["duplicates"] == 1
    bad = spark.createDataFrame([(None, 1, 1), (1, 2, 7)], g.edges.schema)
    assert validate(SignedGraph(bad).edges) == {"nulls": 1, "signs": 1, "keys": 0, "duplicates": 0}


def test_nothing_moves_behind_the_placement(spark):
    ready = count.prepare(from_rows(spark, CASES["random1"]), 4, "hash")
    edges, lists = count.route_two_hop(ready.ranked, ready.assignment)
    plan = count.bins_sql(edges, lists, 4)._jdf.queryExecution().executedPlan().toString()
    ready.release()
    before = plan.split("shufflepartitionidpassthrough")[0]
    assert "Exchange hashpartitioning" not in before and plan.count("shufflepartitionidpassthrough") >= 2  # edges and lists meet as placed


def test_a_list_goes_to_a_bin_once(spark):
    for bins in (1, 3):
        ready = count.prepare(from_rows(spark, CASES["random2"]), bins)
        _, lists = count.route_two_hop(ready.ranked, ready.assignment)
        held = lists.groupBy("bin", "mid").count().agg({"count": "max"}).first()[0]
        ready.release()
        assert held == 1


@pytest.mark.parametrize("piece", [1, 5, 1 << 20])
def test_pieces_of_any_size(piece):
    """The kernel against plain counting, with lists in several segments and split pivots."""
    r = np.random.default_rng(7)
    mids = np.repeat(np.arange(12), 2)
    ends = [np.unique(r.integers(0, 40, 9)) for _ in mids]
    own = [np.unique(np.concatenate(ends[2 * k : 2 * k + 2])) for k in range(12)]
    signs = [r.integers(0, 2, len(o)) for o in own]
    halves = [(k, own[k][h::2], signs[k][h::2]) for k in range(12) for h in (0, 1)]
    size = np.array([len(h[1]) for h in halves])
    stop = np.cumsum(size)
    lists = count.Lists(np.array([h[0] for h in halves]), stop - size, stop, np.concatenate([h[1] << 1 | h[2] for h in halves]))
    pivot = np.sort(r.integers(12, 42, 80))
    mid, sign = r.integers(0, 14, 80), r.integers(0, 2, 80)
    wanted, wedges = Counter(), 0
    for p, m, s in zip(pivot.tolist(), mid.tolist(), sign.tolist(), strict=True):
        for e, t in zip(own[m].tolist(), signs[m].tolist(), strict=True) if m < 12 else ():
            if e < p:
                wanted[p, e, s == t] += 1
                wedges += 1
    total = sum(n * (n - 1) // 2 for n in wanted.values())
    one = np.ones(80, np.int64)
    assert count.count_edges(lists, pivot, mid, sign, one * 0, one, piece) == (total, wedges)
    parts = [count.count_edges(lists, pivot, mid, sign, one * k, one * 3, piece) for k in range(3)]
    assert tuple(map(sum, zip(*parts, strict=True))) == (total, wedges)


def test_large_codes_are_sorted_by_two_keys():
    pivot, code = np.array([5, 5, 5, 9, 9]), np.array([1 << 61, 3, 1 << 61, 3, 3])
    assert [x.tolist() for x in count._tally(pivot, code)] == [[5, 5, 9], [3, 1 << 61, 3], [1, 2, 2]]


def test_totals_are_decimals(spark):
    g = from_rows(spark, CASES["random1"])
    for d in (count.count_wedge_agg(g), count.count_pivot_local(g, 2), count.count_serial(g), plans.count_auto(g)):
        assert dict(d.dtypes)["balanced"] == "decimal(38,0)"


def test_plans(spark):
    g = from_rows(spark, CASES["random2"])
    plan = plans.choose_plan(g)
    assert plan.method == "wedge_agg" and plan.order in ("U", "V")
    with pytest.raises(ValueError, match="budget"):
        plans.choose_plan(g, budget=1)


def peel(rows, weight):
    """Tip or wing numbers by taking the least member away, one at a time."""
    left, level, out = set(rows), 0, {}
    while left:
        counts = {x: weight(x, left) for x in left}
        level = max(level, min(counts.values()))
        x = min(left, key=lambda y: (counts[y], y))
        out[x] = level
        left.remove(x)
    return out


@pytest.mark.parametrize("name", ["random1", "hub", "one_edge"])
def test_tips_and_wings_against_peeling(spark, name):
    rows = CASES[name]
    g = from_rows(spark, rows)
    for side, at in (("U", 0), ("V", 1)):
        def own(x, left, at=at):
            return brute([r for r in rows if r[at] in left])[1] - brute([r for r in rows if r[at] in left and r[at] != x])[1]

        assert {r["key"]: r["tip"] for r in measures.tip_decomposition(g, side).collect()} == peel({r[at] for r in rows}, own)
    if len(rows) < 30:
        wings = peel(rows, lambda x, left: brute(left)[1] - brute(left - {x})[1])
        assert {(r["u"], r["v"]): r["wing"] for r in measures.wing_decomposition(g).collect()} == {(u, v): w for (u, v, _), w in wings.items()}


def test_local_counters_are_guarded(spark):
    with pytest.raises(ValueError, match="edges"):
        count.count_serial(from_rows(spark, CASES["random1"]), cap=3)


@pytest.mark.parametrize("n", (1, 2, 63, 64, 65, 130, 1000))
def test_every_two_bits_are_compared(n):
    bits = np.array([random.Random(n).random() < 0.4 for _ in range(n)]).astype(np.uint8)
    assert count.unequal_pairs(bits) == int(bits.sum()) * (n - int(bits.sum()))


def test_untold_pairs_are_tested_in_long_lists(spark, monkeypatch):
    monkeypatch.setattr(count, "PACK", 50)
    rows = [(u, v, int((u * v + v // 3) % 4 > 0)) for u in range(3) for v in range(150)] + [(u, v, u % 2) for u in range(3, 20) for v in range(3)]
    g = from_rows(spark, rows).cached()
    s = measures.balance_summary(g).first()
    blind = count.count_signblind(g).first()
    assert (blind["total"], blind["balanced"], blind["wasted"]) == (s["total"], s["balanced"], s["unbalanced"])


def test_baseline_is_compared_however_many_butterflies(spark, monkeypatch):
    """Two users with 15,000 products each: over a hundred million butterflies."""
    rows = spark.range(30_000).selectExpr("id % 2 AS u", "id div 2 AS v", "CAST(id % 3 > 0 AS BYTE) AS sign")
    monkeypatch.setattr(experiments.graphs, "build", lambda *_: SignedGraph(rows))
    got = {r["metric"]: r["value"] for r in experiments.compare_baseline(spark, "", ("g",)).collect() if r["config"] == "signblind"}
    assert got["total"] == 15_000 * 14_999 // 2 and got["balanced"] + got["wasted"] == got["total"]


def test_one_process_counters_hold_no_edge_on_the_driver(spark, monkeypatch):
    rows = CASES["random1"]
    g = from_rows(spark, rows)
    monkeypatch.setattr(type(g.edges), "toPandas", None)
    monkeypatch.setattr(type(spark.sparkContext), "broadcast", None)
    assert {f(g).first()["balanced"] for f in (count.count_serial, count.count_shared)} == {brute(rows)[1]}


def test_shards_of_a_pivot_travel_once_a_bin(spark):
    """A pivot of many more shards than bins."""
    rows = CASES["hub"]
    g = from_rows(spark, rows).cached()
    ready = count.prepare(g, 2, "hash", "restricted", 1)
    most = ready.assignment.groupBy("pivot", "bin").count().agg({"count": "max"}).first()[0]
    found = sum(r["balanced"] for form in ("sql", "arrow") for r in count.count_prepared(ready, 2, form=form).collect())
    ready.release()
    assert most == 1 and found == 2 * brute(rows)[1]


def test_a_heavy_bin_is_counted_in_several_tasks(spark):
    """All load in the first bin of four, as with blocks of pivots."""
    held = spark.createDataFrame([(p, 0, 10) for p in range(20)] + [(p, 1 + p % 3, 0) for p in range(20, 30)], assign.ASSIGNMENT)
    assert count._ways(held, 4, 1) == [4, 1, 1, 1] and count._ways(held, 4, 2) == [8, 2, 2, 2]
    g = graphs.build(spark, "/root/testdata/sf0.001", "g1")
    per = {form: [(r["bin"], r["balanced"], r["wedges"]) for r in count.count_pivot_local(g, 8, 1, "blocks", "restricted", form, "bins", experiments.WHOLE).collect()] for form in ("sql", "arrow")}
    assert per["sql"] == per["arrow"]


def test_worked_examples_read_a_table(spark, sf):
    from sbgraph import queries

    found = queries.registry().queries
    lines = spark.read.parquet(f"{sf}/lineitem.parquet")
    assert found["lpt_example"](spark, sf).agg({"load": "sum"}).first()[0] == lines.count()
    pairs = lines.where("l_quantity = 1").select("l_partkey", "l_suppkey").distinct()
    assert found["wing_w2"](spark, sf).count() == pairs.count()
    assert found["tip_w2"](spark, sf).count() == pairs.select("l_partkey").distinct().count()
    one = {r["metric"]: r["value"] for r in found["x13_worked_examples"](spark, sf).collect() if r["graph"] == "lines_of_1"}
    assert one["total"] == measures.balance_summary(graphs.lines_of(spark, sf, 1)).first()["total"]


def test_bins_filter_list_entries_one_by_one(spark):
    """Lists are exploded before they are tested: a lambda over an array is not compiled."""
    edges = spark.createDataFrame([(0, 3, 1, 1, 0, 2), (0, 3, 2, 1, 0, 2), (0, 3, 1, 1, 1, 2), (0, 3, 2, 1, 1, 2)], "bin int, pivot long, mid long, sign long, shard long, shards long")
    lists = spark.createDataFrame([(0, 1, [1, 4, 6, 9]), (0, 2, [1, 5, 6, 9])], "bin int, mid long, codes array<long>")
    rows = count.bins_sql(edges, lists, 1)
    assert "lambda" not in rows._jdf.queryExecution().toString()
    assert tuple(rows.first())[:3] == (0, 1, 4)  # ends 0 and 2, by two mids each
