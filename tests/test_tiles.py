"""Tiles against the join of wedges, forced on small graphs."""

from __future__ import annotations

import random

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from sbgraph import queries
from sbgraph.model import from_rows
from sbgraph.operators import count, measures, tiles


def graph(spark, seed, nu, nv, density):
    r = random.Random(seed)
    return from_rows(spark, [(u, v, int(r.random() < 0.6)) for u in range(nu) for v in range(nv) if r.random() < density or v == 0]).cached()


@pytest.mark.parametrize("dense", (0, 3, 1 << 40))
def test_tiles_count_like_the_join(spark, monkeypatch, dense):
    """All wedges sorted, some mids as matrices, all as matrices; several blocks and pieces."""
    g = graph(spark, dense, 40, 17, 0.3)
    want = {s: count.pairs(g, s).agg(F.sum(F.expr("b1*(b1-1) div 2")).alias("b"), F.sum(F.expr("b2*(b2-1) div 2")).alias("c")).first() for s in "UV"}
    edges = {(r["u"], r["v"]): r["balanced"] for r in measures.edge_counts(g, "V").collect()}
    sweep = {tuple(r) for r in queries._sweep(g).collect()}
    for name, value in (("FAR", 0), ("LEAST", 50), ("DENSE", dense), ("PIECE", 40), ("CELLS", 64)):
        monkeypatch.setattr(tiles, name, value)
    for s in "UV":
        row = tiles.class_counts(g, s, F.col("sign")).first()
        assert (row["symmetric"], row["asymmetric"]) == tuple(want[s])
    assert {(r["u"], r["v"]): r["balanced"] for r in measures.edge_counts(g, "V").collect()} == edges
    assert {tuple(r) for r in queries._sweep(g).collect()} == sweep


def test_many_wedges_are_not_shuffled(spark, monkeypatch):
    g = graph(spark, 1, 30, 9, 0.5)
    want = count.count_wedge_agg(g, "U").first()["balanced"]
    monkeypatch.setattr(tiles, "FAR", 0)
    monkeypatch.setattr(count, "pairs", None)  # what formed a row per wedge
    assert count.count_wedge_agg(g, "U").first()["balanced"] == want


@pytest.mark.parametrize("near", (3, 50, 1 << 17))
def test_dense_tiles_are_summed_in_small_pieces(monkeypatch, near):
    """Where all wedges lie in matrices, with several layers; exact against the plain pairs."""
    monkeypatch.setattr(tiles, "NEAR", near)
    r = np.random.default_rng(near)
    sides = []
    for ends in (19, 26):
        end, mid = np.nonzero(r.random((ends, 6)) < 0.8)
        sides.append((end, mid, r.integers(0, 4, len(end)).astype(np.uint8)))
    m = tiles.Meeting(*(tiles.Block.of(*x) for x in sides))
    assert not len(m.edge)
    a, b = ({(int(e), int(v)): int(k) for e, v, k in zip(*x, strict=True)} for x in sides)
    want = [0] * 4
    for i in range(19):
        for j in range(26):
            odd = [a[i, v] ^ b[j, v] for v in range(6) if (i, v) in a and (j, v) in b]
            for k in range(2):
                n = sum(x >> k & 1 for x in odd)
                want[2 * k] += (len(odd) - n) * (len(odd) - n - 1) // 2
                want[2 * k + 1] += n * (n - 1) // 2
    monkeypatch.setattr(tiles, "CELLS", None)  # passes over many cells at once
    assert tiles._counts(m, 2) == want


def test_split_follows_from_the_other_side(spark, monkeypatch):
    """Many ends, few mids: the wedges of the other side are formed."""
    g = graph(spark, 2, 60, 4, 0.6)
    want = count.pairs(g, "U").agg(F.sum(F.expr("b1*(b1-1) div 2")), F.sum(F.expr("b2*(b2-1) div 2"))).first()
    formed, plain = [], count.wedges
    monkeypatch.setattr(count, "wedges", lambda x, order="priority": formed.append(order) or plain(x, order))
    assert tuple(measures.class_split(g, "U").first()) == tuple(want) and "U" not in formed


@pytest.mark.parametrize("word", (1, 7, 64))
def test_bruteforce_tests_quads_where_blocks_meet(spark, monkeypatch, word):
    g = graph(spark, 3, 37, 13, 0.4)
    held = {(r["u"], r["v"]): r["sign"] for r in g.edges.collect()}
    four = [[held.get(x) for x in ((a, c), (a, d), (b, c), (b, d))] for a in range(37) for b in range(a) for c in range(13) for d in range(c)]
    found = [sum(x) for x in four if None not in x]
    for name, value in (("LEAST", 50), ("WORD", word), ("TESTS", 64)):
        monkeypatch.setattr(tiles, name, value)
    rows = count.count_bruteforce(g)
    assert "NestedLoopJoin" not in rows._jdf.queryExecution().toString() and "Cartesian" not in rows._jdf.queryExecution().toString()
    assert tuple(rows.first()) == (len(found), sum(x % 2 == 0 for x in found))


@pytest.mark.parametrize("balanced", (True, False, None))
def test_enumeration_forms_the_fewer_wedges(spark, monkeypatch, balanced):
    """Many users of few types: the pairs of users are far more than the pairs of types."""
    g = graph(spark, 4, 60, 4, 0.6)
    held = {(r["u"], r["v"]): r["sign"] for r in g.edges.collect()}
    want = set()
    for a, b, c, d in ((a, b, c, d) for b in range(60) for a in range(b) for d in range(4) for c in range(d)):
        signs = [held.get(x) for x in ((a, c), (a, d), (b, c), (b, d))]
        if None not in signs and balanced in (None, sum(signs) % 2 == 0):
            want.add((a, b, c, d, 4 - sum(signs)))
    formed, plain = [], count.wedges
    monkeypatch.setattr(count, "wedges", lambda x, order="priority": formed.append(order) or plain(x, order))
    for h, swap in ((g, False), (g.swapped(), True)):
        rows = [tuple(r) for r in count.enumerate_butterflies(h, balanced).collect()]
        assert len(rows) == len(want) and {(r[2], r[3], r[0], r[1], r[4]) if swap else r for r in rows} == want
    assert formed == ["V", "U"]


def test_blocks_are_packed_small():
    """An edge of a block with a mid for every second edge takes under four bytes, and comes back as it was."""
    r = np.random.default_rng(5)
    block = tiles.Block.of(r.integers(0, 4_000, 200_000) * 2 + 10**9, r.integers(0, 100_000, 200_000) * 2 + 1, r.integers(0, 2, 200_000))
    blob = block.pack()
    back = tiles.Block.unpack(pa.py_buffer(blob))
    for name in ("ends", "mids", "start", "end", "mask"):
        assert np.array_equal(getattr(back, name), getattr(block, name)) and getattr(back, name).dtype == getattr(block, name).dtype
    assert len(blob) < 4 * 200_000
    empty = tiles.Block.of(*(np.zeros(0, np.int64),) * 3)
    assert len(tiles.Block.unpack(pa.py_buffer(empty.pack())).start) == 1


@pytest.mark.parametrize("balanced", (True, None))
@pytest.mark.parametrize("ranges", (1, 2, 5))
def test_enumeration_over_ranges(spark, monkeypatch, balanced, ranges):
    """Every two ranges of middle vertices meet once, and a range meets itself."""
    g = graph(spark, 5, 150, 4, 0.7)
    held = {(r["u"], r["v"]): r["sign"] for r in g.edges.collect()}
    users = {(c, d): [(a, held[a, c], held[a, d]) for a in range(150) if (a, c) in held and (a, d) in held] for d in range(4) for c in range(d)}
    want = sorted((a, b, c, d, 4 - s1 - s2 - t1 - t2) for (c, d), rows in users.items() for a, s1, s2 in rows for b, t1, t2 in rows if a < b and (balanced is None or (s1 + s2 + t1 + t2) % 2 == 0))
    for name, value in (("RANGES", ranges), ("WORTH", 1)):
        monkeypatch.setattr(count, name, value)
    assert sorted(tuple(r) for r in count.enumerate_butterflies(g, balanced).collect()) == want


@pytest.mark.parametrize("size", (1, 7, 1000))
def test_lists_of_a_key_meet(monkeypatch, size):
    """Lists cut small, keys that go on over batches, all against plain pairs."""
    for name, value in (("LIST", 4), ("GROUP", 2), ("MEET", 3), ("PIECE", 5)):
        monkeypatch.setattr(count, name, value)
    r = random.Random(size)
    rows = sorted((1, high, r.choice((0, 1, 2)), m) for high in (2, 3, 9) for m in r.sample(range(100), 30 if high != 3 else 1))
    names = ["low", "high", "p", "m"]
    cut = lambda t: iter(pa.concat_tables([t.slice(k, size) for k in range(0, len(t), size)]).to_batches())
    kinds = [pa.int64(), pa.int64(), pa.int32(), pa.int64()]
    wedges = pa.table([pa.array(x, k) for x, k in zip(zip(*rows, strict=True), kinds, strict=True)], names=names)
    lists = [x for b in count.listed(cut(wedges), 0) for x in b.to_pylist()]
    assert sorted((x["low"], x["high"], x["p"], m) for x in lists for m in x["mids"]) == rows and max(len(x["mids"]) for x in lists) <= 4
    sent = sorted(({k: x[k] for k in ("low", "high", "p", "mids")} | {"odd": x["p"] % 2, "meets": k} for x in lists for k in (0, 1)), key=lambda x: (x["low"], x["high"], x["odd"], x["meets"]))
    schema = pa.schema([("low", pa.int64()), ("high", pa.int64()), ("odd", pa.int32()), ("meets", pa.int32()), ("p", pa.int32()), ("mids", pa.list_(pa.int64()))])
    met = [x for b in count.met_lists(cut(pa.Table.from_pylist(sent, schema))) for x in b.to_pylist()]
    got = sorted((x["high"], a, b, x["negatives"]) for x in met for a in x["first"] for b in x["second"] if a < b)
    assert got == sorted((h, a, b, 4 - p - q) for _, h, p, a in rows for _, i, q, b in rows if h == i and a < b and (p + q) % 2 == 0)


def test_enumerated_rows_are_written_small(spark, tmp_path):
    """Under half a byte a row: values repeat in runs that the files hold once."""
    g = graph(spark, 6, 3000, 3, 1.0)
    count.enumerate_butterflies(g).write.parquet(str(tmp_path / "rows"))
    rows = spark.read.parquet(str(tmp_path / "rows")).count()
    assert rows == count.count_wedge_agg(g, "V").first()["balanced"]
    assert sum(f.stat().st_size for f in (tmp_path / "rows").glob("*.parquet")) < rows // 2
