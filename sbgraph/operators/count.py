"""Counters of balanced butterflies.

A butterfly is balanced when its number of negative edges is even.  Every counter but
the sign-blind ones separates the wedges between two ends by class (equal or different
signs): two wedges of one class close a balanced butterfly, so a pair of ends with b1
and b2 wedges holds C(b1,2) + C(b2,2) of them.
"""

from __future__ import annotations

import time
from collections.abc import Iterator
from dataclasses import dataclass
from decimal import Decimal

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import choose2, higher, owner, packed, total
from ..model import SignedGraph
from ..schemas import TOTAL
from . import index, tiles
from .assign import ASSIGNERS, split_hot

#: Adjacency entries per row: a longer list is several rows, so no array is unbounded.
CHUNK = 1 << 16
#: Edges that the serial and shared-memory counters may hold in one process (24 bytes each), and
#: list entries that a thread takes at a time.
LOCAL_EDGES, SHARE = 40_000_000, 1 << 18


def _answer(pairs: DataFrame) -> DataFrame:
    return pairs.agg(total(choose2(F.col("b1")) + choose2(F.col("b2"))).alias("balanced"))


# --- wedge aggregation -------------------------------------------------------------


def wedges(graph: SignedGraph, order: str = "priority") -> DataFrame:
    """pivot, end, mid, pos (sign sum 0..2).

    ``priority``: the pivot outranks mid and end; ``U`` / ``V``: ends on that side.
    """
    if order in ("U", "V"):
        mid, end = ("gv", "gu") if order == "U" else ("gu", "gv")
        t = graph.tagged
        a = t.select(F.col(mid).alias("mid"), F.col(end).alias("pivot"), F.col("sign").alias("s1"))
        b = t.select(F.col(mid).alias("mid"), F.col(end).alias("end"), F.col("sign").alias("s2"))
        joined = a.join(b, "mid").where("end < pivot")
    else:
        o = index.orient(graph)
        a = o.select(F.col("lo").alias("mid"), F.col("hi").alias("pivot"), F.col("hi_deg").alias("pd"), F.col("sign").alias("s1"))
        b = o.select(F.col("lo").alias("mid"), F.col("hi").alias("end"), F.col("hi_deg").alias("ed"), F.col("sign").alias("s2")).unionByName(o.select(F.col("hi").alias("mid"), F.col("lo").alias("end"), F.col("lo_deg").alias("ed"), F.col("sign").alias("s2")))
        joined = a.join(b, "mid").where(higher(F.col("pd"), F.col("pivot"), F.col("ed"), F.col("end")))
    return joined.select("pivot", "end", "mid", (F.col("s1") + F.col("s2")).cast("int").alias("pos"))


def pairs(graph: SignedGraph, order: str = "priority") -> DataFrame:
    """pivot, end, b1 (equal signs), b2 (different signs); combined before the shuffle."""
    same = F.when(F.col("pos") != 1, 1).otherwise(0)
    return wedges(graph, order).groupBy("pivot", "end").agg(F.sum(same).cast("long").alias("b1"), F.sum(1 - same).cast("long").alias("b2"))


def count_wedge_agg(graph: SignedGraph, order: str = "priority") -> DataFrame:
    """One row ``balanced``: self-join on the middle vertex and two-class counters.

    With ends on one side and many wedges, the tasks that form wedges count them too.
    """
    if order in tiles.SIDES:
        held = graph.cached()
        if tiles.wedges_of(held, order) > tiles.FAR:
            return tiles.class_counts(held, order, F.col("sign")).agg(total(F.col("symmetric") + F.col("asymmetric")).alias("balanced"))
        held.edges.unpersist()
    return _answer(pairs(graph, order))


# --- pivot-partitioned counting ----------------------------------------------------
#
# Edges and lists speak of ranks (dense ids in the order of priority), so an end is below
# a pivot when its rank is smaller; a list entry is the rank above one bit of sign.


def adjacency(ranked: DataFrame, chunk: int = CHUNK) -> DataFrame:
    """mid, codes: a vertex's neighbours, in rows of about ``chunk`` entries each."""
    side = lambda mid, deg, end: ranked.select(F.col(mid).alias("mid"), F.col(deg).alias("d"), packed(F.col(end), F.col("sign")).alias("code"))
    both = side("lo", "lo_deg", "hi").unionByName(side("hi", "hi_deg", "lo"))
    part = F.pmod(F.xxhash64("code"), F.ceil(F.col("d") / chunk))
    return both.groupBy("mid", part.cast("int").alias("part")).agg(F.collect_list("code").alias("codes")).select("mid", "codes")


def route_one_hop(ranked: DataFrame, assignment: DataFrame) -> DataFrame:
    """Edges at the bins of their pivots: bin, pivot, mid, sign, shard, shards."""
    split = "shard" in assignment.columns
    own = assignment.select(F.col("pivot").alias("hi"), "bin", *((F.col(c).cast("long") if split else F.lit(n).cast("long")).alias(c) for c, n in (("shard", 0), ("shards", 1))))
    return ranked.join(own, "hi").select("bin", F.col("hi").alias("pivot"), F.col("lo").alias("mid"), "sign", "shard", "shards")


def route_two_hop(ranked: DataFrame, assignment: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Edges at their bins, and the lists that the bins need: bin, mid, codes.

    A middle vertex's list goes to a bin once, however many of the bin's pivots meet there,
    and is cut at the greatest of them.
    """
    edges = route_one_hop(ranked, assignment)
    # By mid once, with the session's number of tasks: little data here is much work behind it.
    parts = int(ranked.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    need = edges.groupBy("bin", "mid").agg(F.max("pivot").alias("top")).repartition(parts, "mid")
    below = F.filter("codes", lambda c: F.shiftright(c, 1) < F.col("top"))
    lists = need.join(adjacency(ranked), "mid").select("bin", "mid", below.alias("codes"))
    return edges, lists.where(F.size("codes") > 0)


BINS = "bin int, balanced decimal(38,0), wedges long, nanos long, peak_kb long"


def bins_sql(edges: DataFrame, lists: DataFrame, bins: int) -> DataFrame:
    """Per-bin counts with built-in operators; nothing moves behind the placement of edges and lists."""
    met = edges.repartitionById(bins, F.col("bin")).join(lists.repartitionById(bins, F.col("bin")), ["bin", "mid"])
    # Exploded first: a lambda over an array is not compiled.
    flat = met.select("bin", "pivot", "sign", "shard", "shards", F.explode("codes").alias("code")).where(F.shiftright("code", 1) < F.col("pivot"))
    flat = flat.where((F.col("shards") == 1) | (F.pmod(F.xxhash64(F.shiftright("code", 1)), F.col("shards")) == F.col("shard")))
    same = F.when(F.col("code").bitwiseAND(F.lit(1).cast("long")) == F.col("sign"), 1).otherwise(0)
    held = flat.groupBy("bin", "pivot", F.shiftright("code", 1).alias("end")).agg(F.sum(same).cast("long").alias("b1"), F.sum(1 - same).cast("long").alias("b2"))
    none = F.lit(None).cast("long")
    return held.groupBy("bin").agg(total(choose2(F.col("b1")) + choose2(F.col("b2"))).alias("balanced"), F.sum(F.col("b1") + F.col("b2")).cast("long").alias("wedges"), F.first(none).alias("nanos"), F.first(none).alias("peak_kb"))


#: Wedges that a thread sorts at a time.
PIECE = 1 << 20


@dataclass
class Lists:
    """The lists of a bin, one behind the other: segments sorted by middle vertex."""

    mid: np.ndarray
    start: np.ndarray
    stop: np.ndarray
    codes: np.ndarray


def _tally(pivot: np.ndarray, code: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Distinct (pivot, code) with their numbers, by pivot and code; pivots arrive in order."""
    place = np.cumsum(np.concatenate([[0], (pivot[1:] != pivot[:-1]).astype(np.int64)]))
    span = int(code.max()) + 1
    if (int(place[-1]) + 1) * span < 1 << 62:  # both in one number
        key = np.sort(place * span + code)
        first = np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]]))
        names = pivot[np.searchsorted(place, key[first] // span)]
        return names, key[first] % span, np.diff(np.append(first, len(key)))
    order = np.lexsort((code, place))
    pivot, code = pivot[order], code[order]
    first = np.flatnonzero(np.concatenate([[True], (pivot[1:] != pivot[:-1]) | (code[1:] != code[:-1])]))
    return pivot[first], code[first], np.diff(np.append(first, len(code)))


def _pairs_of(n: np.ndarray) -> int:
    return int((n * (n - 1) // 2).sum())


def count_edges(lists: Lists, pivot: np.ndarray, mid: np.ndarray, sign: np.ndarray, shard: np.ndarray, shards: np.ndarray, piece: int = PIECE) -> tuple[int, int]:
    """Balanced butterflies and wedges of edges that come by pivot.

    Wedges are gathered and sorted by pivot, end and class in pieces; what a piece holds of
    its last pivot is carried on as counts.
    """
    low, high = np.searchsorted(lists.mid, mid, "left"), np.searchsorted(lists.mid, mid, "right")
    many = high - low
    edge = np.repeat(np.arange(len(pivot)), many)
    segment = np.arange(len(edge)) - np.repeat(np.cumsum(many) - many, many) + np.repeat(low, many)
    size = (lists.stop - lists.start)[segment]
    until = np.cumsum(size)
    balanced = wedges = at = 0
    last, codes, counts = None, np.zeros(0, np.int64), np.zeros(0, np.int64)
    while at < len(edge):
        to = max(at + 1, int(np.searchsorted(until, (until[at - 1] if at else 0) + piece, "right")))
        n = size[at:to]
        place = np.arange(int(n.sum())) + np.repeat(lists.start[segment[at:to]] - np.cumsum(n) + n, n)
        own = np.repeat(edge[at:to], n)
        code, p, at = lists.codes[place], pivot[own], to
        keep = code >> 1 < p
        if int(shards.max()) > 1:
            mixed = ((code >> 1).astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(33)).astype(np.int64)
            keep &= mixed % shards[own] == shard[own]
        code, p = (code ^ sign[own])[keep], p[keep]  # equal signs end in 0, different ones in 1
        if not len(code):
            continue
        wedges += len(code)
        names, code, n = _tally(p, code)
        if names[0] == last:
            head = int(np.searchsorted(names, last, "right"))
            codes, back = np.unique(np.concatenate([codes, code[:head]]), return_inverse=True)
            counts = np.bincount(back, weights=np.concatenate([counts, n[:head]])).astype(np.int64)
            names, code, n = names[head:], code[head:], n[head:]
        if len(names):
            balanced += _pairs_of(counts)
            tail = int(np.searchsorted(names, names[-1], "left"))
            balanced += _pairs_of(n[:tail])
            last, codes, counts = names[-1], code[tail:], n[tail:]
    return balanced + _pairs_of(counts), wedges


def bins_arrow(edges: DataFrame, lists: DataFrame, bins: int, threads: int) -> DataFrame:
    """Per-bin counts with an Arrow kernel that also reports time and memory.

    A task holds one bin: its lists, which all threads read, and its edges.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import resource
        from concurrent.futures import ThreadPoolExecutor

        lists_, flat_, bin_ = [], [], None
        for batch in batches:
            if not batch.num_rows:
                continue
            bin_ = batch.column(0)[0].as_py()
            is_list = pa.array(batch.column(1).to_numpy() == 0)
            held, flat = batch.filter(is_list), batch.filter(pc.invert(is_list))
            if held.num_rows:
                own = held.column(7)
                lists_.append((held.column(2).to_numpy(), np.diff(own.offsets.to_numpy()).astype(np.int64), own.flatten().to_numpy(zero_copy_only=False)))
            if flat.num_rows:
                flat_.append(np.stack([flat.column(k).to_numpy() for k in range(2, 7)]))
        if bin_ is None:
            return
        began = time.perf_counter_ns()
        mid, size, codes = (np.concatenate(x) for x in zip(*lists_, strict=True)) if lists_ else (np.zeros(0, np.int64),) * 3
        order, stop = np.argsort(mid, kind="stable"), np.cumsum(size)
        held = Lists(mid[order], (stop - size)[order], stop[order], codes)
        found = [(0, 0)]
        if flat_:
            rows = np.concatenate(flat_, axis=1)
            pivot, mid, sign, shard, shards = rows[:, np.argsort(rows[0], kind="stable")]
            heads = np.flatnonzero(np.concatenate([[True], pivot[1:] != pivot[:-1]]))
            cuts = np.unique(heads[np.linspace(0, len(heads), 4 * threads, endpoint=False).astype(int)])
            parts = [slice(a, b) for a, b in zip(cuts, [*cuts[1:], len(pivot)], strict=True)] if threads > 1 else [slice(None)]
            with ThreadPoolExecutor(threads) as pool:
                found = list(pool.map(lambda k: count_edges(held, pivot[k], mid[k], sign[k], shard[k], shards[k]), parts))
        nanos, peak = time.perf_counter_ns() - began, resource.getrusage(resource.RUSAGE_SELF).ru_maxrss
        values = [pa.array([bin_], pa.int32()), pa.array([Decimal(sum(f[0] for f in found))], pa.decimal128(38, 0)), *(pa.array([v], pa.int64()) for v in (sum(f[1] for f in found), nanos, peak))]
        yield pa.RecordBatch.from_arrays(values, names=["bin", "balanced", "wedges", "nanos", "peak_kb"])

    none = F.lit(None)
    left = lists.select("bin", F.lit(0).alias("kind"), F.col("mid").alias("a"), *(none.cast("long").alias(c) for c in ("b", "sign", "shard", "shards")), "codes")
    right = edges.select("bin", F.lit(1).alias("kind"), F.col("pivot").alias("a"), F.col("mid").alias("b"), "sign", "shard", "shards", none.cast("array<long>").alias("codes"))
    return left.unionByName(right).repartitionById(bins, F.col("bin")).mapInArrow(run, BINS)


@dataclass
class Prepared:
    """Ranked edges and the assignment of ranks to bins, both kept until ``release``."""

    ranked: DataFrame
    assignment: DataFrame
    held: tuple[DataFrame, ...]

    def release(self) -> None:
        for x in self.held:
            x.unpersist()


def prepare(graph: SignedGraph, bins: int, assigner: str = "lpt_scalable", workload: str = "full", max_load: int | None = None) -> Prepared:
    """Index and assignment.  A pivot above ``max_load`` (default: a bin's mean load) is split by ends."""
    edges, kept = graph.edges.persist(), []
    held = SignedGraph(edges, graph.name)
    ids = index.compact_ids(index.degrees(held), held=kept)
    ranked = index.ranked(held, ids).persist()
    work = index.rank_workload(ranked, workload).join(ids.select("gid", "rank_id"), F.col("pivot") == F.col("rank_id"), "right")
    work = work.select(F.col("gid").alias("pivot"), F.coalesce("load", F.lit(0)).cast("long").alias("load")).persist()
    if max_load is None:
        max_load = max(1, (work.agg(F.sum("load")).first()[0] or 0) // bins)
    # A pivot's first ``bins`` shards lie in different bins.  What a bin has of further ones joins
    # the first it has, so that the pivot's edges go there and are read once.
    cut = split_hot(ASSIGNERS[assigner](work, bins), bins, max_load).where(F.col("shard") < bins)
    held_ = F.least(F.col("shards"), F.lit(bins))
    assignment = cut.withColumn("load", F.floor(F.col("load") * F.col("shards") / held_).cast("long")).withColumn("shards", held_)
    by_rank = assignment.join(ids.select(F.col("gid").alias("__gid"), "rank_id"), F.col("pivot") == F.col("__gid"))
    return Prepared(ranked, by_rank.select(F.col("rank_id").alias("pivot"), "bin", "load", "shard", "shards"), (edges, ranked, work, *kept))


def _ways(assignment: DataFrame, bins: int, threads: int) -> list[int]:
    """Sub-bins of every bin: ``threads``, times its load over the mean load."""
    loads = {r["bin"]: int(r["load"] or 0) for r in assignment.groupBy("bin").agg(F.sum("load").alias("load")).collect()}  # a row per bin
    mean = max(1, sum(loads.values()) / bins)
    return [threads * max(1, round(loads.get(b, 0) / mean)) for b in range(bins)]


def count_prepared(ready: Prepared, bins: int, threads: int = 1, form: str = "sql") -> DataFrame:
    """Per-bin rows of the pivot-partitioned counter.

    The SQL form has no threads inside a task: there ``threads`` sub-bins take a bin's pivots, and
    more of them where a bin has more than its share of the load.
    """
    if form == "arrow":
        return bins_arrow(*route_two_hop(ready.ranked, ready.assignment), bins, threads)
    ways = _ways(ready.assignment, bins, threads)
    if sum(ways) == bins:
        return bins_sql(*route_two_hop(ready.ranked, ready.assignment), bins)
    first = [sum(ways[:b]) for b in range(bins + 1)]
    at = lambda values: F.get(F.array(*map(F.lit, values)), F.col("bin"))
    spread = ready.assignment.withColumn("bin", (at(first) + owner(F.col("pivot"), at(ways))).cast("int"))
    per = bins_sql(*route_two_hop(ready.ranked, spread), first[-1])
    per = per.withColumn("bin", F.get(F.array(*(F.lit(b) for b in range(bins) for _ in range(ways[b]))), F.col("bin")))
    return per.groupBy("bin").agg(F.sum("balanced").cast(TOTAL).alias("balanced"), F.sum("wedges").cast("long").alias("wedges"), F.max("nanos").alias("nanos"), F.max("peak_kb").alias("peak_kb"))


def count_pivot_local(graph: SignedGraph, bins: int = 8, threads: int = 1, assigner: str = "lpt_scalable", workload: str = "full", form: str = "sql", return_: str = "total", max_load: int | None = None) -> DataFrame:
    """The pivot-partitioned counter, run at once: what comes back is one row, or one per bin.

    Pivots are assigned to bins by load, the lists they need are placed there once a bin, and
    every bin counts on its own.  ``return_="bins"`` gives per-bin rows.  With
    ``threads=1`` and more bins this is the flat form, with ``assigner="blocks"`` the one
    without load awareness.
    """
    ready = prepare(graph, bins, assigner, workload, max_load)
    found = {r["bin"]: r for r in count_prepared(ready, bins, threads, form).collect()}  # a row per bin
    ready.release()
    if return_ == "bins":
        rows = [(k, *(tuple(found[k])[1:] if k in found else (Decimal(0), 0, None, None))) for k in range(bins)]
        return graph.spark.createDataFrame(rows, BINS)
    return graph.spark.createDataFrame([(sum((r["balanced"] for r in found.values()), Decimal(0)),)], f"balanced {TOTAL}")


# --- counters that hold the graph in one process ------------------------------------


def _lists(keys: np.ndarray) -> Lists:
    """Adjacency by rank from sorted keys (rank, neighbour's rank, sign): 31, 32 and 1 bits."""
    many = int(keys[-1] >> 33) + 1 if len(keys) else 0
    start = np.searchsorted(keys, np.arange(many + 1) << 33)
    codes = np.empty(len(keys), np.int32 if many < 1 << 30 else np.int64)
    for at in range(0, len(keys), PIECE):
        codes[at : at + PIECE] = keys[at : at + PIECE] & ((1 << 33) - 1)
    return Lists(np.arange(many), start[:-1], start[1:], codes)


def _count_pivots(lists: Lists, first: int, last: int) -> int:
    """Balanced butterflies led by the pivots (ranks) from first to last."""
    begin, stop = (int(lists.start[first]), int(lists.stop[last - 1])) if last > first else (0, 0)
    pivot, code = np.repeat(lists.mid[first:last], (lists.stop - lists.start)[first:last]), lists.codes[begin:stop]
    below = code >> 1 < pivot
    pivot, code = pivot[below], code[below].astype(np.int64)
    one = np.ones(len(pivot), np.int64)
    return count_edges(lists, pivot, code >> 1, code & 1, one * 0, one)[0] if len(pivot) else 0


def count_shared(graph: SignedGraph, threads: int = 8, cap: int = LOCAL_EDGES) -> DataFrame:
    """The shared-memory counter: one read-only graph in one task, pivots in parallel threads, private counters.

    The driver holds no edge: the task gets them by rank and forms the lists.
    """
    if (n := graph.edges.count()) > cap:
        raise ValueError(f"{n} edges are more than {cap}; use count_pivot_local or count_wedge_agg")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from concurrent.futures import ThreadPoolExecutor

        keys, at = np.empty(2 * n, np.int64), 0
        for b in batches:
            hi, lo, sign = (b.column(k).to_numpy() for k in range(3))
            for x, y in ((hi, lo), (lo, hi)):
                keys[at : at + len(x)] = x << 33 | y << 1 | sign
                at += len(x)
        keys = keys[:at]
        keys.sort()
        lists = _lists(keys)
        del keys
        shares = np.arange(0, at + SHARE, SHARE)
        cuts = np.unique(np.append(np.searchsorted(lists.start, shares), len(lists.mid)))
        with ThreadPoolExecutor(threads) as pool:
            found = sum(pool.map(lambda k: _count_pivots(lists, int(cuts[k]), int(cuts[k + 1])), range(len(cuts) - 1)))
        yield pa.RecordBatch.from_arrays([pa.array([Decimal(found)], pa.decimal128(38, 0))], names=["n"])

    ranked = index.ranked(graph).select("hi", "lo", "sign")
    return ranked.repartition(1).mapInArrow(run, f"n {TOTAL}").agg(total(F.col("n")).alias("balanced"))


def count_serial(graph: SignedGraph, cap: int = LOCAL_EDGES) -> DataFrame:
    """The serial counter: one task of one thread."""
    return count_shared(graph, 1, cap)


# --- sign-blind counters -------------------------------------------------------------
#
# Every two wedges of a pair of ends are tested, as bits: a word holds the tests of 64 of them.

#: Wedges that a task packs at a time; a packed row of up to a word needs no bytes of its own.
PACK, WORD = 1 << 21, 64
PACKED = "pivot long, end long, n int, word long, bits binary"


def pack_wedges(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Wedges (pivot, end, odd) as rows of many bits; a pair of ends has one row per ``PACK`` wedges."""
    held, size = [], 0

    def flush() -> pa.RecordBatch:
        pivot, end, odd = (np.concatenate(x) for x in zip(*held, strict=True))
        order = np.lexsort((end, pivot))
        pivot, end, odd = pivot[order], end[order], odd[order].astype(np.uint64)
        first = np.flatnonzero(np.concatenate([[True], (pivot[1:] != pivot[:-1]) | (end[1:] != end[:-1])]))
        n = np.diff(np.append(first, len(pivot)))
        within = (np.arange(len(pivot)) - np.repeat(first, n)) % WORD
        word = np.where(n <= WORD, np.bitwise_or.reduceat(odd << within.astype(np.uint64), first), np.uint64(0))
        bits = [None] * len(first)
        for k in np.flatnonzero(n > WORD).tolist():
            bits[k] = np.packbits(odd[first[k] : first[k] + n[k]].astype(np.uint8), bitorder="little").tobytes()
        return pa.RecordBatch.from_arrays([pa.array(pivot[first]), pa.array(end[first]), pa.array(n.astype(np.int32)), pa.array(word.view(np.int64)), pa.array(bits, pa.binary())], names=["pivot", "end", "n", "word", "bits"])

    for b in batches:
        held.append(tuple(b.column(k).to_numpy() for k in range(3)))
        size += b.num_rows
        if size >= PACK:
            yield flush()
            held, size = [], 0
    if size:
        yield flush()


def _shifted(words: np.ndarray) -> np.ndarray:
    """The bits of ``words`` moved down by 0 to 63 places, a row each."""
    out = np.empty((WORD, len(words)), np.uint64)
    out[0], after = words, np.append(words[1:], np.uint64(0))
    for r in range(1, WORD):
        out[r] = (words >> np.uint64(r)) | (after << np.uint64(WORD - r))
    return out


def unequal_pairs(bits: np.ndarray) -> int:
    """Pairs of unequal bits: every two are compared, by all distances."""
    full = -(-len(bits) // WORD)
    pad = lambda x: np.packbits(np.append(x, np.zeros(full * WORD - len(x), np.uint8)), bitorder="little").view(np.uint64)
    words = pad(bits)
    moved, valid, found = _shifted(words), _shifted(pad(np.ones(len(bits), np.uint8))), 0
    for q in range(full):
        r = 0 if q else 1  # no bit meets itself
        met = moved[r:, q:] ^ words[: full - q]
        met &= valid[r:, q:]
        found += int(np.bitwise_count(met).sum(dtype=np.int64))
    return found


def _unequal_words(word: np.ndarray, n: np.ndarray) -> int:
    """The same for many lists of a word at most."""
    found = 0
    for s in range(1, int(n.max(initial=1))):
        some = n > s
        word, n = word[some], n[some]
        valid = (np.uint64(1) << (n - s).astype(np.uint64)) - np.uint64(1)
        found += int(np.bitwise_count((word ^ (word >> np.uint64(s))) & valid).sum(dtype=np.int64))
    return found


def tested_pairs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """total, wasted of packed rows that come by pair of ends."""
    total_ = wasted = 0
    key, kept = None, []

    def close(rows: list[tuple[int, int, bytes | None]]) -> tuple[int, int]:
        parts = [np.unpackbits(np.frombuffer(b if b is not None else int(w).to_bytes(8, "little", signed=True), np.uint8), count=n, bitorder="little") for n, w, b in rows]
        bits = np.concatenate(parts)
        return len(bits) * (len(bits) - 1) // 2, unequal_pairs(bits)

    for b in batches:
        if not b.num_rows:
            continue
        pivot, end, n, word = (b.column(k).to_numpy() for k in range(4))
        first = np.flatnonzero(np.concatenate([[True], (pivot[1:] != pivot[:-1]) | (end[1:] != end[:-1])]))
        last = np.append(first[1:], len(pivot))
        sizes = np.add.reduceat(n.astype(np.int64), first)
        row = lambda k: (int(n[k]), int(word[k]), b.column(4)[k].as_py())  # noqa: B023, E731
        edge = np.zeros(len(first), bool)
        edge[[0, -1]] = True  # runs that another batch may share
        small = (sizes <= WORD) & ~edge
        at = np.cumsum(n, dtype=np.int64) - n
        at -= np.repeat(at[first], last - first)
        fits = np.repeat(small, last - first)
        words = np.bitwise_or.reduceat(np.where(fits, word.view(np.uint64) << np.where(fits, at, 0).astype(np.uint64), np.uint64(0)), first)[small]
        total_ += int((sizes[small] * (sizes[small] - 1) // 2).sum())
        wasted += _unequal_words(words, sizes[small])
        for k in np.flatnonzero(~small).tolist():
            own = (int(pivot[first[k]]), int(end[first[k]]))
            if own != key:
                if kept:
                    t, w = close(kept)
                    total_, wasted = total_ + t, wasted + w
                key, kept = own, []
            kept += [row(x) for x in range(first[k], last[k])]
    if kept:
        t, w = close(kept)
        total_, wasted = total_ + t, wasted + w
    yield pa.RecordBatch.from_arrays([pa.array([Decimal(x)], pa.decimal128(38, 0)) for x in (total_, wasted)], names=["total", "wasted"])


def _tested(graph: SignedGraph) -> DataFrame:
    """One row: total, balanced, wasted."""
    packed_ = wedges(graph, "priority").select("pivot", "end", (F.col("pos") % 2).cast("long").alias("odd")).mapInArrow(pack_wedges, PACKED)
    parts = int(graph.spark.conf.get("spark.sql.shuffle.partitions"))
    met = packed_.repartition(parts, "pivot", "end").sortWithinPartitions("pivot", "end").mapInArrow(tested_pairs, "total decimal(38,0), wasted decimal(38,0)")
    return met.agg(total(F.col("total")).alias("total"), total(F.col("total") - F.col("wasted")).alias("balanced"), total(F.col("wasted")).alias("wasted"))


def count_signblind(graph: SignedGraph) -> DataFrame:
    """Meets all butterflies, tests signs afterwards: total, balanced, wasted."""
    return _tested(graph).select(*(F.col(c).cast("long").alias(c) for c in ("total", "balanced", "wasted")))


def count_no_separation(graph: SignedGraph) -> DataFrame:
    """One list of wedges per pair of ends; every two of them are tested."""
    return _tested(graph).select("balanced")


def count_bruteforce(graph: SignedGraph) -> DataFrame:
    """The definition: all pairs of both sides and four edge lookups (small graphs only), tested as bits in tiles."""
    return tiles.quads(graph.cached())


#: Wedges that the enumeration may send, ranges of middle vertices at most, and wedges that are worth a range.
SPREAD, RANGES, WORTH = 1 << 24, 16, 1 << 15
#: Middle vertices of a list, what its length is a multiple of where it can be (files pack so many values
#: together), and lists that are met at a time.
LIST, GROUP, MEET = 256, 8, 256

LISTS = "low long, high long, p int, range int, mids array<long>"
MET = "low long, high long, negatives int, first array<long>, second array<long>"


def _changes(b: pa.RecordBatch | pa.Table, keys: list[str]) -> np.ndarray:
    """Places where runs of equal keys begin."""
    new = np.zeros(b.num_rows, bool)
    new[:1] = True
    for k in keys:
        c = b.column(k).to_numpy()
        new[1:] |= c[1:] != c[:-1]
    return np.flatnonzero(new)


def listed(batches: Iterator[pa.RecordBatch], range_: int) -> Iterator[pa.RecordBatch]:
    """Sorted wedges (low, high, p, m) of a range as lists of at most ``LIST`` middle vertices."""
    for b in batches:
        if not b.num_rows:
            continue
        runs = _changes(b, ["low", "high", "p"])
        size = np.diff(np.append(runs, b.num_rows))
        within, size = np.arange(b.num_rows) - np.repeat(runs, size), np.repeat(size, size)
        first = np.flatnonzero((within % LIST == 0) | (within == size - size % GROUP))
        mids = pa.ListArray.from_arrays(pa.array(np.append(first, b.num_rows).astype(np.int32)), b.column("m"))
        yield pa.RecordBatch.from_arrays([*(b.column(k).take(pa.array(first)) for k in ("low", "high", "p")), pa.array([range_] * len(first), pa.int32()), mids], names=["low", "high", "p", "range", "mids"])


def met_lists(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Every two lists of a key (low, high, odd) that may close butterflies; its lists to meet come before those that meet them."""
    keys, held = ["low", "high", "odd"], None
    for b in batches:
        if not b.num_rows:
            continue
        t = pa.Table.from_batches([b] if held is None else [held, b]).combine_chunks().to_batches()[0]
        begin = _changes(t, keys)
        own = t.column("meets").to_numpy()
        many = np.add.reduceat(1 - own, begin)
        mids, p = t.column("mids"), t.column("p").to_numpy()
        at, values = mids.offsets.to_numpy(), mids.values.to_numpy()
        least, most = values[at[:-1]], values[at[1:] - 1]
        left = np.flatnonzero(own)
        key = np.searchsorted(begin, left, "right") - 1
        until, done = np.cumsum(many[key]), 0
        while done < len(left):  # of a few lists that meet all of their key's others
            to = max(done + 1, int(np.searchsorted(until, (until[done - 1] if done else 0) + PIECE, "right")))
            x, y = np.repeat(left[done:to], many[key[done:to]]), tiles._runs(many[key[done:to]], begin[key[done:to]])
            some = most[y] > least[x]
            x, y, done = x[some], y[some], to
            for k in range(0, len(x), MEET):
                i, j = pa.array(x[k : k + MEET]), pa.array(y[k : k + MEET])
                negatives = pa.array((4 - p[x[k : k + MEET]] - p[y[k : k + MEET]]).astype(np.int32))
                yield pa.RecordBatch.from_arrays([t.column("low").take(i), t.column("high").take(i), negatives, mids.take(i), mids.take(j)], names=["low", "high", "negatives", "first", "second"])
        last = int(begin[-1])
        held = t.slice(last, int(many[-1]))


def enumerate_butterflies(graph: SignedGraph, balanced: bool | None = True, limit: int | None = None) -> DataFrame:
    """u1, u2, v1, v2, negatives: butterflies as rows.

    The balance condition is part of the meeting, so unbalanced candidates are never made.  Wedges
    are formed on the side that has fewer of them and go as sorted lists of middle vertices.  Every two
    ranges of middle vertices meet in a task, list by list, and rows are made of two lists where they are
    written: values repeat in runs, which files keep small.
    """
    held = graph.cached()
    few = {s: tiles.wedges_of(held, s) for s in tiles.SIDES}
    ends = min(few, key=few.get)
    x, y = ("u", "v") if ends == "U" else ("v", "u")
    parts = int(graph.spark.conf.get("spark.sql.shuffle.partitions"))
    ranges = max(1, min(RANGES, few[ends] // WORTH, SPREAD // max(1, few[ends]) - 1))
    cuts, cells = -(-parts // ranges), ranges * (ranges + 1) // 2
    ways = -(-parts // cells)

    w = wedges(held, ends).select(F.shiftright("end", 1).alias("low"), F.shiftright("pivot", 1).alias("high"), F.shiftright("mid", 1).alias("m"), F.col("pos").alias("p"))
    dealt = w.repartitionByRange(ranges * cuts, "m", "low", "high").sortWithinPartitions("low", "high", "p", "m")
    lists = dealt.mapInArrow(lambda batches: listed(batches, TaskContext.get().partitionId() // cuts), LISTS)

    # A list goes to a cell for each range: it is met by lower ranges and its own, and meets its own and upper ones.
    both = lists.withColumn("k", F.explode(F.sequence(F.lit(0), F.lit(ranges)))).withColumn("meets", (F.col("k") > F.col("range")).cast("int")).withColumn("other", F.col("k") - F.col("meets"))
    odd = F.lit(0) if balanced is None else F.col("p") % 2 if balanced else (F.col("p") + F.col("meets")) % 2
    upper = F.greatest("range", "other").cast("long")
    cell = F.shiftright(upper * (upper + 1), 1) + F.least("range", "other")
    cell = F.pmod(F.xxhash64("low", "high", "odd"), F.lit(ways)) * cells + cell
    both = both.withColumn("odd", odd.cast("int")).select(cell.cast("int").alias("cell"), "low", "high", "odd", "meets", "p", "mids").repartitionById(ways * cells, F.col("cell"))
    met = both.sortWithinPartitions("low", "high", "odd", "meets").mapInArrow(met_lists, MET)
    rows = met.select(F.col("low").alias(f"{x}1"), F.col("high").alias(f"{x}2"), "negatives", F.explode("first").alias(f"{y}1"), "second")
    rows = rows.select(f"{x}1", f"{x}2", "negatives", f"{y}1", F.explode("second").alias(f"{y}2")).where(F.col(f"{y}1") < F.col(f"{y}2"))
    out = rows.select("u1", "u2", "v1", "v2", "negatives")
    return out if limit is None else out.limit(limit)
