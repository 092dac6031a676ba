"""Benchmark decontamination by a prefix-filtered set join.

Every run of ``WINDOW`` consecutive words of a benchmark item is a window (an item
of fewer words is one window).  A window occurs in a document when the document
holds all of it, so for containment 1 the prefix that must be joined is a single
shingle: the window's rarest one, by its count over all documents.

1. Count the benchmark's shingles over all documents (one pass; what comes back is
   bounded by the benchmark).
2. Keep each window's rarest shingle, with its offset in the window.
3. Probe the documents' shingles: a hit proposes a window at one start only (the
   positional bound); a window that would begin before or end behind the document
   is discarded (the length bound).
4. Verify exact containment: all words of the window are compared, in order, over
   the item-sized window of the document.

Windows are made by Spark and kept in a table, with the items that hold each in another.
The driver holds one part of the windows at a time, of about ``INDEX_WORDS`` words, which it
sends to the executors; a larger benchmark takes several passes, whose hits are merged.
The items of a document are joined to the windows that it holds.

Defined cases: null and blank texts have no words and are never contaminated; items
without words have no window; repeated items and items with equal windows all count; the
windows of an item without an id are found, but it is counted among no items;
repeated rows are scanned row by row; an empty table on either side gives no hits;
other columns of both tables are ignored.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import kernels as K
from .store import Store

WINDOW, SHINGLE = 10, 3
#: Words of all windows of one index part (8 bytes each), and windows of one row batch.
INDEX_WORDS, ROWS = 4_000_000, 100_000
_MASK = np.uint64((1 << 20) - 1)


@dataclass
class Windows:
    """Distinct windows of equal length, as word hashes."""

    length: int
    words: np.ndarray


def windows(benchmark: DataFrame) -> DataFrame:
    """item (its id as a string) and words (the hashes of one window) of all windows of all items."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch, words in _words(batches):
            for k, (a, b) in enumerate(zip(words.first[:-1].tolist(), words.first[1:].tolist(), strict=True)):
                own, length = words.hashes[a:b], min(WINDOW, b - a)
                for at in range(0, b - a - length + 1 if b > a else 0, ROWS):
                    rows = np.lib.stride_tricks.sliding_window_view(own[at : at + ROWS + length - 1], length)
                    flat = np.ascontiguousarray(rows, dtype="<u8").tobytes()
                    held = sorted({flat[i : i + 8 * length] for i in range(0, len(flat), 8 * length)})
                    yield pa.RecordBatch.from_arrays([pa.array([batch.column("item")[k].as_py()] * len(held), pa.string()), pa.array(held, pa.binary())], names=["item", "words"])

    rows = benchmark.select(F.col("`item_id`").cast("string").alias("item"), F.col("`text`").alias("text"))
    return rows.mapInArrow(run, "item string, words binary").distinct()


def index_parts(found: DataFrame) -> Iterator[list[Windows]]:
    """The distinct windows, a part at a time."""
    distinct = found.select("words").distinct()
    size = distinct.agg(F.sum(F.octet_length("words"))).first()[0] or 0
    parts = max(1, -(-size // (8 * INDEX_WORDS)))
    for k in range(parts if size else 0):
        held = distinct.where(F.pmod(F.xxhash64("words"), F.lit(parts)) == k).toArrow().column("words").to_pylist()
        by_length: dict[int, list[bytes]] = {}
        for w in sorted(held):
            by_length.setdefault(len(w) // 8, []).append(w)
        yield [Windows(n, np.frombuffer(b"".join(w), dtype=np.uint64).reshape(-1, n)) for n, w in sorted(by_length.items())]


class Probe:
    """Finds members of a fixed set of hashes in long arrays."""

    def __init__(self, hashes: np.ndarray) -> None:
        self.hashes = hashes
        self.bits = np.zeros(1 << 20, dtype=bool)
        self.bits[(hashes & _MASK).astype(np.int64)] = True

    def __call__(self, values: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Positions in ``values`` that are members, and which member."""
        at = np.flatnonzero(self.bits[(values & _MASK).astype(np.int64)])
        if not len(self.hashes) or not len(at):
            return at[:0], at[:0]
        which = np.minimum(np.searchsorted(self.hashes, values[at]), len(self.hashes) - 1)
        same = self.hashes[which] == values[at]
        return at[same], which[same]


def _window_shingles(w: Windows) -> tuple[int, np.ndarray]:
    """Size and hashes (windows x offsets) of a group's shingles."""
    size = min(SHINGLE, w.length)
    return size, np.stack([K.window_hashes(row, size) for row in w.words])


def _words(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[pa.RecordBatch, K.Words]]:
    for batch in batches:
        for part in K.slices(batch, "text"):
            yield part, K.words_of(*K.text_buffer(part.column("text")), K.ALNUM)


def shingle_counts(docs: DataFrame, groups: list[Windows]) -> dict[int, tuple[np.ndarray, np.ndarray]]:
    """By shingle size: the benchmark's distinct shingles and their counts over all documents."""
    sizes: dict[int, list[np.ndarray]] = {}
    for w in groups:
        size, own = _window_shingles(w)
        sizes.setdefault(size, []).append(own.ravel())
    known = {k: np.unique(np.concatenate(v)) for k, v in sizes.items()}
    shared = docs.sparkSession.sparkContext.broadcast(known)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        probes = {k: Probe(v) for k, v in shared.value.items()}
        total = {k: np.zeros(len(v), np.int64) for k, v in shared.value.items()}
        for _, words in _words(batches):
            for size, probe in probes.items():
                total[size] += np.bincount(probe(K.window_hashes(words.hashes, size))[1], minlength=len(total[size]))
        for size, n in total.items():
            at = np.flatnonzero(n)
            yield pa.RecordBatch.from_arrays([pa.array(np.full(len(at), size)), pa.array(at), pa.array(n[at])], names=["size", "k", "n"])

    counted = docs.select(F.col("`text`").alias("text")).mapInArrow(run, "size long, k long, n long").groupBy("size", "k").agg(F.sum("n").alias("n"))
    out = {k: (v, np.zeros(len(v), np.int64)) for k, v in known.items()}
    for r in counted.collect():  # at most one row per distinct shingle of the benchmark
        out[r["size"]][1][r["k"]] = r["n"]
    return out


@dataclass
class Index:
    """Windows of one length with their prefix shingles, sorted by shingle."""

    length: int
    size: int
    words: np.ndarray
    prefix: np.ndarray
    offset: np.ndarray


def build_index(groups: list[Windows], counts: dict[int, tuple[np.ndarray, np.ndarray]]) -> list[Index]:
    """Each window under its rarest shingle."""
    out = []
    for w in groups:
        size, own = _window_shingles(w)
        known, n = counts[size]
        offset = np.argmin(n[np.searchsorted(known, own)], axis=1)
        prefix = own[np.arange(len(own)), offset]
        order = np.argsort(prefix, kind="stable")
        out.append(Index(w.length, size, w.words[order], prefix[order], offset[order]))
    return out


def _occurrences(words: K.Words, index: Index, probe: Probe) -> tuple[np.ndarray, np.ndarray]:
    """Start words and windows of all occurrences in a batch."""
    at, which = probe(K.window_hashes(words.hashes, index.size))
    low, high = np.searchsorted(index.prefix, probe.hashes[which], "left"), np.searchsorted(index.prefix, probe.hashes[which], "right")
    many = high - low
    window = np.repeat(low - np.cumsum(many) + many, many) + np.arange(many.sum())
    start = np.repeat(at, many) - index.offset[window]
    doc = np.searchsorted(words.first, np.repeat(at, many), "right") - 1
    fits = (start >= words.first[doc]) & (start + index.length <= words.first[doc + 1])
    start, window = start[fits], window[fits]
    held = (words.hashes[start[:, None] + np.arange(index.length)] == index.words[window]).all(axis=1) if len(start) else np.zeros(0, bool)
    return start[held], window[held]


def _hits(words: K.Words, parts: list[Index], probes: list[Probe]) -> tuple[np.ndarray, list[set[bytes]]]:
    """Hit mark of every word, and the windows that occur in every document."""
    change = np.zeros(len(words.hashes) + 1, np.int32)
    held: list[set[bytes]] = [set() for _ in range(len(words.first) - 1)]
    for index, probe in zip(parts, probes, strict=True):
        start, window = _occurrences(words, index, probe)
        np.add.at(change, start, 1)
        np.add.at(change, start + index.length, -1)
        for d, w in zip((np.searchsorted(words.first, start, "right") - 1).tolist(), window.tolist(), strict=True):
            held[d].add(index.words[w].tobytes())
    return np.cumsum(change[:-1]) > 0, held


SCAN = "doc_id long, text_key long, n_words long, runs array<struct<start: long, end: long>>, windows array<binary>"


def _scan(docs: DataFrame, part: list[Index]) -> DataFrame:
    shared = docs.sparkSession.sparkContext.broadcast(part)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts = shared.value
        probes = [Probe(np.unique(p.prefix)) for p in parts]
        run_type = pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())]))
        for batch, words in _words(batches):
            hit, held = _hits(words, parts, probes)
            runs = []
            for a, b in zip(words.first[:-1].tolist(), words.first[1:].tolist(), strict=True):
                edge = np.flatnonzero(np.diff(np.concatenate([[0], hit[a:b].view(np.int8), [0]]))).reshape(-1, 2) if hit[a:b].any() else ()
                runs.append([{"start": int(s), "end": int(e)} for s, e in edge])
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("text_key"), pa.array(words.counts(), pa.int64()), pa.array(runs, run_type), pa.array([sorted(w) for w in held], pa.list_(pa.binary()))], names=["doc_id", "text_key", "n_words", "runs", "windows"])

    return docs.select(F.col("`doc_id`").cast("long").alias("doc_id"), F.xxhash64("`text`").alias("text_key"), F.col("`text`").alias("text")).mapInArrow(run, SCAN)


def scan(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """doc_id, text_key, n_words, runs (hit words, [start, end)) and items of every row."""
    store = Store(docs.sparkSession)
    found = store.put("windows", windows(benchmark))
    first, *rest = [store.put(f"scan{k}", _scan(docs, build_index(p, shingle_counts(docs, p)))) for k, p in enumerate(index_parts(found))] or [_scan(docs, [])]
    # Equal (doc_id, text) rows have equal hits, so hits are merged once and joined back.
    key = ["doc_id", "text_key"]
    held = [r.where(F.size("windows") > 0).select(*key, "runs", "windows") for r in (first, *rest)]
    met = held[0]
    for h in held[1:]:
        met = met.unionByName(h)
    items = met.select(*key, F.explode("windows").alias("words")).distinct().join(found, "words").groupBy(*key).agg(F.sort_array(F.collect_set("item")).alias("items"))
    items = items.select(*[F.col(c).alias(f"__{c}") for c in key], "items")
    same = lambda p: [F.col(c).eqNullSafe(F.col(f"{p}{c}")) for c in key]
    rows = first.select(*key, "n_words", "runs")
    if rest:
        more = met.groupBy(*key).agg(F.flatten(F.collect_set("runs")).alias("more")).select(*[F.col(c).alias(f"_m_{c}") for c in key], "more")
        rows = rows.join(more, same("_m_"), "left").select(*key, "n_words", F.coalesce(_merged(F.col("more")), F.col("runs")).alias("runs"))
    none = F.array().cast("array<string>")
    return rows.join(items, same("__"), "left").select(*key, "n_words", "runs", F.coalesce("items", none).alias("items"))


def _merged(runs: Column) -> Column:
    """Runs that overlap or touch become one."""
    last = lambda done: F.element_at(done, -1)
    joined = lambda done, r: F.struct(last(done)["start"].alias("start"), F.greatest(last(done)["end"], r["end"]).alias("end"))
    grow = lambda done, r: F.when((F.size(done) > 0) & (last(done)["end"] >= r["start"]), F.concat(F.slice(done, 1, F.size(done) - 1), F.array(joined(done, r)))).otherwise(F.concat(done, F.array(r)))
    return F.aggregate(F.sort_array(runs), F.expr("filter(runs, x -> false)"), grow)


def report(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """doc_id, n_words, n_hit, n_items, items_sha256, contaminated of every row."""
    n_hit = F.aggregate("runs", F.lit(0).cast("long"), lambda n, r: n + r["end"] - r["start"])
    return scan(docs, benchmark).select("doc_id", "n_words", n_hit.alias("n_hit"), F.size("items").cast("long").alias("n_items"), F.sha2(F.array_join("items", ",").cast("binary"), 256).alias("items_sha256"), (n_hit > 0).alias("contaminated"))


def drop_contaminated(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """The rows (same columns) in which no window occurs."""
    cols = docs.columns
    kept = docs.select(F.struct(*[F.col(f"`{c}`") for c in cols]).alias("row"), F.col("`text`").alias("text"))
    for part in index_parts(Store(docs.sparkSession).put("windows", windows(benchmark))):
        kept = _filter(kept, build_index(part, shingle_counts(docs, part)))
    return kept.select(*[F.col("row")[c].alias(c) for c in cols])


def _filter(rows: DataFrame, part: list[Index]) -> DataFrame:
    shared = rows.sparkSession.sparkContext.broadcast(part)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts = shared.value
        probes = [Probe(np.unique(p.prefix)) for p in parts]
        for batch, words in _words(batches):
            hit, _ = _hits(words, parts, probes)
            total = np.concatenate([[0], np.cumsum(hit)])
            yield batch.filter(pa.array(total[words.first[1:]] == total[words.first[:-1]]))

    return rows.mapInArrow(run, rows.schema)


def digest(items: list) -> str:
    """The items' digest, for tests."""
    return hashlib.sha256(",".join(sorted(map(str, items))).encode()).hexdigest()
