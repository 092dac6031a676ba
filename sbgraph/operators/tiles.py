"""Wedges between ends of one side, counted in tiles: no wedge leaves the task that forms it.

Ends are dealt into blocks by a hash; a block is one packed row (its lists by middle vertex).
Every two blocks meet in one tile, which holds all wedges between their ends, so its pairs are
complete.  What moves are packed edges, once per block, instead of wedges.  Inside a tile, mids
that most ends share are multiplied as dense matrices, wedges of the others are sorted by pair.

An edge has a mask of sign bits, one for each layer: one topology under several signs is
counted at once.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from decimal import Decimal
from functools import cached_property

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import choose2, total
from ..model import SignedGraph

#: Wedges from which tiles replace the shuffle of wedges.
FAR = 1 << 30
#: Edges of a block; a smaller graph has up to ``WIDE`` blocks of ``LEAST`` edges.
BLOCK, LEAST, WIDE = 1 << 22, 1 << 16, 8
#: Edges of a block where every edge is counted: a task holds eight numbers for each edge of a tile's first block.
COUNTED = 3 << 20
#: Wedges sorted and cells held at a time; wedges that cost as much as a pass over all cells of a pair of mids.
PIECE, CELLS, DENSE = 1 << 20, 1 << 22, 64
#: Cells that stay near a core, and the whole numbers that 32-bit floats hold.
NEAR, EXACT = 1 << 17, 1 << 24
#: Pairs of mids that a word tests, and pairs of ends that are tested at a time.
WORD, TESTS = 64, 1 << 18

SIDES = {"U": ("gu", "gv"), "V": ("gv", "gu")}


def wedges_of(graph: SignedGraph, ends: str) -> int:
    """Wedges with both ends on a side, from the degrees of the other one."""
    held = graph.tagged.groupBy(SIDES[ends][1]).agg(F.count(F.lit(1)).alias("d"))
    return int(held.agg(total(choose2(F.col("d")))).first()[0])


@dataclass
class Block:
    """Lists by middle vertex: ``end`` (places in ``ends``) and ``mask`` from ``start`` on."""

    ends: np.ndarray
    mids: np.ndarray
    start: np.ndarray
    end: np.ndarray
    mask: np.ndarray

    @classmethod
    def of(cls, end: np.ndarray, mid: np.ndarray, mask: np.ndarray) -> Block:
        ends, place = np.unique(end, return_inverse=True)
        order = np.lexsort((place, mid))
        mids, first = np.unique(mid[order], return_index=True)
        return cls(ends, mids, np.append(first, len(order)).astype(np.int64), place[order].astype(np.uint32), mask[order].astype(np.uint8))

    def pack(self) -> bytes:
        """Sizes, then the compressed byte planes of the steps between ids and of the lists."""
        steps = (np.diff(self.ends, prepend=0), np.diff(self.mids, prepend=0), np.diff(self.start), self.end, self.mask)
        planes = b"".join(np.ascontiguousarray(x.view(np.uint8).reshape(len(x), x.itemsize).T).tobytes() for x in steps)
        return np.array([len(self.ends), len(self.mids), len(self.end)], np.int64).tobytes() + pa.compress(planes, codec="zstd", asbytes=True)

    @classmethod
    def unpack(cls, blob: pa.Buffer) -> Block:
        n, m, e = np.frombuffer(blob, np.int64, 3).tolist()
        kinds, at, parts = ((np.int64, n), (np.int64, m), (np.int64, m), (np.uint32, e), (np.uint8, e)), 0, []
        planes = pa.decompress(blob[24:], decompressed_size=8 * (n + 2 * m) + 5 * e, codec="zstd")
        for kind, size in kinds:
            wide = np.dtype(kind).itemsize
            parts.append(np.ascontiguousarray(np.frombuffer(planes, np.uint8, size * wide, at).reshape(wide, size).T).view(kind).ravel())
            at += size * wide
        return cls(np.cumsum(parts[0]), np.cumsum(parts[1]), np.append(0, np.cumsum(parts[2])), *parts[3:])

    @cached_property
    def degree(self) -> np.ndarray:
        return np.bincount(self.end, minlength=len(self.ends))

    def dense(self, mids: np.ndarray, layer: int | None) -> np.ndarray:
        """Ends by the given mids (places): 1 for an edge, or its sign in a layer."""
        out = np.zeros((len(self.ends), len(mids)), np.float32)
        for k, m in enumerate(mids.tolist()):
            own = slice(self.start[m], self.start[m + 1])
            out[self.end[own], k] = 1 if layer is None else ((self.mask[own] >> layer) & 1) * 2.0 - 1
        return out


def _runs(n: np.ndarray, first: np.ndarray) -> np.ndarray:
    """Places ``first[k]``, ... of runs of length ``n[k]``, one behind the other."""
    return np.arange(int(n.sum())) + np.repeat(first - np.cumsum(n) + n, n)


@dataclass
class Meeting:
    """Two blocks over their common mids; ``few`` are those whose wedges are formed one by one."""

    a: Block
    b: Block
    matrices: bool = True

    def __post_init__(self) -> None:
        _, at, bt = np.intersect1d(self.a.mids, self.b.mids, assume_unique=True, return_indices=True)
        da, db = np.diff(self.a.start)[at], np.diff(self.b.start)[bt]
        many = (da * db * DENSE >= len(self.a.ends) * len(self.b.ends)) & self.matrices
        self.dense = (at[many], bt[many])
        at, bt, da = at[~many], bt[~many], da[~many]
        edge = _runs(da, self.a.start[at])
        order = np.argsort(self.a.end[edge], kind="stable")
        self.edge, mid = edge[order], np.repeat(bt, da)[order]
        self.low, self.size = self.b.start[mid], np.diff(self.b.start)[mid]
        self.until = np.cumsum(self.size)
        self.own = self.a.end[self.edge].astype(np.int64)

    def pieces(self) -> Iterator[tuple[int, int]]:
        """Ranges of edges that end with an end, of about ``PIECE`` wedges."""
        at = 0
        while at < len(self.edge):
            to = max(at + 1, int(np.searchsorted(self.until, (self.until[at - 1] if at else 0) + PIECE, "right")))
            to = int(np.searchsorted(self.own, self.own[to - 1], "right"))
            yield at, to
            at = to

    def wedges(self, at: int, to: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Pair (cell in a x b), differing sign bits and edge of ``a`` (place in at..to) of the wedges of a range."""
        n = self.size[at:to]
        place, edge = _runs(n, self.low[at:to]), np.repeat(np.arange(to - at), n)
        pair = np.repeat(self.own[at:to] * len(self.b.ends), n) + self.b.end[place]
        return pair, np.repeat(self.a.mask[self.edge[at:to]], n) ^ self.b.mask[place], edge


def _choose2(n: np.ndarray) -> int:
    return int((n * (n - 1) // 2).sum())


def _dense_counts(m: Meeting, layers: int) -> list[int]:
    """``_counts`` where all wedges lie in the matrices: sums over cells of n and of the signs' sum s.

    A cell has (n + s) / 2 wedges of equal signs.  A row's sums are whole numbers below ``EXACT``.
    """
    found, mids = [0] * (2 * layers), len(m.dense[0])
    right = [m.b.dense(m.dense[1], k) for k in (None, *range(layers))]
    left = [m.a.dense(m.dense[0], k) for k in (None, *range(layers))]
    cols = max(1, min(len(m.b.ends), EXACT // mids**2 - 1, NEAR))
    rows = max(1, NEAR // cols)
    dot = lambda x, y: int(np.einsum("ij,ij->i", x, y).sum(dtype=np.float64))
    for c in range(0, len(m.b.ends), cols):
        turned = [np.ascontiguousarray(y[c : c + cols].T) for y in right]
        for r in range(0, len(m.a.ends), rows):
            n, *signs = (x[r : r + rows] @ y for x, y in zip(left, turned, strict=True))
            nn, n1 = dot(n, n), int(n.sum(axis=1).sum(dtype=np.float64))
            for k, s in enumerate(signs):
                ss, ns, s1 = dot(s, s), dot(n, s), int(s.sum(axis=1).sum(dtype=np.float64))
                found[2 * k] += ((nn + 2 * ns + ss) // 4 - (n1 + s1) // 2) // 2
                found[2 * k + 1] += ((nn - 2 * ns + ss) // 4 - (n1 - s1) // 2) // 2
    return found


def _counts(m: Meeting, layers: int) -> list[int]:
    """Pairs of wedges of equal and of different signs, by layer, over all ends of a and of b."""
    found = [0] * (2 * layers)

    def add(n: np.ndarray, other: list[np.ndarray]) -> None:
        for k, b2 in enumerate(other):
            found[2 * k] += _choose2(n - b2)
            found[2 * k + 1] += _choose2(b2)

    if not len(m.dense[0]):
        for at, to in m.pieces():
            pair, odd, _ = m.wedges(at, to)
            if not len(pair):
                continue
            key = np.sort((pair - int(pair[0]) // len(m.b.ends) * len(m.b.ends)) << layers | odd)
            first = np.flatnonzero(np.concatenate([[True], (key[1:] >> layers) != (key[:-1] >> layers)]))
            add(np.diff(np.append(first, len(key))), [np.add.reduceat((key >> k) & 1, first) for k in range(layers)])
        return found
    if not len(m.edge) and 2 * len(m.dense[0]) ** 2 <= EXACT:
        return _dense_counts(m, layers)
    wide = len(m.b.ends)
    rows = max(1, CELLS // wide)
    right = [m.b.dense(m.dense[1], k) for k in (None, *range(layers))]
    left = [m.a.dense(m.dense[0], k) for k in (None, *range(layers))]
    for r in range(0, len(m.a.ends), rows):
        size = min(rows, len(m.a.ends) - r) * wide
        met = [np.rint(x[r : r + rows] @ y.T).astype(np.int64).ravel() for x, y in zip(left, right, strict=True)]
        n, other = met[0], [(met[0] - s) >> 1 for s in met[1:]]
        begin, stop = np.searchsorted(m.own, [r, r + rows])
        at = int(begin)
        while at < stop:
            to = min(int(stop), max(at + 1, int(np.searchsorted(m.until, (m.until[at - 1] if at else 0) + PIECE, "right"))))
            pair, odd, _ = m.wedges(at, to)
            n += np.bincount(pair - r * wide, minlength=size)
            for k in range(layers):
                other[k] += np.bincount(pair[(odd >> k) & 1 == 1] - r * wide, minlength=size)
            at = to
        add(n, other)
    return found


def _halved(found: list[int], block: Block) -> list[int]:
    """A block met with itself: every pair came twice, every end met itself in wedges of equal signs."""
    own = _choose2(block.degree)
    return [(x - (0 if k % 2 else own)) // 2 for k, x in enumerate(found)]


def _blocks(graph: SignedGraph, ends: str, masks: Column, block: int | None = None) -> tuple[DataFrame, int]:
    end, mid = SIDES[ends]
    rows = graph.edges.withColumn("mask", masks.cast("short"))
    tagged = SignedGraph(rows).edges.select(F.shiftleft("u", 1).alias("gu"), (F.shiftleft("v", 1) + 1).alias("gv"), "mask")
    edges = graph.edges.count()
    many = max(-(-edges // (block or BLOCK)), min(WIDE, -(-edges // LEAST)), 1)
    dealt = tagged.select(F.pmod(F.xxhash64(end), F.lit(many)).cast("int").alias("block"), F.col(end).alias("end"), F.col(mid).alias("mid"), "mask")

    def pack(table: pa.Table) -> pa.Table:
        block = Block.of(*(table.column(c).to_numpy() for c in ("end", "mid", "mask")))
        return pa.table({"block": pa.array([table.column("block")[0].as_py()], pa.int32()), "blob": pa.array([block.pack()], pa.binary())})

    return dealt.groupBy("block").applyInArrow(pack, "block int, blob binary"), many


def _tiles(blocks: DataFrame, many: int) -> DataFrame:
    """tile, block, other, blob: every two blocks in one tile."""
    other = F.explode(F.sequence(F.lit(0), F.lit(many - 1)))
    return blocks.withColumn("other", other).select((F.least("block", "other") * many + F.greatest("block", "other")).alias("tile"), "block", "other", "blob")


def class_counts(graph: SignedGraph, ends: str, masks: Column, layers: int = 1) -> DataFrame:
    """layer, symmetric, asymmetric: pairs of wedges of one class, for the ends of one side."""
    blocks, many = _blocks(graph, ends, masks)

    def count(table: pa.Table) -> pa.Table:
        same = table.column("block")[0] == table.column("other")[0]
        held = [Block.unpack(x.as_buffer()) for x in table.column("blob")]
        met = same or len(held) == 2  # no row where no end has that hash
        found = _counts(Meeting(held[0], held[-1]), layers) if met else [0] * (2 * layers)
        found = _halved(found, held[0]) if same else found
        sums = [pa.array([Decimal(x) for x in found[k::2]], pa.decimal128(38, 0)) for k in (0, 1)]
        return pa.table([pa.array(range(layers), pa.int32()), *sums], names=["layer", "symmetric", "asymmetric"])

    per = _tiles(blocks, many).groupBy("tile").applyInArrow(count, "layer int, symmetric decimal(38,0), asymmetric decimal(38,0)")
    all_ = graph.spark.range(layers).select(F.col("id").cast("int").alias("layer"))
    sums = per.groupBy("layer").agg(total(F.col("symmetric")).alias("symmetric"), total(F.col("asymmetric")).alias("asymmetric"))
    none = F.lit(0).cast("decimal(38,0)")
    return all_.join(sums, "layer", "left").select("layer", F.coalesce("symmetric", none).alias("symmetric"), F.coalesce("asymmetric", none).alias("asymmetric"))


def _twos(m: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """All pairs first < second of m places, ``WORD`` at a time."""
    for at in range(0, m * (m - 1) // 2, WORD):
        k = np.arange(at, min(m * (m - 1) // 2, at + WORD))
        second = ((1 + np.sqrt(1 + 8 * k)) / 2).astype(np.int64)
        second -= second * (second - 1) // 2 > k  # roots are rounded
        second += second * (second + 1) // 2 <= k
        yield k - second * (second - 1) // 2, second


def _words(bits: np.ndarray) -> np.ndarray:
    """Rows of up to 64 bits, as the narrowest whole numbers that hold them."""
    wide = 1 << max(0, (bits.shape[1] - 1).bit_length() - 3)
    packed = np.zeros((len(bits), wide), np.uint8)
    packed[:, : -(-bits.shape[1] // 8)] = np.packbits(bits, axis=1, bitorder="little")
    return packed.view(f"u{wide}").ravel()


def _tests(a: Block, b: Block) -> tuple[int, int]:
    """Quads of an end of a, an end of b and two mids whose four edges exist, and those with odd signs."""
    _, at, bt = np.intersect1d(a.mids, b.mids, assume_unique=True, return_indices=True)
    found = odd = 0
    for first, second in _twos(len(at)):
        sides = []
        for block, mids in ((a, at), (b, bt)):
            used, place = np.unique(np.concatenate([first, second]), return_inverse=True)
            one, two = place[: len(first)], place[len(first) :]
            edge, sign = block.dense(mids[used], None) > 0, block.dense(mids[used], 0) > 0
            sides.append((_words(edge[:, one] & edge[:, two]), _words(sign[:, one] ^ sign[:, two])))
        (have, sign), (have2, sign2) = sides
        rows = max(1, TESTS // max(1, len(have2)))
        for r in range(0, len(have), rows):
            met = have[r : r + rows, None] & have2
            found += int(np.bitwise_count(met).sum(dtype=np.int64))
            met &= sign[r : r + rows, None] ^ sign2
            odd += int(np.bitwise_count(met).sum(dtype=np.int64))
    return found, odd


def quads(graph: SignedGraph) -> DataFrame:
    """total, balanced: every two ends of U are tested with every two mids, four lookups each."""

    def count(table: pa.Table) -> pa.Table:
        same = table.column("block")[0] == table.column("other")[0]
        held = [Block.unpack(x.as_buffer()) for x in table.column("blob")]
        found, odd = _tests(held[0], held[-1]) if same or len(held) == 2 else (0, 0)  # no row where no end has that hash
        if same:  # every pair came twice, every end met itself in equal signs
            found, odd = (found - _choose2(held[0].degree)) // 2, odd // 2
        return pa.table([pa.array([Decimal(x)], pa.decimal128(38, 0)) for x in (found, odd)], names=["total", "odd"])

    per = _tiles(*_blocks(graph, "U", F.col("sign"))).groupBy("tile").applyInArrow(count, "total decimal(38,0), odd decimal(38,0)")
    return per.agg(total(F.col("total")).cast("long").alias("total"), total(F.col("total") - F.col("odd")).cast("long").alias("balanced"))


def edge_counts(graph: SignedGraph, ends: str) -> DataFrame:
    """g, mid, balanced of the edges: over an edge's wedges, the other wedges of their class and pair."""
    blocks, many = _blocks(graph, ends, F.col("sign"), COUNTED)
    pairs = F.explode(F.sequence(F.lit(0), F.lit(many - 1)))
    turned = blocks.withColumn("other", pairs)
    met = turned.select((F.col("block") * many + F.col("other")).alias("tile"), F.lit(0).alias("kind"), "block", "blob")
    met = met.unionByName(turned.select((F.col("other") * many + F.col("block")).alias("tile"), F.lit(1).alias("kind"), F.col("other").alias("block"), "blob"))

    def count(table: pa.Table) -> pa.Table:
        kinds = table.column("kind").to_pylist()
        if len(kinds) < 2:  # no end has the other hash
            return pa.table({"block": pa.array([], pa.int32()), "n": pa.array([], pa.binary())})
        a, b = (Block.unpack(table.column("blob")[kinds.index(k)].as_buffer()) for k in (0, 1))
        own = table.column("block")[kinds.index(0)].as_py()
        same = bool(len(a.ends) and len(b.ends) and a.ends[0] == b.ends[0])
        m, held = Meeting(a, b, False), np.zeros(len(a.end), np.int64)
        for at, to in m.pieces():
            pair, odd, edge = m.wedges(at, to)
            if not len(pair):
                continue
            base = int(pair[0]) // len(b.ends) * len(b.ends)
            key = (pair - base) << 1 | odd
            if int(key.max()) < 8 * len(key):
                n = np.bincount(key)[key] - 1
            else:
                order = np.argsort(key)
                ranked = key[order]
                first = np.flatnonzero(np.concatenate([[True], ranked[1:] != ranked[:-1]]))
                size = np.diff(np.append(first, len(key)))
                n = np.empty(len(key), np.int64)
                n[order] = np.repeat(size, size) - 1
            if same:
                n[pair % len(b.ends) == pair // len(b.ends)] = 0  # an end with itself
            held[m.edge[at:to]] += np.bincount(edge, weights=n, minlength=to - at).astype(np.int64)
        return pa.table({"block": pa.array([own], pa.int32()), "n": pa.array([pa.compress(held.tobytes(), codec="zstd", asbytes=True)], pa.binary())})

    def add(block: pa.Table, parts: pa.Table) -> pa.Table:
        b = Block.unpack(block.column("blob")[0].as_buffer())
        held = np.zeros(len(b.end), np.int64)
        for x in parts.column("n"):
            held += np.frombuffer(pa.decompress(x.as_buffer(), decompressed_size=8 * len(held), codec="zstd"), np.int64)
        return pa.table({"g": b.ends[b.end], "mid": np.repeat(b.mids, np.diff(b.start)), "balanced": held})

    per = met.groupBy("tile").applyInArrow(count, "block int, n binary")
    return blocks.groupBy("block").cogroup(per.groupBy("block")).applyInArrow(add, "g long, mid long, balanced long")
