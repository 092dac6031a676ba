"""N-gram Jaccard join as a blocked sparse matrix product.

Documents are rows and five-word shingles columns of an incidence matrix A; two
documents link when their entry of ``A A^T`` (the overlap) is large enough for
their sizes.  Only blocks of that product that can hold a link are formed:

1. Texts with equal shingle sets are one class, represented by its least doc_id.
2. Each class keeps the prefix of its set that any linking partner must meet
   (``n - ceil(3n/4) + 1`` shingles, rare ones first).  Shingles that are frequent
   in the corpus come last in that order; frequencies are counted over all
   documents, in a table of fixed size.
3. Classes that share a prefix shingle and have sizes within a bound are put into the
   block of a leader (the smallest of them).  Every pair that can link meets in
   the block of some leader, and no pair is written out.
4. A block is multiplied by column slices: overlap counts accumulate, and pairs
   whose size bound or remaining columns rule a link out are discarded.  A block
   too large for one task becomes tiles of member groups; the sides of a tile grow with
   its block, and a task multiplies a tile in squares of ``CELL`` members.  A tile returns
   a spanning forest of its links and each member's number of links; a pair that meets
   under several leaders counts under the least of them.
5. Connected components of the forests give ``component_id``; the numbers of links,
   weighted by class sizes, give ``n_links``.  ``pairs`` writes the links themselves out.

Nothing whose size follows the input is broadcast by hand: joins are planned by Spark from
the sizes of the tables, and bitmaps of at most ``BITS`` bits spare most rows with long
columns their shuffle (a bit that is set by chance costs a shuffled row, nothing else).

Defined cases: a null or blank text has an empty set and links with nothing; a
null doc_id links with nothing and keeps a null component_id; rows that share a
doc_id are one node of a component, so all of them have its component_id, and different
texts of one doc_id join what they link with (``n_links`` is that of the row's own text,
and counts a doc_id once for each of its different sets); an empty table gives an empty
result; other columns of the input are ignored, so their names cannot clash.
"""

from __future__ import annotations

import hashlib
import itertools
import zlib
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import kernels as K
from .components import components
from .store import Store

SIZE = 5
#: Cells and blocks of the frequency table; shingles counted at a time.
CELL_BITS, CELL_BLOCKS, RUN = 23, 32, 2_000_000
#: A cell's count in one task stops here; a shingle that frequent is last in any case.
MOST = 65_535
#: Shingles of one tile side, columns of one slice of the product, members of one square of it.
TILE, SLICE, CELL = 1_500_000, 4096, 512
#: A block's tiles have a sixth of its members on a side, but not fewer or more than these.
SHARE, SIDES = 6, (384, 8192)
#: Level from which a shingle's classes are led by an aggregate and a join (about 8,000 holders).
HOT = 8 * 13
#: Most bits of the bitmap of wanted doc_ids.
BITS = 1 << 28


def prefix_length(n: int) -> int:
    return n - (3 * n + 3) // 4 + 1 if n else 0


def _texts(docs: DataFrame) -> DataFrame:
    return docs.select(F.col("`doc_id`").cast("long").alias("doc_id"), F.col("`text`").alias("text"))


def _sets(batches: Iterator[pa.RecordBatch], size: int) -> Iterator[tuple[pa.RecordBatch, list[np.ndarray]]]:
    for batch in batches:
        for part in K.slices(batch, "text"):
            yield part, list(K.shingles(K.words_of(*K.text_buffer(part.column("text")), K.SPACED), size))


def _lists(arrays: list[np.ndarray]) -> pa.ListArray:
    ends = np.concatenate([[0], np.cumsum([len(a) for a in arrays])]).astype(np.int32)
    flat = np.concatenate(arrays).view(np.int64) if arrays else np.zeros(0, np.int64)
    return pa.ListArray.from_arrays(pa.array(ends), pa.array(flat))


def _marks(sets: list[np.ndarray]) -> np.ndarray:
    """Fingerprints of sets, as two numbers each."""
    return np.frombuffer(b"".join(hashlib.blake2b(s.tobytes(), digest_size=16).digest() for s in sets), dtype=np.int64).reshape(-1, 2)


def _cell(hashes: np.ndarray) -> np.ndarray:
    return (hashes >> np.uint64(64 - CELL_BITS)).astype(np.int64)


def frequencies(docs: DataFrame, size: int = SIZE) -> np.ndarray:
    """Counts of all shingles of all documents, by hash cell, as levels (8 per doubling).

    The table has a fixed size and only sets the order of shingles: a shingle that many
    documents share has a high level, one of few documents that of its cell's chance
    company.  Any table gives the same links.
    """
    n_cells, step = 1 << CELL_BITS, (1 << CELL_BITS) // CELL_BLOCKS

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total, held, waiting = None, [], 0
        for _, sets in _sets(batches, size):
            held += [_cell(s).astype(np.int32) for s in sets]
            waiting += sum(map(len, sets))
            if waiting >= RUN:
                total = np.zeros(n_cells, np.uint16) if total is None else total
                cells, n = np.unique(np.concatenate(held), return_counts=True)
                total[cells] = np.minimum(total[cells] + n, MOST)
                held, waiting = [], 0
        cells, n = np.unique(np.concatenate([*held, np.zeros(0, np.int32)]), return_counts=True)
        n = np.minimum(n, MOST).astype(np.uint16)
        if total is None:  # a small task: its cells and their counts
            cuts = np.searchsorted(cells, np.arange(CELL_BLOCKS + 1) * step)
            blocks = [cells[a:b].astype(np.int32).tobytes() + n[a:b].tobytes() for a, b in zip(cuts[:-1], cuts[1:], strict=True)]
        else:
            total[cells] = np.minimum(total[cells].astype(np.int64) + n, MOST)
            blocks = [zlib.compress(total[k * step : (k + 1) * step].tobytes(), 1) for k in range(CELL_BLOCKS)]
        sparse = [total is None] * CELL_BLOCKS
        yield pa.RecordBatch.from_arrays([pa.array(range(CELL_BLOCKS), pa.int32()), pa.array(sparse), pa.array(blocks, pa.binary())], names=["k", "sparse", "part"])

    def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums: dict[int, np.ndarray] = {}
        for batch in batches:
            for k, sparse, part in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2), strict=True):
                held, data = sums.setdefault(k, np.zeros(step, np.int64)), part.as_py()
                if sparse:
                    m = len(data) // 6
                    held[np.frombuffer(data, np.int32, m) - k * step] += np.frombuffer(data, np.uint16, m, 4 * m)
                else:
                    held += np.frombuffer(zlib.decompress(data), np.uint16)
        yield pa.RecordBatch.from_arrays([pa.array(list(sums), pa.int32()), pa.array([_levels(v).tobytes() for v in sums.values()], pa.binary())], names=["k", "part"])

    partial = _texts(docs).select("text").mapInArrow(K.released(count), "k int, sparse boolean, part binary")
    out = np.zeros(n_cells, np.uint8)
    for r in partial.repartition("k").mapInArrow(K.released(add), "k int, part binary").collect():  # CELL_BLOCKS rows of a fixed size
        out[r["k"] * step : (r["k"] + 1) * step] = np.frombuffer(r["part"], np.uint8)
    return out


def _levels(counts: np.ndarray) -> np.ndarray:
    """Counts as levels, 8 per doubling; small counts keep levels of their own."""
    return np.minimum(8 * np.log2(counts.astype(np.float64) + 1), 255).astype(np.uint8)


def prefix(own: np.ndarray, table: np.ndarray) -> np.ndarray:
    """The prefix of a set as order keys (level, then hash), ascending."""
    keys = table[_cell(own)].astype(np.uint64) << np.uint64(56) | own >> np.uint64(8)
    return np.sort(keys)[: prefix_length(len(own))]


def sketches(docs: DataFrame, table: np.ndarray, size: int = SIZE) -> DataFrame:
    """doc_id, n, f1, f2 (fingerprint of the set), prefix."""
    shared = docs.sparkSession.sparkContext.broadcast(table)  # 2**CELL_BITS bytes

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part, sets in _sets(batches, size):
            f = _marks(sets)
            columns = {
                "doc_id": part.column("doc_id"),
                "n": pa.array([len(s) for s in sets], pa.int64()),
                "f1": pa.array(f[:, 0].copy()),
                "f2": pa.array(f[:, 1].copy()),
                "prefix": _lists([prefix(s, shared.value) for s in sets]),
            }
            yield pa.RecordBatch.from_pydict(columns)

    return _texts(docs).mapInArrow(K.released(run), "doc_id long, n long, f1 long, f2 long, prefix array<long>")


def _band(n: np.ndarray) -> np.ndarray:
    """Size bands: sets whose sizes differ by 4/3 at most are in the same or in adjacent bands."""
    return np.searchsorted(_EDGES, n, "right")


_EDGES = np.array([(4**k) // (3**k) + 1 for k in range(140) if (4**k) // (3**k) < 2**60], dtype=np.int64)


def _filed(h: np.ndarray, mark: np.ndarray, n: np.ndarray) -> np.ndarray:
    """Rows (shingle, file, mark, size): a class of band b is filed under b and b + 1."""
    band = _band(n)
    return np.stack([np.tile(h, 2), np.concatenate([band, band + 1]), np.tile(mark, 2), np.tile(n, 2)])


MEMBERS = "leader long, f1 long, n long"


def _led(entries: DataFrame) -> DataFrame:
    """Members of the files of shingles of moderate frequency, in one sorted pass.

    Rows arrive sorted by shingle and size, and the first row of a file leads it.  What is
    kept between batches is one row per open file of a single shingle.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kept = np.zeros((4, 0), np.int64)  # the open files' leaders
        for batch in batches:
            if not batch.num_rows:
                continue
            h, mark, n = (batch.column(k).to_numpy() for k in range(3))
            single = np.concatenate([[True], h[1:] != h[:-1]]) & np.concatenate([h[1:] != h[:-1], [True]])
            single[[0, -1]] = False  # their runs may go on in another batch
            rows = np.concatenate([kept, _filed(h[~single], mark[~single], n[~single])], axis=1)
            # Stable: leaders kept from before come first, then smaller sets.
            order = np.lexsort((np.concatenate([np.zeros(kept.shape[1], np.int64), rows[3, kept.shape[1] :]]), rows[1], rows[0]))
            rows = rows[:, order]
            new = np.concatenate([[True], (rows[:2, 1:] != rows[:2, :-1]).any(axis=0)])
            heads = np.flatnonzero(new)
            sizes = np.diff(np.append(heads, rows.shape[1]))
            many = np.repeat(sizes > 1, sizes)
            yield pa.RecordBatch.from_arrays([pa.array(x[many]) for x in (np.repeat(rows[2][heads], sizes), rows[2], rows[3])], names=["leader", "f1", "n"])
            kept = rows[:, new & (rows[0] == batch.column(0)[-1].as_py())]

    dealt = entries.repartition("h").sortWithinPartitions("h", "n", "f1").select("h", "f1", "n")
    return dealt.mapInArrow(K.released(run), MEMBERS)


def _led_hot(entries: DataFrame) -> DataFrame:
    """The same for shingles that very many classes hold.

    The leader is an aggregate, combined before its shuffle, and reaches the classes by a
    join whose other side has one row per file, so that Spark can split a hot shingle.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield pa.RecordBatch.from_arrays([pa.array(x) for x in _filed(*(batch.column(k).to_numpy() for k in range(3)))], names=["h", "file", "f1", "n"])

    filed = entries.select("h", "f1", "n").mapInArrow(K.released(run), "h long, file long, f1 long, n long")
    first = filed.groupBy("h", "file").agg(F.min(F.struct("n", "f1")).alias("first"), F.count(F.lit(1)).alias("held")).where("held > 1")
    first = first.select(F.col("h").alias("__h"), F.col("file").alias("__file"), F.col("first.f1").alias("leader"))
    return filed.join(first, (F.col("h") == F.col("__h")) & (F.col("file") == F.col("__file"))).select("leader", "f1", "n")


def _members(entries: DataFrame) -> DataFrame:
    """(leader, f1, n) of every shingle and pair of size bands that two classes or more hold.

    Two classes of linkable sizes share a file of every shingle that both hold, and the
    file's leader has both as members (itself included).  Classes and leaders go by ``f1``
    here; classes whose marks clash share their places, and are told apart by their reps later.
    """
    hot = F.shiftrightunsigned("h", 56) >= HOT
    return _led(entries.where(~hot)).unionByName(_led_hot(entries.where(hot))).distinct()


def _linkable(n: np.ndarray, side: np.ndarray | None) -> tuple[np.ndarray, np.ndarray]:
    """Pairs whose sizes allow a link, and the overlap each needs (3/7 of both sizes).

    ``side`` restricts the pairs to those of a marked and an unmarked set.
    """
    a, b = n[:, None], n[None, :]
    open_ = (4 * np.minimum(a, b) >= 3 * np.maximum(a, b)) & (a > 0) & (b > 0)
    np.fill_diagonal(open_, False)
    return (open_ if side is None else open_ & (side[:, None] != side[None, :])), -(-3 * (a + b) // 7)


def product(sets: list[np.ndarray], open_: np.ndarray, need: np.ndarray) -> np.ndarray:
    """The open pairs whose overlap reaches what they need.

    Overlaps accumulate over slices of columns; a pair leaves as soon as what is left
    of its columns cannot reach the overlap it needs.
    """
    if not open_.any():
        return open_
    row = np.repeat(np.arange(len(sets)), [len(s) for s in sets])
    _, inverse, count = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
    keep = count[inverse] > 1
    row, inverse = row[keep], inverse[keep]
    rest = np.bincount(row, minlength=len(sets))  # entries that still can meet another set
    order = np.argsort(inverse, kind="stable")
    row, inverse = row[order], inverse[order]
    number = np.cumsum(np.concatenate([[0], (inverse[1:] != inverse[:-1]).astype(np.int64)])) if len(inverse) else inverse
    width = int(number[-1]) + 1 if len(number) else 0
    overlap = np.zeros(open_.shape, dtype=np.float32)
    for base in range(0, width, SLICE):
        a, b = np.searchsorted(number, [base, base + SLICE])
        block = np.zeros((len(sets), min(SLICE, width - base)), dtype=np.float32)
        block[row[a:b], number[a:b] - base] = 1
        overlap += block @ block.T
        rest = rest - np.bincount(row[a:b], minlength=len(sets))
        open_ &= overlap + np.minimum(rest[:, None], rest[None, :]) >= need
        if not open_.any():
            return open_
    return open_ & (overlap >= need)


def multiply(sets: list[np.ndarray], side: np.ndarray | None = None) -> np.ndarray:
    """Links (boolean matrix) among whole sets: 100 * overlap >= 75 * union."""
    return product(sets, *_linkable(np.array([len(s) for s in sets], dtype=np.int64), side))


def survivors(prefixes: list[np.ndarray], n: np.ndarray, side: np.ndarray | None = None) -> np.ndarray:
    """Pairs that may link, from the prefixes alone.

    Up to the smaller of two prefixes' last keys both sets are known, so the overlap up
    to there is exact and the rest of either set bounds what can follow.
    """
    open_, need = _linkable(n, side)
    if not open_.any():
        return open_
    last = np.array([p[-1] if len(p) < k else np.uint64(2**64 - 1) for p, k in zip(prefixes, n.tolist(), strict=True)], dtype=np.uint64)
    below = np.stack([np.searchsorted(p, last, "right") for p in prefixes])
    outside = np.minimum(n[:, None] - below, (n[:, None] - below).T)
    return product(prefixes, open_, need - outside)


def forest(links: np.ndarray, names: np.ndarray) -> np.ndarray:
    """Edges (name, least name of its component) of a link matrix."""
    todo, edges = links.any(axis=1), []
    for seed in np.argsort(names, kind="stable"):
        if not todo[seed]:
            continue
        todo[seed], stack, reached = False, [seed], []
        while stack:
            new = np.flatnonzero(links[stack.pop()] & todo)
            todo[new] = False
            stack += new.tolist()
            reached += new.tolist()
        edges += [(names[r], names[seed]) for r in reached]
    return np.array(edges, dtype=np.int64).reshape(-1, 2)


TILE_KEY = ("leader", "i", "j")


def _groups(batches: Iterator[pa.RecordBatch], keys: tuple[str, ...]) -> Iterator[tuple[tuple, dict[str, list]]]:
    """Consecutive rows of equal keys, columns as lists (list columns as arrays)."""
    key, held = None, {}
    for batch in batches:
        columns = {}
        for name in batch.schema.names:
            column = batch.column(name)
            if pa.types.is_list(column.type):
                flat, ends = column.values.to_numpy(zero_copy_only=False).view(np.uint64), column.offsets.to_numpy()
                columns[name] = [flat[a:b].copy() for a, b in zip(ends[:-1], ends[1:], strict=True)]
            else:
                columns[name] = column.to_pylist()
        ids = list(zip(*[columns[k] for k in keys], strict=True))
        at = 0
        while at < len(ids):
            end = at + 1
            while end < len(ids) and ids[end] == ids[at]:
                end += 1
            if ids[at] != key:
                if key is not None:
                    yield key, held
                key, held = ids[at], {k: [] for k in columns}
            for k, v in columns.items():
                held[k] += v[at:end]
            at = end
    if key is not None:
        yield key, held


def _squares(key: tuple, side: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray | None]]:
    """A tile in squares: places of its members, and which of them are on one side (None: all meet all).

    Tiles off the diagonal only multiply one member group with the other.
    """
    cut = lambda at: np.array_split(at, max(1, -(-len(at) // CELL)))
    if key[1] != key[2]:
        pairs = itertools.product(cut(np.flatnonzero(side == key[1])), cut(np.flatnonzero(side != key[1])))
    else:
        pairs = itertools.combinations_with_replacement(cut(np.arange(len(side))), 2)
    for a, b in pairs:
        if a is b:
            yield a, None
        elif len(a) and len(b):
            yield np.concatenate([a, b]), np.arange(len(a) + len(b)) < len(a)


def _pick(rows: list, at: np.ndarray) -> list:
    return [rows[k] for k in at.tolist()]


def _roots(n: int, edges: np.ndarray) -> np.ndarray:
    """The least place of each place's component."""
    root = np.arange(n)
    while True:
        low = root.copy()
        np.minimum.at(low, edges[:, 0], root[edges[:, 1]])
        np.minimum.at(low, edges[:, 1], root[edges[:, 0]])
        low = low[low]
        if (low == root).all():
            return root
        root = low


def _candidates(rows: DataFrame) -> DataFrame:
    """Tile members with a partner they may link with, by group of such members (``sub``)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for key, held in _groups(batches, TILE_KEY):
            n, side = np.array(held["n"], dtype=np.int64), np.array(held["side"])
            edges = [np.zeros((0, 2), np.int64)]
            for at, one in _squares(key, side):
                edges.append(at[forest(survivors(_pick(held["prefix"], at), n[at], one), np.arange(len(at)))])
            pairs = np.concatenate(edges)
            if at := np.unique(pairs).tolist():
                sub = _roots(len(n), pairs)
                fixed = {k: pa.array(np.full(len(at), v)) for k, v in zip(TILE_KEY, key, strict=True)}
                yield pa.RecordBatch.from_pydict({"rep": pa.array([held["rep"][k] for k in at], pa.int64()), "f1": pa.array([held["f1"][k] for k in at], pa.int64()), **fixed, "side": pa.array(side[at]), "sub": pa.array(sub[at])})

    dealt = rows.repartition(*TILE_KEY).sortWithinPartitions(*TILE_KEY)
    return dealt.mapInArrow(K.released(run), "rep long, f1 long, leader long, i long, j long, side long, sub long")


def _met_before(lower: list[np.ndarray]) -> np.ndarray:
    """Pairs of members that also meet under a lesser leader (``lower``: a member's lesser leaders)."""
    _, at = np.unique(np.concatenate(lower), return_inverse=True)
    row, width = np.repeat(np.arange(len(lower)), [len(x) for x in lower]), int(at.max(initial=-1)) + 1
    met = np.zeros((len(lower), len(lower)), dtype=np.float32)
    for base in range(0, width, SLICE):
        own = (at >= base) & (at < base + SLICE)
        block = np.zeros((len(lower), min(SLICE, width - base)), dtype=np.float32)
        block[row[own], at[own] - base] = 1
        met += block @ block.T
    return met > 0


def _tile_links(rows: DataFrame, write: bool = False) -> DataFrame:
    """Links of candidate groups; rows: leader, i, j, sub, side, rep, f1, size, lower, set.

    Spanning forests (a, b), and of members with links (a, f1, links): how many nodes
    link with it, each pair counted in one group only.  ``write``: the pairs instead.
    """
    keys = (*TILE_KEY, "sub")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for key, held in _groups(batches, keys):
            names, marks, side = np.array(held["rep"]), np.array(held["f1"]), np.array(held["side"])
            sizes, first = np.array(held["size"], dtype=np.float64), np.zeros(len(names), bool)  # rows of one class may come again
            first[np.unique(np.stack([names, marks]), axis=1, return_index=True)[1]] = True
            links, edges = np.zeros(len(names)), [np.zeros((0, 2), np.int64)]
            for at, one in _squares(key, side):
                sets = _pick(held["set"], at)
                found = multiply(sets, one)
                edges.append(at[forest(found, np.arange(len(at)))])
                found = found & first[at] & first[at][:, None]
                if not found.any():
                    continue
                found &= ~_met_before(_pick(held["lower"], at))
                links[at] += found @ sizes[at]
                if write:
                    a, b = np.nonzero(np.triu(found))
                    overlap = [len(np.intersect1d(sets[i], sets[j], assume_unique=True)) for i, j in zip(a.tolist(), b.tolist(), strict=True)]
                    a, b = at[a], at[b]
                    yield pa.RecordBatch.from_arrays([pa.array(x) for x in (names[a], marks[a], names[b], marks[b], np.array(overlap, np.int64))], names=["a", "f1_a", "b", "f1_b", "overlap"])
            if write:
                continue
            pairs = np.concatenate(edges)
            root = _roots(len(names), pairs)
            least = np.full(len(names), np.iinfo(np.int64).max)
            np.minimum.at(least, root, names)
            at = np.unique(pairs)
            none = pa.nulls(len(at), pa.int64())
            yield pa.RecordBatch.from_arrays([pa.array(names[at]), pa.array(least[root[at]]), none, none], names=["a", "b", "f1", "links"])
            at = np.flatnonzero(links)
            yield pa.RecordBatch.from_arrays([pa.array(names[at]), pa.nulls(len(at), pa.int64()), pa.array(marks[at]), pa.array(links[at].astype(np.int64))], names=["a", "b", "f1", "links"])

    schema = "a long, f1_a long, b long, f1_b long, overlap long" if write else "a long, b long, f1 long, links long"
    return rows.repartition(*keys).sortWithinPartitions(*keys).mapInArrow(K.released(run), schema)


def _bitmap(rows: DataFrame, key: str) -> tuple[np.ndarray, int]:
    """A bitmap (bytes) of the hashes of a key, of about sixteen bits a row; and its number of bits."""
    bits = 1 << min(BITS.bit_length() - 1, max(16, (16 * rows.count()).bit_length()))
    words = rows.select(F.pmod(F.xxhash64(key), F.lit(bits)).alias("at")).select(F.shiftright("at", 6).alias("word"), F.expr("shiftleft(1L, CAST(at & 63 AS INT))").alias("bit"))
    held = words.groupBy("word").agg(F.bit_or("bit").alias("bit")).toArrow()  # BITS / 64 rows at most
    out = np.zeros(bits >> 6, np.int64)
    out[held.column("word").to_numpy()] = held.column("bit").to_numpy()
    return out.view(np.uint8), bits


def _among(rows: DataFrame, key: str) -> Callable[[str], Column]:
    """Whether a column's value may be one of a key's: never false for one that is."""
    wanted, bits = _bitmap(rows, key)
    shared = rows.sparkSession.sparkContext.broadcast(wanted)

    @F.arrow_udf("boolean")
    def flag(at: pa.Array) -> pa.Array:
        place = at.to_numpy()
        return pa.array((shared.value[place >> 3] >> (place & 7).astype(np.uint8) & 1).astype(bool))

    return lambda name: flag(F.pmod(F.xxhash64(name), F.lit(bits)))


def links(docs: DataFrame, heads: DataFrame, members: DataFrame, classes: DataFrame, store: Store, size: int = SIZE, write: bool = False) -> DataFrame:
    """What ``_tile_links`` finds among class representatives.

    heads: rep, f1, n, prefix; members: leader, f1, n; classes: rep, f1, size.
    """
    count = F.count(F.lit(1))
    side = F.least(F.greatest(F.ceil(count / SHARE), F.lit(SIDES[0])), F.lit(SIDES[1]))
    groups = F.greatest(F.lit(1), F.ceil(F.sum("n") / TILE), F.ceil(count / side))
    large = members.groupBy("leader").agg(groups.cast("long").alias("groups")).where("groups > 1").withColumnRenamed("leader", "__leader")
    tiled = members.join(large, F.col("leader") == F.col("__leader"), "left").withColumn("groups", F.coalesce("groups", F.lit(1).cast("long")))
    tiled = tiled.withColumn("side", F.pmod(F.xxhash64("f1", F.lit("tile")), F.col("groups")))
    tiled = tiled.withColumn("other", F.explode(F.sequence(F.lit(0).cast("long"), F.col("groups") - 1)))
    tiled = tiled.select("f1", "leader", F.least("side", "other").alias("i"), F.greatest("side", "other").alias("j"), "side")
    paired = heads.where(_among(members.select("f1").distinct(), "f1")("f1"))  # the others stay where they are
    found = store.put("candidates", _candidates(tiled.join(paired, "f1")))
    own = found.groupBy("rep", "f1").agg(F.collect_set("leader").alias("leaders")).join(classes.select("rep", "f1", "size"), ["rep", "f1"])
    wanted, bits = _bitmap(own, "rep")
    shared = docs.sparkSession.sparkContext.broadcast(wanted)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bit = np.unpackbits(shared.value, bitorder="little").astype(bool)
        chosen = (batch.filter(pa.array(bit[batch.column("at").to_numpy()])) for batch in batches)
        for part, sets in _sets(chosen, size):
            yield pa.RecordBatch.from_arrays([part.column("rep"), pa.array(_marks(sets)[:, 0].copy()), _lists(sets)], names=["rep", "f1", "set"])

    texts = _texts(docs).where("doc_id IS NOT NULL").select(F.col("doc_id").alias("rep"), F.pmod(F.xxhash64("doc_id"), F.lit(bits)).alias("at"), "text")
    rows = texts.mapInArrow(K.released(run), "rep long, f1 long, set array<long>").join(own, ["rep", "f1"]).join(found, ["rep", "f1"])
    lower = F.filter("leaders", lambda x: x < F.col("leader")).alias("lower")
    return _tile_links(rows.select(*TILE_KEY, "sub", "side", "rep", "f1", "size", lower, "set"), write)


def _classes(docs: DataFrame, store: Store, size: int) -> tuple[DataFrame, DataFrame, DataFrame, DataFrame]:
    """Sketches, classes (f1, f2, n, rep, size), heads and members."""
    known = store.put("sketches", sketches(docs, frequencies(docs, size), size))
    own = known.where("n > 0 AND doc_id IS NOT NULL")
    same = ["f1", "f2", "n"]
    # Counted in two steps: a class's copies are combined before they meet.
    classes = store.put("classes", own.groupBy(*same, "doc_id").agg(F.lit(1).alias("one")).groupBy(*same).agg(F.min("doc_id").alias("rep"), F.count(F.lit(1)).alias("size")))
    marked = classes.select("rep", *[F.col(c).alias(f"__{c}") for c in same])
    equal = [F.col(c) == F.col(f"__{c}") for c in same]
    copies = own.select("doc_id", *same).join(marked, equal).where("doc_id <> rep").select("doc_id").distinct()
    # What may be a copy is looked up; all other rows are heads.
    own = own.withColumn("copy", _among(store.put("copies", copies), "doc_id")("doc_id"))
    firsts = own.where("copy").join(marked, [F.col("doc_id") == F.col("rep"), *equal])
    # Written once: it is read twice, and a task looks up one bitmap at a time.
    heads = store.put("heads", own.where("NOT copy").select(F.col("doc_id").alias("rep"), "f1", "n", "prefix").unionByName(firsts.select("rep", "f1", "n", "prefix")))
    entries = heads.select("f1", "n", F.explode("prefix").alias("h"))
    return known, classes, heads, store.put("members", _members(entries))


def _several(known: DataFrame, classes: DataFrame) -> DataFrame:
    """(doc_id, rep) of every set of a doc_id of more than one row (rep is null for an empty set)."""
    same = ["f1", "f2", "n"]
    many = known.where("doc_id IS NOT NULL").groupBy("doc_id").agg(F.count(F.lit(1)).alias("rows")).where("rows > 1").select(F.col("doc_id").alias("id"))
    sets = known.join(many, F.col("id") == F.col("doc_id")).select("doc_id", *same).distinct()
    return sets.join(classes.select(*same, "rep"), same, "left").select("doc_id", "rep")


def pairs(docs: DataFrame, size: int = SIZE) -> tuple[DataFrame, DataFrame]:
    """All links, whole: membership (doc_id, rep, f1, n) and pairs (a, f1_a, b, f1_b, overlap).

    A class (rep, f1) holds the doc_ids of one shingle set of n shingles, which all link with
    each other; a pair links every doc_id of one class with every doc_id of the other.
    """
    store = Store(docs.sparkSession)
    known, classes, heads, members = _classes(docs, store, size)
    same = classes.select(F.col("f1").alias("g1"), F.col("f2").alias("g2"), F.col("n").alias("m"), "rep")
    rows = known.where("doc_id IS NOT NULL").join(same, (F.col("f1") == F.col("g1")) & (F.col("f2") == F.col("g2")) & (F.col("n") == F.col("m")))
    return rows.select("doc_id", "rep", "f1", "n").distinct(), links(docs, heads, members, classes, store, size, True)


def join(docs: DataFrame, size: int = SIZE) -> DataFrame:
    """doc_id, n_shingles, component_id, n_links (other documents that link with it) of every row."""
    store = Store(docs.sparkSession)
    known, classes, heads, members = _classes(docs, store, size)
    tiles = store.put("links", links(docs, heads, members, classes, store, size))
    store.drop("members", "candidates", "heads", "copies")
    several = store.put("several", _several(known, classes))
    both = several.where("rep IS NOT NULL").select(F.col("doc_id").alias("a"), F.col("rep").alias("b")).where("a <> b")
    found = components(tiles.where("b IS NOT NULL").select("a", "b").unionByName(both), store)
    degrees = tiles.where("b IS NULL").groupBy(F.col("a").alias("rep"), "f1").agg(F.sum("links").alias("links"))
    labelled = classes.join(found.withColumnRenamed("node", "rep"), "rep", "left").join(degrees, ["rep", "f1"], "left")
    count = (F.col("size") - 1 + F.coalesce("links", F.lit(0))).alias("k")
    labelled = labelled.select(F.col("f1").alias("g1"), F.col("f2").alias("g2"), F.col("n").alias("m"), F.coalesce("component", "rep").alias("c"), count)
    rows = known.select("doc_id", "n", "f1", "f2").join(labelled, (F.col("f1") == F.col("g1")) & (F.col("f2") == F.col("g2")) & (F.col("n") == F.col("m")), "left")
    # The rows of a doc_id without words have the component of its other texts.
    own = several.where("rep IS NOT NULL").select(F.col("doc_id").alias("id"), F.col("rep").alias("node")).join(found, "node", "left")
    own = own.groupBy("id").agg(F.min(F.coalesce("component", "node")).alias("other"))
    rows = rows.join(own, F.col("doc_id") == F.col("id"), "left")
    component = F.when(F.col("n") > 0, F.when(F.col("doc_id").isNotNull(), F.col("c"))).otherwise(F.coalesce("other", "doc_id"))
    n_links = F.when(F.col("doc_id").isNotNull(), F.coalesce("k", F.lit(0))).otherwise(0)
    return rows.select("doc_id", F.col("n").alias("n_shingles"), component.alias("component_id"), n_links.alias("n_links"))


def dedupe(docs: DataFrame, size: int = SIZE) -> DataFrame:
    """One document of each component (same columns): the row of the least doc_id.

    Rows with a null doc_id are kept; of rows that share the least doc_id one is kept.
    Only rows that a bitmap of the dropped and the repeated doc_ids lets past are joined
    with those ids; all other rows stay where they are.
    """
    cols, store = docs.columns, Store(docs.sparkSession)
    decided = join(docs, size).where("doc_id IS NOT NULL").groupBy("doc_id").agg(F.min(F.col("doc_id") == F.col("component_id")).alias("keep"), F.count(F.lit(1)).alias("rows"))
    odd = store.put("odd", decided.where("rows > 1 OR NOT keep").select(F.col("doc_id").alias("id"), "keep"))
    named = docs.select(F.struct(*[F.col(f"`{c}`") for c in cols]).alias("row"), F.col("`doc_id`").cast("long").alias("doc_id"))
    named = named.withColumn("marked", F.col("doc_id").isNotNull() & _among(odd, "id")("doc_id"))
    met = named.where("marked").select("row", "doc_id").join(odd, F.col("doc_id") == F.col("id"), "left")
    one = met.where("keep").groupBy("doc_id").agg(F.min_by("row", F.xxhash64("row")).alias("row"))
    rows = named.where("NOT marked").select("row").unionByName(met.where("id IS NULL").select("row")).unionByName(one.select("row"))
    return rows.select(*[F.col("row")[c].alias(c) for c in cols])
