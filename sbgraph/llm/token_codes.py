"""Token-id output as directly addressable codes.

An id is split into chunks of ``WIDTH`` bits, least significant first.  Level 0 holds
the first chunk of every id, level k the (k+1)-th chunk of the ids that have one.  A
bitmap per level marks the ids that go on, and a rank directory holds the number of
marks before every ``STEP`` bits, so that one id is reached by a chunk, a bit and a
rank per level, without decoding anything around it.

File format: a Parquet table in ascending document order, one row per block of
documents with ``part`` and ``block`` (their order), ``doc_ids``, ``ends`` (ids up to
the end of each document) and ``codes``, a byte string::

    "DAC1", ids u32, levels u32, then per level: ids u32, chunks u8[ids],
    bitmap u8[ceil(ids / 8)] (least significant bit first), rank u32[ceil(ids / STEP)]

Defined cases: a null text is empty; an empty text has the end id only; a document of
any length is one block at least as long as itself; repeated rows are documents of
their own, ordered by id and a hash of the text, and those of one id may lie in several
parts; null doc_ids come first; other columns are ignored;
an empty table writes an empty file.
"""

from __future__ import annotations

import gc
import struct
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .kernels import give_back, released
from .store import Store
from .tokens import VOCABULARY, forget, id_parts

WIDTH, STEP = 8, 512
#: Ids after which a block is closed.
BLOCK = 1 << 18
#: Blocks whose places may be broadcast.
SMALL = 1 << 20
END_ID = 2


def encode_ids(ids: np.ndarray) -> bytes:
    """The byte string of a block of ids."""
    levels, rest = [], ids.astype(np.uint32)
    while True:
        more = rest >> WIDTH > 0
        held = np.add.reduceat(more, np.arange(0, len(more), STEP), dtype=np.int64) if len(more) else np.zeros(0, np.int64)
        marks = np.cumsum(held) - held
        levels.append(struct.pack("<I", len(rest)) + rest.astype(np.uint8).tobytes() + np.packbits(more, bitorder="little").tobytes() + marks.astype("<u4").tobytes())
        if not more.any():
            break
        rest = rest[more] >> WIDTH
    return b"DAC1" + struct.pack("<II", len(ids), len(levels)) + b"".join(levels)


class Codes:
    """Random access to a block."""

    def __init__(self, data: bytes | memoryview) -> None:
        if data[:4] != b"DAC1":
            raise ValueError("not a block of directly addressable codes")
        self.size, n_levels = struct.unpack_from("<II", data, 4)
        self.levels, at = [], 12
        for _ in range(n_levels):
            (n,) = struct.unpack_from("<I", data, at)
            at += 4
            chunks = np.frombuffer(data, np.uint8, n, at)
            bitmap = np.frombuffer(data, np.uint8, -(-n // 8), at + n)
            at += n + len(bitmap)
            rank = np.frombuffer(data, "<u4", -(-n // STEP), at)
            at += 4 * len(rank)
            self.levels.append((chunks, bitmap, rank))

    def __len__(self) -> int:
        return self.size

    def __getitem__(self, i: int) -> int:
        """One id: a chunk, a bit and a rank per level."""
        if not 0 <= i < self.size:
            raise IndexError(i)
        value, shift = 0, 0
        for chunks, bitmap, rank in self.levels:
            value |= int(chunks[i]) << shift
            if not bitmap[i >> 3] >> (i & 7) & 1:
                break
            base = i // STEP * STEP
            bits = np.unpackbits(bitmap[base // 8 : i // 8 + 1], bitorder="little")[: i - base]
            i, shift = int(rank[i // STEP]) + int(bits.sum()), shift + WIDTH
        return value

    def decode(self) -> np.ndarray:
        """All ids."""
        out, at = np.zeros(self.size, np.uint32), None
        for k, (chunks, bitmap, _) in enumerate(self.levels):
            part = chunks.astype(np.uint32) << np.uint32(WIDTH * k)
            if at is None:
                out, at = part, np.arange(self.size)
            else:
                out[at] |= part
            at = at[np.unpackbits(bitmap, count=len(chunks), bitorder="little").astype(bool)]
        return out


BLOCKS = "part int, block int, doc_ids array<long>, ends array<long>, codes binary"


def blocks(docs: DataFrame, vocabulary: str = VOCABULARY, end_id: int | None = END_ID) -> DataFrame:
    """The file's rows: encoded blocks of documents in ascending doc_id order."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts, number, part = id_parts(vocabulary), 0, TaskContext.get().partitionId()
        gc.disable()  # the caches have no cycles, and collections would walk them
        end = b"" if end_id is None else np.array([end_id], "<u4").tobytes()
        names, held, size = [], [], 0

        def close() -> pa.RecordBatch:
            ids = np.frombuffer(b"".join(held), "<u4")
            ends = np.cumsum([len(h) // 4 for h in held])
            columns = [pa.array([part], pa.int32()), pa.array([number], pa.int32()), pa.array([names], pa.list_(pa.int64())), pa.array([ends.tolist()], pa.list_(pa.int64())), pa.array([encode_ids(ids)], pa.binary())]
            return pa.RecordBatch.from_arrays(columns, names=["part", "block", "doc_ids", "ends", "codes"])

        for batch in batches:
            for name, own in zip(batch.column("doc_id").to_pylist(), parts.each(batch.column("text").to_pylist()), strict=True):
                names.append(name)
                held.append(own + end)
                size += len(held[-1]) // 4
                if size >= BLOCK:
                    yield close()
                    names, held, size, number = [], [], 0, number + 1
        if held:
            yield close()

    rows = docs.select(F.col("`doc_id`").cast("long").alias("doc_id"), F.col("`text`").alias("text"))
    # Texts of one id follow a hash, and equal rows any order, so that ranges can cut a much repeated id.
    rows = rows.withColumn("mark", F.xxhash64("text")).withColumn("tie", F.monotonically_increasing_id())
    ordered = rows.repartitionByRange("doc_id", "mark", "tie").sortWithinPartitions("doc_id", "mark", "text")
    return ordered.select("doc_id", "text").mapInArrow(released(run), BLOCKS)


def write(docs: DataFrame, path: str, vocabulary: str = VOCABULARY, end_id: int | None = END_ID) -> None:
    """Writes the file of a document table."""
    blocks(docs, vocabulary, end_id).write.parquet(path)


def _starts(file: DataFrame) -> DataFrame:
    """__p, __b, start (ids before the block), n (its ids) of every block."""
    n = F.coalesce(F.element_at("ends", -1), F.lit(0))
    sizes = file.groupBy("part").agg(F.sum(n).alias("n"))
    # One row per written part: windows over parts and over the blocks of a part only.
    before = lambda w: w.rowsBetween(Window.unboundedPreceding, -1)
    parts = sizes.select(F.col("part").alias("__part"), F.coalesce(F.sum("n").over(before(Window.orderBy("part"))), F.lit(0)).alias("base"))
    inner = file.select("part", "block", n.alias("n"))
    inner = inner.select(F.col("part").alias("__p"), F.col("block").alias("__b"), F.coalesce(F.sum("n").over(before(Window.partitionBy("part").orderBy("block"))), F.lit(0)).alias("inner"), "n")
    return inner.join(parts, F.col("__p") == F.col("__part")).select("__p", "__b", (F.col("base") + F.col("inner")).alias("start"), "n")


def lookup(file: DataFrame, places: DataFrame, place: str = "place") -> DataFrame:
    """place and id of every token that is asked for by its place in the whole file.

    Places meet their blocks by equal ranges of places; of a block, only the chunks, bits and
    ranks of the tokens asked for are read.  Places outside the file have no row.
    """
    spans = _starts(file).where("n > 0").withColumn("range", F.explode(F.sequence(F.floor(F.col("start") / BLOCK), F.floor((F.col("start") + F.col("n") - 1) / BLOCK))))
    asked = places.select(F.col(f"`{place}`").cast("long").alias("place")).distinct().withColumn("range", F.floor(F.col("place") / BLOCK))
    met = asked.join(spans, "range").where("place >= start AND place < start + n")
    wanted = met.groupBy("__p", "__b", "start").agg(F.collect_list("place").alias("places"))  # a block's ids at most
    rows = file.select("part", "block", "codes").join(wanted, (F.col("part") == F.col("__p")) & (F.col("block") == F.col("__b")))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for codes, start, own in zip(*[batch.column(k).to_pylist() for k in range(3)], strict=True):
                held = Codes(codes)
                yield pa.RecordBatch.from_arrays([pa.array(own, pa.int64()), pa.array([held[i - start] for i in own], pa.int64())], names=["place", "id"])

    return rows.select("codes", "start", "places").mapInArrow(run, "place long, id long")


def read(file: DataFrame) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32 of every document of a file."""
    starts = _starts(file).drop("n")
    # Broadcast behind a check of the size, so that the codes stay where they are read.
    side = F.broadcast(starts) if file.select("block").count() <= SMALL else starts
    placed = file.join(side, (F.col("part") == F.col("__p")) & (F.col("block") == F.col("__b")))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        forget()  # the worker may have encoded before
        give_back()
        for batch in batches:
            for row in range(batch.num_rows):  # one block at a time
                names, ends, codes, start = (batch.column(k)[row] for k in range(4))
                ids = Codes(memoryview(codes.as_buffer())).decode().astype("<u4")
                edges = np.concatenate([[0], ends.values.to_numpy()]).astype(np.int64)
                crc = [zlib.crc32(ids[a:b]) for a, b in zip(edges[:-1].tolist(), edges[1:].tolist(), strict=True)]
                yield pa.RecordBatch.from_arrays([names.values, pa.array(edges[:-1] + start.as_py()), pa.array(np.diff(edges)), pa.array(crc, pa.int64())], names=["doc_id", "start", "n_tokens", "ids_crc32"])

    return placed.select("doc_ids", "ends", "codes", "start").mapInArrow(run, "doc_id long, start long, n_tokens long, ids_crc32 long")


def round_trip(docs: DataFrame, vocabulary: str = VOCABULARY) -> DataFrame:
    """Writes the file into the shared folder and reads it back."""
    return read(Store(docs.sparkSession).put("token_codes", blocks(docs, vocabulary)))
