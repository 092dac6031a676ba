"""Vectorised word kernels over Arrow string columns.

A batch's UTF-8 bytes are read in place.  Words are found with a 256-entry byte
class table and hashed eight bytes at a time, all words of a chunk together; chunks
are cut at separators, so memory depends on the chunk size and the longest word only.

Hashes have 64 bits.  Two words of different lengths or bytes clash by chance only
(2**-64 a pair): a word of up to ``LONG`` bytes runs through two chained, non-linear
lanes whose 128 bits are folded at the end, so no step can be solved for a clash; a
longer one is hashed by BLAKE2b.
"""

from __future__ import annotations

import ctypes
import hashlib
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa

CHUNK = 1 << 20
_U = np.uint64
#: Bytes of the longest word that is hashed with all others of its chunk.
LONG = 64


def give_back() -> None:
    """Gives freed memory back to the system."""
    pa.default_memory_pool().release_unused()
    if trim := getattr(ctypes.CDLL(None), "malloc_trim", None):
        trim(0)


def released(run: Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]) -> Callable[[Iterator[pa.RecordBatch]], Iterator[pa.RecordBatch]]:
    """A kernel that gives what it has freed back to the system, since its worker stays."""

    def inner(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield from run(batches)
        give_back()

    return inner


def mix64(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser (bijective)."""
    x = x ^ (x >> _U(30))
    x = x * _U(0xBF58476D1CE4E5B9)
    x = x ^ (x >> _U(27))
    x = x * _U(0x94D049BB133111EB)
    return x ^ (x >> _U(31))


def byte_class(separators: bytes) -> np.ndarray:
    """True for the bytes of words."""
    table = np.ones(256, dtype=bool)
    table[list(separators)] = False
    return table


#: Word bytes are all but space and 0x09-0x0D.
SPACED = byte_class(bytes([0x20, *range(0x09, 0x0E)]))
#: Word bytes are digits, letters (after lower-casing) and all bytes from 0x80.
ALNUM = byte_class(bytes([*range(0x00, 0x30), *range(0x3A, 0x61), *range(0x7B, 0x80)]))

_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
#: Masks that keep the first 0 to 8 bytes of a block.
_KEEP = np.array([(1 << 8 * k) - 1 for k in range(9)], dtype=np.uint64)


def word_hashes(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """64-bit hashes of byte spans of at least one byte."""
    size = ends - starts
    padded = np.concatenate([data, np.zeros(8, np.uint8)])
    eight = np.ndarray(len(data) + 1, "<u8", padded, strides=(1,))  # the eight bytes from any place on
    one = mix64(size.astype(np.uint64) * _U(0x9E3779B97F4A7C15))
    two = ~one
    block = eight[starts] & _KEEP[np.minimum(size, 8)]
    one, two = mix64(one ^ block), mix64(two + block * _U(0xD6E8FEB86659FD93))
    live = np.arange(len(size))
    for k in range(8, min(LONG, int(size.max(initial=0))), 8):
        live = live[size[live] > k]
        block = eight[starts[live] + k] & _KEEP[np.minimum(size[live] - k, 8)]
        one[live] = mix64(one[live] ^ block)
        two[live] = mix64(two[live] + block * _U(0xD6E8FEB86659FD93))
    out = mix64(one * _U(0xC2B2AE3D27D4EB4F) + (two << _U(23) | two >> _U(41)))
    for w in np.flatnonzero(size > LONG).tolist():
        out[w] = int.from_bytes(hashlib.blake2b(data[starts[w] : ends[w]].tobytes(), digest_size=8).digest(), "little")
    return out


@dataclass
class Words:
    """Words of a batch: byte spans, hashes, and ``first[d]`` the first word of document d."""

    starts: np.ndarray
    ends: np.ndarray
    hashes: np.ndarray
    first: np.ndarray

    def counts(self) -> np.ndarray:
        return np.diff(self.first)


def text_buffer(column: pa.ChunkedArray | pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Bytes and int64 offsets of a string column; nulls become empty texts."""
    array = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    array = array.cast(pa.large_string()).fill_null("")
    if len(array) == 0:
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    offsets = np.frombuffer(array.buffers()[1], dtype=np.int64, count=len(array) + 1 + array.offset)[array.offset :]
    data = np.frombuffer(array.buffers()[2] or b"", dtype=np.uint8)[offsets[0] : offsets[-1]]
    return data, offsets - offsets[0]


def _chunks(data: np.ndarray, offsets: np.ndarray, word: np.ndarray) -> Iterator[tuple[int, int]]:
    """Byte ranges of about CHUNK bytes that begin at a document or behind a separator."""
    at, n = 0, len(data)
    while at < n:
        end = min(n, at + CHUNK)
        if end < n:
            doc = offsets[np.searchsorted(offsets, end, "right") - 1]
            if doc > at:
                end = int(doc)
            else:  # inside a long document: cut behind its last separator, or read on to the next one
                sep = np.flatnonzero(~word[data[at:end]])
                if len(sep):
                    end = at + int(sep[-1]) + 1
                else:
                    stop = int(offsets[np.searchsorted(offsets, at, "right")])
                    sep = np.flatnonzero(~word[data[end:stop]])
                    end = end + int(sep[0]) + 1 if len(sep) else stop
        yield at, end
        at = end


def words_of(data: np.ndarray, offsets: np.ndarray, word: np.ndarray, lower: bool = True, table: np.ndarray | None = None) -> Words:
    """Words of all documents; ``table`` maps bytes before hashing (default: A-Z lower-cased)."""
    starts, ends, hashes = [], [], []
    marks = np.unique(offsets[(offsets > 0) & (offsets < len(data))])
    for at, end in _chunks(data, offsets, word[_LOWER] if lower else word):
        b = data[at:end]
        if lower:
            b = _LOWER[b]
        inside = word[b]
        cut = marks[np.searchsorted(marks, at, "right") : np.searchsorted(marks, end, "left")] - at
        before = np.concatenate([[False], inside[:-1]])
        after = np.concatenate([inside[1:], [False]])
        before[cut] = False
        after[cut - 1] = False
        s, e = np.flatnonzero(inside & ~before), np.flatnonzero(inside & ~after) + 1
        hashes.append(word_hashes(b if table is None else table[b], s, e))
        starts.append(s + at)
        ends.append(e + at)
    join = lambda x, t: np.concatenate(x) if x else np.zeros(0, t)
    starts, ends, hashes = join(starts, np.int64), join(ends, np.int64), join(hashes, np.uint64)
    return Words(starts, ends, hashes, np.searchsorted(starts, offsets))


def window_hashes(words: np.ndarray, size: int) -> np.ndarray:
    """Hash of every run of ``size`` words (runs across documents included)."""
    n = len(words) - size + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    out = np.full(n, size, dtype=np.uint64)
    for k in range(size):
        out = out * _U(0xC2B2AE3D27D4EB4F) + words[k : k + n]
        out ^= out >> _U(29)
    return mix64(out)


def shingles(words: Words, size: int) -> Iterator[np.ndarray]:
    """Per document the sorted distinct shingles; shorter texts are one shingle, empty ones none."""
    whole = window_hashes(words.hashes, size)
    for a, b in zip(words.first[:-1].tolist(), words.first[1:].tolist(), strict=True):
        if b - a >= size:
            yield np.unique(whole[a : b - size + 1])
        elif b > a:
            yield window_hashes(words.hashes[a:b], b - a)
        else:
            yield np.zeros(0, np.uint64)


def slices(batch: pa.RecordBatch, column: str, limit: int = 4 << 20) -> Iterator[pa.RecordBatch]:
    """The batch in slices of about ``limit`` text bytes (one row at least)."""
    _, offsets = text_buffer(batch.column(column))
    at = 0
    while at < batch.num_rows:
        end = max(at + 1, int(np.searchsorted(offsets, offsets[at] + limit, "right")) - 1)
        yield batch.slice(at, end - at)
        at = end
