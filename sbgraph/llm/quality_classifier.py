"""Quality classifier: random-indexing word vectors, a two-layer network, calibration.

1. *Random indexing* over all documents: every word has a sparse ternary index vector
   (a few +1 / -1 at hashed places).  The context vector of a word is the sum of the
   index vectors of its neighbours.  Words are kept apart by their 64-bit hashes, so the
   statistics grow with the vocabulary; they are a distributed table.  Documents are dealt
   into buckets; a bucket sends its sums by part of the hash range, a part adds up its
   words over all buckets and answers each bucket with the words that it sent.  Texts go to
   their buckets compressed and are read in slices, so that a bucket may be large: the larger
   it is, the fewer words lie in several buckets.
2. A text is pooled into the mean of its tokens' vectors: words, the words' shapes
   (letter case, digits and marks kept) and a mark for a word that repeats the one
   before it.  Each token's vector is its damped context vector beside its index vector.
3. A two-layer network (numpy, Adam) is fitted on a sample of labelled documents, at
   most ``SAMPLE`` of them in hash order; its temperature is fitted on a part it was not
   trained on, so the probabilities are calibrated.

Labels, language, source and ids are never inputs of a score.  Defined cases: null and
empty texts pool to zeros and get the score of zeros; null or missing labels are not
used; a single class or no label at all gives the constant score of its share (0.5
without labels); repeated rows are scored row by row; long texts are pooled whole; other
columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import kernels as K
from .store import Store

#: Dimensions and non-zeros of an index vector; six bits of a hash draw a non-zero.
DIM, NONZERO = 32, 8
#: Text bytes of a bucket (a fifth as many words); fewer texts have up to ``WIDE`` buckets of ``LEAST`` bytes.
BUCKET, LEAST, WIDE = 168 << 20, 32 << 20, 6
#: Parts of the hash range for each bucket.
PARTS = 4
#: Words whose sums are formed, neighbours that are drawn, text bytes that are read and words that are gathered at a time.
BLOCK, DRAWN, SLICE, GATHERED = 1 << 15, 1 << 18, 1 << 19, 1 << 22
#: Level of the texts' compression, and the kind of the numbers in which features are kept between training and scoring.
LEVEL, KEPT = 6, np.float16
#: Labelled documents that may be fitted (the documented bound), and held-back share.
SAMPLE, CALIBRATION = 12_000, 5
HIDDEN, EPOCHS, BATCH, RATE, DECAY = 24, 30, 128, 4e-3, 1e-4
#: Predicted 1 from this score on.
THRESHOLD = 0.3

_SHAPE = np.arange(256, dtype=np.uint8)
_SHAPE[ord("a") : ord("z") + 1] = ord("a")
_SHAPE[128:] = ord("a")
_SHAPE[ord("A") : ord("Z") + 1] = ord("A")
_SHAPE[ord("0") : ord("9") + 1] = ord("0")
_REPEAT = np.uint64(0x5851F42D4C957F2D)


def _draws(hashes: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Place and sign of each non-zero of the words' index vectors."""
    draw = K.mix64(hashes + np.uint64(5))
    for k in range(NONZERO):
        six = (draw >> np.uint64(6 * k)).astype(np.int64) & 63
        yield six >> 1, np.where(six & 1, 1.0, -1.0)


def index_vectors(hashes: np.ndarray) -> np.ndarray:
    """The ternary index vectors of words (places drawn twice add up), of unit length on average."""
    out, rows = np.zeros((len(hashes), DIM), np.float32), np.arange(len(hashes))
    for place, sign in _draws(hashes):
        out[rows, place] += sign
    return out / np.float32(np.sqrt(NONZERO))


def _shapes(data: np.ndarray, offsets: np.ndarray, words: np.ndarray, first: np.ndarray) -> np.ndarray:
    """Hashes of the words' shapes; a word that repeats the one before it has a shape of its own."""
    shapes = K.words_of(data, offsets, K.SPACED, lower=False, table=_SHAPE)
    same = np.zeros(len(words), bool)
    same[1:] = words[1:] == words[:-1]
    inner = first[:-1]
    same[inner[inner < len(same)]] = False
    return np.where(same, _REPEAT, shapes.hashes)


def _pack(values: np.ndarray) -> bytes:
    """Whole numbers as compressed byte planes (the first byte is their width)."""
    zigzag = ((values << 1) ^ (values >> 63)).astype("<u8")
    width = max(1, (int(zigzag.max(initial=0)).bit_length() + 7) // 8)
    planes = zigzag.view(np.uint8).reshape(*values.shape, 8)[:, :, :width].transpose(2, 1, 0)
    return bytes([width]) + pa.compress(np.ascontiguousarray(planes).tobytes(), codec="zstd", asbytes=True)


def _unpack(blob: bytes, rows: int) -> np.ndarray:
    """rows x (DIM + 1) numbers of a packed table."""
    width = blob[0]
    planes = pa.decompress(blob[1:], decompressed_size=width * (DIM + 1) * rows, codec="zstd", asbytes=True)
    zigzag = np.zeros((rows, DIM + 1, 8), np.uint8)
    zigzag[:, :, :width] = np.frombuffer(planes, np.uint8).reshape(width, DIM + 1, rows).transpose(2, 1, 0)
    zigzag = zigzag.view("<u8")[:, :, 0]
    return (zigzag >> np.uint64(1)).astype(np.int64) ^ -(zigzag & np.uint64(1)).astype(np.int64)


def _pack_names(names: np.ndarray) -> bytes:
    """Sorted hashes: their number, then the compressed byte planes of the steps between them."""
    steps = np.diff(names, prepend=np.uint64(0)).astype("<u8")
    planes = np.ascontiguousarray(steps.view(np.uint8).reshape(-1, 8).T).tobytes()
    return len(names).to_bytes(8, "little") + pa.compress(planes, codec="zstd", asbytes=True)


def _unpack_names(blob: bytes) -> np.ndarray:
    n = int.from_bytes(blob[:8], "little")
    planes = pa.decompress(blob[8:], decompressed_size=8 * n, codec="zstd", asbytes=True)
    return np.cumsum(np.ascontiguousarray(np.frombuffer(planes, np.uint8).reshape(8, n).T).view("<u8").ravel(), dtype=np.uint64)


def _slices(table: pa.Table) -> Iterator[pa.RecordBatch]:
    """The rows of a bucket's packed texts, a slice at a time."""
    for blob in table.column("texts"):
        for batch in pa.ipc.open_stream(blob.as_buffer()):
            yield from K.slices(batch, "text", SLICE)


def _words(table: pa.Table) -> tuple[list[np.ndarray], list[np.ndarray], np.ndarray]:
    """Per slice of a bucket: the words' places in its names, and first words; and the sorted distinct words."""
    at, firsts, held, size, names = [], [], [], 0, np.zeros(0, np.uint64)
    for part in _slices(table):
        words = K.words_of(*K.text_buffer(part.column("text")), K.SPACED, lower=False)
        at.append(words.hashes)
        firsts.append(words.first)
        held.append(np.unique(words.hashes))
        size += len(held[-1])
        if size >= GATHERED:
            names, held, size = np.unique(np.concatenate([names, *held])), [], 0
    names = np.unique(np.concatenate([names, *held]))
    del held
    for k, words in enumerate(at):  # hashes go as places come
        at[k] = np.searchsorted(names, words).astype(np.int32)
    return at, firsts, names


def _texts_packed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows (bucket, doc_id, text) as one compressed row per bucket and batch."""
    for batch in batches:
        where = batch.column("bucket").to_numpy()
        order = np.argsort(where, kind="stable")
        names, first = np.unique(where[order], return_index=True)
        blobs = []
        for a, b in zip(first, [*first[1:], len(order)], strict=True):
            own, sink = batch.select(["doc_id", "text"]).take(pa.array(order[a:b])), pa.BufferOutputStream()
            with pa.ipc.new_stream(sink, own.schema, options=pa.ipc.IpcWriteOptions(compression=pa.Codec("zstd", LEVEL))) as out:
                out.write_batch(own)
            blobs.append(sink.getvalue().to_pybytes())
        yield pa.RecordBatch.from_arrays([pa.array(names, pa.int64()), pa.array(blobs, pa.binary())], names=["bucket", "texts"])


def _texts(table: pa.Table) -> pa.Table:
    """doc_id and text of a bucket's packed rows."""
    return pa.concat_tables([pa.ipc.open_stream(x.as_buffer()).read_all() for x in table.column("texts")])


def _parts(names: np.ndarray, parts: int) -> list[tuple[int, int, int]]:
    """(part, begin, end) of sorted words: parts are equal ranges of the hashes."""
    part = ((names >> np.uint64(32)) * np.uint64(parts) >> np.uint64(32)).astype(np.int64)
    edges = np.flatnonzero(np.diff(part, prepend=-1)).tolist()
    return [(int(part[a]), a, b) for a, b in zip(edges, [*edges[1:], len(names)], strict=True)]


def _joined(at: list[np.ndarray], firsts: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray]:
    """The words of all slices, and whether the next one is a neighbour."""
    met = np.ones(sum(map(len, at)), bool)
    base = 0
    for own, first in zip(at, firsts, strict=True):
        met[base + first[1:][first[1:] > 0] - 1] = False
        base += len(own)
    return np.concatenate([np.zeros(0, np.int32), *at]), met


def _sums_of(at: np.ndarray, met: np.ndarray, names: np.ndarray, begin: int, end: int) -> np.ndarray:
    """Summed neighbour index vectors and counts (words x (DIM + 1)) of a range of a bucket's names."""
    out = np.zeros((end - begin, DIM + 1), np.int64)
    for base in range(begin, end, BLOCK):
        size = min(BLOCK, end - base)
        inside = (at >= base) & (at < base + size)
        out[base - begin : base - begin + size, DIM] = np.bincount(at[inside] - base, minlength=size)
        for mine, theirs in ((slice(None, -1), slice(1, None)), (slice(1, None), slice(None, -1))):
            place = np.flatnonzero(inside[mine] & met[:-1])
            for c in range(0, len(place), DRAWN):
                own = place[c : c + DRAWN]
                me, other = (at[mine][own].astype(np.int64) - base) * DIM, names[at[theirs][own]]
                for cell, sign in _draws(other):
                    out[base - begin : base - begin + size, :DIM] += np.bincount(me + cell, weights=sign, minlength=size * DIM).reshape(size, DIM).astype(np.int64)
    return out


def _sums(found: list[tuple], names: np.ndarray) -> np.ndarray:
    """The same for all names."""
    at, firsts = [np.searchsorted(names, f[1]).astype(np.int32) for f in found], [f[2] for f in found]
    return _sums_of(*_joined(at, firsts), names, 0, len(names))


def context_vectors(sums: np.ndarray, tokens: int) -> tuple[np.ndarray, np.ndarray]:
    """Unit context vectors, damped for frequent words, and the damping."""
    unit = sums[:, :DIM] / np.maximum(np.linalg.norm(sums[:, :DIM], axis=1, keepdims=True), 1e-9)
    damp = 1 / np.sqrt(1 + sums[:, DIM] / max(tokens, 1) * 1000)
    return (unit * damp[:, None]).astype(np.float32), damp


def _pool(values: np.ndarray, first: np.ndarray) -> np.ndarray:
    """Mean row of each document."""
    n = np.diff(first)
    sums = np.add.reduceat(np.concatenate([values, np.zeros((1, values.shape[1]), values.dtype)]), np.minimum(first[:-1], len(values)), axis=0)
    return sums * (n > 0)[:, None] / np.maximum(n, 1)[:, None]


def _measure(docs: DataFrame) -> tuple[int, int]:
    """Text bytes and words of all documents."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        size = tokens = 0
        for batch in batches:
            for part in K.slices(batch, "text", 1 << 21):
                data, offsets = K.text_buffer(part.column("text"))
                inside = K.SPACED[data]
                begins = inside.copy()
                begins[1:] &= ~inside[:-1]
                at = np.unique(offsets[(offsets > 0) & (offsets < len(data))])
                begins[at] = inside[at]
                size, tokens = size + len(data), tokens + int(begins.sum())
        yield pa.RecordBatch.from_arrays([pa.array([size], pa.int64()), pa.array([tokens], pa.int64())], names=["size", "tokens"])

    r = docs.select("text").mapInArrow(run, "size long, tokens long").agg(F.sum("size").alias("size"), F.sum("tokens").alias("tokens")).first()
    return r["size"] or 0, r["tokens"] or 0


#: Mean word vector, mean shape vector, log length.
WIDTH = 2 * DIM + DIM + 1


def features(docs: DataFrame, kept: type = np.float32) -> DataFrame:
    """doc_id and pooled features (x: bytes of numbers of that kind) of every row."""
    rows = docs.select(F.col("`doc_id`").cast("long").alias("doc_id"), F.col("`text`").alias("text"))
    size, tokens = _measure(rows)
    buckets = max(1, -(-size // BUCKET), -(-5 * tokens // BUCKET), min(WIDE, -(-size // LEAST)))
    parts = PARTS * buckets
    dealt = rows.select(F.pmod(F.xxhash64("doc_id", "text"), F.lit(buckets)).alias("bucket"), "doc_id", "text").mapInArrow(_texts_packed, "bucket long, texts binary")

    def gather(table: pa.Table) -> pa.Table:
        at, firsts, names = _words(table)
        at, met = _joined(at, firsts)
        own = _parts(names, parts)
        columns = [[table.column("bucket")[0].as_py()] * len(own), [p for p, _, _ in own], [_pack_names(names[a:b]) for _, a, b in own], [_pack(_sums_of(at, met, names, a, b)) for _, a, b in own]]
        K.give_back()
        return pa.table([pa.array(c, t) for c, t in zip(columns, (pa.int64(), pa.int64(), pa.binary(), pa.binary()), strict=True)], names=["bucket", "part", "words", "sums"])

    def add(table: pa.Table) -> pa.Table:
        sent = [_unpack_names(w) for w in table.column("words").to_pylist()]
        names = np.unique(np.concatenate(sent))
        total = np.zeros((len(names), DIM + 1), np.int64)
        for own, blob in zip(sent, table.column("sums"), strict=True):
            total[np.searchsorted(names, own)] += _unpack(blob.as_py(), len(own))
        answers = [_pack(total[np.searchsorted(names, own)]) for own in sent]
        return pa.table([table.column("bucket"), table.column("part"), pa.array(answers, pa.binary())], names=["bucket", "part", "sums"])

    def pool(texts: pa.Table, answers: pa.Table) -> pa.Table:
        at, firsts, names = _words(texts)
        sums = dict(zip(answers.column("part").to_pylist(), answers.column("sums"), strict=True))
        context, damp = np.zeros((len(names), DIM), np.float32), np.zeros(len(names))
        for part, a, b in _parts(names, parts):
            context[a:b], damp[a:b] = context_vectors(_unpack(sums[part].as_py(), b - a), tokens)
        ids, out = [pa.array([], pa.int64())], []
        for part, words, first in zip(_slices(texts), at, firsts, strict=True):
            own, word = np.unique(words, return_inverse=True)
            vectors = np.concatenate([context[own], (index_vectors(names[own]) * damp[own][:, None]).astype(np.float32)], axis=1)
            kinds, kind = np.unique(_shapes(*K.text_buffer(part.column("text")), words, first), return_inverse=True)
            means = [_pool(vectors[word], first), _pool(index_vectors(kinds)[kind], first)]
            x = np.concatenate([*means, np.log1p(np.diff(first))[:, None] / 10], axis=1).astype(kept)
            ids.append(part.column("doc_id"))
            out += [r.tobytes() for r in x]
        K.give_back()
        return pa.table([pa.chunked_array(ids, pa.int64()).combine_chunks(), pa.array(out, pa.binary())], names=["doc_id", "x"])

    sent = dealt.groupBy("bucket").applyInArrow(gather, "bucket long, part long, words binary, sums binary")
    answers = sent.groupBy("part").applyInArrow(add, "bucket long, part long, sums binary")
    return dealt.groupBy("bucket").cogroup(answers.groupBy("bucket")).applyInArrow(pool, "doc_id long, x binary")


def _rows(blobs: list[bytes]) -> np.ndarray:
    """The features of rows, whichever kind they are kept in."""
    if not len(blobs):
        return np.zeros((0, WIDTH))
    return np.frombuffer(b"".join(blobs), f"<f{len(blobs[0]) // WIDTH}").reshape(-1, WIDTH).astype(np.float64)


@dataclass
class Network:
    """A two-layer network over standardised features."""

    mean: np.ndarray
    scale: np.ndarray
    w1: np.ndarray
    b1: np.ndarray
    w2: np.ndarray
    b2: float
    temperature: float = 1.0

    def logit(self, x: np.ndarray) -> np.ndarray:
        hidden = np.maximum((x - self.mean) / self.scale @ self.w1 + self.b1, 0)
        return hidden @ self.w2 + self.b2

    def score(self, x: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(self.logit(x) / self.temperature, -30, 30)))


def constant(width: int, share: float) -> Network:
    share = min(max(share, 1e-6), 1 - 1e-6)
    return Network(np.zeros(width), np.ones(width), np.zeros((width, 1)), np.zeros(1), np.zeros(1), float(np.log(share / (1 - share))))


def fit(x: np.ndarray, y: np.ndarray, seed: int = 11) -> Network:
    """Trains on four fifths of the rows and fits the temperature on the rest."""
    if len(np.unique(y)) < 2 or len(y) < 10:
        return constant(x.shape[1], float(y.mean()) if len(y) else 0.5)
    rng = np.random.default_rng(seed)
    order = rng.permutation(len(y))
    held, train = order[:: CALIBRATION], np.setdiff1d(order, order[:: CALIBRATION])
    mean, scale = x[train].mean(axis=0), x[train].std(axis=0) + 1e-3
    z, t = (x[train] - mean) / scale, y[train].astype(float)
    p = [rng.normal(0, np.sqrt(2 / z.shape[1]), (z.shape[1], HIDDEN)), np.zeros(HIDDEN), rng.normal(0, np.sqrt(1 / HIDDEN), HIDDEN), np.zeros(1)]
    m, v, step = [np.zeros_like(a) for a in p], [np.zeros_like(a) for a in p], 0
    for _ in range(EPOCHS):
        for at in np.array_split(rng.permutation(len(t)), max(1, len(t) // BATCH)):
            hidden = np.maximum(z[at] @ p[0] + p[1], 0)
            wrong = (1 / (1 + np.exp(-np.clip(hidden @ p[2] + p[3], -30, 30))) - t[at]) / len(at)
            back = wrong[:, None] * p[2] * (hidden > 0)
            grads = [z[at].T @ back + DECAY * p[0], back.sum(axis=0), hidden.T @ wrong + DECAY * p[2], np.array([wrong.sum()])]
            step += 1
            for k, g in enumerate(grads):
                m[k] = 0.9 * m[k] + 0.1 * g
                v[k] = 0.999 * v[k] + 0.001 * g * g
                p[k] -= RATE * (m[k] / (1 - 0.9**step)) / (np.sqrt(v[k] / (1 - 0.999**step)) + 1e-8)
    net = Network(mean, scale, p[0], p[1], p[2], float(p[3][0]))
    logit, truth = net.logit(x[held]), y[held]
    loss = lambda s: np.mean(np.logaddexp(0, -np.where(truth == 1, 1, -1) * logit / s))
    net.temperature = float(min(np.exp(np.linspace(-1.5, 2.5, 81)), key=loss))
    return net


def held_out(doc_id: Column) -> Column:
    """The fold that is never learned from."""
    return F.crc32(doc_id.cast("string").cast("binary")) % 5 == 0


def train(known_x: DataFrame, labels: DataFrame, label: str = "quality", sample: int = SAMPLE) -> Network:
    """A network from the features of labelled documents outside the held-out fold."""
    known = labels.select(F.col("`doc_id`").cast("long").alias("__id"), F.col(f"`{label}`").cast("long").alias("y")).where(F.col("y").isin(0, 1) & ~held_out(F.col("__id")))
    # The documented bound: at most ``sample`` labels, in hash order.
    known = known.orderBy(F.xxhash64("__id"), "__id", "y").limit(sample)
    # Of the texts of one doc_id one is fitted, so that no more rows than labels come to the driver.
    found = known_x.join(F.broadcast(known), F.col("doc_id") == F.col("__id")).groupBy("__id", "y").agg(F.min("x").alias("x")).select("y", "x").toPandas()
    x = _rows(found["x"].tolist())
    y = found["y"].to_numpy(np.int64)
    order = np.lexsort((*x.T, y)) if len(y) else slice(0)  # the order of rows from a join is not fixed
    return fit(x[order], y[order])


def score(known_x: DataFrame, network: Network) -> DataFrame:
    """doc_id and score of every row."""
    shared = known_x.sparkSession.sparkContext.broadcast(network)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x = _rows(batch.column("x").to_pylist())
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(shared.value.score(x))], names=["doc_id", "score"])

    return known_x.select("doc_id", "x").mapInArrow(run, "doc_id long, score double")


def classify(docs: DataFrame, labels: DataFrame, label: str = "quality", sample: int = SAMPLE) -> DataFrame:
    """doc_id, held_out, score, predicted of every row."""
    known_x = Store(docs.sparkSession).put("features", features(docs, KEPT))
    scored = score(known_x, train(known_x, labels, label, sample))
    return scored.select("doc_id", F.coalesce(held_out(F.col("doc_id")), F.lit(False)).alias("held_out"), "score", (F.col("score") >= THRESHOLD).cast("int").alias("predicted"))
