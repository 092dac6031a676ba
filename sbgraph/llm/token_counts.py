"""Token counts by offset-mapped attribution.

A whole text is encoded once; its tokens' character spans are joined to the text's
sections (an interval join by binary search, inside the row).  A token that crosses a
boundary is allocated by an explicit rule:

* ``first`` / ``last``: the section of its first / last character,
* ``most``: the section that holds most of its characters, the earlier one on a tie,
* ``split``: shared in proportion to the characters held (counts are doubles).

Sections are the lines of a text (a line keeps its newline), or those whose start
characters an array column gives.  Defined cases: null and empty texts have no
sections and no tokens; characters before the first given start belong to the first
section; unsorted or repeated starts are put in order once; repeated rows are counted
row by row; other columns are ignored; an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .tokens import VOCABULARY, span_parts, spans_of

RULES = ("first", "last", "most", "split")


def line_starts(text: str) -> np.ndarray:
    """First characters of the lines of a text."""
    if not text:
        return np.zeros(0, np.int64)
    points = np.frombuffer(text.encode("utf-32-le"), dtype="<u4")
    starts = np.concatenate([[0], np.flatnonzero(points == 10) + 1])
    return starts[starts < len(points)]


def allocate(spans: np.ndarray, starts: np.ndarray, rule: str = "most") -> tuple[np.ndarray, int]:
    """Tokens per section and the number of tokens that cross a boundary."""
    out = np.zeros(len(starts))
    if not len(starts) or not len(spans):
        return out, 0
    low = np.maximum(np.searchsorted(starts, spans[:, 0], "right") - 1, 0)
    high = np.maximum(np.searchsorted(starts, np.maximum(spans[:, 1] - 1, spans[:, 0]), "right") - 1, low)
    crossing = np.flatnonzero(high > low)
    if rule == "last":
        return np.bincount(high, minlength=len(starts)).astype(float), len(crossing)
    if rule == "first":
        return np.bincount(low, minlength=len(starts)).astype(float), len(crossing)
    out += np.bincount(np.delete(low, crossing), minlength=len(starts))
    for k in crossing:
        a, b = spans[k]
        edges = np.concatenate([[a], starts[low[k] + 1 : high[k] + 1], [b]])
        held = np.diff(edges)
        if rule == "most":
            out[low[k] + int(np.argmax(held))] += 1
        else:
            out[low[k] : high[k] + 1] += held / (b - a)
    return out, len(crossing)


def attribute(docs: DataFrame, rule: str = "most", sections: str | None = None, vocabulary: str = VOCABULARY) -> DataFrame:
    """doc_id, n_tokens, n_sections, n_crossing and section_tokens of every row."""
    if rule not in RULES:
        raise ValueError(f"rule must be one of {RULES}")
    kind = "double" if rule == "split" else "long"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts = span_parts(vocabulary)
        for batch in batches:
            texts = [t or "" for t in batch.column("text").to_pylist()]
            given = batch.column("starts").to_pylist() if sections else [None] * len(texts)
            counts, crossing, total = [], [], []
            for text, starts in zip(texts, given, strict=True):
                own = line_starts(text) if not sections else np.unique(np.array(starts or [], dtype=np.int64))
                spans = spans_of(*parts.of(text))
                per, crossed = allocate(spans, own, rule)
                counts.append(per.tolist() if rule == "split" else per.astype(np.int64).tolist())
                crossing.append(crossed)
                total.append(len(spans))
            values = pa.array(counts, pa.list_(pa.float64() if rule == "split" else pa.int64()))
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(total, pa.int64()), pa.array([len(c) for c in counts], pa.int64()), pa.array(crossing, pa.int64()), values], names=["doc_id", "n_tokens", "n_sections", "n_crossing", "section_tokens"])

    own = [F.col(f"`{sections}`").alias("starts")] if sections else []
    rows = docs.select(F.col("`doc_id`").cast("long").alias("doc_id"), F.col("`text`").alias("text"), *own)
    return rows.mapInArrow(run, f"doc_id long, n_tokens long, n_sections long, n_crossing long, section_tokens array<{kind}>")
