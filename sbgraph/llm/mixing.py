"""Mixing sources to target weights by the cube method.

``targets`` shares all words among the sources by weight; a target stops at
``CAP`` times its source and the excess is shared again (water filling, with
windows over the sources only).  A document of a source with ratio
``target / size`` is taken ``floor(ratio)`` times, and once more with probability
``frac(ratio)``.  Those fractional probabilities are rounded by the cube method:
a *flight* moves undecided documents along the null space of the two balance
constraints (words and documents), so both totals stay as they are.  The large
documents of a group are settled first, each against small changes of all others;
then three documents at a time move, until at most two per group are undecided.
Groups are hash bins of bounded size within a source; what they leave undecided flies
again in the next round, and the last round *lands* what remains of each source (two
documents and twelve of no great size that waited) on the corner nearest to the word
total, and among corners as near in words, to the document total.  Where a document too
large to be offset leaves that corner far off, single decisions are changed.

Rows equal in id, source and size are one unit: of ``m`` rows, ``floor(m * frac)`` are
taken once more for certain, and one at most is left to the flight.

Draws come from hashes of the rows, so reruns agree.  Defined cases: null or
blank texts have size 0 and are taken 0 words; a null source is the last source;
a null doc_id is drawn like any other value; an empty table gives an empty mix; a source
of only empty texts has target 0.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .exprs import n_words_of
from .store import Store

WEIGHTS = (1.0, 2.0, 3.0)
CAP = 3
#: Documents that fly together at most (expected size of a bin).
GROUP = 4096
#: Documents of a source that wait for the landing.
LANDING = 12
#: A document above so many times its group's median size is large.
LARGE = 4
#: Sources whose targets may be broadcast; rows that one task writes of one unit, bins of a unit's rows.
SMALL, SPREAD, BINS = 1 << 16, 1024, 256
EPS = 1e-9


def targets(sizes: DataFrame, weights: tuple[float, ...] = WEIGHTS, cap: int = CAP) -> DataFrame:
    """source, source_size, source_docs, target; input rows: source, size."""
    per = sizes.groupBy("source").agg(F.sum("size").cast("long").alias("source_size"), F.count(F.lit(1)).alias("source_docs"))
    # One row per source from here on: windows without a key see the sources, never the documents.
    place = F.row_number().over(Window.orderBy(F.col("source").asc_nulls_last())) - 1
    w = F.element_at(F.array(*map(F.lit, weights)), (F.pmod(place, F.lit(len(weights))) + 1).cast("int"))
    per = per.withColumn("weight", w).withColumn("limit", (F.col("source_size") * cap).cast("double"))
    whole = Window.partitionBy(F.lit(0))
    by_ratio = whole.orderBy((F.col("limit") / F.col("weight")).asc(), F.col("source").asc_nulls_last())
    before = by_ratio.rowsBetween(Window.unboundedPreceding, -1)
    free = F.sum("source_size").over(whole) - F.coalesce(F.sum("limit").over(before), F.lit(0.0))
    left = F.sum("weight").over(whole) - F.coalesce(F.sum("weight").over(before), F.lit(0.0))
    per = per.withColumn("capped", free / left * F.col("weight") > F.col("limit"))
    spent = F.sum(F.when(F.col("capped"), F.col("limit")).otherwise(0.0)).over(whole)
    open_w = F.sum(F.when(F.col("capped"), 0.0).otherwise(F.col("weight"))).over(whole)
    level = (F.sum("source_size").over(whole) - spent) / open_w
    share = F.when(F.col("capped"), F.col("limit")).otherwise(F.least(level * F.col("weight"), F.col("limit")))
    return per.withColumn("target", F.coalesce(share, F.lit(0.0))).select("source", "source_size", "source_docs", "target")


def _settle(x: np.ndarray, sizes: np.ndarray, large: np.ndarray, rng: np.random.Generator) -> np.ndarray:
    """Decides the given entries one by one; all undecided entries move a little to keep both totals."""
    x, s = x.copy(), sizes / max(sizes.mean(), 1e-9)
    for a in large.tolist():
        while EPS < x[a] < 1 - EPS:
            at = np.flatnonzero((x > EPS) & (x < 1 - EPS))
            at = at[at != a]
            room = np.minimum(x[at], 1 - x[at])  # entries near a bound move less
            basis = np.stack([room, room * s[at]])
            system = basis @ np.stack([np.ones(len(at)), s[at]]).T
            if len(at) > 2 and np.linalg.cond(system) < 1e9:
                v = -np.linalg.solve(system.T, np.array([1.0, s[a]])) @ basis
            elif system[1, 1] > 0:  # all others are of one size: the words alone are kept
                v = -s[a] / system[1, 1] * basis[1]
            else:
                break
            v = np.concatenate([[1.0], v])
            own = np.concatenate([[a], at])
            with np.errstate(divide="ignore", invalid="ignore"):
                up = np.min(np.where(v > 0, (1 - x[own]) / v, np.where(v < 0, x[own] / -v, np.inf)))
                down = np.min(np.where(v > 0, x[own] / v, np.where(v < 0, (1 - x[own]) / -v, np.inf)))
            x[own] += (up if rng.random() * (up + down) < down else -down) * v
            near = np.round(x[own])
            x[own] = np.where(np.abs(x[own] - near) <= EPS, near, x[own])
    return x


def flight(x: np.ndarray, sizes: np.ndarray, rng: np.random.Generator) -> np.ndarray:
    """Cube flight: x with the same totals of ``sizes * x`` and ``x``, two entries undecided at most."""
    x, s = x.astype(float).tolist(), sizes.astype(float).tolist()
    waiting = [k for k, v in enumerate(x) if EPS < v < 1 - EPS]
    draws, used = rng.random(len(waiting) + 4), 0
    hand, at = [], 0
    while True:
        while len(hand) < 3 and at < len(waiting):
            hand.append(waiting[at])
            at += 1
        if len(hand) < 3:
            break
        a, b, c = (s[k] for k in hand)
        u = (b - c, c - a, a - b) if a != b or b != c else (1.0, -1.0, 0.0)  # keeps both totals
        up = min((1 - x[k]) / v if v > 0 else x[k] / -v for k, v in zip(hand, u, strict=True) if v)
        down = min(x[k] / v if v > 0 else (1 - x[k]) / -v for k, v in zip(hand, u, strict=True) if v)
        move = up if draws[used] * (up + down) < down else -down
        used += 1
        for k, v in zip(hand, u, strict=True):
            x[k] += move * v
            if x[k] <= EPS or x[k] >= 1 - EPS:
                x[k] = float(round(x[k]))
        hand = [k for k in hand if 0.0 < x[k] < 1.0]
    return np.array(x)


def land(x: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """Rounds the last undecided entries (LANDING + 2 at most) together: the corner nearest
    in words (steps of a two-thousandth of all words), then in documents."""
    x, left = x.copy(), np.flatnonzero((x > EPS) & (x < 1 - EPS))
    corners = (np.arange(1 << len(left))[:, None] >> np.arange(len(left)) & 1).astype(float)
    words = np.round(np.abs((corners - x[left]) @ sizes[left]), 6)
    docs = np.round(np.abs((corners - x[left]).sum(axis=1)), 6)
    best = np.lexsort((words, docs, np.floor(words / (1 + (sizes @ x) / 2000))))[0]
    x[left] = corners[best]
    return np.round(x)


def mend(x: np.ndarray, sizes: np.ndarray, wanted: float) -> np.ndarray:
    """Where the corner is off by over a two-thousandth, decisions are changed, large documents first.

    That happens where one document outweighs all that others can offset.
    """
    x, off = x.copy(), float(sizes @ x) - wanted
    if abs(off) > 1 + wanted / 2000:
        for k in np.argsort(-sizes, kind="stable").tolist():
            if 0 < sizes[k] <= abs(off) and x[k] == (off > 0):
                off -= sizes[k] if off > 0 else -sizes[k]
                x[k] = 1 - x[k]
    return x


def _fly(last: bool):
    def run(rows: pd.DataFrame) -> pd.DataFrame:
        # Large documents come first, so that what stays undecided is small.
        rows = rows.sort_values(["size", "draw"], ascending=[False, True], kind="stable", ignore_index=True)
        rng = np.random.default_rng(int(np.bitwise_xor.reduce(rows["draw"].to_numpy())) & (2**63 - 1))
        size = rows["size"].to_numpy()
        x = _settle(rows["x"].to_numpy(), size, np.flatnonzero(size > LARGE * np.median(size)), rng)
        open_ = np.flatnonzero((x > EPS) & (x < 1 - EPS))
        if last:  # documents of all sizes that are left wait for the landing
            open_ = np.delete(open_, np.linspace(0, len(open_) - 1, min(LANDING, len(open_))).astype(int))
        x[open_] = flight(x[open_], size[open_], rng)
        return rows.assign(x=mend(land(x, size), size, float(size @ rows["x"].to_numpy())) if last else x)

    return run


def _round(rows: DataFrame, bins, last: bool) -> DataFrame:
    salted = rows.withColumn("bin", F.pmod(F.xxhash64("draw", F.lit("bin")), bins))
    return salted.groupBy("source", "bin").applyInPandas(_fly(last), salted.schema).drop("bin")


def inclusions(rows: DataFrame, store: Store, group: int = GROUP) -> DataFrame:
    """Rows with ``x`` (a probability) rounded to 0 or 1, balanced per source.

    Input: source, n (rows of the source), size, x, draw and any other columns.
    """
    most = rows.agg(F.max("n")).first()[0] or 0
    done, level = [], 0
    while True:
        last = most <= group
        bins = F.lit(1) if last else F.greatest(F.lit(1), F.ceil(F.col("n") / group))
        flown = store.put(f"flight{level}", _round(rows.where((F.col("x") > 0) & (F.col("x") < 1)), bins, last))
        done.append(rows.where((F.col("x") <= 0) | (F.col("x") >= 1)) if level == 0 else None)
        if last:
            done.append(flown)
            break
        open_ = (F.col("x") > 0) & (F.col("x") < 1)
        done.append(flown.where(~open_))
        rows = flown.where(open_)
        counts = rows.groupBy("source").agg(F.count(F.lit(1)).alias("__n")).withColumnRenamed("source", "__source")
        rows = rows.join(counts, F.col("source").eqNullSafe(F.col("__source"))).withColumn("n", F.col("__n")).drop("__n", "__source")
        most, level = counts.agg(F.max("__n")).first()[0] or 0, level + 1
    whole = [d for d in done if d is not None]
    out = whole[0]
    for d in whole[1:]:
        out = out.unionByName(d)
    return out


def mix(docs: DataFrame, weights: tuple[float, ...] = WEIGHTS, cap: int = CAP, group: int = GROUP, keep_rows: bool = False) -> DataFrame:
    """doc_id, size, source_size, target, taken of every row (and ``copies``).

    ``keep_rows`` returns the input's own rows instead, each as often as taken.
    """
    store = Store(docs.sparkSession)
    base = docs.select(F.col("`doc_id`").alias("doc_id"), F.col("`source`").alias("source"), n_words_of(F.col("`text`")).alias("size"))
    units = store.put("units", base.groupBy("doc_id", "source", "size").agg(F.count(F.lit(1)).alias("m")))
    wanted = store.put("targets", targets(units.select("source", (F.col("size") * F.col("m")).alias("size")), weights, cap)).withColumnRenamed("source", "__source")
    rows = units.join(F.broadcast(wanted) if wanted.count() <= SMALL else wanted, F.col("source").eqNullSafe(F.col("__source"))).drop("__source")
    ratio = F.when(F.col("source_size") > 0, F.least(F.col("target") / F.col("source_size"), F.lit(float(cap)))).otherwise(0.0)
    draw = F.xxhash64(F.coalesce(F.col("doc_id").cast("string"), F.lit("null")), "source", "size", F.lit("cube"))
    rows = rows.withColumn("draw", draw).withColumn("whole", F.floor(ratio + F.lit(EPS)).cast("int")).withColumn("x", (ratio - F.col("whole")) * F.col("m"))
    # Rows of a unit that are taken once more in any case, and the share that is left of one row.
    rows = rows.withColumn("more", F.greatest(F.lit(0), F.floor(F.col("x") + F.lit(EPS))).cast("long")).withColumn("x", F.col("x") - F.col("more"))
    rows = rows.withColumn("x", F.when(F.col("x") > EPS, F.col("x")).otherwise(0.0)).withColumnRenamed("source_docs", "n")
    flown = inclusions(rows, store, group).withColumn("more", F.col("more") + F.col("x").cast("long"))
    if keep_rows:
        return _copies(docs, flown.select("doc_id", "source", "size", "m", "whole", "more"))
    many = _spread(flown, F.col("m"))
    copies = (F.col("whole") + F.when(F.col("no") <= F.col("more"), 1).otherwise(0)).cast("int").alias("copies")
    return many.select("doc_id", "size", "source_size", "target", (F.col("size") * copies).alias("taken"), copies)


def _spread(rows: DataFrame, times: Column) -> DataFrame:
    """Every row as often as ``times`` says, with ``no`` from 1; a row of very many is dealt to several tasks."""
    step = F.lit(SPREAD).cast("long")
    held = rows.withColumn("__n", times.cast("long"))
    few = held.where(F.col("__n") <= step).withColumn("__k", F.lit(0).cast("long"))
    lots = held.where(F.col("__n") > step).withColumn("__k", F.explode(F.sequence(F.lit(0).cast("long"), F.floor((F.col("__n") - 1) / step))))
    lots = lots.repartition(F.xxhash64("__k", *[F.col(f"`{c}`") for c, t in rows.dtypes if not t.startswith("map")]))
    both = few.unionByName(lots).where("__n > 0")
    no = F.sequence(F.col("__k") * step + 1, F.least((F.col("__k") + 1) * step, F.col("__n")))
    return both.withColumn("no", F.explode(no)).drop("__n", "__k")


def _copies(docs: DataFrame, decided: DataFrame) -> DataFrame:
    """The rows of the documents, each as often as it is taken.

    Of a unit of several rows, those of the least hashes are taken once more; equal rows are
    counted, not numbered.
    """
    cols = docs.columns
    decided = decided.where("whole > 0 OR more > 0").select(F.col("doc_id").alias("__d"), F.col("source").alias("__s"), F.col("size").alias("__z"), "m", "whole", "more")
    rows = docs.select(F.struct(*[F.col(f"`{c}`") for c in cols]).alias("row"), F.col("`doc_id`").alias("doc_id"), F.col("`source`").alias("source"), n_words_of(F.col("`text`")).alias("size"))
    both = rows.join(decided, F.col("doc_id").eqNullSafe(F.col("__d")) & F.col("source").eqNullSafe(F.col("__s")) & (F.col("size") == F.col("__z")))
    single = both.where("m = 1").select("row", (F.col("whole") + F.col("more")).alias("times"))
    unit, place = ["__d", "__s", "__z"], F.xxhash64("row")
    equal = both.where("m > 1").groupBy("row", *unit, "whole", "more").agg(F.count(F.lit(1)).alias("c"))
    equal = equal.withColumn("bin", F.pmod(place, F.lit(BINS)))
    # Rows of a unit are numbered inside hash bins, and a bin goes on where the bins before it end.
    before = lambda w: F.coalesce(F.sum("c").over(w.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    bins = equal.groupBy(*unit, "bin").agg(F.sum("c").alias("c")).select(*[F.col(c).alias(f"{c}_b") for c in (*unit, "bin")], before(Window.partitionBy(*unit).orderBy("bin")).alias("base"))
    met = equal.join(bins, [F.col(c).eqNullSafe(F.col(f"{c}_b")) for c in (*unit, "bin")])
    met = met.withColumn("base", F.col("base") + before(Window.partitionBy(*unit, "bin").orderBy(place, "row")))
    more = F.least(F.greatest(F.col("more") - F.col("base"), F.lit(0)), F.col("c"))
    several = met.select("row", (F.col("whole") * F.col("c") + more).alias("times"))
    many = _spread(single.unionByName(several), F.col("times"))
    return many.select(*[F.col("row")[c].alias(c) for c in cols])
