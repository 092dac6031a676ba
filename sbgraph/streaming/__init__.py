"""Streams of signed interactions."""

from __future__ import annotations

import functools
import uuid
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.errors import AnalysisException
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..functions import choose2, owner, total
from ..ingest import resolve_conflicts
from ..model import SignedGraph
from ..schemas import TOTAL
from ..sources import cut, for_each_batch, shared_folder

EVENTS = "event_id bigint, ts timestamp_ntz, user_id bigint, event_type string, value double, props string"


def read_events(spark: SparkSession, path: str, files_per_trigger: int = 1) -> DataFrame:
    """The events table as a stream."""
    return spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


def event_edges(events: DataFrame, lateness: str | None = "1 hour") -> DataFrame:
    """u, v, sign, ts, k1, k2, event_id of a stream (or table) of events."""
    code = F.get_json_object("props", "$.k").cast("long")
    rows = events.select(F.col("user_id").alias("u"), code.alias("v"), F.when(F.col("event_type") != "error", 1).otherwise(0).cast("byte").alias("sign"), F.col("ts").cast("timestamp").alias("ts"), F.col("event_id").alias("k1"), F.lit(0).cast("long").alias("k2"), "event_id").where("u IS NOT NULL AND v IS NOT NULL")
    return rows.withWatermark("ts", lateness) if rows.isStreaming and lateness else rows


def without_replays(edges: DataFrame) -> DataFrame:
    """Each event once, however often it is delivered within the watermark."""
    return edges.dropDuplicatesWithinWatermark(["event_id"]) if edges.isStreaming else edges.dropDuplicates(["event_id"])


def latest_signs(edges: DataFrame) -> DataFrame:
    """The latest sign per pair, by event time and not by arrival (update or complete mode)."""
    return edges.groupBy("u", "v").agg(F.max_by("sign", F.struct("ts", "k1", "k2", "sign")).alias("sign"))


STATE = "ts timestamp, k1 long, k2 long, sign byte"


def latest_signs_state(edges: DataFrame) -> DataFrame:
    """u, v, sign, ts: the latest sign per pair from a state of its own, in update mode.

    A row is emitted when it is the greatest by (ts, k1, k2, sign) that its pair has seen; rows
    older than the watermark are dropped.  A pair's state goes once the watermark has passed
    it: whatever may still come is later, so a sink that keeps the last row of a pair is right.
    """

    def update(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        best = state.get if state.exists else None
        was = best
        for rows in batches:
            for row in zip([x.to_pydatetime() for x in rows["ts"]], rows["k1"].tolist(), rows["k2"].tolist(), rows["sign"].tolist(), strict=True):
                best = row if best is None or row > tuple(best) else best
        state.update(tuple(best))
        # Milliseconds; the timeout has to lie behind the watermark.
        state.setTimeoutTimestamp(max(int(best[0].timestamp() * 1000), state.getCurrentWatermarkMs()) + 1)
        if best != was:
            yield pd.DataFrame({"u": [key[0]], "v": [key[1]], "sign": [best[3]], "ts": [best[0]]})

    rows = edges.select("u", "v", "ts", "k1", "k2", "sign")
    return rows.groupBy("u", "v").applyInPandasWithState(update, "u long, v long, sign byte, ts timestamp", STATE, "update", GroupStateTimeout.EventTimeTimeout)


class LatestTable:
    """A table of the latest signs, kept by merging batches (for ``foreachBatch``).

    Rows lie in hash buckets of u; a batch writes the buckets that it touches anew under its
    number, so a batch that is replayed replaces itself and other buckets are not read.
    """

    def __init__(self, spark: SparkSession, folder: str, buckets: int = 64) -> None:
        self.spark, self.folder, self.buckets = spark, folder, buckets
        self.schema = "u long, v long, sign byte, ts timestamp, k1 long, k2 long, bucket int, batch long"

    def _rows(self, before: int | None = None) -> DataFrame:
        try:
            rows = self.spark.read.schema(self.schema).parquet(self.folder)
        except AnalysisException:  # nothing is written yet
            return self.spark.createDataFrame([], self.schema)
        rows = rows if before is None else rows.where(F.col("batch") < before)
        last = rows.groupBy("bucket").agg(F.max("batch").alias("__last")).withColumnRenamed("bucket", "__bucket")
        return rows.join(F.broadcast(last), (F.col("bucket") == F.col("__bucket")) & (F.col("batch") == F.col("__last"))).drop("__bucket", "__last")  # ``buckets`` rows

    def merge(self, batch: DataFrame, number: int) -> None:
        """Merges interactions u, v, sign, ts, k1, k2."""
        fresh = batch.select("u", "v", "sign", "ts", "k1", "k2").withColumn("bucket", owner(F.col("u"), self.buckets))
        held = fresh.persist()
        touched = [r["bucket"] for r in held.select("bucket").distinct().collect()]  # ``buckets`` rows at most
        if touched:
            both = held.unionByName(self._rows(number).where(F.col("bucket").isin(touched)).drop("batch"))
            last = both.groupBy("bucket", "u", "v").agg(F.max(F.struct("ts", "k1", "k2", "sign")).alias("x")).select("u", "v", "x.sign", "x.ts", "x.k1", "x.k2", "bucket", F.lit(number).cast("long").alias("batch"))
            last.write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("bucket", "batch").parquet(self.folder)
        held.unpersist()

    def edges(self) -> DataFrame:
        return self._rows().select("u", "v", "sign")


def windowed_graphs(edges: DataFrame, length: str = "1 day", slide: str | None = None) -> DataFrame:
    """window, u, v, sign: the latest sign per pair in tumbling or sliding windows."""
    return edges.groupBy(F.window("ts", length, slide or length).alias("window"), "u", "v").agg(F.max_by("sign", F.struct("ts", "k1", "k2", "sign")).alias("sign"))


def session_graphs(edges: DataFrame, gap: str = "1 hour") -> DataFrame:
    """window, u, edges, positive: the sessions of a vertex of U."""
    return edges.groupBy(F.session_window("ts", gap).alias("window"), "u").agg(F.count(F.lit(1)).alias("edges"), F.sum(F.col("sign").cast("long")).alias("positive"))


def session_windows(edges: DataFrame, gap_minutes: int = 60) -> DataFrame:
    """window (start), u, v, sign: the latest sign per pair in sessions of the whole graph.

    A session ends where no interaction follows for ``gap_minutes``.  Sessions are found over
    the distinct minutes with interactions, which are few, and met by equal minutes.
    """
    minute = F.date_trunc("minute", F.col("ts"))
    busy = edges.select(minute.alias("minute")).distinct()
    # One row per minute from here on: the window without a key sees minutes, never interactions.
    order = Window.orderBy("minute")
    new = F.when(F.col("minute").cast("long") - F.lag("minute").over(order).cast("long") <= 60 * gap_minutes, 0).otherwise(1)
    numbered = busy.withColumn("new", new).withColumn("session", F.sum("new").over(order))
    starts = numbered.select("minute", F.min("minute").over(Window.partitionBy("session")).alias("start"))
    met = edges.withColumn("minute", minute).join(starts, "minute")
    return met.groupBy(F.struct("start").alias("window"), "u", "v").agg(F.max_by("sign", F.struct("ts", "k1", "k2", "sign")).alias("sign"))


def windowed_counts(edges: DataFrame) -> DataFrame:
    """start, balanced of every window (edges: window, u, v, sign): the window is part of every key."""
    # All columns get names of their own: the result table of a stream cannot be joined with itself otherwise.
    a = edges.select(F.col("window.start").alias("start"), F.col("u").alias("u1"), F.col("v").alias("v1"), F.col("sign").alias("s1"))
    b = edges.select(F.col("window.start").alias("start2"), F.col("u").alias("u2"), F.col("v").alias("v2"), F.col("sign").alias("s2"))
    same = F.when(F.col("s1") == F.col("s2"), 1).otherwise(0)
    held = a.join(b, (F.col("start") == F.col("start2")) & (F.col("u1") == F.col("u2"))).where("v1 < v2").groupBy("start", "v1", "v2").agg(F.sum(same).cast("long").alias("b1"), F.sum(1 - same).cast("long").alias("b2"))
    return held.groupBy("start").agg(total(choose2(F.col("b1")) + choose2(F.col("b2"))).cast("long").alias("balanced"))


class IncrementalTotal:
    """The balanced total kept up to date under batches of interactions.

    The state is two logs: edges with the order of their signs, and changes of the wedge counters
    of pairs of V.  A batch joins only the edges of the vertices of U that it touches, once as
    they were and once as they are; the difference of their wedges changes the counters of
    some pairs, and those pairs alone are looked up.  Logs are folded every ``fold`` batches.
    """

    def __init__(self, start: SignedGraph, fold: int = 16) -> None:
        self.fold, self.number = fold, 0
        order = [F.lit(None).cast("timestamp").alias("ts"), *(F.lit(None).cast("long").alias(c) for c in ("k1", "k2")), F.lit(0).cast("long").alias("no")]
        self.log = [cut(start.edges.select("u", "v", "sign", F.struct(*order).alias("o")))]
        self.pairs = [cut(self._wedges(self.log[0]))]
        self.total = int(self.pairs[0].agg(total(self._balanced("b1", "b2"))).first()[0])

    @staticmethod
    def _balanced(b1: str, b2: str) -> Column:
        return choose2(F.col(b1)) + choose2(F.col(b2))

    @staticmethod
    def _wedges(edges: DataFrame) -> DataFrame:
        """a, b, b1, b2: wedge counters of pairs of V over the given edges."""
        a = edges.select("u", F.col("v").alias("a"), F.col("sign").alias("s1"))
        b = edges.select("u", F.col("v").alias("b"), F.col("sign").alias("s2"))
        same = F.when(F.col("s1") == F.col("s2"), 1).otherwise(0)
        return a.join(b, "u").where("a < b").groupBy("a", "b").agg(F.sum(same).cast("long").alias("b1"), F.sum(1 - same).cast("long").alias("b2"))

    @staticmethod
    def _latest(rows: DataFrame) -> DataFrame:
        """The last row of every pair, deletions (sign null) included."""
        return rows.groupBy("u", "v").agg(F.max(F.struct("o", "sign")).alias("x")).select("u", "v", "x.sign", "x.o")

    @staticmethod
    def _all(rows: list[DataFrame]) -> DataFrame:
        return functools.reduce(DataFrame.unionByName, rows)

    @property
    def edges(self) -> DataFrame:
        return self._latest(self._all(self.log)).where("sign IS NOT NULL").select("u", "v", "sign")

    def apply(self, batch: DataFrame) -> int:
        """Upserts u, v, sign rows (sign null deletes) and returns the new total.

        With ts, k1, k2 the greatest by (ts, k1, k2, sign) holds, whichever batch brought it;
        without them later batches win, and a pair may come once in a batch.
        """
        self.number += 1
        timed = {"ts", "k1", "k2"} <= set(batch.columns)
        order = [F.col(c) if timed else F.lit(None).cast("timestamp" if c == "ts" else "long").alias(c) for c in ("ts", "k1", "k2")]
        number = F.lit(0 if timed else self.number).cast("long").alias("no")
        fresh = cut(batch.select("u", "v", F.col("sign").cast("byte").alias("sign"), F.struct(*order, number).alias("o")))
        if not timed and not fresh.groupBy("u", "v").count().where("count > 1").isEmpty():
            raise ValueError("a pair comes twice in a batch; give ts, k1 and k2")
        touched = fresh.select("u").distinct()
        near = cut(self._all(self.log).join(touched, "u", "left_semi"))
        before, after = (self._latest(x).where("sign IS NOT NULL") for x in (near, near.unionByName(fresh)))
        minus = self._wedges(before).select("a", "b", (-F.col("b1")).alias("b1"), (-F.col("b2")).alias("b2"))
        sums = [F.sum(c).cast("long").alias(c) for c in ("b1", "b2")]
        change = cut(self._wedges(after).unionByName(minus).groupBy("a", "b").agg(*sums).where("b1 <> 0 OR b2 <> 0"))
        old = self._all(self.pairs).join(change.select("a", "b"), ["a", "b"], "left_semi").groupBy("a", "b").agg(*[x.alias(f"o{k}") for k, x in enumerate(sums, 1)])
        met = change.join(old, ["a", "b"], "left").select(*[F.coalesce(f"o{k}", F.lit(0)).cast("long").alias(f"o{k}") for k in (1, 2)], "b1", "b2")
        moved = self._balanced("n1", "n2").cast(TOTAL) - self._balanced("o1", "o2").cast(TOTAL)
        self.total += int(met.select("o1", "o2", (F.col("o1") + F.col("b1")).alias("n1"), (F.col("o2") + F.col("b2")).alias("n2")).agg(F.coalesce(F.sum(moved), F.lit(0))).first()[0])
        self.log, self.pairs = [*self.log, fresh], [*self.pairs, change]
        if len(self.log) > self.fold:
            self.log = [cut(self._latest(self._all(self.log)))]
            self.pairs = [cut(self._all(self.pairs).groupBy("a", "b").agg(*sums).where("b1 <> 0 OR b2 <> 0"))]
        return self.total


def with_attributes(edges: DataFrame, vertices: DataFrame, key: str = "u") -> DataFrame:
    """A stream of edges beside a static table of vertex attributes."""
    return edges.join(vertices, key, "left")


def replay(spark: SparkSession, path: str, transform: Callable[[DataFrame], DataFrame], mode: str = "complete", files_per_trigger: int = 1) -> DataFrame:
    """Runs a stream over files until they are read; the table that its last batch left.

    In ``complete`` mode a batch is the whole result; otherwise all batches' rows follow one
    another, with their number in ``batch``.  Results and progress lie in the shared folder.
    """
    root = f"{shared_folder(spark).rstrip('/')}/stream_{uuid.uuid4().hex}"
    done: list[int] = []

    def keep(rows: DataFrame, number: int) -> None:
        rows.withColumn("batch", F.lit(number)).write.mode("overwrite").parquet(f"{root}/rows/{number}")
        done.append(number)

    rows = transform(event_edges(read_events(spark, path, files_per_trigger)))
    for_each_batch(rows, keep, f"{root}/progress", mode).awaitTermination()
    if not done:
        return spark.createDataFrame([], rows.schema)
    last = [f"{root}/rows/{done[-1]}"] if mode == "complete" else [f"{root}/rows/{k}" for k in sorted(set(done))]
    found = spark.read.parquet(*last)
    return found.drop("batch") if mode == "complete" else found


def resolve_stream_batch(edges: DataFrame) -> DataFrame:
    """The batch answer that the stream must equal."""
    return resolve_conflicts(edges)
