"""Edge sources and sinks."""

from __future__ import annotations

import tempfile
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..schemas import EDGES, INTERACTIONS


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_edges(spark: SparkSession, path: str, fmt: str = "parquet", cols: tuple[str, str, str] = ("u", "v", "sign"), delim: str = ",", comment: str = "#") -> DataFrame:
    """Edges of a file: parquet, orc, json, csv or (white-space separated) text.

    Spark splits text files into byte ranges aligned to record ends, so that every
    record is read by one task.
    """
    if fmt in ("parquet", "orc"):
        raw = getattr(spark.read, fmt)(path)
        return raw.select(*[F.col(c).cast(f.dataType).alias(f.name) for c, f in zip(cols, EDGES.fields, strict=True)])
    if fmt == "json":
        return spark.read.schema(", ".join(f"`{c}` bigint" for c in cols)).json(path).select(*[F.col(c).cast(f.dataType).alias(f.name) for c, f in zip(cols, EDGES.fields, strict=True)])
    if fmt == "csv":
        return spark.read.schema(EDGES).option("sep", delim).option("comment", comment).csv(path)
    if fmt == "text":
        parts = F.split(F.trim("value"), r"[\s,]+")
        lines = spark.read.text(path).where(~F.col("value").rlike(r"^\s*([#%]|$)"))
        return lines.select(*[F.get(parts, k).cast("long").cast(f.dataType).alias(f.name) for k, f in enumerate(EDGES.fields)])
    raise ValueError(f"unknown format {fmt}")


def read_catalog(spark: SparkSession, name: str) -> DataFrame:
    return spark.table(name).select("u", "v", "sign")


def read_jdbc(spark: SparkSession, url: str, name: str, parts: int, bounds: tuple[int, int], **options: str) -> DataFrame:
    """Edges of a relational table, read by ranges of u."""
    return spark.read.jdbc(url, name, column="u", lowerBound=bounds[0], upperBound=bounds[1], numPartitions=parts, properties=options).select("u", "v", "sign")


def stream_edges(spark: SparkSession, path: str) -> DataFrame:
    """Interactions as a stream of Parquet files."""
    return spark.readStream.schema(INTERACTIONS).parquet(path)


def write_edges(edges: DataFrame, path: str, fmt: str = "parquet", bins: int | None = None) -> None:
    """Edges as parquet, orc, json or csv; ``bins`` partitions them by a hash of u."""
    out = edges if bins is None else edges.withColumn("bin", F.pmod(F.xxhash64("u"), F.lit(bins)).cast("int")).repartition(bins, "bin")
    writer = out.write.mode("overwrite")
    getattr(writer if bins is None else writer.partitionBy("bin"), fmt)(path)


def save_bucketed(edges: DataFrame, name: str, key: str, buckets: int) -> None:
    """A bucketed table: later joins on the key need no shuffle."""
    edges.write.mode("overwrite").bucketBy(buckets, key).sortBy(key).saveAsTable(name)


def noop(rows: DataFrame) -> None:
    """Runs a plan without keeping its rows."""
    rows.write.format("noop").mode("overwrite").save()


def shared_folder(spark: SparkSession) -> str:
    """The folder for checkpoints that the session names; a temporary one on a local master only."""
    context = spark.sparkContext
    if (known := context._jsc.sc().getCheckpointDir()).isDefined():
        return known.get()
    folder = spark.conf.get("spark.checkpoint.dir", None)
    if not folder and not context.master.startswith("local["):
        raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
    context.setCheckpointDir(folder or tempfile.mkdtemp(prefix="checkpoints_"))
    return context._jsc.sc().getCheckpointDir().get()


def cut(rows: DataFrame) -> DataFrame:
    """Rows behind a checkpoint (loops and drawn ranges need one).

    They are held while the checkpoint is written, which would compute them twice otherwise.
    """
    shared_folder(rows.sparkSession)
    held = rows.persist()
    done = held.checkpoint()
    held.unpersist()
    return done


def ingest_audit(rows: DataFrame, columns: tuple[str, ...] = ("u", "v", "sign")) -> DataFrame:
    """One row over rows as they are read: rows, key checksum, files, partitions, the largest partition.

    The checksum is the sum of a hash of the columns, the same for any order and dealing.
    """
    mark = F.conv(F.substring(F.md5(F.concat_ws("|", *(F.coalesce(F.col(c).cast("string"), F.lit("")) for c in columns))), 1, 12), 16, 10).cast("decimal(38,0)")
    per = rows.groupBy(F.spark_partition_id().alias("p"), F.input_file_name().alias("f")).agg(F.count(F.lit(1)).alias("n"), F.sum(mark).alias("h"))
    sums = per.groupBy("p").agg(F.sum("n").alias("n"), F.sum("h").alias("h"), F.collect_set("f").alias("f"))
    files = F.size(F.array_distinct(F.flatten(F.collect_set(F.filter("f", lambda x: x != "")))))
    return sums.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n_rows"), F.coalesce(F.sum("h").cast("string"), F.lit("0")).alias("checksum"), files.cast("long").alias("files"), F.count(F.lit(1)).alias("partitions"), F.max("n").alias("largest"))


def to_console(rows: DataFrame, mode: str = "update"):
    """A stream's rows printed by the driver, until what is there is read."""
    return rows.writeStream.format("console").outputMode(mode).trigger(availableNow=True).start()


def for_each_batch(rows: DataFrame, merge: Callable[[DataFrame, int], None], folder: str, mode: str = "append"):
    """A stream whose batches are merged by a function of (batch, number); progress is kept in ``folder``."""
    return rows.writeStream.foreachBatch(merge).outputMode(mode).option("checkpointLocation", folder).trigger(availableNow=True).start()
