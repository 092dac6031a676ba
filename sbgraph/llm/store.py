"""Tables written to the shared folder, to cut lineage where a step is read twice."""

from __future__ import annotations

import tempfile
import uuid
from typing import ClassVar

from pyspark.sql import DataFrame, SparkSession


def shared_folder(spark: SparkSession) -> str:
    """The folder the cluster names in ``spark.checkpoint.dir``.

    Where it is unset (tests), the context's own checkpoint folder, or else a
    temporary folder on a local master only.
    """
    if found := spark.conf.get("spark.checkpoint.dir", None):
        return found
    context = spark.sparkContext
    if (known := context._jsc.sc().getCheckpointDir()).isDefined():
        return known.get()
    if not context.master.startswith("local"):
        raise RuntimeError("set spark.checkpoint.dir to a folder that driver and executors share")
    context.setCheckpointDir(made := tempfile.mkdtemp(prefix="shared_"))
    return made


class Store:
    """Written tables of one run; ``drop`` and ``keep`` delete those that nothing reads any more."""

    #: Stores of this process whose tables may still lie in the shared folder.
    made: ClassVar[list[Store]] = []

    def __init__(self, spark: SparkSession) -> None:
        self.spark, self.root, self.names = spark, f"{shared_folder(spark).rstrip('/')}/{uuid.uuid4().hex}", []
        Store.made.append(self)

    def put(self, name: str, rows: DataFrame) -> DataFrame:
        rows.write.parquet(path := f"{self.root}/{name}")
        self.names.append(name)
        return self.spark.read.schema(rows.schema).parquet(path)

    def drop(self, *names: str) -> None:
        jvm = self.spark.sparkContext._jvm
        for name in names:
            path = jvm.org.apache.hadoop.fs.Path(f"{self.root}/{name}")
            path.getFileSystem(self.spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)
            self.names = [n for n in self.names if n != name]

    def keep(self, *names: str) -> None:
        """Deletes all tables but these."""
        self.drop(*[n for n in self.names if n not in names])

    @classmethod
    def sweep(cls, since: int) -> None:
        """Deletes the tables of all stores that were made after the first ``since``."""
        while len(cls.made) > since:
            cls.made.pop().keep()
