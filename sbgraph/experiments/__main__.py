"""python -m sbgraph.experiments SF_DIR OUT_DIR [NAME...]: runs experiments and writes their rows."""

from __future__ import annotations

import sys

from pyspark.sql import SparkSession

from . import ALL


def main() -> None:
    sf, out, *names = sys.argv[1:]
    spark = SparkSession.builder.master("local[8]").config("spark.ui.enabled", "false").config("spark.sql.shuffle.partitions", "16").getOrCreate()
    for f in ALL:
        if not names or f.__name__ in names:
            f(spark, sf).write.mode("overwrite").parquet(f"{out}/{f.__name__}")
            spark.read.parquet(f"{out}/{f.__name__}").show(200, truncate=False)


if __name__ == "__main__":
    main()
