"""Explicit schemas; nothing is inferred."""

from __future__ import annotations

from pyspark.sql import types as T

EDGES = T.StructType([T.StructField("u", T.LongType()), T.StructField("v", T.LongType()), T.StructField("sign", T.ByteType())])
INTERACTIONS = T.StructType([*EDGES.fields, T.StructField("ts", T.TimestampType()), T.StructField("k1", T.LongType()), T.StructField("k2", T.LongType())])
RESULT = "experiment string, graph string, config string, metric string, value double"

#: ``gid = 2 * key + side`` needs keys below this.
MAX_KEY = 1 << 62
#: Totals pass 2**63 at scale, so they are summed as decimals.
TOTAL = "decimal(38,0)"
