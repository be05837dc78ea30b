"""Canonical schemas, and a check that a frame fits one."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import types as T

SAMPLE = T.StructType(
    [
        T.StructField("sample", T.IntegerType(), False),
        T.StructField("idx", T.LongType(), False),
        T.StructField("key", T.StringType(), False),
        T.StructField("score", T.DoubleType()),
    ]
)
ASSIGNMENT = T.StructType(
    [
        T.StructField("round", T.IntegerType()),
        T.StructField("sample", T.IntegerType()),
        T.StructField("key", T.StringType()),
        T.StructField("worker", T.IntegerType()),
        T.StructField("slot", T.LongType()),
    ]
)
LOCAL = T.StructType(
    [
        T.StructField("round", T.IntegerType()),
        T.StructField("worker", T.IntegerType()),
        T.StructField("tuples", T.LongType()),
        T.StructField("total", T.DoubleType()),
        T.StructField("value", T.DoubleType()),
    ]
)
TRACE = T.StructType(
    [
        T.StructField("run", T.IntegerType()),
        T.StructField("iteration", T.IntegerType()),
        T.StructField("round", T.IntegerType()),
        T.StructField("metric", T.StringType()),
        T.StructField("value", T.DoubleType()),
    ]
)


def require(df: DataFrame, schema: T.StructType) -> DataFrame:
    """`df` itself; raises ValueError naming the first column that is missing or of another type."""
    have = {f.name: f.dataType for f in df.schema}
    for f in schema:
        if f.name not in have:
            raise ValueError(f"column {f.name} is missing")
        if have[f.name] != f.dataType:
            raise ValueError(f"column {f.name} is {have[f.name].simpleString()}, not {f.dataType.simpleString()}")
    return df
