"""Samples in canonical form: (sample, idx, key, score), densely numbered within each sample."""

from __future__ import annotations

from functools import reduce

from pyspark import StorageLevel
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def as_sample(df: DataFrame, sample: int, key: Column, score: Column, nulls: str = "drop") -> DataFrame:
    """sample, key, score of the rows of `df`. Null or NaN scores are dropped, or an error."""
    out = df.select(F.lit(sample).alias("sample"), key.cast("string").alias("key"), score.cast("double").alias("score"))
    bad = F.col("score").isNull() | F.isnan("score")
    if nulls == "error":
        return out.withColumn("score", F.when(bad, F.raise_error(F.lit("null or NaN score"))).otherwise(F.col("score")))
    return out.where(~bad)


_KEPT: list[DataFrame] = []


def kept(df: DataFrame, level: StorageLevel = StorageLevel.MEMORY_AND_DISK_DESER) -> DataFrame:
    """`df` persisted because two passes must see the same partitions; `release` frees it."""
    _KEPT.append(df.persist(level))
    return _KEPT[-1]


def release(since: int = 0) -> None:
    """Free what `kept` holds, or what it holds beyond the first `since` frames. Results built on
    them still work: Spark computes a freed frame again from the same shuffle."""
    while len(_KEPT) > since:
        _KEPT.pop().unpersist()


def held_frames() -> int:
    return len(_KEPT)


def number_rows(df: DataFrame, order_by: str = "key", within: str = "sample") -> DataFrame:
    """`df` with idx: 0, 1, ... in the order of `order_by` within each value of `within`.

    Rows are range-partitioned and sorted; a row's number is its rank in its partition plus the
    counts of earlier partitions (one row per partition and value, joined back by broadcast).
    No window spans a whole sample. The partitioned rows are kept for both passes (see `release`).
    """
    part = df.repartitionByRange(F.col(within), F.col(order_by)).sortWithinPartitions(within, order_by)
    # A row's place in its sorted partition is the low part of the id that Spark gives it.
    part = part.withColumn("_p", F.spark_partition_id()).withColumn("_at", F.monotonically_increasing_id().bitwiseAND(F.lit((1 << 33) - 1)))
    part = kept(part)
    before = Window.partitionBy(within).orderBy("_p").rowsBetween(Window.unboundedPreceding, -1)
    offsets = part.groupBy("_p", within).agg(F.count("*").alias("_n"), F.min("_at").alias("_first"))
    offsets = offsets.select("_p", within, (F.coalesce(F.sum("_n").over(before), F.lit(0)) - F.col("_first")).alias("_before"))
    return (
        part.join(F.broadcast(offsets), ["_p", within])
        .withColumn("idx", (F.col("_at") + F.col("_before")).cast("long"))
        .drop("_p", "_at", "_before")
    )


def samples(*parts: DataFrame) -> DataFrame:
    return reduce(DataFrame.unionByName, parts)


def two_sample(x: DataFrame, z: DataFrame, x_key: str, x_score: str, z_key: str, z_score: str) -> DataFrame:
    return as_sample(x, 0, F.col(x_key), F.col(x_score)).unionByName(as_sample(z, 1, F.col(z_key), F.col(z_score)))


def sizes(df: DataFrame) -> dict[int, int]:
    """Rows of each sample; a handful of numbers."""
    return {r["sample"]: r["n"] for r in df.groupBy("sample").agg(F.count("*").alias("n")).collect()}
