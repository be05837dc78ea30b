"""Relational operators around the methods, composed of built-in ones."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def theta_join(left: DataFrame, right: DataFrame, predicate: Column, broadcast: bool = False) -> DataFrame:
    """Any predicate. Nested loops: `broadcast` only a right side of checked size."""
    return left.join(F.broadcast(right) if broadcast else right, predicate)


def range_join(left: DataFrame, right: DataFrame, lcol: str, rcol: str, width: float) -> DataFrame:
    """Pairs with |left - right| < width, as an equi-join on buckets of that width: the right side
    is copied to its own and both neighbouring buckets, the left side is not."""
    bucket = lambda c: F.floor(F.col(c) / F.lit(width))
    near = right.withColumn("_b", F.explode(F.array(*[bucket(rcol) + k for k in (-1, 0, 1)])))
    return left.withColumn("_b", bucket(lcol)).join(near, "_b").where(F.abs(F.col(lcol) - F.col(rcol)) < width).drop("_b")


def interval_join(left: DataFrame, right: DataFrame, on: list[str], ltime: str, rtime: str, before: str, after: str) -> DataFrame:
    """Pairs of one key whose right time lies in [left - before, left + after] (SQL intervals)."""
    inside = F.col(rtime).between(F.col(ltime) - F.expr(f"interval {before}"), F.col(ltime) + F.expr(f"interval {after}"))
    return left.join(right, on).where(inside)


def asof_join(left: DataFrame, right: DataFrame, on: list[str], ltime: str, rtime: str, values: list[str]) -> DataFrame:
    """Each left row with `values` of the last right row at or before its time: one union, one
    sort per key, no pairs."""
    r = right.select(*on, F.col(rtime).alias("_t"), F.lit(0).alias("_side"), F.struct(*values).alias("_v"))
    l = left.withColumn("_t", F.col(ltime)).withColumn("_side", F.lit(1))
    both = l.unionByName(r, allowMissingColumns=True)
    w = Window.partitionBy(*on).orderBy("_t", "_side").rowsBetween(Window.unboundedPreceding, 0)
    out = both.withColumn("_last", F.last("_v", ignorenulls=True).over(w)).where("_side = 1")
    return out.select(*left.columns, *[F.col(f"_last.{v}").alias(f"last_{v}") for v in values])


def keep_matching(left: DataFrame, right: DataFrame, on: list[str]) -> DataFrame:
    return left.join(right, on, "left_semi")


def drop_matching(left: DataFrame, right: DataFrame, on: list[str]) -> DataFrame:
    return left.join(right, on, "left_anti")


def complete_grid(df: DataFrame, keys: list[str], grid: DataFrame, fill: dict) -> DataFrame:
    """A row for every row of `grid`, filled where `df` has none."""
    return grid.join(df, keys, "left").fillna(fill)


def ordered_tuples(df: DataFrame, by: list[str], order: str, d: int) -> DataFrame:
    """d-tuples inside each group with rising `order`; columns get suffixes _1.._d."""
    parts = [df.select(*[F.col(c).alias(c if c in by and k == 0 else f"{c}_{k + 1}") for c in df.columns]) for k in range(d)]
    out = parts[0]
    last = f"{order}" if order in by else f"{order}_1"
    for k in range(1, d):
        same = [F.col(b) == F.col(f"{b}_{k + 1}") for b in by]
        out = out.join(parts[k], reduce(lambda p, q: p & q, [*same, F.col(last) < F.col(f"{order}_{k + 1}")])).drop(*[f"{b}_{k + 1}" for b in by])
        last = f"{order}_{k + 1}"
    return out


def ranked(df: DataFrame, partition_by: list[str], order_by: list[Column], kinds: tuple[str, ...]) -> DataFrame:
    w = Window.partitionBy(*partition_by).orderBy(*order_by)
    made = {"row_number": F.row_number, "rank": F.rank, "dense_rank": F.dense_rank, "percent_rank": F.percent_rank, "quartile": lambda: F.ntile(4)}
    for k in kinds:
        df = df.withColumn(k, made[k]().over(w))
    return df


def framed(df: DataFrame, partition_by: list[str], order_by: list, rows: tuple[int, int], aggs: dict[str, Column]) -> DataFrame:
    w = Window.partitionBy(*partition_by).orderBy(*order_by).rowsBetween(*rows)
    for name, agg in aggs.items():
        df = df.withColumn(name, agg.over(w))
    return df


def top_k(df: DataFrame, order_by: list[Column], k: int, partition_by: list[str] | None = None) -> DataFrame:
    if not partition_by:
        return df.orderBy(*order_by).limit(k)
    w = Window.partitionBy(*partition_by).orderBy(*order_by)
    return df.withColumn("_r", F.row_number().over(w)).where(F.col("_r") <= k).drop("_r")


def grouped(df: DataFrame, keys: list[str], aggs: list[Column], mode: str = "plain") -> DataFrame:
    made = {"plain": df.groupBy, "rollup": df.rollup, "cube": df.cube}[mode](*keys)
    return made.agg(*aggs)


def to_wide(df: DataFrame, row: list[str], col: str, names: list, value: Column) -> DataFrame:
    return df.groupBy(*row).pivot(col, names).agg(value)


def to_long(df: DataFrame, ids: list[str], values: list[str]) -> DataFrame:
    return df.unpivot(ids, values, "name", "value")
