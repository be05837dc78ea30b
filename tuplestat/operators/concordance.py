"""Concordant pairs of two columns, exactly and without forming pairs.

Rows are aggregated to distinct points and cut into blocks of the first column at quantiles, ties
never split; there are more blocks where there are more points. Pairs in one block are counted by
divided searches in one task per block; a block of one x has none. Pairs across blocks are counted
level by level of a binary tree over the blocks: at each level a point belongs to one pair of
neighbouring halves and needs the count of smaller y in the left half, a prefix sum that spreads
over range partitions. A point is copied once per level, the logarithm of the number of blocks.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .sorted_forms import prefix_sums


LEAF = 256
BLOCK_POINTS = 100_000


def ordered_pairs(x: np.ndarray, y: np.ndarray, c: np.ndarray) -> int:
    """Weighted pairs with both coordinates strictly smaller, x in order: halves are split where x
    changes and counted across by a search in the left half's sorted y; leaves are compared at once."""
    n = len(x)
    if n < 2 or x[0] == x[-1]:
        return 0
    if n <= LEAF:
        less = (x[:, None] < x[None]) & (y[:, None] < y[None])
        return int(c @ less @ c)
    cut = int(np.searchsorted(x, x[n // 2], side="left"))
    if cut == 0:
        cut = int(np.searchsorted(x, x[n // 2], side="right"))
    order = np.argsort(y[:cut], kind="stable")
    weight = np.concatenate([[0], np.cumsum(c[:cut][order])])
    across = int(c[cut:] @ weight[np.searchsorted(y[:cut][order], y[cut:], side="left")])
    return across + ordered_pairs(x[:cut], y[:cut], c[:cut]) + ordered_pairs(x[cut:], y[cut:], c[cut:])


def below_in_block(frame: pd.DataFrame) -> pd.DataFrame:
    """block, inner: pairs (weighted) with both coordinates smaller, within one block."""
    f = frame.sort_values(["x", "y"])
    total = ordered_pairs(f["x"].to_numpy(), f["y"].to_numpy(), f["c"].to_numpy(dtype=np.int64))
    return pd.DataFrame({"block": [frame["block"].iloc[0]], "inner": [total]})


def concordance_counts(df: DataFrame, x: str, y: str, blocks: int | None = None) -> DataFrame:
    """pairs, concordant, estimate: pairs of rows that both columns order alike, strictly."""
    points = df.select(F.col(x).alias("x"), F.col(y).alias("y")).where("x IS NOT NULL AND y IS NOT NULL").groupBy("x", "y").agg(
        F.count("*").alias("c")
    )
    if blocks is None:
        blocks = max(64, points.count() // BLOCK_POINTS)
    levels = max(1, (blocks - 1).bit_length())
    ranked = prefix_sums(points.groupBy("x").agg(F.sum("c").alias("k")), "x", ("k",))
    total = points.agg(F.sum("c").alias("n"))
    placed = ranked.join(F.broadcast(total)).select(
        "x", F.least(F.lit(blocks - 1), F.floor(F.col("before_k") * blocks / F.col("n"))).cast("int").alias("block")
    )
    points = points.join(placed, "x")
    mixed = placed.groupBy("block").agg(F.count("*").alias("xs")).where("xs > 1").select("block")  # a row per block
    inner = points.join(F.broadcast(mixed), "block").groupBy("block").applyInPandas(below_in_block, "block int, inner long")
    inner = inner.agg(F.coalesce(F.sum("inner"), F.lit(0)).alias("inner"))
    halves = points.groupBy("block", "y").agg(F.sum("c").alias("c")).withColumn("level", F.explode(F.sequence(F.lit(1), F.lit(levels))))
    right = F.expr("shiftright(block, level - 1) & 1") == 1
    halves = halves.groupBy("level", F.expr("shiftright(block, level)").alias("pair"), "y").agg(
        F.sum(F.when(right, 0).otherwise(F.col("c"))).alias("left"), F.sum(F.when(right, F.col("c")).otherwise(0)).alias("right")
    )
    across = prefix_sums(halves, "y", ("left",), ("level", "pair")).agg(
        F.coalesce(F.sum(F.col("right") * F.col("before_left")), F.lit(0)).alias("across")
    )
    n = F.col("n")
    return total.join(F.broadcast(inner)).join(F.broadcast(across)).select(  # one row each
        F.floor(n * (n - 1) / 2).cast("long").alias("pairs"),
        (F.col("inner") + F.col("across")).cast("long").alias("concordant"),
        ((F.col("inner") + F.col("across")) / (n * (n - 1) / 2)).alias("estimate"),
    )
