"""Evaluation measures of scores: areas, pair losses, breakdowns."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.keyed import keyed_u64
from .sorted_forms import auc_counts, prefix_sums, vus_counts


def auc(df: DataFrame, score: Column, positive: Column) -> DataFrame:
    """n, m, wins, ties, auc, auc_half over all pairs, exact."""
    return auc_counts(df, score, positive)


def auc_by(df: DataFrame, score: Column, positive: Column, keys: tuple[str, ...]) -> DataFrame:
    return auc_counts(df, score, positive, keys)


def auc_binned(df: DataFrame, score: Column, positive: Column, lo: float, hi: float, bins: int) -> DataFrame:
    """AUC from equal-width score bins, ties inside a bin counting a half: `bins` rows are sorted,
    whatever the size of the data. low and high bound the exact (half-tie) value."""
    b = F.least(F.lit(bins - 1), F.greatest(F.lit(0), F.floor((score - lo) / F.lit((hi - lo) / bins)))).cast("int")
    counts = df.select(b.alias("bin"), positive.cast("long").alias("y")).groupBy("bin").agg(
        F.sum("y").alias("pos"), F.sum(1 - F.col("y")).alias("neg")
    )
    ranked = prefix_sums(counts, "bin", ("neg",))
    s = ranked.agg(
        F.sum("pos").alias("n"),
        F.sum("neg").alias("m"),
        F.sum(F.col("pos") * F.col("before_neg")).alias("wins"),
        F.sum(F.col("pos") * F.col("neg")).alias("unsure"),
    )
    nm = F.col("n").cast("double") * F.col("m")
    return s.select(
        "n",
        "m",
        (F.col("wins") / nm).alias("low"),
        ((F.col("wins") + F.col("unsure") / 2) / nm).alias("auc"),
        ((F.col("wins") + F.col("unsure")) / nm).alias("high"),
    )


def vus(df: DataFrame, score: Column, label: Column, k: int) -> DataFrame:
    return vus_counts(df, score, label, k)


def fixed_pairs(samples: DataFrame, sizes: dict[int, int], batch: int, seed: int) -> DataFrame:
    """draw, x, z: scores of a fixed keyed set of pairs (rows numbered by idx), for monitoring."""
    d = samples.sparkSession.range(batch).select(
        F.col("id").alias("draw"),
        F.pmod(keyed_u64(seed, "monitor", 0, F.col("id")), F.lit(sizes[0])).alias("i"),
        F.pmod(keyed_u64(seed, "monitor", 1, F.col("id")), F.lit(sizes[1])).alias("j"),
    )
    x = samples.where("sample = 0").select(F.col("idx").alias("i"), F.col("score").alias("x"))
    z = samples.where("sample = 1").select(F.col("idx").alias("j"), F.col("score").alias("z"))
    return d.join(x, "i").join(z, "j").select("draw", "x", "z")


def pair_loss(pairs: DataFrame) -> DataFrame:
    """pairs, loss (hinge), accuracy (share with x below z) of columns x, z."""
    return pairs.agg(
        F.count("*").alias("pairs"),
        F.avg(F.greatest(F.lit(0.0), F.lit(1.0) + F.col("x") - F.col("z"))).alias("loss"),
        F.avg(F.when(F.col("x") < F.col("z"), 1.0).otherwise(0.0)).alias("accuracy"),
    )


def hardest_pairs(pairs: DataFrame, k: int, tie: tuple[str, ...]) -> DataFrame:
    """The `k` pairs of smallest margin z - x: per-task heaps, then one merge."""
    return pairs.withColumn("margin", F.col("z") - F.col("x")).orderBy("margin", *tie).limit(k)
