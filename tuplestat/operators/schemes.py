"""Assignment of rows to logical workers, one frame for all rounds.

Input: samples (sample, key, score[, idx]). Output: the same rows once per round, with
round (from 1), worker (from 0) and, where the scheme fixes it, slot: the row's place within its
(round, sample, worker). N workers are logical: results do not depend on Spark's partitions.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions.keyed import keyed_u64, layer_keys, permute

SCHEMES = ("prop_swor", "swor", "swor_iid", "prop_swr", "stride", "static")


def each_round(df: DataFrame, rounds: int, first: int = 1) -> DataFrame:
    return df.withColumn("round", F.explode(F.sequence(F.lit(first), F.lit(first + rounds - 1))))


def _dealt(df: DataFrame, workers: int, place: Column) -> DataFrame:
    return df.withColumn("worker", (place % workers).cast("int")).withColumn("slot", F.floor(place / workers).cast("long"))


def hash_rank(df: DataFrame, workers: int, rounds: int, seed: int, by_sample: bool = True, first: int = 1) -> DataFrame:
    """Rank the rows by a keyed hash in every round and deal the ranks out. By sample, parts are
    proportional; over the union, a worker's share of each sample is random (hypergeometric).
    A window over (round, sample): exact and repeatable in SQL, but a sort of each sample; `seeded`
    is the scheme for large data."""
    df = each_round(df, rounds, first)
    h = keyed_u64(seed, F.col("round"), F.col("sample"), F.col("key"))
    keys = ["round", "sample"] if by_sample else ["round"]
    rank = F.row_number().over(Window.partitionBy(*keys).orderBy(h, "sample", "key")) - 1
    return _dealt(df.withColumn("_rank", rank), workers, F.col("_rank")).drop("_rank")


def seeded(
    df: DataFrame, sizes: dict[int, int], workers: int, rounds: int, seed: int, first: int = 1, hashed: str = "xxhash64"
) -> DataFrame:
    """Proportional parts without coordination: every row computes its place under the shared
    keyed permutation of its sample. Needs idx; no window, no sort, no shuffle."""
    df = each_round(df, rounds, first)
    place = None
    for sample, n in sorted(sizes.items()):
        keys = None
        if hashed == "md5" and rounds <= 16:
            keys = F.element_at(layer_keys(n, seed, range(first, first + rounds), sample), F.col("round") - first + 1)
        here = permute(F.col("idx"), n, seed, F.col("round"), sample, hashed, keys)
        place = F.when(F.col("sample") == sample, here) if place is None else place.when(F.col("sample") == sample, here)
    return _dealt(df.withColumn("_place", place), workers, F.col("_place")).drop("_place")


def swor_iid(df: DataFrame, workers: int, rounds: int, seed: int, first: int = 1) -> DataFrame:
    """Every row thrown to a worker independently (multinomial parts; parts may be empty)."""
    df = each_round(df, rounds, first)
    h = keyed_u64(seed, "iid", F.col("round"), F.col("sample"), F.col("key"))
    return df.withColumn("worker", F.pmod(h, F.lit(workers)).cast("int"))


def prop_swr(df: DataFrame, sizes: dict[int, int], workers: int, rounds: int, seed: int) -> DataFrame:
    """Every worker draws its share of each sample with replacement, by row number."""
    spark = df.sparkSession
    shares = [(s, n, n // workers) for s, n in sorted(sizes.items()) if n >= workers]
    if len(shares) < len(sizes):
        raise ValueError("a sample is smaller than the number of workers")
    draws = (
        spark.createDataFrame(shares, "sample int, n long, share long")
        .withColumn("round", F.explode(F.sequence(F.lit(1), F.lit(rounds))))
        .withColumn("worker", F.explode(F.sequence(F.lit(0), F.lit(workers - 1))))
        .withColumn("slot", F.explode(F.sequence(F.lit(0).cast("long"), F.col("share") - 1)))
        .withColumn("idx", F.pmod(keyed_u64(seed, "swr", *map(F.col, ("round", "sample", "worker", "slot"))), F.col("n")))
    )
    return draws.select("round", "sample", "worker", "slot", "idx").join(df, ["sample", "idx"])


def stride(df: DataFrame, workers: int, rounds: int) -> DataFrame:
    """Deterministic parts of sizes that differ by one at most; needs idx."""
    df = each_round(df, rounds)
    place = F.col("idx") + F.floor(F.col("idx") / workers) * F.col("round")
    return df.withColumn("worker", (place % workers).cast("int"))


def static(df: DataFrame, workers: int, seed: int, by: Column | None = None) -> DataFrame:
    """The initial placement for good: by a keyed hash, or by a column (not random at all)."""
    place = F.pmod(keyed_u64(seed, "static", F.col("sample"), F.col("key")), F.lit(workers)) if by is None else F.pmod(
        by.cast("long"), F.lit(workers)
    )
    return df.withColumn("round", F.lit(1)).withColumn("worker", place.cast("int"))


def place_rows(df: DataFrame, partitions: int) -> DataFrame:
    """Rows of a worker together in one of `partitions` physical partitions, dealt evenly."""
    by_id = getattr(df, "repartitionById", None)
    target = (F.col("worker") % partitions).cast("int")
    return by_id(partitions, target) if by_id is not None else df.repartition(partitions, target)


def assignment_stats(assigned: DataFrame, workers: int, samples: int = 2) -> DataFrame:
    """Per round: least and largest part of each sample, empty parts, rows that changed worker."""
    rounds = assigned.select("round").distinct()
    spark = assigned.sparkSession
    grid = rounds.withColumn("worker", F.explode(F.sequence(F.lit(0), F.lit(workers - 1)))).withColumn(
        "sample", F.explode(F.sequence(F.lit(0), F.lit(samples - 1)))
    )
    parts = assigned.groupBy("round", "worker", "sample").agg(F.count("*").alias("n"))
    sizes = grid.join(parts, ["round", "worker", "sample"], "left").fillna(0, ["n"])
    before = F.lag("worker").over(Window.partitionBy("sample", "key").orderBy("round"))
    moved = assigned.withColumn("was", before).groupBy("round").agg(
        F.sum(F.when(F.col("was") != F.col("worker"), 1).otherwise(0)).cast("long").alias("moved_rows")
    )
    return (
        sizes.groupBy("round")
        .agg(
            *[
                f(F.when(F.col("sample") == s, F.col("n"))).cast("long").alias(f"{name}_{s}")
                for s in range(samples)
                for f, name in ((F.min, "least"), (F.max, "most"))
            ],
            F.sum(F.when(F.col("n") == 0, 1).otherwise(0)).cast("long").alias("empty_parts"),
        )
        .join(moved, "round")
    )
