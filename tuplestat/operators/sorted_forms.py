"""The same averages without tuples, for kernels that only need order and sums.

Each form aggregates by distinct score first (so heavy ties cost nothing), then needs prefix
sums over the distinct scores. `prefix_sums` computes those over any number of partitions: sums
inside range partitions, plus the totals of earlier partitions (a row each).
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .samples import kept


def prefix_sums(df: DataFrame, order_by: str, values: tuple[str, ...], by: tuple[str, ...] = (), local: bool = False) -> DataFrame:
    """`df` with before_<value>: sums over rows with smaller `order_by` (distinct within `by`).

    Range partitions over (by, order_by) with sums of their own, plus what earlier partitions hold of a
    partition's first group: one broadcast row per partition at most, so neither a large group nor
    many groups meet in one task. `local`: a window inside each group instead, for groups that fit
    a task by definition (the parts of logical workers)."""
    if local:
        w = Window.partitionBy(*by).orderBy(order_by).rowsBetween(Window.unboundedPreceding, -1)
        for v in values:
            df = df.withColumn(f"before_{v}", F.coalesce(F.sum(v).over(w), F.lit(0)))
        return df
    part = df.repartitionByRange(*by, order_by).sortWithinPartitions(*by, order_by)
    part = kept(part.withColumn("_p", F.spark_partition_id()))
    inner = Window.partitionBy("_p", *by).orderBy(order_by).rowsBetween(Window.unboundedPreceding, -1)
    # A row per partition and group; those of one group are as few as the partitions it spans.
    outer = Window.partitionBy(*by).orderBy("_p").rowsBetween(Window.unboundedPreceding, -1)
    totals = part.groupBy("_p", *by).agg(*[F.sum(v).alias(v) for v in values])
    totals = totals.select("_p", *by, F.count("*").over(outer).alias("_earlier_parts"), *[F.sum(v).over(outer).alias(f"_part_{v}") for v in values])
    out = part.join(F.broadcast(totals.where("_earlier_parts > 0").drop("_earlier_parts")), ["_p", *by], "left")
    for v in values:
        out = out.withColumn(f"before_{v}", F.coalesce(F.sum(v).over(inner), F.lit(0)) + F.coalesce(F.col(f"_part_{v}"), F.lit(0)))
    return out.drop("_p", *[f"_part_{v}" for v in values])


def auc_counts(df: DataFrame, score: Column, positive: Column, by: tuple[str, ...] = ()) -> DataFrame:
    """by..., n, m, wins (pairs with positive above), ties, auc (ties strict), auc_half; exact."""
    distinct = (
        df.select(*by, score.alias("_s"), positive.cast("long").alias("_y"))
        .groupBy(*by, "_s")
        .agg(F.sum("_y").alias("pos"), F.sum(1 - F.col("_y")).alias("neg"))
    )
    ranked = prefix_sums(distinct, "_s", ("neg",), by)
    n, m = F.col("n").cast("double"), F.col("m").cast("double")
    return (
        ranked.groupBy(*by)
        .agg(
            F.sum("pos").alias("n"),
            F.sum("neg").alias("m"),
            F.sum(F.col("pos") * F.col("before_neg")).alias("wins"),
            F.sum(F.col("pos") * F.col("neg")).alias("ties"),
        )
        .withColumn("auc", F.when((n > 0) & (m > 0), F.col("wins") / (n * m)))
        .withColumn("auc_half", F.when((n > 0) & (m > 0), (F.col("wins") + F.col("ties") / 2) / (n * m)))
    )


def auc_by_worker(assigned: DataFrame) -> DataFrame:
    """round, worker, tuples, total, value of the strict AUC kernel: the sorted form of the
    within-worker average. A shuffle of (round, worker, score) counts, a sort, no pairs."""
    counted = (
        assigned.select("round", "worker", "score", (F.col("sample") == 0).cast("long").alias("x"))
        .groupBy("round", "worker", "score")
        .agg(F.sum("x").alias("pos"), F.sum(1 - F.col("x")).alias("neg"))
    )
    ranked = prefix_sums(counted, "score", ("neg",), ("round", "worker"), local=True)
    return (
        ranked.groupBy("round", "worker")
        .agg(
            (F.sum("pos") * F.sum("neg")).alias("tuples"),
            F.sum(F.col("pos") * F.col("before_neg")).cast("double").alias("total"),
        )
        .withColumn("value", F.when(F.col("tuples") > 0, F.col("total") / F.col("tuples")).otherwise(0.0))
    )


def vus_counts(df: DataFrame, score: Column, label: Column, k: int, number: str = "double") -> DataFrame:
    """tuples, chains, estimate: share of k-tuples (label 1..k, one row each) with rising scores.

    Chains ending in class c at a score are its rows times the chains of c-1 at smaller scores:
    one prefix sum per class after the first. Doubles, exact below 2**53, or a `number` type of the caller's
    ("decimal(38,0)" counts exactly)."""
    cur = (
        df.select(score.alias("_s"), label.cast("int").alias("_y"))
        .where(F.col("_y").between(1, k))
        .groupBy("_s")
        .agg(*[F.sum((F.col("_y") == c).cast("long")).cast(number).alias(f"n{c}") for c in range(1, k + 1)])
        .withColumn("chain1", F.col("n1"))
    )
    for c in range(2, k + 1):
        cur = prefix_sums(cur, "_s", (f"chain{c - 1}",)).withColumn(f"chain{c}", F.col(f"n{c}") * F.col(f"before_chain{c - 1}"))
        cur = cur.select("_s", *[f"n{i}" for i in range(1, k + 1)], f"chain{c}")
    product = F.lit(1).cast(number)
    for c in range(1, k + 1):
        product = product * F.sum(f"n{c}")
    return cur.agg(product.alias("tuples"), F.sum(f"chain{k}").alias("chains")).withColumn(
        "estimate", F.when(F.col("tuples") > 0, F.col("chains").cast("double") / F.col("tuples").cast("double"))
    )


#: Exact whole numbers of any size that sums of products of rows and cents reach.
WHOLE = "decimal(38,0)"
FACTOR = "decimal(20,0)"


def chain_sums(df: DataFrame, k: int) -> DataFrame:
    """tuples, total, estimate of the chain kernel of k samples 0..k-1 with scores: `vus_counts` in exact
    whole numbers."""
    r = vus_counts(df, F.col("score"), F.col("sample") + 1, k, WHOLE)
    tuples = F.coalesce("tuples", F.lit(0)).cast(WHOLE)
    return r.select(tuples.alias("tuples"), F.when(F.col("tuples") > 0, F.col("chains")).alias("total"), "estimate")


def square_gaps(df: DataFrame) -> DataFrame:
    """tuples, total, estimate of (a - b)^2 over pairs of rows whose scores are whole numbers: the number of
    rows times their squares, less the square of their sum. Exact."""
    v = F.col("score").cast(FACTOR)
    s = df.agg(F.count("score").alias("n"), F.sum(v).alias("s"), F.sum((v * v).cast(WHOLE)).alias("q"))
    n = F.col("n").cast(FACTOR)
    pairs, total = (F.col("n") * (F.col("n") - 1) / 2).cast("long"), n * F.col("q") - F.col("s") * F.col("s")
    r = s.select(pairs.alias("tuples"), F.when(F.col("n") > 1, total.cast(WHOLE)).alias("total"))
    return r.withColumn("estimate", F.when(F.col("tuples") > 0, F.col("total").cast("double") / F.col("tuples")))


def triple_ranges(df: DataFrame) -> DataFrame:
    """tuples, total, estimate of the range of three rows whose scores are whole numbers: each score counts
    in the triples of which it is the largest, less those of which it is the smallest. Exact."""
    counted = df.groupBy(F.col("score").alias("v")).agg(F.count("*").alias("c"))
    ranked = prefix_sums(counted, "v", ("c",)).join(F.broadcast(counted.agg(F.sum("c").alias("n"))))

    def six(n: Column) -> Column:  # six times the triples of n rows
        n = n.cast("decimal(12,0)")
        return n * (n - 1).cast("decimal(12,0)") * (n - 2).cast("decimal(12,0)")

    below, to, n = F.col("before_c"), F.col("before_c") + F.col("c"), F.col("n")
    sign = six(to) - six(below) - (six(n - below) - six(n - to))
    s = ranked.agg(F.max(six(n)).cast(WHOLE).alias("t"), F.sum((F.col("v").cast(FACTOR) * sign).cast(WHOLE)).alias("s"))
    part = lambda c: F.floor(F.col(c) / 6).cast(WHOLE)
    r = s.select(F.coalesce(part("t"), F.lit(0)).cast(WHOLE).alias("tuples"), F.when(F.col("t") > 0, part("s")).alias("total"))
    return r.withColumn("estimate", F.when(F.col("tuples") > 0, F.col("total").cast("double") / F.col("tuples").cast("double")))


def chains_by_worker(assigned: DataFrame, k: int) -> DataFrame:
    """round, worker, tuples, total of the chain kernel inside workers, exact: a prefix sum per class."""
    by = ("round", "worker")
    counts = [F.sum((F.col("sample") == c).cast("long")).cast(WHOLE).alias(f"n{c}") for c in range(k)]
    cur = assigned.groupBy(*by, "score").agg(*counts).withColumn("chain", F.col("n0"))
    for c in range(1, k):
        cur = prefix_sums(cur, "score", ("chain",), by, local=True).withColumn("chain", (F.col(f"n{c}") * F.col("before_chain")).cast(WHOLE))
    tuples = F.sum("n0")
    for c in range(1, k):
        tuples = (tuples * F.sum(f"n{c}")).cast(WHOLE)
    return cur.groupBy(*by).agg(tuples.cast("long").alias("tuples"), F.sum("chain").alias("total"))


def gaps_by_worker(assigned: DataFrame) -> DataFrame:
    """round, worker, tuples, total of |a - b| over pairs of rows inside workers, exact for scores that are
    whole numbers: from the counts and sums of smaller scores."""
    by, c, v = ("round", "worker"), F.col("c").cast(FACTOR), F.col("score").cast(FACTOR)
    cur = assigned.groupBy(*by, "score").agg(F.count("*").alias("c"))
    cur = prefix_sums(cur.withColumn("w", (c * v).cast(WHOLE)), "score", ("c", "w"), by, local=True)
    above = (v * F.col("before_c").cast(FACTOR)).cast(WHOLE) - F.col("before_w")
    r = cur.groupBy(*by).agg(F.sum("c").alias("n"), F.sum((c * above).cast(WHOLE)).alias("total"))
    return r.select(*by, (F.col("n") * (F.col("n") - 1) / 2).cast("long").alias("tuples"), "total")


def mean_absolute_difference(df: DataFrame, value: Column) -> DataFrame:
    """n, total, estimate: mean of |a - b| over pairs, from the ordered values' weights."""
    distinct = df.select(value.alias("v")).groupBy("v").agg(F.count("*").cast("double").alias("c"))
    ranked = prefix_sums(distinct.withColumn("w", F.col("v") * F.col("c")), "v", ("c", "w"))
    return ranked.agg(
        F.sum("c").cast("long").alias("n"),
        F.sum(F.col("c") * (F.col("v") * F.col("before_c") - F.col("before_w"))).alias("total"),
    ).withColumn("estimate", F.when(F.col("n") > 1, F.col("total") / (F.col("n") * (F.col("n") - 1) / 2)))


def squared_difference(df: DataFrame, value: Column) -> DataFrame:
    """n, estimate (mean of (a-b)^2 over pairs, twice the sample variance)."""
    return df.agg(F.count(value).alias("n"), (2 * F.var_samp(value)).alias("estimate"))


def product_mean(df: DataFrame, score: Column, first: Column) -> DataFrame:
    """n, m, estimate of the product kernel: the product of the two samples' means."""
    x, z = F.when(first, score), F.when(~first, score)
    return df.agg(F.count(x).alias("n"), F.count(z).alias("m"), (F.avg(x) * F.avg(z)).alias("estimate"))


def hinge_sums(df: DataFrame, score: Column, first: Column, margin: float = 1.0) -> DataFrame:
    """n, m, active, total, estimate of the ranking hinge: a pair costs margin + x - z where that is
    positive, so each x needs the count and sum of the z below x + margin: one merge of shifted
    scores and prefix sums."""
    rows = df.select(score.alias("s"), first.cast("long").alias("f"))
    # z at its score (counted strictly below), x at its score plus margin.
    at = F.when(F.col("f") == 1, F.col("s") + margin).otherwise(F.col("s"))
    counted = rows.groupBy(at.alias("t")).agg(
        F.sum("f").cast("double").alias("nx"),
        F.sum(F.when(F.col("f") == 1, F.col("s") + margin).otherwise(0.0)).alias("sx"),
        F.sum(1 - F.col("f")).cast("double").alias("nz"),
        F.sum(F.when(F.col("f") == 0, F.col("s")).otherwise(0.0)).alias("sz"),
    )
    ranked = prefix_sums(counted, "t", ("nz", "sz"))
    return ranked.agg(
        F.sum("nx").cast("long").alias("n"),
        F.sum("nz").cast("long").alias("m"),
        F.sum(F.col("nx") * F.col("before_nz")).cast("long").alias("active"),
        F.sum(F.col("sx") * F.col("before_nz") - F.col("nx") * F.col("before_sz")).alias("total"),
    ).withColumn("estimate", F.col("total") / (F.col("n").cast("double") * F.col("m")))
