"""Variance of every estimator, from the components v1, v2 (row effects) and v0 (pair effect).

The formulas are plain arithmetic, so they take numbers or Columns. `components_*` estimate the
components from data (two-way random effects, unbiased); `discrete_law` has them in closed form
for the two-point law used as a worst case.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..operators.sorted_forms import prefix_sums


@dataclass(frozen=True)
class Components:
    v1: float
    v2: float
    v0: float

    @property
    def v(self) -> float:
        return self.v0 + self.v1 + self.v2


def var_complete(c, n, m):
    return c.v1 / n + c.v2 / m + c.v0 / (n * m)


def var_incomplete(c, n, m, batch):
    return (1 - 1 / batch) * var_complete(c, n, m) + c.v / batch


def var_local(c, n, m, workers):
    """Mean of within-worker averages, proportional parts without replacement."""
    return var_complete(c, n, m) + (workers - 1) * c.v0 / (n * m)


def var_local_incomplete(c, n, m, workers, batch):
    return (1 - 1 / batch) * var_local(c, n, m, workers) + c.v / (workers * batch)


def var_repartitioned(c, n, m, workers, rounds):
    return var_complete(c, n, m) + (workers - 1) * c.v0 / (n * m * rounds)


def var_repartitioned_incomplete(c, n, m, workers, rounds, batch):
    return (
        var_repartitioned(c, n, m, workers, rounds)
        - var_local(c, n, m, workers) / (rounds * batch)
        + c.v / (workers * rounds * batch)
    )


def conditional_variance(ms0, n, m, workers, rounds):
    """Variance over shuffles of one fixed table, when the workers divide both samples."""
    return (workers - 1) * ms0 / (n * m * rounds)


def var_prop_swr(c, n, m, workers, rounds, batch=None):
    """Parts drawn with replacement, proportional sizes; with `batch`, pairs drawn inside them."""

    def whole(t):
        extra = (
            (1 - 1 / n) * (c.v1 / n + c.v0 / (n * m))
            + (1 - 1 / m) * (c.v2 / m + c.v0 / (n * m))
            + workers * (1 - 1 / n) * (1 - 1 / m) * c.v0 / (n * m)
        )
        return var_complete(c, n, m) + extra / t

    if batch is None:
        return whole(rounds)
    block = workers * whole(1) - (workers - 1) * var_complete(c, n, m)
    return whole(rounds) + (c.v - block) / (workers * batch * rounds)


def swor_empty_probability(n: int, m: int, workers: int, fixed_size: bool = True) -> float:
    """Chance that a given worker gets none of the m minority rows when rows are dealt without
    regard to sample: hypergeometric for parts of fixed size, else a power."""
    if not fixed_size:
        return (1 - 1 / workers) ** m
    part = (n + m) // workers
    if part > n:
        return 0.0
    return math.exp(math.fsum(math.log((n - i) / (n + m - i)) for i in range(part)))


def swor_bias(u: float, n: int, m: int, workers: int, fixed_size: bool = True) -> float:
    """Bias of the zero rule for empty workers."""
    return -u * swor_empty_probability(n, m, workers, fixed_size)


def swor_numeric(c: Components, n: int, m: int, workers: int) -> float:
    """Variance of one round with independently thrown rows and skipped empty workers, by summing
    the variance of a worker's block over its binomial minority size (majority taken as fixed)."""
    part_n, total, mass = n / workers, 0.0, 0.0
    p = 1 / workers
    for k in range(1, m + 1):
        log = math.lgamma(m + 1) - math.lgamma(k + 1) - math.lgamma(m - k + 1) + k * math.log(p) + (m - k) * math.log1p(-p)
        w = math.exp(log)
        total, mass = total + w * (c.v1 / part_n + c.v2 / k + c.v0 / (part_n * k)), mass + w
    return total / mass / workers


def is_degenerate(c, tolerance: float = 0.05):
    """Row effects vanish beside the pair effect."""
    return (c.v1 + c.v2) <= tolerance * c.v0


def relative_variance(variance, c, n, m):
    return variance / var_complete(c, n, m)


def discrete_law(p, q) -> Components:
    """Components of the strict AUC kernel when Z is +1 with chance p (else -1) and X is 2 with
    chance q (else 0)."""
    v1 = p * p * q * (1 - q)
    v2 = (1 - q) * (1 - q) * p * (1 - p)
    v = p * (1 - p + p * q) * (1 - q)
    return Components(v1, v2, v - v1 - v2)


def epsilon_law(eps) -> Components:
    return discrete_law(eps, 1 - eps)


def equal_budget(n: int, m: int, workers: int, rounds0: int, batch: int) -> float:
    """Rounds T with workers * batch * T pairs equal to `rounds0` complete rounds."""
    return n * m * rounds0 / workers / (workers * batch)


def dominance_gap(c, n, m, workers, rounds0, batch):
    """Sampled minus complete variance at equal pairs; never negative for workers <= min(n, m)."""
    return var_repartitioned_incomplete(c, n, m, workers, equal_budget(n, m, workers, rounds0, batch), batch) - var_repartitioned(
        c, n, m, workers, rounds0
    )


def rate_table(n, degrees: tuple[int, ...]) -> dict[str, float]:
    """Orders of uniform deviations at sample size n: sampled tuples against subsampled rows."""
    return {
        "sampled_tuples": math.sqrt(math.log(n) / n),
        "subsampled_rows": math.sqrt(math.log(n) / n ** (1 / sum(degrees))),
    }


# ------------------------------------------------------------------ from data


def auc_effects(df: DataFrame, score: Column, first: Column) -> DataFrame:
    """score, pos, neg, r, c: rows of either sample at each distinct score and the row means of
    the strict AUC kernel there. No pairs."""
    counts = (
        df.select(score.alias("score"), first.cast("long").alias("_f"))
        .groupBy("score")
        .agg(F.sum("_f").alias("pos"), F.sum(1 - F.col("_f")).alias("neg"))
    )
    ranked = prefix_sums(counts, "score", ("pos", "neg"))
    totals = counts.agg(F.sum("pos").alias("n"), F.sum("neg").alias("m"))
    return ranked.join(F.broadcast(totals)).select(
        "score",
        "pos",
        "neg",
        "n",
        "m",
        (F.col("before_neg") / F.col("m")).alias("r"),
        ((F.col("n") - F.col("before_pos") - F.col("pos")) / F.col("n")).alias("c"),
    )


def auc_components(df: DataFrame, score: Column, first: Column) -> DataFrame:
    """n, m, u, ms0, v0, v1, v2 of the strict AUC kernel, unbiased; an indicator's total sum of
    squares follows from its mean."""
    e = auc_effects(df, score, first)
    s = e.agg(
        F.max("n").cast("double").alias("n"),
        F.max("m").cast("double").alias("m"),
        F.sum(F.col("pos") * F.col("r")).alias("sr"),
        F.sum(F.col("pos") * F.col("r") * F.col("r")).alias("srr"),
        F.sum(F.col("neg") * F.col("c") * F.col("c")).alias("scc"),
    ).withColumn("u", F.col("sr") / F.col("n"))
    n, m, u = F.col("n"), F.col("m"), F.col("u")
    ss_x = m * (F.col("srr") - n * u * u)
    ss_z = n * (F.col("scc") - m * u * u)
    ms0 = (n * m * u * (1 - u) - ss_x - ss_z) / ((n - 1) * (m - 1))
    return s.select(
        n.cast("long").alias("n"),
        m.cast("long").alias("m"),
        "u",
        ms0.alias("v0"),
        ((ss_x / (n - 1) - ms0) / m).alias("v1"),
        ((ss_z / (m - 1) - ms0) / n).alias("v2"),
    )


def pair_components(pairs: DataFrame, x_key: str, z_key: str, value: Column) -> DataFrame:
    """The same for any kernel, from all pairs (small samples)."""
    p = pairs.select(F.col(x_key).alias("x"), F.col(z_key).alias("z"), value.alias("h"))
    t = p.agg(F.count("*").cast("double").alias("nm"), F.avg("h").alias("u"), F.sum(F.col("h") * F.col("h")).alias("hh"))
    r = p.groupBy("x").agg(F.avg("h").alias("r")).agg(F.count("*").cast("double").alias("n"), F.sum(F.col("r") * F.col("r")).alias("rr"))
    c = p.groupBy("z").agg(F.avg("h").alias("c")).agg(F.count("*").cast("double").alias("m"), F.sum(F.col("c") * F.col("c")).alias("cc"))
    n, m, u = F.col("n"), F.col("m"), F.col("u")
    ss_x, ss_z = m * (F.col("rr") - n * u * u), n * (F.col("cc") - m * u * u)
    ms0 = (F.col("hh") - F.col("nm") * u * u - ss_x - ss_z) / ((n - 1) * (m - 1))
    return t.join(F.broadcast(r)).join(F.broadcast(c)).select(  # one row each
        n.cast("long").alias("n"),
        m.cast("long").alias("m"),
        "u",
        ms0.alias("v0"),
        ((ss_x / (n - 1) - ms0) / m).alias("v1"),
        ((ss_z / (m - 1) - ms0) / n).alias("v2"),
    )


def block_components(samples: DataFrame, kernel) -> DataFrame:
    """The same for any kernel with a NumPy twin, pairs met block by block."""
    from ..operators.blocks import pair_sums

    h, k = F.col("rows") * F.col("total"), F.col("rows") * F.col("total") * F.col("total")
    side = lambda s, v: F.sum(F.when(F.col("side") == s, v).otherwise(0.0))
    t = pair_sums(samples, kernel).agg(
        side(0, F.col("rows")).alias("n"), side(1, F.col("rows")).alias("m"), side(0, h).alias("h"),
        side(0, F.col("rows") * F.col("squares")).alias("hh"), side(0, k).alias("k0"), side(1, k).alias("k1"),
    )
    n, m = F.col("n"), F.col("m")
    u = F.col("h") / (n * m)
    ss_x, ss_z = F.col("k0") / m - n * m * u * u, F.col("k1") / n - n * m * u * u
    ms0 = (F.col("hh") - n * m * u * u - ss_x - ss_z) / ((n - 1) * (m - 1))
    v1, v2 = (ss_x / (n - 1) - ms0) / m, (ss_z / (m - 1) - ms0) / n
    return t.select(n.cast("long").alias("n"), m.cast("long").alias("m"), u.alias("u"), ms0.alias("v0"), v1.alias("v1"), v2.alias("v2"))


def confidence_interval(estimate: Column, variance: Column, level: float = 0.95) -> tuple[Column, Column]:
    """Normal approximation; the quantile by bisection of the error function."""
    lo, hi = 0.0, 10.0
    for _ in range(80):
        mid = (lo + hi) / 2
        lo, hi = (mid, hi) if math.erf(mid / math.sqrt(2)) < level else (lo, mid)
    half = F.lit(lo) * F.sqrt(F.greatest(variance, F.lit(0.0)))
    return estimate - half, estimate + half
