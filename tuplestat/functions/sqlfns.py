"""The SQL surface: functions and table functions registered under plain names."""

from __future__ import annotations

import hashlib

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


def _u64(*parts) -> int:
    return int(hashlib.md5("|".join(map(str, parts)).encode()).hexdigest()[:15], 16)


@F.pandas_udf(T.DoubleType())
def auc_agg(score: pd.Series, label: pd.Series) -> float:
    """Strict AUC of a group (label 1 against the rest); a group must fit a worker."""
    s, y = score.to_numpy(dtype=float), label.to_numpy() == 1
    n, m = int(y.sum()), int((~y).sum())
    if not n or not m:
        return float("nan")
    return float(np.searchsorted(np.sort(s[~y]), s[y], side="left").sum()) / (n * m)


@F.pandas_udf(T.DoubleType())
def gini_agg(value: pd.Series) -> float:
    """Mean absolute difference of a group."""
    v = np.sort(value.to_numpy(dtype=float))
    n = len(v)
    return float((2 * np.arange(1, n + 1) - n - 1) @ v) / (n * (n - 1) / 2) if n > 1 else float("nan")


@F.pandas_udf(T.DoubleType())
def kendall_agg(x: pd.Series, y: pd.Series) -> float:
    """Share of concordant pairs of a group, by merge counting on ranks."""
    a, b = x.to_numpy(dtype=float), y.to_numpy(dtype=float)
    n = len(a)
    if n < 2:
        return float("nan")
    return float(concordant_pairs(a, b)) / (n * (n - 1) / 2)


def concordant_pairs(a: np.ndarray, b: np.ndarray) -> int:
    """Pairs ordered alike in both coordinates: a Fenwick tree over the ranks of b, groups of
    equal a counted before they are entered. O(n log n)."""
    rank = np.unique(b, return_inverse=True)[1] + 1
    order = np.argsort(a, kind="stable")
    tree = np.zeros(rank.max(initial=0) + 2, dtype=np.int64)
    total, i, n = 0, 0, len(a)
    while i < n:
        j = i
        while j < n and a[order[j]] == a[order[i]]:
            j += 1
        for k in order[i:j]:
            r = rank[k] - 1
            while r > 0:
                total += int(tree[r])
                r -= r & -r
        for k in order[i:j]:
            r = rank[k]
            while r < len(tree):
                tree[r] += 1
                r += r & -r
        i = j
    return total


@F.pandas_udf(T.DoubleType())
def vus3_agg(score: pd.Series, label: pd.Series) -> float:
    """Share of rising triples (labels 1, 2, 3) of a group."""
    s, y = score.to_numpy(dtype=float), label.to_numpy()
    a, b, c = (np.sort(s[y == k]) for k in (1, 2, 3))
    if not (len(a) and len(b) and len(c)):
        return float("nan")
    below = np.searchsorted(a, b, side="left")
    above = len(c) - np.searchsorted(c, b, side="right")
    return float((below * above).sum()) / (len(a) * len(b) * len(c))


@F.udtf(returnType=T.StructType([T.StructField(n, T.LongType()) for n in ("draw", "i", "j")]))
class PairDraws:
    """pair_draws(n, m, batch, seed): row numbers of pairs drawn with replacement."""

    def eval(self, n: int, m: int, batch: int, seed: int):
        for b in range(batch):
            yield b, _u64(seed, "pair", 0, b) % n, _u64(seed, "pair", 1, b) % m


@F.udtf(returnType=T.StructType([T.StructField("round", T.IntegerType()), T.StructField("idx", T.LongType()), T.StructField("worker", T.IntegerType())]))
class AssignRounds:
    """assign_rounds(n, workers, rounds, seed): a strided deal with a keyed offset per round."""

    def eval(self, n: int, workers: int, rounds: int, seed: int):
        for t in range(1, rounds + 1):
            shift = _u64(seed, "stride", t) % workers
            for i in range(n):
                yield t, i, (i + shift + i // workers * t) % workers


def register_all(spark: SparkSession) -> None:
    """SQL functions hinge_pair, keyed_worker, auc_pair (inlined by the optimizer), aggregates
    auc_agg, gini_agg, kendall_agg, vus3_agg, and the table functions."""
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION hinge_pair(sx DOUBLE, sz DOUBLE) RETURNS DOUBLE RETURN greatest(0D, 1D + sx - sz)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION auc_pair(sx DOUBLE, sz DOUBLE) RETURNS INT RETURN CASE WHEN sz < sx THEN 1 ELSE 0 END")
    spark.sql(
        "CREATE OR REPLACE TEMPORARY FUNCTION keyed_worker(seed INT, rnd INT, k STRING, n INT) RETURNS INT "
        "RETURN cast(pmod(cast(conv(substr(md5(concat_ws('|', cast(seed AS STRING), cast(rnd AS STRING), k)), 1, 15), 16, 10) AS BIGINT), n) AS INT)"
    )
    for name, f in (("auc_agg", auc_agg), ("gini_agg", gini_agg), ("kendall_agg", kendall_agg), ("vus3_agg", vus3_agg)):
        spark.udf.register(name, f)
    spark.udtf.register("pair_draws", PairDraws)
    spark.udtf.register("assign_rounds", AssignRounds)
