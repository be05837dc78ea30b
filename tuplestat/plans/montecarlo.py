"""Monte-Carlo runs in parallel: one keyed generator per run, runs spread over tasks."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

SCHEMES = ("prop_swor", "swor", "swor_iid", "prop_swr", "stride", "static")


def strict_auc(x: np.ndarray, z: np.ndarray) -> float:
    """Share of pairs with z < x; 0 without pairs."""
    if not len(x) or not len(z):
        return 0.0
    return float(np.searchsorted(np.sort(z), x, side="left").sum()) / (len(x) * len(z))


def parts(rng: np.random.Generator, n: int, m: int, workers: int, scheme: str, rnd: int = 1) -> list[tuple[np.ndarray, np.ndarray]]:
    """Row numbers of both samples on each worker. Stride and static use no randomness: they depend on
    the rows' order, and on the round or not even on that."""
    if scheme in ("stride", "static"):
        where = [(i + (i // workers * rnd if scheme == "stride" else 0)) % workers for i in (np.arange(n), np.arange(m))]
        return [tuple(np.flatnonzero(a == w) for a in where) for w in range(workers)]
    if scheme == "prop_swor":
        p, q = rng.permutation(n), rng.permutation(m)
        return [(p[w::workers], q[w::workers]) for w in range(workers)]
    if scheme == "swor":
        p = rng.permutation(n + m)
        cut = [p[w::workers] for w in range(workers)]
        return [(c[c < n], c[c >= n] - n) for c in cut]
    if scheme == "swor_iid":
        a, b = rng.integers(workers, size=n), rng.integers(workers, size=m)
        return [(np.flatnonzero(a == w), np.flatnonzero(b == w)) for w in range(workers)]
    if scheme == "prop_swr":
        return [(rng.integers(n, size=n // workers), rng.integers(m, size=m // workers)) for _ in range(workers)]
    raise ValueError(f"unknown scheme {scheme}")


def one_run(x: np.ndarray, z: np.ndarray, workers: int, rounds: int, batch: int, scheme: str, rng: np.random.Generator) -> dict[str, float]:
    """All estimators of the strict AUC on one pair of samples."""
    n, m = len(x), len(z)
    out = {"complete": strict_auc(x, z)}
    i, j = rng.integers(n, size=workers * batch), rng.integers(m, size=workers * batch)
    out["incomplete"] = float((z[j] < x[i]).mean())
    full, drawn = [], []
    for t in range(rounds):
        f, d = 0.0, 0.0
        for a, b in parts(rng, n, m, workers, scheme, t + 1):
            f += strict_auc(x[a], z[b])
            if len(a) and len(b):
                d += (z[rng.choice(b, size=batch)] < x[rng.choice(a, size=batch)]).mean()
        full.append(f / workers)
        drawn.append(d / workers)
    out["local"], out["local_incomplete"] = full[0], float(drawn[0])
    out["repartitioned"], out["repartitioned_incomplete"] = float(np.mean(full)), float(np.mean(drawn))
    k, h = max(1, int(round((workers * batch * n / m) ** 0.5))), max(1, int(round((workers * batch * m / n) ** 0.5)))
    out["subsample"] = strict_auc(x[rng.permutation(n)[:k]], z[rng.permutation(m)[:h]])
    return out


def two_point_runs(rng: np.random.Generator, runs: int, eps: tuple[float, float], n: int, m: int, workers: int, rounds: int, batch: int) -> dict[str, np.ndarray]:
    """`one_run` under proportional shuffles for many samples of the two-point law at once. A pair is
    out of order only where x is 0 and z is 1, so an area is one minus a product of shares, and shares
    of a worker are hypergeometric: the same law without rows."""
    a, b = rng.binomial(n, eps[0], runs), rng.binomial(m, eps[1], runs)  # rows that can lose
    sizes = [np.array([k // workers + (w < k % workers) for w in range(workers)]) for k in (n, m)]

    def dealt(total: np.ndarray, rows: int, part: np.ndarray) -> np.ndarray:
        out, left, room = np.zeros((runs, workers), dtype=np.int64), total.copy(), rows
        for w in range(workers):
            out[:, w] = rng.hypergeometric(left, room - left, part[w]) if room > part[w] else left
            left, room = left - out[:, w], room - part[w]
        return out

    out = {"complete": 1 - a * b / (n * m), "incomplete": 1 - rng.binomial(workers * batch, a * b / (n * m)) / (workers * batch)}
    full, drawn = np.zeros((rounds, runs)), np.zeros((rounds, runs))
    for t in range(rounds):
        lost = dealt(a, n, sizes[0]) * dealt(b, m, sizes[1]) / (sizes[0] * sizes[1])
        full[t], drawn[t] = 1 - lost.mean(axis=1), 1 - (rng.binomial(batch, lost) / batch).mean(axis=1)
    out |= {"local": full[0], "local_incomplete": drawn[0], "repartitioned": full.mean(axis=0), "repartitioned_incomplete": drawn.mean(axis=0)}
    k, h = max(1, int(round((workers * batch * n / m) ** 0.5))), max(1, int(round((workers * batch * m / n) ** 0.5)))
    out["subsample"] = 1 - rng.hypergeometric(a, n - a, k) * rng.hypergeometric(b, m - b, h) / (k * h)
    return out


def law_runs(
    spark: SparkSession, runs: int, n: int, m: int, eps: tuple[float, ...], workers: int, rounds: int, batch: int = 100, scheme: str = "prop_swor", seed: int = 7,
    shares: dict[float, tuple[float, float]] | None = None,
) -> DataFrame:
    """run, eps, estimator, value: fresh samples of the two-point law in every run. `shares`: of each eps, the
    share of rows of both samples that can lose, where it is not eps itself."""
    shares = shares or {e: (e, e) for e in eps}
    schema = pa.schema([("run", pa.int32()), ("eps", pa.float64()), ("estimator", pa.string()), ("value", pa.float64())])

    def at_once(batches):
        for b in batches:
            ids = b.column(0).to_numpy()
            for k, e in enumerate(eps):
                found = two_point_runs(np.random.default_rng([seed, int(ids[0]), k]), len(ids), shares[e], n, m, workers, rounds, batch)
                for name, values in found.items():
                    yield pa.RecordBatch.from_arrays([pa.array(c, t.type) for c, t in zip((ids, np.full(len(ids), e), [name] * len(ids), values), schema)], schema=schema)

    def work(batches):
        for b in batches:
            rows = []
            for run in b.column(0).to_pylist():
                for k, e in enumerate(eps):
                    rng = np.random.default_rng([seed, run, k])
                    x = np.where(rng.random(n) < shares[e][0], 0.0, 2.0)
                    z = np.where(rng.random(m) < shares[e][1], 1.0, -1.0)
                    rows += [(run, e, name, v) for name, v in one_run(x, z, workers, rounds, batch, scheme, rng).items()]
            yield pa.RecordBatch.from_arrays([pa.array(c, type=f.type) for c, f in zip(zip(*rows), schema)], schema=schema)

    spread = max(1, min(runs, 64))
    if scheme == "prop_swor" and n >= workers and m >= workers:
        ids = spark.range(0, runs, 1, spread).select(F.col("id").cast("int").alias("run"))
        return ids.mapInArrow(at_once, "run int, eps double, estimator string, value double")
    ids = spark.range(runs).select(F.col("id").cast("int").alias("run")).repartition(spread)
    return ids.mapInArrow(work, "run int, eps double, estimator string, value double")


def table_runs(
    samples: DataFrame, runs: int, workers: int, rounds: int, batch: int = 100, scheme: str = "prop_swor", seed: int = 7
) -> DataFrame:
    """run, estimator, value on one fixed table: only the shuffles vary. The two samples' scores
    are shipped to the runs, so they must be small (64 MB, checked first)."""
    if samples.count() * 8 > 64 << 20:
        raise ValueError("conditional runs are for tables of at most 64 MB of scores")
    spark = samples.sparkSession
    rows = samples.select("sample", "key", "score").orderBy("sample", "key").select("sample", "score").toArrow()
    sample, score = rows.column(0).to_numpy(), rows.column(1).to_numpy()
    x, z = score[sample == 0], score[sample == 1]
    shipped = spark.sparkContext.broadcast((x, z))
    schema = pa.schema([("run", pa.int32()), ("estimator", pa.string()), ("value", pa.float64())])

    def work(batches):
        a, b = shipped.value
        for part in batches:
            out = []
            for run in part.column(0).to_pylist():
                found = one_run(a, b, workers, rounds, batch, scheme, np.random.default_rng([seed, run]))
                out += [(run, name, v) for name, v in found.items()]
            yield pa.RecordBatch.from_arrays([pa.array(c, type=f.type) for c, f in zip(zip(*out), schema)], schema=schema)

    ids = spark.range(runs).select(F.col("id").cast("int").alias("run")).repartition(max(1, min(runs, 64)))
    return ids.mapInArrow(work, "run int, estimator string, value double")


def mc_summary(runs: DataFrame, by: tuple[str, ...], truth: dict | None = None) -> DataFrame:
    """by..., runs, mean, variance, and bias and mse where the truth is known."""
    out = runs.groupBy(*by).agg(F.count("*").alias("runs"), F.avg("value").alias("mean"), F.var_samp("value").alias("variance"))
    if truth is None:
        return out
    known = runs.sparkSession.createDataFrame([(k, float(v)) for k, v in truth.items()], f"{by[0]} double, truth double")
    out = out.join(F.broadcast(known), by[0])
    bias = F.col("mean") - F.col("truth")
    return out.withColumn("bias", bias).withColumn("mse", F.col("variance") * (F.col("runs") - 1) / F.col("runs") + bias * bias).drop("truth")


def trace_bands(trace: DataFrame, by: tuple[str, ...], lo: float = 0.05, hi: float = 0.95) -> DataFrame:
    """by..., runs, low, median, high of `value` across runs."""
    return trace.groupBy(*by).agg(
        F.count("*").alias("runs"),
        F.percentile("value", lo).alias("low"),
        F.percentile("value", 0.5).alias("median"),
        F.percentile("value", hi).alias("high"),
    )
