"""Averages of a kernel over tuples: complete, sampled, within workers, and over repeated shuffles.

All estimators return their parts as frames: `local_*` one row per (round, worker), `combine`
one row. A worker without tuples contributes 0 by default (`empty="zero"`), is left out
(`"skip"`) or is an error (`"error"`).
"""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.keyed import keyed_u64, permute, sample_rows, unpermute
from .kernels import Kernel
from .samples import number_rows
from .samples import sizes as count_rows
from .schemes import hash_rank, seeded
from .sorted_forms import auc_by_worker, auc_counts, chain_sums, chains_by_worker, gaps_by_worker, product_mean, square_gaps, triple_ranges


def _named(df: DataFrame, sample: int, name: str, extra: tuple[str, ...] = ()) -> DataFrame:
    return df.where(F.col("sample") == sample).select(*extra, F.col("score").alias(name), F.col("key").alias(f"{name}_key"))


def summed(pairs: DataFrame, value: Column, by: tuple[str, ...] = ()) -> DataFrame:
    """by..., tuples, total: the partial-and-final aggregate that all estimators end in."""
    return pairs.select(*by, value.alias("_h")).groupBy(*by).agg(
        F.count("_h").alias("tuples"), F.sum("_h").alias("total")
    )


#: The largest table of numbers that an estimator ships to every task.
BROADCAST_BYTES = 64 << 20


# ------------------------------------------------------------------ over all tuples


def tuples(samples: DataFrame, kernel: Kernel, by: tuple[str, ...] = ()) -> DataFrame:
    """Every tuple of the kernel's degrees, joined on `by` (equal) and, inside a block, in the
    order of the keys. Columns are x, z for two samples of degree one, else s0, s1, ..."""
    names = ["x", "z"] if kernel.degrees == (1, 1) else ["a", "b", "c"][: kernel.arity] if len(kernel.degrees) == 1 else [
        f"s{i}" for i in range(kernel.arity)
    ]
    out, at = None, 0
    for sample, d in enumerate(kernel.degrees):
        for k in range(d):
            name = names[at]
            part = _named(samples, sample, name, by)
            if out is None:
                out = part
            elif k:
                ordered = F.col(f"{names[at - 1]}_key") < F.col(f"{name}_key")
                part = part.select(*[F.col(c).alias(f"_{name}_{c}") for c in by], name, f"{name}_key")
                same = [F.col(c) == F.col(f"_{name}_{c}") for c in by]
                out = out.join(part, reduce(lambda p, q: p & q, [*same, ordered])).drop(*[f"_{name}_{c}" for c in by])
            else:
                out = out.join(part, list(by)) if by else out.crossJoin(part)
            at += 1
    return out.drop(*[f"{n}_key" for n in names])


def complete_u(samples: DataFrame, kernel: Kernel) -> DataFrame:
    """tuples, total, estimate over every tuple. Quadratic by definition: for small samples, as
    the gold standard; `sorted_forms` gives the same number without pairs where it can."""
    pairs = tuples(samples, kernel)
    names = [c for c in pairs.columns]
    return summed(pairs, kernel(*map(F.col, names))).withColumn("estimate", F.col("total") / F.col("tuples"))


def _auc_sums(samples: DataFrame, by: tuple[str, ...] = ()) -> DataFrame:
    r = auc_counts(samples, F.col("score"), F.col("sample") == 0, by)
    tuples = F.coalesce(F.col("n") * F.col("m"), F.lit(0))
    return r.select(tuples.alias("tuples"), F.when(tuples > 0, F.col("wins")).alias("total"), F.col("auc").alias("estimate"))


def _product_sums(samples: DataFrame) -> DataFrame:
    r = product_mean(samples, F.col("score"), F.col("sample") == 0).withColumn("tuples", F.col("n") * F.col("m"))
    return r.select("tuples", (F.col("estimate") * F.col("tuples")).alias("total"), "estimate")


#: Forms without tuples, by the kernel's name. Those of one sample are for whole-number scores.
COMPLETE_FORMS = {
    "auc_strict": _auc_sums, "chain3": lambda s: chain_sums(s, 3), "product": _product_sums, "sqdiff": square_gaps, "range3": triple_ranges,
}
LOCAL_FORMS = {"auc_strict": lambda a: auc_by_worker(a).drop("value"), "chain3": lambda a: chains_by_worker(a, 3), "absdiff": gaps_by_worker}


def complete_sorted(samples: DataFrame, kernel: Kernel) -> DataFrame:
    """`complete_u` of a kernel that has a form without tuples."""
    return COMPLETE_FORMS[kernel.name](samples)


def local_sorted(assigned: DataFrame, kernel: Kernel, workers: int, rounds: int, empty: str = "zero", first: int = 1) -> DataFrame:
    """`local_estimates` of a kernel that has a form without tuples."""
    return _with_empty(LOCAL_FORMS[kernel.name](assigned), workers, rounds, empty, first)


def complete_tiled(samples: DataFrame, kernel: Kernel, grid: tuple[int, int], seed: int) -> DataFrame:
    """The complete two-sample statistic with its communication made explicit: rows are hashed to
    a row or column of a grid of tiles and copied along it, so that every pair meets in exactly
    one tile, through an equi-join that spreads over any number of tasks. Tiles of the strict area are
    counted by sorting, others by pairs."""
    gx, gz = grid
    h = keyed_u64(seed, "tile", F.col("sample"), F.col("key"))
    x = _named(samples.withColumn("_tx", F.pmod(h, F.lit(gx))), 0, "x", ("_tx",)).withColumn(
        "_tz", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(gz - 1).cast("long")))
    )
    z = _named(samples.withColumn("_tz", F.pmod(h, F.lit(gz))), 1, "z", ("_tz",)).withColumn(
        "_tx", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(gx - 1).cast("long")))
    )
    copied = samples.agg(
        F.sum(F.when(F.col("sample") == 0, gz).otherwise(gx)).cast("long").alias("moved_rows")
    )
    if kernel.name == "auc_strict":
        tile = ("_tx", "_tz")
        sides = [df.select(*tile, F.lit(k).alias("sample"), F.col(c).alias("score")) for k, (df, c) in enumerate(((x, "x"), (z, "z")))]
        sums = _auc_sums(sides[0].unionByName(sides[1]), tile).agg(F.coalesce(F.sum("tuples"), F.lit(0)).alias("tuples"), F.sum("total").alias("total"))
    else:
        sums = summed(x.join(z, ["_tx", "_tz"]), kernel(F.col("x"), F.col("z")))
    return (
        sums
        .withColumn("estimate", F.col("total") / F.col("tuples"))
        .join(F.broadcast(copied))  # one row
    )


def complete_auc_broadcast(samples: DataFrame, most_rows: int = BROADCAST_BYTES // 8) -> DataFrame:
    """tuples, total, estimate of the strict AUC when the second sample is small (checked): its
    sorted scores go to every task, which answers each of its rows by binary search. Nothing is
    shuffled but one short row per task, whatever the size of the first sample."""
    import numpy as np
    import pyarrow as pa

    minority = samples.where("sample = 1").select("score")
    m = minority.count()
    if m > most_rows:
        raise ValueError(f"{m} rows are too many to broadcast; use sorted_forms.auc_counts")
    z = np.sort(minority.toArrow().column(0).to_numpy())
    shipped = samples.sparkSession.sparkContext.broadcast(z)
    schema = pa.schema([("tuples", pa.int64()), ("total", pa.float64())])

    def run(batches):
        below, rows = 0, 0
        for b in batches:
            x = b.column(0).to_numpy(zero_copy_only=False)
            below, rows = below + int(np.searchsorted(shipped.value, x, side="left").sum()), rows + len(x)
        yield pa.RecordBatch.from_arrays([pa.array([rows * len(shipped.value)]), pa.array([float(below)])], schema=schema)

    parts = samples.where("sample = 0").select("score").mapInArrow(run, "tuples long, total double")
    return parts.agg(F.sum("tuples").alias("tuples"), F.sum("total").alias("total")).withColumn(
        "estimate", F.when(F.col("tuples") > 0, F.col("total") / F.col("tuples"))
    )


# ------------------------------------------------------------------ over sampled tuples


def draws(spark, batch: int, n: int, m: int, seed: int, sampling: str = "with_replacement") -> DataFrame:
    """draw, i, j: row numbers of `batch` pairs. Without replacement, the first places of a keyed
    permutation of all n*m pairs; Bernoulli, every pair with chance batch/(n*m), by jumps of
    geometric length, so that the work is in the pairs that are kept."""
    if sampling == "with_replacement":
        b = F.col("id")
        return spark.range(batch).select(
            b.alias("draw"),
            F.pmod(keyed_u64(seed, "pair", 0, b), F.lit(n)).alias("i"),
            F.pmod(keyed_u64(seed, "pair", 1, b), F.lit(m)).alias("j"),
        )
    if sampling == "without_replacement":
        if batch > n * m:
            raise ValueError("more pairs than there are")
        place = permute(F.col("id"), n * m, seed, 0, 0)
        return spark.range(batch).select(F.col("id").alias("draw"), place.alias("_p")).select(
            "draw", F.floor(F.col("_p") / m).alias("i"), (F.col("_p") % m).alias("j")
        )
    if sampling == "bernoulli":
        p = min(1.0, batch / (n * m))
        cells = min(max(1, batch // 64), n * m)
        width = -(-n * m // cells)

        def run(batches):
            import numpy as np
            import pandas as pd

            for frame in batches:
                for cell in frame["id"]:
                    rng = np.random.default_rng([seed, int(cell)])
                    lo, hi = int(cell) * width, min(n * m, (int(cell) + 1) * width)
                    if hi <= lo:
                        continue
                    if p >= 1:
                        at = np.arange(lo, hi)
                    else:
                        at = lo - 1 + np.cumsum(rng.geometric(p, size=int((hi - lo) * p * 2 + 64)))
                        while at[-1] < hi:
                            at = np.concatenate([at, at[-1] + np.cumsum(rng.geometric(p, size=64))])
                        at = at[at < hi]
                    yield pd.DataFrame({"draw": at, "i": at // m, "j": at % m})

        return spark.range(cells).mapInPandas(run, "draw long, i long, j long")
    raise ValueError(f"unknown sampling {sampling}")


def incomplete_u(samples: DataFrame, kernel: Kernel, batch: int, seed: int, sizes: dict[int, int], sampling: str = "with_replacement") -> DataFrame:
    """tuples, total, estimate over drawn pairs of two numbered samples: two equi-joins on idx.
    The draws are the smaller side, so they filter the data early. Without replacement, as many draws as
    there are pairs are every pair once: that is the complete statistic, without pairs where it can be."""
    if sampling == "without_replacement" and batch == sizes[0] * sizes[1] and kernel.name in COMPLETE_FORMS:
        return complete_sorted(samples, kernel)
    drawn = draws(samples.sparkSession, batch, sizes[0], sizes[1], seed, sampling)
    x = samples.where("sample = 0").select(F.col("idx").alias("i"), F.col("score").alias("x"))
    z = samples.where("sample = 1").select(F.col("idx").alias("j"), F.col("score").alias("z"))
    pairs = drawn.join(x, "i").join(z, "j")
    return summed(pairs, kernel(F.col("x"), F.col("z"))).withColumn("estimate", F.col("total") / F.col("tuples"))


def subsample_u(samples: DataFrame, kernel: Kernel, sizes: dict[int, int], seed: int) -> DataFrame:
    """The complete statistic on a keyed subsample of each sample; a slower rate at equal work."""
    parts = [
        sample_rows(samples.where(F.col("sample") == s), F.concat_ws("|", F.lit(str(s)), F.col("key")), n, seed)
        for s, n in sorted(sizes.items())
    ]
    return complete_u(reduce(DataFrame.unionByName, parts), kernel)


# ------------------------------------------------------------------ within workers


def worker_grid(spark, workers: int, rounds: int, first: int = 1) -> DataFrame:
    return spark.range(workers).select(F.col("id").cast("int").alias("worker")).withColumn(
        "round", F.explode(F.sequence(F.lit(first), F.lit(first + rounds - 1)))
    )


def local_estimates(assigned: DataFrame, kernel: Kernel, workers: int, rounds: int, empty: str = "zero", first: int = 1) -> DataFrame:
    """round, worker, tuples, total, value: the kernel's mean over the tuples inside each worker.

    Tuples meet through an equi-join on (round, worker). The grid of all workers is joined last,
    so that one without tuples is seen.
    """
    by = ("round", "worker")
    pairs = tuples(assigned, kernel, by)
    names = [c for c in pairs.columns if c not in by]
    return _with_empty(summed(pairs, kernel(*map(F.col, names)), by), workers, rounds, empty, first)


def _with_empty(found: DataFrame, workers: int, rounds: int, empty: str, first: int = 1) -> DataFrame:
    value = F.when(F.col("tuples") > 0, F.col("total").cast("double") / F.col("tuples"))
    if empty == "skip":
        return found.withColumn("value", value)
    grid = worker_grid(found.sparkSession, workers, rounds, first)
    full = grid.join(found, ["round", "worker"], "left").fillna(0, ["tuples"]).fillna(0.0, ["total"])
    missing = F.lit(0.0) if empty == "zero" else F.raise_error(F.lit("a worker has no tuples")).cast("double")
    return full.withColumn("value", F.coalesce(value, missing))


def local_incomplete(
    assigned: DataFrame, kernel: Kernel, workers: int, rounds: int, batch: int, seed: int, sizes: dict[int, int], empty: str = "zero", first: int = 1
) -> DataFrame:
    """The same over `batch` pairs drawn with replacement inside each worker and round. Parts are
    proportional, so their sizes and slots are known without a window. The draws (which the
    caller sizes) are what the joins are sized by."""
    by = ["round", "worker"]
    spark = assigned.sparkSession

    def part(sample: int) -> Column:  # rows of a sample on a worker: n div N, one more for the first
        n = sizes[sample]
        return (F.lit(n // workers) + F.when(F.col("worker") < n % workers, 1).otherwise(0)).cast("long")

    d = F.col("draw")
    drawn = (
        worker_grid(spark, workers, rounds, first)
        .withColumn("draw", F.explode(F.sequence(F.lit(0), F.lit(batch - 1))))
        .where((part(0) > 0) & (part(1) > 0))
        .select(
            *by,
            "draw",
            F.pmod(keyed_u64(seed, "local", F.col("round"), F.col("worker"), 0, d), part(0)).alias("i"),
            F.pmod(keyed_u64(seed, "local", F.col("round"), F.col("worker"), 1, d), part(1)).alias("j"),
        )
    )
    x = assigned.where("sample = 0").select(*by, F.col("slot").alias("i"), F.col("score").alias("x"))
    z = assigned.where("sample = 1").select(*by, F.col("slot").alias("j"), F.col("score").alias("z"))
    pairs = drawn.join(x, [*by, "i"]).join(z, [*by, "j"])
    return _with_empty(summed(pairs, kernel(F.col("x"), F.col("z")), tuple(by)), workers, rounds, empty, first)


def local_incomplete_by_inverse(
    samples: DataFrame, kernel: Kernel, workers: int, rounds: int, batch: int, seed: int, sizes: dict[int, int], hashed: str = "xxhash64"
) -> DataFrame:
    """`local_incomplete` under the seeded permutation without repartitioning at all: each drawn
    (round, worker, slot) is turned back into the row number that stands there, so only the drawn
    rows are looked up. Same draws, same value."""
    spark = samples.sparkSession

    def part(sample: int) -> Column:
        n = sizes[sample]
        return (F.lit(n // workers) + F.when(F.col("worker") < n % workers, 1).otherwise(0)).cast("long")

    def row(sample: int) -> Column:
        slot = F.pmod(keyed_u64(seed, "local", F.col("round"), F.col("worker"), sample, F.col("draw")), part(sample))
        return unpermute(slot * workers + F.col("worker"), sizes[sample], seed, F.col("round"), sample, hashed)

    drawn = (
        worker_grid(spark, workers, rounds)
        .withColumn("draw", F.explode(F.sequence(F.lit(0), F.lit(batch - 1))))
        .where((part(0) > 0) & (part(1) > 0))
        .select("round", "worker", row(0).alias("i"), row(1).alias("j"))
    )
    x = samples.where("sample = 0").select(F.col("idx").alias("i"), F.col("score").alias("x"))
    z = samples.where("sample = 1").select(F.col("idx").alias("j"), F.col("score").alias("z"))
    pairs = drawn.join(x, "i").join(z, "j")
    return _with_empty(summed(pairs, kernel(F.col("x"), F.col("z")), ("round", "worker")), workers, rounds, "zero")


def combine(local: DataFrame, weighting: str = "equal", moved_rows: int | None = None) -> DataFrame:
    """workers, rounds, tuples, estimate (and moved_rows, if the caller knows them): mean over workers, then over rounds. `tuples` weighting
    (by tuples, not the method's own) is on offer for unequal parts."""
    weight = F.avg("value") if weighting == "equal" else F.sum("total") / F.sum("tuples")
    by_round = local.groupBy("round").agg(F.count("*").alias("workers"), F.sum("tuples").alias("tuples"), weight.alias("value"))
    out = by_round.agg(
        F.max("workers").alias("workers"),
        F.count("*").alias("rounds"),
        F.sum("tuples").cast("long").alias("tuples"),
        F.avg("value").alias("estimate"),
    )
    return out if moved_rows is None else out.withColumn("moved_rows", F.lit(moved_rows).cast("long"))


def shipped_rows(sizes: dict[int, int], rounds: int) -> int:
    """Rows that `rounds` repartitions ship: all of them, every time."""
    return rounds * sum(sizes.values())


def _numbered(samples: DataFrame, sizes: dict[int, int] | None) -> tuple[DataFrame, dict[int, int]]:
    return samples if "idx" in samples.columns else number_rows(samples), sizes or count_rows(samples)


def repartitioned_u(
    samples: DataFrame,
    kernel: Kernel,
    workers: int,
    rounds: int,
    seed: int,
    batch: int | None = None,
    sizes: dict[int, int] | None = None,
    permutation: str = "swap_or_not",
    execution: str = "auto",
    empty: str = "zero",
    hashed: str = "xxhash64",
) -> DataFrame:
    """Per-(round, worker) estimates over `rounds` fresh shuffles.

    By default rows find their workers by the seeded permutation of their numbers ("hash_rank" sorts
    each sample instead). Kernels with a sorted form take no pairs. Fused: one plan for all rounds,
    rows copied once per round. Iterative: a job per round, whose short result rows are folded on
    the driver before its shuffle files go, so that shuffle storage holds one copy of the data.
    Inverse: drawn pairs only, looked up by the inverse permutation, no repartition. "auto" leaves
    this to `planner.choose_plan`."""
    from ..plans.planner import choose_plan

    ranked = permutation == "hash_rank"
    if not ranked or batch is not None or execution == "auto":
        samples, sizes = (samples, sizes or count_rows(samples)) if ranked else _numbered(samples, sizes)
    has_sorted = kernel.name == "auc_strict" and batch is None
    if execution == "auto":
        plan = choose_plan(has_sorted, sizes[0], sizes.get(1, sizes[0]), workers, rounds)
        execution = "iterative" if plan["execution"] == "iterative" else "fused"
        if batch is not None and not ranked and set(sizes) == {0, 1} and empty == "zero":
            execution = "inverse"
    if execution == "inverse":
        return local_incomplete_by_inverse(samples, kernel, workers, rounds, batch, seed, sizes, hashed)

    def one(first: int, count: int) -> DataFrame:
        if ranked:
            assigned = hash_rank(samples, workers, count, seed, True, first)
        else:
            assigned = seeded(samples, sizes, workers, count, seed, first, hashed)
        if batch is not None:
            return local_incomplete(assigned, kernel, workers, count, batch, seed, sizes, empty, first)
        if has_sorted:
            return _with_empty(auc_by_worker(assigned).drop("value"), workers, count, empty, first)
        return local_estimates(assigned, kernel, workers, count, empty, first)

    if execution == "fused":
        return one(1, rounds)
    spark, rows = samples.sparkSession, []
    for t in range(1, rounds + 1):  # a row per worker and round comes back
        here = one(t, 1).select("round", "worker", "tuples", "total", "value")
        rows += [tuple(r) for r in here.collect()]
        spark.sparkContext._jvm.System.gc()  # lets Spark delete the round's shuffle files
    return spark.createDataFrame(rows, "round int, worker int, tuples long, total double, value double")


def early_stopped(
    samples: DataFrame,
    kernel: Kernel,
    workers: int,
    seed: int,
    tolerance: float,
    max_rounds: int = 32,
    least_rounds: int = 3,
    hashed: str = "xxhash64",
) -> DataFrame:
    """round, value, estimate, std_error: shuffle until the standard error of the mean over the
    rounds is below `tolerance`. One action per round; a handful of numbers on the driver."""
    values: list[float] = []
    rows = []
    samples, sizes = _numbered(samples, None)
    for t in range(1, max_rounds + 1):
        local = local_estimates(seeded(samples, sizes, workers, 1, seed, t, hashed), kernel, workers, 1, "zero", t)
        values.append(local.agg(F.avg("value").alias("v")).first().v)
        mean = sum(values) / t
        error = (sum((v - mean) ** 2 for v in values) / (t - 1) / t) ** 0.5 if t > 1 else None
        rows.append((t, values[-1], mean, error))
        if t >= least_rounds and error is not None and error <= tolerance:
            break
    return samples.sparkSession.createDataFrame(rows, "round int, value double, estimate double, std_error double")
