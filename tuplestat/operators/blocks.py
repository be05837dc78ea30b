"""Kernels over all pairs in NumPy, block against block, for kernels that have no form without pairs.

Rows are packed into blocks that meet in a cross join; a task holds two blocks at a time. Scores are
aggregated first, so rows of one score are worked out once."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .kernels import Kernel

BLOCK = 4096
#: Rows of the first block that are worked out at once.
STRIP = 256
#: Vectors of a block.
VECTORS = 1024
#: Most bytes of blocks in one Arrow batch.
BATCH_BYTES = 8 << 20


def _small_batches(df: DataFrame) -> None:
    conf = df.sparkSession.conf
    now = conf.get("spark.sql.execution.arrow.maxBytesPerBatch", None)
    if now is None or not now.isdigit() or int(now) > BATCH_BYTES:
        conf.set("spark.sql.execution.arrow.maxBytesPerBatch", str(BATCH_BYTES))


def _tasks(df: DataFrame) -> int:
    return max(2, df.sparkSession.sparkContext.defaultParallelism)


def _packed(counted: DataFrame, side: str, parts: int) -> DataFrame:
    """Blocks (scores, weights) of score, c."""
    schema = pa.schema([(f"v{side}", pa.binary()), (f"w{side}", pa.binary())])

    def pack(batches):
        for b in batches:
            v, w = (np.asarray(b.column(k).to_numpy(zero_copy_only=False), dtype=float) for k in (0, 1))
            for at in range(0, len(v), BLOCK):
                one = [a[at : at + BLOCK].tobytes() for a in (v, w)]
                yield pa.RecordBatch.from_arrays([pa.array([x], pa.binary()) for x in one], schema=schema)

    return counted.select("score", "c").repartition(parts, "score").mapInArrow(pack, f"v{side} binary, w{side} binary")


def pair_sums(samples: DataFrame, kernel: Kernel) -> DataFrame:
    """side, score, rows, total, squares: for each distinct score of sample 0 or 1, its rows and the sums of
    the kernel and of its square over all rows of the other sample. Needs the kernel's NumPy twin."""
    _small_batches(samples)
    counted = samples.groupBy("sample", "score").agg(F.count("*").alias("c"))
    x = _packed(counted.where("sample = 0"), "x", _tasks(samples))
    z = _packed(counted.where("sample = 1"), "z", 4)
    value = kernel.numpy
    schema = pa.schema([("side", pa.int32()), ("score", pa.float64()), ("rows", pa.float64()), ("total", pa.float64()), ("squares", pa.float64())])

    def run(batches):
        for b in batches:
            for row in zip(*(c.to_pylist() for c in b.columns)):
                vx, wx, vz, wz = (np.frombuffer(a) for a in row)
                tx, qx, tz, qz = (np.zeros(k) for k in (len(vx), len(vx), len(vz), len(vz)))
                for at in range(0, len(vx), STRIP):
                    s = slice(at, at + STRIP)
                    h = np.asarray(value(vx[s, None], vz[None]), dtype=float)
                    tx[s], tz = h @ wz, tz + wx[s] @ h
                    h *= h
                    qx[s], qz = h @ wz, qz + wx[s] @ h
                for side, columns in enumerate(((vx, wx, tx, qx), (vz, wz, tz, qz))):
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(columns[0]), side), pa.int32()), *map(pa.array, columns)], schema=schema)

    met = x.crossJoin(z).mapInArrow(run, "side int, score double, rows double, total double, squares double")
    return met.groupBy("side", "score").agg(F.max("rows").alias("rows"), F.sum("total").alias("total"), F.sum("squares").alias("squares"))


def complete_blocks(samples: DataFrame, kernel: Kernel) -> DataFrame:
    """tuples, total, estimate over all pairs."""
    s = pair_sums(samples, kernel).groupBy("side").agg(F.sum("rows").alias("n"), F.sum(F.col("rows") * F.col("total")).alias("t"))
    size = lambda k: F.coalesce(F.max(F.when(F.col("side") == k, F.col("n"))), F.lit(0.0))
    r = s.agg((size(0) * size(1)).cast("long").alias("tuples"), F.max(F.when(F.col("side") == 0, F.col("t"))).alias("total"))
    return r.withColumn("estimate", F.when(F.col("tuples") > 0, F.col("total") / F.col("tuples")))


def _vector_blocks(v: DataFrame, side: str) -> DataFrame:
    names = ("lo", "hi", "k", "y", "e", "none")
    kinds = (pa.int64(), pa.int64(), pa.binary(), pa.binary(), pa.binary(), pa.binary())
    schema = pa.schema([(n + side, t) for n, t in zip(names, kinds)])

    def pack(batches):
        for b in batches:
            for at in range(0, b.num_rows, VECTORS):
                key, label, vectors = (b.column(k).slice(at, VECTORS) for k in range(3))
                vectors = vectors.to_pylist()
                none = np.array([e is None or any(x is None for x in e) for e in vectors])
                width = max((len(e) for e in vectors if e is not None), default=0)
                e = np.array([[0.0] * width if n else x for n, x in zip(none, vectors)], dtype=float)
                k, y = key.to_numpy(zero_copy_only=False), np.array([np.nan if x is None else x for x in label.to_pylist()], dtype=float)
                made = (int(k.min()), int(k.max()), k.tobytes(), y.tobytes(), e.tobytes(), none.tobytes())
                yield pa.RecordBatch.from_arrays([pa.array([x], t) for x, t in zip(made, kinds)], schema=schema)

    types = ("long", "long", *["binary"] * 4)
    return v.repartitionByRange(_tasks(v), "key").sortWithinPartitions("key").mapInArrow(pack, ", ".join(f"{n}{side} {t}" for n, t in zip(names, types)))


def metric_pairs(v: DataFrame, margin: float) -> DataFrame:
    """pairs, estimate: the mean of `kernels.metric_pair` over all pairs of rows key, label, vector with
    rising keys. Distances come from inner products of whole blocks. A vector that is null or holds a null
    has no distance; its pairs count with no loss, as `greatest` passes over nulls."""
    _small_batches(v)
    v = v.select(F.col("key").cast("long").alias("key"), "label", F.col("vector").cast("array<double>").alias("vector")).where("key IS NOT NULL")
    a, b = _vector_blocks(v, "a"), _vector_blocks(v, "b")

    def run(batches):
        for batch in batches:
            for r in batch.to_pylist():
                (ka, kb), (ya, yb), (na, nb) = ([np.frombuffer(r[n + s], t) for s in "ab"] for n, t in (("k", np.int64), ("y", float), ("none", bool)))
                ea, eb = np.frombuffer(r["ea"]).reshape(len(ka), -1), np.frombuffer(r["eb"]).reshape(len(kb), -1)
                gap = (ea * ea).sum(axis=1)[:, None] + (eb * eb).sum(axis=1)[None] - 2 * (ea @ eb.T) - margin
                loss = np.where(ya[:, None] == yb[None], gap, -gap)
                loss += 1
                np.maximum(loss, 0, out=loss)
                loss[na], loss[:, nb] = 0, 0
                if r["hia"] < r["lob"]:
                    pairs, total = loss.size, loss.sum()
                else:
                    rising = ka[:, None] < kb[None]
                    pairs, total = rising.sum(), loss[rising].sum()
                yield pa.RecordBatch.from_pydict({"pairs": [int(pairs)], "total": [float(total)]})

    met = a.join(b, F.col("loa") < F.col("hib")).mapInArrow(run, "pairs long, total double")
    r = met.agg(F.coalesce(F.sum("pairs"), F.lit(0)).alias("pairs"), F.sum("total").alias("total"))
    return r.select("pairs", F.when(F.col("pairs") > 0, F.col("total") / F.col("pairs")).alias("estimate"))
