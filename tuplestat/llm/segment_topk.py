"""Exact top-k search by inner product, with multi-resolution segment statistics as filter.

Each vector is cut into equal segments; a segment is summed up by its mean and deviation. For
two segments of length L the inner product is at most L (m m' + s s') (means multiply out, the
centred parts obey Cauchy-Schwarz), and for the distance this is the usual lower bound from
segment means and deviations. Bounds go from one segment to many: whatever cannot reach the
query's current k-th score at a coarse level is never looked at finer, and only survivors get
an exact product in 64-bit integers.

Work is a grid: the query set in blocks of `query_block`, all rows in hashed blocks of
`row_block`; a pair of blocks meets in one task, whose memory is bounded by the two sizes.
Blocks are dealt by a hash of the row, so common vectors spread. Each task returns k rows per
query, and the best k of those are kept.

Vectors that are null or hold null or non-finite components take no part; integer components are
held to the 64-bit range (2**63 - 1 in size), and so are scores, whose sums are exact; vectors of different
length are compared over the shorter one's components; a row does not answer a query of the
same vec_id; equal scores go to the smaller vec_id; repeated rows of one id count once each as
candidates and once as a query; rows with a null id take no part; an empty table, or one
without queries, gives an empty result.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

LEVELS = (1, 4, 16)
ROWS_AT_ONCE = 2048
MOST = 2**63 - 1


def quantised(df: DataFrame, scale: int, id_col: str, vec_col: str) -> DataFrame:
    """vec_id, v (array<bigint>): floor(scale * x) of the rows that take part, held to the 64-bit range."""
    ok = F.col("v").isNotNull() & ~F.exists("v", lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == F.lit(float("inf"))))
    most = F.lit(2.0**63)

    def whole(x):
        y = F.floor(F.when(F.abs(x * F.lit(float(scale))) < most, x * F.lit(float(scale))).otherwise(F.lit(0.0)))
        edge = F.when(x > 0, F.lit(MOST)).otherwise(F.lit(-MOST))
        return F.when(F.abs(x * F.lit(float(scale))) < most, y).otherwise(edge)

    return (
        df.select(F.col(id_col).cast("long").alias("vec_id"), F.col(vec_col).cast("array<double>").alias("v"))
        .where(F.col("vec_id").isNotNull() & ok)
        .select("vec_id", F.transform("v", whole).alias("v"))
    )


def matrix(lists: pa.ChunkedArray) -> np.ndarray:
    """Rows of integers, filled up with zeros (which leave inner products as they are)."""
    rows = lists.combine_chunks() if isinstance(lists, pa.ChunkedArray) else lists
    lengths = rows.value_lengths().fill_null(0).to_numpy(zero_copy_only=False)
    out = np.zeros((len(rows), max(1, int(lengths.max(initial=0)))), dtype=np.int64)
    out[np.arange(out.shape[1])[None, :] < lengths[:, None]] = rows.flatten().to_numpy(zero_copy_only=False)
    return out


def segment_stats(x: np.ndarray, parts: int) -> np.ndarray:
    """Root-length-weighted means and deviations, so that a bound is a dot product of two rows."""
    n, d = x.shape
    parts = min(parts, d)
    edges = np.linspace(0, d, parts + 1).astype(int)
    y, length = x.astype(np.float64), np.diff(edges)
    total = np.add.reduceat(y, edges[:-1], axis=1)
    square = np.add.reduceat(y * y, edges[:-1], axis=1)
    mean = total / length
    centred = np.sqrt(np.maximum(square - total * mean, 0.0))
    return np.concatenate([mean * np.sqrt(length), centred], axis=1)


class Search:
    """Running top k of a block of queries against rows that come in pieces."""

    def __init__(self, ids: np.ndarray, vectors: np.ndarray, k: int):
        self.ids, self.vectors, self.k = ids, vectors, k
        self.score: list[np.ndarray] = [np.zeros(0, np.int64)] * len(ids)
        self.found: list[np.ndarray] = [np.zeros(0, np.int64)] * len(ids)
        self.least = np.full(len(ids), -np.inf)
        self.stats: dict[int, list[np.ndarray]] = {}
        self.products = 0

    def add(self, ids: np.ndarray, rows: np.ndarray) -> None:
        d = max(rows.shape[1], self.vectors.shape[1])
        rows = np.pad(rows, ((0, 0), (0, d - rows.shape[1])))
        if self.vectors.shape[1] < d:
            self.vectors = np.pad(self.vectors, ((0, 0), (0, d - self.vectors.shape[1])))
        if d not in self.stats:
            self.stats = {d: [segment_stats(self.vectors, p) for p in LEVELS]}
        levels = [segment_stats(rows, p) for p in LEVELS]
        mine = self.stats[d]
        # Rounding of the bounds in double precision is far below this slack.
        slack = 1.0 + 1e-9 * np.abs(mine[0]).max(initial=0) * np.abs(levels[0]).max(initial=0) * d
        # Scores are held to the 64-bit range, so no bound is below it.
        coarse = np.maximum(mine[0] @ levels[0].T + slack, -(2.0**63))
        # Components past 2**20 or so could overflow 64-bit products: exact Python integers then.
        top = [max(int(x.max(initial=0)), -int(x.min(initial=0))) for x in (rows, self.vectors)]
        exact = top[0] * top[1] * d < 2**62
        for q in range(len(self.ids)):
            order = np.argsort(-coarse[q], kind="stable")
            for lo in range(0, len(order), 512):
                part = order[lo : lo + 512]
                part = part[(coarse[q, part] >= self.least[q]) & (ids[part] != self.ids[q])]
                if coarse[q, order[lo]] < self.least[q]:
                    break
                for a, b in zip(mine[1:], levels[1:]):
                    if len(part) and np.isfinite(self.least[q]):
                        part = part[np.maximum(b[part] @ a[q] + slack, -(2.0**63)) >= self.least[q]]
                if len(part):
                    self.keep(q, ids[part], rows[part], exact)

    def keep(self, q: int, ids: np.ndarray, rows: np.ndarray, exact: bool) -> None:
        if exact:
            got = rows @ self.vectors[q]
        else:
            own = self.vectors[q].tolist()
            sums = (sum(a * b for a, b in zip(r, own)) for r in rows.tolist())
            got = np.array([max(-MOST - 1, min(MOST, x)) for x in sums], dtype=np.int64)
        self.products += len(ids)
        score = np.concatenate([self.score[q], got])
        found = np.concatenate([self.found[q], ids])
        best = np.lexsort((found, ~score))[: self.k]  # ~ turns the order around without overflow
        self.score[q], self.found[q] = score[best], found[best]
        if len(best) == self.k:
            self.least[q] = float(self.score[q][-1])


def top_k(
    df: DataFrame,
    query_filter,
    k: int = 10,
    scale: int = 1024,
    id_col: str = "vec_id",
    vec_col: str = "embedding",
    query_block: int = 2048,
    row_block: int = 16384,
) -> DataFrame:
    """query_id, rank (from 1), vec_id, score: each query's `k` highest integer inner products.

    `query_filter` is a Column over vec_id that names the stated query set.
    """
    rows = quantised(df, scale, id_col, vec_col)
    n_queries, n_rows = (
        df.select(F.col(id_col).cast("long").alias("vec_id"))
        .agg(F.count(F.when(query_filter, 1)), F.count("vec_id"))
        .first()
    )
    across = max(1, math.ceil(n_queries / query_block))
    down = max(1, math.ceil(n_rows / row_block))
    queries = (
        rows.where(query_filter)
        .dropDuplicates(["vec_id", "v"])
        .withColumn("qb", F.pmod(F.xxhash64("vec_id"), F.lit(across)).cast("int"))
        .withColumn("rb", F.explode(F.sequence(F.lit(0), F.lit(down - 1))))
    )
    spread = F.pmod(F.xxhash64("vec_id", F.monotonically_increasing_id() % 64), F.lit(down)).cast("int")
    candidates = rows.withColumn("rb", spread).withColumn("qb", F.explode(F.sequence(F.lit(0), F.lit(across - 1))))
    tiles = "qb", "rb"
    schema = pa.schema([("query_id", pa.int64()), ("vec_id", pa.int64()), ("score", pa.int64())])

    def meet(left, right):
        if left.num_rows == 0 or right.num_rows == 0:
            return schema.empty_table()
        search = Search(left.column("vec_id").to_numpy(), matrix(left.column("v")), k)
        ids, v = right.column("vec_id").to_numpy(), matrix(right.column("v"))
        for lo in range(0, len(ids), ROWS_AT_ONCE):
            search.add(ids[lo : lo + ROWS_AT_ONCE], v[lo : lo + ROWS_AT_ONCE])
        n = [len(x) for x in search.found]
        if not sum(n):
            return schema.empty_table()
        return pa.Table.from_arrays(
            [
                pa.array(np.repeat(search.ids, n)),
                pa.array(np.concatenate(search.found)),
                pa.array(np.concatenate(search.score)),
            ],
            schema=schema,
        )

    met = (
        queries.groupBy(*tiles)
        .cogroup(candidates.groupBy(*tiles))
        .applyInArrow(meet, "query_id long, vec_id long, score long")
    )
    best = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return (
        met.withColumn("rank", F.row_number().over(best))
        .where(F.col("rank") <= k)
        .select("query_id", "rank", "vec_id", "score")
    )
