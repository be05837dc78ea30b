"""Synthetic samples as a Spark data source, drawn by keyed hashes.

`spark.read.format("tuplestat_synthetic").option("law", ...)`:
`hard_pairs` two samples of the discrete law whose informative pairs are rare (options n, m,
eps, seed); `gaussian` two normal samples `shift` apart; `linear` feature vectors with a planted
rule. Rows are cut into partitions by index, so any size is generated in parallel.
"""

from __future__ import annotations

import hashlib
import math
from collections.abc import Iterator

from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


def _u64(*parts) -> int:
    return int(hashlib.md5("|".join(map(str, parts)).encode()).hexdigest()[:15], 16)


def _unit(*parts) -> float:
    return (_u64(*parts) >> 30) / float(1 << 30)


class _Slice(InputPartition):
    def __init__(self, sample: int, lo: int, hi: int):
        self.sample, self.lo, self.hi = sample, lo, hi


class _Reader(DataSourceReader):
    def __init__(self, options):
        self.law = options.get("law", "hard_pairs")
        self.n, self.m = int(options.get("n", 1000)), int(options.get("m", 100))
        self.eps, self.seed = float(options.get("eps", 0.1)), int(options.get("seed", 7))
        self.shift, self.parts = float(options.get("shift", 1.0)), int(options.get("partitions", 4))

    def partitions(self):
        out = []
        for sample, size in ((0, self.n), (1, self.m)):
            step = max(1, math.ceil(size / self.parts))
            out += [_Slice(sample, lo, min(size, lo + step)) for lo in range(0, size, step)]
        return out or [_Slice(0, 0, 0)]

    def score(self, sample: int, i: int) -> float:
        u = _unit(self.seed, sample, i)
        if self.law == "hard_pairs":
            return (0.0 if u < self.eps else 2.0) if sample == 0 else (1.0 if u < self.eps else -1.0)
        if self.law == "gaussian":
            v = max(_unit(self.seed, sample, i, "b"), 2.0**-31)
            return math.sqrt(-2 * math.log(v)) * math.cos(2 * math.pi * u) + (self.shift if sample == 0 else 0.0)
        if self.law == "linear":
            return 2 * u - 1 + (self.shift if sample == 0 else 0.0)
        raise ValueError(f"unknown law {self.law}")

    def read(self, partition: _Slice) -> Iterator[tuple]:
        for i in range(partition.lo, partition.hi):
            yield partition.sample, i, f"{partition.sample}-{i}", self.score(partition.sample, i)


class SyntheticSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "tuplestat_synthetic"

    def schema(self) -> str:
        return "sample int, idx bigint, key string, score double"

    def reader(self, schema) -> DataSourceReader:
        return _Reader(self.options)


def register(spark) -> None:
    spark.dataSource.register(SyntheticSource)
