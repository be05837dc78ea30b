"""Kernels: functions of a tuple of rows, as Column builders with NumPy twins.

A kernel names how many samples it takes and how many rows of each (`degrees`), and builds its
value from one Column (score) per row, in sample order. Where a kernel has a form that needs no
pairs, `sorted_forms` holds it under the same name.
"""

from __future__ import annotations

import itertools
from collections.abc import Callable
from dataclasses import dataclass
from functools import reduce

import numpy as np
import pandas as pd
from pyspark.sql import Column
from pyspark.sql import functions as F
from pyspark.sql import types as T


@dataclass(frozen=True)
class Kernel:
    name: str
    degrees: tuple[int, ...]
    build: Callable[..., Column]
    numpy: Callable[..., np.ndarray] | None = None
    symmetric: bool = True

    @property
    def arity(self) -> int:
        return sum(self.degrees)

    def __call__(self, *cols: Column) -> Column:
        return self.build(*cols)

    def symmetrized(self) -> "Kernel":
        """Mean over the orders of the rows inside each block."""
        orders, at = [], 0
        for d in self.degrees:
            orders.append(list(itertools.permutations(range(at, at + d))))
            at += d
        picks = [sum(p, ()) for p in itertools.product(*orders)]

        def mean(*cols):
            return reduce(lambda a, b: a + b, (self.build(*[cols[i] for i in p]) for p in picks)) / F.lit(float(len(picks)))

        return Kernel(f"{self.name}_sym", self.degrees, mean)

    @classmethod
    def from_sql(cls, text: str, degrees: tuple[int, ...]) -> "Kernel":
        """From SQL text over x, z (two samples) or a, b, c (one): the columns of the tuple join
        have those names, so the text is bound by Spark's own resolution."""
        return cls(f"sql:{text}", degrees, lambda *_: F.expr(text).cast("double"))

    @classmethod
    def from_numpy(cls, function: Callable[..., np.ndarray], degrees: tuple[int, ...], name: str = "numpy") -> "Kernel":
        """From a vectorised function of arrays; runs as an Arrow-batched UDF over pairs."""

        def two(a: pd.Series, b: pd.Series) -> pd.Series:
            return pd.Series(np.asarray(function(a.to_numpy(), b.to_numpy()), dtype=float))

        def three(a: pd.Series, b: pd.Series, c: pd.Series) -> pd.Series:
            return pd.Series(np.asarray(function(a.to_numpy(), b.to_numpy(), c.to_numpy()), dtype=float))

        if sum(degrees) not in (2, 3):
            raise ValueError("kernels of two or three rows only")

        def build(*cols):
            return F.pandas_udf(two if len(cols) == 2 else three, T.DoubleType())(*cols)

        return cls(name, degrees, build, function)


def _double(c: Column) -> Column:
    return c.cast("double")


def auc(ties: str = "strict") -> Kernel:
    """1 where the first sample's score is above the second's; ties count 0, or a half."""

    def build(x, z):
        win = F.when(z < x, 1.0)
        return (win.when(z == x, 0.5) if ties == "half" else win).otherwise(0.0)

    return Kernel(f"auc_{ties}", (1, 1), build, lambda x, z: (z < x) + (0.5 * (z == x) if ties == "half" else 0.0))


def chain(k: int) -> Kernel:
    """1 where k rows, one of each class in order, have strictly rising scores."""

    def build(*s):
        return F.when(reduce(lambda a, b: a & b, (a < b for a, b in zip(s, s[1:]))), 1.0).otherwise(0.0)

    def numpy(*s):
        return np.logical_and.reduce([a < b for a, b in zip(s, s[1:])]).astype(float)

    return Kernel(f"chain{k}", (1,) * k, build, numpy)


SQDIFF = Kernel("sqdiff", (2,), lambda a, b: (a - b) * (a - b), lambda a, b: (a - b) ** 2)
HALF_SQDIFF = Kernel("half_sqdiff", (2,), lambda a, b: (a - b) * (a - b) / 2, lambda a, b: (a - b) ** 2 / 2)
ABSDIFF = Kernel("absdiff", (2,), lambda a, b: F.abs(a - b), lambda a, b: np.abs(a - b))
PRODUCT = Kernel("product", (1, 1), lambda x, z: x * z, lambda x, z: x * z)


def concordance(ax: Column, ay: Column, bx: Column, by: Column) -> Column:
    """1 where two points are ordered alike in both coordinates."""
    return F.when((ax - bx) * (ay - by) > 0, 1.0).otherwise(0.0)


def hinge_rank(margin: float = 1.0) -> Kernel:
    """Loss of a pair whose first row (the lower class) doesn't score `margin` below the second."""
    return Kernel(
        "hinge_rank", (1, 1), lambda x, z: F.greatest(F.lit(0.0), F.lit(margin) + x - z), lambda x, z: np.maximum(0.0, margin + x - z)
    )


def logistic_rank() -> Kernel:
    """A smooth convex stand-in: log(1 + exp(first - second)), stable for large differences."""

    def build(x, z):
        d = x - z
        return F.greatest(d, F.lit(0.0)) + F.log1p(F.exp(-F.abs(d)))

    return Kernel("logistic_rank", (1, 1), build, lambda x, z: np.logaddexp(0, x - z))


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda p, q: _double(p) * _double(q)), F.lit(0.0), lambda s, v: s + v)


def squared_distance(a: Column, b: Column) -> Column:
    gap = F.zip_with(a, b, lambda p, q: (_double(p) - _double(q)) * (_double(p) - _double(q)))
    return F.aggregate(gap, F.lit(0.0), lambda s, v: s + v)


def within_cluster(a: Column, b: Column, ca: Column, cb: Column) -> Column:
    """Dissimilarity of a pair in one cluster, 0 across clusters."""
    return F.when(ca == cb, squared_distance(a, b)).otherwise(0.0)


def metric_pair(a: Column, b: Column, la: Column, lb: Column, weights: list[float] | None = None, margin: float = 1.0) -> Column:
    """Hinge of a diagonal distance: pairs of one label should be closer than `margin`, others
    farther; weights default to one."""
    if weights is None:
        d = squared_distance(a, b)
    else:
        w = F.array(*[F.lit(float(x)) for x in weights])
        gap = F.zip_with(F.zip_with(a, b, lambda p, q: (_double(p) - _double(q)) * (_double(p) - _double(q))), w, lambda g, x: g * x)
        d = F.aggregate(gap, F.lit(0.0), lambda s, v: s + v)
    sign = F.when(la == lb, 1.0).otherwise(-1.0)
    return F.greatest(F.lit(0.0), F.lit(1.0) + sign * (d - F.lit(margin)))
