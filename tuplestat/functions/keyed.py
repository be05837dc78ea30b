"""Randomness as a pure function of keys, so that retries and other plans see the same draws.

`keyed_u64` is the first 60 bits of an md5 of the joined parts; any SQL engine can repeat it.
`fast_u64` is xxhash64 for paths that no other engine has to follow. `permute` is a keyed
bijection of 0..n-1 (the swap-or-not construction) that needs neither a sort nor a window: each
layer pairs x with k - x modulo n and a hash of the larger one decides whether they swap.
"""

from __future__ import annotations

import hashlib
import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def _digest(*parts) -> Column:
    cols = [p if isinstance(p, Column) else F.lit(str(p)) for p in parts]
    return F.md5(F.concat_ws("|", *[c.cast("string") for c in cols]))


def keyed_u64(*parts) -> Column:
    """60 bits from parts (integers, strings or columns of such), joined by a bar."""
    return F.conv(F.substring(_digest(*parts), 1, 15), 16, 10).cast("long")


def keyed_odd(*parts) -> Column:
    """Whether keyed_u64 of the parts is odd, read off its last digit."""
    return F.substring(_digest(*parts), 15, 1).isin(*"13579bdf")


def keyed_int(*parts) -> int:
    """The same number on the driver."""
    return int(hashlib.md5("|".join(map(str, parts)).encode()).hexdigest()[:15], 16)


def keyed_uniform(*parts) -> Column:
    """In [0, 1), from keyed_u64 (a multiple of 2**-30, exact in a double)."""
    return F.shiftright(keyed_u64(*parts), 30) / F.lit(float(1 << 30))


def fast_u64(*cols: Column) -> Column:
    return F.shiftrightunsigned(F.xxhash64(*cols), 1)


def layers(n: int) -> int:
    return max(24, 2 * math.ceil(math.log2(max(n, 2))))


def layer_keys(n: int, seed: int, rounds: range, sample: int) -> Column:
    """k of every round and layer under md5, worked out once on the driver: they depend on no row."""
    numbers = [[keyed_int(seed, r, sample, j) % max(n, 1) for j in range(1, layers(n) + 1)] for r in rounds]
    return F.array(*[F.array(*[F.lit(k).cast("long") for k in row]) for row in numbers])


def _layer(n: int, seed: int, rnd: Column, sample: int, hashed: str, keys: Column | None = None):
    """One layer: x meets its partner k - x modulo n, and a hash of the larger one decides on a swap.
    The layer undoes itself. Under "md5" any SQL engine can repeat it; "xxhash64" is faster. `keys`:
    the round's k of each layer, if known."""

    def h(shift: int, *parts: Column) -> Column:
        if hashed == "md5":
            return keyed_u64(seed + shift, rnd, sample, *parts)
        return F.xxhash64(F.lit(seed + shift), rnd, F.lit(sample), *parts)

    def layer(x, j):
        k = F.pmod(h(0, j), F.lit(n)) if keys is None else F.element_at(keys, j)
        partner = F.pmod(k + F.lit(n) - x, F.lit(n))
        top = F.greatest(x, partner)
        swap = keyed_odd(seed + 1, rnd, sample, j, top) if hashed == "md5" else h(1, j, top).bitwiseAND(F.lit(1)) == 1
        return F.when(swap, partner).otherwise(x)

    return layer


def permute(
    idx: Column, n: int, seed: int, rnd: Column | int, sample: int, hashed: str = "xxhash64", keys: Column | None = None
) -> Column:
    """Place of `idx` under the keyed permutation of 0..n-1 for (seed, rnd, sample)."""
    rnd = rnd if isinstance(rnd, Column) else F.lit(rnd)
    return F.aggregate(F.sequence(F.lit(1), F.lit(layers(n))), idx.cast("long"), _layer(n, seed, rnd, sample, hashed, keys))


def unpermute(place: Column, n: int, seed: int, rnd: Column | int, sample: int, hashed: str = "xxhash64") -> Column:
    """Inverse of `permute`: every layer undoes itself, so the layers run backwards."""
    rnd = rnd if isinstance(rnd, Column) else F.lit(rnd)
    keys = F.sequence(F.lit(layers(n)), F.lit(1), F.lit(-1))
    return F.aggregate(keys, place.cast("long"), _layer(n, seed, rnd, sample, hashed))


def sample_fraction(df: DataFrame, key: Column, fraction: float, seed: int) -> DataFrame:
    """Bernoulli sample by key: the same rows whatever the plan."""
    return df.where(keyed_u64(seed, "bernoulli", key) < F.lit(int(fraction * (1 << 60))))


def sample_rows(df: DataFrame, key: Column, n: int, seed: int) -> DataFrame:
    """`n` rows without replacement: the least keyed hashes (ties by key); a distributed top-n."""
    return df.orderBy(keyed_u64(seed, "rows", key), key).limit(n)
