"""Column functions: vectors, document features, dates, JSON, combinatorics."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda p, q: p.cast("double") * q.cast("double")), F.lit(0.0), lambda s, v: s + v)


def norm2(a: Column) -> Column:
    return F.sqrt(dot(a, a))


def axpy(alpha: float, a: Column, b: Column) -> Column:
    return F.zip_with(a, b, lambda p, q: F.lit(float(alpha)) * p.cast("double") + q.cast("double"))


def binomial(n: Column, d: int) -> Column:
    """Exact for d up to 4, as decimal(38,0)."""
    if not 0 <= d <= 4:
        raise ValueError("d is at most four")
    out = F.lit(1).cast("decimal(38,0)")
    for k in range(d):
        out = (out * (n - k).cast("decimal(18,0)")).cast("decimal(38,0)")
        out = F.floor(out / F.lit(k + 1)).cast("decimal(38,0)")
    return out


def whole_type(largest: int | None) -> str:
    """Type of a column of whole numbers up to `largest`: long, or decimal(38,0) beyond 64 bits."""
    return "long" if (largest or 0) < 1 << 63 else "decimal(38,0)"


def doc_features(text: Column) -> Column:
    """Nine numbers of a text: log length, share of distinct words, of marks, of digits, mean word
    length, log lines, share of capitals, log of the longest word, share of repeated lines."""
    t = F.coalesce(text, F.lit(""))
    words = F.filter(F.split(t, r"\s+"), lambda w: w != "")
    lines = F.split(t, "\n")
    n = F.greatest(F.char_length(t), F.lit(1)).cast("double")
    k = F.greatest(F.size(words), F.lit(1)).cast("double")
    longest = F.aggregate(words, F.lit(0), lambda s, w: F.greatest(s, F.char_length(w)))
    total = F.aggregate(words, F.lit(0), lambda s, w: s + F.char_length(w))
    return F.array(
        F.log1p(F.char_length(t).cast("double")),
        F.size(F.array_distinct(words)) / k,
        F.char_length(F.regexp_replace(t, r"[^!-/:-@\[-`{-~]", "")) / n,
        F.char_length(F.regexp_replace(t, "[^0-9]", "")) / n,
        total / k,
        F.log1p(F.size(lines).cast("double")),
        F.char_length(F.regexp_replace(t, "[^A-Z]", "")) / n,
        F.log1p(longest.cast("double")),
        F.lit(1.0) - F.size(F.array_distinct(lines)) / F.size(lines),
    )


def json_number(col: Column, path: str) -> Column:
    return F.get_json_object(col, path).cast("double")


def metrics_map(pairs: dict[str, Column]) -> Column:
    return F.map_from_entries(F.array(*[F.struct(F.lit(k).alias("key"), v.cast("double").alias("value")) for k, v in pairs.items()]))


def day_gap(a: Column, b: Column) -> Column:
    return F.datediff(a, b)
