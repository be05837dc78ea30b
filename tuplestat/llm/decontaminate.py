"""Benchmark decontamination with DataFrame functions only.

Benchmark items become windows of `n` consecutive normalised words (a shorter item is one
window of its own length). Their hashes form a set that is broadcast after its size has been
checked. Documents are scanned once: each row hashes its word windows in place and looks the
hashes up in a byte table of the set (a binary literal, two slots per hash, so that it lets few
others pass and loses none); only windows that pass leave the row, with their words. An
equi-join on hash and words verifies them; a set beyond the bound takes the same join as a
shuffle, without the table. What is shuffled afterwards are hits and a short row per document,
never texts.

Words are maximal runs of digits, ASCII letters (A-Z lowered) and non-ASCII characters. Null
and wordless texts have no words, no hits, and an items digest of the empty string; items
without words are no windows; items with a null id make hits but are not listed; repeated rows
each give a row; empty tables give an empty result or no hits. Only id and text columns of
either table are read.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: What separates words, and the letters that are lowered.
SEPARATORS = r"[\x00-\x2F\x3A-\x60\x7B-\x7F]+"
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"

#: Windows of the benchmark up to which their set is broadcast (about 100 bytes each).
MOST_WINDOWS = 500_000


def words_of(text: Column) -> Column:
    """Array of normalised words. ASCII texts (as many bytes as characters) take a faster way
    to the same lower case."""
    text = F.coalesce(text.cast("string"), F.lit(""))
    lowered = F.when(F.octet_length(text) == F.char_length(text), F.lower(text)).otherwise(
        F.translate(text, UPPER, LOWER)
    )
    return F.filter(F.split(lowered, SEPARATORS), lambda w: w != F.lit(""))


def item_windows(items: DataFrame, n: int, id_col: str = "item_id", text_col: str = "text") -> DataFrame:
    """h, size, words, items: each distinct window of the benchmark and the items that have it."""
    w = items.select(F.col(id_col).cast("string").alias("item"), words_of(F.col(text_col)).alias("w"))
    sized = w.where(F.size("w") > 0).withColumn("size", F.least(F.size("w"), F.lit(n)))
    return (
        sized.withColumn("at", F.explode(F.expr("sequence(1, size(w) - size + 1)")))
        .select("item", "size", F.slice("w", F.col("at"), F.col("size")).alias("w"))
        .groupBy("size", F.xxhash64("w").alias("h"), F.array_join("w", " ").alias("words"))
        .agg(F.collect_set("item").alias("items"))
    )


def slots(h: Column, size: int) -> tuple[Column, Column]:
    """Two places of a hash in a table of `size` (a power of two) bytes, from 1."""
    bits = size.bit_length() - 1
    first = h.bitwiseAND(F.lit(size - 1)).cast("int") + 1
    second = F.shiftrightunsigned(h, 64 - bits).cast("int") + 1
    return first, second


def byte_table(grams: DataFrame, total: int) -> bytes:
    """One byte a slot, set where a window's hash has a slot; at least 32 slots a window up to
    four million. Only distinct slots come to the driver, at most two for each window."""
    size = 1 << min(22, max(16, (32 * total - 1).bit_length()))
    first, second = slots(F.col("h"), size)
    rows = grams.select(F.explode(F.array(first, second)).alias("slot")).distinct().collect()
    table = bytearray(size)
    for r in rows:
        table[r.slot - 1] = 1
    return bytes(table)


def window_hits(
    docs: DataFrame,
    items: DataFrame,
    n: int = 10,
    id_col: str = "doc_id",
    text_col: str = "text",
    item_id_col: str = "item_id",
    item_text_col: str = "text",
) -> DataFrame:
    """row, doc_id, text_hash, n_words, at, size, items: one row for each verified occurrence of
    a window in a row of `docs` (`at` from 1), and one with null `at` for each candidate that
    failed and for each row without any."""
    grams = item_windows(items, n, item_id_col, item_text_col)
    sizes = sorted(r.size for r in grams.select("size").distinct().collect())  # n values at most
    total = grams.count()
    small = total <= MOST_WINDOWS
    table = F.lit(bytearray(byte_table(grams, total))) if small and sizes else None
    size_of_table = 1 << min(22, max(16, (32 * total - 1).bit_length())) if sizes else 0

    def passing(size: int) -> Column:
        at_hash = F.transform(
            F.expr(f"sequence(1, size(w) - {size - 1})"),
            lambda at: F.struct(at.alias("at"), F.lit(size).alias("size"), F.xxhash64(F.slice("w", at, size)).alias("h")),
        )
        if table is not None:

            def known(x):
                first, second = slots(x["h"], size_of_table)
                one = F.lit(bytearray(b"\x01"))
                return (F.substring(table, first, F.lit(1)) == one) & (F.substring(table, second, F.lit(1)) == one)

            at_hash = F.filter(at_hash, known)
        some = F.transform(
            at_hash,
            lambda x: F.struct(
                x["at"].alias("at"),
                x["size"].alias("size"),
                x["h"].alias("h"),
                F.array_join(F.slice("w", x["at"], x["size"]), " ").alias("words"),
            ),
        )
        return F.when(F.size("w") >= size, some)

    none = F.lit(None).cast("array<struct<at:int,size:int,h:bigint,words:string>>")
    every = [F.coalesce(passing(s), F.array().cast("array<struct<at:int,size:int,h:bigint,words:string>>")) for s in sizes]
    found = every[0] if len(every) == 1 else F.concat(*every) if every else none
    rows = docs.select(
        F.monotonically_increasing_id().alias("row"),
        F.col(id_col).cast("long").alias("doc_id"),
        F.xxhash64(F.col(text_col).cast("string")).alias("text_hash"),
        words_of(F.col(text_col)).alias("w"),
    ).select("row", "doc_id", "text_hash", F.size("w").cast("long").alias("n_words"), found.alias("found"))
    flat = rows.select("row", "doc_id", "text_hash", "n_words", F.explode_outer("found").alias("x")).select(
        "row", "doc_id", "text_hash", "n_words", "x.at", "x.size", "x.h", "x.words"
    )
    side = F.broadcast(grams) if small else grams
    return flat.join(side, ["h", "size", "words"], "left").select(
        "row",
        "doc_id",
        "text_hash",
        "n_words",
        F.when(F.col("items").isNotNull(), F.col("at")).alias("at"),
        "size",
        "items",
    )


def covered(spans: Column) -> Column:
    """Places that the union of (at, size) spans covers; spans overlap at will."""
    step = F.aggregate(
        F.array_sort(spans),
        F.struct(F.lit(0).cast("long").alias("end"), F.lit(0).cast("long").alias("n")),
        lambda acc, x: F.struct(
            F.greatest(acc["end"], x["at"] + x["size"] - F.lit(1).cast("long")).alias("end"),
            (
                acc["n"]
                + F.greatest(
                    F.lit(0).cast("long"),
                    x["at"] + x["size"] - F.lit(1).cast("long") - F.greatest(acc["end"], x["at"] - F.lit(1).cast("long")),
                )
            ).alias("n"),
        ),
    )
    return step["n"]


def decontaminate(docs: DataFrame, items: DataFrame, n: int = 10, **columns) -> DataFrame:
    """doc_id, text_hash, n_words, n_hit, n_items, items_sha256, contaminated, spans (array of
    at, size in words) of every row of `docs`."""
    hits = window_hits(docs, items, n, **columns)
    span = F.when(F.col("at").isNotNull(), F.struct("at", "size"))
    grouped = hits.groupBy("row", "doc_id", "text_hash").agg(
        F.max("n_words").alias("n_words"),
        F.collect_set(span).alias("spans"),
        F.array_sort(F.array_distinct(F.flatten(F.collect_set("items")))).alias("ids"),
    )
    return grouped.select(
        "doc_id",
        "text_hash",
        "n_words",
        covered(F.col("spans")).alias("n_hit"),
        F.size("ids").cast("long").alias("n_items"),
        F.sha2(F.array_join("ids", ","), 256).alias("items_sha256"),
        (F.size("spans") > 0).alias("contaminated"),
        "spans",
    )


def drop_contaminated(docs: DataFrame, items: DataFrame, n: int = 10, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The rows of `docs`, all their columns, whose text holds no window of the benchmark."""
    hits = window_hits(docs, items, n, id_col, text_col).where(F.col("at").isNotNull())
    bad = hits.select(F.col("doc_id").alias("_bad_id"), F.col("text_hash").alias("_bad_hash")).distinct()
    same = docs[id_col].cast("long").eqNullSafe(bad["_bad_id"]) & (
        F.xxhash64(docs[text_col].cast("string")) == bad["_bad_hash"]
    )
    return docs.join(bad, same, "left_anti")
