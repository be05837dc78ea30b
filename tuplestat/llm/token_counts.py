"""Token counts without token ids: pieces are counted once per distinct pre-token of the corpus.

A text, with the model's leading space marker in front, is cut where no piece of the vocabulary
can reach across: before a run of spaces, and on both sides of a line feed (which only byte
fallback covers). Merges never cross such a cut, so a text's count is the sum over its
pre-tokens of frequency times pieces. `check_cuts` proves the two conditions on the vocabulary
and the operator refuses a model that breaks them.

1. A scan collects the distinct pre-tokens with their uses; the pieces of each are counted once and
   written as a table.
2. A second scan has each text's pre-token frequencies. The most used pre-tokens (`common` rows at
   most, of at most COMMON_BYTES bytes each, so a bounded broadcast) are joined and summed in place; the
   frequencies of all others leave the scan, are joined with the table and summed by row.

A very common pre-token is thus never shuffled, and a rare one only meets its own uses. Token ids
are never kept. Nulls count as empty texts; empty texts have no tokens; null ids are kept; repeated
rows each give a row; long texts are cut like others; an empty table gives an empty result. Only
the id and text columns are read.
"""

from __future__ import annotations

import re

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import sentencepiece
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .shared import batch_of, discard, held, id_text, slices, staged

MARK = "▁"
PRE_TOKEN = re.compile(f"\n|[ {MARK}]+[^ {MARK}\n]*|[^ {MARK}\n]+")
COMMON, COMMON_BYTES = 250_000, 32


def check_cuts(pieces: list[str]) -> None:
    """Raise unless no piece has a space marker behind another character, or a line feed."""
    for p in pieces:
        if MARK in p.lstrip(MARK) or "\n" in p:
            raise ValueError(f"piece {p!r} reaches across a pre-token cut")


def pre_tokens(texts: pa.Array) -> tuple[pa.Array, np.ndarray]:
    """(pre-tokens of all texts end to end, number of them in each text).

    A pre-token is named without its leading space; one that begins with a line feed is that feed
    and the unmarked pre-token behind it, if any. Texts with single spaces only are cut by Arrow,
    the others (runs of spaces, markers) one by one."""
    texts = texts.fill_null("")
    odd = pc.or_(pc.match_substring(texts, "  "), pc.or_(pc.match_substring(texts, MARK), pc.starts_with(texts, " ")))
    lists = pc.split_pattern(pc.replace_substring(pc.if_else(odd, "", texts), "\n", " \n"), " ")
    count = lists.value_lengths().to_numpy(zero_copy_only=False).astype(np.int64)
    flat = lists.flatten()
    empty = pc.equal(pc.binary_length(texts), 0).to_numpy(zero_copy_only=False)
    at = np.flatnonzero(odd.to_numpy(zero_copy_only=False))
    if not len(at) and not empty.any():
        return flat, count
    own = [cut_slowly(t) for t in texts.take(pa.array(at)).to_pylist()]
    # Odd texts' lists stand behind the others, and a gather puts all in order; the single empty
    # string that an empty or odd text fell into goes.
    start = np.concatenate([[0], np.cumsum(count)[:-1]]) if len(count) else count
    tail = len(flat)
    for i, x in zip(at.tolist(), own):
        start[i], count[i] = tail, len(x)
        tail += len(x)
    count[empty] = 0
    total = int(count.sum())
    first = np.concatenate([[0], np.cumsum(count)[:-1]]) if len(count) else count
    gather = np.arange(total) + np.repeat(start - first, count)
    both = pa.concat_arrays([flat, pa.array([k for x in own for k in x], pa.string())])
    return both.take(pa.array(gather)), count


def cut_slowly(text: str) -> list[str]:
    """Names of one text's pre-tokens, by the pattern; a marker in the text counts as a space."""
    out = []
    for k in PRE_TOKEN.findall(" " + text.replace(MARK, " ")):
        if k[0] == " ":
            out.append(k[1:])
        elif k == "\n":
            out.append(k)
        else:  # unmarked: it stands behind a line feed
            out[-1] += k
    return out


def count_pieces(names: list[str], model: sentencepiece.SentencePieceProcessor) -> np.ndarray:
    """Pieces of each named pre-token. The library puts its own marker in front: that is the
    pre-token's own space, or one too many before a line feed."""
    ids = model.encode(names, num_threads=1)
    return np.array([len(x) - 1 if k[:1] == "\n" else len(x) or 1 for k, x in zip(names, ids)], dtype=np.int64)


def distinct_pieces(docs: DataFrame, shipped, key: int) -> DataFrame:
    """name, uses, pieces: a row for each distinct pre-token of the texts."""
    used = pa.schema([("name", pa.string()), ("uses", pa.int64())])

    def scan(batches):
        for part in slices(batches, 4 << 20):
            counted = pc.value_counts(pre_tokens(part.column(1))[0])
            if len(counted):
                yield batch_of(used, counted.field(0), counted.field(1))

    whole = pa.schema([("name", pa.string()), ("uses", pa.int64()), ("pieces", pa.int64())])

    def count(batches):
        model = held(("pieces of", key), lambda: sentencepiece.SentencePieceProcessor(model_proto=shipped.value))
        for part in slices(batches, 1 << 20):
            yield batch_of(whole, part.column(0), part.column(1), count_pieces(part.column(0).to_pylist(), model))

    distinct = docs.mapInArrow(scan, "name string, uses long").groupBy("name").agg(F.sum("uses").alias("uses"))
    return distinct.mapInArrow(count, "name string, uses long, pieces long")


def frequencies(docs: DataFrame, common) -> DataFrame:
    """row, doc_id, n_bytes, n (tokens of common pre-tokens), rest (name and frequency of the others)."""
    rest = pa.list_(pa.struct([("name", pa.string()), ("times", pa.int32())]))
    schema = pa.schema([("row", pa.int64()), ("doc_id", pa.int64()), ("n_bytes", pa.int64()), ("n", pa.int64()), ("rest", rest)])

    def scan(batches):
        names, pieces = common.value
        for part in slices(batches, 4 << 20):
            n = part.num_rows
            flat, count = pre_tokens(part.column(2))
            coded = flat.dictionary_encode()
            code = coded.indices.to_numpy()
            place = pc.fill_null(pc.index_in(coded.dictionary, value_set=names), -1).to_numpy(zero_copy_only=False)
            owner = np.repeat(np.arange(n), count)
            known = place[code] >= 0
            total = np.bincount(owner[known], weights=pieces[place[code[known]]], minlength=n).astype(np.int64)
            pair, times = np.unique(owner[~known] * len(coded.dictionary) + code[~known], return_counts=True)
            row, name = np.divmod(pair, max(len(coded.dictionary), 1))
            offsets = np.searchsorted(row, np.arange(n + 1)).astype(np.int32)
            other = pa.StructArray.from_arrays([coded.dictionary.take(pa.array(name)), pa.array(times.astype(np.int32))], fields=list(rest.value_type))
            size = pc.binary_length(part.column(2).fill_null("")).cast(pa.int64())
            yield batch_of(schema, part.column(0), part.column(1), size, total, pa.ListArray.from_arrays(pa.array(offsets), other, type=rest))

    rows = docs.select(F.monotonically_increasing_id().alias("row"), "doc_id", "text")
    return rows.mapInArrow(scan, "row long, doc_id long, n_bytes long, n long, rest array<struct<name:string,times:int>>")


def token_counts(
    docs: DataFrame, model_path: str, limit: int = 4096, common: int = COMMON, id_col: str = "doc_id", text_col: str = "text"
) -> DataFrame:
    """doc_id, n_bytes, n_tokens, over_limit of every row of `docs` under a sentencepiece model."""
    context = docs.sparkSession.sparkContext
    with open(model_path, "rb") as f:
        proto = f.read()
    sp = sentencepiece.SentencePieceProcessor(model_proto=proto)
    check_cuts([sp.id_to_piece(i) for i in range(sp.get_piece_size())])
    docs = id_text(docs, id_col, text_col)
    table = staged(distinct_pieces(docs, context.broadcast(proto), hash(proto)), "pieces")
    # `common` rows of at most COMMON_BYTES and a number each, whatever the corpus.
    short = table.where(F.octet_length("name") <= COMMON_BYTES).withColumn("level", F.floor(8 * F.log2("uses")).cast("int"))
    levels = short.groupBy("level").agg(F.count("*").alias("n")).collect()  # eight levels for each power of two
    least, room = 1 << 30, common
    for r in sorted(levels, key=lambda r: -r.level):
        if r.n > room:
            break
        least, room = r.level, room - r.n
    top = short.where(F.col("level") >= least).select("name", "pieces").toArrow()
    names = pa.concat_arrays([pa.array([], pa.string()), *top.column(0).cast(pa.string()).chunks])
    shipped = context.broadcast((names, top.column(1).to_numpy()))
    rows = staged(frequencies(docs, shipped), "frequencies")
    others = rows.where(F.size("rest") > 0).select("row", F.explode("rest").alias("x")).select("row", "x.name", "x.times")
    more = others.join(table.select("name", "pieces"), "name").groupBy("row").agg(F.sum(F.col("times") * F.col("pieces")).alias("more"))
    more = staged(more, "counts")
    discard(table)
    n = F.col("n") + F.coalesce("more", F.lit(0))
    return rows.select("row", "doc_id", "n_bytes", "n").join(more, "row", "left").select(
        "doc_id", "n_bytes", n.alias("n_tokens"), (n > limit).alias("over_limit")
    )
