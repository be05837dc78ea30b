"""Token ids of a corpus in Simple-8b blocks, in ascending document order, and back.

Writing: rows are range-partitioned and sorted by (doc_id, text hash) on the JVM side; each
task encodes its stretch with the tokenizers library and closes a block when it holds
`block_ids` ids or more (a document never spans two blocks). A Parquet row carries one block:
its shard, number, first id within the shard, document ids and payload, so that any store that
Spark writes to will do. Reading decodes blocks independently; the ids before a document are
the totals of earlier shards (one row per shard) plus its place within its own.

A tokenizer that drops white space and never joins across it (`cuts_at_space` proves this on its
settings) encodes a text chunk by chunk through a bounded table of chunks already seen; the table
holds what the library returned for a chunk. Any other tokenizer encodes whole texts; truncation and
padding in its file are switched off. A block closes at the first document that fills it.

Nulls are empty texts (only the end id is written); a null doc_id sorts first; repeated rows
are written each; an empty table gives no blocks. Only the id and text columns are read.
"""

from __future__ import annotations

import json
import os
import re
import zlib
from itertools import compress

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .id_table import IdTable, flat_ids
from .shared import batch_of, bounded_batches, held, id_text, slices, text_bytes
from .simple8b import pack_block, unpack_block

BLOCKS = "shard int, block int, first long, n_ids long, doc_ids array<long>, payload binary"
TABLE_BYTES = 192 << 20
SLICE_BYTES = 8 << 20


class ChunkIds(IdTable):
    """Chunks of texts between white space; joined texts fall apart at word-end pieces."""

    def __init__(self, tokenizer, most_bytes: int = TABLE_BYTES):
        super().__init__(most_bytes)
        self.encode = getattr(tokenizer, "encode_batch_fast", tokenizer.encode_batch)
        vocab = tokenizer.get_vocab(with_added_tokens=True)
        suffix = getattr(tokenizer.model, "end_of_word_suffix", None)
        self.ends = np.zeros(max(vocab.values(), default=0) + 1, dtype=bool)
        if suffix:
            for piece, k in vocab.items():
                self.ends[k] = piece.endswith(suffix)
        self.joins = bool(suffix)
        added = getattr(tokenizer, "get_added_tokens_decoder", dict)()
        self.special = tuple(t.content.lower() for t in added.values())

    def lists(self, chunks: list[str]) -> list[list[int]]:
        return [e.ids for e in self.encode(chunks, add_special_tokens=False)]

    def made(self, new: list[str]):
        """Plain chunks (one run of small letters, one mark behind it at most) are encoded in long
        joined texts, the others one by one."""
        lengths = np.zeros(len(new), dtype=np.int64)
        runs = np.array([self.joins and (PLAIN(c) is not None) * (2 if c[-1:] in MARKS else 1) for c in new], dtype=np.int64)
        plain = runs > 0
        words = list(compress(new, plain.tolist()))
        others = list(compress(new, (~plain).tolist()))
        ids = flat_ids(self.lists([" ".join(words[i : i + 500]) for i in range(0, len(words), 500)]))
        ends = np.flatnonzero(self.ends[ids])
        upto = np.cumsum(runs[plain])
        if len(ends) == (upto[-1] if len(upto) else 0):
            last = ends[upto - 1]
        else:  # a vocabulary that doesn't mark the ends of runs this way
            lists = self.lists(words)
            ids, last = flat_ids(lists), np.cumsum([len(x) for x in lists], dtype=np.int64) - 1
        lengths[plain] = np.diff(last, prepend=-1)
        rest = self.lists(others)
        lengths[~plain] = [len(x) for x in rest]
        flat = np.zeros(int(lengths.sum()), dtype=np.uint32)
        mine = np.repeat(plain, lengths)
        flat[mine], flat[~mine] = ids, flat_ids(rest)
        return flat, lengths, np.zeros(len(new), dtype=np.int8)


#: Runs of small letters that neither the normaliser nor the pre-tokenizer changes or cuts, and
#: marks that are a run of their own behind them.
MARKS = ".,;:!?"
PLAIN = re.compile(f"[a-z\xe0-\xf6\xf8-\xfe]+[{MARKS}]?").fullmatch


def chunks_of(texts: pa.Array, special: tuple[str, ...] = ()) -> pa.ListArray:
    """Pieces of each text between spaces and line feeds; nulls are empty texts.

    A-Z is lowered first in rows of Latin-1 characters (no UTF-8 byte from 0xC4 on), where the
    normaliser lowers each letter by itself to the same letter. A row that then holds a special
    string stays as it is, since those are matched before lowering.
    """
    texts = texts.fill_null("")
    raw, offsets = text_bytes(texts)
    wide = np.concatenate([[0], np.cumsum(raw >= 0xC4, dtype=np.int64)])
    low = pc.ascii_lower(texts)
    lower = pa.array(wide[offsets[1:]] == wide[offsets[:-1]])
    for s in special:
        lower = pc.and_not(lower, pc.match_substring(low, s))
    return pc.split_pattern(pc.replace_substring(pc.if_else(lower, low, texts), "\n", " "), " ")


#: Settings of a tokenizer file under which spaces and line feeds only separate. The pattern's
#: branches match no white space but runs of it, and what it doesn't match is removed.
SPACE_NORMALISERS = (
    {"type": "NFC"},
    {"type": "Replace", "pattern": {"Regex": r"\s+"}, "content": " "},
    {"type": "Lowercase"},
)
NO_SPACE_PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"


def cuts_at_space(source: str) -> bool:
    """Whether a tokenizer file is known to give each stretch between spaces or line feeds the ids that
    it has inside any text, with A-Z lowered: the settings of the word-level file, and added tokens
    that hold no white space, do not strip it and are matched as they stand."""
    j = json.loads(source)
    steps = (j.get("pre_tokenizer") or {}).get("pretokenizers") or [{}]
    split, rest = steps[0], steps[1:]
    return (
        (j.get("normalizer") or {}).get("type") == "Sequence"
        and tuple(j["normalizer"]["normalizers"]) == SPACE_NORMALISERS
        and (split.get("type"), split.get("pattern"), split.get("behavior"), split.get("invert"))
        == ("Split", {"Regex": NO_SPACE_PATTERN}, "Removed", True)
        and len(rest) == 1
        and (rest[0].get("type"), rest[0].get("add_prefix_space"), rest[0].get("use_regex")) == ("ByteLevel", False, False)
        and j["model"].get("type") == "BPE"
        and not j["model"].get("dropout")
        and not any(
            t["single_word"] or t["lstrip"] or t["rstrip"] or t["normalized"] or any(c.isspace() for c in t["content"])
            for t in j.get("added_tokens", ())
        )
    )


class WholeTexts:
    """Texts to ids without cuts."""

    def __init__(self, tokenizer):
        tokenizer.no_truncation()
        tokenizer.no_padding()
        self.encode = getattr(tokenizer, "encode_batch_fast", tokenizer.encode_batch)

    def encoded(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        lists = [e.ids for e in self.encode([t or "" for t in texts.to_pylist()], add_special_tokens=False)]
        return flat_ids(lists), np.array([len(x) for x in lists], dtype=np.int64)


def coder(source: str):
    """What encodes texts under a tokenizer file."""
    from tokenizers import Tokenizer

    tokenizer = Tokenizer.from_str(source)
    if not cuts_at_space(source):
        return WholeTexts(tokenizer)
    tokenizer.no_truncation()
    tokenizer.no_padding()
    return ChunkIds(tokenizer)


def encode_texts(texts: pa.Array, table: ChunkIds | WholeTexts, end: int | None) -> tuple[np.ndarray, np.ndarray]:
    """(ids of all texts end to end, number of ids of each); `end` goes behind every text."""
    if isinstance(table, WholeTexts):
        ids, per_text = table.encoded(texts)
    else:
        ids, per_text, _ = table.encoded_column(chunks_of(texts, table.special))
    if end is not None:
        ids = np.insert(ids, np.cumsum(per_text), np.uint32(end))
        per_text = per_text + 1
    return ids, per_text


def write_tokens(
    docs: DataFrame,
    path: str,
    tokenizer_path: str,
    end_id: int = 1,
    block_ids: int = 1 << 16,
    id_col: str = "doc_id",
    text_col: str = "text",
) -> None:
    """Encode every row of `docs` and write the blocks under `path` (must not exist)."""
    spark = docs.sparkSession
    with open(tokenizer_path, encoding="utf-8") as f:
        source = f.read()
    shipped = spark.sparkContext.broadcast(source)
    key = hash(source)

    def run(batches):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        table = held(("store", key), lambda: coder(shipped.value))
        schema = pa.schema(
            [
                ("shard", pa.int32()),
                ("block", pa.int32()),
                ("first", pa.int64()),
                ("n_ids", pa.int64()),
                ("doc_ids", pa.list_(pa.int64())),
                ("payload", pa.binary()),
            ]
        )
        shard, block, first = TaskContext.get().partitionId(), 0, 0
        coded: list[np.ndarray] = []
        sizes: list[int] = []
        names: list[int | None] = []

        def close():
            nonlocal block, first, coded, sizes, names
            ids = np.concatenate(coded)
            payload = pack_block(np.array(sizes, dtype=np.uint64), ids)
            out = batch_of(schema, [shard], [block], [first], [len(ids)], [names], [payload])
            block, first, coded, sizes, names = block + 1, first + len(ids), [], [], []
            return out

        for part in slices(batches, SLICE_BYTES):
            ids, lengths = encode_texts(part.column(1), table, end_id)
            at = size = 0
            for name, n in zip(part.column(0).to_pylist(), lengths.tolist()):
                names.append(name)
                sizes.append(n)
                size += n
                if size >= block_ids:
                    coded.append(ids[at : at + size])
                    at, size = at + size, 0
                    yield close()
            if size:
                coded.append(ids[at : at + size])
        if names:
            yield close()

    rows = id_text(docs, id_col, text_col)
    bounded_batches(spark, SLICE_BYTES)  # larger slices have fewer distinct chunks for their size
    rows = rows.withColumn("tie", F.xxhash64("text"))
    ordered = rows.repartitionByRange("doc_id", "tie").sortWithinPartitions("doc_id", "tie")
    ordered.select("doc_id", "text").mapInArrow(run, BLOCKS).write.parquet(path)


def read_tokens(spark: SparkSession, path: str) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32 of every document in the blocks under `path`.

    The shards' totals come to the driver (one small row for each partition that was written)
    and return as a broadcast table of that size.
    """
    blocks = spark.read.schema(BLOCKS).parquet(path)
    totals = sorted((r.shard, r.n) for r in blocks.groupBy("shard").agg(F.sum("n_ids").alias("n")).collect())
    before, offsets = 0, []
    for shard, n in totals:
        offsets.append((shard, before))
        before += n
    starts = spark.createDataFrame(offsets, "shard int, before long")

    def run(batches):
        schema = pa.schema(
            [
                ("shard", pa.int32()),
                ("doc_id", pa.int64()),
                ("local", pa.int64()),
                ("n_tokens", pa.int64()),
                ("ids_crc32", pa.int64()),
            ]
        )
        for part in slices(batches, 1 << 20):
            for row in part.to_pylist():
                lengths, ids = unpack_block(row["payload"])
                raw = ids.astype("<u4").tobytes()
                at = np.concatenate([[0], np.cumsum(lengths)])
                crc = [zlib.crc32(raw[4 * a : 4 * b]) for a, b in zip(at[:-1].tolist(), at[1:].tolist())]
                yield batch_of(
                    schema, [row["shard"]] * len(lengths), row["doc_ids"], at[:-1] + row["first"], lengths, crc
                )

    found = blocks.select("shard", "first", "doc_ids", "payload").mapInArrow(
        run, "shard int, doc_id long, local long, n_tokens long, ids_crc32 long"
    )
    return found.join(F.broadcast(starts), "shard").select(
        "doc_id", (F.col("local") + F.col("before")).alias("start"), "n_tokens", "ids_crc32"
    )


def read_ids(spark: SparkSession, path: str) -> DataFrame:
    """doc_id, ids (array<long>) of every document, for users who want the ids themselves."""
    blocks = spark.read.schema(BLOCKS).parquet(path)

    def run(batches):
        schema = pa.schema([("doc_id", pa.int64()), ("ids", pa.list_(pa.int64()))])
        for part in slices(batches, 1 << 20):
            for row in part.to_pylist():
                lengths, ids = unpack_block(row["payload"])
                offsets = pa.array(np.concatenate([[0], np.cumsum(lengths)]).astype(np.int32))
                yield batch_of(schema, row["doc_ids"], pa.ListArray.from_arrays(offsets, pa.array(ids.astype(np.int64))))

    return blocks.select("doc_ids", "payload").mapInArrow(run, "doc_id long, ids array<long>")
