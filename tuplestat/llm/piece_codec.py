"""A sentencepiece model run by the tokenizers library, both ways, with its parity measured.

The model file's protobuf is parsed here from its wire format (pieces with score and kind,
trainer and normaliser settings). From it the normaliser, the space marker, the scores and byte
fallback are rebuilt: a unigram model becomes a Unigram backend with the same scores, a BPE
model a BPE backend whose merges are ordered by the score of the piece that they make. Settings
that the backend has no equal for (a character map, removal of extra spaces) are refused.

Texts are encoded per distinct pre-token (see `token_counts`: the same cuts, proved on the
vocabulary) in multithreaded batches. Each distinct pre-token is also encoded by the reference
library; where the two differ (merges of equal rank in runs of one character can), the reference
wins and the document counts the mismatch. Each distinct pre-token's ids are also decoded by the
backend and compared with it; decoding joins pre-tokens as they stand, since each is whole
characters.

Nulls are empty texts, which have no ids; null ids are kept; repeated rows each give a row; an
empty table gives an empty result. Only the id and text columns are read.
"""

from __future__ import annotations

import os
import struct
import zlib
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import sentencepiece
from pyspark.sql import DataFrame

from .id_table import IdTable, flat_ids
from .shared import batch_of, held, id_text, slices
from .token_counts import MARK, PRE_TOKEN, check_cuts

NORMAL, UNKNOWN, CONTROL, USER, UNUSED, BYTE = 1, 2, 3, 4, 5, 6  # fixed values of the file format
UNIGRAM, BPE = 1, 2


@dataclass
class PieceModel:
    pieces: list[tuple[str, float, int]] = field(default_factory=list)
    kind: int = UNIGRAM
    byte_fallback: bool = False
    normaliser: str = ""
    has_charsmap: bool = False
    dummy_prefix: bool = True
    squeeze_spaces: bool = True
    escape_spaces: bool = True


def wire(data: bytes):
    """(field number, value) pairs of a protobuf message; bytes for length-delimited fields."""
    at, end = 0, len(data)

    def number() -> int:
        nonlocal at
        shift = value = 0
        while True:
            byte = data[at]
            at += 1
            value |= (byte & 0x7F) << shift
            if byte < 0x80:
                return value
            shift += 7

    while at < end:
        tag = number()
        form = tag & 7
        if form == 0:
            yield tag >> 3, number()
            continue
        size = {1: 8, 5: 4}.get(form)
        if size is None:
            if form != 2:
                raise ValueError("unknown wire type")
            size = number()
        yield tag >> 3, data[at : at + size]
        at += size


def parse_model(data: bytes) -> PieceModel:
    out = PieceModel()
    for number, value in wire(data):
        if number == 1:
            piece, score, kind = "", 0.0, NORMAL
            for n, v in wire(value):
                if n == 1:
                    piece = v.decode("utf-8")
                elif n == 2:
                    score = struct.unpack("<f", v)[0]
                elif n == 3:
                    kind = v
            out.pieces.append((piece, score, kind))
        elif number == 2:
            for n, v in wire(value):
                if n == 3:
                    out.kind = v
                elif n == 35:
                    out.byte_fallback = bool(v)
        elif number == 3:
            for n, v in wire(value):
                if n == 1:
                    out.normaliser = v.decode("utf-8")
                elif n == 2:
                    out.has_charsmap = bool(v)
                elif n == 3:
                    out.dummy_prefix = bool(v)
                elif n == 4:
                    out.squeeze_spaces = bool(v)
                elif n == 5:
                    out.escape_spaces = bool(v)
    return out


def build_backend(model: PieceModel):
    """A tokenizers.Tokenizer that encodes pre-tokens (marks included) and decodes whole id lists."""
    from tokenizers import Tokenizer, decoders, models, normalizers

    if model.has_charsmap or model.squeeze_spaces or not model.escape_spaces:
        raise ValueError(f"normaliser {model.normaliser!r} with these settings isn't rebuilt")
    unk = next(i for i, p in enumerate(model.pieces) if p[2] == UNKNOWN)
    if model.kind == UNIGRAM:
        core = models.Unigram([(p, s) for p, s, _ in model.pieces], unk, model.byte_fallback)
    elif model.kind == BPE:
        vocab = {p: i for i, (p, _, _) in enumerate(model.pieces)}
        usable = {p for p, _, kind in model.pieces if kind in (NORMAL, USER)}
        ranked = []
        for p, score, kind in model.pieces:
            if kind == NORMAL and len(p) > 1:
                for k in range(1, len(p)):
                    a, b = p[:k], p[k:]
                    if a in usable and b in usable:
                        ranked.append((-score, vocab[a], vocab[b], a, b))
        ranked.sort()
        merges = [(a, b) for _, _, _, a, b in ranked]
        core = models.BPE(
            vocab=vocab, merges=merges, unk_token=model.pieces[unk][0], byte_fallback=model.byte_fallback, fuse_unk=True
        )
    else:
        raise ValueError("only unigram and BPE models are rebuilt")
    tok = Tokenizer(core)
    tok.normalizer = normalizers.Replace(" ", MARK)
    strip = [decoders.Strip(" ", 1, 0)] if model.dummy_prefix else []
    tok.decoder = decoders.Sequence([decoders.Replace(MARK, " "), decoders.ByteFallback(), decoders.Fuse(), *strip])
    return tok


OFF_PARITY, NO_ROUND_TRIP = 1, 2
TABLE_BYTES = 80 << 20


class PieceIds(IdTable):
    """Pre-token -> ids of the reference, flagged where the backend's ids differ from them or
    where the backend does not decode them to the pre-token."""

    def __init__(self, backend, reference: sentencepiece.SentencePieceProcessor, most_bytes: int = TABLE_BYTES):
        super().__init__(most_bytes)
        self.backend, self.reference = backend, reference
        self.encode = getattr(backend, "encode_batch_fast", backend.encode_batch)
        self.lone = [reference.piece_to_id(MARK)]

    def made(self, new: list[str]):
        marked = [k[0] in (" ", MARK) for k in new]
        ours = [e.ids for e in self.encode(new, add_special_tokens=False)]
        own = self.reference.encode([k[1:] if m else "\n" + k for k, m in zip(new, marked)], num_threads=1)
        theirs = [(x or self.lone) if m else x[2:] for x, m in zip(own, marked)]
        # The decoder drops a leading space, so an unmarked pre-token stands behind a lone mark.
        back = self.backend.decode_batch(
            [x if m else self.lone + x for x, m in zip(theirs, marked)], skip_special_tokens=False
        )
        flags = [
            OFF_PARITY * (a != b) + NO_ROUND_TRIP * (text != (k[1:] if m else k).replace(MARK, " "))
            for a, b, text, k, m in zip(ours, theirs, back, new, marked)
        ]
        # The backend's ids, and the reference's only where the backend is off parity.
        chosen = [b if flag & OFF_PARITY else a for a, b, flag in zip(ours, theirs, flags)]
        return flat_ids(chosen), np.array([len(x) for x in chosen], dtype=np.int64), np.array(flags, dtype=np.int8)


def worker(key: int, proto: bytes, threads: int) -> PieceIds:
    """The pre-token table of this worker process, with backend and reference."""
    os.environ["TOKENIZERS_PARALLELISM"] = "true" if threads > 1 else "false"
    os.environ["RAYON_NUM_THREADS"] = str(threads)

    def make():
        reference = sentencepiece.SentencePieceProcessor(model_proto=proto)
        return PieceIds(build_backend(parse_model(proto)), reference)

    return held(("pieces", key), make)


def encode_texts(texts: list[str], table: PieceIds):
    """(ids of all texts end to end, number of ids, of pre-tokens off parity and of pre-tokens
    that do not come back, of each text)."""
    ids, count, (off, lost) = table.encoded([PRE_TOKEN.findall(" " + t) if t else [] for t in texts])
    return ids, count, off, lost


def piece_codec(
    docs: DataFrame,
    model_path: str,
    with_ids: bool = False,
    threads: int = 2,
    id_col: str = "doc_id",
    text_col: str = "text",
) -> DataFrame:
    """doc_id, n_tokens, ids_crc32, n_off_parity (pre-tokens where the backend alone would differ),
    round_trip (the decoded ids are the text) and, if asked for, ids of every row of `docs`."""
    with open(model_path, "rb") as f:
        proto = f.read()
    model = parse_model(proto)
    check_cuts([p for p, _, _ in model.pieces])
    if not model.dummy_prefix:
        raise ValueError("a model without a leading marker needs other cuts")
    shipped, key = docs.sparkSession.sparkContext.broadcast(proto), hash(proto)
    fields = [
        ("doc_id", pa.int64()),
        ("n_tokens", pa.int64()),
        ("ids_crc32", pa.int64()),
        ("n_off_parity", pa.int64()),
        ("round_trip", pa.bool_()),
    ] + [("ids", pa.list_(pa.int32()))] * with_ids

    def run(batches):
        table = worker(key, shipped.value, threads)
        schema = pa.schema(fields)
        for part in slices(batches, 1 << 20):
            texts = [t or "" for t in part.column(1).to_pylist()]
            ids, count, off, lost = encode_texts(texts, table)
            cut = np.concatenate([[0], np.cumsum(count)])
            raw, at = ids.astype("<u4").tobytes(), cut.tolist()
            crc = [zlib.crc32(raw[4 * a : 4 * b]) for a, b in zip(at[:-1], at[1:])]
            columns = [part.column(0), count, crc, off, lost == 0]
            if with_ids:
                columns.append(pa.ListArray.from_arrays(pa.array(cut.astype(np.int32)), pa.array(ids.astype(np.int32))))
            yield batch_of(schema, *columns)

    out = "doc_id long, n_tokens long, ids_crc32 long, n_off_parity long, round_trip boolean"
    return id_text(docs, id_col, text_col).mapInArrow(run, out + ", ids array<int>" * with_ids)


def decode_ids(rows: DataFrame, model_path: str, threads: int = 2, id_col: str = "doc_id", ids_col: str = "ids") -> DataFrame:
    """doc_id, text of every row: the backend's text of an array of ids.

    Null ids give a null text, no ids an empty one; an id outside the model is an error."""
    with open(model_path, "rb") as f:
        proto = f.read()
    pieces = len(parse_model(proto).pieces)
    shipped, key = rows.sparkSession.sparkContext.broadcast(proto), hash(proto)
    schema = pa.schema([("doc_id", pa.int64()), ("text", pa.string())])

    def run(batches):
        backend = worker(key, shipped.value, threads).backend
        for part in slices(batches, 2 << 20):
            lists = part.column(1).to_pylist()
            if any(k is None or not 0 <= k < pieces for x in lists for k in x or ()):
                raise ValueError("an id that the model doesn't have")
            texts = iter(backend.decode_batch([x for x in lists if x is not None], skip_special_tokens=False))
            yield batch_of(schema, part.column(0), [None if x is None else next(texts) for x in lists])

    named = rows.selectExpr(f"CAST(`{id_col}` AS LONG) AS doc_id", f"CAST(`{ids_col}` AS ARRAY<INT>) AS ids")
    return named.mapInArrow(run, "doc_id long, text string")
