"""Simple-8b: a word-aligned code that packs a varying count of ids into each 64-bit word.

The top four bits of a word select how many values of how many bits the other sixty hold. A
value of sixty bits or more goes to an escape list behind the words; its word (selector 15)
holds its place there. Both directions work on whole arrays: the encoder finds, for each
position at once, the densest selector that fits, then follows the chain of word starts; the
decoder unpacks all words of one selector together.
"""

from __future__ import annotations

import numpy as np

#: Fixed values of the code: bits and values per word of selectors 1 to 14.
WIDTHS = (1, 2, 3, 4, 5, 6, 7, 8, 10, 12, 15, 20, 30, 60)
COUNTS = (60, 30, 20, 15, 12, 10, 8, 7, 6, 5, 4, 3, 2, 1)
ESCAPE = 15

_STEPS = np.array((0, *COUNTS, 1), dtype=np.int64)


_SHORT = np.array([max(1, v.bit_length()) for v in range(1 << 16)], dtype=np.int8)


def bit_lengths(values: np.ndarray) -> np.ndarray:
    """Bits of each unsigned value, 1 for zero."""
    top = int(values.max()) if len(values) else 0
    if top < 1 << 16:
        return _SHORT[values.astype(np.uint16)]
    bits = np.ones(len(values), dtype=np.int8)
    for b in range(1, top.bit_length()):
        bits += values >= np.uint64(1 << b)
    return bits


def encode(values: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(words, escapes) of a one-dimensional array of unsigned integers."""
    values = np.ascontiguousarray(values, dtype=np.uint64)
    n = len(values)
    if n == 0:
        return np.zeros(0, np.uint64), np.zeros(0, np.uint64)
    bits = bit_lengths(values)
    choice = np.full(n, len(WIDTHS), dtype=np.int8)  # one value of sixty bits
    # Longer windows hold a shorter one, so once no window fits, no longer one does.
    peak, width_of_peak = bits, 1
    for s in range(len(WIDTHS) - 1, 0, -1):
        count = COUNTS[s - 1]
        while width_of_peak < count:
            grow = min(width_of_peak, count - width_of_peak)
            nxt = peak.copy()
            if grow < n:
                np.maximum(peak[:-grow], peak[grow:], out=nxt[:-grow])
            peak, width_of_peak = nxt, width_of_peak + grow
        fits = peak <= WIDTHS[s - 1]  # past the end, a window is filled up with zeros
        if not fits.any():
            break
        np.copyto(choice, s, where=fits, casting="unsafe")
    choice[bits > 60] = ESCAPE
    step = _STEPS.astype(np.uint8)[choice].tobytes()
    chain, at = [], 0
    push = chain.append
    while at < n:
        push(at)
        at += step[at]
    starts = np.array(chain, dtype=np.int64)
    chosen = choice[starts]
    words = chosen.astype(np.uint64) << np.uint64(60)
    padded = np.concatenate([values, np.zeros(60, np.uint64)])
    for s in np.unique(chosen):
        if s == ESCAPE:
            continue
        mine = np.flatnonzero(chosen == s)
        width, acc = np.uint64(WIDTHS[s - 1]), np.zeros(len(mine), np.uint64)
        for k in range(COUNTS[s - 1]):
            acc |= padded[starts[mine] + k] << (width * np.uint64(k))
        words[mine] |= acc
    out = np.flatnonzero(chosen == ESCAPE)
    words[out] |= np.arange(len(out), dtype=np.uint64)
    return words, values[starts[out]]


def decode(words: np.ndarray, escapes: np.ndarray, n: int) -> np.ndarray:
    """The first `n` values that `words` hold."""
    if n == 0:
        return np.zeros(0, np.uint64)
    sel = (words >> np.uint64(60)).astype(np.int64)
    at = np.concatenate([[0], np.cumsum(_STEPS[sel])])
    out = np.zeros(int(at[-1]), dtype=np.uint64)
    body = words & np.uint64((1 << 60) - 1)
    for s in np.unique(sel):
        mine = np.flatnonzero(sel == s)
        if s == ESCAPE:
            out[at[mine]] = escapes[body[mine].astype(np.int64)]
            continue
        width = WIDTHS[s - 1]
        mask = np.uint64((1 << width) - 1)
        for k in range(COUNTS[s - 1]):
            out[at[mine] + k] = (body[mine] >> np.uint64(width * k)) & mask
    return out[:n]


#: A block: magic, number of documents, of length words, of length escapes, of ids, of id words,
#: of id escapes; then those arrays; then the first word of every STRIDE-th word's values.
MAGIC = 0x31423853
STRIDE = 1024


def pack_block(lengths: np.ndarray, ids: np.ndarray) -> bytes:
    """A block's bytes: lengths of its documents, their ids end to end, offsets for entry midway."""
    lw, le = encode(lengths)
    iw, ie = encode(ids)
    sel = (iw >> np.uint64(60)).astype(np.int64)
    before = np.concatenate([[0], np.cumsum(_STEPS[sel])])[:-1][::STRIDE].astype("<u8")
    head = np.array([MAGIC, len(lengths), len(lw), len(le), len(ids), len(iw), len(ie)], dtype="<u8")
    return b"".join(np.ascontiguousarray(x, dtype="<u8").tobytes() for x in (head, lw, le, iw, ie, before))


def unpack_block(data: bytes) -> tuple[np.ndarray, np.ndarray]:
    """(lengths, ids) of a block; raises ValueError on anything that pack_block did not make."""
    x = np.frombuffer(data, dtype="<u8")
    if len(x) < 7 or int(x[0]) != MAGIC:
        raise ValueError("not a token block")
    _, docs, nlw, nle, n, niw, nie = (int(v) for v in x[:7])
    cut = np.cumsum([7, nlw, nle, niw, nie])
    if len(x) != cut[-1] + -(-niw // STRIDE):
        raise ValueError("truncated token block")
    lw, le, iw, ie = (x[a:b] for a, b in zip(cut[:-1], cut[1:]))
    return decode(lw, le, docs).astype(np.int64), decode(iw, ie, n)


def read_from(data: bytes, first: int, count: int) -> np.ndarray:
    """Ids first .. first+count-1 of a block, decoded from the nearest stored offset on."""
    x = np.frombuffer(data, dtype="<u8")
    _, _, nlw, nle, n, niw, nie = (int(v) for v in x[:7])
    at = 7 + nlw + nle
    words, escapes = x[at : at + niw], x[at + niw : at + niw + nie]
    before = x[at + niw + nie :].astype(np.int64)
    count = max(0, min(count, n - first))
    if count == 0:
        return np.zeros(0, np.uint64)
    a = int(np.searchsorted(before, first, side="right")) - 1
    b = int(np.searchsorted(before, first + count, side="left"))
    part = words[a * STRIDE : b * STRIDE]
    got = decode(part, escapes, min(n, int(before[b]) if b < len(before) else n) - int(before[a]))
    skip = first - int(before[a])
    return got[skip : skip + count]
