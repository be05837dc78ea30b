"""A bounded table from strings to their ids, read by whole slices of texts at once."""

from __future__ import annotations

from itertools import chain

import numpy as np
import pyarrow as pa


#: A string's head, its place in the dictionary, its number, start, flag and count of uses.
ENTRY_BYTES = 220


def flat_ids(lists: list) -> np.ndarray:
    return np.fromiter(chain.from_iterable(lists), dtype=np.uint32)


def spread(first: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """The places first, first+1, ... of each run, end to end."""
    out = np.ones(int(lengths.sum()), dtype=np.int64)
    some = lengths > 0
    first, lengths = first[some], lengths[some]
    if not len(first):
        return out
    at = np.concatenate([[0], np.cumsum(lengths)[:-1]])
    out[at] = np.concatenate([[first[0]], first[1:] - first[:-1] - lengths[:-1] + 1])
    return np.cumsum(out)


class IdTable(dict):
    """String -> its number; ids by number in two flat arrays, and a small flag for each number,
    so that texts become id arrays by lookups and one gather. Strings that a slice brings anew are
    made together by `made`. When the table takes more than about `most_bytes`, the rarer half leaves.
    """

    def __init__(self, most_bytes: int):
        super().__init__()
        self.most_bytes = most_bytes
        self.forget()

    def made(self, new: list[str]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(ids end to end, number of ids of each, flag of each) of strings, in their order."""
        raise NotImplementedError

    def forget(self) -> None:
        self.clear()
        self.pending: list[str] = []
        self.first = np.zeros(1, dtype=np.int64)  # where each number's ids begin, and the end
        self.flat = np.zeros(0, dtype=np.uint32)
        self.flags = np.zeros(0, dtype=np.int8)
        self.uses = np.zeros(0, dtype=np.int64)
        self.text_bytes = 0

    def size(self) -> int:
        """About the bytes in use: strings with their heads, hash slots, numbers and ids."""
        return self.text_bytes + ENTRY_BYTES * len(self) + self.flat.nbytes

    def __missing__(self, string: str) -> int:
        number = self[string] = len(self)
        self.pending.append(string)
        return number

    def flush(self) -> None:
        new, self.pending = self.pending, []
        if not new:
            return
        flat, lengths, flags = self.made(new)
        self.first = np.concatenate([self.first, self.first[-1] + np.cumsum(lengths)])
        self.flat = np.concatenate([self.flat, flat])
        self.flags = np.concatenate([self.flags, flags])
        self.uses = np.concatenate([self.uses, np.zeros(len(new), dtype=np.int64)])
        self.text_bytes += sum(map(len, new))

    def trim(self) -> None:
        if self.size() <= self.most_bytes:
            return
        keep = np.sort(np.argsort(-self.uses, kind="stable")[: len(self) // 2])
        strings = list(self)
        names = [strings[i] for i in keep.tolist()]
        lengths, flags = np.diff(self.first)[keep], self.flags[keep]
        flat = self.flat[spread(self.first[keep], lengths)]
        self.forget()
        self.update(zip(names, range(len(names))))
        self.first = np.concatenate([[0], np.cumsum(lengths)])
        self.flat, self.flags, self.uses = flat, flags, np.zeros(len(names), dtype=np.int64)
        self.text_bytes = sum(map(len, names))

    def encoded(self, texts: list[list[str]]) -> tuple[np.ndarray, np.ndarray, list[np.ndarray]]:
        """(ids of all texts end to end, number of ids of each text, per flag bit the number of
        strings of each text that have it), from texts cut into strings."""
        stop = np.cumsum([len(x) for x in texts], dtype=np.int64)
        n = int(stop[-1]) if len(stop) else 0
        at = np.fromiter(map(self.__getitem__, chain.from_iterable(texts)), dtype=np.int64, count=n)
        self.flush()
        return self.gathered(at, stop)

    def encoded_column(self, texts: pa.ListArray) -> tuple[np.ndarray, np.ndarray, list[np.ndarray]]:
        """The same from a column of string lists: Arrow finds a slice's distinct strings, and only
        those become Python strings."""
        coded = texts.flatten().dictionary_encode()
        own = coded.dictionary.to_pylist()
        numbers = np.fromiter(map(self.__getitem__, own), dtype=np.int64, count=len(own))
        self.flush()
        return self.gathered(numbers[coded.indices.to_numpy()], np.cumsum(texts.value_lengths().to_numpy(), dtype=np.int64))

    def gathered(self, at: np.ndarray, stop: np.ndarray) -> tuple[np.ndarray, np.ndarray, list[np.ndarray]]:
        self.uses += np.bincount(at, minlength=len(self.uses))
        lengths = np.diff(self.first)[at]
        ids = self.flat[spread(self.first[at], lengths)]
        begin = np.concatenate([[0], stop[:-1]]) if len(stop) else stop
        sums = np.concatenate([[0], np.cumsum(lengths)])
        bits = []
        for b in (1, 2):
            some = np.concatenate([[0], np.cumsum((self.flags[at] & b) > 0)])
            bits.append(some[stop] - some[begin])
        self.trim()
        return ids, sums[stop] - sums[begin], bits
