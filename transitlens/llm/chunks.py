"""Pieces of texts that a tokenizer treats apart, so that each distinct piece needs its tokens found once."""

from __future__ import annotations

import re
from collections import defaultdict
from itertools import chain, count, islice

import numpy as np

_LOOSE = re.compile(r" (?=\s|$)").search
_START = re.compile(r"(?= \S)").split


def chunk_keys(text: str) -> list[str]:
    """``text`` cut before each space that another character than white space follows; each chunk by its key (:func:`chunk_of`).

    No pre-token of the byte-level BPE has such a space inside, and whether white space follows a chunk's end changes none of its
    own pre-tokens, so a text's tokens are those of its chunks end to end. An empty text has none.
    """
    if not text:
        return []
    if _LOOSE(text):
        return [c[1:] if c[0] == " " and c[1:2].strip() else " " + c for c in _START(text) if c]
    parts = text.split(" ")
    if parts[0]:
        parts[0] = " " + parts[0]
        return parts
    return parts[1:]


def chunk_of(key: str) -> str:
    """The chunk of a key: most chunks start with one space, which their key leaves out; the key of any other has one more."""
    return key[1:] if key[:1] == " " else " " + key


class CodeTable(defaultdict):
    """Numbers the distinct keys that it meets; how many it holds, and how long they are, is bounded between batches.

    ``new`` lists the keys met first in the last batch, in order of their codes.
    """

    def __init__(self, limit: int = 800_000, longest: int = 64):
        super().__init__(count().__next__)
        self.limit, self.longest = limit, longest
        self.new: list[str] = []
        self.size = 0
        self.seen = np.zeros(0, np.int64)

    def trim(self) -> np.ndarray | None:
        """Before a batch: forgets the keys met once, or all if that is not enough. The old codes of those kept, in the order of their
        new ones; None if nothing changed."""
        for key in [k for k in self.new if len(k) > self.longest]:
            del self[key]
        self.new = []
        if self.size <= self.limit:
            return None
        kept = [k for k, c in self.items() if self.seen[c] > 1]
        if len(kept) > self.limit // 2:
            kept = []
        old = np.fromiter(map(self.__getitem__, kept), np.int64, len(kept))
        self.clear()
        self.update(zip(kept, range(len(kept)), strict=True))
        self.size, self.seen = len(kept), self.seen[old]
        self.default_factory = count(self.size).__next__
        return old

    def codes(self, cut: list[list[str]]) -> tuple[np.ndarray, np.ndarray]:
        """The codes of all keys end to end, and where each list ends."""
        ends = np.cumsum(np.fromiter(map(len, cut), np.int64, len(cut)))
        found = np.fromiter(map(self.__getitem__, chain.from_iterable(cut)), np.int64, int(ends[-1]) if len(cut) else 0)
        more = int(found.max(initial=-1)) + 1 - self.size
        if more > 0:
            self.new = list(islice(reversed(self), more))[::-1]
            self.size += more
            self.seen = np.concatenate([self.seen, np.zeros(more, np.int64)])
        self.seen += np.bincount(found, minlength=self.size)
        return found, ends


def sums(values: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """Sums of consecutive ranges of ``values``, of which some may be empty."""
    total = np.concatenate([[0], np.cumsum(values)])
    return np.diff(total[np.concatenate([[0], ends])])


class Ragged:
    """Lists of numbers by code, end to end in one array."""

    def __init__(self, kind: type):
        self.flat, self.start, self.size = np.zeros(0, kind), np.zeros(0, np.int64), np.zeros(0, np.int64)

    def extend(self, flat: np.ndarray, size: np.ndarray) -> None:
        """Adds lists: their numbers end to end, and how many each has."""
        start = self.flat.size + np.cumsum(size) - size
        self.flat = np.concatenate([self.flat, flat.astype(self.flat.dtype)])
        self.start, self.size = np.concatenate([self.start, start]), np.concatenate([self.size, size])

    def take(self, codes: np.ndarray) -> np.ndarray:
        """The lists of these codes end to end."""
        n = self.size[codes]
        ends = np.cumsum(n)
        if not ends.size:
            return self.flat[:0]
        return self.flat[np.arange(ends[-1]) + np.repeat(self.start[codes] - ends + n, n)]

    def keep(self, codes: np.ndarray) -> None:
        """Only the lists of these codes, in their order."""
        flat, size = self.take(codes), self.size[codes]
        self.__init__(self.flat.dtype)
        self.extend(flat, size)
