"""Token counts of whole texts by rank-synchronous array merging.

A batch's distinct pre-tokens lie end to end in one symbol array, with a start for each (a ragged array). In each round every
sequence finds the lowest rank among its adjacent pairs and merges all places of that pair at once, the left one first where two
overlap; a sequence without a known pair leaves the array with the count of its symbols. The counts equal those of the
byte-level BPE of the tokenizers library.

Defined cases: a null text counts as empty (0 bytes, 0 tokens); strings of added tokens inside a text count as one token, the
library's default; repeated rows give repeated rows; an empty table gives an empty table; other columns of the input are ignored.
"""

from __future__ import annotations

import json
from collections.abc import Iterable, Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .chunks import CodeTable, chunk_keys, chunk_of, sums
from .common import slices, text_or_empty
from .token_files import in_chunks

#: Fixed value: the split of the byte-level BPE before merges.
SPLIT = r"""'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"""
_NONE = np.iinfo(np.int64).max


def _byte_chars() -> dict[str, int]:
    """The vocabulary's printable stand-in for each byte: itself if printable Latin-1, else the next code point from 256."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [b for b in range(256) if b not in set(plain)]
    return {chr(b): b for b in plain} | {chr(256 + i): b for i, b in enumerate(rest)}


class RankMerger:
    """Counts tokens of pre-tokens; holds the merge table as sorted arrays."""

    def __init__(self, path: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        if not in_chunks(path) or spec["model"].get("ignore_merges") or spec["model"].get("dropout"):
            raise ValueError(f"{path}: not a byte-level BPE with its own split and without a normaliser")
        vocab = spec["model"]["vocab"]
        self.first = np.zeros(256, np.int64)
        for c, b in _byte_chars().items():
            self.first[b] = vocab[c]
        pairs = [m if isinstance(m, list) else m.split(" ") for m in spec["model"]["merges"]]
        keys = np.array([vocab[a] << 24 | vocab[b] for a, b in pairs], np.int64)
        order = np.argsort(keys, kind="stable")
        self.keys = np.append(keys[order], _NONE)
        self.rank = np.append(order, 0).astype(np.int64)
        self.made = np.array([vocab[a + b] for a, b in pairs], np.int64)
        added = sorted((x["content"] for x in spec.get("added_tokens", [])), key=len, reverse=True)
        self.added = regex.compile("|".join(map(regex.escape, added))) if added else None
        self.split = regex.compile(SPLIT)
        self.table, self.known = CodeTable(), np.zeros(0, np.int64)

    def _ranks(self, sym: np.ndarray, at: np.ndarray) -> np.ndarray:
        """Rank of the pair at each place, the largest integer where the vocabulary has none."""
        key = sym[at] << 24 | sym[at + 1]
        found = np.searchsorted(self.keys, key)
        return np.where(self.keys[found] == key, self.rank[found], _NONE)

    def merge_counts(self, words: list[str]) -> np.ndarray:
        """Symbols left of each word after all merges."""
        raw = [w.encode("utf-8") for w in words]
        length = np.fromiter(map(len, raw), np.int64, len(raw))
        count = np.zeros(len(raw), np.int64)
        who = np.flatnonzero(length)
        length = length[who]
        sym = self.first[np.frombuffer(b"".join(raw), np.uint8)]
        rank = self._ranks(sym, np.arange(sym.size - 1))
        rank = np.append(rank, _NONE) if sym.size else rank
        rank[np.cumsum(length) - 1] = _NONE
        while who.size:
            start = np.cumsum(length) - length
            low = np.minimum.reduceat(rank, start)
            on = low != _NONE
            count[who[~on]] = length[~on]
            if not on.any():
                break
            own = np.repeat(np.arange(who.size), length)
            keep = on[own]
            at = np.flatnonzero((rank == low[own]) & keep)
            # Hits that touch form runs of one doubled symbol: every other one merges, from the left.
            if (touch := np.diff(at) == 1).any():
                nth = np.arange(at.size)
                run = np.maximum.accumulate(np.where(np.append(True, ~touch), nth, 0))
                at = at[(nth - run) % 2 == 0]
            sym[at] = self.made[rank[at]]
            last = rank[at + 1] == _NONE  # of the right half: kept where the pair ended its sequence
            ends = last & (np.append(own, -1)[at + 2] != own[at])
            keep[at + 1] = False
            length = np.add.reduceat(keep.astype(np.int64), start)[on]
            place = np.cumsum(keep) - 1
            sym, rank, own, who = sym[keep], rank[keep], own[keep], who[on]
            at = place[at]
            rank[at[ends]] = _NONE
            near = np.concatenate([at[~ends], (left := at[at > 0] - 1)[own[left] == own[left + 1]]])
            rank[near] = self._ranks(sym, near)
        return count

    def _learn(self, chunks: list[str]) -> np.ndarray:
        """Counts of chunks: distinct pre-tokens are merged together, and summed for each chunk."""
        cut: list[list[str]] = []
        extra = np.zeros(len(chunks), np.int64)
        for i, t in enumerate(chunks):
            if t[1:].isalpha() and t[:1] == " ":
                cut.append([t])
            elif self.added is not None and (n := len(self.added.findall(t))):
                extra[i] = n
                cut.append([w for part in self.added.split(t) for w in self.split.findall(part)])
            else:
                cut.append(self.split.findall(t))
        words = CodeTable()
        codes, ends = words.codes(cut)
        return extra + sums(self.merge_counts(words.new)[codes], ends)

    def counts(self, texts: list[str]) -> list[int]:
        """Tokens of each text."""
        if (kept := self.table.trim()) is not None:
            self.known = self.known[kept]
        codes, ends = self.table.codes(list(map(chunk_keys, texts)))
        if self.table.new:
            self.known = np.concatenate([self.known, self._learn(list(map(chunk_of, self.table.new)))])
        return sums(self.known[codes], ends).tolist()


@lru_cache(maxsize=2)
def merger(path: str) -> RankMerger:
    return RankMerger(path)


def token_counts(docs: DataFrame, path: str, limit: int = 1024) -> DataFrame:
    """``(doc_id, n_bytes, n_tokens, over_limit)`` of each row of ``docs(doc_id, text)``."""
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_or_empty().alias("text"))

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = merger(path)
        for b in batches:
            for lo, hi, part in slices(b.column(1)):
                n = own.counts(part)
                yield pa.RecordBatch.from_arrays(
                    [b.column(0).slice(lo, hi - lo), pa.array([len(t.encode("utf-8")) for t in part], pa.int64()), pa.array(n, pa.int64()), pa.array([x > limit for x in n], pa.bool_())],
                    names=["doc_id", "n_bytes", "n_tokens", "over_limit"],
                )

    return rows.mapInArrow(run, "doc_id long, n_bytes long, n_tokens long, over_limit boolean")
