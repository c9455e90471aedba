"""SentencePiece encoding and decoding by the tokenizers library.

The model file is parsed from its wire format, without the sentencepiece library: pieces with scores and kinds, trainer settings
and normaliser settings. From these the tokenizers library gets a normaliser (white space rules, character map), the metaspace
marker, the scores (as they are for a unigram model; as ranks of all merges that make a piece for a BPE model), byte fallback and
a decoder. Batches are encoded by the library's own threads. Parity with sentencepiece is verified row by row where asked for.

Defined cases: a null text counts as empty (no ids, empty decoding); repeated rows stay; an empty table gives an empty table;
other columns of the input are ignored by :func:`encode_pieces` and kept by :func:`with_piece_ids`.
"""

from __future__ import annotations

import os
import re
import zlib
from collections.abc import Iterable, Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .chunks import CodeTable, Ragged, sums
from .common import slices, text_or_empty

MARK = "▁"
#: Kinds of a piece in the model file.
NORMAL, UNKNOWN, CONTROL, USER, UNUSED, BYTE = 1, 2, 3, 4, 5, 6
#: Model types of the trainer settings.
UNIGRAM, BPE = 1, 2


def _varint(b: bytes, i: int) -> tuple[int, int]:
    x = shift = 0
    while True:
        x |= (b[i] & 127) << shift
        shift += 7
        i += 1
        if b[i - 1] < 128:
            return x, i


def _fields(b: bytes) -> Iterator[tuple[int, object]]:
    """Field numbers and values of a protobuf message: ints, or bytes for the rest."""
    i = 0
    while i < len(b):
        tag, i = _varint(b, i)
        kind = tag & 7
        if kind == 0:
            value, i = _varint(b, i)
        else:
            size, i = _varint(b, i) if kind == 2 else ({1: 8, 5: 4}[kind], i)
            value, i = b[i : i + size], i + size
        yield tag >> 3, value


class PieceModel:
    """What a model file says."""

    def __init__(self, raw: bytes):
        self.pieces: list[tuple[str, float, int]] = []
        trainer: dict[int, object] = {}
        rules: dict[int, object] = {}
        for field, value in _fields(raw):
            if field == 1:
                got = dict(_fields(value))
                self.pieces.append((got[1].decode("utf-8"), float(np.frombuffer(got.get(2, b"\0\0\0\0"), "<f4")[0]), got.get(3, NORMAL)))
            elif field == 2:
                trainer = dict(_fields(value))
            elif field == 3:
                rules = dict(_fields(value))
        self.model_type = trainer.get(3, UNIGRAM)
        self.byte_fallback = bool(trainer.get(35, 0))
        self.charsmap: bytes = rules.get(2, b"")
        self.dummy_prefix = bool(rules.get(3, 1))
        self.squeeze = bool(rules.get(4, 1))
        self.escape = bool(rules.get(5, 1))
        self.unk_id = next(i for i, p in enumerate(self.pieces) if p[2] == UNKNOWN)


def _merges(model: PieceModel, vocab: dict[str, int]) -> list[tuple[str, str]]:
    """Each split of a normal piece into two pieces, best score of the whole first."""
    own = {p for p, _, k in model.pieces if k in (NORMAL, USER)}
    found = []
    for piece, score, kind in model.pieces:
        if kind == NORMAL and len(piece) > 1:
            found += [(-score, vocab[piece[:i]], vocab[piece[i:]], piece[:i], piece[i:]) for i in range(1, len(piece)) if piece[:i] in own and piece[i:] in own]
    return [x[3:] for x in sorted(found)]


def build_tokenizer(model: PieceModel):
    """A tokenizers-library tokenizer that encodes and decodes as the model file says."""
    from tokenizers import AddedToken, Regex, Tokenizer, decoders, models, normalizers

    vocab = {p: i for i, (p, _, _) in enumerate(model.pieces)}
    if model.model_type == BPE:
        core = models.BPE(vocab=vocab, merges=_merges(model, vocab), unk_token=model.pieces[model.unk_id][0], fuse_unk=True, byte_fallback=model.byte_fallback)
    elif model.model_type == UNIGRAM:
        core = models.Unigram([(p, s) for p, s, _ in model.pieces], unk_id=model.unk_id, byte_fallback=model.byte_fallback)
    else:
        raise ValueError(f"model type {model.model_type} has no counterpart")
    own = Tokenizer(core)
    steps = [normalizers.Precompiled(model.charsmap)] if model.charsmap else []
    if model.squeeze:
        steps += [normalizers.Strip(), normalizers.Replace(Regex(" {2,}"), " ")]
    if model.dummy_prefix:
        steps.append(normalizers.Prepend(MARK if model.escape else " "))
    if model.escape:
        steps.append(normalizers.Replace(" ", MARK))
    own.normalizer = normalizers.Sequence(steps)
    tail = [decoders.Strip(" ", 1, 0)] if model.dummy_prefix else []
    own.decoder = decoders.Sequence([decoders.Replace(MARK, " "), decoders.ByteFallback(), decoders.Fuse(), *tail])
    if user := [AddedToken(p, normalized=False, special=False) for p, _, k in model.pieces if k == USER]:
        own.add_tokens(user)
    return own


class PieceCodec:
    """Encodes texts through the tokenizers library, each distinct word once.

    Where no piece has the marker after another character, no piece crosses the start of a word, so a text's ids are those of its
    words (each with the markers before it) end to end; else a text is one word. Words met before come from a bounded table; new
    ones go to the library many in one text, in which each piece with the marker starts a word.
    """

    def __init__(self, path: str, threads: int):
        # The library reads these when it starts its pool, once in a worker.
        os.environ.setdefault("RAYON_NUM_THREADS", str(threads))
        os.environ["TOKENIZERS_PARALLELISM"] = "true" if threads > 1 else "false"
        with open(path, "rb") as f:
            self.model = PieceModel(f.read())
        self.path, self.threads = path, threads
        self.own = build_tokenizer(self.model)
        m = self.model
        by_word = m.dummy_prefix and m.escape and not m.squeeze and not m.charsmap and not any(MARK in p.lstrip(MARK) or k == USER for p, _, k in m.pieces if k in (NORMAL, USER))
        self.words = re.compile(f"{MARK}*[^{MARK}]+|{MARK}+").findall if by_word else None
        self.starts = np.array([p.startswith(MARK) for p, _, _ in m.pieces])
        self.table, self.ids, self.lossy = CodeTable(), Ragged(np.dtype("<i4")), np.zeros(0, bool)

    def _split(self, text: str) -> list[str]:
        """Words, each as a text of its own would look."""
        if not text:
            return []
        if self.words is None:
            return [text]
        if MARK in text or "  " in text or text[0] == " " or text[-1] == " ":
            # The library puts the marker before a text, as it stands before a word.
            return [w[1:].replace(MARK, " ") for w in self.words(MARK + text.replace(" ", MARK))]
        return text.split(" ")

    def _learn(self, words: list[str]) -> None:
        plain = np.array([bool(w) and self.words is not None and " " not in w for w in words])
        order = np.argsort(~plain, kind="stable")
        one = [w for w, p in zip(words, plain, strict=True) if p]
        odd = [w for w, p in zip(words, plain, strict=True) if not p]
        flat, size, lossy = [], np.zeros(len(words), np.int64), np.zeros(len(words), bool)
        for lo in range(0, len(one), 1 << 14):
            held = [one[i : i + 256] for i in range(lo, min(lo + (1 << 14), len(one)), 256)]
            texts = list(map(" ".join, held))
            ids = [e.ids for e in self.own.encode_batch_fast(texts, add_special_tokens=False)]
            at = lo
            for part, text, x, back in zip(held, texts, ids, self.own.decode_batch(ids, skip_special_tokens=False), strict=True):
                x = np.array(x, "<i4")
                first = np.flatnonzero(self.starts[x])
                if first.size != len(part):
                    raise ValueError("a word has not one piece with the marker")
                flat.append(x)
                size[at : at + len(part)] = np.diff(np.append(first, x.size))
                if back != text:
                    alone = np.split(x, first[1:])
                    lossy[at : at + len(part)] = [d != w for d, w in zip(self.own.decode_batch([y.tolist() for y in alone], skip_special_tokens=False), part, strict=True)]
                at += len(part)
        # A text that is a marker alone: the library gives nothing for an empty text.
        ids = [[self.own.token_to_id(MARK)] if self.words and not w else e.ids for w, e in zip(odd, self.own.encode_batch_fast(odd, add_special_tokens=False), strict=True)]
        back = self.own.decode_batch(ids, skip_special_tokens=False)
        for n, (w, x, d) in enumerate(zip(odd, ids, back, strict=True), len(one)):
            flat.append(np.array(x, "<i4"))
            size[n], lossy[n] = len(x), d != w
        found = Ragged(np.dtype("<i4"))
        found.extend(np.concatenate(flat) if flat else self.ids.flat[:0], size)
        back = np.argsort(order)
        self.ids.extend(found.take(back), size[back])
        self.lossy = np.concatenate([self.lossy, lossy[back]])

    def encode(self, texts: list[str], parity: bool = False) -> list[tuple[np.ndarray, bool, bool | None]]:
        """Each text's ids as 32-bit integers, whether all its words decode to themselves, whether sentencepiece gives the same ids
        for the whole text."""
        if (kept := self.table.trim()) is not None:
            self.ids.keep(kept)
            self.lossy = self.lossy[kept]
        codes, ends = self.table.codes(list(map(self._split, texts)))
        if self.table.new:
            self._learn(self.table.new)
        ids = np.split(self.ids.take(codes), np.cumsum(sums(self.ids.size[codes], ends))[:-1])
        lossy = sums(self.lossy[codes], ends) > 0
        same: list[bool | None] = [None] * len(texts)
        if parity:
            same = [np.array_equal(x, y) for x, y in zip(ids, reference(self.path).encode(texts, num_threads=self.threads), strict=True)]
        return [(x, MARK not in t and not bad, p) for t, x, bad, p in zip(texts, ids, lossy, same, strict=True)]

    def decode(self, ids: list[list[int]]) -> list[str]:
        return self.own.decode_batch(ids, skip_special_tokens=False)


@lru_cache(maxsize=2)
def codec(path: str, threads: int = 2) -> PieceCodec:
    return PieceCodec(path, threads)


@lru_cache(maxsize=2)
def reference(path: str):
    import sentencepiece

    return sentencepiece.SentencePieceProcessor(model_file=path)


def _lists(ids: list[np.ndarray]) -> pa.Array:
    ends = np.cumsum([0, *map(len, ids)]).astype(np.int32)
    return pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate(ids)))


def with_piece_ids(docs: DataFrame, path: str, threads: int = 2) -> DataFrame:
    """``docs`` with a column ``piece_ids`` of the ids of ``text``, replacing one of that name."""
    rest = docs.drop("piece_ids")
    where = rest.columns.index("text")

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = codec(path, threads)
        for b in batches:
            for lo, hi, texts in slices(pc.fill_null(b.column(where), "")):
                ids = _lists([x for x, _, _ in own.encode(texts)])
                yield pa.RecordBatch.from_arrays([*b.slice(lo, hi - lo).columns, ids], names=[*b.schema.names, "piece_ids"])

    fields = T.StructType([*(T.StructField(f.name, f.dataType) for f in rest.schema), T.StructField("piece_ids", T.ArrayType(T.IntegerType()))])
    return rest.mapInArrow(run, fields)


def decode_pieces(rows: DataFrame, path: str, threads: int = 2) -> DataFrame:
    """``rows(doc_id, piece_ids)`` to ``(doc_id, text)``; null ids give an empty text."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = codec(path, threads)
        for b in batches:
            for lo in range(0, b.num_rows, 256):
                part = b.slice(lo, 256)
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(own.decode([x or [] for x in part.column(1).to_pylist()]), pa.string())], names=["doc_id", "text"])

    return rows.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("piece_ids").cast("array<int>").alias("piece_ids")).mapInArrow(run, "doc_id long, text string")


def encode_pieces(docs: DataFrame, path: str, threads: int = 2, parity: bool = True) -> DataFrame:
    """Per row of ``docs(doc_id, text)``: number and crc32 (little-endian 32-bit) of the ids, whether all its words decode to
    themselves, and whether sentencepiece gives the same ids for the whole text (null if not ``parity``)."""
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_or_empty().alias("text"))

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = codec(path, threads)
        for b in batches:
            for lo, hi, texts in slices(b.column(1)):
                got = own.encode(texts, parity)
                yield pa.RecordBatch.from_arrays(
                    [
                        b.column(0).slice(lo, hi - lo),
                        pa.array([x.size for x, _, _ in got], pa.int64()),
                        pa.array([zlib.crc32(x.data) for x, _, _ in got], pa.int64()),
                        pa.array([x for _, x, _ in got], pa.bool_()),
                        pa.array([x for _, _, x in got], pa.bool_()),
                    ],
                    names=["doc_id", "n_pieces", "ids_crc32", "words_decode", "parity"],
                )

    return rows.mapInArrow(run, "doc_id long, n_pieces long, ids_crc32 long, words_decode boolean, parity boolean")
