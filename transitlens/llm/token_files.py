"""Token ids as Arrow stream files of fixed-size lists.

A shard is one Arrow IPC stream file, uncompressed: batches of ``rows_per_batch`` sequences, each an ``input_ids`` list and an
``attention_mask`` list of exactly ``seq_len`` items. Documents lie end to end; only the last sequence of a shard is padded, with
mask false there. Every batch but the last has the same number of rows, so sequence ``i`` of a memory-mapped shard is a slice of one
batch's flat values: no copy, no parse; masks take a bit an item. Beside each shard an index file (Arrow IPC too) holds a row per document: its id, the
first id's place in the shard and its length. Ids take 16 bits where the vocabulary allows, else 32.

Writing is one range exchange by document id and one pass over its partitions. Each attempt of a task writes files under a name of
its own, and the manifest, a Parquet table in the shared folder, names those of the attempt that Spark committed: a lost executor
costs a retry, never a torn or doubled shard. Shard offsets are running sums over the manifest, a row per shard.

Defined cases: a null text counts as empty and holds the end id alone; null ids come first; rows that repeat an id stay, in order
of their text's hash; an empty table gives a manifest without shards and reads back as an empty table.
"""

from __future__ import annotations

import json
import os
import string
import uuid
import zlib
from collections.abc import Iterable, Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import pyarrow.fs as pafs
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .chunks import CodeTable, Ragged, chunk_keys, chunk_of, sums
from .common import slices, text_or_empty

MANIFEST = "shard int, name string, n_docs long, n_ids long, n_sequences long"


@lru_cache(maxsize=2)
def tokenizer(path: str):
    os.environ["TOKENIZERS_PARALLELISM"] = "false"  # Spark runs a task on each core already
    from tokenizers import Tokenizer

    return Tokenizer.from_file(path)


def in_chunks(path: str) -> bool:
    """Whether chunks can be encoded apart: byte-level BPE with its own split, no normaliser, no added token with white space."""
    with open(path, encoding="utf-8") as f:
        spec = json.load(f)
    split = spec.get("pre_tokenizer") or {}
    plain = split.get("type") == "ByteLevel" and not split.get("add_prefix_space") and split.get("use_regex", True) and not spec.get("normalizer")
    added = all(not (set(x["content"]) & set(string.whitespace) or x["lstrip"] or x["rstrip"] or x["single_word"]) for x in spec.get("added_tokens", []))
    return plain and added and spec["model"]["type"] == "BPE"


class ChunkEncoder:
    """Encodes texts through the tokenizers library, each distinct chunk once; chunks met before come from a bounded table.

    New chunks go to the library many in one text, and as each token stands for a number of bytes, byte places tell whose it is. Where
    chunks cannot be encoded apart, texts go to the library whole.
    """

    def __init__(self, path: str, wide: bool, end_id: int):
        self.own, self.apart = tokenizer(path), in_chunks(path)
        self.kind = np.dtype("<u4" if wide else "<u2")
        self.end, self.table, self.ids = np.array([end_id], self.kind), CodeTable(), Ragged(self.kind)
        added = {i: len(x.content.encode("utf-8")) for i, x in self.own.get_added_tokens_decoder().items()}
        # The vocabulary has a character for each byte.
        self.bytes = np.zeros(max(self.own.get_vocab().values()) + 1, np.int64)
        for t, i in self.own.get_vocab().items():
            self.bytes[i] = added.get(i, len(t))

    def _learn(self, keys: list[str]) -> None:
        # Chunks that start with one space can follow each other; the others stand alone.
        joined = np.array([k[:1] != " " for k in keys])
        order = np.argsort(~joined, kind="stable")
        plain, odd = [k for k, j in zip(keys, joined, strict=True) if j], [chunk_of(k) for k, j in zip(keys, joined, strict=True) if not j]
        size = pc.binary_length(pa.array(plain + odd, pa.large_string())).to_numpy(zero_copy_only=False).astype(np.int64)
        size[: len(plain)] += 1
        texts = [" " + " ".join(plain[lo : lo + 256]) for lo in range(0, len(plain), 256)] + odd
        flat = np.concatenate([np.array(e.ids, self.kind) for lo in range(0, len(texts), 64) for e in self.own.encode_batch_fast(texts[lo : lo + 64], add_special_tokens=False)])
        starts, place = np.cumsum(size) - size, np.cumsum(self.bytes[flat])
        if place[-1:].sum() != size.sum():
            raise ValueError("tokens do not add up to the bytes of their texts")
        found = Ragged(self.kind)
        found.extend(flat, np.bincount(np.searchsorted(starts, place - self.bytes[flat], side="right") - 1, minlength=len(keys)))
        back = np.argsort(order)
        self.ids.extend(found.take(back), found.size[back])

    def encode(self, texts: list[str]) -> list[np.ndarray]:
        """Each text's ids, with the end id."""
        if not self.apart:
            return [np.append(np.array(e.ids, self.kind), self.end) for e in self.own.encode_batch_fast(texts, add_special_tokens=False)]
        if (kept := self.table.trim()) is not None:
            self.ids.keep(kept)
        codes, ends = self.table.codes(list(map(chunk_keys, texts)))
        if self.table.new:
            self._learn(self.table.new)
        flat, at = self.ids.take(codes), np.cumsum(sums(self.ids.size[codes], ends))
        # The end ids go in between.
        flat = np.insert(flat, at, self.end[0])
        return np.split(flat, (at + np.arange(1, at.size + 1))[:-1])


@lru_cache(maxsize=2)
def encoder(path: str, wide: bool, end_id: int) -> ChunkEncoder:
    """One for all tasks that a worker runs."""
    return ChunkEncoder(path, wide, end_id)


def sequence_schema(seq_len: int, wide: bool) -> pa.Schema:
    ids = pa.list_(pa.field("item", pa.uint32() if wide else pa.uint16(), nullable=False), seq_len)
    mask = pa.list_(pa.field("item", pa.bool_(), nullable=False), seq_len)
    return pa.schema([pa.field("input_ids", ids, nullable=False), pa.field("attention_mask", mask, nullable=False)])


INDEX = pa.schema([("doc_id", pa.int64()), ("at", pa.int64()), ("n_tokens", pa.int64())])


class ShardWriter:
    """Packs documents into one shard; holds at most a batch of sequences."""

    def __init__(self, fs: pafs.FileSystem, stem: str, seq_len: int, rows_per_batch: int, wide: bool):
        self.schema, self.kind = sequence_schema(seq_len, wide), np.uint32 if wide else np.uint16
        self.seq_len, self.need = seq_len, seq_len * rows_per_batch
        self.files = [fs.open_output_stream(f"{stem}.arrow"), fs.open_output_stream(f"{stem}.docs.arrow")]
        self.out, self.index = pa.ipc.new_stream(self.files[0], self.schema), pa.ipc.new_stream(self.files[1], INDEX)
        self.held: list[np.ndarray] = []
        self.n_held = self.n_ids = self.n_docs = self.n_sequences = 0

    def add(self, doc_ids: pa.Array, docs: list[np.ndarray]) -> None:
        n = np.array([d.size for d in docs], np.int64)
        self.index.write_batch(pa.RecordBatch.from_arrays([doc_ids, pa.array(self.n_ids + np.cumsum(n) - n), pa.array(n)], schema=INDEX))
        self.held += docs
        self.n_held += int(n.sum())
        self.n_ids += int(n.sum())
        self.n_docs += len(docs)
        if self.n_held >= self.need:
            flat = np.concatenate(self.held)
            whole = flat.size // self.need * self.need
            for lo in range(0, whole, self.need):
                self._write(flat[lo : lo + self.need], self.need)
            self.held, self.n_held = [flat[whole:]], flat.size - whole

    def _write(self, ids: np.ndarray, real: int) -> None:
        mask = np.arange(ids.size) < real
        lists = [pa.FixedSizeListArray.from_arrays(pa.array(v), type=f.type) for v, f in zip((ids, mask), self.schema, strict=True)]
        self.out.write_batch(pa.RecordBatch.from_arrays(lists, schema=self.schema))
        self.n_sequences += ids.size // self.seq_len

    def close(self) -> None:
        if self.n_held:
            flat = np.concatenate(self.held)
            self._write(np.pad(flat, (0, -flat.size % self.seq_len)).astype(self.kind), flat.size)
        for x in (self.out, self.index, *self.files):
            x.close()


def write_token_files(docs: DataFrame, tokenizer_path: str, folder: str, end_id: int = 2, seq_len: int = 2048, rows_per_batch: int = 64) -> DataFrame:
    """Writes ``docs(doc_id, text)`` under ``folder`` in ascending ``doc_id`` order; returns the manifest."""
    spark = docs.sparkSession
    wide = max(tokenizer(tokenizer_path).get_vocab_size(), end_id + 1) > 1 << 16
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_or_empty().alias("text"), F.xxhash64("text").alias("tie"))
    # The tie spreads rows that repeat an id; the row's own place in the scan spreads exact repeats.
    rows = rows.withColumn("place", F.monotonically_increasing_id())
    keys = [F.col("doc_id").asc_nulls_first(), "tie", "place"]
    rows = rows.repartitionByRange(*keys).sortWithinPartitions(*keys).select("doc_id", "text")

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own, out, name = encoder(tokenizer_path, wide, end_id), None, uuid.uuid4().hex
        shard = TaskContext.get().partitionId()
        for b in batches:
            for lo, hi, texts in slices(b.column(1)):
                if out is None:
                    fs, base = pafs.FileSystem.from_uri(folder)
                    fs.create_dir(base, recursive=True)
                    name = f"shard-{shard:06d}-{name}"
                    out = ShardWriter(fs, f"{base}/{name}", seq_len, rows_per_batch, wide)
                out.add(b.column(0).slice(lo, hi - lo), own.encode(texts))
        if out is not None:
            out.close()
            yield pa.RecordBatch.from_pydict({"shard": pa.array([shard], pa.int32()), "name": [name], "n_docs": [out.n_docs], "n_ids": [out.n_ids], "n_sequences": [out.n_sequences]})

    rows.mapInArrow(run, MANIFEST).write.mode("errorifexists").parquet(f"{folder}/manifest")
    return spark.read.schema(MANIFEST).parquet(f"{folder}/manifest")


class Shard:
    """A shard's sequences and documents; memory-mapped where the file is local, so that no id is copied."""

    def __init__(self, folder: str, name: str):
        fs, base = pafs.FileSystem.from_uri(folder)
        stem = f"{base}/{name}"
        local = isinstance(fs, pafs.LocalFileSystem)
        self.source = pa.memory_map(f"{stem}.arrow") if local else fs.open_input_stream(f"{stem}.arrow")
        self.batches = list(pa.ipc.open_stream(self.source))
        self.per_batch = self.batches[0].num_rows
        self.seq_len = self.batches[0].schema.field("input_ids").type.list_size
        with fs.open_input_stream(f"{stem}.docs.arrow") as f:
            self.docs = pa.ipc.open_stream(f).read_all()

    def __len__(self) -> int:
        return sum(b.num_rows for b in self.batches)

    def _flat(self, batch: int) -> np.ndarray:
        return self.batches[batch].column(0).values.to_numpy(zero_copy_only=True)

    def sequence(self, i: int) -> tuple[np.ndarray, pa.BooleanArray]:
        """Ids and mask (bits) of sequence ``i``: views into the file."""
        b, r = divmod(i, self.per_batch)
        at = r * self.seq_len
        return self._flat(b)[at : at + self.seq_len], self.batches[b].column(1).values.slice(at, self.seq_len)

    def ids(self, at: int, n: int) -> Iterator[np.ndarray]:
        """The ids from place ``at``, as views, one for each batch touched."""
        per = self.per_batch * self.seq_len
        while n > 0:
            b, r = divmod(at, per)
            got = self._flat(b)[r : r + n]
            yield got
            at += got.size
            n -= got.size


def _shard_starts(manifest: DataFrame) -> DataFrame:
    """The manifest (a row per shard) with the ids of all shards before each."""
    before = Window.orderBy("shard").rowsBetween(Window.unboundedPreceding, -1)
    return manifest.withColumn("base", F.coalesce(F.sum("n_ids").over(before), F.lit(0)))


def read_token_files(spark: SparkSession, folder: str) -> DataFrame:
    """``(doc_id, start, n_tokens, ids_crc32)`` per document, read from the files."""
    manifest = spark.read.schema(MANIFEST).parquet(f"{folder}/manifest")
    n = max(1, manifest.count())
    shards = _shard_starts(manifest).select("name", "base").repartition(n, "name")

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for name, base in zip(*map(pa.Array.to_pylist, b.columns), strict=True):
                shard = Shard(folder, name)
                for d in shard.docs.to_batches(max_chunksize=4096):
                    crc = []
                    for at, size in zip(d.column(1).to_pylist(), d.column(2).to_pylist(), strict=True):
                        c = 0
                        for part in shard.ids(at, size):
                            c = zlib.crc32(part.astype("<u4").data, c)
                        crc.append(c)
                    yield pa.RecordBatch.from_arrays([d.column(0), pa.array(d.column(1).to_numpy() + base), d.column(2), pa.array(crc, pa.int64())], names=["doc_id", "start", "n_tokens", "ids_crc32"])

    return shards.mapInArrow(run, "doc_id long, start long, n_tokens long, ids_crc32 long")
