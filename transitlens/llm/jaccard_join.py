"""Documents whose 5-word shingle sets have a Jaccard similarity of at least 0.8, joined by parity sketches.

A document's shingles are hashed; a hash picks a block and toggles one of its bits. Two sketches of the same number of blocks
differ in at most as many blocks, and bits, as there are shingles in one set only. A block has a bit for every hash there is, so that
blocks of few shingles do not agree by chance; the XOR of the hashes whose bits are set stands for them. Sets of sizes a and b that
link differ by at most ``(a + b) * (1 - s) / (1 + s)`` shingles, D say, so of m blocks at least m - D are equal: documents meet in a
shared block value.

Sizes fall into bands (powers of two), each with a number of blocks of its own, somewhat above D; a document also takes part in the
next band if a partner there can be similar enough. In any order of the block values that is the same for all documents, the first
D + 1 of a document's m values suffice: two documents with m - D common values share one of those (prefix filtering). The order is by
hash, empty blocks last. Values that many documents carry are counted over all documents; documents that carry some move all such
values to the end of the order and carry later values instead, which changes nothing for the others. So documents that share a passage
and little more do not meet by it. Of a value five bytes are kept, and documents meet through packed blocks (:mod:`key_groups`): a
few documents that share no value meet as well, and are compared.

Each document also has one parity sketch of its whole set, some bits for each shingle it may differ by. Pairs whose sketches differ in
more bits than D cannot link.

Equal sets are one class from the start, so copies cost a row each and nothing more. Members of a group of equal block values first
meet its smallest member, one pair for each document, and verified links form components; a pair inside one component changes no
result. Groups that still hold two components are compared in tiles of bounded size (:mod:`group_compare`): sketches of different
components within a task, and only pairs that may link leave it. Of large groups each component's nearest pair goes first, as the links
found leave little for the last round, which compares all that is left. Every pair that could link two components is compared, on whole
shingle sets.

Defined cases: null or empty texts, and texts without words, have no shingles and link with nothing; fewer than five words are one
shingle; a row that repeats an id is a document of its own, linked by its own text; an empty table gives an empty table; other
columns are ignored (:func:`jaccard_components`) or kept (:func:`one_of_each_group`, which decides by id and text, so rows that repeat
both, and rows with a null id, are copies as any other).
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import drop_written, slices, text_or_empty, written
from .components import connected_components
from .group_compare import near_in_groups
from .key_groups import KEY_BYTES, bitmaps, frequent, low_bytes, meetings

N = 5
#: Similarity as a fraction: 100 * intersection >= PERCENT * union.
PERCENT = 80
#: Blocks beyond D + 1, as a share of D: room to leave out values that many documents carry.
SPARE = 0.4
#: Documents above which a value counts as one of many; members above which a group's components offer their nearest pairs first.
MANY, GROUP = 8, 48
#: Rounds in which components of large groups offer their nearest pair, before the last.
OFFERS = 1
#: A table of ids of at most so many rows is broadcast; above, Spark shuffles.
BROADCAST_IDS = 400_000

_MIX = [np.uint64(x) for x in (0x9E3779B97F4A7C15, 0xBF58476D1CE4E5B9, 0x94D049BB133111EB, 0xD6E8FEB86659FD93, 0xA0761D6478BD642F)]


def _mixed(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * _MIX[1]
    x = (x ^ (x >> np.uint64(27))) * _MIX[2]
    return x ^ (x >> np.uint64(31))


class _Hashes(dict):
    def __missing__(self, word: bytes) -> int:
        self[word] = h = xxhash.xxh3_64_intdigest(word)
        return h


class Shingler:
    """Shingle hashes and sketch keys of texts; one for each task."""

    def __init__(self, n: int = N, percent: int = PERCENT, most_words: int = 500_000):
        self.n, self.percent, self.most_words, self.hashes = n, percent, most_words, _Hashes()

    def shingles(self, text: str) -> np.ndarray:
        """Sorted distinct hashes of the text's shingles."""
        words = text.encode("utf-8").lower().split()
        if len(self.hashes) > self.most_words:
            self.hashes.clear()
        w = np.fromiter(map(self.hashes.__getitem__, words), np.uint64, len(words))
        if not w.size:
            return w
        k = min(self.n, w.size)
        h = np.full(w.size - k + 1, k, np.uint64)
        for i in range(k):
            h = (h ^ w[i : w.size - k + 1 + i]) * _MIX[i % len(_MIX)]
            h ^= h >> np.uint64(29)
        return np.unique(_mixed(h))

    def most_apart(self, a: int, b: int) -> int:
        """The largest symmetric difference of linked sets of these sizes."""
        return (a + b) * (100 - self.percent) // (100 + self.percent)

    def keys(self, h: np.ndarray) -> list[tuple[np.ndarray, int]]:
        """For each band in which a set may have partners: its block values, hashed with band and block, in order, and how many of
        them it carries."""
        a = h.size
        if a == 0:
            return []
        band = a.bit_length() - 1
        found = [self._keys(h, band)]
        if a * 100 >= self.percent << (band + 1):
            found.append(self._keys(h, band + 1))
        return [x for x in found if x[1]]

    def _keys(self, h: np.ndarray, band: int) -> tuple[np.ndarray, int]:
        a, top = h.size, (2 << band) - 1
        apart = self.most_apart(a, min(a * 100 // self.percent, top))
        if apart == 0:
            return h[:0], 0  # only an equal set links
        most = self.most_apart(top, top)
        blocks = most + 1 + int(np.ceil(most * SPARE))
        block = ((h >> np.uint64(32)) * np.uint64(blocks) >> np.uint64(32)).astype(np.int64)
        start = np.flatnonzero(np.append(True, block[1:] != block[:-1]))
        value = np.zeros(blocks, np.uint64)
        # A block's bits are as many as there are hashes: few are set, and the XOR of those hashes stands for them.
        value[block[start]] = np.bitwise_xor.reduceat(_mixed(h), start)
        key = _mixed(_mixed(value) ^ (np.arange(blocks, dtype=np.uint64) << np.uint64(8) | np.uint64(band))) >> np.uint64(64 - 8 * KEY_BYTES)
        order = np.lexsort((key, value == 0))
        # Documents differ in at most ``apart`` blocks, so apart + 1 values suffice; a band has more blocks than that.
        return key[order], apart + 1

    def sketch(self, h: np.ndarray) -> np.ndarray:
        """The parity sketch of a whole set, in a power of two of 64-bit words; folding its halves gives the next smaller one."""
        bits = max(64, 4 << (max(1, h.size).bit_length() - 1))
        odd = np.bincount((h >> np.uint64(6) & np.uint64(bits - 1)).astype(np.int64), minlength=bits) & 1
        return np.packbits(odd.astype(np.uint8)).view(np.int64)


def _lists(parts: list[np.ndarray], kind: type) -> pa.ListArray:
    ends = np.cumsum([0, *map(len, parts)]).astype(np.int32)
    return pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate(parts).view(kind)))


def _print(h: np.ndarray) -> np.ndarray:
    return np.frombuffer(xxhash.xxh3_128_digest(h.tobytes()), "<i8")


def _sketches(rows: DataFrame, n: int, percent: int) -> DataFrame:
    """``rows(doc_id, text, text_hash)`` to ``(doc_id, text_hash, n_shingles, fp1, fp2, keys, held, carried, sketch)``; the fingerprint is
    a 128-bit hash of the set, ``keys`` has the values of all bands, ``held`` how many each band has and ``carried`` how many of them
    count at first."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = Shingler(n, percent)
        for b in batches:
            for lo, hi, texts in slices(b.column(1)):
                sets = [own.shingles(t) for t in texts]
                prints = np.array([_print(h) for h in sets])
                keys = [own.keys(h) for h in sets]
                packed = [low_bytes(np.concatenate([h[:0], *(k for k, _ in found)]), KEY_BYTES).tobytes() for h, found in zip(sets, keys, strict=True)]
                ends = pa.array(np.cumsum([0, *map(len, keys)]).astype(np.int32))
                yield pa.RecordBatch.from_arrays(
                    [
                        b.column(0).slice(lo, hi - lo),
                        b.column(2).slice(lo, hi - lo),
                        pa.array([h.size for h in sets], pa.int64()),
                        pa.array(np.ascontiguousarray(prints[:, 0])),
                        pa.array(np.ascontiguousarray(prints[:, 1])),
                        pa.array(packed, pa.binary()),
                        pa.ListArray.from_arrays(ends, pa.array([k.size for found in keys for k, _ in found] or [0], pa.int32())),
                        pa.ListArray.from_arrays(ends, pa.array([c for found in keys for _, c in found] or [0], pa.int32())),
                        _lists([own.sketch(h) for h in sets], np.int64),
                    ],
                    names=["doc_id", "text_hash", "n_shingles", "fp1", "fp2", "keys", "held", "carried", "sketch"],
                )

    return rows.mapInArrow(run, "doc_id long, text_hash long, n_shingles long, fp1 long, fp2 long, keys binary, held array<int>, carried array<int>, sketch array<long>")


def _sets(rows: DataFrame, n: int, percent: int) -> DataFrame:
    """``rows(doc_id, text)`` to ``(fp1, fp2, shingles)``."""

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = Shingler(n, percent)
        for b in batches:
            for _, _, texts in slices(b.column(1)):
                sets = [own.shingles(t) for t in texts]
                prints = np.array([_print(h) for h in sets])
                yield pa.RecordBatch.from_arrays([pa.array(np.ascontiguousarray(prints[:, 0])), pa.array(np.ascontiguousarray(prints[:, 1])), _lists(sets, np.int64)], names=["fp1", "fp2", "shingles"])

    return rows.mapInArrow(run, "fp1 long, fp2 long, shingles array<long>")


def _can_link(a: Column, b: Column, percent: int) -> Column:
    return (100 * a >= percent * b) & (100 * b >= percent * a)


def _bits_apart(a: Column, b: Column) -> Column:
    """Hamming distance of two sketches; the longer one, of the next band, is folded."""

    def folded(x: Column, other: Column) -> Column:
        half = F.floor(F.size(x) / 2).cast("int")
        return F.when(F.size(x) > F.size(other), F.zip_with(F.slice(x, F.lit(1), half), F.slice(x, half + 1, half), lambda p, q: p.bitwiseXOR(q))).otherwise(x)

    return F.aggregate(F.zip_with(folded(a, b), folded(b, a), lambda p, q: F.bit_count(p.bitwiseXOR(q))), F.lit(0), lambda acc, x: acc + x)


def _near(pairs: DataFrame, nodes: DataFrame, percent: int) -> DataFrame:
    """Those of ``pairs(u, v)`` whose sizes and sketches allow a link, from ``nodes(node, size, sketch)``; written."""
    for end in "uv":
        pairs = pairs.join(nodes.select(F.col("node").alias(end), F.col("size").alias(f"n{end}"), F.col("sketch").alias(f"s{end}")), end)
    most = F.floor((F.col("nu") + F.col("nv")) * (100 - percent) / (100 + percent) + 1e-9)
    return written(pairs.filter(_can_link(F.col("nu"), F.col("nv"), percent) & (_bits_apart(F.col("su"), F.col("sv")) <= most)).select("u", "v"), "jaccard-near")


def _verified(pairs: DataFrame, docs: DataFrame, classes: DataFrame, n: int, percent: int) -> DataFrame:
    """Those of ``pairs(u, v)``, a written table, whose sets link; written. Texts are read of the documents in pairs only."""
    if pairs.isEmpty():
        return pairs
    ends = pairs.select(F.col("u").alias("node")).union(pairs.select("v")).distinct()
    ids = written(ends.join(classes, "node").select("node", "low", "fp1", "fp2"), "jaccard-ends")
    count = ids.count()
    few = F.broadcast(ids) if count <= BROADCAST_IDS else ids
    low = few.select(F.col("low").alias("_low")).distinct()
    texts = docs.join(F.broadcast(low) if count <= BROADCAST_IDS else low, docs["doc_id"].eqNullSafe(low["_low"]), "left_semi")
    sets = written(_sets(texts, n, percent).join(few, ["fp1", "fp2"]).select("node", "shingles"), "jaccard-sets")
    if sets.count() > count:  # rows that repeat both id and text
        sets = sets.dropDuplicates(["node"])
    left, right = (sets.select(F.col("node").alias(x), F.col("shingles").alias(f"s{x}")) for x in "uv")
    both = pairs.join(left, "u").join(right, "v")
    common = F.size(F.array_intersect("su", "sv"))
    linked = 100 * common >= percent * (F.size("su") + F.size("sv") - common)
    links = written(both.filter(linked).select("u", "v"), "jaccard-links")
    drop_written(sets)
    return links


def _labelled(rows: DataFrame, labels: DataFrame, node: str, name: str) -> DataFrame:
    """``rows`` with the component of column ``node`` as ``name``; a node without a link is its own."""
    found = labels.select(F.col("node").alias(node), F.col("component").alias("_c"))
    return rows.join(found, node, "left").withColumn(name, F.coalesce("_c", node)).drop("_c")


def _few(table: DataFrame) -> DataFrame:
    """A written table, broadcast only where its counted rows are few."""
    return F.broadcast(table) if table.count() <= BROADCAST_IDS else table


def _meetings(sketches: DataFrame, classes: DataFrame) -> DataFrame:
    """``(key, node, center)``: the groups in which documents of ``sketches(row_id, keys, held, carried)`` meet that are a ``node`` of
    ``classes``."""
    rows = sketches.withColumnRenamed("row_id", "node").select("node", "keys", "held", "carried")
    first = bitmaps(classes.select("node"))
    if first is None:
        rows = rows.join(classes.select("node"), "node", "left_semi")
    met = written(meetings(rows, first).drop("new"), "jaccard-groups")
    counts = written(met.groupBy("key").agg(F.count("*").alias("count")).filter(F.col("count") > MANY), "jaccard-many")
    moved, many = frequent(counts)
    if not many.size:
        return met
    # Two documents of which one carries no such value share another one already, so only those that do meet anew.
    late = written(meetings(rows, first, many), "jaccard-late")
    fresh = late.groupBy("key").agg(F.max("new").alias("new")).filter("new").select("key")
    anew = written(met.join(_few(moved), "key", "left_anti").unionByName(late.join(fresh, "key", "left_semi").drop("new")), "jaccard-met")
    for table in (met, late):
        drop_written(table)
    return anew


def _class_components(sketches: DataFrame, classes: DataFrame, docs: DataFrame, n: int, percent: int) -> DataFrame:
    """``(node, component)`` of the classes (a row per distinct set) that link with another."""
    # Where the ids are few they are broadcast, so that the sketches stay where they are.
    first_rows = sketches.join(_few(classes.select(F.col("node").alias("row_id"))), "row_id", "left_semi").withColumnRenamed("row_id", "node")
    nodes = first_rows.select("node", F.col("n_shingles").cast("int").alias("size"), "sketch")
    met = _meetings(sketches, classes)

    first = met.filter("node <> center").groupBy(F.col("node").alias("v")).agg(F.min("center").alias("u")).select("u", "v")
    tested = _near(first, nodes, percent)
    links = _verified(tested, docs, classes, n, percent)
    labels = connected_components(links)

    for offer in range(OFFERS + 1):
        named = _labelled(met.select("key", "node"), labels, "node", "component")
        parts = [F.bit_xor(F.xxhash64(F.lit(i), "node")).alias(f"h{i}") for i in range(2)]
        mixed = named.groupBy("key").agg(F.min("component").alias("a"), F.max("component").alias("b"), F.count("*").alias("members"), *parts).filter("a <> b")
        if offer:
            mixed = mixed.filter(F.col("members") > GROUP)
        # Of groups with the same members one is enough.
        mixed = written(mixed.groupBy("members", "h0", "h1").agg(F.min("key").alias("key")).select("key", "members"), "jaccard-mixed")
        if mixed.isEmpty():
            break
        rows = named.join(_few(mixed), "key").join(nodes, "node")
        rows = rows.withColumn("offer", (F.col("members") > GROUP) & F.lit(offer < OFFERS))
        near = written(near_in_groups(rows, percent).distinct(), "jaccard-late-near")
        if near.isEmpty():  # so there is nothing left in large groups either
            break
        pairs = written(near.join(tested, ["u", "v"], "left_anti"), "jaccard-late-pairs")
        found = _verified(pairs, docs, classes, n, percent)
        tested = tested.unionByName(pairs)
        if not found.isEmpty():
            links = links.unionByName(found)
            labels = connected_components(links)
    return labels


def _text_hash() -> Column:
    return F.xxhash64(text_or_empty())


def _row_components(docs: DataFrame, n: int, percent: int) -> DataFrame:
    """``(doc_id, text_hash, n_shingles, component, component_id)`` of each document; ``component`` is null without shingles, and tells
    components apart that have the same smallest id."""
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_or_empty().alias("text"))
    hashed = rows.withColumn("text_hash", _text_hash())
    # Written once, so the row ids are settled.
    sketches = written(_sketches(hashed, n, percent).withColumn("row_id", F.monotonically_increasing_id()), "jaccard-sketches")
    full = sketches.filter("n_shingles > 0")
    classes = written(full.groupBy("fp1", "fp2").agg(F.min("row_id").alias("node"), F.min(F.struct("row_id", "doc_id"))["doc_id"].alias("low"), F.min("doc_id").alias("least")), "jaccard-classes")
    labels = _class_components(sketches, classes, rows, n, percent)
    named = _labelled(classes.select("fp1", "fp2", "node", "least"), labels, "node", "component")
    least = named.groupBy("component").agg(F.min("least").alias("component_id"))
    named = named.join(least, "component").select("fp1", "fp2", "component", "component_id")
    out = sketches.select("doc_id", "text_hash", "n_shingles", "fp1", "fp2").join(named, ["fp1", "fp2"], "left")
    return out.select("doc_id", "text_hash", "n_shingles", "component", F.coalesce("component_id", "doc_id").alias("component_id"))


def jaccard_components(docs: DataFrame, n: int = N, percent: int = PERCENT) -> DataFrame:
    """``(doc_id, n_shingles, component_id)`` of each document; the id is the smallest ``doc_id`` reachable by links."""
    return _row_components(docs, n, percent).select("doc_id", "n_shingles", "component_id")


def one_of_each_group(docs: DataFrame, n: int = N, percent: int = PERCENT) -> DataFrame:
    """One row of each component of ``docs``, all columns: of the smallest id, null last, then of the smallest hash of the text, then of
    the smallest text of the row; documents without words stay."""
    found = _row_components(docs, n, percent).filter("component IS NOT NULL")
    found = written(found.groupBy("component", "doc_id", "text_hash").agg(F.count("*").alias("n")), "jaccard-components")
    key = F.struct(F.col("doc_id").isNull().alias("no_id"), "doc_id", "text_hash")
    first = found.groupBy("component").agg(F.min(key).alias("first"))
    # Rows of equal id and text are in one component, so these two name a row up to its repeats.
    told = found.join(first, "component").select(F.col("doc_id").alias("_i"), F.col("text_hash").alias("_t"), key.eqNullSafe(F.col("first")).alias("stays"), "n")
    told = written(told.filter("NOT stays OR n > 1"), "jaccard-told")
    few = F.broadcast(told) if told.count() <= BROADCAST_IDS else told
    rows = docs.select(F.struct("*").alias("row"), F.col("doc_id").cast("long").alias("_id"), _text_hash().alias("_hash"))
    same = rows["_id"].eqNullSafe(few["_i"]) & (rows["_hash"] == few["_t"])
    others = rows.join(few, same, "left_anti").select("row")
    repeated = rows.join(few.filter("stays"), same, "left_semi").groupBy("_id", "_hash").agg(F.min_by("row", F.to_json("row")).alias("row")).select("row")
    return others.unionByName(repeated).select("row.*")
