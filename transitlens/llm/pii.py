"""Personal data: patterns, and terms that give a person away; DataFrame functions only.

Base spans come from four patterns with their checks. A protected entity is a base match, normalised. Beside it, terms of its texts may
reveal it: over the distinct texts of the corpus, the pointwise mutual information of a term and an entity in the same text is held
against the entity's own information content. A term that gives at least ``alpha`` of it is a disclosing term wherever a text holds
that entity. How many texts that takes follows from the counts: a bound of how likely so many common texts are by chance must not
exceed ``chance``, so one text is enough for a rare term and a rare entity in a corpus of some hundreds of texts. Base spans are
generalised to a label of their kind, disclosing terms are removed.

Patterns are written so that Java's matcher neither backtracks without bound nor recurses on long runs: runs are taken whole
(possessive), and a run is tried from its start or from the end of the last match only. Matches are the same as those of the plain
patterns. Offsets are code points: a text is split at the matches, and lengths of gaps and matches add up.

Work: one pass over the texts writes narrow rows of spans, with the words of those texts that have any; entity and term counts are
partial sums; a second pass counts the terms that may be rare enough, a third places disclosing terms in their texts.

Defined cases: a null or empty text has no spans; rows equal in id and text each get the same spans; a null id is an id of its own;
an empty table gives an empty table; other columns are ignored (:func:`personal_spans`) or kept (:func:`sanitised_rows`).
"""

from __future__ import annotations

import math
from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import text_or_empty, written

#: The kinds in order, each with its pattern; ``term`` comes last and has no pattern.
KINDS = ("email", "ip", "card", "phone", "term")
PATTERNS = {
    "email": r"(?:\G|(?<![A-Za-z0-9._%+-]))[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?:\G|(?<![0-9]))[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++",
    # Shorter runs fail the check anyway, at every start.
    "card": r"[0-9](?:[ -]?[0-9]){13,}+",
    "phone": r"\+[0-9][ ().0-9-]+[0-9]",
}
IP_PARTS = r"^(?:0*(?:25[0-5]|2[0-4][0-9]|1[0-9][0-9]|[1-9]?[0-9])(?:\.|$)){4}$"
LABELS = {"email": "[EMAIL]", "ip": "[IP]", "card": "[CARD]", "phone": "[PHONE]", "term": ""}
SPAN = "array<struct<start int, kind int, end int, text string>>"
#: A term: a run of letters, whole.
TERM = r"\p{L}{4,}+"
#: Rows of the table of term bits, of 64 bits each; hashes, and lists of terms or spans, up to which a table of them is broadcast.
BUCKETS, BROADCAST_HASHES, BROADCAST_LISTS = 1 << 20, 1_000_000, 30_000


def _digits(x: Column) -> Column:
    return F.regexp_replace(x, "[^0-9]", "")


def _valid(kind: str, x: Column) -> Column:
    if kind == "ip":
        return x.rlike(IP_PARTS)
    if kind == "card":
        return F.length(_digits(x)).between(14, 19) & F.call_function("luhn_check", F.substring(_digits(x), 1, 19))
    if kind == "phone":
        return F.length(_digits(x)).between(10, 15)
    return F.lit(True)


def _placed(text: Column, matches: Column, pattern: Column, kind: int, wanted: Callable[[Column], Column] | None = None) -> Column:
    """The matches, or the ``wanted`` ones of them, as spans."""
    gaps = F.slice(F.split(text, pattern, -1), F.lit(1), F.size(matches))
    steps = F.zip_with(gaps, matches, lambda g, m: F.struct(F.length(g).alias("gap"), m.alias("m")))
    start = F.struct(F.lit(0).alias("at"), F.array().cast(SPAN).alias("out"))

    def step(acc: Column, s: Column) -> Column:
        lo = acc["at"] + s["gap"]
        hi = lo + F.length(s["m"])
        span = F.struct(lo.alias("start"), F.lit(kind).alias("kind"), hi.alias("end"), s["m"].alias("text"))
        out = F.concat(acc["out"], F.array(span)).cast(SPAN)
        if wanted is not None:
            out = F.when(wanted(s["m"]), out).otherwise(acc["out"])
        return F.struct(hi.alias("at"), out.alias("out"))

    placed = F.aggregate(steps, start, step, lambda acc: acc["out"])
    return F.when(F.size(matches) > 0, placed).otherwise(F.array().cast(SPAN))


def with_base_spans(rows: DataFrame) -> DataFrame:
    """``rows`` with ``_spans``, the checked matches of ``_text`` in order of start and kind."""
    for kind in PATTERNS:
        hint = {"email": "@", "phone": "+", "ip": "."}.get(kind)
        found = F.regexp_extract_all("_text", F.lit(PATTERNS[kind]), F.lit(0))
        rows = rows.withColumn(f"_{kind}", F.when(F.contains("_text", F.lit(hint)), found).otherwise(F.array().cast("array<string>")) if hint else found)

    def checked(kind: str) -> Column:
        return F.filter(_placed(F.col("_text"), F.col(f"_{kind}"), F.lit(PATTERNS[kind]), KINDS.index(kind)), lambda s: _valid(kind, s["text"]))

    spans = [checked(kind) for kind in PATTERNS]
    return rows.withColumn("_spans", F.array_sort(F.concat(*spans))).drop(*(f"_{kind}" for kind in PATTERNS))


def _entity(span: Column) -> Column:
    """A match as a name for what it names."""
    email = span["kind"] == F.lit(KINDS.index("email"))
    ip = span["kind"] == F.lit(KINDS.index("ip"))
    return F.concat(span["kind"].cast("string"), F.lit(":"), F.when(email | ip, F.lower(span["text"])).otherwise(_digits(span["text"])))


def _lower_words(text: Column) -> Column:
    """The words of a text, lower-cased, as often as they stand there."""
    return F.transform(F.regexp_extract_all(text, F.lit(TERM), F.lit(0)), F.lower)


def _other_terms(text: Column, spans: Column) -> Column:
    """Distinct words of a text outside its base spans."""
    start = F.struct(F.lit(0).alias("at"), F.array().cast("array<string>").alias("out"))

    def step(acc: Column, s: Column) -> Column:
        gap = F.substring(text, acc["at"] + 1, F.greatest(s["start"] - acc["at"], F.lit(0)))
        return F.struct(F.greatest(acc["at"], s["end"]).alias("at"), F.concat(acc["out"], F.array(gap)).alias("out"))

    rest = F.aggregate(spans, start, step, lambda acc: F.concat(F.array_join(acc["out"], "\n"), F.lit("\n"), F.substring(text, acc["at"] + 1, F.length(text))))
    return F.array_distinct(_lower_words(rest))


def _rows(docs: DataFrame) -> DataFrame:
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_or_empty().alias("_text")).withColumn("_hash", F.xxhash64("_text"))


def _term_counts(docs: DataFrame, wanted: DataFrame) -> DataFrame:
    """``(term, t)`` of ``wanted(term)``: the distinct texts of ``docs`` that hold the term."""
    # One bit per hashed term, in a table of at most BUCKETS rows, keeps most other words from the shuffle however many are wanted.
    bucket, bit = F.pmod(F.xxhash64("term"), F.lit(BUCKETS)), F.pmod(F.shiftright(F.xxhash64("term"), 32), F.lit(64)).cast("int")
    bits = wanted.groupBy(bucket.alias("_b")).agg(F.bit_or(F.call_function("shiftleft", F.lit(1).cast("long"), bit)).alias("_bits"))
    words = _rows(docs).select("_hash", F.explode(F.array_distinct(_lower_words(F.col("_text")))).alias("term")).withColumn("_b", bucket)
    words = words.join(F.broadcast(bits), "_b").filter(F.call_function("shiftrightunsigned", F.col("_bits"), bit).bitwiseAND(F.lit(1).cast("long")) == 1)
    return words.select("_hash", "term").distinct().groupBy("term").agg(F.count("*").alias("t")).join(wanted, "term", "left_semi")


def disclosing_terms(found: DataFrame, docs: DataFrame, alpha: float = 0.9, chance: float = 0.01) -> DataFrame:
    """``(_hash, words)``: of each distinct text, the terms that disclose an entity it holds; written. ``found(_hash, entities, terms)``
    is a written row per document.

    Counts are of distinct texts: N of all, e of those with the entity, t with the term, et with both. With
    ``pmi = log(N * et / (e * t))`` a term discloses if ``pmi >= alpha * log(N / e)`` and ``et * (pmi - 1) >= log(1 / chance)``.
    """
    n = float(max(1, found.select("_hash").distinct().count()))
    texts = written(found.filter(F.size("entities") > 0).dropDuplicates(["_hash"]).select("_hash", "entities", "terms"), "pii-texts")
    held = texts.select("_hash", F.explode("entities").alias("entity"))
    # Entities of the same texts have the same counts with every term: they are one class.
    prints = held.groupBy("entity").agg(F.count("*").alias("e"), F.bit_xor("_hash").alias("x"), F.bit_xor(F.xxhash64("_hash")).alias("y"))
    classes = written(held.join(prints, "entity").select("_hash", "e", "x", "y").distinct(), "pii-classes")
    words = texts.select("_hash", F.explode("terms").alias("term"))

    def most(e: str) -> Column:
        """What t cannot exceed, as et is at most e."""
        return F.pow(F.col(e), F.lit(alpha)) * (n ** (1 - alpha) * (1 + 1e-9))

    # Texts with the term beside any entity are some of those that hold it, so this bounds t from below without reading a text.
    largest = classes.groupBy("_hash").agg(F.max("e").alias("e"))
    least = words.join(largest, "_hash").groupBy("term").agg(F.count("*").alias("least"), F.max("e").alias("e"))
    wanted = written(least.filter(F.col("least") <= most("e")).select("term"), "pii-terms")
    terms = written(_term_counts(docs, wanted), "pii-term-counts")
    pairs = written(words.join(terms, "term").join(classes, "_hash").filter(F.col("t") <= most("e")), "pii-pairs")
    pmi = F.log(F.lit(n) * F.col("et") / (F.col("e") * F.col("t")))
    told = pairs.groupBy("e", "x", "y", "term", "t").agg(F.count("*").alias("et"))
    told = told.filter((pmi >= alpha * F.log(F.lit(n) / F.col("e"))) & (F.col("et") * (pmi - 1) >= -math.log(chance)))
    return written(pairs.join(told.select("e", "x", "y", "term"), ["e", "x", "y", "term"], "left_semi").groupBy("_hash").agg(F.array_sort(F.collect_set("term")).alias("words")), "pii-disclosing")


def _some(rows: DataFrame, table: DataFrame, how: str) -> DataFrame:
    """``rows`` semi- or anti-joined to the hashes of ``table``, a written table, broadcast only where its counted rows are few."""
    hashes = table.select("_h").distinct()
    return rows.join(F.broadcast(hashes) if table.count() <= BROADCAST_HASHES else hashes, rows["_hash"] == hashes["_h"], how)


def _term_spans(docs: DataFrame, found: DataFrame, disclosing: DataFrame) -> DataFrame:
    """``(_id, _h, terms)``: spans of disclosing terms in the distinct documents that hold their entity; written."""
    per_doc = found.filter(F.size("entities") > 0).select("doc_id", "_hash").distinct().join(disclosing, "_hash")
    per_doc = written(per_doc.select(F.col("doc_id").alias("_id"), F.col("_hash").alias("_h"), "words"), "pii-doc-terms")
    few = F.broadcast(per_doc) if per_doc.count() <= BROADCAST_LISTS else per_doc
    rows = _some(_rows(docs), per_doc, "left_semi")
    rows = rows.join(few, rows["doc_id"].eqNullSafe(few["_id"]) & (rows["_hash"] == few["_h"])).dropDuplicates(["doc_id", "_hash"])
    rows = rows.withColumn("_m", F.regexp_extract_all("_text", F.lit(TERM), F.lit(0)))
    told = _placed(F.col("_text"), F.col("_m"), F.lit(TERM), KINDS.index("term"), lambda m: F.array_contains("words", F.lower(m)))
    return written(rows.select("_id", "_h", told.alias("terms")), "pii-term-spans")


def _found(docs: DataFrame) -> DataFrame:
    """A narrow row per document: its base spans, its entities, and the terms beside them; written."""
    terms = F.when(F.size("_spans") > 0, _other_terms(F.col("_text"), F.col("_spans"))).otherwise(F.array().cast("array<string>"))
    return written(with_base_spans(_rows(docs)).select("doc_id", "_hash", "_spans", F.array_distinct(F.transform("_spans", _entity)).alias("entities"), terms.alias("terms")), "pii-spans")


def _with_terms(rows: DataFrame, docs: DataFrame, found: DataFrame, alpha: float, chance: float) -> DataFrame:
    """``rows(doc_id, _hash, ...)`` with ``_terms``, the spans of disclosing terms."""
    none = F.array().cast(SPAN)
    disclosing = disclosing_terms(found, docs, alpha, chance)
    if disclosing.isEmpty():
        return rows.withColumn("_terms", none)
    terms = _term_spans(docs, found, disclosing)

    def joined(some: DataFrame, few: DataFrame) -> DataFrame:
        return some.join(few, some["doc_id"].eqNullSafe(few["_id"]) & (some["_hash"] == few["_h"]), "left").withColumn("_terms", F.coalesce("terms", none)).drop("_id", "_h", "terms")

    if terms.count() <= BROADCAST_LISTS:
        return joined(rows, F.broadcast(terms))
    # Only the rows of texts with terms are shuffled.
    return joined(_some(rows, terms, "left_semi"), terms).unionByName(_some(rows, terms, "left_anti").withColumn("_terms", none))


def _listed(spans: Column) -> Column:
    names = F.array(*map(F.lit, KINDS))
    return F.array_join(F.transform(spans, lambda s: F.concat(names[s["kind"]], F.lit(":"), s["start"].cast("string"), F.lit(":"), s["end"].cast("string"))), ",")


def personal_spans(docs: DataFrame, alpha: float = 0.9, chance: float = 0.01) -> DataFrame:
    """``(doc_id, n_email, n_ip, n_card, n_phone, base_sha256, spans, n_term)`` of each document."""
    found = _found(docs)
    rows = _with_terms(found.select("doc_id", "_hash", "_spans"), docs, found, alpha, chance)
    kinds = F.transform("_spans", lambda s: s["kind"])
    counts = [(F.size(kinds) - F.size(F.array_remove(kinds, F.lit(i)))).cast("long").alias(f"n_{KINDS[i]}") for i in range(4)]
    return rows.select("doc_id", *counts, F.sha2(_listed(F.col("_spans")), 256).alias("base_sha256"), _listed(F.array_sort(F.concat("_spans", "_terms"))).alias("spans"), F.size("_terms").cast("long").alias("n_term"))


def _replaced(text: Column, spans: Column) -> Column:
    """``text`` with a label for each span; what overlaps an earlier span falls under that one's label."""
    labels = F.array(*(F.lit(LABELS[k]) for k in KINDS))
    start = F.struct(F.lit(0).alias("at"), F.array().cast("array<string>").alias("out"))

    def step(acc: Column, s: Column) -> Column:
        part = F.concat(F.substring(text, acc["at"] + 1, s["start"] - acc["at"]), labels[s["kind"]])
        out = F.when(s["start"] >= acc["at"], F.concat(acc["out"], F.array(part))).otherwise(acc["out"])
        return F.struct(F.greatest(acc["at"], s["end"]).alias("at"), out.alias("out"))

    return F.aggregate(spans, start, step, lambda acc: F.concat(F.array_join(acc["out"], ""), F.substring(text, acc["at"] + 1, F.length(text))))


def sanitised_rows(docs: DataFrame, alpha: float = 0.9, chance: float = 0.01) -> DataFrame:
    """``docs``, all columns and rows, with ``text`` sanitised; a null text stays null."""
    found = _found(docs)
    marked = docs.select(F.struct("*").alias("row"), F.col("doc_id").cast("long").alias("doc_id"), text_or_empty().alias("_text")).withColumn("_hash", F.xxhash64("_text"))
    rows = _with_terms(with_base_spans(marked), docs, found, alpha, chance)
    spans = F.array_sort(F.concat("_spans", "_terms"))
    clean = F.when(F.size("_spans") + F.size("_terms") > 0, _replaced(F.col("_text"), spans)).otherwise(F.col("row.text"))
    return rows.withColumn("_clean", clean).select(*(F.col("_clean").alias(c) if c == "text" else F.col(f"row.`{c}`").alias(c) for c in docs.columns))
