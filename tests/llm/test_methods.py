"""The methods of the corpus operators against plain versions of themselves, and their defined cases."""

import math
import random
import re
import struct

import numpy as np
import pytest
import sentencepiece
from pyspark.sql import functions as F

from transitlens.llm import pii, quality_model, topk_search
from transitlens.llm.common import written
from transitlens.llm.piece_tokenizer import PieceCodec
from transitlens.llm.quality_rules import judge_documents
from transitlens.llm.topk_search import top_k
from transitlens.llm.url_filters import propagated

draw = random.Random(21)


def best_of(rows, k):
    """Rows are (id, vector); every row with an id divisible by 3 asks."""
    whole = [(i, [math.floor(256 * v) for v in x]) for i, x in rows]
    out = []
    for a, (i, x) in enumerate(whole):
        if i % 3 == 0:
            scores = sorted((-sum(p * q for p, q in zip(x, y, strict=True)), j) for b, (j, y) in enumerate(whole) if a != b)[:k]
            out += [(i, n + 1, j, min(max(-s, -(2**63)), 2**63 - 1)) for n, (s, j) in enumerate(scores)]
    return sorted(out)


@pytest.mark.parametrize("scale", [1.0, 1e9])
def test_top_k_is_exact_for_all_finite_vectors(spark, monkeypatch, scale):
    monkeypatch.setattr(topk_search, "TILE", 20)
    monkeypatch.setattr(topk_search, "BLOCK", 4)
    rows = [(draw.randrange(60), [draw.choice([draw.uniform(-1, 1), draw.uniform(-1, 1) * scale]) for _ in range(6)]) for _ in range(70)]
    table = spark.createDataFrame([(i, x, "clash") for i, x in rows], "vec_id long, embedding array<double>, score string")
    assert sorted(map(tuple, top_k(table, F.col("vec_id") % 3 == 0, 4).collect())) == best_of(rows, 4)


def test_top_k_beyond_64_bits(spark):
    rows = [(0, [1e30, 0.5]), (3, [2e12, -1.0]), (4, [1.0, 1.0]), (5, [-1e30, 1.0]), (6, [float("inf"), 1.0])]
    got = sorted(map(tuple, top_k(spark.createDataFrame(rows, "vec_id long, embedding array<double>"), F.col("vec_id") == 0).collect()))
    assert got == [(0, 1, 3, 2**63 - 1), (0, 2, 4, 2**63 - 1), (0, 3, 5, -(2**63))]


def plain_statistics(text):
    words = [w for w in re.split(r"[\x20\x09-\x0D]+", text) if w]
    lines = [x for x in text.split("\n") if x.strip(" ")]
    n = len(text)

    def share(a, b):
        return a / b if b else 0.0

    def chars(some):
        return share(sum(c in some for c in text), n)

    upper = "ABCDEFGHIJKLMNOPQRSTUVWXYZ"
    return [len(words), share(sum(c not in " \n\t\r\x0b\x0c" for c in text), len(words)), chars("#*$%&|<>"), chars(upper), chars("0123456789"), chars("!?"), chars(".,;:"), chars("|"), share(len(set(words)), len(words)), share(len(set(lines)), len(lines)), share(len(words), len(lines))]


def test_statistics_and_the_compiled_column(spark):
    texts = ["", " \n \n", "One two!\nOne two!\n", "a|b #1 éÉ\t x" * 7, "w " * 5000, *("".join(draw.choice("aB1 .\n|#?") for _ in range(draw.randint(0, 80))) for _ in range(200))]
    rows = quality_model.with_text_statistics(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string"))
    x = np.array([plain_statistics(t) for t in texts], float)
    got = {r.doc_id: [r[n] for n in quality_model.NAMES] for r in rows.collect()}
    assert all(got[i] == pytest.approx(x[i].tolist()) for i in range(len(texts)))
    y = (x[:, 2] > 0.1).astype(float)
    model = quality_model.fit_rules(np.repeat(x, 3, axis=0), np.repeat(y, 3))
    assert model.rules
    scored = {r.doc_id: r.s for r in rows.select("doc_id", model.score().alias("s")).collect()}
    exact = np.array([got[i] for i in range(len(texts))])
    assert [scored[i] for i in range(len(texts))] == pytest.approx(model.score_rows(exact).tolist())


def test_training_rows_are_bounded_and_repeats_train_once(spark):
    docs = spark.createDataFrame([(i % 400, f"text {i}") for i in range(1200)], "doc_id long, text string")
    labels = spark.createDataFrame([(i, i % 2) for i in range(400)] * 3, "doc_id long, quality int")
    stats = quality_model.with_statistics(docs)
    x, y = quality_model.training_rows(stats, labels, 100)
    assert 20 < len(y) <= 100 and x.shape[1] == len(quality_model.NAMES)
    assert len(quality_model.training_rows(stats, labels, 10_000)[1]) == sum(1 for i in range(400) if __import__("zlib").crc32(str(i).encode()) % 5)


def test_hosts_are_rejected_by_the_rule_most_of_their_documents_fail(spark):
    def prose(n):
        return " ".join(draw.choice(["river", "stone", "cloud", "tree", "lamp"]) + str(draw.randrange(900)) for _ in range(n))

    rows = [(i, prose(60), "good") for i in range(60)]
    rows += [(100 + i, " ".join(w + "##########" for w in prose(40).split()), "symbols") for i in range(60)]  # no base rule fails
    rows += [(200 + i, "short", "small") for i in range(2)] + [(300 + i, prose(60) if i % 3 else "short", "mixed") for i in range(60)]
    got = {r.doc_id: r for r in judge_documents(spark.createDataFrame(rows, "doc_id long, text string, source string")).collect()}
    assert all(got[i].kept for i in range(60)) and not any(got[100 + i].kept or got[100 + i].base_failed for i in range(60))
    assert all(got[300 + i].kept == bool(i % 3) for i in range(60)) and not got[200].host_rejected  # two documents tell too little


def terms_brute(texts, alpha=0.9, chance=0.01):
    """Term spans of distinct texts, from the definition."""
    entity = re.compile(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+")
    term = re.compile(r"[^\W\d_]{4,}")
    distinct = set(texts)
    n = len(distinct)
    words = {t: {w.lower() for w in term.findall(t)} for t in distinct}
    beside = {t: {w.lower() for w in term.findall(entity.sub("\n", t))} for t in distinct}
    held = {t: {m[0].lower() for m in entity.finditer(t)} for t in distinct}
    out = {}
    for t in distinct:
        told = set()
        for e in held[t]:
            with_e = [x for x in distinct if e in held[x]]
            for w in beside[t]:
                count = sum(w in words[x] for x in distinct)
                both = sum(w in beside[x] for x in with_e)
                pmi = math.log(n * both / (len(with_e) * count))
                if pmi >= alpha * math.log(n / len(with_e)) - 1e-12 and both * (pmi - 1) >= -math.log(chance) - 1e-12:
                    told.add(w)
        out[t] = [(m.start(), m.end()) for m in term.finditer(t) if m[0].lower() in told]
    return out


def test_disclosing_terms_by_brute_force(spark):
    common = ["alpha", "bravo", "charlie", "delta", "echo", "foxtrot", "golf", "hotel"]
    rare = [f"zork{c}" for c in "abcdefghijklmnop"]
    texts = []
    for _ in range(260):
        words = [draw.choice(common) for _ in range(draw.randint(3, 9))] + [draw.choice(rare) for _ in range(draw.randint(0, 2))]
        if draw.random() < 0.25:
            n = draw.randrange(12)
            words.insert(draw.randrange(len(words)), f"p{n}@corp.example")
            words += [f"name{'abcdefghijkl'[n]}"] * draw.randint(0, 2)
        texts.append(" ".join(words))
    texts += texts[:20]
    want = terms_brute(texts)
    got = pii.personal_spans(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")).collect()
    found = {r.doc_id: sorted(tuple(map(int, s.split(":")[1:])) for s in r.spans.split(",") if s.startswith("term:")) for r in got}
    assert sum(map(len, want.values())) > 20
    assert all(found[i] == want[t] for i, t in enumerate(texts))


def test_propagation_on_a_random_graph(spark):
    hosts = [f"h{i}.net" for i in range(40)]
    links = [(a, b, draw.randint(1, 4)) for a in hosts for b in hosts if a != b and draw.random() < 0.08]
    seeds = {h: draw.randint(1, 5) for h in draw.sample(hosts, 8)}
    rank = {h: n * 10**15 for h, n in seeds.items()}
    start = dict(rank)
    total = {a: sum(n for x, _, n in links if x == a) for a in hosts}
    for _ in range(10):
        got = {}
        for a, b, n in links:
            if a in rank:
                got[b] = got.get(b, 0) + rank[a] * n // total[a]
        rank = {h: got.get(h, 0) * 85 // 100 + start.get(h, 0) * 15 // 100 for h in {*got, *start}}
    seeds_t = written(spark.createDataFrame(list(seeds.items()), "host string, n long"), "seeds")
    links_t = written(spark.createDataFrame(links, "src string, dst string, n long"), "links")
    assert {r.host: int(r["rank"]) for r in propagated(seeds_t, links_t).collect()} == rank


def field(number, kind, value):
    def varint(x):
        out = b""
        while x > 127:
            out += bytes([x & 127 | 128])
            x >>= 7
        return out + bytes([x])

    if kind == "int":
        return varint(number << 3) + varint(value)
    if kind == "float":
        return varint(number << 3 | 5) + struct.pack("<f", value)
    return varint(number << 3 | 2) + varint(len(value)) + value


def test_unigram_model_with_a_character_map(tmp_path):
    normal = [*"abcdefgh ABCé▁".replace(" ", ""), "▁ab", "▁abc", "cd", "ef", "gh", "▁he", "abc", "fi", "1"]
    pieces = [("<unk>", 0.0, 2), ("<s>", 0.0, 3), ("</s>", 0.0, 3), *((p, -1.0 - 0.37 * i, 1) for i, p in enumerate(normal))]
    try:
        normaliser = sentencepiece.SentencePieceNormalizer(rule_name="nmt_nfkc", add_dummy_prefix=True, escape_whitespaces=True, remove_extra_whitespaces=True).serialized_model_proto()
    except (AttributeError, TypeError):
        pytest.skip("this sentencepiece has no normaliser of its own")
    from transitlens.llm.piece_tokenizer import _fields

    rules = next((v for f, v in _fields(normaliser) if f == 3), b"")
    model = b"".join(field(1, "bytes", field(1, "bytes", p.encode()) + field(2, "float", s) + field(3, "int", k)) for p, s, k in pieces)
    model += field(2, "bytes", field(3, "int", 1)) + field(3, "bytes", rules)
    path = tmp_path / "own.model"
    path.write_bytes(model)
    own, sp = PieceCodec(str(path), 1), sentencepiece.SentencePieceProcessor(model_file=str(path))
    texts = ["abc cd", "  abc   efgh ", "ABC", "ﬁ ①", "é", "", "abcabc hehe", "a　b"]
    texts += ["".join(draw.choice("abcdefgh  A1é") for _ in range(draw.randint(0, 30))) for _ in range(300)]
    for t, (ids, _, same) in zip(texts, own.encode(texts, parity=True), strict=True):
        assert ids.tolist() == sp.encode(t) and same
