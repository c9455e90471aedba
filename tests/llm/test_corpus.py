"""Corpus operators against brute force on small tables, with their defined cases."""

import hashlib
import random
import re

import numpy as np
import pytest
from pyspark.sql import functions as F

from transitlens.llm import pii, quality_model
from transitlens.llm.components import connected_components
from transitlens.llm.jaccard_join import jaccard_components, one_of_each_group
from transitlens.llm.quality_rules import beta_prior, judge_documents, keep_good_documents, repeated_words
from transitlens.llm.source_mix import mix_documents, mixed_rows, source_targets
from transitlens.llm.topk_search import search_tile, top_k
from transitlens.llm.url_filters import judge_urls

draw = random.Random(11)
WORDS = [f"w{i}" for i in range(400)]


def prose(n):
    return " ".join(draw.choice(WORDS) for _ in range(n))


def docs_of(spark, rows):
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, kept string, size int")


def filled(rows):
    return [(i, t, "en", s, len(t or ""), "clash", 1) for i, t, s in rows]


def test_repeated_words_by_brute_force():
    for _ in range(200):
        words = [draw.choice("abc").encode() for _ in range(draw.randint(0, 40))]
        seen = {}
        for i in range(len(words) - 7):
            seen.setdefault(tuple(words[i : i + 8]), []).append(i)
        hit = {i + j for at in seen.values() if len(at) > 1 for i in at for j in range(8)}
        assert repeated_words(words) == len(hit)


def test_quality_rules_and_hosts(spark):
    rows = [(i, prose(40), "good") for i in range(30)] + [(100 + i, "short", "bad") for i in range(30)] + [(200, prose(40), "bad"), (201, None, None), (202, "", "good")]
    got = {r.doc_id: r for r in judge_documents(docs_of(spark, filled(rows))).collect()}
    assert all(got[i].kept for i in range(30)) and not any(got[100 + i].kept for i in range(30))
    assert not got[200].base_failed and not got[200].kept  # its host is rejected
    assert got[201].base_failed and got[201].n_words == 0 and not got[202].kept
    kept = keep_good_documents(docs_of(spark, filled(rows)))
    assert kept.columns == docs_of(spark, []).columns and sorted(r.doc_id for r in kept.collect()) == list(range(30))
    assert judge_documents(docs_of(spark, [])).count() == 0
    assert beta_prior(0, 0, 0, 0.0) == (0.0, 1.0) and beta_prior(100, 10, 10, 1.0)[1] == 1e6


def test_mix_meets_targets_and_reruns_agree(spark):
    rows = [(i, prose(draw.randint(1, 60)), s) for i, s in enumerate(draw.choice(["a", "a", "a", "b", "c", None]) for _ in range(900))] + [(5000, None, "zero"), (5001, "", "zero")]
    docs = docs_of(spark, filled(rows))
    got = mix_documents(docs).collect()
    size = {i: len(re.findall(r"[^\x20\x09-\x0D]+", t or "")) for i, t, _ in rows}
    source = {i: s for i, _, s in rows}
    assert all(r["size"] == size[r.doc_id] and r.taken <= 3 * r["size"] for r in got) and len(got) == len(rows)
    total = {s: sum(size[i] for i in size if source[i] == s) for s in set(source.values())}
    order = sorted(total, key=lambda s: (s is None, s or ""))
    weight = {s: i % 3 + 1 for i, s in enumerate(order)}
    target, open_, left = {}, set(order), float(sum(total.values()))
    while True:  # resharing until none is above its cap
        level = left / sum(weight[s] for s in open_) if open_ else 0
        over = {s for s in open_ if level * weight[s] > 3 * total[s]}
        if not over:
            break
        for s in over:
            target[s] = 3.0 * total[s]
        left -= sum(target[s] for s in over)
        open_ -= over
    target |= {s: level * weight[s] for s in open_}
    for s in order:
        mine = [r for r in got if source[r.doc_id] == s]
        assert all(abs(r.target - target[s]) < 1e-6 and r.source_size == total[s] for r in mine)
        assert abs(sum(r.taken for r in mine) - target[s]) <= 60
    assert sorted(map(tuple, got)) == sorted(map(tuple, mix_documents(docs.repartition(7)).collect()))
    assert mixed_rows(docs).count() == sum(r.copies for r in got)
    assert mix_documents(docs_of(spark, [])).count() == 0
    assert source_targets(spark.createDataFrame([("x", 0)], "source string, source_size long")).first().target == 0


def jaccard_brute(rows):
    sets = {}
    for i, t in rows:
        w = (t or "").encode().lower().split()
        sets[i] = frozenset(tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))) if w else frozenset()
    root = {i: i for i in sets}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    ids = sorted(sets)
    for a in range(len(ids)):
        for b in range(a + 1, len(ids)):
            s, t = sets[ids[a]], sets[ids[b]]
            if s and t and 100 * len(s & t) >= 80 * len(s | t):
                x, y = sorted((find(ids[a]), find(ids[b])))
                root[y] = x
    return {i: (len(sets[i]), find(i)) for i in ids}


def test_jaccard_components_by_brute_force(spark):
    rows = [(0, None), (1, ""), (2, " \n"), (3, "one two"), (4, "ONE two"), (5, "one two three")]
    common = prose(40)
    for g in range(60):
        base = prose(draw.choice([6, 9, 12, 30, 60, 130])).split()
        for _ in range(draw.randint(1, 8)):
            w = list(base)
            for _ in range(draw.randint(0, 3)):
                w[draw.randrange(len(w))] = draw.choice(WORDS)
            if draw.random() < 0.3:
                w += common.split()
            rows.append((len(rows), " ".join(w)))
    rows += [(len(rows) + i, common) for i in range(30)]
    docs = spark.createDataFrame([(i, t, "x") for i, t in rows], "doc_id long, text string, component_id string")
    want = jaccard_brute(rows)
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in jaccard_components(docs).collect()}
    assert got == want
    left = {r.doc_id for r in one_of_each_group(docs).collect()}
    assert left == {i for i, (_, c) in want.items() if i == c}
    assert jaccard_components(docs.limit(0)).count() == 0


def test_components(spark):
    links = spark.createDataFrame([(i, i + 1) for i in range(0, 40)] + [(100, 102), (101, 102), (7, 7)], "u long, v long")
    got = dict(map(tuple, connected_components(links).collect()))
    assert got == {i: 0 for i in range(41)} | {100: 100, 101: 100, 102: 100}
    assert connected_components(links.limit(0)).count() == 0


def test_top_k_by_brute_force(spark):
    rng = np.random.default_rng(2)
    x = rng.normal(0, 0.2, (700, 16)).round(2)
    x[300:400] = x[0]
    rows = [(i, v.tolist()) for i, v in enumerate(x)] + [(700, None), (701, [float("nan")] * 16), (702, [None] * 16), (None, x[0].tolist()), (5, x[5].tolist()), (703, [])]
    table = spark.createDataFrame(rows, "vec_id long, embedding array<float>")
    q = np.floor(256 * x.astype(np.float32).astype(float)).astype(int)
    every = [*range(700), 5]  # a row that repeats an id takes part as well
    want = set()
    for i in range(0, 700, 50):
        best = sorted((-int(q[j] @ q[i]), j) for j in every if j != i)[:5]
        want |= {(i, n + 1, j, -s) for n, (s, j) in enumerate(best)}
    assert set(map(tuple, top_k(table, F.col("vec_id") % 50 == 0).collect())) == want
    assert top_k(table.limit(0), F.col("vec_id") % 50 == 0).count() == 0
    clusters = np.repeat(rng.normal(0, 100, (20, 16)).round(), 64, axis=0) + rng.integers(-3, 4, (1280, 16))
    names = np.arange(1280)
    *_, scored = search_tile(names, names, clusters, names[::64], clusters[::64], 5)
    assert scored < 20 * 20 * 0.5  # most blocks are left out


def test_url_rules_and_host_verdicts(spark):
    bad = '<a href="http://evil.net/x">x</a>'
    rows = [(1, "http://a.ORG/p?q", ""), (2, "https://m.example.org/es/1", bad), (3, "https://example.org/en/17#a", None), (4, "no url", ""), (5, None, ""), (6, "http://x.com/fr/", ""), (7, "http://evil.com/de/1", ""), (8, "http://evil.com/en", ""), (9, "http://friend.net/", "<a href='//evil.com/'>")]
    got = {r.page_id: r for r in judge_urls(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()}
    assert (got[1].host, got[1].path, got[1].rule, got[1].verdict) == ("a.org", "/p", "org/", "allow")
    assert (got[2].rule, got[2].verdict) == ("example.org/es/", "block") and (got[3].rule, got[3].path) == ("example.org/en/1", "/en/17")
    assert (got[4].host, got[4].path, got[4].verdict) == ("", "", "allow") == (got[5].host, got[5].path, got[5].verdict)
    assert got[6].verdict == "allow" and got[7].verdict == "block" and got[8].verdict == "block"
    assert got[9].verdict == "block" and got[9].distrust > 0  # links to a distrusted host
    assert judge_urls(spark.createDataFrame([], "page_id long, url string, html string")).count() == 0


PATTERNS = [("email", r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+"), ("ip", r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)"), ("card", r"[0-9]([\x20-]?[0-9])+"), ("phone", r"\+[0-9][\x20().0-9-]+[0-9]")]


def luhn(digits):
    return sum(int(c) if i % 2 == 0 else sum(divmod(2 * int(c), 10)) for i, c in enumerate(reversed(digits))) % 10 == 0


def spans_brute(text):
    out = []
    for k, (kind, pattern) in enumerate(PATTERNS):
        for m in re.finditer(pattern, text or ""):
            digits = re.sub("[^0-9]", "", m[0])
            fine = {"email": True, "ip": kind != "ip" or all(int(p) <= 255 for p in m[0].split(".")), "card": 14 <= len(digits) <= 19 and luhn(digits), "phone": 10 <= len(digits) <= 15}[kind]
            if fine:
                out.append((m.start(), k, f"{kind}:{m.start()}:{m.end()}"))
    return ",".join(s for _, _, s in sorted(out))


def test_personal_spans_by_brute_force(spark):
    texts = ["".join(draw.choice("a1.@+-_ ()%é🦄4\n") for _ in range(draw.randint(0, 60))) for _ in range(800)]
    texts += ["".join(draw.choice("0123456789 -.+4") for _ in range(draw.randint(0, 60))) for _ in range(800)]
    texts += [None, "", "4" * 20000, "4 " * 20000, "a@b" + ".c" * 20000, "a" * 100_000, "1." * 20000, "é 4111 1111 1111 1111 +1 (415) 555-2671 a@b.c.d_e@f.g 1.2.3.4.5.6.7.8 0001.2.3.255"]
    got = {r.doc_id: r for r in pii.personal_spans(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")).collect()}
    for i, t in enumerate(texts):
        want = spans_brute(t)
        assert got[i].base_sha256 == hashlib.sha256(want.encode()).hexdigest()
        assert got[i].n_term or got[i].spans == want


def test_disclosing_terms_are_removed_and_clean_texts_stay(spark):
    rows = [(i, f"Note {i}: ask Zorbax now at zo@corp.example about item{i} please, the usual way") for i in range(8)] + [(100 + i, f"the usual way is fine about please item note {i}") for i in range(200)]
    docs = spark.createDataFrame(rows + [(None, None)], "doc_id long, text string")
    got = {r.doc_id: r.text for r in pii.sanitised_rows(docs).collect()}
    assert got[0] == "Note 0: ask  now at [EMAIL] about item0 please, the usual way"
    assert all(got[i] == t for i, t in rows if i >= 100) and got[None] is None
    assert pii.personal_spans(docs.limit(0)).count() == 0


def test_terms_disclose_an_entity_of_one_text(spark):
    filler = "the usual way with some more words between them " * 4
    rows = [(1, f"Quorvane came along. {filler} mail qu@corp.example"), (2, f"ask mo@corp.example {filler} Mulbrick"), (3, f"{filler} Mulbrick told mo@corp.example")]
    rows += [(100 + i, f"{filler} {'Quorvanes' * (i % 2)}") for i in range(2)] + [(200 + i, f"{filler} note {i}") for i in range(600)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    got = {r.doc_id: r for r in pii.personal_spans(docs).collect()}
    assert {i: r.n_term for i, r in got.items() if r.n_term} == {1: 4, 2: 1, 3: 2}  # also "came", "along" and "mail", "told"
    assert got[1].spans.startswith("term:0:8,term:9:13,")
    clean = {r.doc_id: r.text for r in pii.sanitised_rows(docs).collect()}
    assert clean[2] == f"ask [EMAIL] {filler} " and "Mulbrick" not in clean[3] and "Quorvane" not in clean[1]
    assert all(clean[i] == t for i, t in rows if i >= 100)
    few = spark.createDataFrame(rows[:3] + rows[5:55], "doc_id long, text string")
    assert all(r.n_term == 0 for r in pii.personal_spans(few).collect() if r.doc_id == 1)  # so few texts tell nothing


def test_quality_model_on_held_out_rows(spark):
    rows = [(i, prose(50) if i % 3 else " ".join(w + "###" for w in prose(50).split()), int(i % 3 > 0)) for i in range(900)]
    docs = spark.createDataFrame([(i, t) for i, t, _ in rows] + [(2000, None), (2001, "")], "doc_id long, text string")
    labels = spark.createDataFrame([(i, y) for i, _, y in rows] + [(None, 1), (3000, 0), (4000, None)], "doc_id long, quality int")
    got = {r.doc_id: r for r in quality_model.quality_scores(docs, labels).collect()}
    held = [i for i, _, _ in rows if got[i].held_out]
    assert held and np.mean([got[i].predicted == int(i % 3 > 0) for i in held]) > 0.97
    assert 0 <= got[2000].score <= 1 and got[2000].score == got[2001].score
    flat = quality_model.quality_scores(docs, labels.limit(0)).first()
    assert flat.score == pytest.approx(0.5)
