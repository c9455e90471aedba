"""Token operators against their libraries, and the file round trip; defined cases."""

import zlib

import numpy as np
import public_tokenizers
import pytest
from tokenizers import Tokenizer

from transitlens.llm.common import scratch_path
from transitlens.llm.piece_tokenizer import codec, decode_pieces, encode_pieces, reference, with_piece_ids
from transitlens.llm.token_counts import token_counts
from transitlens.llm.token_files import MANIFEST, Shard, read_token_files, write_token_files

BPE, PIECE = public_tokenizers.path("byte_bpe_50k.json"), public_tokenizers.path("piece_bpe_32k.model")
TEXTS = [None, "", " ", "a  b\n c", "x<|endoftext|> y", "aaaa" * 300, "日本語 テキスト", "\x1f \x1fz\t", "  lead", "t  ", "\n  b", "don't 123 we'll", "word " * 3000, "🦄 é", "same", "same", "▁ a▁b", "  a  b "]


@pytest.fixture(scope="module")
def docs(spark):
    rows = [(i, t, len(t or ""), "clash") for i, t in enumerate(TEXTS)] + [(3, TEXTS[3], 0, None)]
    return spark.createDataFrame(rows, "doc_id long, text string, n_tokens int, start string")


def ids(text):
    return Tokenizer.from_file(BPE).encode(text or "", add_special_tokens=False).ids


def test_counts_equal_the_library(docs):
    got = token_counts(docs, BPE).collect()
    assert len(got) == len(TEXTS) + 1
    for r in got:
        n = len(ids(TEXTS[r.doc_id]))
        assert (r.n_tokens, r.n_bytes, r.over_limit) == (n, len((TEXTS[r.doc_id] or "").encode()), n > 1024)


def test_files_give_back_the_ids(spark, docs):
    folder = scratch_path(spark, "test-files")
    manifest = write_token_files(docs, BPE, folder, seq_len=64, rows_per_batch=4)
    rows = sorted(read_token_files(spark, folder).collect(), key=lambda r: r.start)
    assert [r.doc_id for r in rows] == sorted([*range(len(TEXTS)), 3])
    start = 0
    for r in rows:
        want = [*ids(TEXTS[r.doc_id]), 2]
        assert (r.start, r.n_tokens, r.ids_crc32) == (start, len(want), zlib.crc32(np.array(want, "<u4").tobytes()))
        start += len(want)
    for m in manifest.collect():
        shard = Shard(folder, m.name)
        assert len(shard) == m.n_sequences == -(-m.n_ids // 64)
        assert sum(sum(shard.sequence(i)[1].to_pylist()) for i in range(len(shard))) == m.n_ids
        assert not shard.sequence(0)[0].flags.owndata


def test_empty_tables(spark, docs):
    none = docs.limit(0)
    assert token_counts(none, BPE).count() == 0
    assert encode_pieces(none, PIECE).count() == 0
    folder = scratch_path(spark, "test-none")
    assert write_token_files(none, BPE, folder).count() == 0
    assert read_token_files(spark, folder).count() == 0
    assert "name" in MANIFEST


def test_pieces_equal_sentencepiece_and_decode(docs):
    sp = reference(PIECE)
    for r in with_piece_ids(docs, PIECE).collect():
        assert list(r.piece_ids) == sp.encode(r.text or "")
    assert all(r.parity for r in encode_pieces(docs, PIECE).collect())
    back = decode_pieces(with_piece_ids(docs, PIECE), PIECE).collect()
    assert sorted((r.doc_id, r.text) for r in back) == sorted((i, sp.decode(sp.encode(t or ""))) for i, t in [*enumerate(TEXTS), (3, TEXTS[3])])
    assert codec(PIECE).decode([sp.encode("a b")]) == ["a b"]
