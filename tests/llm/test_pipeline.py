"""The pipeline's stages on a small folder, and its rows against the operators' own results."""

import zlib

import numpy as np
import public_tokenizers
import sentencepiece

import corpus_pipeline
from transitlens.llm.common import scratch_path


def test_stages_and_run(spark):
    good = "the quick brown fox jumps over a lazy dog and then it runs back home to sleep near the warm fire with mail {} end"
    rows = [(i, good.format(f"u{i}@mail.example") + f" unique{i} words{i} here{i} so{i} that{i} it{i} stays{i} alone{i}", "en", "abc"[i % 3], 1) for i in range(30)]
    rows += [(100, rows[0][1], "en", "a", 1), (101, "too short", "en", "a", 1), (102, None, "en", None, 1)]
    folder = scratch_path(spark, "pipeline-in")
    spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long").write.parquet(f"{folder}/documents.parquet")
    docs, seen = spark.read.parquet(f"{folder}/documents.parquet"), {}
    columns = docs.columns
    for name, stage in corpus_pipeline.STAGES[:-1]:
        path = scratch_path(spark, "stage")
        stage(spark, docs, folder).write.parquet(path)
        docs = spark.read.parquet(path)
        assert docs.columns == columns
        seen[name] = docs.collect()
    assert {r.doc_id for r in seen["quality"]} == {*range(30), 100}
    assert {r.doc_id for r in seen["near_duplicates"]} == set(range(30))
    assert all("@" not in r.text and "[EMAIL]" in r.text for r in seen["personal_data"])
    sp = sentencepiece.SentencePieceProcessor(model_file=public_tokenizers.path("piece_bpe_32k.model"))
    want = sorted((r.doc_id, len(x := sp.encode(r.text)), zlib.crc32(np.array(x, "<u4").tobytes())) for r in seen["mixing"])
    got = corpus_pipeline.run(spark, folder).collect()
    assert sorted((r.doc_id, r.n_pieces, r.ids_crc32) for r in got) == want and all(r.parity for r in got)


def test_odd_rows(spark):
    """Long texts, repeated ids with different texts, null ids and sources, columns with the operators' own names."""
    words = " ".join(f"word{i % 977}x{i}" for i in range(30_000))
    rows = [(1, words, "en", "a", 1, 5, "k"), (2, words + " more", "en", "a", 1, 5, "k"), (2, " ".join(f"other{i}" for i in range(40)), "en", None, 1, 5, "k"), (None, " ".join(f"none{i}" for i in range(40)), "en", "b", 1, 5, "k"), (None, None, None, None, None, None, None)]
    schema = "doc_id long, text string, lang string, source string, n_chars long, n_words long, component_id string"
    for table, want in ((rows, {1, 2, None}), ([], set())):
        folder = scratch_path(spark, "pipeline-odd")
        spark.createDataFrame(table, schema).write.parquet(f"{folder}/documents.parquet")
        docs = spark.read.parquet(f"{folder}/documents.parquet")
        for _, stage in corpus_pipeline.STAGES[:2]:
            path = scratch_path(spark, "odd")
            stage(spark, docs, folder).write.parquet(path)
            docs = spark.read.parquet(path)
        kept = docs.collect()
        assert docs.columns == spark.createDataFrame([], schema).columns and {r.doc_id for r in kept} == want and len(kept) == len(want)
        assert corpus_pipeline.run(spark, folder).count() >= (1 if table else 0)
