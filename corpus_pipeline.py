"""The corpus pipeline: documents through five of the operators, each stage written as Parquet and read again as the next one's input.

Quality rules drop documents that fail; of each group of near duplicates one document stays; personal data is replaced by labels;
sources are mixed to target weights, a document as often as the mix takes it; the last stage encodes what is left as SentencePiece
ids and returns a row of figures per document. All stages but the last return the columns of ``documents``, whatever those are called. An
empty table stays empty through all stages; very long texts are handled whole.
"""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession

from transitlens.llm.common import scratch_path
from transitlens.llm.jaccard_join import one_of_each_group
from transitlens.llm.pii import sanitised_rows
from transitlens.llm.piece_tokenizer import encode_pieces
from transitlens.llm.quality_rules import keep_good_documents
from transitlens.llm.source_mix import mixed_rows


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The documents that keep the base rules and whose source is not rejected. Null, empty and short texts go; rows that repeat stay."""
    return keep_good_documents(docs)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row of each group of near duplicates, of the smallest id, null last; rows that repeat one id with different texts are judged
    by their texts; documents without words stay."""
    return one_of_each_group(docs)


def personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All rows, personal data in ``text`` replaced or removed; a null text stays null."""
    return sanitised_rows(docs)


def mixing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each row as often as the mix takes it; a null source is one of its own; rows equal in id and text are taken alike."""
    return mixed_rows(docs)


def encoding(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """A row of figures for each row; a null text has no ids."""
    return encode_pieces(docs, public_tokenizers.path("piece_bpe_32k.model"))


STAGES = [("quality", quality), ("near_duplicates", near_duplicates), ("personal_data", personal_data), ("mixing", mixing), ("encoding", encoding)]

#: SentencePiece ids have no SQL form; tests/llm holds the rows against a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over the table ``documents`` of ``sf_dir``."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES:
        path = scratch_path(spark, f"pipeline-{name}")
        stage(spark, docs, sf_dir).write.parquet(path)
        docs = spark.read.parquet(path)
    return docs
