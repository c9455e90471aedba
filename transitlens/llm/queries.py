"""The queries of the corpus operators over the given tables, and their SQL."""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import oracles
from .common import scratch_path
from .jaccard_join import jaccard_components
from .pii import personal_spans
from .piece_tokenizer import encode_pieces
from .quality_model import quality_scores
from .quality_rules import judge_documents
from .source_mix import mix_documents
from .token_counts import token_counts
from .token_files import read_token_files, write_token_files
from .topk_search import top_k
from .url_filters import judge_urls


def _documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def op1_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_counts(_documents(spark, sf_dir), public_tokenizers.path("byte_bpe_50k.json"))


def op2_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    folder = scratch_path(spark, "token-files")
    write_token_files(_documents(spark, sf_dir), public_tokenizers.path("byte_bpe_50k.json"), folder)
    return read_token_files(spark, folder)


def op3_sentencepiece(spark: SparkSession, sf_dir: str) -> DataFrame:
    return encode_pieces(_documents(spark, sf_dir), public_tokenizers.path("piece_bpe_32k.model"))


def op4_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judge_documents(_documents(spark, sf_dir)).drop("host_rejected")


def op6_source_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mix_documents(_documents(spark, sf_dir)).drop("copies")


def op8_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard_components(_documents(spark, sf_dir))


def op5_topk_search(spark: SparkSession, sf_dir: str) -> DataFrame:
    return top_k(spark.read.parquet(f"{sf_dir}/embeddings.parquet"), F.col("vec_id") % 50 == 0)


def op7_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_scores(_documents(spark, sf_dir), spark.read.parquet(f"{sf_dir}/labels.parquet"))


def op9_url_filters(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judge_urls(spark.read.parquet(f"{sf_dir}/pages.parquet"))


def op10_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    return personal_spans(_documents(spark, sf_dir))


def queries() -> dict:
    return {f.__name__: f for f in (op1_token_counts, op2_token_files, op3_sentencepiece, op4_quality_rules, op5_topk_search, op6_source_mix, op7_quality_classifier, op8_jaccard_join, op9_url_filters, op10_pii)}


def oracle_sql() -> dict[str, str]:
    """Of the queries that SQL can express; the others are tested against brute force, a round trip or held-out accuracy."""
    return {"op4_quality_rules": oracles.QUALITY_RULES, "op5_topk_search": oracles.TOPK_SEARCH, "op8_jaccard_join": oracles.JACCARD_JOIN, "op9_url_filters": oracles.url_filters()}
