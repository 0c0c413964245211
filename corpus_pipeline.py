"""A training corpus from raw documents, stage by stage.

Each stage takes (spark, docs, sf_dir) and works on all rows that the stage before it kept. All but the last return the columns
of ``documents``; the last returns doc_id, n_tokens, ids_sha256 and decoded_sha256 for every row of the mix (a document
that the mix repeats has as many rows). Near duplicates are taken at five words and a similarity of 0.8.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from bandspark.llm import bpe, exactdup, mixing, ngramjoin, quality
from bandspark.session import arrow_rows, materialize

SHINGLE_WORDS, SIMILAR_PERCENT = 5, 80


def quality_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the rules' posterior keeps."""
    return quality.keep_good(docs)


def exact_dedup_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of equal texts, the row of largest id."""
    return exactdup.drop_duplicates(docs)


def near_dedup_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of every class of similar documents, the one of smallest id."""
    return ngramjoin.one_of_each(docs, SHINGLE_WORDS, SIMILAR_PERCENT)


def mixing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every document as many times as the mix takes it."""
    return mixing.mixed_documents(docs)


def encoding_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Every row encoded, and its ids decoded. Texts are sent to Python few at a time; the digests are small."""
    with arrow_rows(spark, ngramjoin.TEXTS):
        return materialize(bpe.round_trip(docs), "pipeline-encoded")


STAGES = [
    ("quality_rules", quality_stage),
    ("exact_dedup", exact_dedup_stage),
    ("ngram_join", near_dedup_stage),
    ("mix_sources", mixing_stage),
    ("bpe_encoding", encoding_stage),
]

#: The fit of the quality rules and the tokens are beyond SQL; tests/llm compares the stages with brute-force versions.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``; each result is written as Parquet and read again for the next."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        docs = materialize(stage(spark, docs, sf_dir), f"pipeline-{name}")
    return STAGES[-1][1](spark, docs, sf_dir)
