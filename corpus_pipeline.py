"""A corpus pipeline over documents: quality rules, near-duplicates, decontamination, personal data, byte-level BPE.

Each stage takes all rows that the one before it kept, as Parquet, and its decisions take effect: rejected,
repeated and contaminated documents go, personal data is replaced, texts become token ids beside the other columns.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from setoverlap.llm import bytebpe, decontam, neardup, pii, quality
from setoverlap.llm.common import materialised, table


def good_documents(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return quality.keep_good(docs)


def distinct_documents(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return neardup.keep_first(docs)


def clean_of_benchmark(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return decontam.decontaminate(docs, table(spark, sf_dir, "benchmark"))


def without_personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return pii.redact(docs)


def token_ids(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return bytebpe.tokenised(docs, public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN)


STAGES = [
    ("quality_rules", good_documents),
    ("near_dedup", distinct_documents),
    ("decontamination", clean_of_benchmark),
    ("pii", without_personal_data),
    ("byte_bpe", token_ids),
]

#: SQL expresses neither boosted trees nor byte pair merges; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for i, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if i < len(STAGES) - 1:
            docs = materialised(docs)
    return docs
