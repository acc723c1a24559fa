"""A corpus pipeline of five stages, each by one operator of replica_sync.llm, each written and read again.

quality classifier, near-duplicate join, secret scan, mixing, byte-level BPE.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from replica_sync.llm import bpe, jaccard_join, mixing, quality_nb, secret_scan
from replica_sync.llm.common import kept_as_table


#: Near duplicates of this pipeline: sets of five words, similar from 80 % on (op3 has its own defaults).
WIDTH, PERCENT = 5, 80


def good_documents(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality classifier rejects go; null and empty texts have the score of nothing, repeated rows stay or go together."""
    return quality_nb.keep_good(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))


def distinct_documents(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of near duplicates (five-word sets, similarity 0.8 or more) the document with the smallest id stays, once;
    documents without an id or without words stay."""
    return jaccard_join.one_of_each(docs, WIDTH, PERCENT)


def without_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Secrets in the texts are replaced; null and empty texts and repeated rows stay as they are."""
    return secret_scan.redact_secrets(docs)


def mixed_documents(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents as often as the mix of their sources takes them; rows without words are not taken, a null source is one of its own."""
    return mixing.repeated_rows(docs)


def token_ids(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token counts and digests of the ids of every document, one row for each row; a null text counts as empty."""
    return bpe.encode_texts(docs)


STAGES = [
    ("quality", good_documents),
    ("near_duplicates", distinct_documents),
    ("secrets", without_secrets),
    ("mixing", mixed_documents),
    ("byte_bpe", token_ids),
]

#: The stages learn models and merge bytes: no SQL expresses them. They are tested against plain Python.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        docs = kept_as_table(stage(spark, docs, sf_dir), f"stage-{name}")
    return STAGES[-1][1](spark, docs, sf_dir)
