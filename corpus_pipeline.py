"""A training-data pipeline over `documents`: each stage's output is written and reread by the next."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from groupmatch.llm import bpe, curriculum, ngram_jaccard, perplexity, secret_scan
from groupmatch.durable import settle
from groupmatch.session import ship


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the base rules or their language's perplexity bands reject go."""
    return perplexity.reject(_own(spark, docs))


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each component of similar documents stays (five words, 0.8 or more)."""
    return ngram_jaccard.keep_one(_own(spark, docs), n=5, percent=80)


def secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Live credentials are masked; all documents stay."""
    return secret_scan.mask(_own(spark, docs))


def mixing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents as often as the mix takes them, in training order."""
    return curriculum.train_order(_own(spark, docs))


def tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The documents' columns with their token ids."""
    import public_tokenizers

    return bpe.encode(_own(spark, docs), public_tokenizers.path("byte_bpe_50k.json"))


def _own(spark: SparkSession, docs: DataFrame) -> DataFrame:
    ship(spark)
    return docs


STAGES = [("quality rules", quality), ("n-gram Jaccard join", near_duplicates), ("secret scans", secrets), ("mixing sources", mixing), ("BPE encoding", tokens)]
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for k, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k < len(STAGES) - 1:
            docs = settle(docs, "pipeline")
    return docs
