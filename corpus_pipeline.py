"""Corpus cleaning in five stages; each keeps the columns of documents, the last adds the sampled segmentation.

quality   rows that fail the text rules, or whose host fails, go
near      one row of each component of near copies stays, that with the smallest id
leaks     rows with a benchmark window go
private   spans of personal data are replaced by their kind
pieces    the text is encoded with merge-dropout; `piece_ids` decodes to exactly the text
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from cellscrub.llm import jaccard_join, merge_dropout, pii_votes, quality_hosts, winnowing
from cellscrub.session import materialize


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return quality_hosts.filter_documents(docs)


def near(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return jaccard_join.keep_representatives(docs)


def leaks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return winnowing.clean_documents(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet"))


def private(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return pii_votes.mask_documents(docs)


def pieces(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return merge_dropout.encode_documents(docs)


STAGES = [("quality", quality), ("near", near), ("leaks", leaks), ("private", private), ("pieces", pieces)]

#: Stages 4 and 5 have no SQL form; tests/llm compare the pipeline with a plain Python version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES:
        docs = materialize(stage(spark, docs, sf_dir), f"pipeline-{name}")
    return docs
