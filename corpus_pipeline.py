"""A corpus pipeline of the operators: documents in, packed training sequences out."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession

from docprofile.llm import exact, near, packing, quality, secrets
from docprofile.llm.common import collect_garbage, scratch, shuffles_dropped
from docprofile.llm.queries import quality_scorer


def quality_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the compression classifier rejects go."""
    return quality.keep_good(docs, quality_scorer(spark, docs, sf_dir))


def exact_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of documents with equal texts one stays."""
    collect_garbage(spark)
    return exact.keep_first(docs)


def near_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of near copies (sets of five-word shingles similar by 0.8) the document with the smallest id stays."""
    collect_garbage(spark)
    return near.keep_one(docs)


def secret_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Secrets that look live are replaced by a mark; every document stays."""
    collect_garbage(spark)
    return secrets.redact(docs)


def packing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces with their places in training sequences."""
    collect_garbage(spark)
    return packing.pack_documents(docs)


STAGES = [("quality classifier", quality_stage), ("exact dedup", exact_stage), ("simhash near-dedup", near_stage), ("secret scans", secret_stage), ("best-fit packing", packing_stage)]

#: SQL can't express the first, third and last stage; tests hold run() against a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents, each stage's result written to the shared folder and read again."""
    docs, at = spark.read.parquet(f"{sf_dir}/documents.parquet"), scratch(spark, f"pipeline-{uuid.uuid4().hex[:8]}")
    for i, (_, stage) in enumerate(STAGES):
        done = stage(spark, docs, sf_dir)
        with shuffles_dropped(spark):
            done.write.parquet(f"{at}/{i}")
        docs = spark.read.parquet(f"{at}/{i}")
    return docs
