"""Sources of documents and sinks of results. A document frame is (doc_id, json)."""

from __future__ import annotations

import json

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def from_table(df: DataFrame, id_col: str) -> DataFrame:
    """Rows of a table as documents; null fields are absent attributes."""
    return df.select(F.col(id_col).cast("long").alias("doc_id"), F.to_json(F.struct(*df.columns)).alias("json"))


def json_lines(spark: SparkSession, path: str) -> DataFrame:
    """One document a line. Ids come from file and place, not from a sort: unique, and the same when a task is retried."""
    return spark.read.text(path).select(F.xxhash64(F.input_file_name(), F.monotonically_increasing_id()).alias("doc_id"), F.col("value").alias("json"))


def json_files(spark: SparkSession, path: str) -> DataFrame:
    """One document a file, of any number of lines."""
    return spark.read.text(path, wholetext=True).select(F.xxhash64(F.input_file_name()).alias("doc_id"), F.col("value").alias("json"))


def csv(spark: SparkSession, path: str, schema: str, id_col: str) -> DataFrame:
    return from_table(spark.read.csv(path, header=True, schema=schema), id_col)


def rows(spark: SparkSession, documents: list) -> DataFrame:
    """Python values, or texts as they are."""
    return spark.createDataFrame([(i, d if isinstance(d, str) else json.dumps(d)) for i, d in enumerate(documents)], "doc_id long, json string")


def json_stream(spark: SparkSession, path: str, files_per_trigger: int = 1) -> DataFrame:
    """One document a line of the files that arrive in a folder."""
    return spark.readStream.option("maxFilesPerTrigger", files_per_trigger).text(path).select(F.xxhash64("value").alias("doc_id"), F.col("value").alias("json"))


def rate_stream(spark: SparkSession, per_second: int) -> DataFrame:
    """Synthetic load for rate tests."""
    return spark.readStream.format("rate").option("rowsPerSecond", per_second).load().select(F.col("value").alias("doc_id"), F.to_json(F.struct("value", "timestamp")).alias("json"), F.col("timestamp").alias("ts"))


def write_parquet(df: DataFrame, path: str) -> None:
    df.write.mode("overwrite").parquet(path)


def write_schema(spark: SparkSession, schema: dict, path: str) -> None:
    """A JSON Schema as one text, through Spark's writer, so to any store."""
    spark.createDataFrame([(json.dumps(schema, ensure_ascii=False, sort_keys=True),)], "value string").coalesce(1).write.mode("overwrite").text(path)
