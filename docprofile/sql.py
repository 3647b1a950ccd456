"""SQL surface: profiles as views, and scalar functions for use in SQL text."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .functions.formats import FORMATS
from .operators.discover import Profile, discover, facts_of

FUNCTIONS = {
    "json_kind": "json_kind(v VARIANT) RETURNS STRING RETURN CASE WHEN is_variant_null(v) THEN 'null' WHEN schema_of_variant(v) LIKE 'OBJECT%' THEN 'object' WHEN schema_of_variant(v) LIKE 'ARRAY%' THEN 'array' WHEN schema_of_variant(v) = 'STRING' THEN 'string' WHEN schema_of_variant(v) = 'BOOLEAN' THEN 'boolean' WHEN v IS NOT NULL THEN 'number' END",
    "string_format": "string_format(s STRING) RETURNS STRING RETURN CASE " + " ".join(f"WHEN rlike(s, r'{p}') THEN '{n}'" for n, p in FORMATS.items()) + " END",
    "md5_bucket": "md5_bucket(k STRING, seed INT) RETURNS BIGINT RETURN CAST(conv(substr(md5(concat(k, ':', seed)), 1, 8), 16, 10) AS BIGINT) % 100",
}


def register(spark: SparkSession) -> None:
    """Temporary functions json_kind, string_format and md5_bucket."""
    for body in FUNCTIONS.values():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {body}")


def profile_view(spark: SparkSession, table: str, json_col: str, id_col: str, view: str, monoids="simple") -> Profile:
    """The profile of a table's or view's JSON column as a view `view` of what its states say, and `view`_keys of key counts."""
    docs = spark.table(table).select(F.col(id_col).alias("doc_id"), F.col(json_col).alias("json"))
    p = discover(docs, monoids)
    p.finished().createOrReplaceTempView(view)
    if p.keysets is not None:
        p.keysets.createOrReplaceTempView(f"{view}_keys")
    return p


def alternatives(docs: DataFrame) -> DataFrame:
    """typed_path with the engine's other sketches beside those of the monoids: approximate distinct values and quartiles."""
    f = facts_of(docs, ("num", "text")).where("kind in ('number', 'string')")
    return f.groupBy("typed_path").agg(F.approx_count_distinct("text", 0.02).alias("distinct"), F.percentile_approx("num", [0.25, 0.5, 0.75], 1000).alias("quartiles"), F.count(F.lit(1)).alias("n"))
