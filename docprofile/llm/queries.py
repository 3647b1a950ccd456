"""One query for each operator over its whole table, with production parameters, and SQL where SQL can say the same."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import ann, bpe, exact, kneser_ney, packing, pii, quality, secrets, simhash, warc
from .common import crc_mod

#: Key of the surrogates here; a deployment passes its own.
SURROGATE_KEY = b"surrogate key of the public test tables"


def _read(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def op1_nearest_vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ann.nearest(_read(spark, sf_dir, "embeddings"), lambda i: i % 50 == 0)


def op2_warc_round_trip(spark: SparkSession, sf_dir: str) -> DataFrame:
    return warc.round_trip(_read(spark, sf_dir, "pages"))


def quality_scorer(spark: SparkSession, docs: DataFrame, sf_dir: str):
    """Fitted on labels whose documents aren't held out."""
    labels = _read(spark, sf_dir, "labels")
    return quality.fit(docs, labels.where(crc_mod(F.col("doc_id"), 3) != 1))


def op3_quality_score(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _read(spark, sf_dir, "documents")
    return quality.score(docs, quality_scorer(spark, docs, sf_dir))


def op4_byte_bpe_round_trip(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.encode_decode(_read(spark, sf_dir, "documents"))


def op5_simhash_groups(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.near_groups(_read(spark, sf_dir, "documents"))


def op6_exact_groups(spark: SparkSession, sf_dir: str) -> DataFrame:
    return exact.classes(_read(spark, sf_dir, "documents")).drop("n_points", "copy")


def op7_packed_pieces(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.pack_documents(_read(spark, sf_dir, "documents"))


def op8_surrogates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pii.replace(_read(spark, sf_dir, "documents"), SURROGATE_KEY)


def op9_secret_spans(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secrets.scan(_read(spark, sf_dir, "documents"))


def op10_kneser_ney(spark: SparkSession, sf_dir: str) -> DataFrame:
    return kneser_ney.fit_score(_read(spark, sf_dir, "documents"))


QUERIES = {f.__name__: f for f in (op1_nearest_vectors, op2_warc_round_trip, op3_quality_score, op4_byte_bpe_round_trip, op5_simhash_groups, op6_exact_groups, op7_packed_pieces, op8_surrogates, op9_secret_spans, op10_kneser_ney)}

ORACLE_SQL = {
    "op2_warc_round_trip": r"""
with p as (select page_id, coalesce(html, '') as body from pages),
g as (select page_id, strlen(body) as payload_bytes, sha1(body) as sha, min(page_id) over (partition by body) as first_id from p)
select page_id, payload_bytes::bigint as payload_bytes,
  list_aggregate(list_transform(range(8), lambda i: list_aggregate(list_transform([15, 10, 5, 0], lambda s:
    substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567', (((('0x' || substr(sha, (5 * i + 1)::int, 5))::bigint >> s) & 31) + 1)::int, 1)), 'string_agg', '')), 'string_agg', '') as payload_digest,
  case when page_id = first_id then 'response' else 'revisit' end as record_type,
  case when page_id <> first_id then first_id end as refers_to
from g""",
    "op6_exact_groups": r"""
with d as (select doc_id, coalesce(text, '') as t, regexp_replace(coalesce(text, ''), '[\x20\x09-\x0D]', '', 'g') as n from documents),
w as (select doc_id, n, first_value(doc_id) over (partition by n order by length(t) desc, doc_id) as keep_id, count(*) over (partition by n) as group_size from d)
select doc_id, keep_id, group_size::bigint as group_size, doc_id = keep_id as kept, sha256(n) as text_sha256 from w""",
}
