"""Queries of the profile engine over the given tables, and DuckDB SQL for those that SQL can express."""

from __future__ import annotations

import json
import uuid
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .functions import formats, portable
from .functions.texts import bucket
from .operators import baselines, discover as D, extensions, measures, usecases
from .operators.discover import Profile, discover, facts_of
from .operators.flatten import flatten_typed, fold_arrow
from .operators.generate import generate
from .operators.validate import validate
from .plans.ground_truth import manifest_schema
from .plans.json_schema import to_json_schema
from .sources import workloads as W
from .sources.readers import table
from .sql import alternatives, profile_view, register
from .streaming import stream as S

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLE_SQL: dict[str, str] = {}


def query(sql: str | None = None):
    def put(f):
        QUERIES[f.__name__] = f
        if sql is not None:
            ORACLE_SQL[f.__name__] = sql
        return f

    return put


# --- the same documents and facts in DuckDB ---
EVENTS = """select event_id as doc_id, ('{"event_id":' || event_id || ',"ts":"' || strftime(ts, '%Y-%m-%dT%H:%M:%SZ') || '","user_id":' || user_id || ',"event_type":"' || event_type || '","props":' || props
  || case event_type when 'purchase' then ',"payload":{"amount":' || value::decimal(20,6) || '}' when 'error' then ',"payload":"E' || (event_id % 7) || '"'
     when 'click' then ',"payload":[' || (event_id % 1000) || ',' || (event_id % 700) || ']' when 'signup' then ',"payload":null' else '' end || '}')::json as j from events"""
THREADS = """select conv_id as doc_id, ('{"conv_id":' || conv_id || coalesce(',"system_prompt":' || to_json(max(case when role = 'system' then text end))::varchar, '') || ',"turns":['
  || string_agg('{"turn":' || turn || ',"role":"' || role || '","n":' || length(text) || case when turn > 0 then ',"reply_to":{"turn":' || (turn - 1) || '}' else '' end || '}', ',' order by turn) || ']}')::json as j
  from conversations group by conv_id"""
LABELLED = """select d.doc_id, ('{"doc_id":' || d.doc_id || ',"lang":"' || lang || '"' || coalesce(',"quality":' || quality || ',"toxic":' || toxic, '') || '}')::json as j from documents d left join labels l using (doc_id)"""
PAGES = """select page_id as doc_id, ('{"page_id":' || page_id || ',"url":' || to_json(url)::varchar || '}')::json as j from pages"""
CUSTOMERS = """select c_custkey as doc_id, ('{"c_custkey":' || c_custkey || ',"c_name":' || to_json(c_name)::varchar || ',"segment":' || to_json(c_mktsegment)::varchar || '}')::json as j from customer"""


def docs_labelled(spark: SparkSession, d: str) -> DataFrame:
    j = table(spark, d, "documents").join(table(spark, d, "labels"), "doc_id", "left")
    return j.select("doc_id", F.to_json(F.struct("doc_id", "lang", "quality", "toxic")).alias("json"))


def docs_urls(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "pages").select(F.col("page_id").alias("doc_id"), F.to_json(F.struct("page_id", "url")).alias("json"))


def docs_names(spark: SparkSession, d: str) -> DataFrame:
    return table(spark, d, "customer").select(F.col("c_custkey").alias("doc_id"), F.to_json(F.struct("c_custkey", "c_name", F.col("c_mktsegment").alias("segment"))).alias("json"))


KIND = "case json_type({0}) when 'OBJECT' then 'object' when 'ARRAY' then 'array' when 'VARCHAR' then 'string' when 'BOOLEAN' then 'boolean' when 'NULL' then 'null' else 'number' end"
LABEL = "case json_type({0}) when 'OBJECT' then 'object#' || substr(md5(array_to_string(list_sort(json_keys({0})), chr(31))), 1, 16) else " + KIND + " end"


def facts(docs: str, tag: str = KIND, then: str = "") -> str:
    """WITH clause of `node`, the facts of docs, ready for a select."""
    kids = """list_concat(case when kind = 'object' then list_transform(json_keys(j), lambda k: {'step': '.' || k, 'c': json_extract(j, '$."' || k || '"')}) else [] end,
      case when kind = 'array' then list_transform(range(json_array_length(j)::bigint), lambda i: {'step': '[*]', 'c': json_extract(j, '$[' || i || ']')}) else [] end)"""
    return f"""with recursive docs as ({docs}),
tree as (
  select doc_id, '$' as path, '' as ptp, '$' as step, '$<' || {tag.format('j')} || '>' as tp, {KIND.format('j')} as kind, j from docs
  union all
  select doc_id, path || x.step, tp, x.step, tp || x.step || '<' || {tag.format('x.c')} || '>', {KIND.format('x.c')}, x.c
  from (select doc_id, path, tp, unnest({kids}) as x from tree where kind in ('object', 'array'))),
node as (select doc_id, path, tp as typed_path, ptp as parent_typed_path, step, kind, j, case when kind = 'number' then j::varchar::double end as num, case when kind = 'string' then json_extract_string(j, '$') end as str,
  case when kind = 'object' then list_sort(json_keys(j)) end as keys, case when kind = 'array' then json_array_length(j)::int end as arr_len from tree){then}
"""


NUMBER_TEXT = "case when kind = 'number' then case when num = floor(num) then num::bigint::varchar end when kind = 'string' then to_json(str)::varchar end"

MINIMAL = "select typed_path, path, kind, count(*) as n from node group by all"


def _minimal(p: Profile) -> DataFrame:
    return p.nodes.select("typed_path", "path", "kind", "n")


# --- structure ---
@query(facts(EVENTS) + MINIMAL)
def minimal_schema(spark, d):
    return _minimal(discover(W.docs_events(spark, d), "minimum"))


@query(facts(THREADS) + MINIMAL)
def minimal_schema_nested(spark, d):
    return _minimal(discover(W.docs_threads(spark, d), "minimum"))


@query(facts(EVENTS) + MINIMAL)
def minimal_schema_variant_engine(spark, d):
    return _minimal(discover(W.docs_events(spark, d), "minimum", engine="variant", max_depth=4))


@query(facts(THREADS) + MINIMAL)
def minimal_schema_arrow_fold(spark, d):
    return fold_arrow(W.docs_threads(spark, d)).select("typed_path", "path", "kind", "n")


@query(facts(EVENTS, LABEL) + MINIMAL)
def label_schema(spark, d):
    return _minimal(discover(W.docs_events(spark, d), "minimum", "label"))


@query(facts(EVENTS, LABEL) + MINIMAL)
def label_schema_variant_engine(spark, d):
    return _minimal(discover(W.docs_events(spark, d), "minimum", "label", engine="variant", max_depth=4))


@query(facts(EVENTS) + """select case when kind = 'object' and path = '$' then '$<object#' || case when list_contains(keys, 'payload') then 'with' else 'without' end || '>' else path end as shape, count(*) as n
from node where path = '$' group by all""")
def user_equivalence(spark, d):
    p = discover(W.docs_events(spark, d), "minimum", lambda kind, keys: F.when(kind == "object", F.when(F.array_contains(keys, "payload"), "with").otherwise("without")))
    return p.nodes.where("path = '$'").select(F.col("typed_path").alias("shape"), "n")


@query(facts(EVENTS) + "select path, string_agg(distinct kind, ',' order by kind) as kinds, count(distinct kind) as alternatives from node group by path having count(distinct kind) > 1")
def type_alternatives(spark, d):
    n = discover(W.docs_events(spark, d), "minimum").nodes
    return n.groupBy("path").agg(F.array_join(F.array_sort(F.collect_set("kind")), ",").alias("kinds"), F.count_distinct("kind").alias("alternatives")).where("alternatives > 1")


@query("""with o as (select count(distinct l_orderkey) as n, count(*) as m from lineitem)
select '$<object>' as typed_path, n from o union all select '$<object>.l_orderkey<number>', n from o union all select '$<object>.rows<array>', n from o union all
select '$<object>.rows<array>[*]<array>', m from o union all select '$<object>.rows<array>[*]<array>[0]<number>', m from o union all select '$<object>.rows<array>[*]<array>[1]<number>', m from o union all
select '$<object>.rows<array>[*]<array>[2]<number>', m from o union all select '$<object>.rows<array>[*]<array>[3]<string>', m from o""")
def tuple_schema(spark, d):
    return discover(W.docs_tables(spark, d), ["maxmin_array"], tuples=True).nodes.select("typed_path", "n")


@query(facts(THREADS) + "select typed_path, count(*) as n, count(distinct doc_id) as documents from node group by typed_path")
def counting_types(spark, d):
    f = facts_of(W.docs_threads(spark, d), ())
    return f.groupBy("typed_path").agg(F.count(F.lit(1)).alias("n"), F.count_distinct("doc_id").alias("documents"))


@query("""select '$<object>' as typed_path, count(*) as n from part union all select '$<object>.p_name<string>', count(p_name) from part union all select '$<object>.p_partkey<number>', count(p_partkey) from part union all
select '$<object>.p_brand<string>', count(p_brand) from part union all select '$<object>.p_type<string>', count(p_type) from part union all select '$<object>.p_size<number>', count(p_size) from part union all select '$<object>.p_retailprice<number>', count(p_retailprice) from part""")
def typed_route(spark, d):
    return flatten_typed(table(spark, d, "part"), "p_partkey").groupBy("typed_path").agg(F.count(F.lit(1)).alias("n"))


@query(facts(EVENTS) + MINIMAL)
def tree_merge(spark, d):
    return _minimal(discover(W.docs_events(spark, d), "minimum", tree_fanin=4))


@query(facts(EVENTS) + "select typed_path, path, kind, count(*) as n, min(num) as number_min, max(num) as number_max from node group by all")
def merge_profiles(spark, d):
    docs = W.docs_events(spark, d)
    halves = [discover(docs.where(F.col("doc_id") % 2 == k), ["maxmin_number"]) for k in (0, 1)]
    return D.merge_profiles(*halves).nodes.select("typed_path", "path", "kind", "n", "number_min", "number_max")


@query(facts(EVENTS + " where ('0x' || substr(md5(event_id || ':0'), 1, 8))::bigint % 1000000 < 100000") + MINIMAL)
def sampled_discovery(spark, d):
    return _minimal(discover(W.docs_events(spark, d), "minimum", sample_fraction=0.1))


DEEP = 13


@query(f"""with e as (select count(*) as n, sum(event_id % 2)::bigint as odd from events)
select '$' || repeat('.k', i::int) as path, case when i = {DEEP} then 'number' else 'object' end as kind, case when i = {DEEP} then '' when i % 2 = 0 then 'even' else 'odd' end as level, n from e, range({DEEP + 1}) t(i)""")
def user_equivalence_deep(spark, d):
    open_, close = "".join('{"k":' for _ in range(DEEP)), "}" * DEEP
    docs = table(spark, d, "events").select(F.col("event_id").alias("doc_id"), F.concat(F.lit(open_), F.col("event_id").cast("string"), F.lit(close)).alias("json"))
    n = discover(docs, "minimum", lambda kind, keys: F.when(kind == "object", F.array_join(keys, "+"))).nodes
    depth = F.size(F.split("path", r"\.")) - 1
    return n.where("kind = 'number' or tag = 'object#k'").select("path", "kind", F.when(F.col("kind") == "number", "").when(depth % 2 == 0, "even").otherwise("odd").alias("level"), "n")


@query(facts(EVENTS) + MINIMAL)
def discover_string_ids(spark, d):
    docs = W.docs_events(spark, d).select(F.when(F.col("doc_id") % 3 > 0, F.concat(F.lit("e-"), F.col("doc_id"))).alias("doc_id"), "json")
    return _minimal(discover(docs, "simple"))


@query(facts(EVENTS) + "select event_type, typed_path, count(*) as n from node join events on doc_id = event_id group by cube (event_type, typed_path)")
def profile_cube(spark, d):
    f = facts_of(W.docs_events(spark, d), ())
    t = table(spark, d, "events").select(F.col("event_id").alias("doc_id"), "event_type")
    return f.join(t, "doc_id").cube("event_type", "typed_path").agg(F.count(F.lit(1)).alias("n"))


# --- monoids ---
@query(facts(EVENTS) + "select typed_path, min(num) as number_min, max(num) as number_max from node where kind = 'number' group by typed_path")
def maxmin_number(spark, d):
    return discover(W.docs_events(spark, d), ["maxmin_number"]).nodes.where("kind = 'number'").select("typed_path", "number_min", "number_max")


@query(facts(EVENTS) + "select typed_path, min(length(str))::int as string_min, max(length(str))::int as string_max from node where kind = 'string' group by typed_path")
def maxmin_string_length(spark, d):
    return discover(W.docs_events(spark, d), ["maxmin_string"]).nodes.where("kind = 'string'").select("typed_path", "string_min", "string_max")


@query(facts(THREADS) + "select typed_path, min(arr_len)::int as array_min, max(arr_len)::int as array_max from node where kind = 'array' group by typed_path")
def maxmin_array_length(spark, d):
    return discover(W.docs_threads(spark, d), ["maxmin_array"]).nodes.where("kind = 'array'").select("typed_path", "array_min", "array_max")


@query(facts(EVENTS) + "select typed_path, bool_and(len(list_distinct(json_extract(j, '$[*]')::varchar[])) = arr_len) as all_unique, bool_and(arr_len <= 1) as all_unique_capped from node where kind = 'array' group by typed_path")
def unique_items(spark, d):
    docs = W.docs_events(spark, d)
    f = facts_of(docs, ("uniq", "arr_len")).where("kind = 'array'")
    from .operators.monoids import unique

    return f.groupBy("typed_path").agg(unique().partial()["all_unique"].alias("all_unique"), unique(1).partial()["all_unique"].alias("all_unique_capped"))


@query(facts(CUSTOMERS) + """select typed_path, substr(lo, 1, list_max(list_filter(range(0, least(length(lo), length(hi)) + 1), lambda i: left(lo, i) = left(hi, i)))) as prefix,
reverse(substr(rlo, 1, list_max(list_filter(range(0, least(length(rlo), length(rhi)) + 1), lambda i: left(rlo, i) = left(rhi, i))))) as suffix
from (select typed_path, min(str) as lo, max(str) as hi, min(reverse(str)) as rlo, max(reverse(str)) as rhi from node where kind = 'string' group by typed_path)""")
def pattern_prefix_suffix(spark, d):
    return discover(docs_names(spark, d), ["pattern"]).finished().where("kind = 'string'").select("typed_path", "prefix", "suffix")


FORMAT_CASE = "case " + " ".join(f"when regexp_matches(str, '{p}') then '{n}'" for n, p in formats.FORMATS.items()) + " end"
FORMAT_SQL = "select typed_path, case when count(label) = count(*) and min(label) = max(label) then min(label) end as format from (select typed_path, " + FORMAT_CASE + " as label from node where kind = 'string') group by typed_path"


@query(facts(PAGES) + FORMAT_SQL)
def format_detect(spark, d):
    return discover(docs_urls(spark, d), ["format"]).finished().where("kind = 'string'").select("typed_path", "format")


@query(facts(EVENTS) + FORMAT_SQL)
def format_combined(spark, d):
    f = facts_of(W.docs_events(spark, d), ("str",)).where("kind = 'string'")
    from .operators.monoids import format_

    m = format_("combined")
    states = f.groupBy("typed_path").agg(*[c.alias(k) for k, c in m.partial().items()])
    return states.select("typed_path", m.finish()["format"].alias("format"))


@query(facts(EVENTS) + FORMAT_SQL)
def format_early_stop(spark, d):
    import pyarrow as pa

    def fold(batches):
        for b in batches:
            got = formats.labels_early_stop(b.column(0).to_pylist(), b.column(1).to_pylist())
            yield pa.RecordBatch.from_arrays([pa.array([p for p, _ in got], pa.string()), pa.array([v for _, v in got], pa.string())], ["typed_path", "label"])

    parts = facts_of(W.docs_events(spark, d), ("str",)).where("kind = 'string'").select("typed_path", "str").mapInArrow(fold, "typed_path string, label string")
    return parts.groupBy("typed_path").agg(F.when((F.count("label") == F.count(F.lit(1))) & (F.min("label") == F.max("label")), F.min("label")).alias("format"))


STATS_SQL = """select typed_path, count(*) as n, round(avg(num), 4) as mean, round(stddev_pop(num), 4) as stddev, case when m2 > 0 then round(avg(power(num - m, 3)) / power(any_value(m2), 1.5), 4) end as skewness, case when m2 > 0 then round(avg(power(num - m, 4)) / (any_value(m2) * any_value(m2)) - 3, 4) end as kurtosis
from (select typed_path, num, avg(num) over (partition by typed_path) as m, var_pop(num) over (partition by typed_path) as m2 from node where kind = 'number') group by typed_path, m2"""


def _stats(p: Profile) -> DataFrame:
    return p.finished().where("kind = 'number'").select("typed_path", "n", *[F.round(c, 4).alias(c) for c in ("mean", "stddev", "skewness", "kurtosis")])


@query(facts(EVENTS) + STATS_SQL)
def stats_moments(spark, d):
    return _stats(discover(W.docs_events(spark, d), ["stats"]))


@query(facts(EVENTS) + STATS_SQL)
def stats_moments_merged(spark, d):
    docs = W.docs_events(spark, d)
    return _stats(D.merge_all([discover(docs.where(F.col("doc_id") % 3 == k), ["stats"]) for k in range(3)]))


SECONDS = """select event_id as doc_id, ('{"t":' || floor(epoch(ts))::bigint || '}')::json as j from events"""


@query(facts(SECONDS) + STATS_SQL.replace("round(avg(num), 4) as mean, round(stddev_pop(num), 4)", "round(avg(num), 1) as mean, round(stddev_pop(num), 1)"))
def stats_large_offset(spark, d):
    docs = table(spark, d, "events").select(F.col("event_id").alias("doc_id"), F.concat(F.lit('{"t":'), F.unix_timestamp(F.col("ts").cast("timestamp")).cast("string"), F.lit("}")).alias("json")).repartition(7)
    got = discover(docs, ["stats"]).finished().where("kind = 'number'")
    return got.select("typed_path", "n", *[F.round(c, k).alias(c) for c, k in (("mean", 1), ("stddev", 1), ("skewness", 4), ("kurtosis", 4))])


@query("""with v as (unpivot (select l_orderkey::double as l_orderkey, l_partkey::double as l_partkey, l_suppkey::double as l_suppkey, l_linenumber::double as l_linenumber, l_quantity, l_extendedprice, l_discount, l_tax, l_linenumber * 6.0 as qty_pack from lineitem) on columns(*) into name k value x)
select '$<object>.' || k || '<number>' as typed_path, case when bool_and(x = floor(x)) then list_reduce(list(distinct x::bigint), lambda a, b: gcd(a, b)) end as divisor, bool_and(x = floor(x)) as integers from v group by k""")
def multiple_of(spark, d):
    return discover(W.docs_lines(spark, d), ["multiple"]).divisors


@query(facts(EVENTS) + "select typed_path, unnest(keys) as key, count(*) as n, any_value(o) as objects from (select *, count(*) over (partition by typed_path) as o from node where kind = 'object') group by typed_path, key")
def attribute_counts(spark, d):
    return D.attribute_counts(discover(W.docs_events(spark, d), ["attribute_counts"]).keysets).drop("share")


@query(facts(THREADS) + "select typed_path, key from (select typed_path, unnest(keys) as key, o from (select *, count(*) over (partition by typed_path) as o from node where kind = 'object')) group by typed_path, key, o having count(*) = o")
def required_keys(spark, d):
    return D.required_keys(discover(W.docs_threads(spark, d), ["required"]).keysets)


DEPENDS = """,
k as (select typed_path, row_number() over () as node_id, keys from node where kind = 'object'),
e as (select typed_path, node_id, unnest(keys) as key from k),
c as (select typed_path, key, count(*) as n from e group by all), o as (select typed_path, count(*) as objects from k group by all),
pairs as (select x.typed_path, x.key as a, y.key as b, count(*) as together from e x join e y on x.typed_path = y.typed_path and x.node_id = y.node_id and x.key <> y.key group by all)"""


@query(facts(THREADS, then=DEPENDS) + "select p.typed_path, a, b from pairs p join c on c.typed_path = p.typed_path and c.key = a join o on o.typed_path = p.typed_path where together = c.n and c.n < objects")
def dependencies_directional(spark, d):
    return D.dependencies(discover(W.docs_threads(spark, d), ["dependencies"]).keysets)


@query(facts(LABELLED, then=DEPENDS) + "select p.typed_path, a, b from pairs p join c on c.typed_path = p.typed_path and c.key = a join c c2 on c2.typed_path = p.typed_path and c2.key = b join o on o.typed_path = p.typed_path where together = c.n and c.n = c2.n and c.n < objects")
def dependencies_mutual(spark, d):
    return D.dependencies(discover(docs_labelled(spark, d), ["dependencies"]).keysets, "mutual")


@query(facts(LABELLED, then=DEPENDS) + """, m as (select p.typed_path, a, b from pairs p join c on c.typed_path = p.typed_path and c.key = a join c c2 on c2.typed_path = p.typed_path and c2.key = b join o on o.typed_path = p.typed_path where together = c.n and c.n = c2.n and c.n < objects)
select typed_path, string_agg(a, ',' order by a) as keys from (select typed_path, a, least(a, min(b)) as g from m group by typed_path, a) group by typed_path, g""")
def attribute_groups(spark, d):
    got = D.attribute_groups(discover(docs_labelled(spark, d), ["dependencies"]).keysets)
    return spark.createDataFrame([(p, ",".join(k)) for p, k in got], "typed_path string, keys string")


@query(facts(EVENTS) + "select typed_path, key, example from (select typed_path, md5(doc_id || typed_path) as key, " + NUMBER_TEXT + " as example, row_number() over (partition by typed_path order by md5(doc_id || typed_path), " + NUMBER_TEXT + ") as r from node where kind in ('number', 'string') and step <> '.amount') where r <= 5")
def examples_bottomk(spark, d):
    f = facts_of(W.docs_events(spark, d), ("text",)).where("kind in ('number', 'string') and step <> '.amount'")
    return D.bottom_k(f, 5, key=F.md5(F.concat(F.col("doc_id").cast("string"), "typed_path"))).select("typed_path", "key", "example")


@query()
def examples_slots(spark, d):
    return discover(W.docs_events(spark, d), ["examples"]).examples.select("typed_path", "example")


@query()
def examples_distinct(spark, d):
    return D.bottom_k(facts_of(W.docs_events(spark, d), ("text",)), 20, distinct=True)


HLL = f""",
v as (select typed_path, {NUMBER_TEXT} as text from node where kind in ('number', 'string') and step <> '.amount'),
h as (select typed_path, ('0x' || substr(md5(text), 1, 8))::bigint % {portable.REGISTERS} as register, max(case when ('0x' || substr(md5(text), 9, 8))::bigint = 0 then 33 else 32 - floor(log2(('0x' || substr(md5(text), 9, 8))::bigint)) end) as rank from v group by all),
s as (select typed_path, sum(power(2.0, -rank)) as s, {portable.REGISTERS} - count(*) as zero from h group by all),
est as (select typed_path, round(case when {0.7213 / (1 + 1.079 / portable.REGISTERS) * portable.REGISTERS**2} / (s + zero) <= {2.5 * portable.REGISTERS} and zero > 0 then {portable.REGISTERS} * ln({float(portable.REGISTERS)} / zero) else {0.7213 / (1 + 1.079 / portable.REGISTERS) * portable.REGISTERS**2} / (s + zero) end)::bigint as estimate from s)"""


@query(facts(EVENTS, then=HLL) + "select typed_path, estimate from est")
def hll_portable(spark, d):
    return portable.hll_estimate(portable.hll_registers(facts_of(W.docs_events(spark, d), ("text",)).where("step <> '.amount'")))


@query(facts(EVENTS, then=HLL) + f"select est.typed_path, n, estimate from est join (select typed_path, count(*) as n from v group by all) using (typed_path) where n = (select count(*) from docs) and abs(estimate - n) <= {3 * portable.standard_error()} * n")
def primary_keys(spark, d):
    f = facts_of(W.docs_events(spark, d), ("text",)).where("step <> '.amount'")
    n = f.where("text is not null").groupBy("typed_path").agg(F.count(F.lit(1)).alias("n"))
    docs = table(spark, d, "events").count()
    return portable.hll_estimate(portable.hll_registers(f)).join(n, "typed_path").where(F.col("n") == docs).where(F.abs(F.col("estimate") - F.col("n")) <= 3 * portable.standard_error() * F.col("n")).select("typed_path", "n", "estimate")


@query()
def hll_native(spark, d):
    return discover(W.docs_events(spark, d), ["hll"]).finished().select("typed_path", "n", "distinct")


BLOOM = f""",
v as (select distinct typed_path, {NUMBER_TEXT} as text from node where kind in ('number', 'string')),
bits as (select distinct typed_path, (('0x' || substr(md5(text), 1, 8))::bigint + ('0x' || substr(md5(text), 9, 8))::bigint * i) % {portable.BITS} as bit from v, range({portable.HASHES}) t(i))"""


@query(facts(LABELLED, then=BLOOM) + "select typed_path, count(*) as bits, sum(bit)::bigint as total from bits group by typed_path")
def bloom_portable(spark, d):
    b = portable.bloom_bits(facts_of(docs_labelled(spark, d), ("text",)))
    return b.groupBy("typed_path").agg(F.count(F.lit(1)).alias("bits"), F.sum("bit").alias("total"))


@query(facts(LABELLED, then=BLOOM) + """, n as (select typed_path, count(*) as n from bits group by all) select a.typed_path as child, b.typed_path as parent from bits a join bits b on a.bit = b.bit and a.typed_path <> b.typed_path join n on n.typed_path = a.typed_path group by a.typed_path, b.typed_path, n.n having count(*) = n.n""")
def bloom_subset(spark, d):
    return portable.bloom_subset(portable.bloom_bits(facts_of(docs_labelled(spark, d), ("text",))))


@query(facts(LABELLED) + ", v as (select distinct typed_path, " + NUMBER_TEXT + """ as text from node where typed_path = '$<object>.doc_id<number>')
select typed_path, text, true as member from v union all select typed_path, 'no ' || text, false from v""")
def bloom_membership(spark, d):
    # the filter has room for a thousand times these values, so that a false member isn't to be expected
    p = discover(docs_labelled(spark, d), ["bloom"], bloom_expected=10_000_000)
    v = facts_of(docs_labelled(spark, d), ("text",)).where("typed_path = '$<object>.doc_id<number>'").select("typed_path", "text").distinct()
    return D.bloom_contains(p.bloom, v.unionByName(v.withColumn("text", F.concat(F.lit("no "), "text"))), 10_000_000)


@query(facts(LABELLED, then=BLOOM) + "select typed_path, true as within from v group by typed_path")
def bloom_rate(spark, d):
    """The measured rate of false members is at most twice the one that was asked for."""
    docs = docs_labelled(spark, d)
    p = discover(docs, ["bloom"], bloom_expected="estimate")
    asked = spark.range(20_000).select(F.concat(F.lit("no such value "), "id").alias("text"))
    found = D.bloom_contains(p.bloom, p.bloom.select("typed_path").distinct().crossJoin(asked), p.options["bloom_expected"])  # paths of a schema
    return found.groupBy("typed_path").agg((F.avg(F.col("member").cast("double")) <= 2 * D.BLOOM_FPP).alias("within"))


@query()
def bloom_native(spark, d):
    return discover(W.docs_events(spark, d), ["bloom"]).bloom.select("typed_path", "bucket", F.bitmap_count("bits").alias("set"))


@query()
def histogram_native(spark, d):
    return discover(W.docs_events(spark, d), ["histogram"]).nodes.where("kind = 'number'").select("typed_path", F.size("bins").alias("bins"), F.aggregate("bins", F.lit(0.0), lambda a, b: a + b["y"].cast("double")).alias("n"))


@query(facts(EVENTS) + "select typed_path, count(*)::double as n, least(100, count(distinct num))::int as bins from node where kind = 'number' group by typed_path")
def histogram_merged(spark, d):
    docs = W.docs_events(spark, d)
    p = D.merge_profiles(*[discover(docs.where(F.col("doc_id") % 2 == k), ["histogram"]) for k in (0, 1)])
    return p.nodes.where("kind = 'number'").select("typed_path", F.aggregate("bins", F.lit(0.0), lambda a, b: a + b["y"]).alias("n"), F.least(F.lit(100), F.size("bins")).cast("int").alias("bins"))


# --- validation, measures ---
@query("""with t as (select event_id as doc_id, props::json ->> 'k' as k, ('0x' || substr(md5(event_id || ':0'), 1, 8))::bigint % 100 as b from events), r as (select min(k::double) as lo, max(k::double) as hi from t where b < 1)
select doc_id, k::double between lo and hi as valid from t, r where b >= 90""")
def validate_docs(spark, d):
    train, test = measures.split(W.docs_props(spark, d), 1)
    return validate(test, discover(train, ["maxmin_number"])).select("doc_id", "valid")


@query("select (('0x' || substr(md5(event_id || ':0'), 1, 8))::bigint % 100)::bigint as bucket, count(*) as n from events group by 1")
def overfit_split(spark, d):
    return W.docs_events(spark, d).groupBy(bucket(F.col("doc_id"), 0).alias("bucket")).agg(F.count(F.lit(1)).alias("n"))


@query("select 1.0::double as accepted, count(*) as documents from events")
def soundness(spark, d):
    docs = W.docs_events(spark, d)
    return measures.soundness(docs, discover(docs, "all"))


@query("select 1.0::double as accepted, count(*) as documents from events")
def soundness_label(spark, d):
    docs = W.docs_events(spark, d)
    return measures.soundness(docs, discover(docs, "simple", "label"))


@query(facts(EVENTS, LABEL) + """select 'label' as equivalence, count(distinct typed_path) as typed_paths, count(distinct path) as paths from node
union all select 'kind', (select count(*) from (select distinct regexp_replace(typed_path, '#[0-9a-f]{16}', '', 'g') from node)), (select count(distinct path) from node)""")
def schema_size(spark, d):
    docs = W.docs_events(spark, d)
    one = lambda e: measures.schema_size(discover(docs, "minimum", e)).select(F.lit(e).alias("equivalence"), "typed_paths", "paths")
    return one("label").unionByName(one("kind"))


@query()
def ground_truth_rejects(spark, d):
    return measures.ground_truth_filter(W.docs_manifests(spark, d), manifest_schema(spark))[1].select("doc_id")


def _clean_manifests(spark, d):
    return measures.ground_truth_filter(W.docs_manifests(spark, d), manifest_schema(spark))[0]


@query()
def accuracy_sampled(spark, d):
    return measures.accuracy(discover(_clean_manifests(spark, d), measures.FULL), manifest_schema(spark), 500, "sampled")


@query()
def accuracy_random(spark, d):
    return measures.accuracy(discover(_clean_manifests(spark, d), measures.FULL), manifest_schema(spark), 500, "random")


@query()
def overfit(spark, d):
    return measures.overfit(_clean_manifests(spark, d))


@query()
def baseline_accuracy(spark, d):
    return measures.baseline_report(_clean_manifests(spark, d), manifest_schema(spark), 300)


@query()
def acceptance_by_share(spark, d):
    docs, out = W.docs_manifests(spark, d), None
    for preset in ("minimum", "simple"):
        for share in (1, 50, 90):
            row = measures.acceptance(docs, preset, share).select(F.lit(preset).alias("preset"), "share", "accepted")
            out = row if out is None else out.unionByName(row)
    return out


@query()
def generated_documents(spark, d):
    return generate(discover(W.docs_manifests(spark, d), ["examples"]), 100)


@query()
def sketch_error(spark, d):
    return measures.sketch_error(W.docs_events(spark, d))


@query()
def json_schema_text(spark, d):
    schema = to_json_schema(discover(W.docs_products(spark, d), "all"))
    return spark.createDataFrame([(json.dumps(schema, sort_keys=True),)], "schema string")


# --- baselines ---
@query(facts(EVENTS) + "select typed_path, kind, count(*) as n from node group by all")
def type_fusion_kind(spark, d):
    return baselines.type_fusion(W.docs_events(spark, d))


@query(facts(EVENTS, LABEL) + "select distinct typed_path, kind from node")
def type_fusion_label(spark, d):
    return baselines.type_fusion(W.docs_events(spark, d), "label", counts=False)


@query(facts(THREADS) + "select path, count(*) as n from node group by path")
def structure_graph_nodes(spark, d):
    return baselines.structure_graph(W.docs_threads(spark, d))[0]


@query(facts(THREADS) + "select left(path, length(path) - length(step)) as parent, path, count(*) as n from node where path <> '$' group by all")
def structure_graph_edges(spark, d):
    return baselines.structure_graph(W.docs_threads(spark, d))[1]


@query(facts(THREADS) + "select path, count(*) as n, array_to_string(list_sort(list(distinct doc_id)), ',') as documents from node group by path")
def structure_graph_full(spark, d):
    return baselines.structure_graph(W.docs_threads(spark, d), reduced=False)[0].withColumn("documents", F.array_join("documents", ","))


@query(facts(LABELLED, then=DEPENDS) + "select typed_path, string_agg(key, ',' order by key) filter (n = objects) as required, string_agg(key, ',' order by key) as properties from c join o using (typed_path) group by typed_path")
def entity_split(spark, d):
    e = baselines.entity_split(docs_labelled(spark, d))
    return e.select("typed_path", F.array_join("required", ",").alias("required"), F.array_join("properties", ",").alias("properties"))


@query()
def native_inference(spark, d):
    return baselines.native(W.docs_events(spark, d))


@query("""select 'user' as name, count(user_id) as present, count(*) as documents, count(distinct user_id) as "distinct", min(user_id::varchar) as least, max(user_id::varchar) as greatest from events
union all select 'kind', count(event_type), count(*), count(distinct event_type), min(event_type), max(event_type) from events""")
def adhoc_presence(spark, d):
    return baselines.adhoc(W.docs_events(spark, d), {"user": "$.user_id", "kind": "$.event_type"})


PROPS_DOCS = """select event_id as doc_id, props::json as j from events"""


def _preset(name: str):
    """A query of what a preset says of a collection."""
    def put(spark, d):
        p = discover(W.docs_props(spark, d), name).finished()
        more = [F.round(c, 6).alias(c) for c in ("mean", "stddev")] if name == "all" else []
        return p.select("typed_path", "n", "number_min", "number_max", "integers", "divisor", *more)

    put.__name__ = f"preset_{name}"
    return put


# --- the collections ---
def _flat(source: str, columns: dict[str, str], of: str = "$<object>") -> str:
    return " union all ".join([f"select '{of}' as typed_path, count(*) as n from {source}", *[f"select '{of}.{c}<{kind}>', count({c}) from {source}" for c, kind in columns.items()]])


def _counts(name: str):
    """A query of a collection's typed paths and counts."""
    def put(spark, d):
        return discover(W.WORKLOADS[name](spark, d), "minimum").nodes.select("typed_path", "n")

    put.__name__ = f"collection_{name}"
    return put


WORDS = "(select coalesce(sum(len(list_filter(regexp_split_to_array(lower(text), '[^\\p{L}]+')[1:5], lambda w: w <> ''))), 0)::bigint from documents)"
query("select typed_path, n from (" + " union all ".join((
    _flat("documents", {"doc_id": "number", "lang": "string", "source": "string", "n_chars": "number"}),
    "select '$<object>.keywords<array>', count(text) from documents", f"select '$<object>.keywords<array>[*]<string>', {WORDS}",
    _flat("(select l.* from labels l join documents d using (doc_id))", {"quality": "number", "toxic": "number"}, "$<object>.labels<object>"))) + ") where n > 0")(_counts("articles"))
query("select typed_path, n from (" + " union all ".join((
    _flat("supplier", {"s_suppkey": "number", "s_name": "string", "s_acctbal": "number"}), _flat("(select n_name as nation, r_name as region from supplier join nation on s_nationkey = n_nationkey join region on n_regionkey = r_regionkey)", {"nation": "string", "region": "string"}, "$<object>.place<object>"),
    "select '$<object>.parts<array>', count(*) from supplier", "select '$<object>.parts<array>[*]<number>', sum(least(20, k))::bigint from (select count(distinct l_partkey) as k from lineitem join supplier on l_suppkey = s_suppkey group by l_suppkey)")) + ") where n > 0")(_counts("suppliers"))
query("""with h as (select distinct user_id, strftime(ts, '%a') || '-' || hour(ts) as h from events) select '$<object>' as typed_path, count(distinct coalesce(user_id, -1)) as n from h union all select '$<object>.user_id<number>', count(distinct user_id) from h
union all select '$<object>.hours<object>', count(distinct coalesce(user_id, -1)) from h union all select '$<object>.hours<object>."' || h || '"<number>', count(*) from h group by h""")(_counts("checkins"))
query(_flat("part", {"p_partkey": "number", "p_name": "string", "p_brand": "string", "p_type": "string", "p_size": "number", "p_retailprice": "number"}))(_counts("parts"))
query(_flat("conversations", {"conv_id": "number", "turn": "number", "role": "string", "text": "string"}))(_counts("turns"))
query("select typed_path, n from (" + " union all ".join((
    _flat("(select *, c_mktsegment as segment, 0 as n_orders from customer)", {"c_custkey": "number", "c_name": "string", "c_acctbal": "number", "segment": "string", "n_orders": "number"}),
    "select '$<object>.orders<array>', count(*) from customer", "select '$<object>.orders<array>[*]<number>', sum(least(1000, k))::bigint from (select count(*) as k from orders join customer on o_custkey = c_custkey group by o_custkey)")) + ") where n > 0")(_counts("customers"))
query("select typed_path, n from (" + _flat("(select page_id, url, length(html) as html_len, nullif(regexp_extract(html, '<html lang=\"([a-z]+)\"', 1), '') as lang from pages)", {"page_id": "number", "url": "string", "html_len": "number", "lang": "string"}) + ") where n > 0")(_counts("pages"))
query(_flat("region", {"r_regionkey": "number", "r_name": "string"}))(_counts("regions"))
query(_flat("nation", {"n_nationkey": "number", "n_name": "string", "n_regionkey": "number"}))(_counts("nations"))
query(_flat("benchmark", {"item_id": "number", "text": "string"}))(_counts("benchmark"))
query(facts(PROPS_DOCS) + """select typed_path, count(*) as n, min(num) as number_min, max(num) as number_max, bool_and(num = floor(num)) as integers, case when kind = 'number' then list_reduce(list(distinct num::bigint), lambda a, b: gcd(a, b)) end as divisor, count(distinct num) filter (kind = 'number') as values
from node group by typed_path, kind""".replace(", count(distinct num) filter (kind = 'number') as values", ""))(_preset("simple"))
query(facts(PROPS_DOCS) + """select typed_path, count(*) as n, min(num) as number_min, max(num) as number_max, bool_and(num = floor(num)) as integers, case when kind = 'number' then list_reduce(list(distinct num::bigint), lambda a, b: gcd(a, b)) end as divisor,
round(avg(num), 6) as mean, round(stddev_pop(num), 6) as stddev from node group by typed_path, kind""")(_preset("all"))


# --- uses ---
@query("""select 'l_partkey in p_partkey' as name, count(*) as missing from (select distinct l_partkey from lineitem) where l_partkey not in (select p_partkey from part)
union all select 'o_orderkey in l_orderkey', count(*) from orders where o_orderkey not in (select l_orderkey from lineitem)
union all select 'user_id in c_custkey', count(*) from (select distinct user_id from events where user_id is not null) where user_id not in (select c_custkey from customer)""")
def foreign_keys_verified(spark, d):
    out = None
    for name, (t1, c1), (t2, c2) in (("l_partkey in p_partkey", ("lineitem", "l_partkey"), ("part", "p_partkey")), ("o_orderkey in l_orderkey", ("orders", "o_orderkey"), ("lineitem", "l_orderkey")), ("user_id in c_custkey", ("events", "user_id"), ("customer", "c_custkey"))):
        one = usecases.verify_inclusion(table(spark, d, t1).select(F.col(c1).alias("value")), table(spark, d, t2).select(F.col(c2).alias("value"))).select(F.lit(name).alias("name"), "missing")
        out = one if out is None else out.unionByName(one)
    return out


KEYS = ["hll", "bloom", "maxmin", "multiple"]


@query()
def foreign_keys_bloom(spark, d):
    p = discover(W.docs_products(spark, d), KEYS)
    return usecases.rank_foreign_keys(p, usecases.foreign_keys(p))


@query()
def primary_keys_ranked(spark, d):
    docs = W.docs_products(spark, d)
    p = discover(docs, KEYS)
    return usecases.rank_keys(p, usecases.primary_keys(p, docs.count()))


@query(facts(EVENTS) + "select doc_id, typed_path, num as value from (select *, avg(num) over w as m, stddev_pop(num) over w as s from node where kind = 'number' window w as (partition by typed_path)) where s > 0 and abs(num - m) / s > 2.5")
def value_outliers(spark, d):
    docs = W.docs_events(spark, d)
    return usecases.value_outliers(docs, discover(docs, ["stats"]), 2.5).select("doc_id", "typed_path", "value")


@query(facts(THREADS) + "select doc_id, typed_path, length(str)::double as value from (select *, avg(length(str)) over w as m, stddev_pop(length(str)) over w as s from node where kind = 'string' window w as (partition by typed_path)) where s > 0 and abs(length(str) - m) / s > 2")
def length_outliers(spark, d):
    return usecases.length_outliers(W.docs_threads(spark, d), "string", 2.0).select("doc_id", "typed_path", "value")


@query(facts(THREADS) + """select typed_path, key, count(*) as n, any_value(o) as objects, case when count(*) <= 0.3 * any_value(o) then 'rare' else 'nearly always' end as what from (select typed_path, unnest(keys) as key, o from (select *, count(*) over (partition by typed_path) as o from node where kind = 'object'))
group by typed_path, key having count(*) <= 0.3 * any_value(o) or (count(*) < any_value(o) and count(*) >= 0.7 * any_value(o))""")
def structural_outliers(spark, d):
    return usecases.structural_outliers(discover(W.docs_threads(spark, d), ["attribute_counts"]), 0.3).drop("share")


@query("""with v as (select value as x, (event_type = 'purchase')::int as a from events where event_type in ('purchase', 'click') and value is not null),
c as (select x, sum(a) as a, count(*) - sum(a) as b from v group by x), n as (select sum(a) as na, sum(b) as nb from c),
g as (select max(abs(sa / na - sb / nb)) as gap from (select sum(a) over (order by x) as sa, sum(b) over (order by x) as sb from c), n)
select round(gap, 9) as gap, na::double as n_a, nb::double as n_b from g, n""")
def ks_exact(spark, d):
    e = table(spark, d, "events").where("value is not null")
    side = lambda t: e.where(F.col("event_type") == t).select(F.col("value").alias("x"))
    return usecases.ks_exact(side("purchase"), side("click")).select(F.round("gap", 9).alias("gap"), "n_a", "n_b")


@query()
def ks_histogram(spark, d):
    docs = W.docs_events(spark, d)
    late = table(spark, d, "events").select(F.col("event_id").alias("doc_id"), (F.col("event_id") % 2).alias("half"))
    parts = [discover(docs.join(late.where(F.col("half") == k), "doc_id").select("doc_id", "json"), ["histogram"]) for k in (0, 1)]
    return usecases.ks_test(*parts, "$.payload.amount")


OUTLYING = "(select doc_id, typed_path, num, abs(num - m) / s as dev from (select *, avg(num) over w as m, stddev_pop(num) over w as s from node where kind = 'number' window w as (partition by typed_path)) where s > 0 and abs(num - m) / s > 2)"


@query(facts(EVENTS) + "select doc_id, count(*) as n, string_agg(typed_path, ';' order by typed_path, num) as paths from " + OUTLYING + " group by doc_id")
def document_outliers(spark, d):
    docs = W.docs_events(spark, d)
    return usecases.document_outliers(docs, discover(docs, ["stats"]), 2.0).select("doc_id", "n", F.array_join(F.transform("outliers", lambda o: o["typed_path"]), ";").alias("paths"))


@query(facts(EVENTS) + "select doc_id, round(sum(dev - 2), 5) as score from " + OUTLYING + " group by doc_id")
def document_outlier_score(spark, d):
    docs = W.docs_events(spark, d)
    return usecases.outlier_score(docs, discover(docs, ["stats"]), 2.0).select("doc_id", F.round("score", 5).alias("score"))


@query()
def normalize_hints(spark, d):
    docs = W.docs_products(spark, d)
    p = discover(docs, KEYS)
    return usecases.normalize_hints(p, usecases.primary_keys(p, docs.count()), usecases.foreign_keys(p))


@query()
def sizing(spark, d):
    return usecases.sizing(discover(W.docs_events(spark, d), ["maxmin"]))


@query(facts(THREADS) + "select typed_path, key, round(count(*)::double / any_value(o), 9) as share from (select typed_path, unnest(keys) as key, o from (select *, count(*) over (partition by typed_path) as o from node where kind = 'object')) group by typed_path, key")
def presence(spark, d):
    return usecases.presence(discover(W.docs_threads(spark, d), ["attribute_counts"])).withColumn("share", F.round("share", 9))


# --- streaming ---
def _events_stream(spark, d):
    whole = table(spark, d, "events")
    e = spark.readStream.schema(whole.schema).parquet(f"{d}/event[s].parquet")
    return e.select(F.col("event_id").alias("doc_id"), F.col("props").alias("json"), F.col("ts").cast("timestamp").alias("ts"))


PROPS = """select event_id as doc_id, props::json as j from events"""


@query(facts(PROPS) + MINIMAL)
def stream_profile(spark, d):
    name = f"profile_{uuid.uuid4().hex}"
    q = S.discover_stream(_events_stream(spark, d).select("doc_id", "json"), "minimum", name=name)
    q.awaitTermination()
    return spark.table(name).select("typed_path", "path", "kind", "n")


@query(facts(PROPS) + """, k as (select typed_path, any_value(kind) as kind, count(*) as n, min(num) as number_min, max(num) as number_max, count(distinct num) as values, round(avg(num), 6) as mean, round(stddev_pop(num), 6) as stddev from node group by typed_path)
select typed_path, kind, n, number_min, number_max, mean, stddev, case when kind = 'number' then 'integers' end as what from k""")
def stream_all(spark, d):
    """Every monoid over a feed, folded batch by batch."""
    fold = S.Fold(spark, f"{_home(spark)}/fold-{uuid.uuid4().hex}", "all")
    S.fold_stream(_events_stream(spark, d).select("doc_id", "json"), fold).awaitTermination()
    p = fold.load().finished()
    return p.select("typed_path", "kind", "n", "number_min", "number_max", F.round("mean", 6).alias("mean"), F.round("stddev", 6).alias("stddev"), F.when(F.col("integers"), "integers").alias("what"))


def _home(spark) -> str:
    """The folder that the session names for its tables."""
    return (spark.conf.get("spark.checkpoint.dir", None) or spark.conf.get("spark.sql.warehouse.dir")).rstrip("/")


@query("""select strftime(date_trunc('day', ts), '%Y-%m-%d') as day, count(*) as n from events group by 1""")
def stream_windows(spark, d):
    name = f"windows_{uuid.uuid4().hex}"
    q = S.windowed(_events_stream(spark, d)).writeStream.outputMode("complete").format("memory").queryName(name).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.table(name).groupBy(F.date_format("window.start", "yyyy-MM-dd").alias("day")).agg(F.sum("n").alias("n"))


# --- extensions ---
PART_COLUMNS = ("p_partkey", "p_name", "p_brand", "p_type", "p_size", "p_retailprice")
FD_SQL = " union all ".join(f"select '$.{a}' as a, '$.{b}' as b where (select coalesce(max(k), 0) from (select count(distinct {b}) as k from part where {b} is not null group by {a})) = 1" for a in PART_COLUMNS for b in PART_COLUMNS if a != b)


@query(FD_SQL)
def functional_dependencies(spark, d):
    return extensions.functional_dependencies(W.docs_parts(spark, d))


@query("select event_type, count(distinct typed_path) as variants from (" + facts(EVENTS, LABEL) + " select doc_id, typed_path from node where step = '$') join events on doc_id = event_id group by event_type")
def schema_variants(spark, d):
    t = table(spark, d, "events").select(F.col("event_id").alias("doc_id"), "event_type")
    docs = W.docs_events(spark, d).join(t, "doc_id")
    v = extensions.variants_over_time(docs, F.col("event_type"))
    return v.groupBy(F.col("window").alias("event_type")).agg(F.count_distinct("typed_path").alias("variants"))


@query(facts(CUSTOMERS) + "select typed_path, regexp_replace(regexp_replace(regexp_replace(str, '[a-z]+', 'a', 'g'), '[A-Z]+', 'A', 'g'), '[0-9]+', '9', 'g') as skeleton, count(*) as n from node where kind = 'string' group by all")
def pattern_skeletons(spark, d):
    return extensions.skeletons(docs_names(spark, d))


ROUTES = """select s_suppkey as doc_id, ('{"s_suppkey":' || s_suppkey || ',"from":{"key":' || s_nationkey || ',"name":' || to_json(n_name)::varchar || '},"to":{"key":' || n_regionkey || ',"name":' || to_json(s_name)::varchar || '}}')::json as j from supplier join nation on s_nationkey = n_nationkey"""


@query(facts(ROUTES) + """select shape, array_to_string(list_sort(list(parent_typed_path)), ';') as paths from (select parent_typed_path, array_to_string(list_sort(list(step || ':' || kind)), ',') as shape
from (select distinct parent_typed_path, step, kind from node where parent_typed_path like '%<object>') group by parent_typed_path) group by shape having count(*) > 1""")
def shared_definitions(spark, d):
    n = table(spark, d, "nation")
    j = table(spark, d, "supplier").join(n, F.col("s_nationkey") == F.col("n_nationkey"))
    place = lambda key, name: F.struct(F.col(key).alias("key"), F.col(name).alias("name"))
    docs = j.select(F.col("s_suppkey").alias("doc_id"), F.to_json(F.struct("s_suppkey", place("s_nationkey", "n_name").alias("from"), place("n_regionkey", "s_name").alias("to"))).alias("json"))
    return extensions.shared_definitions(discover(docs, "minimum")).select("shape", F.array_join("paths", ";").alias("paths"))


@query("select '$<object>.by_brand<object>' as typed_path, count(distinct p_brand) as keys from lineitem join orders on l_orderkey = o_orderkey join part on l_partkey = p_partkey")
def data_keys(spark, d):
    return extensions.data_keys(discover(W.docs_baskets(spark, d), ["attribute_counts"]), share=1.0).select("typed_path", "keys")


@query()
def widened_bounds(spark, d):
    return extensions.widen_bounds(discover(W.docs_events(spark, d), ["maxmin", "histogram"]))


# --- SQL surface ---
@query(facts(PROPS) + "select typed_path, kind, count(*) as n, min(num) as number_min, max(num) as number_max from node group by all")
def sql_profile_view(spark, d):
    table(spark, d, "events").createOrReplaceTempView("events_raw")
    profile_view(spark, "events_raw", "props", "event_id", "events_profile", ["maxmin_number"])
    return spark.sql("SELECT typed_path, kind, n, number_min, number_max FROM events_profile")


@query("select event_type, 'object' as kind, count(*) as n from events where ('0x' || substr(md5(event_id || ':0'), 1, 8))::bigint % 100 < 50 group by 1")
def sql_functions(spark, d):
    register(spark)
    table(spark, d, "events").createOrReplaceTempView("events_raw")
    return spark.sql("SELECT event_type, json_kind(parse_json(props)) AS kind, count(*) AS n FROM events_raw WHERE md5_bucket(CAST(event_id AS STRING), 0) < 50 GROUP BY 1, 2")


@query()
def sketch_alternatives(spark, d):
    return alternatives(W.docs_events(spark, d))


@query("select user_id, count(*) as n from events group by user_id")
def stream_sessions(spark, d):
    whole = table(spark, d, "events")
    e = spark.readStream.schema(whole.schema).parquet(f"{d}/event[s].parquet").select("user_id", F.col("ts").cast("timestamp").alias("ts"))
    return S.to_table(S.sessions(e, "user_id"), f"{_home(spark)}/sessions-{uuid.uuid4().hex}").groupBy("user_id").agg(F.sum("n").alias("n"))


def entry(spark: SparkSession, d: str) -> DataFrame:
    """The flagship: every monoid of the events collection, read out."""
    p = discover(W.docs_events(spark, d), "all")
    return p.finished().select("typed_path", "path", "kind", "n", "number_min", "number_max", "string_min", "string_max", "prefix", "suffix", "format", "mean", "stddev", "distinct", "divisor")

