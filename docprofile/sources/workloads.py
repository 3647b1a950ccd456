"""The document collections of the experiments, built on the given tables. Each is (doc_id, json)."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .readers import from_table, table


def _json(df: DataFrame, key: str, **fields) -> DataFrame:
    return df.select(F.col(key).cast("long").alias("doc_id"), F.to_json(F.struct(*[(c if not isinstance(c, str) else F.col(c)).alias(k) for k, c in fields.items()])).alias("json"))


def _iso(c: str):
    return F.date_format(c, "yyyy-MM-dd'T'HH:mm:ss'Z'")


def docs_events(spark: SparkSession, d: str) -> DataFrame:
    """Wide and polymorphic; the payload is an object, a code, a pair of numbers, an explicit null or absent."""
    e = table(spark, d, "events")
    value = F.col("value").cast("decimal(20,6)").cast("string")
    payload = (
        F.when(F.col("event_type") == "purchase", F.concat(F.lit('{"amount":'), value, F.lit("}")))
        .when(F.col("event_type") == "error", F.concat(F.lit('"E'), (F.col("event_id") % 7).cast("string"), F.lit('"')))
        .when(F.col("event_type") == "click", F.concat(F.lit("["), (F.col("event_id") % 1000).cast("string"), F.lit(","), (F.col("event_id") % 700).cast("string"), F.lit("]")))
        .when(F.col("event_type") == "signup", "null")
    )
    head = F.to_json(F.struct("event_id", _iso("ts").alias("ts"), "user_id", "event_type"))
    text = F.concat(F.expr("substring(h, 1, length(h) - 1)"), F.lit(',"props":'), F.col("props"), F.coalesce(F.concat(F.lit(',"payload":'), "payload"), F.lit("")), F.lit("}"))
    return e.select(F.col("event_id").alias("doc_id"), "props", head.alias("h"), payload.alias("payload")).select("doc_id", text.alias("json"))


def docs_articles(spark: SparkSession, d: str) -> DataFrame:
    """Text metadata with an optional object."""
    t, labels = table(spark, d, "documents"), table(spark, d, "labels")
    j = t.join(labels.select("doc_id", F.struct("quality", "toxic").alias("labels")), "doc_id", "left")
    words = F.slice(F.split(F.lower("text"), "[^\\p{L}]+"), 1, 5)
    return _json(j, "doc_id", doc_id="doc_id", lang="lang", source="source", n_chars="n_chars", keywords=F.filter(words, lambda w: w != ""), labels="labels")


def docs_baskets(spark: SparkSession, d: str) -> DataFrame:
    """Data as keys: quantity by brand of each customer."""
    li = table(spark, d, "lineitem").select("l_orderkey", "l_partkey", "l_quantity")
    o = table(spark, d, "orders").select(F.col("o_orderkey").alias("l_orderkey"), "o_custkey")
    p = table(spark, d, "part").select(F.col("p_partkey").alias("l_partkey"), "p_brand")
    q = li.join(o, "l_orderkey").join(p, "l_partkey").groupBy("o_custkey", "p_brand").agg(F.sum("l_quantity").cast("long").alias("q"))
    b = q.groupBy("o_custkey").agg(F.map_from_entries(F.sort_array(F.collect_list(F.struct("p_brand", "q")))).alias("by_brand"))  # at most 25 brands
    return _json(b, "o_custkey", c_custkey="o_custkey", by_brand="by_brand")


def docs_threads(spark: SparkSession, d: str) -> DataFrame:
    """Arrays of objects, with optional parts."""
    c = table(spark, d, "conversations").select("conv_id", "turn", "role", F.char_length("text").alias("n"), F.when(F.col("role") == "system", F.col("text")).alias("sys"), F.when(F.col("turn") > 0, F.struct((F.col("turn") - 1).alias("turn"))).alias("reply_to"))
    t = c.groupBy("conv_id").agg(F.sort_array(F.collect_list(F.struct("turn", "role", "n", "reply_to"))).alias("turns"), F.max("sys").alias("sys"))
    return _json(t, "conv_id", conv_id="conv_id", system_prompt="sys", turns="turns")


def docs_suppliers(spark: SparkSession, d: str) -> DataFrame:
    """Nested objects and arrays of keys."""
    s, n, r = (table(spark, d, x) for x in ("supplier", "nation", "region"))
    parts = table(spark, d, "lineitem").select("l_suppkey", "l_partkey").distinct().groupBy("l_suppkey").agg(F.slice(F.sort_array(F.collect_set("l_partkey")), 1, 20).alias("parts"))
    j = s.join(F.broadcast(n), s.s_nationkey == n.n_nationkey).join(F.broadcast(r), n.n_regionkey == r.r_regionkey).join(parts, s.s_suppkey == parts.l_suppkey, "left")  # 25 and 5 rows
    return _json(j, "s_suppkey", s_suppkey="s_suppkey", s_name="s_name", s_acctbal="s_acctbal", place=F.struct(F.col("n_name").alias("nation"), F.col("r_name").alias("region")), parts=F.coalesce("parts", F.array().cast("array<bigint>")))


def docs_checkins(spark: SparkSession, d: str) -> DataFrame:
    """Counts keyed by weekday and hour of each user."""
    e = table(spark, d, "events").select("user_id", F.date_format("ts", "E-H").alias("h"))
    q = e.groupBy("user_id", "h").agg(F.count(F.lit(1)).alias("n")).groupBy("user_id").agg(F.map_from_entries(F.sort_array(F.collect_list(F.struct("h", "n")))).alias("hours"))  # at most 168 hours
    return _json(q, "user_id", user_id="user_id", hours="hours")


def docs_parts(spark: SparkSession, d: str) -> DataFrame:
    """Flat and small."""
    return from_table(table(spark, d, "part"), "p_partkey")


def docs_lines(spark: SparkSession, d: str) -> DataFrame:
    """Many flat documents; qty_pack is a multiple of six."""
    li = table(spark, d, "lineitem").withColumn("doc_id", F.xxhash64("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_extendedprice"))
    return _json(li, "doc_id", l_orderkey="l_orderkey", l_partkey="l_partkey", l_suppkey="l_suppkey", l_linenumber="l_linenumber", l_quantity="l_quantity", l_extendedprice="l_extendedprice", l_discount="l_discount", l_tax="l_tax", flags=F.concat_ws("/", "l_returnflag", "l_linestatus"), shipped=F.date_format("l_shipdate", "yyyy-MM-dd"), qty_pack=F.col("l_linenumber") * 6)


def docs_texts(spark: SparkSession, d: str) -> DataFrame:
    """W8, text-heavy."""
    return from_table(table(spark, d, "documents"), "doc_id")


def docs_turns(spark: SparkSession, d: str) -> DataFrame:
    """Flat turns."""
    c = table(spark, d, "conversations")
    return _json(c.withColumn("doc_id", F.col("conv_id") * 100_000 + F.col("turn")), "doc_id", conv_id="conv_id", turn="turn", role="role", text="text")


def docs_customers(spark: SparkSession, d: str) -> DataFrame:
    """Customers with arrays of order keys and counters."""
    o = table(spark, d, "orders").groupBy("o_custkey").agg(F.slice(F.sort_array(F.collect_list("o_orderkey")), 1, 1000).alias("orders"), F.count(F.lit(1)).alias("n_orders"))
    c = table(spark, d, "customer")
    j = c.join(o, c.c_custkey == o.o_custkey, "left")
    return _json(j, "c_custkey", c_custkey="c_custkey", c_name="c_name", c_acctbal="c_acctbal", segment="c_mktsegment", orders=F.coalesce("orders", F.array().cast("array<bigint>")), n_orders=F.coalesce("n_orders", F.lit(0)))


def docs_manifests(spark: SparkSession, d: str, corrupt: bool = True) -> DataFrame:
    """Package manifests with a hand-written schema; six in a thousand are corrupted by a hash of their id."""
    p = table(spark, d, "part")
    k = F.col("p_partkey")
    name = F.concat(F.lit("pkg-"), F.lower(F.regexp_replace("p_name", "[^A-Za-z0-9]+", "-")), F.lit("-"), k.cast("string"))
    version = F.concat_ws(".", (k % 7).cast("string"), (k % 13).cast("string"), (k % 29).cast("string"))
    libs = F.map_from_entries(F.transform(F.sequence(F.lit(0), (k % 4).cast("int")), lambda i: F.struct(F.concat(F.lit("lib"), ((k * 7 + i * 11) % 25).cast("string")).alias("k"), F.concat(F.lit("^"), ((k + i) % 9).cast("string"), F.lit(".0.0")).alias("v"))))
    # many task names, each in few documents, with commands of any length: what bounds of observed lengths overfit to
    task = lambda i: F.concat(F.lit("task"), ((k * 13 + i * 31) % 120).cast("string"))
    command = lambda i: F.concat(F.lit("node "), F.expr(f"substring(md5(concat(p_partkey, '/', {i})), 1, 1 + cast(conv(substring(md5(concat(p_partkey, ':', {i})), 1, 2), 16, 10) as int) % 30)"))
    scripts = F.when(k % 2 == 0, F.map_from_arrays(F.array(task(0), task(1)), F.array(command(0), command(1)))).when(k % 3 == 0, F.map_from_arrays(F.array(task(0)), F.array(command(0))))
    h = F.conv(F.substring(F.md5(F.concat(F.lit("corrupt:"), k.cast("string"))), 1, 8), 16, 10).cast("long") % 1000 if corrupt else F.lit(999)
    bad = lambda i, x, y: F.when(h == i, x).otherwise(y)
    url = F.concat(F.lit("https://registry.example.org/"), name, F.lit("/-/"), name, F.lit(".tgz"))
    dist = F.struct(F.sha1(k.cast("string").cast("binary")).alias("shasum"), bad(0, F.concat(F.lit("registry/"), name), url).alias("tarball"))
    oses = F.when(k % 3 == 0, F.when(k % 2 == 0, F.array(F.lit("linux"), F.lit("darwin"))).otherwise(F.array(F.lit("win32"))))
    oses = bad(5, F.array(F.lit("linux"), F.lit("linux")), oses)
    site = F.concat(F.lit("https://funding.example.org/"), name)
    fund = F.when(k % 5 == 0, F.to_json(F.struct(site.alias("url")))).when(k % 5 == 1, F.concat(F.lit('"'), site, F.lit('"')))
    body = F.to_json(F.struct(bad(2, F.lit(None).cast("string"), name).alias("name"), bad(1, F.lit(" v 1"), version).alias("version"), dist.alias("dist"), oses.alias("os"), F.split(F.lower("p_type"), " ").alias("keywords"), F.when(k % 4 != 3, libs).alias("dependencies"), scripts.alias("scripts"), bad(4, F.lit(None).cast("int"), F.col("p_size")).alias("size")))
    more = F.concat(F.coalesce(F.concat(F.lit(',"funding":'), fund), F.lit("")), bad(3, F.lit(',"surprise":true'), F.lit("")), bad(4, F.lit(',"size":"5"'), F.lit("")))
    return p.select(k.alias("doc_id"), body.alias("b"), more.alias("m")).select("doc_id", F.concat(F.expr("substring(b, 1, length(b) - 1)"), "m", F.lit("}")).alias("json"))


def docs_products(spark: SparkSession, d: str) -> DataFrame:
    """Products with arrays of related products, a rank under a data key, nested categories."""
    li = table(spark, d, "lineitem").select("l_orderkey", "l_partkey").distinct()
    pairs = li.join(li.select("l_orderkey", F.col("l_partkey").alias("other")), "l_orderkey").where("l_partkey <> other").select("l_partkey", "other").distinct()
    also = pairs.groupBy("l_partkey").agg(F.slice(F.sort_array(F.collect_set("other")), 1, 6).alias("also_bought"), F.slice(F.sort_array(F.collect_set(F.when(F.col("other") % 3 == 0, F.col("other")))), 1, 4).alias("bought_after"))
    p = table(spark, d, "part")
    j = p.join(also, p.p_partkey == also.l_partkey, "left")
    related = F.struct("also_bought", F.when(F.size("bought_after") > 0, F.col("bought_after")).alias("bought_after"))
    rank = F.map_from_arrays(F.array("p_type"), F.array((F.col("p_partkey") * 37 % 1000).cast("long")))
    return _json(j, "p_partkey", sku="p_partkey", title="p_name", price="p_retailprice", related=F.when(F.col("also_bought").isNotNull(), related), sales_rank=rank, categories=F.array(F.array("p_type", "p_brand")))


def docs_tables(spark: SparkSession, d: str) -> DataFrame:
    """Tabular data as arrays of rows."""
    li = table(spark, d, "lineitem")
    row = F.concat(F.lit("["), F.concat_ws(",", F.col("l_linenumber").cast("string"), F.col("l_partkey").cast("string"), F.col("l_quantity").cast("string")), F.lit(',"'), "l_returnflag", F.lit('"]'))
    rows = li.groupBy("l_orderkey").agg(F.array_join(F.sort_array(F.collect_list(row)), ",").alias("rows"))
    return rows.select(F.col("l_orderkey").alias("doc_id"), F.concat(F.lit('{"l_orderkey":'), F.col("l_orderkey").cast("string"), F.lit(',"rows":['), "rows", F.lit("]}")).alias("json"))


def docs_vectors(spark: SparkSession, d: str) -> DataFrame:
    """Arrays of one fixed length."""
    return _json(table(spark, d, "embeddings"), "vec_id", vec_id="vec_id", embedding="embedding")


def docs_pages(spark: SparkSession, d: str) -> DataFrame:
    """Web pages."""
    return _json(table(spark, d, "pages"), "page_id", page_id="page_id", url="url", html_len=F.char_length("html"), lang=F.nullif(F.regexp_extract("html", '<html lang="([a-z]+)"', 1), F.lit("")))


def docs_props(spark: SparkSession, d: str) -> DataFrame:
    """A raw JSON column as given."""
    return table(spark, d, "events").select(F.col("event_id").alias("doc_id"), F.col("props").alias("json"))


def docs_regions(spark: SparkSession, d: str) -> DataFrame:
    """Reference tables."""
    return from_table(table(spark, d, "region"), "r_regionkey")


def docs_nations(spark: SparkSession, d: str) -> DataFrame:
    return from_table(table(spark, d, "nation"), "n_nationkey")


def docs_benchmark(spark: SparkSession, d: str) -> DataFrame:
    return from_table(table(spark, d, "benchmark"), "item_id")


WORKLOADS: dict[str, Callable[[SparkSession, str], DataFrame]] = {k.removeprefix("docs_"): v for k, v in list(globals().items()) if k.startswith("docs_")}
