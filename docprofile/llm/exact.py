"""Exact dedup by deterministic block naming.

Texts are cut into blocks of a fixed size. The distinct blocks are sorted and named by integers in sort order; then
adjacent names are paired and the distinct pairs sorted and named, level by level, until each document has one name.
Equal names mean equal texts: names come from sorting the values themselves, so no hash collision can join two texts.

A document whose length and 64-bit hash nobody shares differs from all others (unequal hashes prove unequal texts), so
its name is its own and its blocks never move. The others' equality is decided by the naming alone.

Defined cases: null text counts as empty; empty texts equal each other; a repeated row (same id and text) is a copy of
its own, of which one is kept; a null id is an id like any other; other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import join_unique, matched, materialise

#: What normalisation deletes: [\x20\x09-\x0D].
BLANKS = (" ", "\t", "\n", "\x0b", "\x0c", "\r")


def normalised(text):
    out = F.coalesce(text, F.lit(""))
    for c in BLANKS:
        out = F.replace(out, F.lit(c), F.lit(""))
    return out


def sort_names(rows: DataFrame, keys: list[str]) -> DataFrame:
    """keys, n, name: one row a distinct key; the names increase in sort order."""
    distinct = rows.groupBy(*keys).agg(F.count(F.lit(1)).alias("n"))
    # blocks are in order of their first bytes, then of a hash, then of all bytes: what is sampled for the ranges' bounds
    # stays small, and many blocks that begin alike don't fall to one task
    first = [F.substring(k, 1, 32) if kind == "binary" else F.col(k) for k, kind in distinct.dtypes if k in keys]
    first += [F.xxhash64(*keys)] if dict(distinct.dtypes)[keys[0]] == "binary" else []
    ordered = distinct.repartitionByRange(*first).sortWithinPartitions(*first, *keys)
    return materialise(ordered.withColumn("name", F.monotonically_increasing_id()), "names")


def name_texts(texts: DataFrame, block_bytes: int = 4096) -> DataFrame:
    """texts(uid, body binary) to (uid, level, name): equal (level, name) if and only if the bodies are equal."""
    nb = F.greatest(F.lit(1), F.ceil(F.length("body") / F.lit(block_bytes))).cast("int")
    rows = texts.select("uid", nb.alias("nb"), "body").select("uid", "nb", F.posexplode(F.expr(f"transform(sequence(0, nb - 1), i -> substring(body, i * {block_bytes} + 1, {block_bytes}))")).alias("pos", "block"))
    rows = materialise(rows, "blocks")
    names, keys, level, done = sort_names(rows, ["block"]), ["block"], 0, []
    while True:
        total = names.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
        rows = materialise(join_unique(rows, names, keys, "n", total).select("uid", "nb", "pos", "name"), "level")
        done.append(rows.where("nb = 1").select("uid", F.lit(level).alias("level"), "name"))
        rows = rows.where("nb > 1")
        if rows.isEmpty():
            break
        side = lambda odd: F.max(F.when(F.col("pos") % 2 == odd, F.col("name")))
        rows = rows.groupBy("uid", "nb", F.expr("pos div 2").cast("int").alias("half")).agg(side(0).alias("a"), F.coalesce(side(1), F.lit(-1)).alias("b"))
        rows = rows.select("uid", F.expr("cast((nb + 1) div 2 as int)").alias("nb"), F.col("half").alias("pos"), "a", "b")
        names, keys, level = sort_names(rows, ["a", "b"]), ["a", "b"], level + 1
    out = done[0]
    for d in done[1:]:
        out = out.unionByName(d)
    return out


def classes(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", block_bytes: int = 4096, name_all: bool = False) -> DataFrame:
    """One row a row of docs: doc_id, keep_id, group_size, kept, text_sha256, n_points, copy (number among equal rows).

    name_all: name every text, also those whose length and hash nobody shares."""
    src = docs.select(F.col(id_col).alias("doc_id"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))
    body = normalised(F.col("text"))
    sig = [F.xxhash64("body").alias("h"), F.octet_length("body").alias("len")]
    plain = src.select("doc_id", F.char_length("text").cast("long").alias("n_points"), body.alias("body"))
    base = plain.select("doc_id", "n_points", *sig, F.sha2(F.col("body").cast("binary"), 256).alias("text_sha256"))
    base = materialise(base.groupBy("doc_id", "n_points", "h", "len", "text_sha256").agg(F.count(F.lit(1)).alias("m")).withColumn("uid", F.monotonically_increasing_id()), "bases")
    total = base.agg(F.count(F.lit(1))).first()[0]
    groups = base.groupBy("h", "len").agg(F.count(F.lit(1)).alias("n"))
    shared = materialise(join_unique(base, groups.where(F.lit(name_all) | (F.col("n") > 1)).withColumn("many", F.lit(True)), ["h", "len"], "n", total).where("many").drop("many"), "shared")
    # the text side streams past a hash table of the narrow side: no sort of texts; a row of docs repeats only with its id
    texts = plain.join(shared.select(F.col("doc_id").alias("_id"), F.col("n_points").alias("_p"), F.col("h").alias("_h"), F.col("len").alias("_l"), "uid").hint("shuffle_hash"), matched([F.col("doc_id"), F.col("n_points"), F.xxhash64("body"), F.octet_length("body")], [F.col(c) for c in ("_id", "_p", "_h", "_l")]))
    named = name_texts(texts.select("uid", F.col("body").cast("binary").alias("body")).dropDuplicates(["uid"]) if base.where("m > 1").limit(1).count() else texts.select("uid", F.col("body").cast("binary").alias("body")), block_bytes)
    member = named.join(shared.select("uid", "doc_id", "n_points", "m"), "uid")
    member = materialise(member, "members")
    best = member.groupBy("level", "name").agg(F.count(F.lit(1)).alias("n"), F.sum("m").alias("group_size"), F.min(F.struct((-F.col("n_points")).alias("p"), F.col("doc_id").alias("d"))).alias("best"))
    best = best.select("level", "name", "n", "group_size", F.col("best.d").alias("keep_id"), (-F.col("best.p")).alias("keep_points"))
    decided = join_unique(member.select("uid", "level", "name"), best, ["level", "name"], "n", total).select("uid", "group_size", "keep_id", "keep_points")
    out = base.join(decided, "uid", "left")
    own = F.col("group_size").isNull()
    out = out.select("doc_id", F.when(own, F.col("doc_id")).otherwise(F.col("keep_id")).alias("keep_id"), F.coalesce("group_size", "m").alias("group_size"), (own | (F.col("keep_id").eqNullSafe(F.col("doc_id")) & (F.col("keep_points") == F.col("n_points")))).alias("_best"), "text_sha256", "n_points", F.explode(F.sequence(F.lit(1), F.col("m").cast("int"))).alias("copy"))
    return out.select("doc_id", "keep_id", "group_size", (F.col("_best") & (F.col("copy") == 1)).alias("kept"), "text_sha256", "n_points", "copy")


def keep_first(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """docs without the rows that `classes` drops; all columns stay."""
    kept = classes(docs, id_col, text_col).where("kept").groupBy(F.col("doc_id").alias("_id"), F.col("n_points").alias("_p"), F.col("text_sha256").alias("_s")).agg(F.max("group_size").alias("_size"))
    text = F.coalesce(F.col(text_col), F.lit(""))
    hit = docs.join(kept.hint("shuffle_hash"), matched([F.col(id_col), F.char_length(text).cast("long"), F.sha2(normalised(F.col(text_col)).cast("binary"), 256)], [F.col(c) for c in ("_id", "_p", "_s")]))
    # only rows of groups can repeat with their id
    again = hit.where("_size > 1").dropDuplicates([id_col, "_p", "_s"])
    return hit.where("_size = 1").unionByName(again).select(*docs.columns)
