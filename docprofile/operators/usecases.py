"""Uses of a profile: exploration, keys and inclusions, outliers, drift, hints."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .discover import Profile, attribute_counts, facts_of, required_keys

#: Width of the key test in standard errors of the estimate, and that error at lg k = 12.
Z, RSE = 3.0, 1.04 / math.sqrt(4096)


def explore(p: Profile, path: str | None = None) -> str:
    """The schema as a tree with counts; path: only what is below it. Schema-sized."""
    rows = p.nodes.orderBy("typed_path").select("typed_path", "path", "step", "kind", "n").toLocalIterator()
    out = []
    for r in rows:
        if path is None or r.path.startswith(path):
            depth = r.typed_path.count("<") - 1
            out.append(f"{'  ' * depth}{r.step} {r.kind} ({r.n})")
    return "\n".join(out)


def node_info(p: Profile, path: str) -> DataFrame:
    """All that is known of one location, one row an alternative."""
    return p.finished().where(F.col("path") == path)


def sample_documents(docs: DataFrame, k: int = 10, seed: int = 0) -> DataFrame:
    """k documents by least keyed hash: a top-k, not a sort."""
    return docs.orderBy(F.xxhash64("doc_id", F.lit(seed)), "doc_id").limit(k)


def sample_values(p: Profile, path: str) -> DataFrame:
    return p.examples.join(p.nodes.where(F.col("path") == path).select("typed_path"), "typed_path", "left_semi").select("typed_path", "example")


def presence(p: Profile) -> DataFrame:
    """typed_path of the object, key, share of its objects that have the key."""
    return attribute_counts(p.keysets).select("typed_path", "key", "share")


def primary_keys(p: Profile, documents: int, z: float = Z) -> DataFrame:
    """Locations whose values look unique over all documents: as many as documents, and the estimate within its error of that."""
    rows = p.finished().where("kind in ('string', 'number')").where(F.col("n") == documents)
    return rows.where(F.abs(F.col("distinct") - F.col("n")) <= z * RSE * F.col("n")).select("typed_path", "path", "kind", "n", "distinct")


def rank_keys(p: Profile, candidates: DataFrame) -> DataFrame:
    """Candidates with a score and rank: whole numbers and short fixed texts, names that say key or id, and top-level places come first."""
    have = p.finished()
    extra = [c for c in ("string_max", "string_min", "integers") if c in have.columns]
    rows = candidates.join(have.select("typed_path", *extra), "typed_path")
    name = F.lower(F.regexp_extract("path", r"([A-Za-z_0-9]+)\W*$", 1))
    score = F.when(name.rlike("(key|id|sku|code)$"), 2.0).otherwise(0.0) + 1.0 / F.size(F.split("path", r"\."))
    if "integers" in extra:
        score = score + F.when(F.col("integers"), 1.0).otherwise(0.0)
    if "string_max" in extra:
        score = score + F.when(F.col("string_max") <= 16, 0.5).otherwise(0.0) + F.when(F.col("string_max") == F.col("string_min"), 0.5).otherwise(0.0)
    w = Window.orderBy(F.desc("score"), "typed_path")  # schema-sized
    return rows.withColumn("score", score).withColumn("rank", F.row_number().over(w)).select("rank", "typed_path", "path", "kind", "score")


def foreign_keys(a: Profile, b: Profile | None = None, least_distinct: int = 2) -> DataFrame:
    """child, parent: the bits of child's filter are a subset of parent's. Pairs of paths of one kind, pruned by bounds and by
    the estimates before any filter is compared; quadratic in the schema, not in the data."""
    b = b or a

    def side(p: Profile, s: str) -> DataFrame:
        rows = p.finished().where("kind in ('string', 'number')")
        keep = [c for c in ("number_min", "number_max", "distinct") if c in rows.columns]
        return rows.select(F.col("typed_path").alias(s), F.col("kind").alias("kind"), *[F.col(c).alias(f"{s}_{c}") for c in keep])

    x, y = side(a, "child"), side(b, "parent")
    pairs = x.join(F.broadcast(y), "kind").where("child <> parent")
    if "child_number_min" in pairs.columns and "parent_number_min" in pairs.columns:
        pairs = pairs.where("child_number_min is null or (child_number_min >= parent_number_min and child_number_max <= parent_number_max)")
    if "child_distinct" in pairs.columns and "parent_distinct" in pairs.columns:
        pairs = pairs.where(f"child_distinct >= {least_distinct} and child_distinct <= parent_distinct * {1 + 2 * Z * RSE}")
    one = a.bloom.select(F.col("typed_path").alias("child"), "bucket", F.col("bits").alias("_c"))
    two = b.bloom.select(F.col("typed_path").alias("parent"), "bucket", F.col("bits").alias("_p"))
    blocks = pairs.select("child", "parent").join(one, "child").join(two, ["parent", "bucket"], "left")
    merged = blocks.select("child", "parent", "bucket", F.explode(F.array("_c", F.coalesce("_p", "_c"))).alias("bits"), "_p").groupBy("child", "parent", "bucket").agg(F.bitmap_count(F.bitmap_or_agg("bits")).alias("either"), F.max(F.coalesce(F.bitmap_count("_p"), F.lit(-1))).alias("of_parent"))
    return merged.groupBy("child", "parent").agg(F.bool_and(F.col("either") == F.col("of_parent")).alias("inside")).where("inside").select("child", "parent")


def rank_foreign_keys(p: Profile, found: DataFrame, keys: DataFrame | None = None) -> DataFrame:
    """Inclusions with a score: the parent looks like a key, the names agree, and the child covers a large part of the parent."""
    info = p.finished().select("typed_path", F.col("distinct"), "n")
    j = found.join(info.select(F.col("typed_path").alias("child"), F.col("distinct").alias("d_c")), "child").join(info.select(F.col("typed_path").alias("parent"), F.col("distinct").alias("d_p"), F.col("n").alias("n_p")), "parent")
    last = lambda c: F.lower(F.regexp_extract(c, r"([A-Za-z0-9]+)<[a-z]+>$", 1))
    score = F.when(F.col("d_p") >= (1 - Z * RSE) * F.col("n_p"), 2.0).otherwise(0.0) + F.when(last("child") == last("parent"), 1.0).otherwise(0.0) + F.least(F.lit(1.0), F.col("d_c") / F.col("d_p"))
    if keys is not None:
        j = j.join(F.broadcast(keys.select(F.col("typed_path").alias("parent"), F.lit(1.0).alias("_key"))), "parent", "left")
        score = score + F.coalesce("_key", F.lit(0.0))
    w = Window.orderBy(F.desc("score"), "child", "parent")  # schema-sized
    return j.withColumn("score", score).withColumn("rank", F.row_number().over(w)).select("rank", "child", "parent", "score")


def verify_inclusion(child: DataFrame, parent: DataFrame) -> DataFrame:
    """missing: distinct values of child(value) that parent(value) lacks; an inclusion has none."""
    return child.where("value is not null").select("value").distinct().join(parent.select("value"), "value", "left_anti").agg(F.count(F.lit(1)).alias("missing"))


def value_outliers(docs: DataFrame, p: Profile, z: float = 3.0) -> DataFrame:
    """doc_id, typed_path, value, deviations of numbers beyond mean +- z standard deviations."""
    rows = p.finished().where("stddev > 0").select("typed_path", "mean", "stddev")
    facts = facts_of(docs, ("num",)).where("num is not null").select("doc_id", "typed_path", "num")
    j = facts.join(F.broadcast(rows), "typed_path")  # schema-sized
    dev = (F.col("num") - F.col("mean")) / F.col("stddev")
    return j.withColumn("deviations", dev).where(F.abs("deviations") > z).select("doc_id", "typed_path", F.col("num").alias("value"), "deviations")


def length_outliers(docs: DataFrame, what: str = "string", z: float = 3.0, facts: DataFrame | None = None) -> DataFrame:
    """Same for lengths of strings or arrays, whose moments come from one more aggregation of the facts."""
    value = F.char_length("str") if what == "string" else F.col("arr_len")
    f = (facts if facts is not None else facts_of(docs, ("str", "arr_len"))).select("doc_id", "typed_path", value.cast("double").alias("v")).where("v is not null")
    m = f.groupBy("typed_path").agg(F.avg("v").alias("mean"), F.stddev_pop("v").alias("stddev")).where("stddev > 0")
    return f.join(F.broadcast(m), "typed_path").withColumn("deviations", (F.col("v") - F.col("mean")) / F.col("stddev")).where(F.abs("deviations") > z).select("doc_id", "typed_path", F.col("v").alias("value"), "deviations")


def structural_outliers(p: Profile, eps: float = 0.01) -> DataFrame:
    """typed_path, key, share, what: keys that are rare, or nearly always there."""
    rows = attribute_counts(p.keysets)
    what: Column = F.when(F.col("share") <= eps, "rare").when((F.col("share") < 1) & (F.col("share") >= 1 - eps), "nearly always")
    return rows.withColumn("what", what).where("what is not null").select("typed_path", "key", "n", "objects", "share", "what")


def document_outliers(docs: DataFrame, p: Profile, z: float = 3.0) -> DataFrame:
    """doc_id, outliers, n: the outlying values of each document, as many as it has."""
    each = value_outliers(docs, p, z)
    return each.groupBy("doc_id").agg(F.sort_array(F.collect_list(F.struct("typed_path", "value"))).alias("outliers"), F.count(F.lit(1)).alias("n"))


def outlier_score(docs: DataFrame, p: Profile, z: float = 3.0, weight: float = 1.0) -> DataFrame:
    """doc_id, score: sum over a document's outlying values of their deviations beyond z (ours: a document-level score)."""
    return value_outliers(docs, p, z).groupBy("doc_id").agg((F.sum(F.abs("deviations") - z) * weight).alias("score"))


def ks_test(a: Profile, b: Profile, path: str, alpha: float = 0.05) -> DataFrame:
    """n_a, n_b, gap, threshold, differs: two-sample test on the histograms of one path."""

    def bins(p, s):
        return p.nodes.where((F.col("path") == path) & (F.col("kind") == "number")).select(F.explode("bins").alias("b")).select(F.col("b.x").cast("double").alias("x"), F.col("b.y").cast("double").alias(s))

    both = bins(a, "a").withColumn("b", F.lit(0.0)).unionByName(bins(b, "b").withColumn("a", F.lit(0.0)))
    return _ks(both, alpha)


def ks_exact(a: DataFrame, b: DataFrame, alpha: float = 0.05) -> DataFrame:
    """Same over all values of a(x) and b(x): counts by value, then running sums over the distinct values."""
    both = a.select("x", F.lit(1.0).alias("a"), F.lit(0.0).alias("b")).unionByName(b.select("x", F.lit(0.0).alias("a"), F.lit(1.0).alias("b")))
    return _ks(both, alpha)


def _ks(both: DataFrame, alpha: float) -> DataFrame:
    counts = both.groupBy("x").agg(F.sum("a").alias("a"), F.sum("b").alias("b"))
    n = counts.agg(F.sum("a").alias("n_a"), F.sum("b").alias("n_b"))
    cum = running_sums(counts, "x", ["a", "b"])
    gap = cum.crossJoin(F.broadcast(n)).agg(F.max(F.abs(F.col("a") / F.col("n_a") - F.col("b") / F.col("n_b"))).alias("gap"), F.first("n_a").alias("n_a"), F.first("n_b").alias("n_b"))
    c = math.sqrt(-math.log(alpha / 2) / 2)
    return gap.withColumn("threshold", c * F.sqrt((F.col("n_a") + F.col("n_b")) / (F.col("n_a") * F.col("n_b")))).withColumn("differs", F.col("gap") > F.col("threshold"))


def running_sums(df: DataFrame, by: str, sums: list[str]) -> DataFrame:
    """df with each of `sums` replaced by its running sum in order of `by`: sums within ranges of `by`, plus those of all
    ranges before, so no task sees all rows. The ranges' own sums are one row a range."""
    ranged = df.repartitionByRange(df.sparkSession.sparkContext.defaultParallelism, by).withColumn("_p", F.spark_partition_id())
    whole = ranged.groupBy("_p").agg(*[F.sum(s).alias(f"_s_{s}") for s in sums], F.min(by).alias("_lo"))
    w = Window.orderBy("_lo").rowsBetween(Window.unboundedPreceding, -1)  # one row a range
    before = whole.select("_p", *[F.coalesce(F.sum(f"_s_{s}").over(w), F.lit(0.0)).alias(f"_b_{s}") for s in sums])
    inside = Window.partitionBy("_p").orderBy(by)
    return ranged.join(F.broadcast(before), "_p").select(*[c for c in df.columns if c not in sums], *[(F.sum(s).over(inside) + F.col(f"_b_{s}")).alias(s) for s in sums])


def normalize_hints(p: Profile, keys: DataFrame, inclusions: DataFrame) -> DataFrame:
    """Entities to split off: each inclusion into a key says that its parent is an entity and the child a reference to it."""
    return inclusions.join(F.broadcast(keys.select(F.col("typed_path").alias("parent"))), "parent").select(F.col("parent").alias("entity_key"), F.col("child").alias("reference"))


def sizing(p: Profile) -> DataFrame:
    """typed_path, kind, n, bytes: rough memory of a location's values, from counts and largest lengths."""
    rows = p.finished()
    each = F.when(F.col("kind") == "string", F.coalesce(F.col("string_max"), F.lit(16)) + 40).when(F.col("kind") == "number", 8).when(F.col("kind") == "boolean", 1).otherwise(16)
    return rows.select("typed_path", "kind", "n", (F.col("n") * each).cast("long").alias("bytes"))


def common_keys(p: Profile) -> DataFrame:
    return required_keys(p.keysets)
