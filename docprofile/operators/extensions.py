"""Extensions that the method leaves to future work; these are ours."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.texts import key_step
from .discover import Profile, discover, facts_of
from .flatten import canonical_text, parse_documents


def widen_bounds(p: Profile, mass: float = 0.05) -> DataFrame:
    """typed_path, number_max, widened: a maximum that few values sit at goes to the next natural boundary (a power of ten);
    one that holds over `mass` of the values stays, as it is likely a true limit."""
    rows = p.nodes.where("bins is not null and number_max is not null")
    at_top = F.aggregate(F.filter("bins", lambda b: b["x"] >= F.col("number_max")), F.lit(0.0), lambda acc, b: acc + b["y"].cast("double"))
    limit = F.pow(F.lit(10.0), F.ceil(F.log10(F.greatest(F.col("number_max"), F.lit(1.0)))))
    return rows.select("typed_path", "number_max", F.when(at_top / F.col("n") > mass, F.col("number_max")).otherwise(limit).alias("widened"))


def _scalars(docs: DataFrame) -> DataFrame:
    """doc_id, all array<struct<path, h>>: the top-level scalar attributes of each document, with hashes of their values. No shuffle."""
    good, _ = parse_documents(docs)
    leaf = F.schema_of_variant
    entries = F.filter(F.map_entries(F.try_variant_get("doc", "$", "map<string,variant>")), lambda e: ~F.is_variant_null(e["value"]) & ~leaf(e["value"]).startswith("OBJECT") & ~leaf(e["value"]).startswith("ARRAY"))
    return good.select("doc_id", F.transform(entries, lambda e: F.struct(F.concat(F.lit("$"), key_step(e["key"])).alias("path"), F.xxhash64(canonical_text(e["value"])).alias("h"))).alias("all"))


def functional_dependencies(docs: DataFrame, exact: bool = True, error: float = 0.01) -> DataFrame:
    """a, b of top-level scalar attributes where a's value fixes b's, over the documents that have both.

    Sketches first: as many distinct a as distinct (a, b), for all pairs at once, which are rows and not columns; then, if
    exact, the pairs that are left are tested value by value. The work grows with the pairs that documents hold.
    """
    rows = _scalars(docs)
    pairs = rows.select(F.explode("all").alias("a"), "all").select("a", F.explode("all").alias("b")).where("a.path <> b.path").select(F.col("a.path").alias("a"), F.col("b.path").alias("b"), F.col("a.h").alias("ha"), F.col("b.h").alias("hb"))
    likely = pairs.groupBy("a", "b").agg(F.approx_count_distinct("ha", error).alias("one"), F.approx_count_distinct(F.xxhash64("ha", "hb"), error).alias("two")).where(F.abs(F.col("two") - F.col("one")) <= 3 * error * F.col("one")).select("a", "b")
    if not exact:
        return likely
    # of each value of a whether its b's are one; equal values are combined before they are shuffled
    per = pairs.join(likely, ["a", "b"], "left_semi").groupBy("a", "b", "ha").agg((F.min("hb") == F.max("hb")).alias("fixed"))
    return per.groupBy("a", "b").agg(F.bool_and("fixed").alias("fixed")).where("fixed").select("a", "b")


def variants_over_time(docs: DataFrame, window_of, equivalence: str = "label") -> DataFrame:
    """window, typed_path, n of the top-level record variants, by a window of each document (a column of docs)."""
    f = facts_of(docs, (), equivalence).where("step = '$'").select("doc_id", "typed_path")
    return docs.select("doc_id", window_of.alias("window")).join(f, "doc_id").groupBy("window", "typed_path").agg(F.count(F.lit(1)).alias("n"))


def shared_definitions(p: Profile) -> DataFrame:
    """shape, paths: object locations with the same keys and kinds, candidates for one shared definition."""
    kids = p.nodes.where("parent_typed_path like '%<object>'").groupBy("parent_typed_path").agg(F.array_sort(F.collect_list(F.concat_ws(":", "step", "kind"))).alias("kids"))
    return kids.groupBy(F.array_join("kids", ",").alias("shape")).agg(F.array_sort(F.collect_list("parent_typed_path")).alias("paths")).where("size(paths) > 1")


def skeletons(docs: DataFrame) -> DataFrame:
    """typed_path, skeleton, n: strings with letters as a, capitals as A and digits as 9 (runs as one), by location."""
    f = facts_of(docs, ("str",)).where("str is not null")
    s = F.regexp_replace(F.regexp_replace(F.regexp_replace("str", "[a-z]+", "a"), "[A-Z]+", "A"), "[0-9]+", "9")
    return f.groupBy("typed_path", s.alias("skeleton")).agg(F.count(F.lit(1)).alias("n"))


def data_keys(p: Profile, least: int = 10, share: float = 0.5) -> DataFrame:
    """typed_path, keys, average_share: objects whose keys look like data: many, each in few objects, all of one kind of value."""
    from .discover import attribute_counts

    c = attribute_counts(p.keysets).groupBy("typed_path").agg(F.count(F.lit(1)).alias("keys"), F.avg("share").alias("average_share"))
    kinds = p.nodes.groupBy(F.col("parent_typed_path").alias("typed_path")).agg(F.count_distinct("kind").alias("kinds"))
    return c.join(kinds, "typed_path").where((F.col("keys") >= least) & (F.col("average_share") <= share) & (F.col("kinds") == 1)).select("typed_path", "keys", "average_share")


def divergence(a: DataFrame, b: DataFrame, preset: str = "all") -> tuple[Profile, Profile]:
    """Profiles of two groups of documents, for ks_test."""
    return discover(a, preset), discover(b, preset)
