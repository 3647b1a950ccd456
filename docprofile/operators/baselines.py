"""Baseline methods: type fusion, entity splitting, structure graphs, Spark's own inference, ad hoc queries."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .discover import discover, facts_of, keysets_of
from .flatten import fold_arrow
from .validate import COLUMNS, _split

#: Distinct key sets of one location that the entity splitter takes.
MAX_KEYSETS = 20_000


def type_fusion(docs: DataFrame, equivalence: str = "kind", counts: bool = True) -> DataFrame:
    """Structure only, by map and reduce: typed_path, kind (and n)."""
    if equivalence == "kind":
        rows = fold_arrow(docs).select("typed_path", "kind", "n")
    else:
        rows = facts_of(docs, (), equivalence).groupBy("typed_path").agg(F.first("kind").alias("kind"), F.count(F.lit(1)).alias("n"))
    return rows if counts else rows.select("typed_path", "kind")


def fusion_rules(docs: DataFrame, counts: bool = True) -> DataFrame:
    """The type-fusion schema as a validator's rows. counts: attributes counted as often as their object are required, the
    others optional, which is what counting types tells."""
    nodes = discover(docs, "minimum").nodes
    rows = nodes.select("typed_path", "parent_typed_path", "step", "kind", "n")
    if counts:
        each = rows.groupBy(F.col("parent_typed_path").alias("_p"), F.col("step").alias("_s")).agg(F.sum("n").alias("_n"))
        full = each.join(rows.where("kind = 'object'").select(F.col("typed_path").alias("_p"), "n"), "_p").where("_n = n").groupBy("_p").agg(F.array_sort(F.collect_list("_s")).alias("_steps"))
        name = lambda s: F.when(s.startswith('."'), F.from_json(F.concat(F.lit("["), F.substring(s, F.lit(2), F.char_length(s)), F.lit("]")), "array<string>")[0]).otherwise(F.substring(s, F.lit(2), F.char_length(s)))
        rows = rows.join(full.select(F.col("_p").alias("typed_path"), F.transform("_steps", name).alias("required")), "typed_path", "left")
    kinds = dict(rows.dtypes)
    return rows.select(*[(F.col(n) if n in kinds else F.lit(None)).cast(t).alias(n) for n, t in (c.strip().split(" ", 1) for c in _split(COLUMNS))])


def entity_types(docs: DataFrame) -> list[dict]:
    """Record types of each object location: typed_path, required and properties of each type.

    From the distinct key sets of a location: keys of all sets are dropped, the others that occur together are components;
    in a component each key set that a larger one contains is absorbed, and what is left are the types (an outline of the
    published method: its text leaves details open). Key sets are schema-sized and bounded by MAX_KEYSETS.
    """
    sets: dict = {}
    keysets = keysets_of(facts_of(docs, ("keys",)))
    if keysets.count() > MAX_KEYSETS:
        raise ValueError(f"over {MAX_KEYSETS} distinct key sets: this method doesn't finish on data keys")
    for r in keysets.select("typed_path", "keys").collect():
        sets.setdefault(r.typed_path, set()).add(frozenset(r["keys"]))
    out = []
    for tp, found in sorted(sets.items()):
        common = frozenset.intersection(*found)
        parent: dict = {}

        def root(k, parent=parent):
            while parent.setdefault(k, k) != k:
                k = parent[k]
            return k

        for s in found:
            rest = sorted(s - common)
            for k in rest[1:]:
                parent[root(k)] = root(rest[0])
        groups: dict = {}
        for s in found:
            rest = sorted(s - common)
            groups.setdefault(root(rest[0]) if rest else None, set()).add(s)
        # a record with common keys only belongs to each type of its location
        plain = groups.pop(None, set()) if len(groups) > 1 else set()
        groups = {k: g | plain for k, g in groups.items()}
        for _, group in sorted(groups.items(), key=lambda g: str(g[0])):
            maximal = [s for s in group if not any(s < t for t in group)]
            for m in sorted(maximal, key=sorted):
                members = [s for s in group if s <= m]
                out.append({"typed_path": tp, "required": sorted(frozenset.intersection(*members)), "properties": sorted(m)})
    return out


def entity_split(docs: DataFrame) -> DataFrame:
    """typed_path, required, properties: one row a record type."""
    rows = [(t["typed_path"], t["required"], t["properties"]) for t in entity_types(docs)]
    return docs.sparkSession.createDataFrame(rows, "typed_path string, required array<string>, properties array<string>")


def entity_validator(docs: DataFrame, closed: bool = False) -> Callable[[DataFrame], DataFrame]:
    """A validator (doc_id, valid): each object must fit one of its location's record types, each known node's kind must be known."""
    types = entity_split(docs).groupBy("typed_path").agg(F.collect_list(F.struct("required", "properties")).alias("types"))
    known = type_fusion(docs, counts=False).select("typed_path", F.lit(True).alias("known"))
    steps = discover(docs, "minimum").nodes.select(F.col("parent_typed_path"), "step", F.lit(True).alias("step_known")).distinct()

    def check(test: DataFrame) -> DataFrame:
        facts = facts_of(test, ("keys",)).select("doc_id", "typed_path", "parent_typed_path", "step", "keys")
        j = facts.join(F.broadcast(known), "typed_path", "left").join(F.broadcast(types), "typed_path", "left").join(F.broadcast(steps), ["parent_typed_path", "step"], "left")  # schema-sized, at most MAX_KEYSETS
        fits = F.exists("types", lambda t: (F.size(F.array_except(t["required"], F.col("keys"))) == 0) & ((F.size(F.array_except(F.col("keys"), t["properties"])) == 0) if closed else F.lit(True)))
        bad = (F.col("known").isNull() & (F.lit(True) if closed else F.col("step_known").isNotNull())) | (F.col("known").isNotNull() & F.col("keys").isNotNull() & ~fits)
        invalid = j.where(bad).select("doc_id").distinct().withColumn("bad", F.lit(True))
        return test.select("doc_id").join(invalid, "doc_id", "left").select("doc_id", F.col("bad").isNull().alias("valid"))

    return check


def structure_graph(docs: DataFrame, reduced: bool = True) -> tuple[DataFrame, DataFrame]:
    """(nodes(path, n), edges(parent, path, n)); not reduced: also the documents' ids of each, which grows with the data."""
    facts = facts_of(docs, ())
    parent = F.regexp_replace("path", r'(\.("(\\.|[^"\\])*"|[A-Za-z_0-9]+)|\[\*\])$', "")
    rows = facts.select("doc_id", "path", F.when(F.col("path") != "$", parent).alias("parent"))
    ids = [] if reduced else [F.sort_array(F.collect_set("doc_id")).alias("documents")]
    nodes = rows.groupBy("path").agg(F.count(F.lit(1)).alias("n"), *ids)
    return nodes, rows.where("parent is not null").groupBy("parent", "path").agg(F.count(F.lit(1)).alias("n"), *ids)


def native(docs: DataFrame) -> DataFrame:
    """Spark's own inference: one type for all documents, without alternatives or metadata."""
    return docs.agg(F.expr("schema_of_variant_agg(try_parse_json(json))").alias("type"))


def adhoc(docs: DataFrame, questions: dict[str, str]) -> DataFrame:
    """Each property by a scan of its own, as an analyst would: name, presence, distinct, least and greatest text of a JSON path."""
    out = None
    for name, path in questions.items():
        v = F.get_json_object("json", path)
        one = docs.agg(F.lit(name).alias("name"), F.count(v).alias("present"), F.count(F.lit(1)).alias("documents"), F.count_distinct(v).alias("distinct"), F.min(v).alias("least"), F.max(v).alias("greatest"))
        out = one if out is None else out.unionByName(one)
    return out
