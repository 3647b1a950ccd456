"""Validation of documents against a profile or a hand-written schema, with the rule that fired.

A schema of up to BROADCAST_ROWS rows travels with the tasks, and each document is judged where it is parsed: one narrow
pass, a row a document, no shuffle. Larger schemas meet the facts of documents by a join on the typed path. A document is
invalid under a variant (a choice of rules) exactly if one of its enabled rules fires, so one pass tells the verdict of
every variant.
"""

from __future__ import annotations

import hashlib
import re

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.formats import FORMATS, label
from .discover import Profile, dependencies, facts_of, required_keys
from .flatten import canonical, label_tag, parse_strict, step_text, tags_of

#: Rules in the order of their bits.
RULES = ("type", "unknown", "required", "dependencies", "maxmin_number", "maxmin_string", "maxmin_array", "multiple", "pattern", "format", "unique")
NEEDS = ("num", "whole", "str", "keys", "arr_len", "uniq")
#: Typed paths that a schema may have for its rows to be broadcast; larger ones are joined by shuffle.
BROADCAST_ROWS = 50_000
COLUMNS = "typed_path string, parent_typed_path string, step string, kind string, required array<string>, depends array<struct<a:string,b:array<string>>>, number_min double, number_max double, string_min int, string_max int, array_min int, array_max int, divisor long, integers boolean, prefix string, suffix string, format string, all_unique boolean"


def schema_rows(p: Profile) -> DataFrame:
    """The rules of a profile, one row a typed path; rules that its monoids don't give are null."""
    nodes = p.finished()
    if p.keysets is not None and "required" in p.choice.side:
        nodes = nodes.join(required_keys(p.keysets).groupBy("typed_path").agg(F.array_sort(F.collect_list("key")).alias("required")), "typed_path", "left")
    if p.keysets is not None and "dependencies" in p.choice.side:
        each = dependencies(p.keysets).groupBy("typed_path", "a").agg(F.array_sort(F.collect_list("b")).alias("b"))
        nodes = nodes.join(each.groupBy("typed_path").agg(F.array_sort(F.collect_list(F.struct("a", "b"))).alias("depends")), "typed_path", "left")
    kinds = dict(nodes.dtypes)
    want = [c.strip().split(" ", 1) for c in _split(COLUMNS)]
    return nodes.select(*[(F.col(n) if n in kinds else F.lit(None)).cast(t).alias(n) for n, t in want])


def _split(ddl: str) -> list[str]:
    out, depth, start = [], 0, 0
    for i, c in enumerate(ddl):
        depth += (c == "<") - (c == ">")
        if c == "," and not depth:
            out.append(ddl[start:i])
            start = i + 1
    return [*out, ddl[start:]]


def violations(facts: DataFrame, rules: DataFrame, closed: bool = True) -> DataFrame:
    """doc_id, typed_path, rule: each rule that a node breaks. Closed: a node on a path that the schema lacks breaks `type`
    (its path has other kinds) or `unknown`; open: properties that the schema doesn't name are fine."""
    n = rules.count()
    rules = rules.withColumn("_known", F.lit(True))
    side = F.broadcast(rules) if n <= BROADCAST_ROWS else rules
    j = facts.select("doc_id", "typed_path", F.col("kind").alias("_kind"), F.col("parent_typed_path").alias("_parent"), F.col("step").alias("_step"), *NEEDS).join(side.drop("parent_typed_path", "step", "kind"), "typed_path", "left")
    # steps that the schema knows below a known parent, whatever their kind
    steps = rules.select(F.col("parent_typed_path").alias("_parent"), F.col("step").alias("_step")).distinct().withColumn("_step_known", F.lit(True))
    j = j.join(F.broadcast(steps) if n <= BROADCAST_ROWS else steps, ["_parent", "_step"], "left")
    unseen = F.col("_known").isNull()
    num, text = F.col("num"), F.col("str")
    ok_dep = F.forall("depends", lambda d: ~F.array_contains(F.col("keys"), d["a"]) | (F.size(F.array_except(d["b"], F.col("keys"))) == 0))
    fires = {
        "type": unseen & F.col("_step_known").isNotNull(),
        "unknown": (unseen & F.col("_step_known").isNull()) if closed else F.lit(False),
        "required": F.size(F.array_except("required", "keys")) > 0,
        "dependencies": ~ok_dep,
        "maxmin_number": (num < F.col("number_min")) | (num > F.col("number_max")),
        "maxmin_string": (F.char_length(text) < F.col("string_min")) | (F.char_length(text) > F.col("string_max")),
        "maxmin_array": (F.col("arr_len") < F.col("array_min")) | (F.col("arr_len") > F.col("array_max")),
        "multiple": F.col("integers") & num.isNotNull() & (F.col("whole").isNull() | ((F.col("divisor") > 1) & (F.col("whole") % F.col("divisor") != 0))),
        "pattern": text.isNotNull() & ~(text.startswith(F.col("prefix")) & text.endswith(F.col("suffix"))),
        "format": F.col("format").isNotNull() & text.isNotNull() & (F.coalesce(label(text), F.lit("")) != F.col("format")),
        "unique": F.col("all_unique") & ~F.col("uniq"),
    }
    fired = F.filter(F.array(*[F.when(F.coalesce(c, F.lit(False)), F.lit(r)) for r, c in fires.items()]), lambda r: r.isNotNull())
    out = j.select("doc_id", "typed_path", F.explode(fired).alias("rule"))
    if not closed:
        # below a property that an open schema doesn't name nothing is checked
        out = out.where(F.col("rule") != "unknown")
    return out


def validate_facts(ids: DataFrame, facts: DataFrame, rules: DataFrame, closed: bool = True) -> DataFrame:
    """doc_id, valid, rules (distinct rules that fired), of each doc_id in ids."""
    bad = violations(facts, rules, closed).groupBy("doc_id").agg(F.array_sort(F.collect_set("rule")).alias("rules"))
    none = F.array().cast("array<string>")
    return ids.select("doc_id").join(bad, "doc_id", "left").select("doc_id", F.col("rules").isNull().alias("valid"), F.coalesce("rules", none).alias("rules"))


def validate(docs: DataFrame, schema: Profile | DataFrame, closed: bool = True, engine: str = "arrow") -> DataFrame:
    """Validate (doc_id, json): doc_id, valid, rules, one row a row of docs. A document that doesn't parse breaks `type`."""
    rules = schema_rows(schema) if isinstance(schema, Profile) else schema
    equivalence = schema.options.get("equivalence", "kind") if isinstance(schema, Profile) else "kind"
    if engine == "arrow":
        rows = rules.limit(BROADCAST_ROWS + 1).collect()
        if len(rows) <= BROADCAST_ROWS:
            return _judged(docs, [r.asDict(recursive=True) for r in rows], tags_of(docs, equivalence) if callable(equivalence) else equivalence, closed)
    facts = facts_of(docs, NEEDS, equivalence, engine)
    out = validate_facts(docs, facts, rules, closed)
    broken = docs.where(F.try_parse_json("json").isNull()).select("doc_id").distinct().withColumn("_broken", F.lit(True))
    out = out.join(broken, "doc_id", "left")
    return out.select("doc_id", (F.col("valid") & F.col("_broken").isNull()).alias("valid"), F.when(F.col("_broken").isNotNull(), F.array(F.lit("type"))).otherwise(F.col("rules")).alias("rules"))


def _checks(r: dict) -> list:
    """(rule, test) of a schema row; a test says of (value, keys) whether the rule is broken."""
    out = []
    kind = r["kind"]
    if kind == "object":
        if r["required"]:
            need = frozenset(r["required"])
            out.append(("required", lambda v, keys: not need <= keys))
        if r["depends"]:
            pairs = [(d["a"], frozenset(d["b"])) for d in r["depends"]]
            out.append(("dependencies", lambda v, keys: any(a in keys and not b <= keys for a, b in pairs)))
    bounds = lambda lo, hi: (float("-inf") if lo is None else lo, float("inf") if hi is None else hi)
    if kind == "number":
        if r["number_min"] is not None or r["number_max"] is not None:
            lo, hi = bounds(r["number_min"], r["number_max"])
            out.append(("maxmin_number", lambda v, keys: not lo <= _double(v) <= hi))
        if r["integers"]:
            by = r["divisor"] if (r["divisor"] or 0) > 1 else 1
            out.append(("multiple", lambda v, keys: not abs(v) < 2**63 or v != int(v) or int(v) % by != 0))
    if kind in ("string", "array"):
        lo, hi = bounds(r[f"{kind}_min"], r[f"{kind}_max"])
        if (lo, hi) != bounds(None, None):
            out.append((f"maxmin_{kind}", lambda v, keys: not lo <= len(v) <= hi))
    if kind == "string":
        if r["prefix"] is not None and r["suffix"] is not None and (r["prefix"] or r["suffix"]):
            first, last = r["prefix"], r["suffix"]
            out.append(("pattern", lambda v, keys: not (v.startswith(first) and v.endswith(last))))
        if r["format"] is not None:
            want, tests = r["format"], [(n, re.compile(p, re.A)) for n, p in FORMATS.items()]
            out.append(("format", lambda v, keys: next((n for n, t in tests if t.search(v)), None) != want))
    if kind == "array" and r["all_unique"]:
        out.append(("unique", lambda v, keys: len(v) > 1 and len({canonical(x) for x in v}) < len(v)))
    return out


def _double(v) -> float:
    try:
        return float(v)
    except OverflowError:
        return float("inf") if v > 0 else float("-inf")


def _judged(docs: DataFrame, rows: list[dict], equivalence: str | dict, closed: bool) -> DataFrame:
    id_kind = dict(docs.dtypes)["doc_id"]

    def run(batches):
        checks = {r["typed_path"]: _checks(r) for r in rows}
        known = {(r["parent_typed_path"], r["step"]) for r in rows}
        paths: list = []  # of each place: typed path, tests, rule broken by being there
        places: dict = {}

        def place(parent, step, tag):
            above = paths[parent][0] if parent >= 0 else ""
            tp = f"{above}{step}<{tag}>"
            lost = None if tp in checks else "type" if (above, step) in known else "unknown" if closed else None
            at = places[parent, step, tag] = len(paths)
            paths.append((tp, checks.get(tp, ()), lost))
            return at

        def broken(text):
            try:
                todo = [(-1, "$", parse_strict(text))]
            except ValueError:
                return ["type"]
            found = set()
            while todo:
                parent, step, v = todo.pop()
                c = v.__class__
                kind = "string" if c is str else "number" if c is int or c is float else "object" if c is dict else "array" if c is list else "null" if v is None else "boolean"
                tag = kind
                if equivalence != "kind":
                    if c is dict:
                        keys = sorted(v)
                        tag = label_tag(keys) if equivalence == "label" else equivalence[hashlib.md5("\x1f".join(keys).encode()).digest()]
                    elif equivalence != "label":
                        tag = equivalence[kind]
                p = places.get((parent, step, tag))
                if p is None:
                    p = place(parent, step, tag)
                _, tests, lost = paths[p]
                if lost:
                    found.add(lost)
                if tests:
                    keys = v.keys() if c is dict else None
                    for rule, bad in tests:
                        if rule not in found and bad(v, keys):
                            found.add(rule)
                if c is dict:
                    todo += [(p, step_text(k), x) for k, x in v.items()]
                elif c is list:
                    todo += [(p, "[*]", x) for x in v]
            return sorted(found)

        for b in batches:
            for at in range(0, b.num_rows, 2000):
                part = b.slice(at, 2000)
                rules = [broken(t) for t in part.column(1).to_pylist()]
                if len(places) > 100_000:  # data keys that the schema lacks: they needn't be held
                    places.clear()
                    paths.clear()
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array([not r for r in rules], pa.bool_()), pa.array(rules, pa.list_(pa.string()))], ["doc_id", "valid", "rules"])

    return docs.select("doc_id", "json").mapInArrow(run, f"doc_id {id_kind}, valid boolean, rules array<string>")


def rejects(validated: DataFrame, enabled: list[str] | tuple[str, ...]) -> DataFrame:
    """validated with `rejected`: one of the enabled rules (and of the structure's, always on) fired."""
    return validated.withColumn("rejected", F.arrays_overlap("rules", F.array(*map(F.lit, ("type", "unknown", *enabled)))))
