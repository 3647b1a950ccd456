"""A JSON Schema (draft 2019-09) from a profile. The profile's rows come to the driver: schema-sized, and bounded."""

from __future__ import annotations

import json

from pyspark.sql import functions as F

from ..functions.texts import regex_escape
from ..operators.discover import Profile, attribute_counts
from ..operators.validate import schema_rows

MAX_ROWS = 200_000


def _key(step: str) -> str:
    return json.loads(step[1:]) if step.startswith('."') else step[1:]


def to_json_schema(p: Profile, closed: bool = True, annotate: bool = True) -> dict:
    """The schema: alternatives of one location as oneOf, whose branches never overlap."""
    rows = {}
    for r in schema_rows(p).limit(MAX_ROWS + 1).toLocalIterator():
        rows[r.typed_path] = r.asDict(recursive=True)
    if len(rows) > MAX_ROWS:
        raise ValueError(f"over {MAX_ROWS} typed paths: collapse data keys or take a coarser equivalence first")
    notes: dict = {}
    if annotate:
        extra = [c for c in ("distinct", "mean", "stddev", "skewness", "kurtosis", "bins", "n") if c in p.finished().columns]
        for r in p.finished().select("typed_path", *extra).toLocalIterator():
            notes[r.typed_path] = {k: v for k, v in r.asDict(recursive=True).items() if k != "typed_path" and v is not None}
        if p.examples is not None:
            for r in p.examples.groupBy("typed_path").agg(F.slice(F.array_sort(F.collect_list("example")), 1, 100).alias("e")).toLocalIterator():
                notes.setdefault(r.typed_path, {})["examples"] = [json.loads(x) if x not in ("Infinity", "-Infinity") else x for x in r.e]
        if p.keysets is not None and "attribute_counts" in p.choice.side:
            for r in attribute_counts(p.keysets).toLocalIterator():
                notes.setdefault(r.typed_path, {}).setdefault("attributeShares", {})[r.key] = r.share
    below: dict = {}
    for tp, r in rows.items():
        below.setdefault(r["parent_typed_path"], []).append(tp)

    def union(paths):
        parts = [node(t) for t in sorted(paths)]
        return parts[0] if len(parts) == 1 else {"oneOf": parts}

    label = p.options.get("equivalence") == "label"

    def node(tp):
        r, out = rows[tp], {}
        kind = r["kind"]
        out["type"] = "integer" if kind == "number" and r["integers"] else kind
        kids = below.get(tp, [])
        if kind == "object":
            by: dict = {}
            for k in kids:
                by.setdefault(_key(rows[k]["step"]), []).append(k)
            out["properties"] = {k: union(v) for k, v in sorted(by.items())}
            if r["required"] or label:
                out["required"] = r["required"] or sorted(by)
            if r["depends"]:
                out["dependentRequired"] = {d["a"]: d["b"] for d in r["depends"]}
            if closed or label:
                out["additionalProperties"] = False
        elif kind == "array":
            placed = {rows[k]["step"] for k in kids if rows[k]["step"] != "[*]"}
            if placed:
                out["items"] = [union([k for k in kids if rows[k]["step"] == f"[{i}]"]) for i in range(len(placed))]
                out["additionalItems"] = False
            elif kids:
                out["items"] = union(kids)
            elif closed:
                out["maxItems"] = 0
            for name, k in (("minItems", "array_min"), ("maxItems", "array_max")):
                if r[k] is not None:
                    out[name] = r[k]
            if r["all_unique"]:
                out["uniqueItems"] = True
        elif kind == "number":
            out |= {name: r[k] for name, k in (("minimum", "number_min"), ("maximum", "number_max")) if r[k] is not None}
            if r["integers"] and (r["divisor"] or 0) > 1:
                out["multipleOf"] = r["divisor"]
        elif kind == "string":
            out |= {name: r[k] for name, k in (("minLength", "string_min"), ("maxLength", "string_max"), ("format", "format")) if r[k] is not None}
            ends = [*(["^" + regex_escape(r["prefix"])] if r["prefix"] else []), *([regex_escape(r["suffix"]) + "$"] if r["suffix"] else [])]
            # prefix and suffix may overlap in short strings, so they are two patterns
            if len(ends) == 1:
                out["pattern"] = ends[0]
            elif ends:
                out["allOf"] = [{"pattern": e} for e in ends]
        more = notes.get(tp, {})
        if "examples" in more:
            out["examples"] = more.pop("examples")
        if more and annotate:
            out["x-profile"] = more
        return out

    roots = below.get("", [])
    top = union(roots) if roots else {"not": {}}
    return {"$schema": "https://json-schema.org/draft/2019-09/schema", **top}
