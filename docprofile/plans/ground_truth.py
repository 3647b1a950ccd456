"""A hand-written schema of the manifest collection, as rule rows, and rule rows from plain Python."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from ..operators.validate import COLUMNS, _split

FIELDS = [c.strip().split(" ", 1)[0] for c in _split(COLUMNS)]


def rules(spark: SparkSession, rows: list[dict]) -> DataFrame:
    """Rule rows of a schema: each has typed_path, parent_typed_path, step, kind and the rules it sets."""
    return spark.createDataFrame([tuple(r.get(f) for f in FIELDS) for r in rows], COLUMNS)


def _row(parent: str, step: str, kind: str, **more) -> dict:
    return {"parent_typed_path": parent, "step": step, "kind": kind, "typed_path": f"{parent}{step}<{kind}>", **more}


def manifest_schema(spark: SparkSession) -> DataFrame:
    """What an author of the manifests of workload docs_manifests would write."""
    root = "$<object>"
    dist, os, words, deps, fund = (f"{root}.{k}<{t}>" for k, t in (("dist", "object"), ("os", "array"), ("keywords", "array"), ("dependencies", "object"), ("funding", "object")))
    out = [
        _row("", "$", "object", required=["dist", "name", "version"]),
        _row(root, ".name", "string", string_min=1), _row(root, ".version", "string", string_min=5, string_max=14),
        _row(root, ".dist", "object", required=["shasum", "tarball"], depends=[("tarball", ["shasum"])]),
        _row(dist, ".shasum", "string", string_min=40, string_max=40), _row(dist, ".tarball", "string", format="uri"),
        _row(root, ".os", "array", all_unique=True, array_min=1), _row(os, "[*]", "string"),
        _row(root, ".keywords", "array"), _row(words, "[*]", "string"),
        _row(root, ".funding", "string", format="uri"), _row(root, ".funding", "object", required=["url"]), _row(fund, ".url", "string", format="uri"),
        _row(root, ".size", "number", number_min=1.0, integers=True),
    ]
    out += [_row(root, ".dependencies", "object"), *[_row(deps, f".{b}", "string") for b in DEPENDENCY_KEYS]]
    out += [_row(root, ".scripts", "object"), *[_row(f"{root}.scripts<object>", f".task{i}", "string", string_min=1) for i in range(TASKS)]]
    return rules(spark, out)


#: Numbered task names that its scripts can have.
TASKS = 120
#: Names that the dependencies of a manifest can have.
DEPENDENCY_KEYS = tuple(f"lib{i}" for i in range(25))
