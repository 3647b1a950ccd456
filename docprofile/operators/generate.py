"""Documents drawn from a minimal schema, with values sampled from the collection or random.

Each document is a choice of a subtree: for each object every property is in by a keyed coin, for each location one of its
alternatives. What is chosen depends on hashes of (document, typed path) only, so generation is one narrow pass over
spark.range(n): the schema tree, schema-sized, travels with the tasks.
"""

from __future__ import annotations

import hashlib
import json
import random

import pyarrow as pa
from pyspark.sql import DataFrame

from .discover import Profile

MAX_PATHS = 50_000
LETTERS = "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789"


def generate(p: Profile, n: int, gen: str = "sampled", seed: int = 0, share: float = 0.5) -> DataFrame:
    """(doc_id, json) of n documents with the names and types of the profile's structure. Sampled values need its examples."""
    spark = p.nodes.sparkSession
    rows = [r.asDict() for r in p.nodes.select("typed_path", "parent_typed_path", "step", "kind").orderBy("typed_path").limit(MAX_PATHS + 1).collect()]
    if len(rows) > MAX_PATHS:
        raise ValueError(f"over {MAX_PATHS} typed paths")
    below: dict = {}
    for r in rows:
        below.setdefault(r["parent_typed_path"], {}).setdefault(r["step"], []).append((r["typed_path"], r["kind"]))
    values: dict = {}
    if gen == "sampled":
        if p.examples is None:
            raise ValueError("sampled values need a profile with examples")
        for r in p.examples.select("typed_path", "example").orderBy("typed_path", "example").toLocalIterator():
            values.setdefault(r.typed_path, []).append(r.example)  # at most EXAMPLES a path

    def run(batches):
        def coin(doc, tp):
            return random.Random(hashlib.md5(f"{seed}:{doc}:{tp}".encode()).digest())

        def value(doc, tp, kind, at):
            rng = coin(doc, f"{tp}@{at}")
            if kind == "object":
                return "{" + ",".join(f"{json.dumps(_name(s))}:{pick(doc, s, alts, at)}" for s, alts in below.get(tp, {}).items() if coin(doc, f"{tp}{s}@{at}").random() < share) + "}"
            if kind == "array":
                alts = below.get(tp, {}).get("[*]")
                return "[" + ",".join(pick(doc, "[*]", alts, f"{at}/{i}") for i in range(rng.randint(0, 5))) + "]" if alts else "[]"
            if gen == "sampled" and values.get(tp):
                return rng.choice(values[tp])
            if kind == "string":
                return json.dumps("".join(rng.choices(LETTERS, k=rng.randint(1, 12))))
            if kind == "number":
                return str(rng.choice([rng.randint(-(10**6), 10**6), round(rng.uniform(-1000, 1000), 3)]))
            return rng.choice(["true", "false"]) if kind == "boolean" else "null"

        def pick(doc, step, alts, at):
            tp, kind = coin(doc, f"{step}{at}{alts[0][0]}").choice(alts)
            return value(doc, tp, kind, at)

        for b in batches:
            ids = b.column(0).to_pylist()
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([pick(i, "$", below[""]["$"], "") for i in ids], pa.string())], ["doc_id", "json"])

    return spark.range(n).withColumnRenamed("id", "doc_id").mapInArrow(run, "doc_id long, json string")


def _name(step: str) -> str:
    return json.loads(step[1:]) if step.startswith('."') else step[1:]
