"""Documents to facts: one row a JSON node, keyed by its typed path.

The typed path is the chain of (step, tag) from the root. Two nodes merge exactly if their typed paths are equal, so
merging schemas is a GROUP BY. A document stays one row until the end: level by level its frontier of nodes is replaced
by their children, and one inline() turns all levels into rows. There is no shuffle and no Python.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.texts import key_step

MAX_DEPTH, MAX_TUPLE = 16, 64
#: Hexadecimal digits of a key set's hash in its label: 64 bits.
LABEL_DIGITS = 16
#: Levels of a document that the engine's own parser takes.
MAX_NESTING = 1000
#: Distinct key sets whose tags an equivalence of the user's own may give on the Arrow path.
MAX_TAGS = 200_000
#: Fact fields that monoids may ask for beyond those of the structure.
VALUES = ("num", "exact", "str", "text", "keys", "arr_len", "uniq")
Equivalence = str | Callable[[Column, Column], Column]


def parse_documents(docs: DataFrame, json_col: str = "json", id_col: str = "doc_id") -> tuple[DataFrame, DataFrame]:
    """(doc_id, doc VARIANT) of what parses, and (doc_id, json, reason) of what doesn't: broken text, empty text, repeated keys."""
    d = docs.select(F.col(id_col).alias("doc_id"), F.col(json_col).alias("json"), F.try_parse_json(json_col).alias("doc"))
    why = F.when(F.col("json").isNull(), "null").when(F.trim("json") == "", "empty").otherwise("not a JSON document, or with a repeated key")
    return d.where("doc is not null").select("doc_id", "doc"), d.where("doc is null").select("doc_id", "json", why.alias("reason"))


def _kind(n: Column) -> Column:
    leaf = F.schema_of_variant(n["v"])
    return (
        F.when(n["ents"].isNotNull(), "object").when(n["arr"].isNotNull(), "array").when(F.is_variant_null(n["v"]), "null")
        .when(leaf == "STRING", "string").when(leaf == "BOOLEAN", "boolean").otherwise("number")
    )


def _tag(n: Column, kind: Column, equivalence: Equivalence) -> Column:
    keys = F.array_sort(F.transform(n["ents"], lambda e: e["key"]))
    if equivalence == "kind":
        return kind
    if equivalence == "label":
        return F.when(kind == "object", F.concat(F.lit("object#"), F.substring(F.md5(F.concat_ws("\x1f", keys)), 1, LABEL_DIGITS))).otherwise(kind)
    return F.concat(kind, F.coalesce(F.concat(F.lit("#"), equivalence(kind, keys)), F.lit("")))


def _open(v: Column, path: Column, parent: Column, step: Column) -> Column:
    """A node with its children in reach."""
    return F.struct(v.alias("v"), F.concat(path, step).alias("path"), parent.alias("ptp"), step.alias("step"), F.map_entries(F.try_variant_get(v, "$", "map<string,variant>")).alias("ents"), F.try_variant_get(v, "$", "array<variant>").alias("arr"))


def _named(nodes: Column, equivalence: Equivalence) -> Column:
    def one(n):
        kind = _kind(n)
        tag = _tag(n, kind, equivalence)
        return F.struct(n["v"].alias("v"), n["path"].alias("path"), n["ptp"].alias("ptp"), n["step"].alias("step"), n["ents"].alias("ents"), n["arr"].alias("arr"), kind.alias("kind"), tag.alias("tag"), F.concat(n["ptp"], n["step"], F.lit("<"), tag, F.lit(">")).alias("tp"))

    return F.transform(nodes, one)


def canonical_text(v: Column) -> Column:
    """Text of a value in which equal numbers are equal."""
    leaf = F.schema_of_variant(v)
    number = leaf.startswith("BIGINT") | leaf.startswith("DECIMAL") | (leaf == "DOUBLE") | (leaf == "FLOAT")
    num = F.try_variant_get(v, "$", "double") + F.lit(0.0)
    whole = (num == F.floor(num)) & (F.abs(num) < 9e15)
    return F.when(number, F.when(whole, num.cast("long").cast("string")).otherwise(num.cast("string"))).otherwise(F.to_json(v))


def flatten(docs: DataFrame, equivalence: Equivalence = "kind", values: tuple[str, ...] = VALUES, max_depth: int = MAX_DEPTH, tuples: bool = False, max_tuple: int = MAX_TUPLE) -> DataFrame:
    """(doc_id, doc VARIANT) to doc_id, ordinal, path, typed_path, parent_typed_path, step, kind, tag, truncated and the asked values.

    Nodes below max_depth are not visited; the containers at the limit are marked `truncated` (facts_of then raises, so
    no profile silently lacks them; the Arrow pass has no such limit). tuples: also positional
    steps [0]...[max_tuple - 1] next to [*]; they are typed paths of their own.
    """
    root = _named(F.array(_open(F.col("doc"), F.lit(""), F.lit(""), F.lit("$"))), equivalence)
    out = docs.where("doc is not null").select("doc_id", root.alias("_f"))
    levels = []

    def children(n):
        inner = F.transform(n["ents"], lambda e: _open(e["value"], n["path"], n["tp"], key_step(e["key"])))
        items = F.transform(n["arr"], lambda x: _open(x, n["path"], n["tp"], F.lit("[*]")))
        some = [F.coalesce(inner, items)]
        if tuples:
            placed = F.transform(F.slice(n["arr"], 1, max_tuple), lambda x, i: _open(x, n["path"], n["tp"], F.concat(F.lit("["), i.cast("string"), F.lit("]"))))
            some.append(placed)
        return F.filter(F.array(*some), lambda a: a.isNotNull()) if tuples else F.array(*some)

    def facts(nodes, last):
        def one(n):
            num = F.when(n["kind"] == "number", F.try_variant_get(n["v"], "$", "double") + F.lit(0.0))
            fields = {
                "num": num,
                "exact": F.when(n["kind"] == "number", F.try_variant_get(n["v"], "$", "decimal(38,9)")),
                "str": F.when(n["kind"] == "string", F.try_variant_get(n["v"], "$", "string")),
                "text": F.when(~n["kind"].isin("object", "array"), canonical_text(n["v"])),
                "keys": F.array_sort(F.transform(n["ents"], lambda e: e["key"])),
                "arr_len": F.when(n["kind"] == "array", F.size(n["arr"])),
                "uniq": F.when(n["kind"] == "array", F.size(F.array_distinct(F.transform(n["arr"], canonical_text))) == F.size(n["arr"])),
            }
            more = F.coalesce(F.size(n["ents"]), F.lit(0)) + F.coalesce(F.size(n["arr"]), F.lit(0)) if last else F.lit(0)
            return F.struct(n["path"].alias("path"), n["tp"].alias("typed_path"), n["ptp"].alias("parent_typed_path"), n["step"].alias("step"), n["kind"].alias("kind"), n["tag"].alias("tag"), (more > 0).alias("truncated"), *[fields[k].alias(k) for k in values])

        return F.transform(nodes, one)

    for k in range(max_depth):
        levels.append(f"_d{k}")
        out = out.withColumn(f"_d{k}", facts(F.col("_f"), k == max_depth - 1))
        if k < max_depth - 1:
            # containers only: leaves have no children to look for
            deep = F.filter("_f", lambda n: n["kind"].isin("object", "array"))
            inner = F.flatten(F.flatten(F.transform(deep, children)))
            out = out.withColumn("_f", _named(F.filter(inner, lambda n: n["v"].isNotNull()), equivalence))
    return out.select("doc_id", F.posexplode(F.concat(*levels)).alias("ordinal", "_n")).select("doc_id", "ordinal", "_n.*")


def flatten_typed(df: DataFrame, id_col: str) -> DataFrame:
    """Facts (doc_id, path, typed_path, kind, num, str) of a columnar table, from its schema: nothing is parsed.

    Null fields are absent attributes, null elements of arrays are nulls. Structs are walked on the driver (schema-sized);
    arrays, and maps as objects with their keys as attributes, are walked by the engine, however they nest.
    """
    from pyspark.sql import types as T

    none = F.array().cast("array<struct<path:string,typed_path:string,kind:string,num:double,str:string>>")

    def fact(path, tp, kind, col=None):
        num = col.cast("double") if kind == "number" and col is not None else F.lit(None).cast("double")
        text = col.cast("string") if kind == "string" and col is not None else F.lit(None).cast("string")
        return F.struct(path.alias("path"), F.concat(tp, F.lit(f"<{kind}>")).alias("typed_path"), F.lit(kind).alias("kind"), num.alias("num"), text.alias("str"))

    def below(col, kind, path, tp):
        """Facts of a value and of what it holds; null has none."""
        if isinstance(kind, T.StructType):
            inside = [below(col[f.name], f.dataType, F.concat(path, key_step(F.lit(f.name))), F.concat(tp, F.lit("<object>"), key_step(F.lit(f.name)))) for f in kind.fields]
            facts = F.concat(F.array(fact(path, tp, "object")), *inside)
        elif isinstance(kind, T.ArrayType):
            star, deeper = F.concat(path, F.lit("[*]")), F.concat(tp, F.lit("<array>[*]"))
            each = F.transform(col, lambda x: F.when(x.isNull(), F.array(fact(star, deeper, "null"))).otherwise(below(x, kind.elementType, star, deeper)))
            facts = F.concat(F.array(fact(path, tp, "array")), F.flatten(each))
        elif isinstance(kind, T.MapType):
            deeper = F.concat(tp, F.lit("<object>"))
            step = lambda e: key_step(e["key"].cast("string"))
            each = F.transform(F.map_entries(col), lambda e: below(e["value"], kind.valueType, F.concat(path, step(e)), F.concat(deeper, step(e))))
            facts = F.concat(F.array(fact(path, tp, "object")), F.flatten(each))
        else:
            name = "boolean" if isinstance(kind, T.BooleanType) else "number" if isinstance(kind, T.NumericType) else "string"
            facts = F.array(fact(path, tp, name, col))
        return F.when(col.isNotNull(), facts).otherwise(none)

    whole = F.struct(*[F.col(f"`{c}`") for c in df.columns])
    return df.select(F.col(id_col).alias("doc_id"), F.inline(below(whole, df.schema, F.lit("$"), F.lit("$"))))


def fold_arrow(docs: DataFrame, json_col: str = "json") -> DataFrame:
    """Counts by typed path (kind equivalence) by a local fold: at most one row a path and task, no depth limit."""
    import pyarrow as pa

    def run(batches):
        n: dict = {}

        def kind(v):
            return "null" if v is None else "boolean" if isinstance(v, bool) else "number" if isinstance(v, int | float) else "string" if isinstance(v, str) else "array" if isinstance(v, list) else "object"

        steps: dict = {}
        for b in batches:
            for text in b.column(0).to_pylist():
                try:
                    todo = [("$", "$", parse_strict(text))]
                except ValueError:
                    continue
                while todo:
                    path, tp, v = todo.pop()
                    k = kind(v)
                    tp = f"{tp}<{k}>"
                    at = (path, tp, k)
                    n[at] = n.get(at, 0) + 1
                    if k == "object":
                        for key, x in v.items():
                            s = steps.get(key) or steps.setdefault(key, step_text(key))
                            todo.append((path + s, tp + s, x))
                    elif k == "array":
                        todo += [(path + "[*]", tp + "[*]", x) for x in v]
        if n:
            p, t, k = zip(*n, strict=True)
            yield pa.RecordBatch.from_pydict({"path": p, "typed_path": t, "kind": k, "n": list(n.values())})

    parts = docs.select(json_col).mapInArrow(run, "path string, typed_path string, kind string, n long")
    return parts.groupBy("typed_path").agg(F.first("path").alias("path"), F.first("kind").alias("kind"), F.sum("n").alias("n"))


def label_tag(keys) -> str:
    """The label of an object with these sorted keys."""
    import hashlib

    return "object#" + hashlib.md5("\x1f".join(keys).encode()).hexdigest()[:LABEL_DIGITS]


def step_text(key: str) -> str:
    return f".{key}" if key.isascii() and key.isidentifier() else '."' + key.replace("\\", "\\\\").replace('"', '\\"') + '"'


def tags_of(docs: DataFrame, equivalence: Callable[[Column, Column], Column]) -> dict:
    """Tags that a user's equivalence gives: by kind, and of objects by the digest of their sorted keys.

    The distinct key sets (schema-sized, at most MAX_TAGS) come from a pass of their own, and the callable is applied to
    them by the engine; so documents of any depth fold under it.
    """
    import hashlib

    from .fold import fold_states

    kinds = docs.sparkSession.createDataFrame([(k, None) for k in ("array", "string", "number", "boolean", "null")], "kind string, keys array<string>")
    sets = fold_states(docs, ("required",)).where("part = 'keyset'").select(F.lit("object").alias("kind"), "keys").distinct()
    tag = F.concat("kind", F.coalesce(F.concat(F.lit("#"), equivalence(F.col("kind"), F.col("keys"))), F.lit("")))
    rows = sets.unionByName(kinds).select("kind", "keys", tag.alias("tag")).limit(MAX_TAGS + 1).collect()
    if len(rows) > MAX_TAGS:
        raise ValueError(f"over {MAX_TAGS} distinct key sets: use engine='variant', which applies the equivalence to each node")
    return {r.kind if r["keys"] is None else hashlib.md5("\x1f".join(r["keys"]).encode()).digest(): r.tag for r in rows}


def _unique_keys(pairs):
    d = dict(pairs)
    if len(d) != len(pairs):
        raise ValueError("repeated key")
    return d


def _no_constant(name):
    raise ValueError(name)


def _paired(v):
    """A value whose texts hold no half of a surrogate pair: such halves become question marks."""
    if isinstance(v, str):
        return v.encode("utf-16", "surrogatepass").decode("utf-16", "replace").replace("\ufffd", "?")
    if isinstance(v, list):
        return [_paired(x) for x in v]
    return {_paired(k): _paired(x) for k, x in v.items()} if isinstance(v, dict) else v


def _not_too_deep(v) -> None:
    level, depth = [v], 0
    while level:
        if depth > MAX_NESTING:
            raise ValueError("too deep")
        level, depth = [y for x in level if isinstance(x, list | dict) for y in (x.values() if isinstance(x, dict) else x)], depth + 1


def parse_strict(text):
    """A JSON value; ValueError for what try_parse_json refuses too: repeated keys, NaN, broken, empty or too deep text."""
    import json

    if text is None:
        raise ValueError("null")
    try:
        v = json.loads(text, object_pairs_hook=_unique_keys, parse_constant=_no_constant)
        if text.count("[") + text.count("{") > MAX_NESTING:
            _not_too_deep(v)
        return _paired(v) if "\\ud" in text or "\\uD" in text else v
    except RecursionError:
        raise ValueError("too deep") from None


def canonical_number(v) -> str:
    """Text in which equal numbers are equal: whole ones without a point."""
    try:
        d = float(v)
    except OverflowError:
        return str(v)
    if d != d or d in (float("inf"), float("-inf")):
        return "Infinity" if d > 0 else "-Infinity"
    return str(int(d)) if d == int(d) and abs(d) < 9e15 else repr(d)


def canonical(v) -> str:
    import json

    if isinstance(v, bool) or v is None or isinstance(v, str):
        return json.dumps(v, ensure_ascii=False)
    if isinstance(v, int | float):
        return canonical_number(v)
    if isinstance(v, list):
        return "[" + ",".join([canonical(x) for x in v]) + "]"
    return "{" + ",".join([f"{json.dumps(k, ensure_ascii=False)}:{canonical(v[k])}" for k in sorted(v)]) + "}"


_FIELDS = {"num": "num double", "whole": "whole long", "str": "str string", "text": "text string", "keys": "keys array<string>", "arr_len": "arr_len int", "uniq": "uniq boolean"}


def flatten_arrow(docs: DataFrame, equivalence: str | dict = "kind", values: tuple[str, ...] = tuple(_FIELDS), tuples: bool = False, max_tuple: int = MAX_TUPLE, json_col: str = "json") -> DataFrame:
    """(doc_id, json) to the facts of `flatten`, by one Arrow pass: no depth limit, about five times as fast.

    `whole` is the value of a whole number as a long (of others null), which the divisor needs. Documents that don't parse
    give no row; parse_documents tells why. A node's texts are built only if asked for.
    """
    import hashlib

    import pyarrow as pa

    kind_of_id = dict(docs.dtypes)["doc_id"]
    names = ["doc_id", "ordinal", "path", "typed_path", "parent_typed_path", "step", "kind", "tag", *values]
    arrow = {"num": pa.float64(), "whole": pa.int64(), "str": pa.string(), "text": pa.string(), "keys": pa.list_(pa.string()), "arr_len": pa.int32(), "uniq": pa.bool_()}
    schema = f"doc_id {kind_of_id}, ordinal int, path string, typed_path string, parent_typed_path string, step string, kind string, tag string" + "".join(f", {_FIELDS[v]}" for v in values)
    ask, own = set(values), isinstance(equivalence, dict)

    def run(batches):
        steps: dict = {}
        nodes: dict = {}  # (parent's place, step, tag) to the place of a path
        paths: list = []  # of each place: path, typed path, parent's typed path, step, kind, tag

        def place(parent, step, kind, tag):
            at = nodes.get((parent, step, tag))
            if at is None:
                at = nodes[parent, step, tag] = len(paths)
                pp, pt = (paths[parent][0], paths[parent][1]) if parent >= 0 else ("", "")
                paths.append((pp + step, f"{pt}{step}<{tag}>", pt, step, kind, tag))
            return at

        def step_of(key):
            s = steps.get(key)
            if s is None:
                s = steps[key] = step_text(key)
            return s

        for b in batches:
            for at in range(0, b.num_rows, 2000):
                part = b.slice(at, 2000)
                rows_doc, ordinal, places = [], [], []
                cols: dict = {v: [] for v in values}
                for doc, text in enumerate(part.column(1).to_pylist()):
                    try:
                        todo = [(-1, "$", parse_strict(text))]
                    except ValueError:
                        continue
                    n = 0
                    while todo:
                        parent, step, v = todo.pop()
                        c = v.__class__
                        kind = "string" if c is str else "number" if c is int or c is float else "object" if c is dict else "array" if c is list else "null" if v is None else "boolean"
                        tag = equivalence[kind] if own and c is not dict else kind
                        keys = None
                        if c is dict:
                            keys = sorted(v)
                            if own:
                                tag = equivalence[hashlib.md5("\x1f".join(keys).encode()).digest()]
                            elif equivalence == "label":
                                tag = label_tag(keys)
                        p = place(parent, step, kind, tag)
                        places.append(p)
                        rows_doc.append(doc)
                        ordinal.append(n)
                        n += 1
                        if c is dict:
                            todo += [(p, step_of(k), x) for k, x in v.items()]
                        elif c is list:
                            todo += [(p, "[*]", x) for x in v]
                            if tuples:
                                todo += [(p, f"[{i}]", x) for i, x in enumerate(v[:max_tuple])]
                        if "num" in ask:
                            try:
                                cols["num"].append(float(v) if kind == "number" else None)
                            except OverflowError:
                                cols["num"].append(float("inf") if v > 0 else float("-inf"))
                        if "whole" in ask:
                            cols["whole"].append(int(v) if kind == "number" and abs(v) < 2**63 and v == int(v) else None)
                        if "str" in ask:
                            cols["str"].append(v if c is str else None)
                        if "text" in ask:
                            cols["text"].append(None if c is dict or c is list else canonical(v))
                        if "keys" in ask:
                            cols["keys"].append(keys)
                        if "arr_len" in ask:
                            cols["arr_len"].append(len(v) if c is list else None)
                        if "uniq" in ask:
                            cols["uniq"].append(len({canonical(x) for x in v}) == len(v) if c is list else None)
                if not places:
                    continue
                known = pa.array(places, pa.int32())
                text = [pa.array([p[i] for p in paths], pa.string()).take(known) for i in range(6)]
                ids = part.column(0).take(pa.array(rows_doc, pa.int32()))
                yield pa.RecordBatch.from_arrays([ids, pa.array(ordinal, pa.int32()), *text, *[pa.array(cols[v], arrow[v]) for v in values]], names)

    return docs.select("doc_id", F.col(json_col)).mapInArrow(run, schema)
