"""The engine against worked examples, brute force, algebraic laws and DuckDB."""

import datetime
import functools
import json
import math
import random
import re

import duckdb
import pytest
from pyspark.sql import functions as F

import __spark_entry__ as entry_point
from docprofile import queries as Q
from docprofile.functions import formats
from docprofile.operators import baselines, extensions, measures, monoids, usecases
from docprofile.operators import discover as D
from docprofile.operators.discover import discover, facts_of
from docprofile.operators.flatten import flatten, flatten_typed, parse_documents
from docprofile.operators.generate import generate
from docprofile.operators.validate import NEEDS, RULES, rejects, schema_rows, validate, validate_facts
from docprofile.plans.ground_truth import manifest_schema, rules
from docprofile.plans.json_schema import to_json_schema
from docprofile.sources import workloads as W
from docprofile.sources.readers import rows
from docprofile.streaming import stream as S

WORKED = [{"a": 1, "b": ["x"]}, {"a": "1"}, {"a": 2, "b": []}]
EDGE = ["{}", "[]", '{"a":{}}', '{"a":[]}', "1", '"x"', "null", "[1]", '{"a.b":1,"a":{"b":2},"":3,"x y":4,"q\\"":5}', "1.0", "1e0", "-0.0", "12345678901234567890123", '{"a":1,"a":2}', '{"a":1', "", None, "[null,[null,{}]]", '{"k":[1,1.0,"1"]}', "NaN"]


def nodes(p, *cols):
    return {r.typed_path: tuple(r[c] for c in cols) for r in p.finished().collect()}


def test_worked_example(spark):
    p = discover(rows(spark, WORKED), "all")
    got = nodes(p, "n", "number_min", "number_max", "string_min", "string_max", "array_min", "array_max")
    assert got["$<object>"][0] == 3
    assert got["$<object>.a<number>"][:3] == (2, 1.0, 2.0)
    assert got["$<object>.a<string>"][0] == 1 and got["$<object>.a<string>"][3:5] == (1, 1)
    assert got["$<object>.b<array>"][0] == 2 and got["$<object>.b<array>"][5:] == (0, 1)
    assert got["$<object>.b<array>[*]<string>"][0] == 1 and len(got) == 5
    assert [r.key for r in D.required_keys(p.keysets).collect()] == ["a"]
    label = discover(rows(spark, WORKED), "minimum", "label")
    assert sorted(n for (n,) in nodes(label, "n").values()) == [1, 1, 1, 2, 2, 2]


def test_engines_agree_on_edge_documents(spark):
    docs = rows(spark, EDGE)
    for equivalence in ("kind", "label"):
        want = sorted((r.doc_id, r.typed_path, r.num, r.str, r.text, r["keys"], r.arr_len, r.uniq) for r in flatten(parse_documents(docs)[0], equivalence, max_depth=5).collect())
        got = sorted((r.doc_id, r.typed_path, r.num, r.str, r.text, r["keys"], r.arr_len, r.uniq) for r in facts_of(docs, ("num", "str", "text", "keys", "arr_len", "uniq"), equivalence).collect())
        key = lambda r: (r[0], r[1], str(r[4]))
        drop = lambda rs: [x for x in sorted(rs, key=key) if "<number>" not in x[1] or x[2] < 1e15]
        assert drop(got) == drop(want)
        folded, plain = discover(docs, "minimum", equivalence), discover(docs, "minimum", equivalence, engine="variant", max_depth=5)
        assert nodes(folded, "n") == nodes(plain, "n")
    bad = {r.doc_id: r.reason for r in parse_documents(docs)[1].collect()}
    assert set(bad) == {13, 14, 15, 19} and bad[15] == "empty"
    none = spark.createDataFrame([(1, None)], "doc_id long, json string")
    assert parse_documents(none)[1].first().reason == "null" and facts_of(none, ("num",)).count() == 0


@pytest.mark.parametrize("name", ["all", "simple"])
def test_fold_equals_facts(spark, sf, name):
    docs = W.docs_events(spark, sf)
    fold, facts = discover(docs, name), discover(docs, name, engine="variant", max_depth=4)
    cols = [c for c in fold.finished().columns if c not in ("bins", "hll", "distinct", "skewness", "kurtosis", "mean", "stddev") and not c.startswith("st_")]
    a, b = nodes(fold, *cols), nodes(facts, *cols)
    fmt = [cols.index(c) for c in ("fmt_n", "fmt_lo", "fmt_hi", "fmt_all")]
    for k in a:
        assert [x for i, x in enumerate(a[k]) if i not in fmt] == [x or None if i in (cols.index("prefix"), cols.index("suffix")) and x is None else x for i, x in enumerate(b[k]) if i not in fmt], k
    assert sorted(map(str, fold.keysets.collect())) == sorted(map(str, facts.keysets.select(fold.keysets.columns).collect()))
    assert sorted(map(str, fold.divisors.collect())) == sorted(map(str, facts.divisors.collect()))
    if name == "all":
        assert sorted(map(str, fold.bloom.collect())) == sorted(map(str, facts.bloom.select(fold.bloom.columns).collect()))
        x, y = nodes(fold, "distinct"), nodes(facts, "distinct")
        assert all(x[k] == y[k] or abs(x[k][0] - y[k][0]) <= 0.02 * y[k][0] for k in x)
        both = fold.nodes.select("typed_path", "hll").unionByName(facts.nodes.select("typed_path", "hll")).groupBy("typed_path").agg(F.hll_sketch_estimate(F.hll_union_agg("hll")).alias("d"))
        assert all(r.d is None or abs(r.d - (x[r.typed_path][0] or 0)) <= 0.02 * r.d for r in both.collect())  # the same registers
        for c in ("mean", "stddev", "skewness", "kurtosis"):
            x, y = nodes(fold, c), nodes(facts, c)
            assert all((x[k][0] is None) == (y[k][0] is None) and (x[k][0] is None or math.isclose(x[k][0], y[k][0], rel_tol=1e-6, abs_tol=1e-9)) for k in x)


def test_examples_are_uniform_and_merge(spark):
    docs = rows(spark, [{"v": i} for i in range(3000)]).repartition(5)
    p = discover(docs, ["examples"])
    got = {int(r.example) for r in p.examples.collect()}
    assert 90 <= len(got) <= 100 and abs(sum(got) / len(got) - 1500) < 350
    halves = [discover(docs.where(f"doc_id % 2 = {k}"), ["examples"]) for k in (0, 1)]
    assert sorted(map(str, D.merge_profiles(*halves).examples.collect())) == sorted(map(str, p.examples.select("typed_path", "slot", "key", "example").collect()))
    f = facts_of(docs, ("text",))
    a, b = (D.bottom_k(f.where(f"doc_id % 2 = {k}"), 20) for k in (0, 1))
    assert sorted(map(str, D.merge_bottom_k(a, b, 20).collect())) == sorted(map(str, D.bottom_k(f, 20).select("typed_path", "key", "example", "total").collect()))


def test_weighted_draws():
    share = sum(sum(x >= 100 for x in D.merge_reservoirs(list(range(10)), 10, list(range(100, 200)), 100, 10, s)[0]) for s in range(300)) / 3000
    assert abs(share - 100 / 110) < 0.03


@pytest.mark.parametrize("seed", [1, 2])
def test_merge_laws(spark, sf, seed):
    docs = W.docs_threads(spark, sf)
    ids = [r.doc_id for r in docs.select("doc_id").collect()]
    rng = random.Random(seed)
    parts = [[] for _ in range(3)]
    for i in ids:
        rng.choice(parts).append(i)
    ps = [discover(docs.where(docs.doc_id.isin(part)) if part else docs.limit(0), "all") for part in parts] + [discover(docs.limit(0), "all")]
    rng.shuffle(ps)
    whole, merged = discover(docs, "all"), functools.reduce(D.merge_profiles, ps)
    cols = ["n", "number_min", "number_max", "string_min", "string_max", "array_min", "array_max", "all_unique", "prefix", "suffix", "format", "distinct", "divisor", "integers"]
    assert nodes(whole, *cols) == nodes(merged, *cols)
    for part in ("keysets", "divisors"):
        a = getattr(whole, part)
        assert sorted(map(str, a.collect())) == sorted(map(str, getattr(merged, part).select(a.columns).collect()))
    assert sorted(map(str, whole.bloom.collect())) == sorted(map(str, merged.bloom.select(whole.bloom.columns).collect()))
    n = nodes(whole, "st_n", "mean", "stddev")
    for k, v in nodes(merged, "st_n", "mean", "stddev").items():
        assert all(x == y or math.isclose(x, y, rel_tol=1e-9, abs_tol=1e-9) for x, y in zip(v, n[k], strict=True))


def test_strings(spark):
    p = discover(rows(spark, [{"u": "é1", "w": "aba", "d": "2024-01-02", "x": "http://a/1.png"}, {"u": "è1", "w": "aba", "d": "2024-02-30x", "x": "http://b/2.png"}]), ["pattern", "format"])
    got = {k.split(".")[-1]: v for k, v in nodes(p, "prefix", "suffix", "format").items() if "string" in k}
    assert got["u<string>"] == ("", "1", None) and got["w<string>"][:2] == ("aba", "aba") and got["d<string>"][2] is None
    assert got["x<string>"] == ("http://", ".png", "uri")
    schema = to_json_schema(p)
    assert "allOf" in schema["properties"]["w"] and schema["properties"]["x"]["format"] == "uri"


def test_divisors(spark):
    p = discover(rows(spark, [{"a": 0, "b": 1.5, "c": 12}, {"a": 12, "b": 2, "c": -18}, {"a": -18, "b": 3, "c": 30.0}]), ["multiple"])
    got = {k[9:]: v for k, v in nodes(p, "divisor", "integers").items() if "number" in k}
    assert got == {".a<number>": (6, True), ".b<number>": (None, False), ".c<number>": (6, True)}
    scaled = discover(rows(spark, [{"b": 1.5}, {"b": 2.25}]), ["multiple"], scale=2)
    assert nodes(scaled, "divisor")["$<object>.b<number>"] == (75,)


def test_tuples(spark):
    p = discover(rows(spark, [{"r": [1, "a"]}, {"r": [2, "b"]}]), "minimum", tuples=True)
    assert set(nodes(p, "n")) == {"$<object>", "$<object>.r<array>", "$<object>.r<array>[0]<number>", "$<object>.r<array>[1]<string>"}
    assert len(to_json_schema(p)["properties"]["r"]["items"]) == 2
    p = discover(rows(spark, [{"r": [1, "a"]}, {"r": [2, "b"]}, {"r": [3]}]), "minimum", tuples=True)
    assert set(nodes(p, "n")) == {"$<object>", "$<object>.r<array>", "$<object>.r<array>[*]<number>", "$<object>.r<array>[*]<string>"}


def test_dependencies(spark):
    p = discover(rows(spark, [{"city": 1, "state": 2}, {"state": 3}, {"z": 1}, {"z": 2, "x": 3, "y": 4}]), ["dependencies"])
    got = {(r.a, r.b) for r in D.dependencies(p.keysets).collect()}
    assert ("city", "state") in got and ("state", "city") not in got
    assert {(r.a, r.b) for r in D.dependencies(p.keysets, "mutual").collect()} == {("x", "y"), ("y", "x")}
    assert D.attribute_groups(p.keysets) == [("$<object>", ("x", "y"))]


def test_histogram_merge(spark):
    rng = random.Random(5)
    vals = [rng.gauss(0, 1) for _ in range(4000)]
    docs = rows(spark, [{"v": v} for v in vals])
    p = D.merge_profiles(*[discover(docs.where(f"doc_id % 2 = {k}"), ["histogram"]) for k in (0, 1)])
    bins = [(b["x"], b["y"]) for b in p.nodes.where("kind = 'number'").first().bins]
    assert len(bins) <= 100 and sum(y for _, y in bins) == 4000
    cum = 0
    for x, y in bins:
        cum += y
        assert abs(cum / 4000 - sum(v <= x for v in vals) / 4000) < 0.05


def test_formats(spark):
    cases = ["2024-01-02", "2024-01-02T03:04:05Z", "03:04:05", "123e4567-e89b-12d3-a456-426614174000", "10.0.0.1", "a@b.org", "http://x.org/y", "x.example.org", "plain", "", "1:2"]
    df = spark.createDataFrame([(c,) for c in cases], "v string")
    got = [(r.a, r.b) for r in df.select(formats.label(df.v).alias("a"), formats.label_combined(df.v).alias("b")).collect()]
    assert [a for a, _ in got] == ["date", "date-time", "time", "uuid", "ipv4", "email", "uri", "hostname", None, None, None]
    assert all(a == b for a, b in got)
    assert formats.labels_early_stop(["p"] * 3, ["10.0.0.1", "plain", "10.0.0.2"]) == [("p", None)]


def check_value(v, schema) -> bool:
    """An independent validator of the keywords that to_json_schema writes."""
    if "oneOf" in schema:
        return sum(check_value(v, s) for s in schema["oneOf"]) == 1
    if "not" in schema:
        return False
    t = schema["type"]
    kinds = {"object": dict, "array": list, "string": str, "boolean": bool, "null": type(None)}
    if t in kinds:
        if not isinstance(v, kinds[t]):
            return False
    elif isinstance(v, bool) or not isinstance(v, int | float) or (t == "integer" and v != int(v)):
        return False
    if t == "object":
        props = schema["properties"]
        ok = set(schema.get("required", [])) <= set(v) and (schema.get("additionalProperties", True) or set(v) <= set(props))
        ok &= all(set(b) <= set(v) for a, b in schema.get("dependentRequired", {}).items() if a in v)
        return ok and all(check_value(x, props[k]) for k, x in v.items() if k in props)
    if t == "array":
        ok = schema.get("minItems", 0) <= len(v) <= schema.get("maxItems", 1e9)
        if schema.get("uniqueItems"):
            ok &= len({json.dumps(x, sort_keys=True) for x in v}) == len(v)
        return ok and all(check_value(x, schema["items"]) for x in v if "items" in schema)
    if t == "string":
        pats = [schema["pattern"]] if "pattern" in schema else [p["pattern"] for p in schema.get("allOf", [])]
        return schema.get("minLength", 0) <= len(v) <= schema.get("maxLength", 1e9) and all(re.search(p, v) for p in pats) and ("format" not in schema or bool(re.search(formats.FORMATS[schema["format"]], v)))
    if t in ("number", "integer"):
        return schema.get("minimum", -1e308) <= v <= schema.get("maximum", 1e308) and v % schema.get("multipleOf", v or 1) == 0
    return True


@pytest.mark.parametrize("equivalence", ["kind", "label"])
def test_schema_and_validator_agree(spark, sf, equivalence):
    for docs in (W.docs_manifests(spark, sf), W.docs_threads(spark, sf), W.docs_events(spark, sf).limit(150)):
        train, test = measures.split(docs, 50)
        p = discover(train, measures.FULL, equivalence)
        schema = to_json_schema(p)
        everything = test.unionByName(generate(discover(docs, ["examples"]), 60).withColumn("doc_id", F.col("doc_id") + 10**9)) if equivalence == "kind" else test
        texts = {r.doc_id: r.json for r in everything.collect()}
        for r in validate(everything, p).collect():
            assert r.valid == check_value(json.loads(texts[r.doc_id]), schema), (texts[r.doc_id], r.rules)
        assert measures.soundness(train, p).first().accepted == 1


def test_soundness_of_each_monoid(spark, sf):
    docs = W.docs_products(spark, sf)
    for name in [*monoids.REGISTRY, *monoids.SIDE]:
        assert measures.soundness(docs, discover(docs, [name])).first().accepted == 1, name


def test_monotone_acceptance(spark, sf):
    docs = W.docs_manifests(spark, sf)
    got = [measures.acceptance(docs, "simple", s).first().accepted for s in (1, 50, 90)]
    assert got == sorted(got)
    v = validate(measures.split(docs, 50)[1], discover(measures.split(docs, 50)[0], measures.FULL))
    n = [rejects(v, RULES[: k + 2]).where("rejected").count() for k in range(len(RULES) - 1)]
    assert n == sorted(n)


def test_validator_rules(spark):
    schema = rules(spark, [{"typed_path": "$<object>", "parent_typed_path": "", "step": "$", "kind": "object", "required": ["a"]}, {"typed_path": "$<object>.a<number>", "parent_typed_path": "$<object>", "step": ".a", "kind": "number", "number_min": 0.0, "divisor": 3, "integers": True}])
    docs = rows(spark, [{"a": 3}, {"a": 4}, {"a": -3}, {}, {"a": "3"}, {"a": 3, "b": 1}, "{", {"a": 3.5}])
    got = [r.rules for r in validate(docs, schema).orderBy("doc_id").collect()]
    assert got == [[], ["multiple"], ["maxmin_number"], ["required"], ["type"], ["unknown"], ["type"], ["multiple"]]
    assert [r.valid for r in validate(docs, schema, closed=False).orderBy("doc_id").collect()] == [True, False, False, False, False, True, False, False]


def test_ground_truth_and_accuracy(spark):
    d = "/root/testdata/sf0.01"
    docs, truth = W.docs_manifests(spark, d), manifest_schema(spark)
    good, bad = measures.ground_truth_filter(docs, truth)
    assert 0 < bad.count() < 0.02 * docs.count() and good.count() + bad.count() == docs.count()
    p = discover(good, measures.FULL)
    for gen in ("sampled", "random"):
        got = {r.variant: r[1] for r in measures.accuracy(p, truth, 300, gen).collect()}
        assert got["all"] == max(got.values()) and got["all"] > 0.9 and got["minimum"] == 0 and got["required"] > 0.5
    over = {r.variant: r.overfit for r in measures.overfit(good).collect()}
    assert over["minimum"] <= 0.02 and over["all"] == max(over.values()) and over["required"] <= over["maxmin string"] + 0.05
    base = {r.variant: r for r in measures.baseline_report(good, truth, 200).collect()}
    assert base["entity split closed"].accuracy_sampled >= base["entity split"].accuracy_sampled
    assert base["entity split closed"].overfit >= base["entity split"].overfit


def test_entity_split(spark):
    got = {(r.typed_path, tuple(r.properties)) for r in baselines.entity_split(rows(spark, [{"a": 1, "b": 2}, {"c": 1, "d": 2}, {"a": 3, "b": 1}])).collect()}
    assert got == {("$<object>", ("a", "b")), ("$<object>", ("c", "d"))}
    check = baselines.entity_validator(rows(spark, [{"a": 1, "b": 2}, {"c": 1, "d": 2}]), closed=True)
    assert [r.valid for r in check(rows(spark, [{"a": 1, "b": 2}, {"a": 1, "d": 2}, {"c": 1, "d": 1, "e": 1}])).orderBy("doc_id").collect()] == [True, False, False]


def test_keys_and_inclusions(spark, sf):
    docs = W.docs_products(spark, sf)
    p = discover(docs, ["hll", "bloom", "maxmin", "multiple"])
    keys = usecases.primary_keys(p, docs.count())
    assert usecases.rank_keys(p, keys).orderBy("rank").first().path == "$.sku"
    found = {(r.child, r.parent) for r in usecases.foreign_keys(p).collect()}
    assert ("$<object>.related<object>.also_bought<array>[*]<number>", "$<object>.sku<number>") in found
    assert "sku" in usecases.explore(p) and usecases.sample_values(discover(docs, ["examples"]), "$.title").count() > 0


def test_bloom_has_no_false_negative(spark):
    docs = rows(spark, [{"v": f"k{i}"} for i in range(500)])
    f = facts_of(docs, ("text",)).where("kind = 'string'").select("typed_path", "text")
    b = D.bloom_of(facts_of(docs, ("text",)), 500, 0.01)
    assert D.bloom_contains(b, f, 500, 0.01).where("not member").count() == 0
    other = spark.createDataFrame([("$<object>.v<string>", f'"z{i}"') for i in range(2000)], "typed_path string, text string")
    assert D.bloom_contains(b, other, 500, 0.01).where("member").count() < 60
    for expected in (500, 20_000, 1_000_000, "estimate"):
        p = discover(spark.range(20_000).selectExpr("id as doc_id", "concat('{\"v\":', id, '}') as json"), ["bloom"], bloom_expected=expected)
        asked = spark.range(50_000, 70_000).selectExpr("'$<object>.v<number>' as typed_path", "cast(id as string) as text")
        rate = D.bloom_contains(p.bloom, asked, p.options["bloom_expected"], 0.01).agg(F.avg(F.col("member").cast("int"))).first()[0]
        told = D.bloom_rates(p).first()
        assert rate == pytest.approx(told.rate, rel=0.25, abs=0.001) and (rate > 0.5 if expected == 500 else rate < 0.02 and abs(told.distinct_values - 20_000) < 600)


def test_outliers_and_drift(spark):
    docs = rows(spark, [{"v": i % 10} for i in range(500)] + [{"v": 1000}])
    got = usecases.value_outliers(docs, discover(docs, ["stats"])).collect()
    assert [(r.doc_id, r.value) for r in got] == [(500, 1000.0)]
    a, b = ([{"v": random.Random(k * 1000 + i).gauss(k, 1)} for i in range(400)] for k in (0, 2))
    pa, pb = discover(rows(spark, a), ["histogram"]), discover(rows(spark, b), ["histogram"])
    assert usecases.ks_test(pa, pb, "$.v").first().differs and not usecases.ks_test(pa, pa, "$.v").first().differs


def test_user_monoid(spark):
    monoids.register_monoid("sum_of_squares", ("num",), lambda: {"sq": F.sum(F.col("num") * F.col("num"))}, lambda: {"sq": F.sum("sq")}, lambda: {"rms": F.sqrt(F.col("sq") / F.col("n"))}, ("number",))
    try:
        docs = rows(spark, [{"v": 3}, {"v": 4}])
        assert nodes(discover(docs, ["sum_of_squares"]), "sq")["$<object>.v<number>"] == (25.0,)
        parts = [discover(docs.where(f"doc_id = {k}"), ["sum_of_squares"]) for k in (0, 1)]
        assert nodes(D.merge_profiles(*parts), "sq")["$<object>.v<number>"] == (25.0,)
    finally:
        del monoids.REGISTRY["sum_of_squares"]


def test_streams(spark, sf, tmp_path):
    docs = W.docs_events(spark, sf)
    docs.repartition(3).write.parquet(str(tmp_path / "in"))
    read = lambda: S.read_stream(spark, str(tmp_path / "in"), docs.schema)
    fold = S.Fold(spark, str(tmp_path / "fold"), "simple")
    S.fold_stream(read(), fold).awaitTermination()
    whole = discover(docs, "simple")
    cols = ["n", "number_min", "string_max", "array_max", "all_unique", "prefix", "format", "divisor"]
    assert nodes(fold.load(), *cols) == nodes(whole, *cols) and fold.done == [1, 2]
    again = S.Fold(spark, str(tmp_path / "fold"), "simple")  # a restart goes on from what is stored
    again.add(docs, 3)
    assert {k: v[0] for k, v in nodes(again.load(), "n").items()} == {k: 2 * v[0] for k, v in nodes(whole, "n").items()} and again.done == [2, 3]
    again.add(docs, 3)  # a replay replaces its own version
    assert nodes(again.load(), "n")["$<object>"] == (2 * docs.count(),)
    two = [S.Fold(spark, str(tmp_path / f"f{k}"), "simple") for k in (0, 1)]
    for k, f in enumerate(two):
        f.add(docs.where(f"doc_id % 2 = {k}"), 0)
    assert nodes(S.discover_hybrid(two), *cols) == nodes(whole, *cols)
    q = S.discover_stream(read(), ["maxmin", "hll", "stats"], str(tmp_path / "cp"), "running_test")
    q.awaitTermination()
    assert {r.typed_path: r.n for r in spark.table("running_test").collect()} == {k: v[0] for k, v in nodes(whole, "n").items()}


def test_merged_moments_keep_their_digits(spark):
    vals = [1.7e9 + i % 2 for i in range(4000)]
    docs = rows(spark, [{"v": v} for v in vals]).repartition(7)
    for p in (discover(docs, ["stats"]), discover(docs, ["stats"], tree_fanin=4), functools.reduce(D.merge_profiles, [discover(docs.where(f"doc_id % 3 = {k}"), ["stats"]) for k in range(3)])):
        n, mean, stddev, skewness, kurtosis = nodes(p, "st_n", "mean", "stddev", "skewness", "kurtosis")["$<object>.v<number>"]
        assert n == 4000 and mean == pytest.approx(1.7e9 + 0.5, rel=1e-15) and stddev == pytest.approx(0.5) and skewness == pytest.approx(0, abs=1e-6) and kurtosis == pytest.approx(-2)


def test_nothing_is_lost_silently(spark):
    deep = "1"
    for k in range(25):
        deep = f'{{"k{k}":{deep}}}' if k % 2 else f"[{deep}]"
    docs = spark.createDataFrame([("a", deep), ("b", deep), (None, '"\\ud800"'), ("a", "[" * 2000 + "]" * 2000)], "doc_id string, json string")
    by_keys = lambda kind, keys: F.when(kind == "object", F.array_join(keys, "+"))
    for equivalence in ("kind", "label", by_keys):
        p = discover(docs, "all", equivalence)
        assert nodes(p, "n")["$<string>"] == (1,) and p.nodes.count() == 27 and sum(n for (n,) in nodes(p, "n").values()) == 53
        assert [r.valid for r in validate(docs, p).collect()] == [True, True, True, False]
    with pytest.raises(Exception, match="max_depth"):
        discover(docs, "minimum", engine="variant", max_depth=8).nodes.collect()
    examples = {r.example for r in discover(spark.createDataFrame([(None, f'{{"v":{i}}}') for i in range(50)], "doc_id string, json string"), ["examples"]).examples.collect()}
    assert len(examples) > 25  # null ids don't hide each other


def test_labels_of_many_key_sets(spark):
    docs = spark.range(120_000).select(F.col("id").alias("doc_id"), F.concat(F.lit('{"k'), F.col("id").cast("string"), F.lit('":1}')).alias("json"))
    p = discover(docs, ["required"], "label")
    roots = p.nodes.where("path = '$'")
    assert roots.count() == 120_000 and p.keysets.groupBy("typed_path").count().where("count > 1").isEmpty()


def test_typed_route_walks_what_nests(spark):
    df = spark.sql("select 1L as id, named_struct('a b', array(named_struct('x', 1, 'y', cast(null as string)), named_struct('x', 2, 'y', 'z'))) as s, map('k', array(1.5D), 'l', array()) as m, array(cast(null as int), 7) as n")
    got = {r.typed_path: r.n for r in flatten_typed(df, "id").groupBy("typed_path").count().withColumnRenamed("count", "n").collect()}
    docs = df.select(F.col("id").alias("doc_id"), F.to_json(F.struct("*")).alias("json"))
    assert got == {k: v[0] for k, v in nodes(discover(docs, "minimum"), "n").items()}


def test_validators_agree(spark, sf):
    for docs, equivalence in ((W.docs_manifests(spark, sf), "kind"), (W.docs_threads(spark, sf), "label")):
        train, test = measures.split(docs, 50)
        p = discover(train, measures.FULL, equivalence)
        test = test.unionByName(rows(spark, [{"name": 3}, "{", {"conv_id": -1, "turns": [{"a": 1}, 2]}, [1, 1]]).select((F.col("doc_id") - 9).alias("doc_id"), "json"))
        for closed in (True, False):
            by_join = validate_facts(test, facts_of(test, NEEDS, equivalence), schema_rows(p), closed).collect()
            narrow = {r.doc_id: r.rules for r in validate(test, p, closed).collect()}
            assert {r.doc_id: r.rules for r in by_join if r.doc_id != -8} == {k: v for k, v in narrow.items() if k != -8} and narrow[-8] == ["type"]


def test_running_tables(spark, sf, tmp_path):
    docs = W.docs_events(spark, sf)
    docs.repartition(3).write.parquet(str(tmp_path / "in"))
    whole = discover(docs, "all")
    read = lambda: S.read_stream(spark, str(tmp_path / "in"), docs.schema)
    for name, df, want in (("k", S.running_keysets(read()), whole.keysets), ("d", S.running_divisors(read()), whole.divisors), ("b", S.running_bloom(read()), whole.bloom), ("e", S.running_examples(read()), None)):
        df.writeStream.outputMode("complete").format("memory").queryName(f"running_{name}").trigger(availableNow=True).start().awaitTermination()
        got = spark.table(f"running_{name}")
        assert got.count() > 100 if want is None else sorted(map(str, got.collect())) == sorted(map(str, want.select(got.columns).collect()))


def test_plans(spark, sf):
    docs = W.docs_events(spark, sf)
    plan = discover(docs, "minimum", engine="variant", max_depth=4).nodes._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange hashpartitioning") == 1 and not re.search("Python|Arrow", plan)
    plan = discover(docs, "minimum", sample_fraction=0.1, engine="variant", max_depth=3).nodes._jdf.queryExecution().optimizedPlan().toString()
    assert plan.rindex("pmod") > plan.rindex("try_parse_json") if "try_parse_json" in plan else True


def test_extensions(spark, sf):
    assert {(r.a, r.b) for r in extensions.functional_dependencies(W.docs_nations(spark, sf)).collect()} >= {("$.n_nationkey", "$.n_regionkey")}
    assert extensions.data_keys(discover(W.docs_checkins(spark, sf), ["attribute_counts"])).first().typed_path == "$<object>.hours<object>"


def norm(v):
    return None if isinstance(v, float) and math.isnan(v) else v + 0.0 if isinstance(v, float) else str(v) if isinstance(v, datetime.datetime) else v


@pytest.mark.parametrize("name", sorted(Q.ORACLE_SQL))
def test_oracle(spark, sf, name):
    con = duckdb.connect()
    for t in ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations"):
        con.execute(f"create view {t} as select * from '{sf}/{t}.parquet'")
    df = Q.QUERIES[name](spark, sf)
    r = con.execute(Q.ORACLE_SQL[name])
    cols = [c[0] for c in r.description]
    assert sorted(cols) == sorted(df.columns)
    want = sorted((tuple(map(norm, x)) for x in r.fetchall()), key=repr)
    assert sorted((tuple(norm(x[c]) for c in cols) for x in df.collect()), key=repr) == want


def test_entry(spark):
    df = entry_point.entry(spark)
    assert df.count() > 0 and set(entry_point.oracle_sql()) <= set(entry_point.queries())


def test_schema_rows_of_empty_input(spark):
    p = discover(spark.createDataFrame([], "doc_id long, json string"), "all")
    assert schema_rows(p).count() == 0 and "not" in to_json_schema(p)
