"""Measures: soundness, accuracy, overfit, acceptance, schema size, linearity, sketch errors."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.texts import bucket
from . import baselines
from .discover import Profile, bloom_contains, bloom_rates, discover, facts_of
from .generate import generate
from .validate import RULES, validate

#: Rows of the accuracy report: minimum and one monoid, by the validation rules that each enables.
VARIANTS = {
    "minimum": (), "maxmin number": ("maxmin_number",), "multiple": ("multiple",), "maxmin string": ("maxmin_string",), "pattern": ("pattern",), "format": ("format",),
    "maxmin array": ("maxmin_array",), "unique": ("unique",), "required": ("required",), "dependencies": ("dependencies",), "all": RULES,
}
FULL = ["required", "dependencies", "maxmin", "multiple", "pattern", "format", "unique", "examples"]


def split(docs: DataFrame, share: int, seed: int = 0) -> tuple[DataFrame, DataFrame]:
    """(training, test): buckets under `share`, and the last ten of a hundred. Training sets of growing shares are nested."""
    b = bucket(F.col("doc_id"), seed)
    return docs.where(b < share), docs.where(b >= 90)


def soundness(docs: DataFrame, p: Profile) -> DataFrame:
    """Share of the documents that their own schema accepts: 1."""
    return validate(docs, p).agg(F.avg(F.col("valid").cast("double")).alias("accepted"), F.count(F.lit(1)).alias("documents"))


def ground_truth_filter(docs: DataFrame, schema: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(documents that the hand-written schema accepts, those it rejects)."""
    v = validate(docs, schema)
    return docs.join(v.where("valid").select("doc_id"), "doc_id", "left_semi"), docs.join(v.where("not valid").select("doc_id"), "doc_id", "left_semi")


def reject_filter(docs: DataFrame, schema: DataFrame) -> DataFrame:
    """Generated documents that the ground truth rejects."""
    return ground_truth_filter(docs, schema)[1]


def shares(validated: DataFrame, name: str) -> DataFrame:
    """variant, <name>: share rejected by each variant; all variants from one validation."""
    cols = [F.avg(rejects_column(rules).cast("double")).alias(v) for v, rules in VARIANTS.items()]
    one = validated.agg(*cols)
    return one.select(F.explode(F.array(*[F.struct(F.lit(v).alias("variant"), F.col(f"`{v}`").alias(name)) for v in VARIANTS])).alias("s")).select("s.*")


def rejects_column(rules):
    return F.arrays_overlap("rules", F.array(*map(F.lit, ("type", "unknown", *rules))))


def accuracy(p: Profile, truth: DataFrame, n: int = 1000, gen: str = "sampled", seed: int = 0) -> DataFrame:
    """variant, accuracy: share of generated documents, invalid under the truth, that each variant rejects."""
    bad = reject_filter(generate(p, n, gen, seed), truth)
    return shares(validate(bad, p), f"accuracy_{gen}")


def overfit(docs: DataFrame, seed: int = 0) -> DataFrame:
    """variant, overfit: share of the held-out tenth that the schema of the other nine rejects."""
    train, test = split(docs, 90, seed)
    return shares(validate(test, discover(train, FULL)), "overfit")


def acceptance(docs: DataFrame, monoids="simple", share: int = 90, seed: int = 0) -> DataFrame:
    """share, accepted: of the test tenth, by the schema of `share` percent."""
    train, test = split(docs, share, seed)
    return validate(test, discover(train, monoids)).agg(F.lit(share).alias("share"), F.avg(F.col("valid").cast("double")).alias("accepted"))


def baseline_report(docs: DataFrame, truth: DataFrame, n: int = 1000, seed: int = 0) -> DataFrame:
    """variant, accuracy_sampled, accuracy_random, overfit of the baseline schemas."""
    train, test = split(docs, 90, seed)
    p = discover(docs, ["examples"])
    bad = {g: reject_filter(generate(p, n, g, seed), truth) for g in ("sampled", "random")}
    out = None
    for name, make in (("type fusion", lambda d: (lambda x: validate(x, baselines.fusion_rules(d, False)))), ("type fusion with counts", lambda d: (lambda x: validate(x, baselines.fusion_rules(d)))), ("entity split", lambda d: baselines.entity_validator(d, closed=False)), ("entity split closed", lambda d: baselines.entity_validator(d, closed=True))):
        check = make(train)
        cols = {"accuracy_sampled": check(bad["sampled"]), "accuracy_random": check(bad["random"]), "overfit": check(test)}
        row = None
        for c, v in cols.items():
            one = v.agg(F.avg((~F.col("valid")).cast("double")).alias(c))
            row = one if row is None else row.crossJoin(one)  # one row each
        row = row.select(F.lit(name).alias("variant"), *cols)
        out = row if out is None else out.unionByName(row)
    return out


def schema_size(p: Profile) -> DataFrame:
    """paths, locations, alternatives: typed paths, paths, and typed paths beyond one a path."""
    return p.nodes.agg(F.count(F.lit(1)).alias("typed_paths"), F.count_distinct("path").alias("paths")).withColumn("alternatives", F.col("typed_paths") - F.col("paths"))


def seconds(df: DataFrame) -> float:
    """Time of computing all rows."""
    t = time.time()
    df.write.format("noop").mode("overwrite").save()
    return time.time() - t


def profile_seconds(p: Profile) -> float:
    out = sum(seconds(d) for d in (p.nodes, p.keysets, p.examples, p.divisors, p.bloom) if d is not None)
    p.release()
    return out


def bench_batch(docs: DataFrame, presets=("minimum", "simple", "all"), shares_=(1, 50, 90), seed: int = 0) -> list[dict]:
    """Seconds of each preset and of the type-fusion baseline at each share."""
    out = []
    for share in shares_:
        train, _ = split(docs, share, seed)
        for preset in presets:
            out.append({"share": share, "method": preset, "seconds": profile_seconds(discover(train, preset))})
        out.append({"share": share, "method": "type fusion", "seconds": seconds(baselines.type_fusion(train))})
        t = time.time()
        try:
            baselines.entity_types(train)
            out.append({"share": share, "method": "entity split", "seconds": time.time() - t})
        except ValueError:  # over its bound of key sets
            out.append({"share": share, "method": "entity split", "seconds": None})
    return out


def linearity(rows: DataFrame) -> DataFrame:
    """method, slope, r2 of seconds over shares, from rows(method, share, seconds)."""
    return rows.groupBy("method").agg(F.regr_slope("seconds", "share").alias("slope"), F.regr_r2("seconds", "share").alias("r2"))


def sketch_error(docs: DataFrame, equivalence="kind", bloom_expected: int = 10_000, fpp: float = 0.01, asked: int = 20_000) -> DataFrame:
    """sketch, typed_path, exact, estimate, error of each sketch: HyperLogLog against the number of distinct values; a
    membership filter's rate by its bits against that of `asked` texts that no document holds; a histogram's running
    shares against those of all values, at its worst bin."""
    p = discover(docs, ["hll", "histogram", "bloom"], equivalence, bloom_expected=bloom_expected, bloom_fpp=fpp)
    facts = facts_of(docs, ("text", "num"), equivalence)
    exact = facts.where("text is not null and kind in ('number', 'string')").groupBy("typed_path").agg(F.count_distinct("text").cast("double").alias("exact"))
    hll = exact.join(p.finished().select("typed_path", F.col("distinct").cast("double").alias("estimate")), "typed_path")
    hll = hll.select(F.lit("hll").alias("sketch"), "typed_path", "exact", "estimate", (F.abs(F.col("estimate") - F.col("exact")) / F.col("exact")).alias("error"))
    strange = docs.sparkSession.range(asked).select(F.concat(F.lit("no such value "), "id").alias("text"))
    paths = p.bloom.select("typed_path").distinct()
    found = bloom_contains(p.bloom, paths.crossJoin(strange), bloom_expected, fpp)  # paths, schema-sized, times `asked`
    rate = found.groupBy("typed_path").agg(F.avg(F.col("member").cast("double")).alias("exact")).join(bloom_rates(p).select("typed_path", F.col("rate").alias("estimate")), "typed_path")
    rate = rate.select(F.lit("bloom").alias("sketch"), "typed_path", "exact", "estimate", F.abs(F.col("estimate") - F.col("exact")).alias("error"))
    bins = p.nodes.where("bins is not null").select("typed_path", F.posexplode("bins").alias("k", "b"), F.aggregate("bins", F.lit(0.0), lambda a, b: a + b["y"]).alias("all"))
    upto = Window.partitionBy("typed_path").orderBy("k")  # at most 100 bins a path
    bins = bins.select("typed_path", F.col("b.x").alias("x"), ((F.sum("b.y").over(upto) - F.col("b.y") / 2) / F.col("all")).alias("share"))
    values = facts.where("num is not null").groupBy("typed_path", "num").agg(F.count(F.lit(1)).cast("double").alias("c"))
    below = bins.join(values, "typed_path").groupBy("typed_path", "x", "share").agg((F.sum(F.when(F.col("num") < F.col("x"), F.col("c")).when(F.col("num") == F.col("x"), F.col("c") / 2).otherwise(0.0)) / F.sum("c")).alias("true"))
    cdf = below.groupBy("typed_path").agg(F.max(F.struct(F.abs(F.col("share") - F.col("true")).alias("e"), "true", "share")).alias("w"))
    cdf = cdf.select(F.lit("histogram").alias("sketch"), "typed_path", F.col("w.true").alias("exact"), F.col("w.share").alias("estimate"), F.col("w.e").alias("error"))
    return hll.unionByName(rate).unionByName(cdf)
