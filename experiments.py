"""The experiments on the given tables: python experiments.py SF_DIR [E1 E2 ...]; prints one table each.

E1 accuracy and E2 overfit by monoid with the baselines, E3 seconds and E4 acceptance by preset and training share,
E5 added cost of each monoid on a feed, E6 open against closed, E7 kind against label, E8 keys and inclusions, E9 drift.
"""

from __future__ import annotations

import os
import sys
import tempfile
import time

from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from docprofile.operators import baselines, measures, usecases
from docprofile.operators.discover import discover
from docprofile.plans.ground_truth import manifest_schema
from docprofile.sources import workloads as W
from docprofile.sources.readers import table
from docprofile.streaming import stream as S

COLLECTIONS = ("events", "articles", "baskets", "threads", "suppliers", "checkins", "parts", "lines", "turns", "customers")


def clean(spark, d):
    return measures.ground_truth_filter(W.docs_manifests(spark, d), manifest_schema(spark))[0]


def e1(spark, d):
    docs = clean(spark, d).cache()
    p, truth = discover(docs, measures.FULL), manifest_schema(spark)
    return measures.accuracy(p, truth, 1000, "sampled").join(measures.accuracy(p, truth, 1000, "random"), "variant").join(measures.overfit(docs), "variant").orderBy("variant")


def e2(spark, d):
    return measures.baseline_report(clean(spark, d).cache(), manifest_schema(spark), 1000)


def e3(spark, d):
    out = []
    for name in COLLECTIONS:
        docs = W.WORKLOADS[name](spark, d).cache()
        docs.count()
        out += [(name, r["share"], r["method"], round(r["seconds"], 2)) for r in measures.bench_batch(docs)]
        docs.unpersist()
    return spark.createDataFrame(out, "collection string, share int, method string, seconds double").groupBy("collection", "share").pivot("method").agg(F.first("seconds")).orderBy("collection", "share")


def e4(spark, d):
    out = None
    for name in COLLECTIONS:
        docs = W.WORKLOADS[name](spark, d)
        for preset in ("minimum", "simple"):
            for share in (1, 50, 90):
                row = measures.acceptance(docs, preset, share).select(F.lit(name).alias("collection"), F.lit(preset).alias("preset"), "share", "accepted")
                out = row if out is None else out.unionByName(row)
    return out.groupBy("collection", "preset").pivot("share", [1, 50, 90]).agg(F.first("accepted")).orderBy("collection", "preset")


def e5(spark, d):
    home = tempfile.mkdtemp() + "/feed"
    W.docs_events(spark, d).repartition(8).write.parquet(home)
    n, out, least = spark.read.parquet(home).count(), [], None
    for name in ("minimum", "maxmin", "pattern", "format", "unique", "stats", "hll", "histogram", "required", "dependencies", "examples", "multiple", "attribute_counts"):
        t = time.time()
        feed = S.read_stream(spark, home, spark.read.parquet(home).schema, 2)
        if name in ("minimum", "maxmin", "pattern", "format", "unique", "stats", "hll", "histogram"):
            S.discover_stream(feed, "minimum" if name == "minimum" else [name], name=f"e5_{name}").awaitTermination()
        else:
            S.fold_stream(feed, S.Fold(spark, tempfile.mkdtemp(), [name])).awaitTermination()
        s = time.time() - t
        least = s if least is None else least
        out.append((name, round(s, 2), round(s - least, 2), round(n / s)))
    return spark.createDataFrame(out, "monoid string, seconds double, added double, documents_per_second long")


def e6(spark, d):
    return e2(spark, d).where("variant like 'entity%'")


def e7(spark, d):
    out = None
    for name in COLLECTIONS:
        docs = W.WORKLOADS[name](spark, d)
        train, test = measures.split(docs, 50)
        for eq in ("kind", "label"):
            p = discover(train, "minimum", eq)
            row = measures.schema_size(p).crossJoin(measures.soundness(test, p).select("accepted")).select(F.lit(name).alias("collection"), F.lit(eq).alias("equivalence"), "typed_paths", "alternatives", "accepted")  # one row each
            out = row if out is None else out.unionByName(row)
    return out


def e8(spark, d):
    docs = W.docs_products(spark, d).cache()
    p = discover(docs, ["hll", "bloom", "maxmin", "multiple"])
    usecases.rank_keys(p, usecases.primary_keys(p, docs.count())).orderBy("rank").show(10, False)
    return usecases.rank_foreign_keys(p, usecases.foreign_keys(p)).orderBy("rank")


def e9(spark, d):
    e = table(spark, d, "events").where("value is not null")
    side = lambda c: e.where(c).select(F.col("value").alias("x"))
    mid = e.agg(F.expr("percentile_approx(ts, 0.5)").alias("m")).first().m
    halves = usecases.ks_exact(side(F.col("ts") < F.lit(mid)), side(F.col("ts") >= F.lit(mid))).select(F.lit("two halves of time").alias("groups"), "gap", "threshold", "differs")
    return halves.unionByName(usecases.ks_exact(side("event_type = 'purchase'"), side("event_type = 'click'")).select(F.lit("purchase and click").alias("groups"), "gap", "threshold", "differs"))


def entity(spark, d):
    return baselines.entity_split(W.docs_manifests(spark, d))


def main() -> None:
    d, names = sys.argv[1] if len(sys.argv) > 1 else "/root/testdata/sf0.01", sys.argv[2:] or [f"E{i}" for i in range(1, 10)]
    spark = SparkSession.builder.master(f"local[{os.environ.get('BENCH_CPUS', '8')}]").config("spark.sql.shuffle.partitions", "8").config("spark.driver.memory", "12g").config("spark.ui.enabled", "false").config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    for n in names:
        print(n, (globals()[n.lower()].__name__))
        globals()[n.lower()](spark, d).show(100, False)


if __name__ == "__main__":
    main()
