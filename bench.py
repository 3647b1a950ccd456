"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one JSON line."""

from __future__ import annotations

import json
import os
import sys
import time

sys.path.insert(0, os.path.dirname(os.path.abspath(__file__)))

from pyspark.sql import SparkSession  # noqa: E402

from docprofile.operators import baselines, measures  # noqa: E402
from docprofile.operators.discover import discover  # noqa: E402
from docprofile.operators.validate import validate  # noqa: E402
from docprofile.sources import workloads as W  # noqa: E402
from docprofile.streaming import stream as S  # noqa: E402


def stream_seconds(spark, docs_dir: str, preset) -> tuple[float, float]:
    """Seconds and documents a second of a feed of JSON lines."""
    t = time.time()
    feed = spark.readStream.schema("doc_id long, json string").parquet(docs_dir)
    q = S.discover_stream(feed, preset, name=f"bench_{int(t * 1000)}")
    q.awaitTermination()
    s = time.time() - t
    return s, spark.read.parquet(docs_dir).count() / s


def main() -> None:
    d, cpus = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1"), os.environ.get("BENCH_CPUS", "8")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]").config("spark.sql.shuffle.partitions", cpus).config("spark.driver.memory", "12g").config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false").config("spark.sql.session.timeZone", "UTC").config("spark.sql.objectHashAggregate.sortBased.fallbackThreshold", "40000").getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    import tempfile

    home = tempfile.mkdtemp()
    docs, rates = {}, {}
    for name in ("events", "lines", "manifests", "customers", "baskets"):
        W.WORKLOADS[name](spark, d).repartition(int(cpus)).write.parquet(f"{home}/{name}")  # the collections as files, as the experiments read them
        docs[name] = spark.read.parquet(f"{home}/{name}")
    discover(docs["events"].limit(1000), "all").nodes.count()  # start workers
    out: dict[str, float] = {}

    def timed(name, f):
        t = time.time()
        f()
        out[name] = round(time.time() - t, 3)
        print(name, out[name], file=sys.stderr, flush=True)

    for name in docs:
        n = docs[name].count()
        for preset in ("minimum", "simple", "all"):
            timed(f"{name}_{preset}", lambda name=name, preset=preset: measures.profile_seconds(discover(docs[name], preset)))
            rates[f"{name}_{preset}"] = round(n / out[f"{name}_{preset}"])
        timed(f"{name}_type_fusion", lambda name=name: measures.seconds(baselines.type_fusion(docs[name])))
    timed("lines_native", lambda: baselines.native(docs["lines"]).collect())
    timed("events_native", lambda: baselines.native(docs["events"]).collect())
    timed("manifests_entity_split", lambda: baselines.entity_types(docs["manifests"]))
    p = discover(docs["events"], "simple")
    timed("events_validate", lambda: measures.seconds(validate(docs["events"], p)))
    streams = {}
    for preset, monoids in (("minimum", "minimum"), ("columns of simple", ["format", "maxmin", "pattern", "unique"]), ("columns of all", ["format", "maxmin", "pattern", "unique", "stats", "hll", "histogram"])):
        s, r = stream_seconds(spark, f"{home}/events", monoids)
        out[f"stream_{preset.replace(' ', '_')}"] = round(s, 3)
        streams[preset] = round(r)
    fold = S.Fold(spark, f"{home}/fold", "all")
    t = time.time()
    S.fold_stream(spark.readStream.schema("doc_id long, json string").parquet(f"{home}/events"), fold).awaitTermination()
    out["stream_all"] = round(time.time() - t, 3)
    streams["all"] = round(docs["events"].count() / (time.time() - t))
    shares = []
    for k in (1, 50, 90):
        part, _ = measures.split(docs["lines"], k)
        shares.append((k, measures.profile_seconds(discover(part, "minimum"))))
    lin = spark.createDataFrame([("minimum", k, s) for k, s in shares], "method string, share int, seconds double")
    slope = measures.linearity(lin).first()
    print(json.dumps({"metric": "total of the headline queries", "value": round(sum(out.values()), 3), "unit": "sec", "queries": out, "sf": os.path.basename(d.rstrip("/")), "docs_per_second": rates, "stream_docs_per_second": streams, "linearity": {"slope": slope.slope, "r2": slope.r2, "points": shares}}))


if __name__ == "__main__":
    main()
