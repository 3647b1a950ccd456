"""Connected components by alternating large and small stars on DataFrames; nothing is collected."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import discard, join_unique, materialise


def components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """edges(u long, v long) to (node, root): root is the smallest node that a node can reach. Nodes without edges have no row."""
    e = edges.where("u <> v").select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).distinct()
    e, seen = materialise(e, "edges"), None
    for _ in range(max_rounds):
        now = e.agg(F.count(F.lit(1)).alias("c"), F.coalesce(F.sum(F.xxhash64("u", "v").cast("decimal(38,0)")), F.lit(0)).alias("h")).first()
        if now == seen or now["c"] == 0:
            break
        seen = now
        both = e.unionByName(e.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.min("v").alias("m"), F.count(F.lit(1)).alias("n"))
        large = join_unique(both, low, ["u"], "n", 2 * now["c"]).where("v > u").select(F.col("v").alias("u"), F.least("u", "m").alias("v"))
        large = materialise(large.where("u <> v").distinct(), "large")
        low = large.groupBy("u").agg(F.min("v").alias("m"), F.count(F.lit(1)).alias("n"))
        small = join_unique(large, low, ["u"], "n", now["c"]).where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v"))
        past, e = e, materialise(small.unionByName(low.select("u", F.col("m").alias("v"))).distinct(), "small")
        discard(past, large)
    return e.select(F.col("u").alias("node"), F.col("v").alias("root")).unionByName(e.select(F.col("v").alias("node"), F.col("v").alias("root")).distinct())
