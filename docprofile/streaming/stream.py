"""Streaming discovery: a running profile by stateful aggregation, by a fold of batches, or by sub-streams merged now and then."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery

from ..operators.discover import BLOOM_EXPECTED, BLOOM_FPP, IDENTITY, Profile, bloom_of, discover, divisor_rows, facts_of, gcd_of_all, merge_all, slots
from ..operators.monoids import choose
from ..sources import folders

#: The engine's setting for where streaming state lies, and its store on local disks.
STATE_STORE, ROCKS = "spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider"


def read_stream(spark: SparkSession, path: str, schema, files_per_trigger: int = 1) -> DataFrame:
    """Parquet files as they arrive."""
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


def running(stream: DataFrame, monoids="minimum", equivalence: str = "kind") -> DataFrame:
    """The running profile of a stream of (doc_id, json) as a streaming aggregation: state of one row a typed path.

    Column monoids only; the others are running tables of their own (running_keysets for required keys, dependencies and
    counts, running_examples, running_divisors, running_bloom), and a Fold has them all in one pass. Merging is
    commutative, so late documents need no watermark.
    """
    choice = choose(monoids)
    f = facts_of(stream, choice.needs, equivalence)
    ids = [F.first(c).alias(c) for c in IDENTITY]
    return f.groupBy("typed_path").agg(*ids, *[c.alias(k) for m in choice.columns for k, c in m.partial().items()])


def running_keysets(stream: DataFrame) -> DataFrame:
    f = facts_of(stream, ("keys",))
    return f.where("kind = 'object'").groupBy("typed_path", "keys").agg(F.count(F.lit(1)).alias("n"))


def running_examples(stream: DataFrame, k: int = 100, seed: int = 0) -> DataFrame:
    return slots(facts_of(stream, ("text",)), k, seed)


def running_divisors(stream: DataFrame, scale: int = 0) -> DataFrame:
    """State: the distinct divisors of batches, which are soon one another's."""
    return gcd_of_all(divisor_rows(facts_of(stream, ("num", "whole")), scale), "typed_path")


def running_bloom(stream: DataFrame, expected: int = BLOOM_EXPECTED, fpp: float = BLOOM_FPP) -> DataFrame:
    return bloom_of(facts_of(stream, ("text",)), expected, fpp)


def discover_stream(stream: DataFrame, monoids="minimum", checkpoint: str | None = None, name: str = "profile", available_now: bool = True) -> StreamingQuery:
    """Start the running profile into a table in memory of this name (complete mode)."""
    w = running(stream, monoids).writeStream.outputMode("complete").format("memory").queryName(name)
    if checkpoint:
        w = w.option("checkpointLocation", checkpoint)
    return (w.trigger(availableNow=True) if available_now else w).start()


def windowed(stream: DataFrame, ts: str = "ts", width: str = "1 day", late: str = "1 hour", slide: str | None = None) -> DataFrame:
    """Counts by window and typed path of (doc_id, json, ts): late rows beyond the watermark are dropped from closed windows only."""
    timed = stream.withWatermark(ts, late)
    at = F.window(ts, width, slide) if slide else F.window(ts, width)
    return timed.groupBy(at.alias("window"), F.expr("schema_of_variant(try_parse_json(json))").alias("shape")).agg(F.count(F.lit(1)).alias("n"))


def sessions(stream: DataFrame, key: str, ts: str = "ts", gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    """Documents by key and session of a feed with columns key and ts."""
    return stream.withWatermark(ts, late).groupBy(F.session_window(ts, gap).alias("session"), key).agg(F.count(F.lit(1)).alias("n"))


def to_table(result: DataFrame, folder: str) -> DataFrame:
    """All that is there of a stream run to its end, its last complete result as a table in a folder that all executors share.

    State lies in RocksDB on the executors' disks and each version is written by tasks, so neither the driver nor an
    executor's heap holds as many rows as the result has. A version that is replaced goes.
    """
    spark, last = result.sparkSession, []

    def put(df: DataFrame, batch: int) -> None:
        df.write.mode("overwrite").parquet(f"{folder}/v{batch}")
        for b in last:
            if b != batch:
                folders.delete(spark, f"{folder}/v{b}")
        last[:] = [batch]

    before = spark.conf.get(STATE_STORE)
    spark.conf.set(STATE_STORE, ROCKS)
    try:
        q = result.writeStream.outputMode("complete").foreachBatch(put).option("checkpointLocation", f"{folder}/checkpoint").trigger(availableNow=True).start()
        q.awaitTermination()
    finally:
        spark.conf.set(STATE_STORE, before)
    return spark.read.schema(result.schema).parquet(f"{folder}/v{last[0]}") if last else spark.createDataFrame([], result.schema)


def deduplicated(stream: DataFrame, ts: str = "ts", late: str = "1 hour") -> DataFrame:
    """A feed that may deliver a document twice, each doc_id once within the watermark."""
    return stream.withWatermark(ts, late).dropDuplicatesWithinWatermark(["doc_id"])


class Fold:
    """A fold of batches: the profile of each batch merged with the stored one, each version at a new path.

    A version's path names its batch, so a batch that is replayed after a failure replaces its own result. A version counts
    once its mark is there, and a new Fold on a folder goes on from the versions that it finds. The last `keep` versions
    stay, older ones go.
    """

    PARTS = ("keysets", "examples", "divisors", "bloom", "nodes")

    def __init__(self, spark: SparkSession, folder: str, monoids="simple", equivalence: str = "kind", keep: int = 2, **options):
        self.spark, self.folder, self.monoids, self.equivalence, self.keep, self.options = spark, folder.rstrip("/"), monoids, equivalence, max(2, keep), options

    def _at(self, batch: int, part: str = "") -> str:
        return f"{self.folder}/v{batch}/{part}".rstrip("/")

    @property
    def done(self) -> list[int]:
        """Batches whose versions are whole."""
        found = [int(n[1:]) for n in folders.names(self.spark, self.folder) if n[:1] == "v" and n[1:].isdigit()]
        return sorted(b for b in found if folders.exists(self.spark, self._at(b, "WHOLE")))

    def load(self, batch: int | None = None) -> Profile | None:
        if batch is None:
            have = self.done
            if not have:
                return None
            batch = have[-1]
        parts = {k: self.spark.read.parquet(self._at(batch, k)) for k in self.PARTS if folders.exists(self.spark, self._at(batch, k))}
        sizes = {"bloom_expected": self.options.get("bloom_expected", BLOOM_EXPECTED), "bloom_fpp": self.options.get("bloom_fpp", BLOOM_FPP)}
        return Profile(parts.pop("nodes"), choose(self.monoids), **parts, options={"equivalence": self.equivalence, **sizes})

    def add(self, docs: DataFrame, batch: int) -> None:
        new = discover(docs, self.monoids, self.equivalence, **self.options)
        have = self.done
        old = next((b for b in reversed(have) if b < batch), None)
        p = new if old is None else merge_all([self.load(old), new])
        folders.delete(self.spark, self._at(batch))
        for part in self.PARTS:
            df = getattr(p, part)
            if df is not None:
                df.coalesce(4).write.parquet(self._at(batch, part))  # schema-sized
        folders.mark(self.spark, self._at(batch, "WHOLE"))
        new.release()
        for b in [b for b in have if b < batch][: -(self.keep - 1)]:
            folders.delete(self.spark, self._at(b))


def fold_stream(stream: DataFrame, fold: Fold, checkpoint: str | None = None) -> StreamingQuery:
    """Start a fold over all that is there of a stream of (doc_id, json)."""
    w = stream.writeStream.foreachBatch(lambda df, batch: fold.add(df, batch)).trigger(availableNow=True)
    return (w.option("checkpointLocation", checkpoint) if checkpoint else w).start()


def discover_hybrid(folds: list[Fold]) -> Profile:
    """The profiles of partitioned sub-streams as one."""
    return merge_all([p for p in (f.load() for f in folds) if p is not None])


def publish(stream: DataFrame, sink: Callable[[DataFrame, int], None]) -> StreamingQuery:
    """Each version of a running profile to a sink."""
    return stream.writeStream.outputMode("complete").foreachBatch(sink).trigger(availableNow=True).start()


__all__ = ["Fold", "discover_hybrid", "discover_stream", "fold_stream", "publish", "read_stream", "running", "running_bloom", "running_divisors", "running_examples", "running_keysets", "sessions", "deduplicated", "to_table", "windowed"]
