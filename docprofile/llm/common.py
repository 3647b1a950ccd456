"""Helpers shared by the operators: scratch tables in the shared folder, skew-proof joins, Arrow batches."""

from __future__ import annotations

import tempfile
import uuid
from contextlib import contextmanager

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: A key is hot when it holds more than one row in HOT_SHARE; so there are fewer than HOT_SHARE hot keys.
HOT_SHARE = 1000
#: The engine's own setting for dropping an execution's shuffle files when it ends, not when the driver next collects garbage.
DROP_SHUFFLES = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def shared_folder(spark: SparkSession) -> str:
    """The folder that all executors share: spark.checkpoint.dir, else the warehouse; a temporary one only in local mode."""
    base = spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if spark.sparkContext.master.startswith("local["):
            base = tempfile.mkdtemp(prefix="shared-")
        else:
            base = spark.conf.get("spark.sql.warehouse.dir")
        spark.conf.set("spark.checkpoint.dir", base)
    return base.rstrip("/")


def scratch(spark: SparkSession, tag: str) -> str:
    """A new path in the shared folder."""
    return f"{shared_folder(spark)}/{tag}-{uuid.uuid4().hex}"


@contextmanager
def shuffles_dropped(spark: SparkSession):
    """What is executed inside leaves no shuffle files behind; the session's own setting comes back after it."""
    before = spark.conf.get(DROP_SHUFFLES, None)
    spark.conf.set(DROP_SHUFFLES, "true")
    try:
        yield
    finally:
        if before is None:
            spark.conf.unset(DROP_SHUFFLES)
        else:
            spark.conf.set(DROP_SHUFFLES, before)


def materialise(df: DataFrame, tag: str) -> DataFrame:
    """Write df as a table in the shared folder and read it back: lineage ends there, and a lost executor loses nothing."""
    path = scratch(df.sparkSession, tag)
    with shuffles_dropped(df.sparkSession):
        df.write.parquet(path)
    out = df.sparkSession.read.schema(df.schema).parquet(path)
    out.written = path
    return out


def discard(*tables: DataFrame) -> None:
    """Delete tables that materialise() wrote and that nothing reads any more."""
    for t in tables:
        delete(t.sparkSession, t.written)


def delete(spark: SparkSession, path: str) -> None:
    """Delete a path that scratch() gave."""
    at = spark._jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark._jsparkSession.sessionState().newHadoopConf()).delete(at, True)


def collect_garbage(spark: SparkSession) -> None:
    """Shuffle files of results that the caller has written go once the driver has collected garbage: not left to chance."""
    spark._jvm.System.gc()


def split_hot(right: DataFrame, n: str, total: int) -> tuple[DataFrame, DataFrame]:
    """Rows of `right` (one a key, n = its rows on the other side) that are hot, fewer than HOT_SHARE of them, and the rest."""
    hot = F.col(n) * HOT_SHARE > total
    return right.where(hot), right.where(~hot)


def join_unique(left: DataFrame, right: DataFrame, keys: list[str], n: str, total: int, hint: str = "") -> DataFrame:
    """left LEFT JOIN right, where right has one row a key.

    Keys with a large share of left's rows are joined by broadcast (at most HOT_SHARE rows, whatever the input),
    so no task gets a hot key's rows; the others are joined by shuffle, as `hint` says. Keys are never null.
    """
    hot, cold = split_hot(right, n, total)
    extra = [c for c in right.columns if c not in keys and c != n]
    named = lambda df, p: df.select(*[F.col(k).alias(f"{p}{k}") for k in keys], *[F.col(c).alias(f"{p}{c}") for c in extra], F.xxhash64(*keys).alias(f"{p}join64"))
    hot, cold = named(hot, "_h_").withColumn("_hot", F.lit(True)), named(cold, "_c_")
    equal = lambda p: [same(F.col(k), F.col(f"{p}{k}")) for k in keys]
    step = left.withColumn("_join64", F.xxhash64(*keys)).join(F.broadcast(hot), _all([F.col("_join64") == F.col("_h_join64"), *equal("_h_")]), "left")
    # hot rows have no partner among the others: a hash of what else they hold deals them out evenly
    rest = [F.col(c) for c in left.columns if c not in keys] or [F.lit(0)]
    step = step.withColumn("_join64", F.when(F.col("_hot"), F.xxhash64(*rest)).otherwise(F.col("_join64")))
    cold = cold.hint(hint) if hint else cold
    out = step.join(cold, _all([F.col("_join64") == F.col("_c_join64"), *equal("_c_")]), "left")
    return out.select(*left.columns, *[F.coalesce(f"_h_{c}", f"_c_{c}").alias(c) for c in extra])


def same(a: Column, b: Column) -> Column:
    """Null-safe equality that the planner keeps as a condition beside the join key."""
    return F.coalesce(~(a < b) & ~(a > b), a.isNull() & b.isNull())


def matched(left: list[Column], right: list[Column]) -> Column:
    """Null-safe equality of rows, joined by one 64-bit key: hash tables of one long take a fraction of the memory of
    those of several columns, and what the hash brings together is compared whole."""
    return _all([F.xxhash64(*left) == F.xxhash64(*right), *[same(a, b) for a, b in zip(left, right, strict=True)]])


def text_digest(text: Column) -> Column:
    """With its id this tells a row whose id is null or stands for several texts."""
    return F.sha2(F.coalesce(text, F.lit("")).cast("binary"), 256)


def _all(conds: list[Column]) -> Column:
    out = conds[0]
    for c in conds[1:]:
        out = out & c
    return out


def utf8(column: pa.Array) -> list[bytes]:
    """Texts of an Arrow column as UTF-8 bytes, null as empty."""
    return [b or b"" for b in column.cast(pa.binary()).to_pylist()]


def slices(batches, rows: int = 256):
    """Record batches of at most `rows` rows, so that the Python objects of one slice stay few."""
    for b in batches:
        for i in range(0, b.num_rows, rows):
            yield b.slice(i, rows)


class Memo(dict):
    """make(key) kept in two generations of at most `size` entries: what is in use outlives a change of generations."""

    def __init__(self, make, size: int = 150_000, longest: int = 64):
        super().__init__()
        self.make, self.size, self.longest, self.old = make, size, longest, {}

    def __missing__(self, key):
        value = self.old.get(key)
        if value is None:
            value = self.make(key)
        if len(key) <= self.longest:
            if len(self) >= self.size:
                self.old = dict(self)
                self.clear()
            self[key] = value
        return value


def tokenizer_path(name: str) -> str:
    """Place of a public tokenizer's file on this machine; every worker has the package."""
    import public_tokenizers

    return public_tokenizers.path(name)


def file_system(uri: str):
    """(file system, path) of a folder that may lie in any store: workers open files of the shared folder through this."""
    from pyarrow import fs

    return fs.FileSystem.from_uri(uri) if "://" in uri or uri.startswith("file:") else (fs.LocalFileSystem(), uri)


def crc_mod(id_col: Column, mod: int) -> Column:
    return F.crc32(id_col.cast("string").cast("binary")) % mod
