"""SimHash near-dedup with multi-index hashing.

A fingerprint of 64 bits is cut into two segments. Fingerprints within two bits have a segment within one bit, so a
table on each segment's value, looked up with the segment's Hamming ball of radius one, finds every pair; the whole
distance is then verified. Of two segments one bit apart one has a 0 where the other has a 1, so a look-up flips zeros
only and still meets each pair. A segment value that more than CROWD fingerprints share isn't listed: all that ask for
it are linked through whole-fingerprint balls of radius one instead (two fingerprints within two bits share a member of
those balls, and all that share a member are within two bits), at most 65 to a group, so no bucket makes all its pairs.

Defined cases: null text counts as empty; a text without words has fingerprint zero and links like any other; repeated
rows each get a row; other columns are ignored; a null id takes part, and is nobody's smallest id while others are there.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import join_unique, materialise, slices, utf8
from .graph import components

CROWD = 24
#: Words of one piece of a very long text.
PIECE = 1 << 16


def bit_counts(words: list[bytes], size: int, seed: int) -> tuple[np.ndarray, int]:
    """How many shingles set each of the 64 bits, most significant first, and the number of shingles."""
    from xxhash import xxh64_intdigest as h

    counts, n = np.zeros(64, np.int64), 0
    if not words:
        return counts, 0
    for at in range(0, max(1, len(words) - size + 1), PIECE):
        part = words[at : at + PIECE + size - 1]
        joined = b" ".join(part)
        ends = np.cumsum(np.fromiter(map(len, part), np.int64, len(part))) + np.arange(len(part))
        k = max(1, len(part) - size + 1)
        starts = np.concatenate(([0], ends[:-1] + 1))[:k].tolist()
        stops = ends[size - 1 :].tolist() if len(part) >= size else [len(joined)]
        hashes = np.array([h(joined[a:b], seed) for a, b in zip(starts, stops, strict=True)], ">u8")
        counts += np.unpackbits(hashes.view(np.uint8).reshape(k, 8), axis=1).sum(axis=0, dtype=np.int64)
        n += k
    return counts, n


def fingerprint(text: bytes, size: int = 3, seed: int = 42) -> int:
    """Signed 64-bit fingerprint of a UTF-8 text: bytes.lower() folds A-Z only and bytes.split() cuts at [\\x20\\x09-\\x0D]."""
    counts, n = bit_counts(text.lower().split(), size, seed)
    return int(np.packbits(2 * counts > n).view(">i8")[0]) if n else 0


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", size: int = 3, seed: int = 42) -> DataFrame:
    """doc_id, fp (long)."""
    kind = dict(docs.dtypes)[id_col]

    def run(batches):
        for b in slices(batches):
            fps = [fingerprint(t, size, seed) for t in utf8(b.column(1))]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(fps, pa.int64())], ["doc_id", "fp"])

    return docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(run, f"doc_id {kind}, fp long")


def links(fps: DataFrame, crowd: int = CROWD) -> DataFrame:
    """Distinct fingerprints fp to edges (u, v) that connect what lies within two bits."""
    # a table's key is the segment's number above its 32 bits
    halves = F.array(*[F.shiftrightunsigned("fp", 32 * s).bitwiseAND(F.lit(0xFFFFFFFF)).bitwiseOR(F.lit(s << 32)) for s in (0, 1)])
    table = fps.select("fp", F.explode(halves).alias("key"))
    size = table.groupBy("key").agg(F.count(F.lit(1)).alias("n"))
    crowded = size.where(F.col("n") > crowd).select("key", F.lit(None).cast("long").alias("found"))
    # at most `crowd` fingerprints a value: what is listed is bounded
    # the planner takes exploded rows for as many as went in and might broadcast them: both joins are told to shuffle
    few = table.join(size.where(F.col("n") <= crowd).select("key").hint("merge"), "key").select("key", F.col("fp").alias("found"))
    flips = F.expr("array_append(transform(filter(sequence(0, 31), b -> (key & shiftleft(1L, b)) = 0), b -> key | shiftleft(1L, b)), key)")
    asked = table.select("fp", F.explode(flips).alias("key"))
    hits = asked.join(few.unionByName(crowded).hint("merge"), "key")
    near = F.bit_count(F.col("fp").bitwiseXOR(F.col("found"))) <= 2
    hits = materialise(hits.where(F.col("found").isNull() | (near & (F.col("fp") != F.col("found")))).select(F.col("fp").alias("u"), F.col("found").alias("v")).distinct(), "hits")
    rest = hits.where("v is null").select(F.col("u").alias("fp")).distinct()
    ball = F.expr("array_append(transform(sequence(0, 63), b -> fp ^ shiftleft(1L, b)), fp)")
    groups = rest.select("fp", F.explode(ball).alias("mid")).groupBy("mid").agg(F.collect_set("fp").alias("all")).where("size(all) > 1")
    stars = groups.select(F.array_min("all").alias("u"), F.explode("all").alias("v")).where("u <> v").distinct()
    return hits.where("v is not null").unionByName(stars)


def near_groups(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", size: int = 3, seed: int = 42, crowd: int = CROWD) -> DataFrame:
    """doc_id, fingerprint (16 hex digits), component_id: one row a row of docs."""
    rows = materialise(fingerprints(docs, id_col, text_col, size, seed), "fps")
    fps = materialise(rows.groupBy("fp").agg(F.min("doc_id").alias("first"), F.count(F.lit(1)).alias("n")), "distinct")
    roots = components(links(fps.select("fp"), crowd))
    roots = fps.join(roots, fps.fp == roots.node, "left").select("fp", "first", "n", F.coalesce("root", "fp").alias("root"))
    total = rows.count()
    least = roots.groupBy("root").agg(F.min("first").alias("component_id"), F.sum("n").alias("docs"), F.count(F.lit(1)).alias("k"))
    # a fingerprint that one document has, linked to none, needs no look-up
    least = least.where("docs > 1")
    at = materialise(join_unique(roots, least.drop("docs"), ["root"], "k", total).where("component_id is not null").select("fp", "n", "component_id"), "roots")
    out = join_unique(rows, at, ["fp"], "n", total)
    return out.select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), F.coalesce("component_id", "doc_id").alias("component_id"))
