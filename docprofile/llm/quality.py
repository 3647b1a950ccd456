"""Quality classifier by compression.

Two zstandard dictionaries are built, from good and from bad labelled text. A text is cut into blocks, each compressed
with either dictionary; (bytes with the bad one - bytes with the good one) / bytes of the text, over the whole text, is its
normalised difference, and a logistic curve fitted on other labelled documents turns that into a score from 0 to 1. The
curve weighs the classes as they stand in all labels, so that good documents, the most, are rarely rejected.

Fitting takes a bounded sample: DOCS labelled documents of each class (those with the smallest hashes), of whose blocks
at most BLOCKS a class build the dictionaries (from half of the documents) while the other half, whole, fits the curve.

Defined cases: null and empty texts score as difference 0; repeated rows each get a row; a document labelled twice counts
with its larger label; with labels of one class only (or none) every score is that class's share (0.5); other columns are
ignored; a null id is not held out and never labelled.
"""

from __future__ import annotations

import math

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import crc_mod, slices, utf8

DOCS, BLOCKS, BLOCK, DICT_BYTES, LEVEL = 1500, 16000, 512, 65536, 3


def _blocks(data: bytes, size: int = 0) -> list[bytes]:
    size = size or BLOCK
    return [data[i : i + size] for i in range(0, len(data), size)]


def train_dictionary(blocks: list[bytes], size: int = DICT_BYTES) -> bytes:
    """A zstandard dictionary of the blocks; of their last bytes, if they are too few to train one."""
    import zstandard

    try:
        return zstandard.train_dictionary(min(size, max(1024, sum(map(len, blocks)) // 8)), blocks).as_bytes()
    except zstandard.ZstdError:
        return b"".join(blocks)[-size:]


class Scorer:
    """Holds two dictionaries and a curve; opens the compressors where it is used."""

    def __init__(self, good: bytes, bad: bytes, slope: float = 1.0, shift: float = 0.0):
        self.dictionaries, self.slope, self.shift, self._open = (good, bad), slope, shift, None

    def __getstate__(self):
        return self.__dict__ | {"_open": None}

    def difference(self, data: bytes) -> float:
        import zstandard

        if self._open is None:
            self._open = []
            for d in self.dictionaries:
                z = zstandard.ZstdCompressionDict(d)
                z.precompute_compress(level=LEVEL)
                self._open.append(zstandard.ZstdCompressor(level=LEVEL, dict_data=z, write_content_size=False, write_checksum=False, write_dict_id=False))
        good, bad = (sum(len(z.compress(b)) for b in _blocks(data)) for z in self._open)
        return (bad - good) / len(data) if data else 0.0

    def score(self, data: bytes) -> float:
        x = self.slope * self.difference(data) + self.shift
        return 1 / (1 + math.exp(-max(-30.0, min(30.0, x))))


def fit_curve(x: list[float], y: list[int], share: float = 0.5, rounds: int = 50) -> tuple[float, float]:
    """Slope and shift of a logistic curve, by Newton's steps with a small ridge on standardised x; share: weight of class 1."""
    import numpy as np

    x, y = np.array(x, float), np.array(y, float)
    mean, std = x.mean(), x.std() or 1.0
    z = np.stack([(x - mean) / std, np.ones(len(x))], 1)
    weight = np.where(y == 1, share / max(1, y.sum()), (1 - share) / max(1, (1 - y).sum()))
    w = np.zeros(2)
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(z @ w, -30, 30)))
        g = z.T @ (weight * (p - y)) + 1e-4 * w
        h = (z * (weight * p * (1 - p))[:, None]).T @ z + 1e-4 * np.eye(2)
        w -= np.linalg.solve(h, g)
    return float(w[0] / std), float(w[1] - w[0] * mean / std)


def fit(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text_col: str = "text", label_col: str = "quality", per_class: int = DOCS) -> Scorer | None:
    """A scorer from the labelled rows of docs; None if a class has no text."""
    known = labels.where(F.col(label_col).isin(0, 1) & F.col(id_col).isNotNull()).groupBy(F.col(id_col).alias("_id")).agg(F.max(label_col).cast("int").alias("_y"))
    order = lambda y: known.where(F.col("_y") == y).orderBy(F.xxhash64("_id"), "_id").limit(per_class)
    drawn = F.broadcast(order(0).unionByName(order(1)))  # at most 2 * per_class rows
    body = F.coalesce(F.col(text_col), F.lit("")).cast("binary")
    cut = F.expr(f"transform(sequence(0, greatest(0, cast(ceil(octet_length(body) / {BLOCK}) as int) - 1)), i -> substring(body, i * {BLOCK} + 1, {BLOCK}))")
    rows = docs.join(drawn, F.col(id_col) == F.col("_id")).select("_id", "_y", body.alias("body"))
    half = F.xxhash64("_id", F.lit(1)) % 2 == 0
    pieces = rows.where("octet_length(body) > 0").select("_id", "_y", half.alias("_train"), F.posexplode(cut).alias("_no", "_block"))
    pick = lambda y: pieces.where((F.col("_y") == y) & F.col("_train")).orderBy(F.xxhash64("_id", "_no"), "_id", "_no").limit(BLOCKS)
    got: dict = {0: [], 1: []}
    for r in pick(0).unionByName(pick(1)).select("_y", "_block").toArrow().to_pylist():
        got[r["_y"]].append(r["_block"])
    if not got[0] or not got[1]:
        return None
    s = Scorer(train_dictionary(got[1]), train_dictionary(got[0]))

    def measure(batches):
        for b in slices(batches):
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([s.difference(t) for t in utf8(b.column(1))], pa.float64())], ["y", "x"])

    # at most 2 * per_class rows, and as many labels' counts as there are classes
    apart = rows.where(~half).select("_y", "body").mapInArrow(measure, "y int, x double").toArrow()
    n = {r["_y"]: r["count"] for r in known.groupBy("_y").count().collect()}
    x, y = apart.column(1).to_pylist(), apart.column(0).to_pylist()
    if len(set(y)) < 2:
        x, y = [s.difference(b) for k in (0, 1) for b in got[k]], [k for k in (0, 1) for _ in got[k]]
    s.slope, s.shift = fit_curve(x, y, n[1] / (n[0] + n[1]))
    return s


def score(docs: DataFrame, scorer: Scorer | None, id_col: str = "doc_id", text_col: str = "text", held_mod: int = 3) -> DataFrame:
    """doc_id, held_out, score, predicted: one row a row of docs."""
    kind = dict(docs.dtypes)[id_col]

    def run(batches):
        for b in slices(batches):
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array([0.5 if scorer is None else scorer.score(t) for t in utf8(b.column(1))], pa.float64())], ["doc_id", "score"])

    out = docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(run, f"doc_id {kind}, score double")
    return out.select("doc_id", F.coalesce(crc_mod(F.col("doc_id"), held_mod) == 1, F.lit(False)).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))


def keep_good(docs: DataFrame, scorer: Scorer | None, text_col: str = "text", least: float = 0.5) -> DataFrame:
    """docs without the rows that score under `least`; all columns stay. Each row is scored where it is read: no join."""
    if scorer is None:
        return docs
    names = docs.columns
    at = names.index(text_col)

    def run(batches):
        for b in slices(batches):
            yield b.filter(pa.array([scorer.score(t) >= least for t in utf8(b.column(at))], pa.bool_()))

    return docs.mapInArrow(run, docs.schema)


def calibration(scored: DataFrame, labels: DataFrame, bins: int = 10) -> DataFrame:
    """held_out, n, accuracy, brier (mean squared error of the score), calibration_error: labelled rows of scored(doc_id,
    held_out, score, predicted) against labels(doc_id, quality); the last is the mean gap of score and label in bins of the score."""
    y = F.col("quality").cast("double")
    rows = scored.join(labels.where("quality is not null").select("doc_id", "quality"), "doc_id")
    each = rows.groupBy("held_out", F.least(F.floor(F.col("score") * bins), F.lit(bins - 1)).alias("bin")).agg(
        F.count(F.lit(1)).alias("n"), F.sum("score").alias("s"), F.sum(y).alias("y"), F.sum((F.col("score") - y) * (F.col("score") - y)).alias("e"), F.sum((F.col("predicted") == F.col("quality")).cast("double")).alias("hits"))
    total = F.sum("n")
    return each.groupBy("held_out").agg(total.alias("n"), (F.sum("hits") / total).alias("accuracy"), (F.sum("e") / total).alias("brier"), (F.sum(F.abs(F.col("s") - F.col("y"))) / total).alias("calibration_error"))
