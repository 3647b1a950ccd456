"""Nearest neighbours by score-aware (anisotropic) product quantisation, four-bit table scans and exact reranking.

Codebooks of 16 centres for each pair of dimensions are fitted on a bounded sample under a loss that weighs the part of
the residual parallel to the vector ETA times the rest, since that part changes large inner products. Every vector is
coded by coordinate descent under the same loss. A search scans all codes through per-query tables, query block by query
block, and reranks the best RERANK (and 4 k at least) of each chunk of rows exactly, in double precision, on the original
vectors. A row's cosine is off its scanned score by no more than the length of its residual, so an exact check follows:
every row of the chunk that could still reach the k-th best found so far is reranked, too, and nothing near is missed on
any distribution of vectors; where codes tell rows badly apart, more rows are reranked. A task keeps the best of all its chunks while these fit MERGE_BYTES, and sends k rows a query then.

Defined cases: vectors that are null, empty, zero or hold null or non-finite components take no part; vectors of different
dimensions have no cosine, so each dimension has its own codebooks and its queries meet vectors of that dimension only; a
query is never its own neighbour; rows that share an id are one neighbour, at the nearest of them, and one query, whose
neighbours are those of all its rows; ties go to the smaller id; with fewer than k candidates all are returned; an empty
table gives an empty result; other columns are ignored; rows with a null id take no part.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import file_system, materialise, scratch

#: Rows the codebooks are fitted on, at most.
SAMPLE = 8192
#: Weight of the parallel residual against the orthogonal one: (d - 1) t^2 / (1 - t^2) at t = 0.2, d = 64.
ETA = 2.6
#: Rows of one scan, exactly reranked rows of each scan and query, and queries of one block.
CHUNK, RERANK, BLOCK = 16384, 48, 512
#: Bytes of a task's best rows of all queries up to which they are merged over its chunks before they are sent.
MERGE_BYTES = 64 << 20


#: More than float32 sums of the scan are off by, and than double sums of the same products in another order are.
SCAN_SLACK, SUM_SLACK = 1e-4, 1e-9


def unit(v: np.ndarray) -> np.ndarray:
    v = scaled(v.astype(np.float64))
    return (v / np.linalg.norm(v, axis=1, keepdims=True)).astype(np.float32)


def scaled(v: np.ndarray) -> np.ndarray:
    """Rows times powers of two that bring their largest components near one: cosines stay, squares don't over- or underflow."""
    return np.ldexp(v, -np.frexp(np.abs(v).max(axis=1, keepdims=True))[1])


def _pairs(x: np.ndarray) -> np.ndarray:
    """(n, d) to (n, subspaces, 2), padded with a zero if d is odd."""
    if x.shape[1] % 2:
        x = np.pad(x, ((0, 0), (0, 1)))
    return x.reshape(len(x), -1, 2)


def encode(x: np.ndarray, books: np.ndarray, eta: float = ETA, rounds: int = 2) -> np.ndarray:
    """Codes (n, subspaces) of unit vectors: nearest centres first, then descent over one subspace at a time."""
    p = _pairs(x)
    d2 = ((p[:, :, None, :] - books[None]) ** 2).sum(-1)
    codes = d2.argmin(2)
    # along[i, s, c]: parallel part of the residual in subspace s if centre c is taken
    along = (p[:, :, None, :] * (p[:, :, None, :] - books[None])).sum(-1)
    rows = np.arange(len(p))
    total = np.take_along_axis(along, codes[:, :, None], 2)[:, :, 0].sum(1)
    for _ in range(rounds):
        for s in range(p.shape[1]):
            rest = total - along[rows, s, codes[:, s]]
            codes[:, s] = (d2[:, s] + (eta - 1) * (rest[:, None] + along[:, s]) ** 2).argmin(1)
            total = rest + along[rows, s, codes[:, s]]
    return codes.astype(np.uint8)


def fit(x: np.ndarray, eta: float = ETA, rounds: int = 8, seed: int = 7) -> np.ndarray:
    """Codebooks (subspaces, 16, 2) of unit vectors: codes and centres in turn, each the best under the loss."""
    p, rng = _pairs(x), np.random.default_rng(seed)
    books = np.stack([p[rng.choice(len(p), 16, replace=len(p) < 16), s] for s in range(p.shape[1])]).astype(np.float32)
    for _ in range(rounds):
        codes = encode(x, books, eta, 1)
        taken = books[np.arange(p.shape[1])[None], codes]
        off = (p * (p - taken)).sum(-1)
        total = off.sum(1)
        for s in range(p.shape[1]):
            rest = total - off[:, s]
            v = p[:, s]
            outer = v[:, :, None] * v[:, None, :]
            a = np.eye(2)[None] + (eta - 1) * outer
            b = v + (eta - 1) * (rest + (v * v).sum(1))[:, None] * v
            for c in range(16):
                m = codes[:, s] == c
                if m.sum() >= 2:
                    books[s, c] = np.linalg.solve(a[m].sum(0) + 1e-6 * np.eye(2), b[m].sum(0))
            off[:, s] = (v * (v - books[s, codes[:, s]])).sum(-1)
            total = rest + off[:, s]
    return books


def scan(tables: np.ndarray, codes: np.ndarray) -> np.ndarray:
    """Approximate scores (queries, rows): for each subspace the table entry that the row's four bits name."""
    out = np.zeros((len(tables), len(codes)), np.float32)
    for s in range(codes.shape[1]):
        out += tables[:, s, :].take(codes[:, s], axis=1)
    return out


def residuals(x: np.ndarray, codes: np.ndarray, books: np.ndarray) -> np.ndarray:
    """Lengths of what the codes leave of unit vectors."""
    p = _pairs(x)
    return np.sqrt(((p - books[np.arange(p.shape[1])[None], codes]) ** 2).sum((1, 2)))


def valid(embedding):
    ok = F.forall(embedding, lambda v: v.isNotNull() & ~F.isnan(v) & (F.abs(v) < F.lit(float("inf"))))
    return embedding.isNotNull() & F.coalesce(ok, F.lit(False)) & F.exists(embedding, lambda v: v != 0)


def build_index(vectors: DataFrame, id_col: str = "vec_id", vec_col: str = "embedding", sample: int = SAMPLE, eta: float = ETA) -> tuple[DataFrame, dict[int, np.ndarray]]:
    """Table (vec_id, vec array<double or float>, dim, code binary: two subspaces a byte) of all vectors that take part, and
    the codebooks by dimension. The sample is the rows of each dimension whose ids have the least hashes, `sample` in all."""
    rows = vectors.where(valid(F.col(vec_col)) & F.col(id_col).isNotNull()).select(F.col(id_col).alias("vec_id"), F.col(vec_col).alias("vec")).withColumn("dim", F.size("vec"))
    dims = [r.dim for r in rows.select("dim").distinct().limit(sample // 16 + 1).collect()]
    if len(dims) > sample // 16:
        raise ValueError(f"over {sample // 16} dimensions of vectors")
    by_hash = Window.partitionBy("dim").orderBy(F.xxhash64("vec_id"), "vec_id", "vec")
    drawn = rows.withColumn("r", F.row_number().over(by_hash)).where(F.col("r") <= sample // max(1, len(dims))).orderBy("dim", "r").select("dim", "vec").toArrow()
    of, vecs = drawn.column(0).to_numpy(), drawn.column(1)
    books = {int(d): fit(unit(np.array(vecs.filter(pa.array(of == d)).to_pylist())), eta) for d in sorted(dims)}

    def run(batches):
        for b in batches:
            for part, d in by_dim(b, 2):
                codes = encode(unit(dense(part.column(1), d)), books[d], eta)
                if codes.shape[1] % 2:
                    codes = np.pad(codes, ((0, 0), (0, 1)))
                packed = codes[:, ::2] << 4 | codes[:, 1::2]
                yield part.append_column("code", pa.array([c.tobytes() for c in packed], pa.binary()))

    kind = dict(rows.dtypes)
    return materialise(rows.mapInArrow(run, f"vec_id {kind['vec_id']}, vec {kind['vec']}, dim int, code binary"), "index"), books


def by_dim(b: pa.RecordBatch, column: int):
    """(rows, dimension) of each dimension in a batch."""
    of = b.column(column).to_numpy()
    found = np.unique(of).tolist()
    return [(b if len(found) == 1 else b.filter(pa.array(of == d)), d) for d in found]


def dense(vecs: pa.Array, dim: int) -> np.ndarray:
    return vecs.flatten().to_numpy(zero_copy_only=False).reshape(-1, dim)


class Best:
    """The k nearest found so far of a list of queries: ids and scores, -inf where there are fewer."""

    def __init__(self, queries: int, k: int):
        self.ids, self.scores, self.k = np.full((queries, k), -1, np.int64), np.full((queries, k), -np.inf), k

    def add(self, i: int, ids: np.ndarray, scores: np.ndarray) -> None:
        ids, scores = np.concatenate((self.ids[i], ids)), np.concatenate((self.scores[i], scores))
        order = np.lexsort((ids, -scores))
        # an id counts once, at its best
        ids, scores = ids[order], scores[order]
        ids, scores = ids[np.isfinite(scores)], scores[np.isfinite(scores)]
        keep = np.sort(np.unique(ids, return_index=True)[1])[: self.k]
        self.ids[i], self.scores[i] = -1, -np.inf
        self.ids[i, : len(keep)], self.scores[i, : len(keep)] = ids[keep], scores[keep]


def search(index: DataFrame, books: dict[int, np.ndarray], queries: DataFrame, k: int = 5) -> DataFrame:
    """query_id, rank, vec_id, score: the k nearest of each row of queries(query_id, vec), a subset of the index's schema.

    Each task holds one chunk of rows of a dimension at a time and streams the query blocks past it from the shared folder.
    """
    spark = index.sparkSession
    if not books:
        return spark.createDataFrame([], "query_id long, rank int, vec_id long, score double")
    at = scratch(spark, "queries")
    asked = queries.select(F.col("query_id").cast("long").alias("query_id"), F.col("vec").cast("array<double>").alias("vec"), F.size("vec").alias("dim"))
    asked.write.parquet(at)
    counts = {r["dim"]: r["count"] for r in spark.read.parquet(at).groupBy("dim").count().collect()}
    merge = sum(counts.values()) * k * 16 <= MERGE_BYTES

    def blocks(d):
        """(number of the first query, ids, vectors) of each block of queries of a dimension, always in one order."""
        import pyarrow.dataset as ds

        fs, path = file_system(at)
        n = 0
        for b in ds.dataset(path, filesystem=fs, format="parquet").to_batches(batch_size=BLOCK, filter=ds.field("dim") == d):
            if b.num_rows:
                yield n, b.column(0).to_numpy(), scaled(dense(b.column(1), d))
                n += b.num_rows

    # rows are scaled alike wherever they are read, so equal vectors have equal sums
    def scanned(d, parts, best, qids):
        ids, vecs, codes = (np.concatenate(p) for p in zip(*parts, strict=True))
        order = np.argsort(ids, kind="stable")
        ids, vecs, codes = ids[order], vecs[order], codes[order]
        norms = np.sqrt((vecs * vecs).sum(1))
        units = vecs / norms[:, None]
        reach = (residuals(units.astype(np.float32), codes, books[d]) + SCAN_SLACK).astype(np.float32)
        take, different = min(len(ids), max(RERANK, 4 * k)), len(np.unique(ids))
        for n, qid, q in blocks(d):
            qids[n : n + len(qid)] = qid
            approx = scan(np.einsum("qsd,scd->qsc", _pairs(unit(q)), books[d]), codes)
            # ties of the scan go to smaller ids: rows are in order of id, and so is the rank within equal scores
            floor = np.partition(approx, len(ids) - take, axis=1)[:, len(ids) - take]
            qn = np.sqrt((q * q).sum(1))
            for i in range(len(qid)):
                over, tied = np.flatnonzero(approx[i] > floor[i]), np.flatnonzero(approx[i] == floor[i])
                pick = np.concatenate((over, tied[: take - len(over) + 1]))
                pick = pick[ids[pick] != qid[i]]
                if take < len(ids) and len(np.unique(ids[pick])) < min(k, different - 1):
                    pick = np.flatnonzero(ids != qid[i])  # repeated ids crowd out others: rerank them all
                best.add(n + i, ids[pick], (vecs[pick] * q[i]).sum(1) / (norms[pick] * qn[i]))
                # what the scan can't rule out; a dot product first, so few are summed in the order that tells ties
                least = best.scores[n + i, -1] - SUM_SLACK
                open_ = np.flatnonzero(approx[i] + reach >= least)
                rest = open_[units[open_] @ (q[i] / qn[i]) >= least]
                rest = np.setdiff1d(rest[ids[rest] != qid[i]], pick)
                if len(rest):
                    best.add(n + i, ids[rest], (vecs[rest] * q[i]).sum(1) / (norms[rest] * qn[i]))

    def run(batches):
        held, kept = {}, {}

        def rows_of(best, qids):
            there = np.isfinite(best.scores)
            return pa.RecordBatch.from_arrays([pa.array(np.repeat(qids, there.sum(1))), pa.array(best.ids[there]), pa.array(best.scores[there])], ["query_id", "vec_id", "score"])

        def flush(d):
            best, qids = kept.get(d) or (Best(counts[d], k), np.zeros(counts[d], np.int64))
            scanned(d, held.pop(d), best, qids)
            if merge:
                kept[d] = best, qids
                return []
            return [rows_of(best, qids)]

        for b in batches:
            for j in range(0, b.num_rows, CHUNK):
                for s, d in by_dim(b.slice(j, CHUNK), 2):
                    if d not in counts:
                        continue
                    packed = np.frombuffer(b"".join(s.column(3).to_pylist()), np.uint8).reshape(s.num_rows, -1)
                    codes = np.stack((packed >> 4, packed & 15), axis=2).reshape(s.num_rows, -1)[:, : books[d].shape[0]]
                    held.setdefault(d, []).append((s.column(0).to_numpy(zero_copy_only=False).astype(np.int64), scaled(dense(s.column(1), d).astype(np.float64)), codes))
                    if sum(len(p[0]) for p in held[d]) >= CHUNK:
                        yield from flush(d)
                if sum(len(p[0]) for ps in held.values() for p in ps) >= 4 * CHUNK:
                    for d in list(held):
                        yield from flush(d)
        for d in list(held):
            yield from flush(d)
        for best, qids in kept.values():
            yield rows_of(best, qids)

    hits = index.mapInArrow(run, "query_id long, vec_id long, score double")
    # equal scores come from equal sums, so a tie is a tie in every task; an id counts once, at its best
    hits = hits.groupBy("query_id", "vec_id").agg(F.max("score").alias("score"))
    w = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return hits.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def nearest(vectors: DataFrame, is_query, id_col: str = "vec_id", vec_col: str = "embedding", k: int = 5) -> DataFrame:
    """The k nearest of each row whose id satisfies is_query(id column), against all rows."""
    index, books = build_index(vectors, id_col, vec_col)
    return search(index, books, index.where(is_query(F.col("vec_id"))).select(F.col("vec_id").alias("query_id"), "vec"), k)
