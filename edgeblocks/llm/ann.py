"""Nearest neighbours by score-aware anisotropic quantisation, four-bit table scans and exact reranking.

Smallest Euclidean distance is largest inner product after a vector x gets one more component -|x|^2/2 and a query the component
1. Vectors are cut into sub-spaces of two components with 16 centres each, so a code has four bits per sub-space. Centres
and codes minimise a loss in which the part of the residual parallel to the vector, which is what changes the score of its
best queries, weighs more than the part across it. A scan adds up 16-entry tables per sub-space and query; the best of
each block are scored again on the original vectors in double precision. So is every other vector whose code score, plus the length of
its residual times that of the query, can still reach the k-th best of these: no neighbour is lost, also among near copies.

Queries are taken in packs of at most PACK (a bounded broadcast); a pack is compared with all vectors in one pass over blocks, each
task keeps per query only the best k of what it has seen, and what a pack finds is written before the next begins. Equal vectors are scanned once, with the smallest k + 1 of
their ids, which loses no neighbour. The index is fitted on at most FIT_SAMPLE vectors, chosen by hash of the id; every vector is
encoded.

Defined cases: vectors that are null, zero, of another length than the most frequent one (of equally frequent ones the shortest), or that hold null
or non-finite components take no part; a query's own id is no candidate; ties go to the smaller id; rows that repeat an id and a vector count
once; fewer candidates than k are all returned; an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..storage import fresh_dir, materialise

#: Vectors that the centres are fitted on, queries in a broadcast, vectors in a block, candidates reranked per query and block before the bound decides about the rest.
FIT_SAMPLE, PACK, BLOCK, RERANK = 8192, 4096, 4096, 64
#: Components in a sub-space, centres (four bits), score threshold as a share of the norm.
WIDTH, CENTRES, THRESHOLD = 2, 16, 0.2


def parallel_weight(dim: int, threshold: float = THRESHOLD) -> float:
    """How much more an error along a vector counts than one across it, for queries that score above threshold times the norm."""
    return max(1.0, (dim - 1) * threshold**2 / (1 - threshold**2))


def _augmented(x: np.ndarray) -> np.ndarray:
    """x with the component that turns distance into inner product, padded to whole sub-spaces."""
    extra = -(x**2).sum(axis=1, keepdims=True) / 2
    pad = np.zeros((len(x), -(x.shape[1] + 1) % WIDTH))
    return np.hstack([x, extra, pad])


class Codebook:
    """Centres of each sub-space (m, 16, WIDTH) for anisotropic loss."""

    def __init__(self, centres: np.ndarray, weight: float, shift: np.ndarray):
        self.centres, self.weight, self.shift = centres, weight, shift

    @classmethod
    def fit(cls, x: np.ndarray, rounds: int = 8) -> Codebook:
        """Alternates coordinate-wise assignment and weighted least squares for the centres, from plain centres at first."""
        a = _augmented(x)
        shift = a.mean(axis=0)
        a = a - shift
        n, m = len(a), a.shape[1] // WIDTH
        order = np.random.default_rng(7).permutation(n)
        centres = np.stack([np.resize(a[order[:CENTRES], j * WIDTH : (j + 1) * WIDTH], (CENTRES, WIDTH)) for j in range(m)])
        book = cls(centres, parallel_weight(x.shape[1]), shift)
        for i in range(rounds):
            codes = book._nearest(a) if i < rounds // 2 else book._assign(a)
            book._move(a, codes, plain=i < rounds // 2)
        return book

    def _nearest(self, a: np.ndarray) -> np.ndarray:
        parts = a.reshape(len(a), -1, WIDTH)
        cross = np.einsum("nmw,mcw->nmc", parts, self.centres)
        return ((self.centres**2).sum(axis=2)[None] - 2 * cross).argmin(axis=2).astype(np.uint8)

    def _assign(self, a: np.ndarray, sweeps: int = 2) -> np.ndarray:
        """Codes by coordinate descent on |r|^2 + (weight - 1) (r . u)^2, r the residual and u the vector's direction."""
        codes = self._nearest(a)
        u = a / np.maximum(np.linalg.norm(a, axis=1, keepdims=True), 1e-12)
        parts, dirs = a.reshape(len(a), -1, WIDTH), u.reshape(len(a), -1, WIDTH)
        rows = np.arange(len(a))
        along = np.zeros(len(a))
        for j in range(parts.shape[1]):
            along += ((parts[:, j] - self.centres[j][codes[:, j]]) * dirs[:, j]).sum(axis=1)
        for _ in range(sweeps):
            for j in range(parts.shape[1]):
                res = parts[:, j, None, :] - self.centres[j][None]
                own = np.einsum("ncw,nw->nc", res, dirs[:, j])
                rest = along - own[rows, codes[:, j]]
                loss = (res**2).sum(axis=2) + (self.weight - 1) * (rest[:, None] + own) ** 2
                codes[:, j] = loss.argmin(axis=1)
                along = rest + own[rows, codes[:, j]]
        return codes

    def _move(self, a: np.ndarray, codes: np.ndarray, plain: bool) -> None:
        u = a / np.maximum(np.linalg.norm(a, axis=1, keepdims=True), 1e-12)
        parts, dirs = a.reshape(len(a), -1, WIDTH), u.reshape(len(a), -1, WIDTH)
        extra = 0.0 if plain else self.weight - 1
        along = sum(((parts[:, j] - self.centres[j][codes[:, j]]) * dirs[:, j]).sum(axis=1) for j in range(parts.shape[1]))
        for j in range(parts.shape[1]):
            own = ((parts[:, j] - self.centres[j][codes[:, j]]) * dirs[:, j]).sum(axis=1)
            rest, d = along - own, dirs[:, j]
            for c in range(CENTRES):
                has = codes[:, j] == c
                if has.any():
                    gram = has.sum() * np.eye(WIDTH) + extra * d[has].T @ d[has]
                    want = parts[has, j].sum(axis=0) + extra * (d[has] * ((parts[has, j] * d[has]).sum(axis=1) + rest[has])[:, None]).sum(axis=0)
                    self.centres[j, c] = np.linalg.solve(gram, want)
            along = rest + ((parts[:, j] - self.centres[j][codes[:, j]]) * d).sum(axis=1)

    def encode(self, x: np.ndarray) -> np.ndarray:
        """Two four-bit codes to a byte."""
        codes = self._assign(_augmented(x) - self.shift)
        codes = np.hstack([codes, np.zeros((len(codes), codes.shape[1] % 2), np.uint8)])
        return codes[:, ::2] | codes[:, 1::2] << 4

    def residuals(self, x: np.ndarray, codes: np.ndarray) -> np.ndarray:
        """Length of what the codes of each vector leave out of it."""
        a = _augmented(x) - self.shift
        m = a.shape[1] // WIDTH
        each = np.stack([codes & 15, codes >> 4], axis=2).reshape(len(codes), -1)[:, :m]
        return np.linalg.norm(a - self.centres[np.arange(m)[None], each].reshape(len(a), -1), axis=1)

    def tables(self, q: np.ndarray) -> np.ndarray:
        """Per query and byte of a code, the score of each of the 256 pairs of centres."""
        pad = np.zeros((len(q), -(q.shape[1] + 1) % WIDTH))
        parts = np.hstack([q, np.ones((len(q), 1)), pad]).reshape(len(q), -1, WIDTH)
        one = np.einsum("qmw,mcw->qmc", parts, self.centres)
        if one.shape[1] % 2:
            one = np.concatenate([one, np.zeros_like(one[:, :1])], axis=1)
        return (one[:, 1::2, :, None] + one[:, ::2, None, :]).reshape(len(q), -1, 256).astype(np.float32)


def scan(book: Codebook, queries: np.ndarray, block: np.ndarray, codes: np.ndarray, rerank: int, k: int, best: np.ndarray | None = None) -> list[np.ndarray]:
    """Per query the positions of the vectors of a block that can be among its k nearest, itself and ties included.

    best: distances beyond which nothing is wanted any more.
    """
    if len(codes) <= max(rerank, k + 1):
        return [np.arange(len(codes))] * len(queries)
    out = []
    columns = [np.ascontiguousarray(c) for c in codes.T]
    lost = book.residuals(block, codes)
    lengths = np.sqrt((queries**2).sum(axis=1) + 1)
    shifts = queries @ book.shift[: queries.shape[1]] + book.shift[queries.shape[1]]
    first = max(rerank, k + 1)
    for i, tables in enumerate(book.tables(queries)):
        score, size = tables[0][columns[0]], np.abs(tables).max(axis=1).sum()
        for table, column in zip(tables[1:], columns[1:]):
            score += table[column]
        top = np.argpartition(score, len(codes) - first)[len(codes) - first :]
        reach = np.partition(((block[top] - queries[i]) ** 2).sum(axis=1), k)[k]
        if best is not None:
            reach = min(reach, best[i] ** 2)
        square = (queries[i] ** 2).sum()
        slack = 1e-5 * size + 1e-9 * (square + reach)  # rounding of the tables, and of distances
        out.append(np.flatnonzero(score + lengths[i] * lost >= (square - reach) / 2 - shifts[i] - slack))
    return out


def usable(vectors: DataFrame, dim: int, id_col: str = "vec_id", vec_col: str = "embedding") -> DataFrame:
    v = F.transform(vec_col, lambda x: x.cast("double"))
    good = F.col(id_col).isNotNull() & (F.size(v) == dim) & F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))) & F.exists(v, lambda x: x != 0)
    return vectors.select(F.col(id_col).alias("vec_id"), v.alias("v")).where(good)


def _matrix(column: pa.Array, dim: int) -> np.ndarray:
    return column.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(-1, dim)


def _codes(rows: list[bytes]) -> np.ndarray:
    return np.frombuffer(b"".join(rows), np.uint8).reshape(len(rows), -1)


def search(vectors: DataFrame, is_query, k: int = 10, rerank: int = RERANK, fit_sample: int = FIT_SAMPLE, pack: int = PACK, id_col: str = "vec_id", vec_col: str = "embedding") -> DataFrame:
    """query_id, rank, vec_id, score (the distance) of each query's k nearest found. is_query: a condition on vec_id."""
    spark = vectors.sparkSession
    lengths = vectors.where(F.size(vec_col) > 0).groupBy(F.size(vec_col).alias("dim")).count().orderBy(F.desc("count"), "dim").first()
    schema = "query_id bigint, rank int, vec_id bigint, score double"
    if lengths is None:
        return spark.createDataFrame([], schema)
    dim = lengths["dim"]
    rows = usable(vectors, dim, id_col, vec_col).distinct()
    # equal vectors once, with their k + 1 smallest ids: the rank limit is applied before the shuffle already
    firsts = rows.withColumn("r", F.row_number().over(Window.partitionBy(F.xxhash64("v"), "v").orderBy("vec_id"))).where(F.col("r") <= k + 1)
    unique = materialise(firsts.groupBy("v").agg(F.sort_array(F.collect_list("vec_id")).alias("ids")), "ann-vectors")
    queries = materialise(rows.where(is_query), "ann-queries")
    sample = unique.orderBy(F.xxhash64(F.element_at("ids", 1)), F.element_at("ids", 1)).limit(fit_sample).select("v").toArrow()
    if sample.num_rows == 0:
        return spark.createDataFrame([], schema)
    book = spark.sparkContext.broadcast(Codebook.fit(_matrix(sample.column("v").combine_chunks(), dim)))
    parts = 4 * spark.sparkContext.defaultParallelism
    indexed = materialise(unique.repartition(parts).mapInArrow(_encoder(book, dim), "ids array<bigint>, v array<double>, code binary"), "ann-index")
    total = queries.count()
    slot = F.pmod(F.xxhash64("vec_id"), F.lit(max(1, -(-total // max(1, pack // 2)))))  # packs of half the size on average
    folder, found_ddl = fresh_dir(spark, "ann-found"), "query_id bigint, vec_id bigint, score double"
    spark.createDataFrame([], found_ddl).write.parquet(folder)
    for p in range(max(1, -(-total // max(1, pack // 2)))):
        part = queries.where(slot == p).select("vec_id", "v").toArrow()
        if part.num_rows:
            sent = spark.sparkContext.broadcast((part.column("vec_id").to_numpy(), _matrix(part.column("v").combine_chunks(), dim)))
            indexed.mapInArrow(_scanner(book, sent, dim, k, rerank), found_ddl).write.mode("append").parquet(folder)
    every = spark.read.schema(found_ddl).parquet(folder)
    best = Window.partitionBy("query_id").orderBy("score", "vec_id")
    return every.withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= k).select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")


def _encoder(book, dim: int):
    def batches(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in it:
            codes = book.value.encode(_matrix(b.column("v"), dim)) if b.num_rows else []
            yield pa.RecordBatch.from_arrays([b.column("ids"), b.column("v"), pa.array([c.tobytes() for c in codes], pa.binary())], names=["ids", "v", "code"])

    return batches


def _scanner(book, sent, dim: int, k: int, rerank: int):
    def batches(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, q = sent.value
        best = [[] for _ in ids]

        def take(block: np.ndarray, codes: np.ndarray, owners: list[list[int]]) -> None:
            far = np.array([x[-1][0] if len(x) >= k else np.inf for x in best])
            for i, near in enumerate(scan(book.value, q, block, codes, rerank, k, far)):
                d = np.sqrt(((block[near] - q[i]) ** 2).sum(axis=1))
                keep = np.argsort(d, kind="stable")
                if len(keep) > k + 1:  # ties at the edge stay
                    keep = keep[d[keep] <= d[keep[k]]]
                if len(best[i]) >= k:
                    keep = keep[d[keep] <= best[i][-1][0]]
                if len(keep):
                    more = [(float(d[j]), v) for j in keep for v in owners[near[j]] if v != ids[i]]
                    best[i] = sorted(best[i] + more)[:k]

        held, coded, owners, n = [], [], [], 0
        for b in it:
            for lo in range(0, b.num_rows, BLOCK):
                part = b.slice(lo, BLOCK)
                held.append(_matrix(part.column("v"), dim))
                coded.extend(part.column("code").to_pylist())
                owners.extend(part.column("ids").to_pylist())
                n += part.num_rows
                if n >= BLOCK:
                    take(np.concatenate(held), _codes(coded), owners)
                    held, coded, owners, n = [], [], [], 0
        if n:
            take(np.concatenate(held), _codes(coded), owners)
        rows = [(ids[i], v, s) for i, found in enumerate(best) for s, v in found]
        yield pa.RecordBatch.from_arrays([pa.array([r[j] for r in rows], t) for j, t in enumerate((pa.int64(), pa.int64(), pa.float64()))], names=["query_id", "vec_id", "score"])

    return batches


def op2_nearest(spark, sf_dir: str) -> DataFrame:
    return search(spark.read.parquet(f"{sf_dir}/embeddings.parquet"), F.col("vec_id") % 100 == 0)


#: All pairs; a distance adds its squares in eight lanes, as numpy does for vectors of 64 components.
SQL = """
WITH d AS (SELECT len(embedding) AS dim FROM embeddings WHERE len(embedding) > 0 GROUP BY 1 ORDER BY count(*) DESC, 1 LIMIT 1),
v AS (SELECT DISTINCT vec_id, embedding::DOUBLE[] AS x FROM embeddings, d WHERE vec_id IS NOT NULL AND len(embedding) = dim
      AND len(list_filter(embedding, lambda c: c IS NULL OR NOT isfinite(c))) = 0 AND len(list_filter(embedding, lambda c: c <> 0)) > 0),
p AS (SELECT q.vec_id AS query_id, v.vec_id, list_transform(list_zip(q.x, v.x), lambda c: (c[2] - c[1]) * (c[2] - c[1])) AS s FROM v q JOIN v ON v.vec_id <> q.vec_id WHERE q.vec_id % 100 = 0),
l AS (SELECT query_id, vec_id, list_transform(range(1, 9), lambda j: list_reduce(list_transform(range(0, len(s) // 8), lambda i: s[8 * i + j]), lambda a, b: a + b)) AS r FROM p),
n AS (SELECT query_id, vec_id, sqrt(((r[1] + r[2]) + (r[3] + r[4])) + ((r[5] + r[6]) + (r[7] + r[8]))) AS score FROM l)
SELECT query_id, rank::INT AS rank, vec_id, score FROM (SELECT *, row_number() OVER (PARTITION BY query_id ORDER BY score, vec_id) AS rank FROM n) WHERE rank <= 10
"""
