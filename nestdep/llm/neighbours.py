"""Nearest neighbours by anisotropic four-bit quantisation and exact reranking.

Vectors are cut into subspaces of two dimensions, each with sixteen centroids.
Codes and centroids minimise a score-aware loss: the part of the residual along
the vector costs more than the part across it, as it is what changes an inner
product with a near query.  A scan adds table entries, two packed codes a
byte, to get inner products; with the exact norm these give squared distances.
The best `rerank` rows of each slice are measured again on the original vectors
in double precision, and only the `k` best of a task leave it.

The codebook is fitted on at most `sample` rows, those with the smallest hash
of their id; every row is coded, once: packed codes and norms are written to the
shared folder beside the vectors.  Queries are broadcast in blocks of at most
`QUERY_BLOCK`, so what a task holds does not grow with the data; each block
scans the stored codes and reads vectors for the exact ranking.

Defined cases: vectors that are null, empty, zero, of another length than the
table's commonest, or that hold null or non-finite components take no part, as
query or candidate; a null id takes no part; a row is never its own neighbour
(nor another row with its id); ties go to the smaller id; fewer than k
candidates are all returned; an empty table gives an empty result; other
columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ._spark import bounded_batches, written

SAMPLE = 8_000
QUERY_BLOCK = 16_384
SLICE_ROWS = 8_192
RERANK = 200
_SUB, _CODES = 2, 16


class Quantiser:
    """Anisotropic product quantiser; dimensions are padded to a multiple of four."""

    def __init__(self, sample: np.ndarray, threshold: float = 0.2, rounds: int = 6, seed: int = 5) -> None:
        self.dims = sample.shape[1]
        x = self.pad(sample)
        n, d = x.shape
        self.parts = d // _SUB
        t2 = threshold * threshold
        self.along = max(1.0, (d - 1) * t2 / (1 - t2))  # weight of the parallel part; the rest weighs one
        rng = np.random.default_rng(seed)
        pick = rng.permutation(n)[np.arange(_CODES) % n]
        self.books = np.stack([x[pick, s * _SUB : (s + 1) * _SUB] for s in range(self.parts)]).astype(np.float64)
        self.books += rng.normal(scale=1e-6, size=self.books.shape)
        for _ in range(rounds):
            codes = self.encode(x)
            self._refit(x, codes)

    def pad(self, x: np.ndarray) -> np.ndarray:
        short = -x.shape[1] % (2 * _SUB)
        return np.pad(x, ((0, 0), (0, short))) if short else x

    def encode(self, x: np.ndarray, sweeps: int = 2) -> np.ndarray:
        """Codes by coordinate descent: each subspace in turn, others held."""
        x = x.astype(np.float64)
        n = len(x)
        norm2 = np.maximum((x * x).sum(axis=1), 1e-30)
        parts = x.reshape(n, self.parts, _SUB)
        across, along = [], []
        codes = np.empty((n, self.parts), dtype=np.uint8)
        gap = np.zeros(n)  # inner product of x with its residual
        for s in range(self.parts):
            own, book = parts[:, s], self.books[s]
            miss = ((own[:, None, :] - book[None]) ** 2).sum(axis=2)
            line = (own * own).sum(axis=1)[:, None] - own @ book.T
            codes[:, s] = miss.argmin(axis=1)
            across.append(miss)
            along.append(line)
            gap += line[np.arange(n), codes[:, s]]
        extra = (self.along - 1) / norm2
        rows = np.arange(n)
        for _ in range(sweeps):
            for s in range(self.parts):
                rest = gap - along[s][rows, codes[:, s]]
                loss = across[s] + extra[:, None] * (rest[:, None] + along[s]) ** 2
                codes[:, s] = loss.argmin(axis=1)
                gap = rest + along[s][rows, codes[:, s]]
        return codes

    def _refit(self, x: np.ndarray, codes: np.ndarray) -> None:
        """Centroids that minimise the loss for given codes: one linear system."""
        n, size = len(x), self.parts * _CODES * _SUB
        unit = x / np.maximum(np.linalg.norm(x, axis=1, keepdims=True), 1e-15)
        at = (np.arange(self.parts) * _CODES + codes)[:, :, None] * _SUB + np.arange(_SUB)
        at = at.reshape(n, -1)
        weight = np.bincount(at.ravel(), minlength=size).astype(float)
        target = np.bincount(at.ravel(), weights=(self.along * x).ravel(), minlength=size)
        system = np.diag(weight + 1e-6)
        for lo in range(0, n, 2048):
            rows = np.zeros((min(2048, n - lo), size))
            np.put_along_axis(rows, at[lo : lo + 2048], unit[lo : lo + 2048], axis=1)
            system += (self.along - 1) * rows.T @ rows
        solved = np.linalg.solve(system, target)
        used = weight > 0
        flat = self.books.reshape(-1)
        flat[used] = solved[used]

    def pack(self, codes: np.ndarray) -> np.ndarray:
        return codes[:, 0::2] | codes[:, 1::2] << 4

    def tables(self, queries: np.ndarray) -> np.ndarray:
        """(queries, bytes, 256): inner products of each packed pair of centroids."""
        q = self.pad(queries).reshape(len(queries), self.parts, _SUB)
        single = np.einsum("qsd,scd->qsc", q, self.books).astype(np.float32)
        low, high = single[:, 0::2], single[:, 1::2]
        return (high[:, :, :, None] + low[:, :, None, :]).reshape(len(queries), self.parts // 2, 256)


def scan(tables: np.ndarray, packed: np.ndarray, half_norms: np.ndarray) -> np.ndarray:
    """Half squared distances up to a term of the query alone: |x|^2 / 2 - <q, x>."""
    out = np.broadcast_to(half_norms, (len(tables), len(packed))).copy()
    for j in range(packed.shape[1]):
        out -= np.take(tables[:, j], packed[:, j], axis=1)
    return out


def best_rows(scores: np.ndarray, n: int) -> np.ndarray:
    """Indices of the n smallest scores; ties to the lower index."""
    if len(scores) <= n:
        return np.arange(len(scores))
    limit = np.partition(scores, n - 1)[n - 1]
    below = np.flatnonzero(scores < limit)
    return np.concatenate([below, np.flatnonzero(scores == limit)[: n - len(below)]])


def usable(vector: Column) -> Column:
    """Not null, all components finite numbers, not all zero."""
    good = F.forall(vector, lambda v: v.isNotNull() & ~F.isnan(v) & (F.abs(v) < F.lit(float("inf"))))
    return vector.isNotNull() & good & F.exists(vector, lambda v: v != 0)


def _matrix(column: pa.Array, dims: int) -> np.ndarray:
    return column.flatten().to_numpy(zero_copy_only=False).reshape(-1, dims).astype(np.float64)


def _floats(vectors: DataFrame, column: str) -> Column:
    """The vectors as they are if of floats or doubles, else as doubles; distances are always of doubles."""
    return F.col(column) if dict(vectors.dtypes)[column] in ("array<float>", "array<double>") else F.col(column).cast("array<double>")


def nearest(vectors: DataFrame, is_query: Column, k: int = 10, id_col: str = "vec_id", vector_col: str = "embedding", sample: int = SAMPLE, rerank: int = RERANK) -> DataFrame:
    """query_id, rank, vec_id, score (Euclidean distance) of the k nearest found for each query."""
    bounded_batches(vectors.sparkSession)
    spark = vectors.sparkSession
    base = vectors.select(F.col(id_col).cast("long").alias("id"), _floats(vectors, vector_col).alias("vector"), is_query.alias("asks"))
    base = base.where(F.col("id").isNotNull() & usable(F.col("vector")))
    shape = base.groupBy(F.size("vector").alias("dims")).agg(F.count(F.lit(1)).alias("n"), F.count_if("asks").alias("q")).orderBy(F.desc("n"), "dims").first()
    schema = "query_id long, id long, score double"
    if shape is None:
        return spark.createDataFrame([], "query_id long, rank int, vec_id long, score double")
    dims, n_queries = shape["dims"], shape["q"]
    base = base.where(F.size("vector") == dims)
    picked = base.orderBy(F.xxhash64("id"), "id").limit(sample).select("vector").toArrow()
    model = Quantiser(_matrix(picked.column("vector").combine_chunks(), dims))
    blocks = max(1, -(-n_queries // QUERY_BLOCK))

    def code(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for lo in range(0, batch.num_rows, SLICE_ROWS):
                part = batch.slice(lo, SLICE_ROWS)
                x = _matrix(part.column("vector"), dims)
                packed = model.pack(model.encode(model.pad(x)))
                width = packed.shape[1]
                codes = pa.Array.from_buffers(pa.binary(width), len(x), [None, pa.py_buffer(np.ascontiguousarray(packed).tobytes())]).cast(pa.binary())
                half = pa.array(((x * x).sum(axis=1) / 2).astype(np.float32))
                yield pa.RecordBatch.from_arrays([part.column("id"), part.column("asks"), part.column("vector"), codes, half], names=["id", "asks", "vector", "codes", "half_norm"])

    kind = dict(base.dtypes)["vector"]
    base = written(base.select("id", "asks", "vector").mapInArrow(code, f"id long, asks boolean, vector {kind}, codes binary, half_norm float"), "codes")

    def scanner(queries) -> DataFrame:
        shared = spark.sparkContext.broadcast(queries)

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            q_ids, q = shared.value
            best_id = np.full((len(q_ids), k), -1, dtype=np.int64)
            best = np.full((len(q_ids), k), np.inf)
            for batch in batches:
                for lo in range(0, batch.num_rows, SLICE_ROWS):
                    part = batch.slice(lo, SLICE_ROWS)
                    ids = part.column("id").to_numpy()
                    order = np.argsort(ids, kind="stable")
                    ids, x = ids[order], _matrix(part.column("vector"), dims)[order]
                    packed = np.frombuffer(b"".join(part.column("codes").to_pylist()), np.uint8).reshape(len(ids), -1)[order]
                    norms = part.column("half_norm").to_numpy()[order]
                    for q0 in range(0, len(q_ids), 64):
                        scores = scan(model.tables(q[q0 : q0 + 64]), packed, norms)
                        for i, row in enumerate(scores, q0):
                            at = best_rows(row, rerank + 1)
                            at = at[ids[at] != q_ids[i]]
                            exact = np.sqrt(((x[at] - q[i]) ** 2).sum(axis=1))
                            all_ids, every = np.concatenate([best_id[i], ids[at]]), np.concatenate([best[i], exact])
                            top = np.lexsort((all_ids, every))[:k]
                            best_id[i], best[i] = all_ids[top], every[top]
            found = best < np.inf
            row = np.nonzero(found)[0]
            yield pa.RecordBatch.from_arrays([pa.array(q_ids[row]), pa.array(best_id[found]), pa.array(best[found])], names=["query_id", "id", "score"])

        return base.select("id", "vector", "codes", "half_norm").mapInArrow(run, schema)

    passes = []
    for b in range(blocks):
        asked = base.where("asks").where(F.pmod(F.xxhash64("id"), F.lit(blocks)) == b).select("id", "vector").dropDuplicates(["id"]).toArrow()
        if asked.num_rows:
            passes.append(scanner((asked.column("id").to_numpy(), _matrix(asked.column("vector").combine_chunks(), dims))))
    if not passes:
        return spark.createDataFrame([], "query_id long, rank int, vec_id long, score double")
    rank = F.row_number().over(Window.partitionBy("query_id").orderBy("score", "id"))
    out = reduce(DataFrame.unionAll, passes).withColumn("rank", rank).where(F.col("rank") <= k)
    return out.select("query_id", F.col("rank").cast("int").alias("rank"), F.col("id").alias("vec_id"), "score")
