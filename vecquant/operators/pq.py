"""Product quantization: centroids per group of dimensions, codes, scans by tables."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vecquant.operators.prep import bounded_sample, column, lists, matrix
from vecquant.operators.search import TOPK, Best, collect_queries, rank_rows

#: Distances of rows to centroids that are held at once.
_BLOCK = 131_072


def lloyd(x: np.ndarray, k: int, iters: int, seed: int) -> np.ndarray:
    """k centroids of the rows; empty ones keep their place. Fewer rows than k: rows repeat."""
    rng = np.random.Generator(np.random.Philox(seed))
    centers = x[rng.permutation(len(x))[np.arange(k) % len(x)]].copy()
    for _ in range(iters):
        near = nearest(x, centers)
        counts = np.bincount(near, minlength=k)
        sums = np.stack([np.bincount(near, weights=x[:, j], minlength=k) for j in range(x.shape[1])], axis=1)
        used = counts > 0
        centers[used] = sums[used] / counts[used][:, None]
    return centers


def nearest(x: np.ndarray, centers: np.ndarray) -> np.ndarray:
    """Place of the nearest centroid of each row, the first of equal ones."""
    out = np.empty(len(x), dtype=np.int64)
    size, across = (centers**2).sum(axis=1), np.ascontiguousarray(centers.T)
    # Distances of one block stay in the cache, in memory that is used again.
    step = max(1, _BLOCK // max(1, len(centers)))
    room = np.empty((step, len(centers)))
    for a in range(0, len(x), step):
        part = 2 * x[a : a + step]
        far = np.matmul(part, across, out=room[: len(part)])
        np.subtract(size, far, out=far).argmin(axis=1, out=out[a : a + step])
    return out


def train(df: DataFrame, group_dims: int = 4, centroids: int = 256, iters: int = 12, sample_rows: int = 50_000, seed: int = 0) -> np.ndarray:
    """Codebook [groups, centroids, group_dims] from a bounded sample, the groups trained apart.

    About sample_rows rows are learned from where there are more, by a hash of the id. The
    codebook has d * centroids numbers.
    """
    sample = bounded_sample(df.select("vec_id", "embedding"), sample_rows, seed)
    # Values move as they are given: floats at half the bytes of doubles.
    single = df.schema["embedding"].dataType.elementType.simpleString() == "float"
    kind = pa.float32() if single else pa.float64()

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                x = matrix(column(batch, "embedding"))
                parts = np.ascontiguousarray(x.reshape(len(x), -1, group_dims).transpose(1, 0, 2))
                ids = np.broadcast_to(column(batch, "vec_id").to_numpy(zero_copy_only=False).astype(np.int64), parts.shape[:2])
                groups = pa.array(range(len(parts)), pa.int32())
                yield pa.RecordBatch.from_arrays([groups, lists(ids, pa.int64()), lists(parts.reshape(len(parts), -1), kind)], names=["part", "ids", "v"])

    def run(table: pa.Table) -> pa.Table:
        part = table["part"][0].as_py()
        ids = table["ids"].combine_chunks().flatten().to_numpy()
        x = table["v"].combine_chunks().flatten().to_numpy().astype(np.float64).reshape(len(ids), -1)[np.argsort(ids, kind="stable")]
        centers = lloyd(x, centroids, iters, seed + part)
        return pa.table({"part": pa.array([part], pa.int32()), "centers": lists(centers.reshape(1, -1), pa.float64())})

    cuts = sample.mapInArrow(cut, f"part int, ids array<long>, v array<{'float' if single else 'double'}>")
    rows = cuts.groupBy("part").applyInArrow(run, "part int, centers array<double>").orderBy("part").collect()
    return np.array([r.centers for r in rows]).reshape(len(rows), centroids, group_dims)


def encode(df: DataFrame, codebook: np.ndarray) -> DataFrame:
    """vec_id, pq: a byte a group."""
    shipped = df.sparkSession.sparkContext.broadcast(codebook)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        book = shipped.value
        for batch in batches:
            if not batch.num_rows:
                continue
            x = matrix(column(batch, "v")).reshape(batch.num_rows, len(book), -1)
            codes = np.stack([nearest(x[:, g], book[g]) for g in range(len(book))], axis=1).astype(np.uint8)
            yield pa.RecordBatch.from_arrays([column(batch, "vec_id"), pa.array([r.tobytes() for r in codes], pa.binary())], names=["vec_id", "pq"])

    return df.select(F.col("vec_id").cast("long").alias("vec_id"), F.col("embedding").alias("v")).mapInArrow(run, "vec_id long, pq binary")


def codes_matrix(array: pa.Array) -> np.ndarray:
    blobs = array.to_pylist()
    return np.frombuffer(b"".join(blobs), dtype=np.uint8).reshape(len(blobs), -1)


def decode_codes(codes: np.ndarray, codebook: np.ndarray) -> np.ndarray:
    return codebook[np.arange(len(codebook))[None, :], codes].reshape(len(codes), -1)


def decode(codes: DataFrame, codebook: np.ndarray) -> DataFrame:
    """vec_id, embedding from the centroids."""
    shipped = codes.sparkSession.sparkContext.broadcast(codebook)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                x = decode_codes(codes_matrix(column(batch, "pq")), shipped.value)
                yield pa.RecordBatch.from_arrays([column(batch, "vec_id"), lists(x, pa.float64())], names=["vec_id", "embedding"])

    return codes.select("vec_id", "pq").mapInArrow(run, "vec_id long, embedding array<double>")


def scan_topk(codes: DataFrame, codebook: np.ndarray, queries: DataFrame, k: int) -> DataFrame:
    """First pass: the k best dot products by a table of (group, centroid) a query."""
    names, q = collect_queries(queries)
    tables = np.einsum("qgd,gcd->qgc", q.reshape(len(q), len(codebook), -1), codebook)
    shipped = codes.sparkSession.sparkContext.broadcast(tables)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        best = Best(len(names), k)
        groups = np.arange(tables.shape[1])
        for batch in batches:
            for start in range(0, batch.num_rows, 1024):
                part = batch.slice(start, 1024)
                raw = codes_matrix(column(part, "pq"))
                score = np.stack([t[groups[None, :], raw].sum(axis=1) for t in shipped.value])
                best.add(score, column(part, "vec_id").to_numpy(zero_copy_only=False))
        yield best.batch(names)

    return rank_rows(codes.select("vec_id", "pq").mapInArrow(run, TOPK), k)
