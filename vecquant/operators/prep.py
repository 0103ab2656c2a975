"""Preparation of vector sets: checks, mean, splits into sub-vectors."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def matrix(array: pa.Array) -> np.ndarray:
    """A list column of equal lengths as a matrix of doubles."""
    if isinstance(array, pa.ChunkedArray):
        array = array.combine_chunks()
    n = len(array)
    return array.flatten().to_numpy(zero_copy_only=False).astype(np.float64).reshape(n, -1) if n else np.zeros((0, 0))


def column(batch: pa.RecordBatch, name: str) -> pa.Array:
    return batch.column(batch.schema.get_field_index(name))


def lists(values: np.ndarray, kind: pa.DataType) -> pa.Array:
    """A matrix as a list column."""
    flat = pa.array(np.ascontiguousarray(values).ravel(), kind)
    return pa.ListArray.from_arrays(np.arange(len(values) + 1, dtype=np.int32) * (values.shape[1] if values.ndim > 1 else 0), flat)


def reject_reason(vector: Column, d: int) -> Column:
    """Why an array can't be encoded, or null."""
    bad = F.exists(vector, lambda v: v.isNull() | F.isnan(v) | (F.abs(v) == float("inf")))
    return (
        F.when(vector.isNull(), "null")
        .when(F.size(vector) == 0, "empty")
        .when(F.size(vector) != d, "length")
        .when(bad, "not finite")
    )


def validate_vectors(df: DataFrame, d: int, vector: str = "embedding") -> tuple[DataFrame, DataFrame]:
    """The rows that can be encoded, and the rejected ones with their reason."""
    marked = df.withColumn("reason", reject_reason(F.col(vector), d))
    return marked.where("reason is null").drop("reason"), marked.where("reason is not null")


def vector_length(df: DataFrame, vector: str = "embedding") -> int:
    """The set's number of dimensions: the most frequent array length of all its rows."""
    row = df.select(F.size(vector).alias("d")).where("d > 0").groupBy("d").count().orderBy(F.desc("count"), "d").first()
    return int(row.d) if row else 0


def fit_mean(df: DataFrame, vector: str = "embedding") -> list[float]:
    """Mean per dimension of the valid rows: sums per partition, then one small total of d numbers."""
    d = vector_length(df, vector)
    if not d:
        return []

    def sums(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total, n = np.zeros(d), 0
        for batch in batches:
            if batch.num_rows:
                x = matrix(column(batch, "v"))
                total += x.sum(axis=0)
                n += len(x)
        yield pa.RecordBatch.from_arrays([pa.array(range(d), pa.int32()), pa.array(total), pa.array([n] * d, pa.int64())], names=["dim", "total", "n"])

    good, _ = validate_vectors(df.select(F.col(vector).alias("v")), d, "v")
    parts = good.mapInArrow(sums, "dim int, total double, n long")
    rows = parts.groupBy("dim").agg((F.sum("total") / F.nullif(F.sum("n"), F.lit(0))).alias("mean")).orderBy("dim").collect()
    return [r.mean or 0.0 for r in rows]


def mean_by_dimension(df: DataFrame, vector: str = "embedding") -> DataFrame:
    """The same mean as rows (dim, mean), in the exploded form."""
    long = df.select(F.posexplode(vector).alias("dim", "value"))
    return long.groupBy("dim").agg(F.avg(F.col("value").cast("double")).alias("mean"))


def center(df: DataFrame, mean: list[float], vector: str = "embedding") -> DataFrame:
    """Doubles with the mean taken off."""
    literal = F.array(*[F.lit(float(v)) for v in mean])
    return df.withColumn(vector, F.zip_with(F.col(vector), literal, lambda a, b: a.cast("double") - b))


def normalize(df: DataFrame, vector: str = "embedding") -> DataFrame:
    """Unit length; zero vectors stay."""
    size = F.sqrt(F.aggregate(vector, F.lit(0.0), lambda s, v: s + v * v))
    return df.withColumn("_size", size).withColumn(
        vector, F.when(F.col("_size") > 0, F.transform(vector, lambda v: v / F.col("_size"))).otherwise(F.col(vector))
    ).drop("_size")


def make_permutation(d: int, m: int, seed: int = 0, split: str = "random") -> np.ndarray:
    """Order of the dimensions: sub-vector j has the j-th of m equal parts of it."""
    if m < 1 or d % m:
        raise ValueError(f"{d} dimensions can't be cut into {m} equal parts")
    if split == "contiguous":
        return np.arange(d)
    return np.random.Generator(np.random.Philox(seed)).permutation(d)


def split_rows(x: np.ndarray, m: int, perm: np.ndarray) -> np.ndarray:
    """[n, d] to [n * m, d / m]: the sub-vectors of each row in turn."""
    return np.ascontiguousarray(x[:, perm]).reshape(len(x) * m, -1)


def unsplit_rows(parts: np.ndarray, m: int, perm: np.ndarray) -> np.ndarray:
    """The inverse of split_rows."""
    x = parts.reshape(len(parts) // m, -1)
    out = np.empty_like(x)
    out[:, perm] = x
    return out


def split_column(vector: Column, m: int, perm: list[int]) -> Column:
    """Sub-vectors as an array of arrays, in columns."""
    width = len(perm) // m
    order = F.array(*[F.lit(int(p) + 1) for p in perm])
    ranked = F.transform(order, lambda i: F.element_at(vector, i))
    return F.transform(F.sequence(F.lit(0), F.lit(m - 1)), lambda j: F.slice(ranked, j * width + 1, width))


def sample(df: DataFrame, fraction: float, seed: int = 0, key: str = "vec_id") -> DataFrame:
    """A sample that is the same at any partitioning: by a hash of the key."""
    return df.where(F.pmod(F.xxhash64(F.lit(seed), F.col(key)), F.lit(1_000_000)) < int(fraction * 1_000_000))


def bounded_sample(df: DataFrame, rows: int, seed: int = 0, key: str = "vec_id") -> DataFrame:
    """About `rows` rows, by a hash of the key, where there are more; nothing passes through the driver."""
    n = df.count()
    return df if n <= rows else sample(df, rows / n, seed, key)


def bounds(vector: Column) -> tuple[Column, Column]:
    return F.array_min(vector), F.array_max(vector)
