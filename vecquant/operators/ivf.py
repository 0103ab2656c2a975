"""Inverted lists: rows under their nearest centroids, some of them copied to several."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vecquant.operators.pq import lloyd
from vecquant.operators.prep import bounded_sample, column, matrix
from vecquant.operators.search import MAX_QUERY_VALUES, all_pairs, query_values, rank_rows


def centroids(df: DataFrame, n: int, iters: int = 10, sample_rows: int = 20_000, seed: int = 0) -> np.ndarray:
    """n centroids of about sample_rows rows, which the driver gets."""
    rows = bounded_sample(df.select("vec_id", "embedding"), sample_rows, seed).toPandas().sort_values("vec_id")
    return lloyd(np.array(rows["embedding"].tolist(), dtype=np.float64), n, iters, seed)


def assign(df: DataFrame, centers: np.ndarray, replicas: int = 1) -> DataFrame:
    """cluster_id, vec_id, embedding: each row under its `replicas` nearest centroids."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        size = (centers**2).sum(axis=1)
        for batch in batches:
            if not batch.num_rows:
                continue
            near = np.argsort(size - 2 * matrix(column(batch, "embedding")) @ centers.T, axis=1, kind="stable")[:, :replicas]
            rows = pa.array(np.repeat(np.arange(batch.num_rows), near.shape[1]))
            yield pa.RecordBatch.from_arrays([pa.array(near.ravel().astype(np.int32)), column(batch, "vec_id").take(rows), column(batch, "embedding").take(rows)], names=["cluster_id", "vec_id", "embedding"])

    kind = df.schema["embedding"].dataType.simpleString()
    return df.select("vec_id", "embedding").mapInArrow(run, f"cluster_id int, vec_id long, embedding {kind}")


def probes(queries: DataFrame, centers: np.ndarray, nprobe: int) -> DataFrame:
    """query_id, qvec, cluster_id of each query's nearest centroids."""
    named = assign(queries.select(F.col("query_id").alias("vec_id"), F.col("qvec").alias("embedding")), centers, nprobe)
    return named.select(F.col("vec_id").alias("query_id"), F.col("embedding").alias("qvec"), "cluster_id")


def search(lists: DataFrame, queries: DataFrame, centers: np.ndarray, k: int = 10, nprobe: int = 4) -> DataFrame:
    """The k best rows of the probed lists; a row that stands in several counts once.

    Lists that are stored partitioned by cluster_id are read only where a query probes them.
    """
    from vecquant.functions import expr

    # Probes are nprobe copies of the queries.
    asked = probes(queries, centers, nprobe)
    if query_values(queries) * nprobe <= MAX_QUERY_VALUES:
        asked = F.broadcast(asked)
    joined = lists.join(asked, "cluster_id")
    scored = joined.select("query_id", "vec_id", expr.dot(F.col("qvec"), F.col("embedding")).alias("score"))
    return rank_rows(scored.dropDuplicates(["query_id", "vec_id"]), k)


__all__ = ["all_pairs", "assign", "centroids", "probes", "search"]
