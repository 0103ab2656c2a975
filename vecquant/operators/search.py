"""Exact, coded and two-stage nearest-neighbour search.

Queries are a bounded set that every task gets as one matrix; base vectors stay where they
are. A task keeps its k best a query and passes on only these, so the exchange has k rows a
query and task, whatever the size of the base.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from vecquant.functions import curves, expr
from vecquant.operators.codec import decode_batch, params_matrix, unpack
from vecquant.operators.fit import Search
from vecquant.operators.prep import column, make_permutation, matrix

TOPK = "query_id long, vec_id long, score double"
#: Doubles a query set may have to be sent to every task.
MAX_QUERY_VALUES = 100_000_000


def query_values(queries: DataFrame, vector: str = "qvec") -> int:
    """Doubles in the query set, counted where it lies."""
    return queries.agg(F.sum(F.size(vector).cast("long")).alias("n")).first().n or 0


def collect_queries(queries: DataFrame, most: int = MAX_QUERY_VALUES) -> tuple[np.ndarray, np.ndarray]:
    """Ids and matrix of the queries, which are counted before any of them leaves its task."""
    if (size := query_values(queries)) > most:
        raise ValueError(f"{size} query values are too many for one broadcast: search in portions")
    rows = queries.select("query_id", "qvec").orderBy("query_id").toPandas()
    q = np.array(rows["qvec"].tolist(), dtype=np.float64).reshape(len(rows), -1)
    return rows["query_id"].to_numpy(dtype=np.int64), q


def beside(queries: DataFrame, most: int = MAX_QUERY_VALUES) -> DataFrame:
    """The queries, marked for a broadcast if a count shows them small; a join shuffles larger ones."""
    return F.broadcast(queries) if query_values(queries) <= most else queries


def scores(q: np.ndarray, x: np.ndarray, similarity: str) -> np.ndarray:
    """[queries, rows]: higher is nearer."""
    if similarity == "dot":
        return q @ x.T
    if similarity == "l2":
        return -np.maximum((q**2).sum(axis=1)[:, None] - 2 * (q @ x.T) + (x**2).sum(axis=1)[None, :], 0)
    if similarity == "cosine":
        norms = np.linalg.norm(q, axis=1)[:, None] * np.linalg.norm(x, axis=1)[None, :]
        return (q @ x.T) / np.maximum(norms, 1e-300)
    raise ValueError(similarity)


class Best:
    """The k best (score, then smallest id) of each query so far."""

    def __init__(self, n: int, k: int) -> None:
        self.k = k
        self.score = np.full((n, 0), -np.inf)
        self.vec = np.zeros((n, 0), dtype=np.int64)

    def add(self, score: np.ndarray, ids: np.ndarray) -> None:
        score = np.concatenate([self.score, score], axis=1)
        vec = np.concatenate([self.vec, np.broadcast_to(ids, (len(score), len(ids)))], axis=1)
        order = np.lexsort((vec, -score), axis=1)[:, : self.k]
        self.score, self.vec = np.take_along_axis(score, order, axis=1), np.take_along_axis(vec, order, axis=1)

    def batch(self, query_ids: np.ndarray) -> pa.RecordBatch:
        names = np.repeat(query_ids, self.score.shape[1])
        return pa.RecordBatch.from_arrays([pa.array(names), pa.array(self.vec.ravel()), pa.array(self.score.ravel())], names=["query_id", "vec_id", "score"])


def rank_rows(rows: DataFrame, k: int, *by: str) -> DataFrame:
    """query_id, vec_id, score, rank of the k best rows a query; ties go to the smaller id."""
    order = Window.partitionBy(*by, "query_id").orderBy(F.desc("score"), "vec_id")
    return rows.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k)


def _topk(base: DataFrame, queries: DataFrame, k: int, vectors: Callable[[pa.RecordBatch], np.ndarray], similarity: str) -> DataFrame:
    names, q = collect_queries(queries)
    shipped = base.sparkSession.sparkContext.broadcast(q)
    # Scores of one step and the held ones stay under 8 million.
    step = max(64, min(4096, 4_000_000 // max(1, len(names))))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        best, q = Best(len(names), k), shipped.value
        for batch in batches:
            for start in range(0, batch.num_rows, step):
                part = batch.slice(start, step)
                best.add(scores(q, vectors(part), similarity), column(part, "vec_id").to_numpy(zero_copy_only=False).astype(np.int64))
        yield best.batch(names)

    return rank_rows(base.mapInArrow(run, TOPK), k)


def exact_topk(base: DataFrame, queries: DataFrame, k: int = 10, similarity: str = "dot", vector: str = "embedding") -> DataFrame:
    """The exact k nearest rows of every query."""
    rows = base.select(F.col("vec_id").cast("long").alias("vec_id"), F.col(vector).alias("v"))
    return _topk(rows, queries, k, lambda b: matrix(column(b, "v")), similarity)


def coded_topk(coded: DataFrame, queries: DataFrame, s: Search, d: int, k: int = 10, similarity: str = "dot", mean: list[float] | None = None) -> DataFrame:
    """The k nearest decoded vectors of every query."""
    shift = None if mean is None else np.array(mean)
    return _topk(coded.select("vec_id", "codes", "params"), queries, k, lambda b: decode_batch(b, s, d, shift), similarity)


def all_pairs(base: DataFrame, queries: DataFrame, similarity: str = "dot", vector: str = "embedding") -> DataFrame:
    """query_id, vec_id, score in columns. The query side has to be small, as its pairs are all made."""
    if (size := query_values(queries)) > MAX_QUERY_VALUES:
        raise ValueError(f"{size} query values are too many to pair with all rows")
    score = {"dot": expr.dot, "cosine": expr.cosine, "l2": lambda a, b: -expr.squared_distance(a, b)}[similarity]
    joined = base.crossJoin(F.broadcast(queries))
    return joined.select("query_id", "vec_id", score(F.col("qvec"), F.col(vector)).alias("score"))


def within(base: DataFrame, queries: DataFrame, least: float, similarity: str = "dot") -> DataFrame:
    """All rows whose score is at least `least`: a narrow map that passes on only these."""
    names, q = collect_queries(queries)
    shipped = base.sparkSession.sparkContext.broadcast(q)
    step = max(64, min(4096, 4_000_000 // max(1, len(names))))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for start in range(0, batch.num_rows, step):
                part = batch.slice(start, step)
                score = scores(shipped.value, matrix(column(part, "v")), similarity)
                at, row = np.nonzero(score >= least)
                ids = column(part, "vec_id").to_numpy(zero_copy_only=False).astype(np.int64)
                yield pa.RecordBatch.from_arrays([pa.array(names[at]), pa.array(ids[row]), pa.array(score[at, row])], names=["query_id", "vec_id", "score"])

    return base.select(F.col("vec_id").cast("long").alias("vec_id"), F.col("embedding").alias("v")).mapInArrow(run, TOPK)


def holdout(df: DataFrame, mod: int = 10) -> tuple[DataFrame, DataFrame]:
    """Base rows, and every mod-th row as a query (query_id, qvec)."""
    key = F.pmod(F.col("vec_id"), F.lit(mod))
    queries = df.where(key == 0).select(F.col("vec_id").alias("query_id"), F.col("embedding").alias("qvec"))
    return df.where(key != 0), queries


def rerank(candidates: DataFrame, store: DataFrame, queries: DataFrame, k: int, factor: float, decode: Callable[[DataFrame], DataFrame] | None = None, similarity: str = "dot") -> DataFrame:
    """The k best of each query's first factor * k candidates by their vectors in the store.

    Only candidate rows are fetched (a semi join by id, before anything is decoded).
    """
    wanted = candidates.where(F.col("rank") <= int(round(factor * k))).select("query_id", "vec_id")
    fetched = store.join(wanted.select("vec_id").distinct(), "vec_id", "left_semi")
    vectors = decode(fetched) if decode else fetched.select("vec_id", "embedding")
    score = {"dot": expr.dot, "cosine": expr.cosine, "l2": lambda a, b: -expr.squared_distance(a, b)}[similarity]
    joined = wanted.join(vectors, "vec_id").join(beside(queries), "query_id")
    return rank_rows(joined.select("query_id", "vec_id", score(F.col("qvec"), F.col("embedding")).alias("score")), k)


def rerank_sweep(candidates: DataFrame, stores: dict[str, tuple[DataFrame, Callable | None]], queries: DataFrame, truth: DataFrame, k: int, factors: list[float]) -> DataFrame:
    """store, r, recall for every factor r: each store is fetched and scored once, at the largest r.

    A cut at r keeps candidates of first-pass rank up to r * k, so one scored frame serves all.
    A candidate whose full-precision score equals the k-th of the truth (a copy of its row, say) is as
    relevant as that row.
    """
    frame = candidates.where(F.col("rank") <= int(round(max(factors) * k))).select("query_id", "vec_id", F.col("rank").alias("first_rank"))
    for name, (store, decode) in stores.items():
        scored = rerank_scores(candidates, store, queries, k, max(factors), decode)
        frame = frame.join(scored.select("query_id", "vec_id", F.col("score").alias(f"_of_{name}")), ["query_id", "vec_id"], "left")
    frame = relevance(frame, truth, "_of_fp32", k)
    kinds = F.explode(F.array(*[F.struct(F.lit(name).alias("store"), F.col(f"_of_{name}").alias("score")) for name in stores])).alias("_kind")
    scored = frame.select("query_id", "vec_id", "first_rank", "relevant", kinds).select("*", "_kind.store", "_kind.score").where("score IS NOT NULL")
    at = F.explode(F.array(*[F.lit(float(f)) for f in factors])).alias("r")
    cut = scored.select("query_id", "vec_id", "first_rank", "relevant", "store", "score", at).where(F.col("first_rank") <= F.round(F.col("r") * k))
    order = Window.partitionBy("store", "r", "query_id").orderBy(F.desc("score"), "vec_id")
    top = cut.withColumn("rank", F.row_number().over(order)).where((F.col("rank") <= k) & F.col("relevant"))
    hits = top.groupBy("store", "r").agg(F.count("*").alias("hits"))
    total = truth.select("query_id").distinct().agg(F.count("*").alias("n"))
    return hits.crossJoin(F.broadcast(total)).select("store", "r", (F.col("hits") / (F.col("n") * k)).alias("recall"))


def relevance(scored: DataFrame, truth: DataFrame, score: str, k: int) -> DataFrame:
    """The rows, and whether they are relevant: of the exact top k, or of an exact score (a column) that is that of the k-th."""
    top = truth.where(F.col("rank") <= k)
    last = top.groupBy("query_id").agg(F.min("score").alias("_least"))
    # The same dot product summed in another order differs in its last digits.
    level = F.col(score) >= F.col("_least") - 1e-12 * F.greatest(F.abs("_least"), F.lit(1.0))
    marked = scored.join(top.select("query_id", "vec_id", F.lit(True).alias("_top")), ["query_id", "vec_id"], "left").join(last, "query_id", "left")
    return marked.withColumn("relevant", F.coalesce(F.col("_top"), level, F.lit(False))).drop("_top", "_least")


def rerank_scores(candidates: DataFrame, store: DataFrame, queries: DataFrame, k: int, factor: float, decode: Callable | None = None) -> DataFrame:
    """query_id, vec_id, first_rank, score of the first factor * k candidates.

    A small query set goes to every task, and a fetched row is scored with all queries that ask for it: it moves once.
    """
    wanted = candidates.where(F.col("rank") <= int(round(factor * k))).select("query_id", "vec_id", F.col("rank").alias("first_rank"))
    fetched = store.join(wanted.select("vec_id").distinct(), "vec_id", "left_semi")
    vectors = decode(fetched) if decode else fetched.select("vec_id", "embedding")
    if query_values(queries) > MAX_QUERY_VALUES:
        joined = wanted.join(vectors, "vec_id").join(queries, "query_id")
        return joined.select("query_id", "vec_id", "first_rank", expr.dot(F.col("qvec"), F.col("embedding")).alias("score"))
    names, q = collect_queries(queries)
    shipped = candidates.sparkSession.sparkContext.broadcast((names, q))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names, q = shipped.value
        for whole in batches:
            for start in range(0, whole.num_rows, 256):
                part = whole.slice(start, 256)
                x, ids = matrix(column(part, "v")), column(part, "vec_id").to_numpy(zero_copy_only=False).astype(np.int64)
                asked, ranks = column(part, "asked"), column(part, "ranks").flatten()
                own = np.repeat(np.arange(len(ids)), np.diff(asked.offsets.to_numpy()))
                asked = asked.flatten().to_numpy(zero_copy_only=False).astype(np.int64)
                at = np.searchsorted(names, asked)
                score = np.empty(len(at))
                for a in range(0, len(at), 1024):
                    cut = slice(a, a + 1024)
                    score[cut] = np.einsum("nd,nd->n", q[at[cut]], x[own[cut]])
                yield pa.RecordBatch.from_arrays([pa.array(asked), pa.array(ids[own]), ranks.cast(pa.int64()), pa.array(score)], names=["query_id", "vec_id", "first_rank", "score"])

    known = wanted.join(beside(queries).select("query_id"), "query_id", "left_semi")
    pairs = known.groupBy("vec_id").agg(F.collect_list(F.struct("query_id", "first_rank")).alias("_asked"))
    pairs = pairs.select("vec_id", F.col("_asked.query_id").cast("array<long>").alias("asked"), F.col("_asked.first_rank").cast("array<long>").alias("ranks"))
    rows = vectors.join(pairs, "vec_id").select(F.col("vec_id").cast("long").alias("vec_id"), F.col("embedding").alias("v"), "asked", "ranks")
    return rows.mapInArrow(run, "query_id long, vec_id long, first_rank long, score double")


def lut_scores(q: np.ndarray, batch: pa.RecordBatch, s: Search, d: int, mean: np.ndarray | None) -> np.ndarray:
    """[queries, rows] dot products by code: each sub-vector's levels are decoded once and looked up."""
    perm = make_permutation(d, s.m, s.split_seed, s.split)
    levels = 2**s.bits
    codes = unpack(column(batch, "codes").to_pylist(), s.bits, d).reshape(batch.num_rows, s.m, -1)
    p0, p1, lo, hi = (params_matrix(column(batch, "params"))[..., k : k + 1] for k in range(4))
    table = curves.unbend(s.curve, np.arange(levels)[None, None, :] / (levels - 1), lo, hi, p0, p1)
    picked = np.take_along_axis(table, codes.astype(np.int64), axis=2)
    score = np.einsum("qmd,nmd->qn", q[:, perm].reshape(len(q), s.m, -1), picked)
    return score if mean is None else score + (q @ mean)[:, None]


def lut_topk(coded: DataFrame, queries: DataFrame, s: Search, d: int, k: int = 10, mean: list[float] | None = None) -> DataFrame:
    """The k best dot products of every query, by levels looked up per code."""
    names, q = collect_queries(queries)
    shipped = coded.sparkSession.sparkContext.broadcast(q)
    shift = None if mean is None else np.array(mean)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        best = Best(len(names), k)
        for batch in batches:
            for start in range(0, batch.num_rows, 1024):
                part = batch.slice(start, 1024)
                best.add(lut_scores(shipped.value, part, s, d, shift), column(part, "vec_id").to_numpy(zero_copy_only=False))
        yield best.batch(names)

    return rank_rows(coded.select("vec_id", "codes", "params").mapInArrow(run, TOPK), k)


def lut_gap(coded: DataFrame, queries: DataFrame, s: Search, d: int, mean: list[float] | None = None) -> DataFrame:
    """vec_id, pairs, gap: per row how far scores by looked-up levels are from those of the decoded vector."""
    _, q = collect_queries(queries)
    shipped = coded.sparkSession.sparkContext.broadcast(q)
    shift = None if mean is None else np.array(mean)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for start in range(0, batch.num_rows, 1024):
                part = batch.slice(start, 1024)
                plain = shipped.value @ decode_batch(part, s, d, shift).T
                gap = np.abs(lut_scores(shipped.value, part, s, d, shift) - plain).max(axis=0, initial=0.0)
                yield pa.RecordBatch.from_arrays([column(part, "vec_id"), pa.array(np.full(len(gap), len(plain))), pa.array(gap)], names=["vec_id", "pairs", "gap"])

    return coded.select("vec_id", "codes", "params").mapInArrow(run, "vec_id long, pairs long, gap double")


def global_topk(base: DataFrame, queries: DataFrame, k: int, similarity: str = "dot") -> DataFrame:
    """The k best pairs over all queries: k rows a query leave a task, and k rows a task the last sort."""
    return exact_topk(base, queries, k, similarity).orderBy(F.desc("score"), "query_id", "vec_id").limit(k).drop("rank")
