"""Accuracy measures over fits, codes and search results."""

from __future__ import annotations

from collections.abc import Iterator
from pathlib import Path

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from vecquant.functions import expr
from vecquant.operators.fit import Search
from vecquant.operators.prep import column, make_permutation, matrix


def long_form(df: DataFrame, vector: str = "embedding") -> DataFrame:
    """vec_id, dim, value, lo, hi: a row a value, with its vector's bounds."""
    bounded = df.select("vec_id", vector, F.array_min(vector).cast("double").alias("lo"), F.array_max(vector).cast("double").alias("hi"))
    long = bounded.select("vec_id", "lo", "hi", F.posexplode(vector).alias("dim", "value"))
    return long.select("vec_id", "dim", F.col("value").cast("double").alias("value"), "lo", "hi")


def doubles(vector: str = "embedding") -> Column:
    return F.transform(vector, lambda v: v.cast("double"))


def loss_of(values: Column, lo: Column, hi: Column, curve: str, p0: Column | float = 1.0, p1: Column | float = 1.0, bits: int = 8) -> Column:
    """Squared round-trip error of an array of doubles, summed in order within its row."""

    def error(x: Column) -> Column:
        code = expr.quantize(curve, x, lo, hi, p0, p1, bits)
        return expr.bind(code, lambda c: F.pow(x - expr.dequantize(curve, c, lo, hi, p0, p1, bits), 2))

    return F.aggregate(values, F.lit(0.0), lambda total, x: total + error(x))


def bounded(df: DataFrame, vector: str = "embedding") -> DataFrame:
    """vec_id, v (doubles), lo, hi of every vector."""
    rows = df.select("vec_id", doubles(vector).alias("v"))
    return rows.select("vec_id", "v", F.array_min("v").alias("lo"), F.array_max("v").alias("hi"))


def recon_loss(df: DataFrame, curve: str = "unif", p0: float = 1.0, p1: float = 1.0, bits: int = 8) -> DataFrame:
    """vec_id, loss with fixed parameters: each row by itself, without an exchange."""
    return bounded(df).select("vec_id", loss_of(F.col("v"), F.col("lo"), F.col("hi"), curve, p0, p1, bits).alias("loss"))


def gain(df: DataFrame, curve: str, p0: float, p1: float, bits: int = 8) -> DataFrame:
    """vec_id, uniform_loss, loss, gain with fixed parameters, in one narrow pass."""
    v, lo, hi = F.col("v"), F.col("lo"), F.col("hi")
    sums = bounded(df).select("vec_id", loss_of(v, lo, hi, "unif", bits=bits).alias("uniform_loss"), loss_of(v, lo, hi, curve, p0, p1, bits).alias("loss"))
    return sums.withColumn("gain", F.when(F.col("loss") > 0, F.col("uniform_loss") / F.col("loss")).otherwise(1.0))


def gain_summary(fits: DataFrame, *by: str) -> DataFrame:
    """n, mean, min, max, sd, quartiles of the gain and the share below 1."""
    g = F.col("gain")
    quartiles = F.percentile("gain", F.array(F.lit(0.25), F.lit(0.5), F.lit(0.75)))
    return fits.groupBy(*by).agg(
        F.count("*").alias("n"), F.avg(g).alias("mean"), F.min(g).alias("least"), F.max(g).alias("most"), F.stddev_samp(g).alias("sd"),
        quartiles.alias("quartiles"), F.avg((g < 1).cast("double")).alias("below_one"),
    )


def mean_recon(pairs: DataFrame) -> DataFrame:
    """Mean squared distance of x and x_hat, columns of one row each."""
    return pairs.agg(F.avg(expr.squared_distance(F.col("x"), F.col("x_hat"))).alias("mean_recon"))


def dot_error(pairs: DataFrame, queries: DataFrame) -> DataFrame:
    """query_id, error: squared gaps of the dot products with x and x_hat, summed over the set.

    The queries are sent to every task as one matrix; partial sums leave a task, one a query.
    """
    from vecquant.operators.search import collect_queries

    names, q = collect_queries(queries)
    shipped = pairs.sparkSession.sparkContext.broadcast(q)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(len(names))
        for batch in batches:
            if batch.num_rows:
                gap = matrix(column(batch, "x")) - matrix(column(batch, "x_hat"))
                total += ((gap @ shipped.value.T) ** 2).sum(axis=0)
        yield pa.RecordBatch.from_arrays([pa.array(names, pa.int64()), pa.array(total)], names=["query_id", "error"])

    parts = pairs.select("x", "x_hat").mapInArrow(run, "query_id long, error double")
    return parts.groupBy("query_id").agg(F.sum("error").alias("error"))


def map_at_k(found: DataFrame, truth: DataFrame, k: int, *by: str) -> DataFrame:
    """query_id, average precision: relevant are the exact top k; found has ranks from 1."""
    relevant = truth.where(F.col("rank") <= k).select("query_id", "vec_id", F.lit(1).alias("rel"))
    hits = found.where(F.col("rank") <= k).join(relevant, ["query_id", "vec_id"], "left").fillna(0, ["rel"])
    order = Window.partitionBy(*by, "query_id").orderBy("rank").rowsBetween(Window.unboundedPreceding, 0)
    precise = hits.withColumn("precision", F.sum("rel").over(order) / F.col("rank"))
    return precise.groupBy(*by, "query_id").agg((F.sum(F.col("precision") * F.col("rel")) / k).alias("average_precision"))


def round_trips(base: DataFrame, queries: DataFrame, searches: list[Search], mean: list[float], k: int) -> DataFrame:
    """m, query_id, vec_id, score, n, gain, recon, error: what each task found with each search, in one scan.

    Every row is coded, packed, unpacked and decoded once a search (one for each m), and what is measured
    stays beside it: no vector leaves its task. Rows with an id of a vector are a task's k best of
    a query, of exact vectors where m is 0; rows with a query alone have its squared gaps of dot products,
    summed; rows with neither have the number of vectors and the sums of gains and of squared errors.
    """
    from vecquant.operators.codec import decode_rows, encode_rows, pack
    from vecquant.operators.search import Best, collect_queries, scores

    names, q = collect_queries(queries)
    shipped = base.sparkSession.sparkContext.broadcast((q, np.array(mean)))
    step = max(64, min(2048, 4_000_000 // max(1, len(names))))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        q, shift = shipped.value
        best = {m: Best(len(names), k) for m in (0, *(s.m for s in searches))}
        sums, errors = {s.m: np.zeros(3) for s in searches}, {s.m: np.zeros(len(names)) for s in searches}
        for whole in batches:
            for start in range(0, whole.num_rows, step):
                batch = whole.slice(start, step)
                ids, x = column(batch, "vec_id").to_numpy(zero_copy_only=False).astype(np.int64), matrix(column(batch, "v"))
                best[0].add(scores(q, x, "dot"), ids)
                for s in searches:
                    perm = make_permutation(x.shape[1], s.m, s.split_seed, s.split)
                    made = encode_rows(x - shift, ids, s, perm)
                    back = decode_rows(pack(made["codes"], s.bits), made["params"], s.curve, s.bits, x.shape[1], perm) + shift
                    best[s.m].add(scores(q, back, "dot"), ids)
                    gap = x - back
                    sums[s.m] += len(ids), made["gain"].sum(), (gap**2).sum()
                    errors[s.m] += ((gap @ q.T) ** 2).sum(axis=0)
        for m, found in best.items():
            top = found.batch(names)
            yield _filled(pa.array(np.full(top.num_rows, m, np.int32)), **{c: column(top, c) for c in top.schema.names})
        for m, total in sums.items():
            yield _filled(pa.array(np.full(len(names), m, np.int32)), query_id=pa.array(names, pa.int64()), error=pa.array(errors[m]))
            yield _filled(pa.array([m], pa.int32()), n=pa.array([int(total[0])]), gain=pa.array(total[1:2]), recon=pa.array(total[2:]))

    return base.select(F.col("vec_id").cast("long").alias("vec_id"), F.col("embedding").alias("v")).mapInArrow(run, _TRIPS)


_TRIPS = "m int, query_id long, vec_id long, score double, n long, gain double, recon double, error double"


def _filled(m: pa.Array, **given: pa.Array) -> pa.RecordBatch:
    """A batch of round_trips: columns that are not given are null."""
    kinds = {"query_id": pa.int64(), "vec_id": pa.int64(), "score": pa.float64(), "n": pa.int64(), "gain": pa.float64(), "recon": pa.float64(), "error": pa.float64()}
    return pa.RecordBatch.from_arrays([m, *(given.get(c, pa.nulls(len(m), kind)) for c, kind in kinds.items())], names=["m", *kinds])


def recall_at_k(found: DataFrame, truth: DataFrame, k: int) -> DataFrame:
    """query_id, recall: the share of the exact top k among the first k found."""
    relevant = truth.where(F.col("rank") <= k).select("query_id", "vec_id")
    own = found.where(F.col("rank") <= k).select("query_id", "vec_id", F.lit(1).alias("hit"))
    return relevant.join(own, ["query_id", "vec_id"], "left").groupBy("query_id").agg((F.sum(F.coalesce("hit", F.lit(0))) / k).alias("recall"))


def recall_delta(sweep: DataFrame) -> DataFrame:
    """r, loss of recall of the coded store against full precision at equal r."""
    coded, full = sweep.where("store = 'coded'"), sweep.where("store = 'fp32'")
    joined = coded.alias("c").join(full.alias("f"), "r")
    return joined.select("r", (F.col("f.recall") - F.col("c.recall")).alias("recall_loss"))


def iteration_hist(fits: DataFrame) -> DataFrame:
    return fits.groupBy("iters").agg(F.count("*").alias("n"))


def convergence_band(traces: DataFrame, *by: str) -> DataFrame:
    """Mean and spread of the gain over runs, by iteration."""
    return traces.groupBy(*by, "iter").agg(F.avg("gain").alias("mean"), F.stddev_samp("gain").alias("sd"))


def step_size(traces: DataFrame) -> DataFrame:
    """Euclidean step of the parameters from one iteration to the next."""
    own = Window.partitionBy("vec_id", "run").orderBy("iter")
    moved = F.sqrt(F.pow(F.col("p0") - F.lag("p0").over(own), 2) + F.pow(F.col("p1") - F.lag("p1").over(own), 2))
    return traces.select("vec_id", "run", "iter", moved.alias("step"))


def param_spread(fits: DataFrame, *by: str) -> DataFrame:
    """Means, spreads and correlation of the fitted parameters."""
    return fits.groupBy(*by).agg(
        F.avg("p0").alias("mean0"), F.avg("p1").alias("mean1"), F.stddev_samp("p0").alias("sd0"), F.stddev_samp("p1").alias("sd1"),
        F.covar_samp("p0", "p1").alias("covariance"), F.corr("p0", "p1").alias("correlation"),
    )


def win_rate(fits: DataFrame, first: str, second: str) -> DataFrame:
    """Share of vectors on which the first curve's gain is above the second's. fits: vec_id, curve, gain."""
    both = fits.groupBy("vec_id").agg(
        F.max(F.when(F.col("curve") == first, F.col("gain"))).alias("a"), F.max(F.when(F.col("curve") == second, F.col("gain"))).alias("b")
    )
    return both.agg(F.lit(first).alias("first"), F.lit(second).alias("second"), F.avg((F.col("a") > F.col("b")).cast("double")).alias("wins"))


def alpha_shift(fits: DataFrame) -> DataFrame:
    """Ratio of the mean slopes of the piecewise-linear and the logistic curve."""
    mean = lambda c: F.avg(F.when(F.col("curve") == c, F.col("p0")))
    return fits.agg((mean("pwl") / mean("logi")).alias("shift"))


def value_density(df: DataFrame, ids: list[int], points: int = 64, bandwidth: float | None = None) -> DataFrame:
    """vec_id, x, density: Gaussian kernel estimate of the values of a few vectors on an even grid."""
    long = long_form(df.where(F.col("vec_id").isin(ids)))
    stats = long.groupBy("vec_id").agg(F.stddev_samp("value").alias("sd"), F.count("*").alias("n"), F.first("lo").alias("lo"), F.first("hi").alias("hi"))
    width = F.lit(bandwidth) if bandwidth else 1.06 * F.col("sd") * F.pow(F.col("n"), F.lit(-0.2))
    spots = stats.withColumn("h", width).select("vec_id", "n", "h", "lo", "hi", F.explode(F.sequence(F.lit(0), F.lit(points - 1))).alias("k"))
    spots = spots.withColumn("x", F.col("lo") + (F.col("hi") - F.col("lo")) * F.col("k") / (points - 1)).select("vec_id", "n", "h", "k", "x")
    joined = spots.join(long.select("vec_id", "value"), "vec_id")
    kernel = F.exp(-0.5 * F.pow((F.col("x") - F.col("value")) / F.col("h"), 2)) / (F.col("n") * F.col("h") * F.sqrt(2 * F.pi()))
    return joined.groupBy("vec_id", "k", "x").agg(F.sum(kernel).alias("density")).select("vec_id", "k", "x", "density")


def fidelity(pairs: DataFrame) -> DataFrame:
    """Per vector the ratio of norms and the cosine of x and x_hat."""
    x, y = F.col("x"), F.col("x_hat")
    return pairs.select("vec_id", (expr.norm(y) / expr.norm(x)).alias("norm_ratio"), expr.cosine(x, y).alias("cosine"))


def flat_prior_check(pairs: DataFrame, directions: int, seed: int = 0) -> DataFrame:
    """Ratio of the mean squared dot error over random unit directions, times d, to the squared error."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if not batch.num_rows:
                continue
            gap = matrix(column(batch, "x")) - matrix(column(batch, "x_hat"))
            q = np.random.Generator(np.random.Philox(seed)).standard_normal((directions, gap.shape[1]))
            q /= np.linalg.norm(q, axis=1, keepdims=True)
            dots = ((gap @ q.T) ** 2).mean(axis=1) * gap.shape[1]
            yield pa.RecordBatch.from_arrays([pa.array(dots), pa.array((gap**2).sum(axis=1))], names=["dots", "squares"])

    parts = pairs.select("x", "x_hat").mapInArrow(run, "dots double, squares double")
    return parts.agg((F.sum("dots") / F.sum("squares")).alias("ratio"))


def pairs_of(df: DataFrame, decoded: DataFrame) -> DataFrame:
    """vec_id, x, x_hat: a shuffle join on the id, or none where both sides are bucketed by it."""
    return df.select("vec_id", F.col("embedding").alias("x")).join(decoded.select("vec_id", F.col("embedding").alias("x_hat")), "vec_id")


def file_bytes(spark, path: str) -> int:  # noqa: ANN001
    """Bytes of the data files under a path, from the listing."""
    files = spark.read.format("binaryFile").option("pathGlobFilter", "*.parquet").option("recursiveFileLookup", "true").load(path)
    return files.agg(F.sum("length").alias("n")).first().n or 0


def footprint_ratio(spark, full: str | Path, coded: str | Path) -> float:  # noqa: ANN001
    return file_bytes(spark, str(full)) / max(1, file_bytes(spark, str(coded)))


def recall_at_equal_time(sweep: DataFrame) -> DataFrame:
    """r, recall_loss: coded recall against full precision interpolated at the same seconds.

    sweep: store, r, recall, seconds, a row a factor. Every coded point has a row: before the
    first and after the last time of full precision, the recall there is the nearest point's.
    """
    order = Window.orderBy("seconds")  # a row a factor: a handful
    full = sweep.where("store = 'fp32'").select(
        F.when(F.row_number().over(order) == 1, float("-inf")).otherwise(F.col("seconds")).alias("from_s"),
        "seconds",
        "recall",
        F.coalesce(F.lead("seconds").over(order), F.lit(float("inf"))).alias("next_s"),
        F.coalesce(F.lead("recall").over(order), F.col("recall")).alias("next_r"),
    )
    coded = sweep.where("store = 'coded'").select("r", F.col("seconds").alias("s"), F.col("recall").alias("own"))
    joined = coded.join(full, (F.col("s") >= F.col("from_s")) & (F.col("s") < F.col("next_s")))
    inside = (F.col("s") > F.col("seconds")) & (F.col("next_s") < float("inf"))
    share = F.when(inside, (F.col("s") - F.col("seconds")) / (F.col("next_s") - F.col("seconds"))).otherwise(0.0)
    return joined.select("r", (F.col("recall") + share * (F.col("next_r") - F.col("recall")) - F.col("own")).alias("recall_loss"))
