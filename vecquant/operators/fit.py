"""Per-vector fitting of curve parameters.

Every vector is a problem of its own with two unknowns, so a fit is a narrow map over Arrow
batches: the search loop runs inside the task over all (sub)vectors of a slice at once, and
rows that have settled leave the slice. No shuffle, no job per iteration.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator
from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from vecquant.functions import curves
from vecquant.operators.prep import column, make_permutation, matrix, split_rows
from vecquant.schema import FIT, GAIN_CAP

#: Doubles of one temporary of the search: slices are cut so that rows * samples * dims stay below. A few of them fit the cache.
_TEMPORARY = 200_000
#: Values that one search holds in order with their sums; more rows are taken in turn.
_HELD = 1_000_000
#: Parameter pairs of a slice whose losses cut it further by themselves.
_PAIRS = 6_000
#: Rows with more values than this are measured at levels and boundaries: than levels, or than where value by value costs as much.
_BY_LEVELS: dict[tuple[str, int], int] = {("logi", 8): 512}
#: Logistic losses of rows with fewer values stay as `loss` takes them.
_BY_VALUES = 96


def default_hparams(p: int = 2) -> tuple[int, float, float]:
    """Samples an iteration, and the learning rates of mean and spread, for p unknowns."""
    samples = 2 * (4 + math.floor(3 * math.log(p)))
    return samples, 1.0, (9 + 3 * math.log(p)) / (5 * p * math.sqrt(p))


def separable_rate(p: int = 2) -> float:
    """The usual spread rate of the separable search."""
    return (3 + math.log(p)) / (5 * math.sqrt(p))


def rank_utilities(n: int) -> np.ndarray:
    """Utilities of ranks 1 (best) to n: decreasing, zero for the worse half, summing to zero."""
    raw = np.maximum(0, np.log(n / 2 + 1) - np.log(np.arange(1, n + 1)))
    return raw / raw.sum() - 1 / n


@dataclass(frozen=True)
class Search:
    """Options of the evolution search.

    mean_clamp: "project" keeps the mean where the curve allows it, "nonneg" clips it at zero.
    x0_domain: the midpoint's range in scaled or raw units. noise: "per_vector" draws by
    (seed, vector, part, iteration), "shared" by (seed, part, iteration). keep_best returns the
    best sample seen instead of the last mean; fallback_uniform gives gain 1 where it is below.
    weights: per-dimension loss weights of a query-aware fit. draws: the noise itself,
    [iterations][samples][2], the same for every vector, where a search is to be retraced.
    """

    curve: str = "logi"
    bits: int = 8
    m: int = 1
    seed: int = 0
    tol: float = 1e-4
    min_iter: int = 10
    max_iter: int = 100
    fixed_iter: int | None = None
    samples: int | None = None
    eta_mu: float = 1.0
    eta_sigma: float | str | None = None
    mu: tuple[float, float] | None = None
    sigma: tuple[float, float] | None = None
    mean_clamp: str = "project"
    x0_domain: str = "scaled"
    noise: str = "per_vector"
    keep_best: bool = False
    fallback_uniform: bool = False
    split: str = "random"
    split_seed: int = 0
    weights: tuple[float, ...] | None = None
    draws: tuple | None = None
    clip_quantile: float = 0.0


def _mix(x: np.ndarray) -> np.ndarray:
    """A counter to well-spread 64-bit numbers."""
    with np.errstate(over="ignore"):
        x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
        x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
        return x ^ (x >> np.uint64(31))


def normals(keys: np.ndarray, seed: int, iteration: int, samples: int) -> np.ndarray:
    """Standard normal draws [len(keys), samples, 2], a function of the key, seed and iteration."""
    with np.errstate(over="ignore"):
        base = _mix(keys.astype(np.uint64) + np.uint64((seed * 0x9E3779B97F4A7C15 + iteration * 0xD1B54A32D192ED03) & (2**64 - 1)))
        k = np.arange(2 * samples, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)
        bits = _mix(base[:, None] + k[None, :])
    u = ((bits >> np.uint64(11)).astype(np.float64) + 0.5) / 2**53
    radius, angle = np.sqrt(-2 * np.log(u[:, :samples])), 2 * np.pi * u[:, samples:]
    return np.stack([radius * np.cos(angle), radius * np.sin(angle)], axis=2)


def bounds_of(x: np.ndarray, clip: float = 0.0) -> tuple[np.ndarray, np.ndarray]:
    """Bounds of each row, or its quantiles where outliers are to be clipped."""
    if clip:
        return np.quantile(x, clip, axis=1, keepdims=True), np.quantile(x, 1 - clip, axis=1, keepdims=True)
    return x.min(axis=1, keepdims=True), x.max(axis=1, keepdims=True)


def gains(uniform: np.ndarray, fitted: np.ndarray) -> np.ndarray:
    """uniform / fitted; 0 for a saturated curve, 1 where both are 0, capped where only the fitted one is."""
    with np.errstate(all="ignore"):
        ratio = uniform / fitted
    ratio = np.where(fitted == 0, np.where(uniform == 0, 1.0, GAIN_CAP), ratio)
    return np.minimum(np.where(np.isfinite(fitted), ratio, 0.0), GAIN_CAP)


def _objective(s: Search, x: np.ndarray, lo: np.ndarray, hi: np.ndarray, uniform: np.ndarray, theta: np.ndarray, w: np.ndarray | None, held: curves.Held | None, rows: np.ndarray) -> np.ndarray:
    """Gains of samples theta [rows, samples, 2]."""
    if held is not None:
        return gains(uniform[:, None], held.loss(s.curve, rows, theta[..., 0], theta[..., 1], s.bits))
    wide = (x[:, None, :], lo[:, None, :], hi[:, None, :])
    found = curves.loss(s.curve, *wide, theta[..., :1], theta[..., 1:], s.bits, None if w is None else w[:, None, :])
    return gains(uniform[:, None], found)


def evolve_rows(x: np.ndarray, keys: np.ndarray, s: Search, weights: np.ndarray | None = None, trace: Callable | None = None) -> dict[str, np.ndarray]:
    """Fit every row of a matrix. Rows are independent of each other."""
    most = max(1, _HELD // max(1, x.shape[1]))
    if trace is None and len(x) > most:
        cuts = range(0, len(x), most)
        parts = [evolve_rows(x[a : a + most], keys[a : a + most], s, None if weights is None else weights[a : a + most]) for a in cuts]
        return {name: np.concatenate([p[name] for p in parts]) for name in parts[0]}
    given = None if s.draws is None else np.array(s.draws)
    n = len(x)
    lo, hi = bounds_of(x, s.clip_quantile)
    x = np.clip(x, lo, hi) if s.clip_quantile else x
    uniform = curves.loss("unif", x, lo, hi, 0.0, 0.0, s.bits, weights)
    samples, _, rate = default_hparams(2)
    samples = s.samples or samples
    rate = {"separable": separable_rate(2), None: rate}.get(s.eta_sigma, s.eta_sigma)
    utilities = rank_utilities(samples)
    mu = np.tile(np.array(s.mu or curves.START[s.curve]), (n, 1))
    mu[:, 0], mu[:, 1] = (v[:, 0] for v in curves.project(s.curve, mu[:, :1], mu[:, 1:], lo, hi, s.x0_domain))
    sigma = np.tile(np.array(s.sigma or curves.SPREAD[s.curve]), (n, 1))
    best, best_gain = mu.copy(), np.full(n, -1.0)
    iters, converged = np.zeros(n, dtype=np.int32), np.zeros(n, dtype=bool)
    degenerate = (hi <= lo)[:, 0]
    active = np.flatnonzero(~degenerate)
    held = None
    if weights is None and x.shape[1] > _BY_LEVELS.get((s.curve, s.bits), 2**s.bits):
        held = curves.Ordered(x, lo, hi)
    elif weights is None and s.curve == "logi" and x.shape[1] >= _BY_VALUES:
        held = curves.Held(x, lo, hi)
    rows_at_once = max(1, _PAIRS // samples if held else _TEMPORARY // (samples * max(1, x.shape[1])))
    limit = s.fixed_iter or s.max_iter
    for t in range(1, limit + 1):
        if not len(active):
            break
        settled = []
        for a in range(0, len(active), rows_at_once):
            rows = active[a : a + rows_at_once]
            if given is None:
                draw = normals(keys[rows] if s.noise == "per_vector" else np.zeros(len(rows), dtype=np.int64), s.seed, t, samples)
            else:
                draw = np.broadcast_to(given[t - 1], (len(rows), samples, 2))
            theta = mu[rows][:, None, :] + sigma[rows][:, None, :] * draw
            theta = np.stack(curves.project(s.curve, theta[..., 0], theta[..., 1], lo[rows], hi[rows], s.x0_domain), axis=2)
            value = _objective(s, x[rows], lo[rows], hi[rows], uniform[rows], theta, None if weights is None else weights[rows], held, rows)
            order = np.argsort(-value, axis=1, kind="stable")
            u = np.empty_like(value)
            np.put_along_axis(u, order, np.broadcast_to(utilities, value.shape), axis=1)
            toward = (u[..., None] * draw).sum(axis=1)
            wider = (u[..., None] * (draw**2 - 1)).sum(axis=1)
            new = mu[rows] + s.eta_mu * sigma[rows] * toward
            if s.mean_clamp == "nonneg":
                new = np.maximum(new, 0)
            new = np.column_stack(curves.project(s.curve, new[:, 0], new[:, 1], lo[rows][:, 0], hi[rows][:, 0], s.x0_domain))
            top = order[:, 0]
            top_gain = value[np.arange(len(rows)), top]
            better = top_gain > best_gain[rows]
            best[rows[better]] = theta[np.arange(len(rows)), top][better]
            best_gain[rows[better]] = top_gain[better]
            step = np.sqrt(((new - mu[rows]) ** 2).sum(axis=1))
            mu[rows], sigma[rows] = new, sigma[rows] * np.exp(rate / 2 * wider)
            iters[rows] = t
            if trace is not None:
                now = _objective(s, x[rows], lo[rows], hi[rows], uniform[rows], new[:, None, :], None if weights is None else weights[rows], held, rows)[:, 0]
                trace(rows, t, new, now)
            if s.fixed_iter is None and t >= s.min_iter:
                done = step < s.tol
                converged[rows[done]] = True
                settled.append(rows[done])
        if settled:
            active = np.setdiff1d(active, np.concatenate(settled), assume_unique=True)
    final = curves.loss(s.curve, x, lo, hi, mu[:, :1], mu[:, 1:], s.bits, weights)
    gain = gains(uniform, final)
    if s.keep_best:
        use = best_gain > gain
        mu[use] = best[use]
        final = curves.loss(s.curve, x, lo, hi, mu[:, :1], mu[:, 1:], s.bits, weights)
        gain = gains(uniform, final)
    final[degenerate], gain[degenerate], converged[degenerate] = 0.0, 1.0, True
    if s.fallback_uniform:
        low = gain < 1
        gain[low], final[low] = 1.0, uniform[low]
    return {
        "p0": mu[:, 0], "p1": mu[:, 1], "lo": lo[:, 0], "hi": hi[:, 0], "gain": gain, "uniform_loss": uniform,
        "loss": final, "iters": iters, "converged": converged, "degenerate": degenerate,
    }


def _parts(x: np.ndarray, ids: np.ndarray, m: int, perm: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Sub-vectors of rows, the number of each, and its key for noise."""
    sub = np.tile(np.arange(m), len(x))
    return split_rows(x, m, perm), sub, np.repeat(ids, m) * 64 + sub


def _ids(array: pa.Array) -> np.ndarray:
    return array.to_numpy(zero_copy_only=False).astype(np.int64)


def evolve(df: DataFrame, s: Search = Search(), mean: list[float] | None = None, id_column: str = "vec_id", vector: str = "embedding") -> DataFrame:
    """Fitted parameters of every (sub)vector: one row each, with the schema FIT.

    Rows are to be valid (see prep.validate_vectors). The plan has no exchange.
    """
    shift = None if mean is None else np.array(mean)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if not batch.num_rows:
                continue
            ids, x = _ids(column(batch, "id")), matrix(column(batch, "v"))
            x = x if shift is None else x - shift
            perm = make_permutation(x.shape[1], s.m, s.split_seed, s.split)
            parts, sub, keys = _parts(x, ids, s.m, perm)
            weights = None
            if s.weights is not None:
                weights = split_rows(np.tile(np.array(s.weights), (len(x), 1)), s.m, perm)
            found = evolve_rows(parts, keys, s, weights)
            columns = [pa.array(np.repeat(ids, s.m)), pa.array(sub.astype(np.int32)), *(pa.array(found[n]) for n in FIT.names[2:])]
            yield pa.RecordBatch.from_arrays(columns, names=FIT.names)

    source = df.select(F.col(id_column).cast("long").alias("id"), F.col(vector).alias("v"))
    return source.mapInArrow(run, FIT).withColumnRenamed("vec_id", id_column)


def trace(df: DataFrame, s: Search, runs: int = 1, mean: list[float] | None = None, vector: str = "embedding") -> DataFrame:
    """vec_id, run, iter, p0, p1, gain after every iteration of `runs` searches with other seeds."""
    shift = None if mean is None else np.array(mean)
    names = ["vec_id", "run", "iter", "p0", "p1", "gain"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if not batch.num_rows:
                continue
            ids, x = _ids(column(batch, "id")), matrix(column(batch, "v"))
            x = x if shift is None else x - shift
            of = _ids(column(batch, "run"))
            for r in np.unique(of):
                rows = np.flatnonzero(of == r)
                out: list[list[np.ndarray]] = []
                keep = lambda at, t, mu, g, rows=rows, out=out, r=r: out.append(
                    [ids[rows[at]], np.full(len(at), r), np.full(len(at), t), mu[:, 0], mu[:, 1], g]
                )
                evolve_rows(x[rows], ids[rows] * 64, replace(s, seed=s.seed + int(r)), trace=keep)
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c)) for c in zip(*out, strict=True)], names=names)

    source = df.select(F.col("vec_id").cast("long").alias("id"), F.col(vector).alias("v"))
    source = source.select("*", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(runs - 1).cast("long"))).alias("run"))
    return source.mapInArrow(run, "vec_id long, run long, iter long, p0 double, p1 double, gain double")


def grid_losses(curve: str, x: np.ndarray, bits: int, p0: np.ndarray, p1: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Gains and losses [rows, grid points] over a grid of parameters, as they are (no projection)."""
    lo, hi = bounds_of(x)
    uniform = curves.loss("unif", x, lo, hi, 0.0, 0.0, bits)
    out = np.empty((len(x), len(p0)))
    at_once = max(1, _TEMPORARY // max(1, x.size))
    for a in range(0, len(p0), at_once):
        q0, q1 = p0[a : a + at_once][None, :, None], p1[a : a + at_once][None, :, None]
        out[:, a : a + at_once] = curves.loss(curve, x[:, None, :], lo[:, None, :], hi[:, None, :], q0, q1, bits)
    return gains(uniform[:, None], out), out


def landscape(df: DataFrame, curve: str, bits: int, p0: list[float], p1: list[float], mean: list[float] | None = None, vector: str = "embedding") -> DataFrame:
    """vec_id, p0, p1, gain, loss at every point of a grid."""
    a, b = (v.ravel() for v in np.meshgrid(np.array(p0), np.array(p1), indexing="ij"))
    shift = None if mean is None else np.array(mean)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids = _ids(column(batch, "id"))
            x = matrix(column(batch, "v"))
            x = x if shift is None or not len(x) else x - shift
            for k in range(0, len(x), 64):
                gain, loss = grid_losses(curve, x[k : k + 64], bits, a, b)
                n = len(gain)
                yield pa.RecordBatch.from_arrays(
                    [pa.array(np.repeat(ids[k : k + 64], len(a))), pa.array(np.tile(a, n)), pa.array(np.tile(b, n)), pa.array(gain.ravel()), pa.array(loss.ravel())],
                    names=["vec_id", "p0", "p1", "gain", "loss"],
                )

    source = df.select(F.col("vec_id").cast("long").alias("id"), F.col(vector).alias("v"))
    return source.mapInArrow(run, "vec_id long, p0 double, p1 double, gain double, loss double")


def grid(df: DataFrame, curve: str, bits: int, p0: list[float], p1: list[float], mean: list[float] | None = None) -> DataFrame:
    """vec_id, p0, p1, gain of the best grid point of each vector; ties go to the smallest (p0, p1)."""
    a, b = (v.ravel() for v in np.meshgrid(np.array(sorted(p0)), np.array(sorted(p1)), indexing="ij"))
    shift = None if mean is None else np.array(mean)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            ids, x = _ids(column(batch, "id")), matrix(column(batch, "v"))
            x = x if shift is None or not len(x) else x - shift
            for k in range(0, len(x), 64):
                gain, _ = grid_losses(curve, x[k : k + 64], bits, a, b)
                best = gain.argmax(axis=1)
                top = gain[np.arange(len(gain)), best]
                yield pa.RecordBatch.from_arrays([pa.array(ids[k : k + 64]), pa.array(a[best]), pa.array(b[best]), pa.array(top)], names=["vec_id", "p0", "p1", "gain"])

    source = df.select(F.col("vec_id").cast("long").alias("id"), F.col("embedding").alias("v"))
    return source.mapInArrow(run, "vec_id long, p0 double, p1 double, gain double")


def global_losses(df: DataFrame, curve: str, bits: int, p0: list[float], p1: list[float], mean: list[float] | None = None) -> DataFrame:
    """p0, p1, total loss over the whole set: one shared parameter pair for all vectors."""
    a, b = (v.ravel() for v in np.meshgrid(np.array(p0), np.array(p1), indexing="ij"))
    shift = None if mean is None else np.array(mean)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(len(a))
        for batch in batches:
            x = matrix(column(batch, "v"))
            x = x if shift is None or not len(x) else x - shift
            for k in range(0, len(x), 64):
                total += grid_losses(curve, x[k : k + 64], bits, a, b)[1].sum(axis=0)
        yield pa.RecordBatch.from_arrays([pa.array(a), pa.array(b), pa.array(total)], names=["p0", "p1", "loss"])

    parts = df.select(F.col("embedding").alias("v")).mapInArrow(run, "p0 double, p1 double, loss double")
    return parts.groupBy("p0", "p1").agg(F.sum("loss").alias("loss"))


def best_curve(df: DataFrame, s: Search, names: tuple[str, ...] = curves.NAMES, mean: list[float] | None = None) -> DataFrame:
    """vec_id, curve, gain of each vector's best curve; ties go to the first by name. One scan, no exchange."""
    shift, ordered = None if mean is None else np.array(mean), sorted(names)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if not batch.num_rows:
                continue
            ids, x = _ids(column(batch, "id")), matrix(column(batch, "v"))
            x = x if shift is None else x - shift
            found = np.stack([evolve_rows(x, ids * 64, replace(s, curve=c, m=1))["gain"] for c in ordered])
            best = found.argmax(axis=0)
            yield pa.RecordBatch.from_arrays([pa.array(ids), pa.array([ordered[k] for k in best]), pa.array(found[best, np.arange(len(ids))])], names=["vec_id", "curve", "gain"])

    source = df.select(F.col("vec_id").cast("long").alias("id"), F.col("embedding").alias("v"))
    return source.mapInArrow(run, "vec_id long, curve string, gain double")


def straight_through(df: DataFrame, curve: str = "logi", bits: int = 8, steps: int = 60, rate: float = 0.05, mean: list[float] | None = None) -> DataFrame:
    """vec_id, p0, p1, gain of a gradient fit in which rounding passes gradients through.

    The derivative of the round trip by each parameter, at fixed codes, is taken by central
    differences; steps are scaled by the root of the mean square gradient.
    """
    shift = None if mean is None else np.array(mean)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if not batch.num_rows:
                continue
            ids, x = _ids(column(batch, "id")), matrix(column(batch, "v"))
            x = x if shift is None else x - shift
            lo, hi = bounds_of(x)
            theta = np.tile(np.array(curves.START[curve]), (len(x), 1))
            scale, best, best_gain = np.zeros_like(theta), theta.copy(), np.full(len(x), -1.0)
            uniform = curves.loss("unif", x, lo, hi, 0.0, 0.0, bits)
            for _ in range(steps):
                codes = curves.quantize(curve, x, lo, hi, theta[:, :1], theta[:, 1:], bits) / (2**bits - 1)
                error = curves.unbend(curve, codes, lo, hi, theta[:, :1], theta[:, 1:]) - x
                slope = np.empty_like(theta)
                for k in range(2):
                    move = np.zeros(2)
                    move[k] = 1e-4
                    up, down = theta + move, theta - move
                    span = curves.unbend(curve, codes, lo, hi, up[:, :1], up[:, 1:]) - curves.unbend(curve, codes, lo, hi, down[:, :1], down[:, 1:])
                    slope[:, k] = np.nan_to_num((2 * error * span / 2e-4).sum(axis=1))
                scale = 0.9 * scale + 0.1 * slope**2
                theta = theta - rate * np.abs(theta).clip(0.2) * slope / np.sqrt(scale + 1e-18)
                theta = np.column_stack(curves.project(curve, theta[:, 0], theta[:, 1], lo[:, 0], hi[:, 0]))
                gain = gains(uniform, curves.loss(curve, x, lo, hi, theta[:, :1], theta[:, 1:], bits))
                better = gain > best_gain
                best[better], best_gain[better] = theta[better], gain[better]
            yield pa.RecordBatch.from_arrays([pa.array(ids), pa.array(best[:, 0]), pa.array(best[:, 1]), pa.array(best_gain)], names=["vec_id", "p0", "p1", "gain"])

    source = df.select(F.col("vec_id").cast("long").alias("id"), F.col("embedding").alias("v"))
    return source.mapInArrow(run, "vec_id long, p0 double, p1 double, gain double")


def median_start(df: DataFrame, s: Search, fraction: float, mean: list[float] | None = None) -> Search:
    """The search with the median parameters of a hashed sample as its start: fewer iterations at scale."""
    from vecquant.operators.prep import sample

    fitted = evolve(sample(df, fraction, s.seed), s, mean)
    row = fitted.agg(F.percentile_approx("p0", 0.5).alias("a"), F.percentile_approx("p1", 0.5).alias("b")).first()
    return s if row.a is None else replace(s, mu=(row.a, row.b), sigma=tuple(v / 4 for v in curves.SPREAD[s.curve]))


LANDSCAPE = T.StructType([T.StructField(n, T.LongType() if n == "vec_id" else T.DoubleType()) for n in ("vec_id", "p0", "p1", "gain", "loss")])
