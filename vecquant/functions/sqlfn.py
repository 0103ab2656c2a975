"""SQL functions: encode, decode, dot, gain and traces for use from SQL text."""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from vecquant.functions import curves


def _alike(vectors: pd.Series, *options: pd.Series) -> Iterator[tuple[np.ndarray, tuple, np.ndarray]]:
    """Rows of equal length and options, the options, and the rows as one matrix; empty and null vectors are left out."""
    sizes = np.array([0 if v is None else len(v) for v in vectors])
    keys = list(zip(sizes.tolist(), *options, strict=True))
    places: dict[tuple, list[int]] = {}
    for i, k in enumerate(keys):
        if k[0]:
            places.setdefault(k, []).append(i)
    for k, rows in places.items():
        yield np.array(rows), k[1:], np.array(vectors.iloc[rows].tolist(), dtype=float).reshape(len(rows), -1)


def register(spark: SparkSession) -> None:
    """Register pcq_gain, pcq_codes, pcq_decode, pcq_dot, vec_avg and pcq_gain_summary (aggregates; the latter
    gives count, mean, least, most and share below 1), pcq_trace and pcq_landscape (table functions)."""
    from vecquant.operators.fit import Search, evolve_rows, grid_losses

    @F.pandas_udf("double")
    def pcq_gain(vectors: pd.Series, curve: pd.Series, bits: pd.Series) -> pd.Series:
        out = np.ones(len(vectors))
        for rows, (c, b), x in _alike(vectors, curve, bits):
            # Noise follows the vector's own bytes: the same gain wherever the row lies.
            keys = np.array([zlib.crc32(v.tobytes()) for v in x], dtype=np.int64)
            out[rows] = evolve_rows(x, keys, Search(curve=c, bits=int(b)))["gain"]
        return pd.Series(out)

    @F.pandas_udf("array<int>")
    def pcq_codes(vectors: pd.Series, curve: pd.Series, bits: pd.Series, p0: pd.Series, p1: pd.Series) -> pd.Series:
        out: list = [[]] * len(vectors)
        first, second = p0.to_numpy(dtype=float)[:, None], p1.to_numpy(dtype=float)[:, None]
        for rows, (c, b), x in _alike(vectors, curve, bits):
            lo, hi = x.min(axis=1, keepdims=True), x.max(axis=1, keepdims=True)
            for i, codes in zip(rows, curves.quantize(c, x, lo, hi, first[rows], second[rows], int(b)).astype(int).tolist(), strict=True):
                out[i] = codes
        return pd.Series(out)

    @F.pandas_udf("array<double>")
    def pcq_decode(codes: pd.Series, curve: pd.Series, bits: pd.Series, p0: pd.Series, p1: pd.Series, lo: pd.Series, hi: pd.Series) -> pd.Series:
        out: list = [[]] * len(codes)
        params = [p.to_numpy(dtype=float)[:, None] for p in (lo, hi, p0, p1)]
        for rows, (c, b), y in _alike(codes, curve, bits):
            for i, values in zip(rows, curves.unbend(c, y / (2 ** int(b) - 1), *(p[rows] for p in params)).tolist(), strict=True):
                out[i] = values
        return pd.Series(out)

    @F.pandas_udf("double")
    def pcq_dot(a: pd.Series, b: pd.Series) -> pd.Series:
        out = np.zeros(len(a))
        for rows, _, x in _alike(a):
            out[rows] = np.einsum("nd,nd->n", x, np.array(b.iloc[rows].tolist(), dtype=float).reshape(len(rows), -1))
        return pd.Series(out)

    @F.pandas_udf("array<double>")
    def vec_avg(vectors: pd.Series) -> list[float]:
        return np.mean(np.stack(vectors.to_numpy()).astype(float), axis=0).tolist() if len(vectors) else []

    @F.pandas_udf("array<double>")
    def pcq_gain_summary(gains: pd.Series) -> list:
        g = gains.dropna().to_numpy(dtype=float)
        return [float(len(g)), *((float(g.mean()), float(g.min()), float(g.max()), float((g < 1).mean())) if len(g) else ())]

    for f in (pcq_gain, pcq_codes, pcq_decode, pcq_dot):
        spark.udf.register(f.__name__, f)
    for f in (vec_avg, pcq_gain_summary):
        spark.udf.register(f.__name__, f)

    @F.udtf(returnType="iter int, p0 double, p1 double, gain double")
    class PcqTrace:
        """The search of one vector, a row an iteration."""

        def eval(self, vector: list, curve: str, bits: int, seed: int) -> Iterator[tuple]:
            rows: list[tuple] = []
            keep = lambda at, t, mu, g: rows.append((t, float(mu[0, 0]), float(mu[0, 1]), float(g[0])))
            evolve_rows(np.array([vector], dtype=float), np.zeros(1, np.int64), Search(curve=curve, bits=bits, seed=seed), trace=keep)
            yield from rows

    spark.udtf.register("pcq_trace", PcqTrace)

    @F.udtf(returnType="p0 double, p1 double, gain double")
    class PcqLandscape:
        """The objective of one vector on an even grid of n by n parameters."""

        def eval(self, vector: list, curve: str, bits: int, low0: float, high0: float, low1: float, high1: float, n: int) -> Iterator[tuple]:
            a, b = (v.ravel() for v in np.meshgrid(np.linspace(float(low0), float(high0), n), np.linspace(float(low1), float(high1), n), indexing="ij"))
            gain, _ = grid_losses(curve, np.array([vector], dtype=float), bits, a, b)
            yield from zip(a.tolist(), b.tolist(), gain[0].tolist(), strict=True)

    spark.udtf.register("pcq_landscape", PcqLandscape)


def register_views(spark: SparkSession, frames: dict[str, DataFrame]) -> None:
    for name, df in frames.items():
        df.createOrReplaceTempView(name)
