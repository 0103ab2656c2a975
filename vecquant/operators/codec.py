"""Coded vectors: packed integers with a few float parameters per (sub)vector."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import replace

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from vecquant.functions import curves
from vecquant.operators.fit import Search, bounds_of, evolve_rows, gains
from vecquant.operators.prep import column, lists, make_permutation, matrix, split_rows, unsplit_rows
from vecquant.schema import CODED


def pack(codes: np.ndarray, bits: int) -> list[bytes]:
    """Codes of each row as bytes: one a value for 8 bits, two values a byte (the first high) for 4."""
    raw = codes.astype(np.uint8)
    if bits == 4:
        if raw.shape[1] % 2:
            raw = np.column_stack([raw, np.zeros(len(raw), dtype=np.uint8)])
        raw = (raw[:, ::2] << 4) | raw[:, 1::2]
    elif bits != 8:
        raise ValueError("codes have 4 or 8 bits")
    return [row.tobytes() for row in raw]


def unpack(blobs: list[bytes], bits: int, d: int) -> np.ndarray:
    """The inverse of pack, for d values a row."""
    raw = np.frombuffer(b"".join(blobs), dtype=np.uint8).reshape(len(blobs), -1)
    if bits == 4:
        raw = np.stack([raw >> 4, raw & 15], axis=2).reshape(len(raw), -1)
    return raw[:, :d]


def encode_rows(x: np.ndarray, ids: np.ndarray, s: Search, perm: np.ndarray) -> dict[str, object]:
    """Codes and payload of rows. Parameters are cut to float32 first, as decoding sees them."""
    parts = split_rows(x, s.m, perm)
    keys = np.repeat(ids, s.m) * 64 + np.tile(np.arange(s.m), len(x))
    if s.curve == "unif":
        lo, hi = bounds_of(parts, s.clip_quantile)
        n = len(parts)
        fitted = {"p0": np.zeros(n), "p1": np.zeros(n), "lo": lo[:, 0], "hi": hi[:, 0], "iters": np.zeros(n, dtype=np.int32), "converged": np.ones(n, dtype=bool), "degenerate": (hi <= lo)[:, 0]}
    else:
        fitted = evolve_rows(parts, keys, s)
    p0, p1, lo, hi = (fitted[n].astype(np.float32).astype(np.float64)[:, None] for n in ("p0", "p1", "lo", "hi"))
    with np.errstate(all="ignore"):
        codes = np.nan_to_num(curves.quantize(s.curve, np.clip(parts, lo, hi), lo, hi, p0, p1, s.bits))
        decoded = curves.unbend(s.curve, codes / (2**s.bits - 1), lo, hi, p0, p1)
    loss = ((parts - decoded) ** 2).sum(axis=1)
    exact_lo, exact_hi = bounds_of(parts, s.clip_quantile)
    uniform = curves.loss("unif", parts, exact_lo, exact_hi, 0.0, 0.0, s.bits)
    gain = gains(uniform.reshape(-1, s.m).sum(axis=1), loss.reshape(-1, s.m).sum(axis=1))
    degenerate = fitted["degenerate"].reshape(-1, s.m).all(axis=1)
    gain[degenerate] = 1.0
    return {
        "codes": codes.reshape(len(x), -1),
        "params": np.concatenate([p0, p1, lo, hi], axis=1).reshape(len(x), s.m, 4),
        "gain": gain,
        "iters": fitted["iters"].reshape(-1, s.m).max(axis=1),
        "converged": fitted["converged"].reshape(-1, s.m).all(axis=1),
        "degenerate": degenerate,
    }


def _params(values: np.ndarray) -> pa.Array:
    n, m, _ = values.shape
    flat = values.reshape(n * m, 4).astype(np.float32)
    structs = pa.StructArray.from_arrays([pa.array(flat[:, k]) for k in range(4)], names=["p0", "p1", "lo", "hi"])
    return pa.ListArray.from_arrays(np.arange(n + 1, dtype=np.int32) * m, structs)


def encode(df: DataFrame, s: Search = Search(), mean: list[float] | None = None, vector: str = "embedding") -> DataFrame:
    """Fit and code every vector: rows of the schema CODED. Narrow, without an exchange."""
    shift = None if mean is None else np.array(mean)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if not batch.num_rows:
                continue
            ids = column(batch, "vec_id").to_numpy(zero_copy_only=False).astype(np.int64)
            x = matrix(column(batch, "v"))
            x = x if shift is None else x - shift
            made = encode_rows(x, ids, s, make_permutation(x.shape[1], s.m, s.split_seed, s.split))
            n = len(x)
            columns = [
                pa.array(ids), pa.array([s.curve] * n), pa.array(np.full(n, s.bits, np.int32)), pa.array(np.full(n, s.m, np.int32)),
                pa.array(pack(made["codes"], s.bits), pa.binary()), _params(made["params"]), pa.array(made["gain"]),
                pa.array(made["iters"].astype(np.int32)), pa.array(made["converged"]), pa.array(made["degenerate"]),
            ]
            yield pa.RecordBatch.from_arrays(columns, names=CODED.names)

    return df.select(F.col("vec_id").cast("long").alias("vec_id"), F.col(vector).alias("v")).mapInArrow(run, CODED)


def decode_rows(blobs: list[bytes], params: np.ndarray, curve: str, bits: int, d: int, perm: np.ndarray) -> np.ndarray:
    """Vectors of coded rows; params is [rows, m, 4].

    A sub-vector has 2**bits levels, so the curve is inverted once a level where that is fewer
    than its values.
    """
    n, m, _ = params.shape
    codes = unpack(blobs, bits, d).reshape(n * m, -1)
    p0, p1, lo, hi = (params.reshape(n * m, 4)[:, k : k + 1] for k in range(4))
    levels = 2**bits
    if codes.shape[1] > levels:
        table = curves.unbend(curve, np.arange(levels)[None, :] / (levels - 1), lo, hi, p0, p1)
        parts = np.take_along_axis(table, codes.astype(np.int64), axis=1)
    else:
        parts = curves.unbend(curve, codes / (levels - 1), lo, hi, p0, p1)
    return unsplit_rows(parts, m, perm)


def params_matrix(array: pa.Array) -> np.ndarray:
    """The params column as [rows, m, 4] doubles."""
    if isinstance(array, pa.ChunkedArray):
        array = array.combine_chunks()
    flat = array.flatten()
    values = np.column_stack([flat.field(k).to_numpy(zero_copy_only=False) for k in range(4)]).astype(np.float64)
    return values.reshape(len(array), -1, 4)


def decode_batch(batch: pa.RecordBatch, s: Search, d: int, shift: np.ndarray | None) -> np.ndarray:
    perm = make_permutation(d, s.m, s.split_seed, s.split)
    x = decode_rows(column(batch, "codes").to_pylist(), params_matrix(column(batch, "params")), s.curve, s.bits, d, perm)
    return x if shift is None else x + shift


def decode(coded: DataFrame, s: Search, d: int, mean: list[float] | None = None) -> DataFrame:
    """vec_id and embedding (doubles) of coded rows; with the mean, not centered any more."""
    shift = None if mean is None else np.array(mean)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if batch.num_rows:
                x = decode_batch(batch, s, d, shift)
                yield pa.RecordBatch.from_arrays([column(batch, "vec_id"), lists(x, pa.float64())], names=["vec_id", "embedding"])

    return coded.select("vec_id", "codes", "params").mapInArrow(run, "vec_id long, embedding array<double>")


def reconstruct(df: DataFrame, s: Search = Search(), mean: list[float] | None = None, d: int | None = None) -> DataFrame:
    """vec_id and the round trip of every vector."""
    from vecquant.operators.prep import vector_length

    return decode(encode(df, s, mean), s, d or vector_length(df), mean)


def pack4_hex(codes: Column) -> Column:
    """Codes of 4 bits as hexadecimal text, in columns: a digit a value."""
    return F.array_join(F.transform(codes, lambda c: F.lower(F.hex(c.cast("long")))), "")


def encode_mixed(df: DataFrame, s: Search, bits: list[int], mean: list[float] | None = None) -> DataFrame:
    """vec_id, sub, bits, gain, loss with a bit width of its own for each sub-vector.

    One scan; every sub-vector is fitted once, at its own width.
    """
    shift, m, widths = None if mean is None else np.array(mean), len(bits), np.array(bits)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if not batch.num_rows:
                continue
            ids, x = column(batch, "vec_id").to_numpy(zero_copy_only=False).astype(np.int64), matrix(column(batch, "v"))
            x = x if shift is None else x - shift
            parts = split_rows(x, m, make_permutation(x.shape[1], m, s.split_seed, s.split))
            sub = np.tile(np.arange(m), len(x))
            keys, own = np.repeat(ids, m) * 64 + sub, widths[sub]
            gain, loss = np.empty(len(parts)), np.empty(len(parts))
            for b in sorted(set(bits)):
                rows = np.flatnonzero(own == b)
                found = evolve_rows(parts[rows], keys[rows], replace(s, m=m, bits=b))
                gain[rows], loss[rows] = found["gain"], found["loss"]
            columns = [np.repeat(ids, m), sub.astype(np.int32), own.astype(np.int32), gain, loss]
            yield pa.RecordBatch.from_arrays([pa.array(c) for c in columns], names=["vec_id", "sub", "bits", "gain", "loss"])

    source = df.select(F.col("vec_id").cast("long").alias("vec_id"), F.col("embedding").alias("v"))
    return source.mapInArrow(run, "vec_id long, sub int, bits int, gain double, loss double")
