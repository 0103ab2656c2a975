"""Explicit schemas and shared constants."""

from __future__ import annotations

from pyspark.sql import types as T

#: Payload parameters of a (sub)vector, bytes of each, and the cap of a gain whose loss is zero.
PAYLOAD_PARAMS, PARAM_BYTES, GAIN_CAP = 4, 4, 1e6

RAW = T.StructType(
    [
        T.StructField("vec_id", T.LongType(), False),
        T.StructField("embedding", T.ArrayType(T.FloatType())),
        T.StructField("label", T.IntegerType()),
    ]
)
PARAMS = T.ArrayType(T.StructType([T.StructField(n, T.FloatType()) for n in ("p0", "p1", "lo", "hi")]))
FIT = T.StructType(
    [
        T.StructField("vec_id", T.LongType()),
        T.StructField("sub", T.IntegerType()),
        T.StructField("p0", T.DoubleType()),
        T.StructField("p1", T.DoubleType()),
        T.StructField("lo", T.DoubleType()),
        T.StructField("hi", T.DoubleType()),
        T.StructField("gain", T.DoubleType()),
        T.StructField("uniform_loss", T.DoubleType()),
        T.StructField("loss", T.DoubleType()),
        T.StructField("iters", T.IntegerType()),
        T.StructField("converged", T.BooleanType()),
        T.StructField("degenerate", T.BooleanType()),
    ]
)
CODED = T.StructType(
    [
        T.StructField("vec_id", T.LongType()),
        T.StructField("curve", T.StringType()),
        T.StructField("bits", T.IntegerType()),
        T.StructField("m", T.IntegerType()),
        T.StructField("codes", T.BinaryType()),
        T.StructField("params", PARAMS),
        T.StructField("gain", T.DoubleType()),
        T.StructField("iters", T.IntegerType()),
        T.StructField("converged", T.BooleanType()),
        T.StructField("degenerate", T.BooleanType()),
    ]
)
