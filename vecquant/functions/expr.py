"""The curves, the quantizer and its losses as Spark columns: scalar and array forms."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column
from pyspark.sql import functions as F

Value = Column | float


def _col(v: Value) -> Column:
    return v if isinstance(v, Column) else F.lit(float(v))


def bind(value: Column, body: Callable[[Column], Column]) -> Column:
    """body(value) with the value worked out once, however often the body names it."""
    return F.transform(F.array(value), body)[0]


def logistic(x: Column, alpha: Value, x0: Value) -> Column:
    return 1 / (1 + F.exp(-_col(alpha) * (x - _col(x0))))


def logit(y: Column, alpha: Value, x0: Value) -> Column:
    return F.log(y / (1 - y)) / _col(alpha) + _col(x0)


def logistic2(x: Column, alpha: Value, x0: Value) -> Column:
    return 1 / (1 + F.pow(F.lit(2.0), -_col(alpha) * (x - _col(x0))))


def logit2(y: Column, alpha: Value, x0: Value) -> Column:
    return F.log2(y / (1 - y)) / _col(alpha) + _col(x0)


def pwl_log2(z: Column) -> Column:
    """Mantissa and exponent by log2, put right where log2 rounds across a power of two."""

    def with_exponent(z: Column, p: Column) -> Column:
        m = z / F.pow(F.lit(2.0), p)
        return F.when(m >= 1, 2 * (m / 2 - 1) + p + 1).when(m < 0.5, 2 * (m * 2 - 1) + p - 1).otherwise(2 * (m - 1) + p)

    return bind(z, lambda v: bind(F.floor(F.log2(v)) + 1, lambda p: with_exponent(v, p)))


def pwl_exp2(v: Column) -> Column:
    return bind(v, lambda u: bind(F.floor(u + 1), lambda p: ((u - p) / 2 + 1) * F.pow(F.lit(2.0), p)))


def pwl_logistic(x: Column, alpha: Value, x0: Value) -> Column:
    return bind(pwl_exp2(_col(alpha) * (x - _col(x0))), lambda z: z / (z + 1))


def pwl_logit(y: Column, alpha: Value, x0: Value) -> Column:
    return pwl_log2(y / (1 - y)) / _col(alpha) + _col(x0)


def kumaraswamy(x: Column, a: Value, b: Value) -> Column:
    return 1 - F.pow(1 - F.pow(x, _col(a)), _col(b))


def kumaraswamy_inverse(y: Column, a: Value, b: Value) -> Column:
    return F.pow(1 - F.pow(1 - y, 1 / _col(b)), 1 / _col(a))


_RAW: dict[str, tuple[Callable, Callable]] = {
    "logi": (logistic, logit),
    "logi2": (logistic2, logit2),
    "pwl": (pwl_logistic, pwl_logit),
}


def bend(curve: str, x: Column, lo: Column, hi: Column, p0: Value = 1.0, p1: Value = 1.0) -> Column:
    """Value in [lo, hi] to [0, 1]; 0 for a constant vector."""
    width = hi - lo
    if curve == "unif":
        bent = (x - lo) / width
    elif curve == "kuma":
        bent = kumaraswamy((x - lo) / width, p0, p1)
    else:
        raw = _RAW[curve][0]
        low, high = raw(lo / width, p0, p1), raw(hi / width, p0, p1)
        bent = bind(low, lambda a: (raw(x / width, p0, p1) - a) / (high - a))
    return F.when(width > 0, bent).otherwise(0.0)


def unbend(curve: str, y: Column, lo: Column, hi: Column, p0: Value = 1.0, p1: Value = 1.0) -> Column:
    width = hi - lo
    if curve == "unif":
        value = lo + y * width
    elif curve == "kuma":
        value = lo + kumaraswamy_inverse(y, p0, p1) * width
    else:
        raw, inverse = _RAW[curve]
        low, high = raw(lo / width, p0, p1), raw(hi / width, p0, p1)
        value = width * inverse(bind(low, lambda a: (high - a) * y + a), p0, p1)
    return F.when(width > 0, value).otherwise(lo)


def quantize(curve: str, x: Column, lo: Column, hi: Column, p0: Value = 1.0, p1: Value = 1.0, bits: int = 8) -> Column:
    """Code of one value."""
    top = 2**bits - 1
    code = F.floor(top * bend(curve, x, lo, hi, p0, p1) + 0.5)
    return F.greatest(F.least(code, F.lit(top)), F.lit(0)).cast("int")


def dequantize(curve: str, code: Column, lo: Column, hi: Column, p0: Value = 1.0, p1: Value = 1.0, bits: int = 8) -> Column:
    return unbend(curve, code / (2**bits - 1), lo, hi, p0, p1)


def quantize_array(curve: str, values: Column, p0: Value = 1.0, p1: Value = 1.0, bits: int = 8) -> Column:
    """Codes of a whole array by its own bounds."""
    lo, hi = F.array_min(values), F.array_max(values)
    return F.transform(values, lambda x: quantize(curve, x, lo, hi, p0, p1, bits))


def dequantize_array(curve: str, codes: Column, lo: Column, hi: Column, p0: Value = 1.0, p1: Value = 1.0, bits: int = 8) -> Column:
    return F.transform(codes, lambda c: dequantize(curve, c, lo, hi, p0, p1, bits))


def dot(a: Column, b: Column) -> Column:
    """Dot product of two arrays, summed in order."""
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, v: s + v)


def squared_distance(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: F.pow(x.cast("double") - y.cast("double"), 2)), F.lit(0.0), lambda s, v: s + v)


def norm(a: Column) -> Column:
    return F.sqrt(dot(a, a))


def cosine(a: Column, b: Column) -> Column:
    return dot(a, b) / (norm(a) * norm(b))
