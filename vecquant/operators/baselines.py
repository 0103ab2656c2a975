"""What the per-vector curves are compared with."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from vecquant.operators.measures import doubles, loss_of


def uniform(df: DataFrame, bits: int = 8, m: int = 1) -> DataFrame:
    """vec_id, loss of uniform codes; m contiguous sub-vectors have bounds of their own. No exchange."""
    width = (F.size("v") / m).cast("int")
    parts = F.transform(F.sequence(F.lit(0), F.lit(m - 1)), lambda j: F.slice("v", j * width + 1, width))

    def of_part(part: Column) -> Column:
        return loss_of(part, F.array_min(part), F.array_max(part), "unif", bits=bits)

    rows = df.select("vec_id", doubles().alias("v"))
    return rows.select("vec_id", F.aggregate(parts, F.lit(0.0), lambda total, part: total + of_part(part)).alias("loss"))


def set_bounds(df: DataFrame) -> tuple[float, float]:
    """Least and largest value of the whole set."""
    ends = df.agg(F.min(F.array_min("embedding")).cast("double").alias("lo"), F.max(F.array_max("embedding")).cast("double").alias("hi")).first()
    return ends.lo or 0.0, ends.hi or 0.0


def uniform_global(df: DataFrame, bits: int = 8) -> DataFrame:
    """vec_id, loss of uniform codes between the bounds of the whole set."""
    lo, hi = set_bounds(df)
    rows = df.select("vec_id", doubles().alias("v"))
    return rows.select("vec_id", loss_of(F.col("v"), F.lit(lo), F.lit(hi), "unif", bits=bits).alias("loss"))


def _level(ranked: Column, share: Column) -> Column:
    """The value at a share of a sorted array, between two neighbours in proportion."""
    at = share * (F.size(ranked) - 1)
    low = F.floor(at).cast("int")
    left = F.element_at(ranked, low + 1)
    right = F.element_at(ranked, F.least(low + 2, F.size(ranked)))
    return left + (at - low) * (right - left)


def cdf_levels(df: DataFrame, bits: int = 4) -> DataFrame:
    """vec_id, v, levels: 2**bits values at evenly spaced shares of each vector's own distribution."""
    top = 2**bits - 1
    rows = df.select("vec_id", doubles().alias("v")).withColumn("ranked", F.sort_array("v"))
    return rows.select("vec_id", "v", F.transform(F.sequence(F.lit(0), F.lit(top)), lambda k: _level(F.col("ranked"), k / top)).alias("levels"))


def set_cdf_levels(df: DataFrame, bits: int = 4) -> list[float]:
    """2**bits values at evenly spaced shares of all values of the set, within a millionth of the share."""
    top = 2**bits - 1
    values = df.select(F.explode(doubles()).alias("value"))
    return values.agg(F.percentile_approx("value", [k / top for k in range(top + 1)], 1_000_000).alias("levels")).first().levels or []


def _nearest(x: Column, levels: Column) -> Column:
    return F.array_min(F.transform(levels, lambda v: F.abs(x - v)))


def cdf(df: DataFrame, bits: int = 4, scope: str = "vector") -> DataFrame:
    """vec_id, loss where every value goes to the nearest equal-mass level, of its vector or of the whole set."""
    rows = cdf_levels(df, bits) if scope == "vector" else df.select("vec_id", doubles().alias("v"), F.array(*map(F.lit, set_cdf_levels(df, bits))).alias("levels"))
    return rows.select("vec_id", F.aggregate("v", F.lit(0.0), lambda total, x: total + F.pow(_nearest(x, F.col("levels")), 2)).alias("loss"))


def cdf_codes(df: DataFrame, bits: int = 4) -> DataFrame:
    """vec_id, codes, levels: each value's place among its vector's equal-mass levels, the first of equally near ones."""
    near = lambda x: F.array_position(F.transform("levels", lambda v: F.abs(x - v)), _nearest(x, F.col("levels"))) - 1
    return cdf_levels(df, bits).select("vec_id", F.transform("v", lambda x: near(x).cast("int")).alias("codes"), "levels")


def lossless_bytes(df: DataFrame) -> DataFrame:
    """vec_id, bytes of a table of distinct values with an index a value, against 4 bytes a value."""
    n, distinct = F.size("embedding"), F.size(F.array_distinct("embedding"))
    index_bits = F.ceil(F.log2(F.greatest(distinct, F.lit(2)).cast("double")))
    return df.select("vec_id", (4 * distinct + F.ceil(n * index_bits / 8)).cast("long").alias("lossless"), (4 * n).cast("long").alias("fp32"))


def level_entropy(codes: Column | str = "code") -> Column:
    """Bits a code from counts n of one group and total: a sum over its rows."""
    share = F.col("n") / F.col("total")
    return -F.sum(share * F.log2(share))
