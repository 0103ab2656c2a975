"""Joins, set operations and aggregates around vectors, codes and results."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def fetch(candidates: DataFrame, store: DataFrame, broadcast_rows: int = 1_000_000) -> DataFrame:
    """Store rows of the candidates. The candidates are broadcast only if a limited count shows they are few."""
    wanted = candidates.select("vec_id").distinct()
    few = wanted.limit(broadcast_rows + 1).count() <= broadcast_rows
    return store.join(F.broadcast(wanted) if few else wanted, "vec_id", "left_semi")


def pair(left: DataFrame, right: DataFrame, on: str = "vec_id", strategy: str = "merge") -> DataFrame:
    """Equi-join by a named strategy: merge, hash (shuffled) or auto."""
    hint = {"merge": "merge", "hash": "shuffle_hash", "auto": None}[strategy]
    return left.join(right.hint(hint) if hint else right, on)


def only_in(left: DataFrame, right: DataFrame, on: str = "vec_id") -> DataFrame:
    return left.join(right, on, "left_semi")


def not_in(left: DataFrame, right: DataFrame, on: str = "vec_id") -> DataFrame:
    return left.join(right, on, "left_anti")


def missing(left: DataFrame, right: DataFrame, on: str = "vec_id") -> DataFrame:
    """Keys that one side lacks, and which."""
    both = left.select(on, F.lit(1).alias("l")).join(right.select(on, F.lit(1).alias("r")), on, "full_outer")
    return both.where("l is null or r is null").select(on, F.when(F.col("l").isNull(), "left").otherwise("right").alias("missing_in"))


def interval(left: DataFrame, right: DataFrame, seconds: int, on: str, time: str = "ts") -> DataFrame:
    """Pairs of one key whose times are at most this many seconds apart.

    Time buckets of that width join with their neighbours, so that no key's rows all meet.
    """
    bucket = F.floor(F.unix_timestamp(time) / seconds)
    a = left.withColumn("_b", bucket)
    b = right.withColumn("_b", F.explode(F.array(bucket - 1, bucket, bucket + 1)))
    joined = a.alias("a").join(b.alias("b"), (F.col(f"a.{on}") == F.col(f"b.{on}")) & (F.col("a._b") == F.col("b._b")))
    near = F.abs(F.unix_timestamp(f"a.{time}") - F.unix_timestamp(f"b.{time}")) <= seconds
    return joined.where(near)


def as_of(left: DataFrame, right: DataFrame, time: str, columns: list[str], on: list[str], seconds: int = 86_400) -> DataFrame:
    """Each left row with the values of the latest right row of its key at or before its time.

    Rows meet by key and span of time, so that a key with very many rows is no single task. What
    held before a span comes from one row a key and span.
    """
    span = F.floor(F.unix_timestamp(time) / seconds)
    latest = right.withColumn("_span", span).groupBy(*on, "_span").agg(F.max_by(F.struct(*columns), F.col(time)).alias("_last"))
    spans = left.select(*on, span.alias("_span")).distinct().join(latest, [*on, "_span"], "full_outer")
    before = Window.partitionBy(*on).orderBy("_span").rowsBetween(Window.unboundedPreceding, -1)
    held = spans.select(*on, "_span", F.last("_last", ignorenulls=True).over(before).alias("_held"))
    own = _as_of_within(left.withColumn("_span", span), right.withColumn("_span", span), time, columns, [*on, "_span"])
    rows = own.join(held, [*on, "_span"], "left")
    return rows.select(*left.columns, *[F.coalesce(F.col(f"_found.{c}"), F.when(F.col("_found").isNull(), F.col(f"_held.{c}"))).alias(c) for c in columns])


def _as_of_within(left: DataFrame, right: DataFrame, time: str, columns: list[str], on: list[str]) -> DataFrame:
    """Left rows with _found: the latest right row's values within the same key, or null."""
    wide = left.select(*left.columns, *[F.lit(None).cast(right.schema[c].dataType).alias(c) for c in columns], F.lit(1).alias("_side"))
    blanks = [F.lit(None).cast(left.schema[c].dataType).alias(c) for c in left.columns if c not in (time, *on)]
    other = right.select(time, *on, *blanks, *columns, F.lit(0).alias("_side"))
    both = wide.unionByName(other)
    order = Window.partitionBy(*on).orderBy(time, "_side").rowsBetween(Window.unboundedPreceding, 0)
    filled = [F.last(F.when(F.col("_side") == 0, F.struct(*columns)), ignorenulls=True).over(order).alias("_found")]
    return both.select(*left.columns, "_side", *filled).where("_side = 1").drop("_side")


def level_lookup(values: DataFrame, levels: DataFrame, most: int = 65_536) -> DataFrame:
    """Rows (value) joined to the level (code, low, high) whose interval holds them; levels are counted first."""
    if levels.limit(most + 1).count() > most:
        raise ValueError(f"over {most} levels: join by ranges of them")
    return values.join(F.broadcast(levels), (F.col("value") >= F.col("low")) & (F.col("value") < F.col("high")))


def topk_per_key(df: DataFrame, key: str, order: list, k: int, how: str = "row_number") -> DataFrame:  # noqa: ANN001
    own = Window.partitionBy(key).orderBy(*order)
    rank = {"row_number": F.row_number, "rank": F.rank, "dense_rank": F.dense_rank}[how]().over(own)
    return df.withColumn("rank", rank).where(F.col("rank") <= k)


def levels_used(codes: DataFrame) -> DataFrame:
    """vec_id, exact and approximate numbers of distinct codes. codes: vec_id, code."""
    return codes.groupBy("vec_id").agg(F.count_distinct("code").alias("levels"), F.approx_count_distinct("code").alias("approx_levels"))


def code_entropy(codes: DataFrame, *by: str) -> DataFrame:
    """Bits a code of its empirical distribution."""
    counts = codes.groupBy(*by, "code").agg(F.count("*").alias("n"))
    total = counts.groupBy(*by).agg(F.sum("n").alias("total"))
    joined = counts.join(total, list(by)) if by else counts.crossJoin(F.broadcast(total))
    share = F.col("n") / F.col("total")
    return joined.groupBy(*by).agg((-F.sum(share * F.log2(share))).alias("entropy"))


def gain_cube(fits: DataFrame, *by: str, how: str = "cube") -> DataFrame:
    """Counts and mean gains over all groupings of the columns; how: cube or rollup."""
    return getattr(fits, how)(*by).agg(F.count("*").alias("n"), F.avg("gain").alias("mean_gain"))


def common(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.select("query_id", "vec_id").intersect(b.select("query_id", "vec_id"))


def only_first(a: DataFrame, b: DataFrame) -> DataFrame:
    return a.select("query_id", "vec_id").exceptAll(b.select("query_id", "vec_id"))


def quantiles(df: DataFrame, value: str, shares: list[float], *by: str, how: str = "exact") -> DataFrame:
    """Quantiles of a column per group: exact, approximate (bounded error), or from a mergeable sketch."""
    if how == "exact":
        found = F.percentile(value, F.array(*map(F.lit, shares)))
    elif how == "approx":
        found = F.percentile_approx(value, shares, 10_000)
    elif how == "sketch":
        grouped = df.groupBy(*by).agg(F.expr(f"kll_sketch_agg_double(CAST({value} AS DOUBLE))").alias("s"))
        picked = F.array(*[F.expr(f"kll_sketch_get_quantile_double(s, CAST({p} AS DOUBLE))") for p in shares])
        return grouped.select(*by, picked.alias("quantiles"))
    else:
        raise ValueError(how)
    return df.groupBy(*by).agg(found.alias("quantiles"))


def code_map(codes: DataFrame) -> DataFrame:
    """vec_id and a map from each used code to its count. A vector has at most 2**bits entries."""
    counts = codes.groupBy("vec_id", "code").agg(F.count("*").alias("n"))
    return counts.groupBy("vec_id").agg(F.map_from_entries(F.sort_array(F.collect_list(F.struct("code", "n")))).alias("codes"))


def rank_bands(df: DataFrame, key: str, order: list, bands: int) -> DataFrame:  # noqa: ANN001
    """Each row's band of equal size and its share of lower rows, within its key."""
    own = Window.partitionBy(key).orderBy(*order)
    return df.withColumns({"band": F.ntile(bands).over(own), "share_below": F.percent_rank().over(own)})
