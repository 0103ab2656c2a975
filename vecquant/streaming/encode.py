"""Insert-time encoding and drift reports on streams."""

from __future__ import annotations

import math
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from vecquant.operators import codec
from vecquant.operators.fit import Search
from vecquant.operators.relational import as_of


def encode_stream(stream: DataFrame, s: Search, mean: list[float] | None = None) -> DataFrame:
    """Coded rows of a stream of vectors: the batch operator, which keeps no state. The mean is frozen per store."""
    return codec.encode(stream, s, mean)


def gain_windows(df: DataFrame, kind: str = "tumbling", size: str = "1 hour", slide: str = "30 minutes", late: str = "10 minutes", time: str = "ts", value: str = "gain", keys: tuple[str, ...] = ()) -> DataFrame:
    """Counts and means of a value by tumbling, sliding or session windows; batch and streams alike."""
    window = {"tumbling": lambda: F.window(time, size), "sliding": lambda: F.window(time, size, slide), "session": lambda: F.session_window(time, size)}[kind]()
    source = _marked(df, time, late) if df.isStreaming else df
    rows = source.groupBy(*keys, window.alias("w")).agg(F.count("*").alias("n"), F.avg(value).alias("mean"))
    return rows.select(*keys, F.col("w.start").alias("start"), F.col("w.end").alias("end"), "n", "mean")


def dedup(stream: DataFrame, key: str = "vec_id", time: str = "ts", late: str = "1 hour") -> DataFrame:
    """One row a key within the watermark."""
    if not stream.isStreaming:
        return stream.dropDuplicates([key])
    return _marked(stream, time, late).dropDuplicatesWithinWatermark([key])


def _marked(stream: DataFrame, time: str, late: str) -> DataFrame:
    """Watermarks need times with a zone; times without one are taken in the session's."""
    return stream.withColumn(time, F.col(time).cast("timestamp")).withWatermark(time, late)


def late_rows(df: DataFrame, seconds: int, order: str, time: str = "ts", ranges: int = 512) -> DataFrame:
    """Rows that come more than `seconds` behind the latest time before them, in arrival order.

    The latest time so far is a running maximum over ranges of the order column, cut at its
    quantiles so that each has about as many rows, however the numbers lie. Each range has a
    maximum of its own, and the at most `ranges` maxima are run over once.
    """
    shares = [k / ranges for k in range(1, ranges)]
    cuts = sorted(set(df.approxQuantile(order, shares, 0.5 / ranges))) if shares else []
    rows = df.withColumn("_range", F.expr(_range_of(order, cuts, 0)))
    tops = rows.groupBy("_range").agg(F.max(time).alias("_top"))
    before = tops.select("_range", F.max("_top").over(Window.orderBy("_range").rowsBetween(Window.unboundedPreceding, -1)).alias("_before"))
    own = Window.partitionBy("_range").orderBy(order).rowsBetween(Window.unboundedPreceding, -1)
    joined = rows.join(F.broadcast(before), "_range").withColumn("_latest", F.greatest("_before", F.max(time).over(own)))
    behind = F.unix_timestamp("_latest") - F.unix_timestamp(time)
    return joined.where(behind > seconds).drop("_range", "_before", "_latest")


def _range_of(order: str, cuts: list[float], first: int) -> str:
    """How many cuts lie at or below the value, by halving."""
    if not cuts:
        return str(first)
    k = len(cuts) // 2
    return f"IF({order} < {cuts[k]!r}D, {_range_of(order, cuts[:k], first)}, {_range_of(order, cuts[k + 1 :], first + k + 1)})"


def running_mean(stream: DataFrame, key: str, value: str, alarm: float) -> DataFrame:
    """key, n, mean, drifted after each micro-batch: the state is a count and a sum a key."""
    kind = stream.schema[key].dataType
    out = T.StructType([T.StructField(key, kind), T.StructField("n", T.LongType()), T.StructField("mean", T.DoubleType()), T.StructField("drifted", T.BooleanType())])
    state = T.StructType([T.StructField("n", T.LongType()), T.StructField("total", T.DoubleType())])

    def update(name: tuple, parts: Iterator[pd.DataFrame], held) -> Iterator[pd.DataFrame]:  # noqa: ANN001
        n, total = held.get if held.exists else (0, 0.0)
        before = total / n if n else math.nan
        for part in parts:
            n, total = n + len(part), total + float(part[value].sum())
        held.update((n, total))
        mean = total / n if n else math.nan
        yield pd.DataFrame({key: [name[0]], "n": [n], "mean": [mean], "drifted": [bool(abs(mean - before) > alarm)]})

    from pyspark.sql.streaming.state import GroupStateTimeout

    return stream.groupBy(key).applyInPandasWithState(update, out, state, "update", GroupStateTimeout.NoTimeout)


def asof_mean(vectors: DataFrame, means: DataFrame, time: str = "ts", on: str = "store_id") -> DataFrame:
    """Each vector with the version of the mean that held at its time."""
    return as_of(vectors, means, time, ["mean_version"], [on])


def merge_batch(spark: SparkSession, path: str, shards: int = 64):  # noqa: ANN201
    """A foreachBatch function that adds a batch's new ids to a coded table; a repeated batch adds nothing.

    The table is partitioned by shards of the id. A batch reads ids only, only of the shards it
    has ids in and only from files whose range of ids meets its own. What makes a batch runs once.
    """

    def merge(batch: DataFrame, number: int) -> None:
        fresh = batch.dropDuplicates(["vec_id"]).withColumn("shard", F.pmod(F.xxhash64("vec_id"), F.lit(shards)).cast("int")).persist()
        try:
            add(fresh)
        finally:
            fresh.unpersist()

    def add(fresh: DataFrame) -> None:
        span = fresh.agg(F.min("vec_id").alias("low"), F.max("vec_id").alias("high"), F.collect_set("shard").alias("shards")).first()
        if span.low is None:
            return
        try:
            old = spark.read.schema(fresh.schema).parquet(path)
            old = old.where(F.col("shard").isin(span.shards) & F.col("vec_id").between(span.low, span.high))
            fresh = fresh.join(old.select("vec_id", "shard"), ["vec_id", "shard"], "left_anti")
        except Exception as error:  # the first batch finds no table
            if "PATH_NOT_FOUND" not in str(error):
                raise
        fresh.repartition("shard").sortWithinPartitions("shard", "vec_id").write.mode("append").partitionBy("shard").parquet(path)

    return merge
