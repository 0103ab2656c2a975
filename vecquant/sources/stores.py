"""Reading vector files and writing and reading coded stores."""

from __future__ import annotations

import json
from dataclasses import asdict, dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from vecquant.operators.fit import Search
from vecquant.schema import CODED, RAW

META_VERSION = 1


@dataclass
class Meta:
    """What a store's rows were coded with."""

    d: int
    m: int
    bits: int
    curve: str
    split: str = "random"
    split_seed: int = 0
    mean: list[float] = field(default_factory=list)
    similarity: str = "dot"
    shards: int = 8
    version: int = META_VERSION

    def search(self) -> Search:
        return Search(curve=self.curve, bits=self.bits, m=self.m, split=self.split, split_seed=self.split_seed)


def read_vectors(spark: SparkSession, path: str, fmt: str = "parquet") -> DataFrame:
    """vec_id, embedding from parquet or orc, JSON lines, CSV (values joined by blanks) or text ("id v v ...")."""
    if fmt in ("parquet", "orc", "json"):
        return spark.read.schema(RAW).format(fmt).load(path).select("vec_id", "embedding")
    if fmt == "csv":
        rows = spark.read.schema("vec_id long, line string").csv(path, header=True)
    elif fmt == "text":
        parts = F.split(F.trim("value"), r"\s+", 2)
        rows = spark.read.text(path).select(parts[0].cast("long").alias("vec_id"), parts[1].alias("line"))
    else:
        raise ValueError(fmt)
    return rows.select("vec_id", F.transform(F.split("line", r"\s+"), lambda v: v.cast("float")).alias("embedding"))


def write_store(coded: DataFrame, path: str, meta: Meta) -> None:
    """Rows by shard of the id, sorted in each file, and one row of metadata. Shards written again replace the old."""
    rows = coded.withColumn("shard", F.pmod(F.xxhash64("vec_id"), F.lit(meta.shards)).cast("int"))
    rows = rows.repartition(meta.shards, "shard").sortWithinPartitions("shard", "vec_id")
    rows.write.option("partitionOverwriteMode", "dynamic").mode("overwrite").partitionBy("shard").parquet(f"{path}/codes")
    coded.sparkSession.createDataFrame([(json.dumps(asdict(meta)),)], "meta string").coalesce(1).write.mode("overwrite").text(f"{path}/meta")


def write_bucketed(coded: DataFrame, table: str, buckets: int) -> None:
    """A table bucketed and sorted by the id, for joins without an exchange."""
    coded.write.mode("overwrite").bucketBy(buckets, "vec_id").sortBy("vec_id").saveAsTable(table)


def read_store(spark: SparkSession, path: str) -> tuple[DataFrame, Meta]:
    """Rows and metadata; a store of another version is refused."""
    meta = Meta(**json.loads(spark.read.text(f"{path}/meta").first()[0]))
    if meta.version != META_VERSION:
        raise ValueError(f"the store has version {meta.version}, not {META_VERSION}")
    schema = T.StructType([*CODED.fields, T.StructField("shard", T.IntegerType())])
    return spark.read.schema(schema).parquet(f"{path}/codes"), meta


def read_fvecs(spark: SparkSession, path: str) -> DataFrame:
    """vec_id (the place in the file), embedding from records of (dimension, floats) of equal length.

    Records are cut by Hadoop's fixed-length reader, so that one large file is read by many
    tasks, from any store that Spark can open. An empty file gives no rows.
    """
    import numpy as np

    context = spark.sparkContext
    head = context.binaryRecords(path, 4).take(1)
    schema = "vec_id long, embedding array<float>"
    if not head:
        return spark.createDataFrame([], schema)
    d = int.from_bytes(head[0], "little")

    def rows(records):  # noqa: ANN001, ANN202
        for record, place in records:
            yield place, np.frombuffer(record, dtype="<f4", offset=4).tolist()

    return spark.createDataFrame(context.binaryRecords(path, 4 + 4 * d).zipWithIndex().mapPartitions(rows), schema)
