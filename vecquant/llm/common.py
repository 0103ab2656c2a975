"""Helpers shared by the training-data operators."""

from __future__ import annotations

import contextlib
import ctypes
import uuid
from collections.abc import Iterator

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession


def ensure_checkpoint_dir(spark: SparkSession) -> str:
    """The shared folder of the session, which is set as its checkpoint folder if it has none.

    Where the session names none: a folder in the warehouse, which all executors share too.
    """
    named = spark.conf.get("spark.checkpoint.dir", None)
    context = spark.sparkContext
    if context._jsc.sc().getCheckpointDir().isEmpty():
        context.setCheckpointDir(named or f"{spark.conf.get('spark.sql.warehouse.dir').rstrip('/')}/_checkpoints")
    return named or context._jsc.sc().getCheckpointDir().get()


def cut_lineage(df: DataFrame) -> DataFrame:
    """Write the rows to the shared folder, so that a lost executor costs no recomputation."""
    ensure_checkpoint_dir(df.sparkSession)
    return df.checkpoint(eager=True)


def text_slices(
    batches: Iterator[pa.RecordBatch], text: str, max_bytes: int = 1_000_000
) -> Iterator[tuple[pa.RecordBatch, list[str]]]:
    """Cut Arrow batches so that each slice holds about max_bytes of text, whole rows only.

    At the end of a task, memory that only the allocators still hold goes back to the machine:
    worker processes live on and would keep the peak of every stage.
    """
    yield from _slices(batches, text, max_bytes)
    give_back()


def give_back() -> None:
    """Return unused memory of Arrow's pool and of the C allocator, where it can."""
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):
        ctypes.CDLL(None).malloc_trim(0)


def _slices(batches: Iterator[pa.RecordBatch], text: str, max_bytes: int) -> Iterator[tuple[pa.RecordBatch, list[str]]]:
    for batch in batches:
        column = batch.column(batch.schema.get_field_index(text))
        if not batch.num_rows:
            continue
        lengths = pc.fill_null(pc.binary_length(column), 0).to_pylist()
        start, size = 0, 0
        for i, n in enumerate(lengths):
            if size and size + n > max_bytes:
                part = batch.slice(start, i - start)
                yield part, [x or "" for x in column.slice(start, i - start).to_pylist()]
                start, size = i, 0
            size += n
        yield batch.slice(start), [x or "" for x in column.slice(start).to_pylist()]


def single_column(batch: pa.RecordBatch, name: str) -> pa.Array:
    return batch.column(batch.schema.get_field_index(name))


def saved(df: DataFrame) -> DataFrame:
    """Write the rows as a table in the shared folder and read them from there."""
    path = f"{ensure_checkpoint_dir(df.sparkSession).rstrip('/')}/table-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)
