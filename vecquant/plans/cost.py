"""Arithmetic models of bytes and operations, and a timer."""

from __future__ import annotations

import math
import time

from pyspark.sql import DataFrame, SparkSession

from vecquant.schema import PARAM_BYTES, PAYLOAD_PARAMS

#: Basic operations a value, (exp, log, fma, mul, div) to encode and to decode.
OPERATIONS = {
    "kuma": ((2, 2, 18, 8, 0), (2, 2, 18, 8, 0)),
    "logi": ((1, 0, 6, 2, 1), (0, 1, 7, 2, 1)),
    "pwl": ((0, 0, 2, 0, 1), (0, 0, 2, 0, 1)),
}
OPERATION_NAMES = ("exp", "log", "fma", "mul", "div")
#: Bytes a graph node has beside its vector, a disk block, and a list cluster.
NODE_OVERHEAD, BLOCK, CLUSTER = 307, 4096, 48 * 1024


def payload_bytes(d: int, bits: int, m: int) -> int:
    """Codes and parameters of one vector."""
    return math.ceil(d * bits / 8) + PAYLOAD_PARAMS * PARAM_BYTES * m


def aligned_bytes(d: int, bits: int, m: int, align: int = 64) -> tuple[int, int]:
    """The payload padded to whole lines, and how many of the bytes that codes alone would pad the parameters use."""
    codes = math.ceil(d * bits / 8)
    padded = lambda n: -(-n // align) * align
    return padded(payload_bytes(d, bits, m)), min(padded(codes) - codes, PAYLOAD_PARAMS * PARAM_BYTES * m)


def index_bytes(d: int, bits: int, m: int, overhead: int = NODE_OVERHEAD) -> tuple[int, int, float]:
    """Bytes a node with full precision, with codes, and their ratio."""
    full, coded = 4 * d + overhead, payload_bytes(d, bits, m) + overhead
    return full, coded, full / coded


def set_gib(n: int, d: int) -> float:
    return n * d * 4 / 2**30


def block_layout(d: int, degree: int = 64) -> tuple[int, int, bool]:
    """Bytes of a vector with its neighbour list, blocks it takes, and whether the vector alone fills one."""
    size = 4 * d + 4 * (degree + 1)
    return size, -(-size // BLOCK), 4 * d >= BLOCK


def inverted_layout(n: int, d: int, replicas: int = 8) -> tuple[int, float]:
    """Bytes of replicated lists, and vectors that fit a cluster."""
    return n * d * 4 * replicas, CLUSTER / (4 * d)


def op_counts(curve: str, values: int) -> list[tuple[str, str, str, int]]:
    """(curve, direction, operation, count) over a number of values."""
    return [(curve, side, name, count * values) for side, counts in zip(("encode", "decode"), OPERATIONS[curve], strict=True) for name, count in zip(OPERATION_NAMES, counts, strict=True)]


def op_frame(spark: SparkSession, values: int) -> DataFrame:
    rows = [row for curve in OPERATIONS for row in op_counts(curve, values)]
    return spark.createDataFrame(rows, "curve string, side string, operation string, total long")


def rerank_bytes(d: int, bits: int, m: int, k: int, factor: float) -> tuple[int, int]:
    """Bytes a query fetches to re-rank: full precision, coded."""
    n = round(k * factor)
    return n * 4 * d, n * payload_bytes(d, bits, m)


def timed(df: DataFrame) -> float:
    """Seconds to run a frame to nowhere."""
    began = time.perf_counter()
    df.write.format("noop").mode("overwrite").save()
    return time.perf_counter() - began


def latency(make, repeats: int, queries: int) -> tuple[float, float, float, float]:  # noqa: ANN001
    """Mean, median and 95th percentile of seconds a query, and queries a second, over repeated runs."""
    seconds = sorted(timed(make()) / max(1, queries) for _ in range(repeats))
    mean = sum(seconds) / len(seconds)
    return mean, seconds[len(seconds) // 2], seconds[min(len(seconds) - 1, int(0.95 * len(seconds)))], 1 / mean
