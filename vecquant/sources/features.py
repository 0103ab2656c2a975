"""Vector sets made from other tables: texts by random indexing, numbers by grouping."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from vecquant.operators.prep import column, lists


_WORD = (1 << 32) - 1


def seeded_states(keys: np.ndarray) -> np.ndarray:
    """The states [keys, 4] that NumPy's SFC64 generators have once seeded with these keys, for all keys at once."""
    words = [keys & np.uint64(_WORD), keys >> np.uint64(32), np.zeros_like(keys), np.zeros_like(keys)]
    low, shift = np.uint64(_WORD), np.uint64(16)
    constant = 0x43B0D7E5

    def scramble(x: np.ndarray, factor: int) -> np.ndarray:
        nonlocal constant
        x = x ^ np.uint64(constant)
        constant = constant * factor & _WORD
        x = x * np.uint64(constant) & low
        return x ^ (x >> shift)

    with np.errstate(over="ignore"):
        pool = [scramble(x, 0x931E8875) for x in words]
        for source in range(4):
            for target in range(4):
                if source != target:
                    x = pool[target] * np.uint64(0xCA01F9DD) - scramble(pool[source], 0x931E8875) * np.uint64(0x4973F715) & low
                    pool[target] = x ^ (x >> shift)
        constant = 0x8B51F9DD
        halves = [scramble(pool[k % 4], 0x58F38DED) for k in range(6)]
        a, b, c = (halves[k] | halves[k + 1] << np.uint64(32) for k in (0, 2, 4))
        count = np.ones_like(a)
        for _ in range(12):
            out = a + b + count
            count = count + np.uint64(1)
            a, b, c = b ^ (b >> np.uint64(11)), c + (c << np.uint64(3)), (c << np.uint64(24) | c >> np.uint64(40)) + out
    return np.stack([a, b, c, count], axis=1)


def token_vectors(tokens: list[str], d: int, seed: int) -> np.ndarray:
    """A Gaussian vector for each token, a function of the token and the seed."""
    out = np.empty((len(tokens), d), dtype=np.float32)
    keys = np.fromiter((xxhash.xxh64_intdigest(token.encode(), seed) for token in tokens), dtype=np.uint64, count=len(tokens))
    source = np.random.SFC64(0)
    draw, state = np.random.Generator(source).standard_normal, source.state
    for row, own in zip(out, seeded_states(keys), strict=True):
        state["state"]["state"] = own
        source.state = state
        draw(dtype=np.float32, out=row)
    return out


def text_vectors(df: DataFrame, d: int = 768, seed: int = 0, id_column: str = "doc_id", text: str = "text") -> DataFrame:
    """vec_id, embedding: sum of token vectors, of unit length. Texts without a token have no row."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for start in range(0, whole.num_rows, 256):
                batch = whole.slice(start, 256)
                words = [(t or "").lower().split() for t in column(batch, "text").to_pylist()]
                names = sorted({w for ws in words for w in ws})
                place = {w: i for i, w in enumerate(names)}
                vectors = np.zeros((len(words), d))
                table = token_vectors(names, d, seed)
                for i, ws in enumerate(words):
                    if ws:
                        at, counts = np.unique([place[w] for w in ws], return_counts=True)
                        vectors[i] = counts @ table[at].astype(np.float64)
                size = np.linalg.norm(vectors, axis=1)
                good = np.flatnonzero(size > 0)
                made = (vectors[good] / size[good][:, None]).astype(np.float32)
                yield pa.RecordBatch.from_arrays([column(batch, "vec_id").take(pa.array(good)), lists(made, pa.float32())], names=["vec_id", "embedding"])

    source = df.select(F.col(id_column).cast("long").alias("vec_id"), F.col(text).alias("text"))
    return source.mapInArrow(run, "vec_id long, embedding array<float>")


def worded(df: DataFrame, id_column: str = "doc_id", text: str = "text") -> DataFrame:
    """vec_id of the texts that have a vector, whatever its length: those with a token."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            good = [bool(t) and not t.isspace() for t in column(batch, "text").to_pylist()]
            yield pa.RecordBatch.from_arrays([column(batch, "vec_id").filter(pa.array(good, pa.bool_()))], names=["vec_id"])

    return df.select(F.col(id_column).cast("long").alias("vec_id"), F.col(text).alias("text")).mapInArrow(run, "vec_id long")


def group_arrays(df: DataFrame, key: str, value: str, order: list[str], size: int) -> DataFrame:
    """vec_id, embedding: the first `size` values of each key in a given order; keys with fewer have no row.

    Ranks are cut before and after the exchange, so that no more than `size` rows of a key and
    task move, and no more than `size` of a key are gathered.
    """
    rank = F.row_number().over(Window.partitionBy("vec_id").orderBy(*order, value))
    ranked = df.select(F.col(key).cast("long").alias("vec_id"), *order, value).withColumn("rank", rank).where(F.col("rank") <= size)
    rows = ranked.groupBy("vec_id").agg(F.sort_array(F.collect_list(F.struct("rank", F.col(value).cast("float").alias("v")))).alias("rows"))
    return rows.where(F.size("rows") == size).select("vec_id", F.transform("rows", lambda r: r["v"]).alias("embedding"))
