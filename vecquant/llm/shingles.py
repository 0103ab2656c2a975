"""Links between texts by the Jaccard similarity of their word shingles.

Each text stands under keys made of a few min-hashes; two texts of at least the wanted
similarity share a key but for about three in a million. Texts that share keys, directly or over others, form
a pool, and within a pool every pair is compared by its full shingle sets, so that only true
links are passed on: a spanning forest of them. A large pool is cut into chunks and compared by
pairs of chunks, so that no task holds more than two chunks.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vecquant.llm.common import cut_lineage, give_back, single_column, text_slices
from vecquant.llm.components import smallest_reachable

WIDTH, SIMILARITY = 5, 0.8
#: Keys of a text, and min-hashes in a key: a pair at 0.8 shares none with a chance of (1 - 0.8^5)^32.
KEYS, ROWS = 32, 5
_rng = np.random.default_rng(11)
_MULTIPLY = _rng.integers(0, 2**63, KEYS * ROWS, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_ADD = _rng.integers(0, 2**63, KEYS * ROWS, dtype=np.uint64)


def shingle_set(text: str, width: int = WIDTH) -> np.ndarray:
    """Sorted hashes of the distinct word shingles; a shorter text is one shingle, one without words none."""
    words = text.encode().lower().split()
    if not words:
        return np.zeros(0, dtype=np.uint64)
    n = max(1, len(words) - width + 1)
    joined = b" ".join(words)
    ends = np.cumsum([len(w) + 1 for w in words]) - 1
    starts = [0, *(ends[: n - 1] + 1).tolist()]
    stops = ends[width - 1 :].tolist() if len(words) > width else [len(joined)]
    hash_ = xxhash.xxh64_intdigest
    return np.unique(np.array([hash_(joined[a:b], 42) for a, b in zip(starts, stops, strict=True)], dtype=np.uint64))


def set_code(shingles: np.ndarray) -> int:
    """One number for the whole set; 0 for the empty one."""
    return xxhash.xxh64_intdigest(shingles.tobytes(), 7) if len(shingles) else 0


def keys(shingles: np.ndarray) -> np.ndarray:
    """The keys that a text stands under."""
    least = np.full(KEYS * ROWS, np.iinfo(np.uint64).max, dtype=np.uint64)
    for i in range(0, len(shingles), 2_048):
        part = shingles[i : i + 2_048]
        for k in range(0, KEYS * ROWS, 16):
            some = slice(k, k + 16)
            np.minimum(least[some], (_MULTIPLY[some, None] * part + _ADD[some, None]).min(axis=1), out=least[some])
    rows = least.reshape(KEYS, ROWS)
    return np.array([xxhash.xxh64_intdigest(r.tobytes(), k) for k, r in enumerate(rows)], dtype=np.uint64)


def similar_pairs(sets: list[np.ndarray], side: np.ndarray, similarity: float = SIMILARITY) -> list[tuple[int, int]]:
    """Places of pairs with at least that Jaccard similarity: a spanning forest. side: 0 and 1 of a tile of two chunks."""
    sizes = np.array([len(s) for s in sets])
    order = np.argsort(sizes, kind="stable")
    sizes, side = sizes[order], side[order]
    cuts = np.concatenate([[0], np.cumsum(sizes)])
    flat = np.concatenate([sets[i] for i in order])
    both, root, kept = len(set(side.tolist())) > 1, np.arange(len(sets)), []
    for i in range(len(sets)):
        own = flat[cuts[i] : cuts[i + 1]]
        # A set more than 1 / similarity times as large can't be as similar.
        end = np.searchsorted(sizes, sizes[i] / similarity + 1e-6, side="right")
        others = i + 1 + np.flatnonzero((root[i + 1 : end] != root[i]) & ((side[i + 1 : end] != side[i]) | (not both)))
        for some in np.array_split(others, max(1, int(sizes[others].sum()) // 1_000_000)):
            if not len(some):
                continue
            rows = np.concatenate([flat[cuts[j] : cuts[j + 1]] for j in some])
            at = np.minimum(np.searchsorted(own, rows), len(own) - 1)
            shared = np.add.reduceat((own[at] == rows).astype(np.int64), np.concatenate([[0], np.cumsum(sizes[some])[:-1]]))
            for j in some[shared >= similarity * (sizes[i] + sizes[some] - shared) - 1e-9].tolist():
                if root[j] != root[i]:
                    root[root == root[j]] = root[i]
                    kept.append((int(order[i]), int(order[j])))
    return kept


def _pool_links(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Links within runs of equal (pool, tile) over rows sorted by them."""
    held: list[tuple[int, int, np.ndarray]] = []
    now = None

    def close() -> pa.RecordBatch:
        pairs = similar_pairs([h[2] for h in held], np.array([h[1] for h in held])) if len(held) > 1 else []
        return pa.RecordBatch.from_arrays([pa.array([held[x[k]][0] for x in pairs], pa.int64()) for k in (0, 1)], names=["a", "b"])

    for batch in batches:
        for pool, tile, code, side, packed in zip(*(single_column(batch, c).to_pylist() for c in ("pool", "tile", "code", "side", "packed")), strict=True):
            if (pool, tile) != now:
                if held:
                    yield close()
                held, now = [], (pool, tile)
            held.append((code, side, np.frombuffer(packed, dtype=np.uint64)))
    if held:
        yield close()
    held = []
    give_back()


def links(docs: DataFrame, prints: DataFrame, text_column: str = "text", chunk: int = 500_000) -> DataFrame:
    """Links a, b between set codes of at least the wanted similarity. prints: doc_id, row (hash of the text), code, keys of every row, written.

    Texts of the same pool are connected exactly where a chain of similar pairs connects them.
    A chunk of a pool holds about that many shingles.
    """
    one = prints.groupBy("code").agg(F.min("row").alias("row"), F.first("keys").alias("keys"))
    one = cut_lineage(one)
    # A key under which one set stands alone links nothing: most keys end here.
    under = one.select(F.explode("keys").alias("key"), "code")
    low = cut_lineage(under.groupBy("key").agg(F.min("code").alias("m"), F.max("code").alias("n")).where("m <> n").select("key", "m"))
    pools = smallest_reachable(under.join(low, "key").select(F.col("code").alias("a"), F.col("m").alias("b")))
    chosen = cut_lineage(one.join(pools, one.code == pools.node).select("code", "row", F.col("component").alias("pool")))
    texts = docs.select(F.xxhash64(text_column).alias("row"), F.col(text_column).alias("text")).join(chosen, "row")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch, some in text_slices(batches, "text"):
            sets = [shingle_set(t) for t in some]
            packed = [pa.array([s.tobytes() for s in sets], pa.binary()), pa.array([len(s) for s in sets], pa.int64())]
            yield pa.RecordBatch.from_arrays([single_column(batch, "pool"), single_column(batch, "code"), *packed], names=["pool", "code", "packed", "n"])

    # Equal texts meet in their partial aggregates.
    texts = texts.groupBy("row", "code", "pool").agg(F.max("text").alias("text"))
    sets = cut_lineage(texts.select("pool", "code", "text").mapInArrow(run, "pool long, code long, packed binary, n long"))
    large = cut_lineage(sets.groupBy("pool").agg(F.ceil(F.sum("n") / chunk).cast("long").alias("chunks")).where("chunks > 1"))
    zero = F.lit(0).cast("long")
    plain = sets.withColumns({"tile": zero, "side": zero})
    if not large.isEmpty():
        joined = sets.join(large, "pool", "left").withColumn("own", F.pmod(F.xxhash64("code"), F.col("chunks")))
        spots = F.transform(
            F.sequence(zero, F.col("chunks") - 1),
            lambda k: F.struct((F.least("own", k) * F.col("chunks") + F.greatest("own", k)).alias("tile"), (F.col("own") > k).cast("long").alias("side")),
        )
        tiled = joined.where("chunks is not null").select("pool", "code", "packed", F.explode(spots).alias("t"))
        plain = joined.where("chunks is null").select("pool", "code", "packed", zero.alias("tile"), zero.alias("side"))
        plain = plain.unionByName(tiled.select("pool", "code", "packed", "t.tile", "t.side"))
    rows = plain.select("pool", "tile", "code", "side", "packed").repartition("pool", "tile").sortWithinPartitions("pool", "tile")
    return rows.mapInArrow(_pool_links, "a long, b long")
