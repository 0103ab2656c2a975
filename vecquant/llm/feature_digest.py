"""Document fingerprints from improbable byte features.

Every window of 64 bytes gets the entropy of its bytes; windows rank by how rare that entropy is
among all windows of the corpus, the rarest first. A window that is the rarest among enough of the 64 starts
around it is a feature. Features are hashed into a chain of Bloom filters, in the order they
stand in, each filter closed at its quota. Two digests are alike as their filters' bits overlap
beyond chance, from 0 to 1.
"""

from __future__ import annotations

import base64
import hashlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from vecquant.llm.common import single_column, text_slices

WINDOW = 64
FILTER_BITS = 2048
HASHES = 5
#: Features a filter takes, and the starts that a feature must win.
QUOTA, POPULARITY = 160, 16
#: Entropy bins: 6 bits at most, in steps of 1/64.
BINS_A_BIT = 64
BINS = 6 * BINS_A_BIT + 1
_UNIT = 1 << 20
_BLOCK, _LONG = 1 << 16, 1 << 19
#: Ranges of ids; beyond this many they grow, and tasks still read their rows in order, two slices at a time.
MAX_RANGES = 20_000


def _near_counts(raw: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """How often each byte recurs in the 63 bytes behind it, and in the 63 before it."""
    n = len(raw)
    after, before = np.zeros(n, dtype=np.uint8), np.zeros(n, dtype=np.uint8)
    for start in range(0, n, _BLOCK):
        end = min(n, start + _BLOCK)
        for d in range(1, WINDOW):
            stop = min(end, n - d)
            if stop <= start:
                break
            same = (raw[start:stop] == raw[start + d : stop + d]).view(np.uint8)
            after[start:stop] += same
            before[start + d : stop + d] += same
    return after, before


def _count_terms() -> np.ndarray:
    """c * log2(c) for the counts a window can hold, in whole units, so that sums are exact."""
    counts = np.arange(WINDOW + 1, dtype=float)
    return np.rint(counts * np.log2(np.maximum(counts, 1)) * _UNIT).astype(np.int64)


def entropy_bins(raw: np.ndarray) -> np.ndarray:
    """Entropy of every window of 64 bytes, in steps of 1/64 bit; the length is len(raw) - 63.

    Sums are of integers: a window has the same bin wherever it stands.
    """
    n = len(raw) - WINDOW + 1
    if n < 1:
        return np.zeros(0, dtype=np.int16)
    term = _count_terms()
    step = np.diff(term).astype(np.int32)  # what one more occurrence adds
    after, before = _near_counts(raw)
    sums = np.empty(n, dtype=np.int64)
    sums[0] = term[np.bincount(raw[:WINDOW], minlength=256)].sum()
    np.subtract(step[before[WINDOW:]], step[after[: n - 1]], out=sums[1:])
    np.cumsum(sums, out=sums)
    whole = int(np.log2(WINDOW)) * WINDOW * _UNIT
    return ((whole - sums) // (WINDOW * _UNIT // BINS_A_BIT)).clip(0, BINS - 1).astype(np.int16)


def ranks_by_rarity(histogram: np.ndarray) -> np.ndarray:
    """Rank of each entropy bin: 0 for the rarest in the histogram, ties in favor of low entropy."""
    ranks = np.empty(BINS, dtype=np.int64)
    ranks[np.lexsort((np.arange(BINS), histogram))] = np.arange(BINS)
    return ranks


def usual_ranks() -> np.ndarray:
    """Ranks without a corpus: entropies far from 4 bits, where prose has most windows, are rare."""
    return ranks_by_rarity(-np.abs(np.arange(BINS) - 4 * BINS_A_BIT))


def measure_rarity(docs: DataFrame, text_column: str = "text") -> np.ndarray:
    """Ranks of entropy bins by how many windows of all rows' texts fall into each.

    One narrow pass over the texts; a task sends one histogram.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(BINS, dtype=np.int64)
        for _, texts in text_slices(batches, "text", 1_000_000):
            for raw in _joined(texts):
                total += np.bincount(entropy_bins(raw), minlength=BINS)
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(BINS, dtype=np.int32)), pa.array(total)], names=["bin", "n"])

    parts = docs.select(F.col(text_column).alias("text")).where("length(text) > 0").mapInArrow(run, "bin int, n long")
    histogram = np.zeros(BINS, dtype=np.int64)
    for row in parts.groupBy("bin").agg(F.sum("n").alias("n")).collect():
        histogram[row.bin] = row.n
    return ranks_by_rarity(histogram) if histogram.any() else usual_ranks()


def _joined(texts: list[str]) -> Iterator[np.ndarray]:
    """Bytes of the texts in stretches of bounded size; windows that span two texts are few and count too."""
    raw = np.frombuffer("".join(texts).encode(), dtype=np.uint8)
    for start in range(0, len(raw), _LONG):
        yield raw[start : start + _LONG + WINDOW - 1]


def _popularity(raw: np.ndarray, ends: np.ndarray, doc: np.ndarray, ranks: np.ndarray) -> np.ndarray:
    """For each place, of how many of the 64 windows up to it, in its text, it is the rarest; ties to the left."""
    n = len(raw)
    at = np.flatnonzero(np.arange(n) <= (ends - WINDOW)[doc])
    key = np.full(n + WINDOW, np.iinfo(np.int64).max)
    key[at] = (ranks[entropy_bins(raw)[at]] << 40) | at
    low, width = key, 1
    while width < WINDOW:  # leftmost lowest rank among 64 starts, by doubling
        low = np.minimum(low[: len(low) - width], low[width:])
        width *= 2
    return np.bincount(low[at] & ((1 << 40) - 1), minlength=n)


def _hash_windows(raw: np.ndarray, chosen: np.ndarray) -> np.ndarray:
    hashes = np.full(len(chosen), 0x9E3779B97F4A7C15, dtype=np.uint64)
    with np.errstate(over="ignore"):
        for k in range(0, WINDOW, 8):
            word = np.zeros(len(chosen), dtype=np.uint64)
            for j in range(8):
                word |= raw[chosen + k + j].astype(np.uint64) << np.uint64(8 * j)
            hashes = (hashes ^ word) * np.uint64(0xFF51AFD7ED558CCD)
            hashes ^= hashes >> np.uint64(29)
        hashes *= np.uint64(0xC4CEB9FE1A85EC53)
        hashes ^= hashes >> np.uint64(32)
    return hashes


def _first_of_equal(owners: np.ndarray, hashes: np.ndarray) -> np.ndarray:
    """Places of features, but for those that an equal feature of the same text precedes."""
    order = np.lexsort((np.arange(len(hashes)), hashes, owners))
    new = np.ones(len(order), dtype=bool)
    new[1:] = (hashes[order][1:] != hashes[order][:-1]) | (owners[order][1:] != owners[order][:-1])
    return np.sort(order[new])


def _long_features(raw: np.ndarray, ranks: np.ndarray) -> np.ndarray:
    """Distinct feature hashes of one long text in order, from blocks that overlap by what a window can see."""
    n, least = len(raw), POPULARITY
    while True:
        found, most = [np.zeros(0, dtype=np.uint64)], 0
        for start in range(0, n - WINDOW + 1, _LONG):
            # 63 more starts on either side, and the bytes of the last one's window.
            left, right = max(0, start - WINDOW + 1), min(n, start + _LONG + 2 * WINDOW)
            part = raw[left:right]
            popularity = _popularity(part, np.array([len(part)]), np.zeros(len(part), dtype=np.int64), ranks)
            own = popularity[start - left : start - left + _LONG]
            most = max(most, int(own.max(initial=0)))
            hashes = _hash_windows(part, start - left + np.flatnonzero(own >= least))
            found.append(hashes[_first_of_equal(np.zeros(len(hashes), dtype=np.int64), hashes)])
        if most >= least:
            hashes = np.concatenate(found)
            return hashes[_first_of_equal(np.zeros(len(hashes), dtype=np.int64), hashes)]
        least = most  # no window wins often, so the best ones count


def _features(blobs: list[bytes], ranks: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(document, hash) of every feature in order, over texts padded with zeros to one window."""
    long_ones = {i: _long_features(np.frombuffer(b, dtype=np.uint8), ranks) for i, b in enumerate(blobs) if len(b) > _LONG}
    some = [(i, b.ljust(WINDOW, b"\0")) for i, b in enumerate(blobs) if b and i not in long_ones]
    owners, hashes = np.zeros(0, dtype=np.int64), np.zeros(0, dtype=np.uint64)
    if some:
        owner = np.array([i for i, _ in some], dtype=np.int64)
        raw = np.frombuffer(b"".join(b for _, b in some), dtype=np.uint8)
        sizes = np.array([len(b) for _, b in some], dtype=np.int64)
        ends = np.cumsum(sizes)
        doc = np.repeat(np.arange(len(some)), sizes)
        popularity = _popularity(raw, ends, doc, ranks)
        most = np.maximum.reduceat(popularity, np.concatenate([[0], ends[:-1]]))
        chosen = np.flatnonzero(popularity >= np.minimum(POPULARITY, most)[doc])
        owners, hashes = owner[doc[chosen]], _hash_windows(raw, chosen)
        first = _first_of_equal(owners, hashes)
        owners, hashes = owners[first], hashes[first]
    for i, more in long_ones.items():
        at = np.searchsorted(owners, i)
        owners = np.concatenate([owners[:at], np.full(len(more), i), owners[at:]])
        hashes = np.concatenate([hashes[:at], more, hashes[at:]])
    return owners, hashes


def digests(texts: list[str], ranks: np.ndarray) -> list[np.ndarray]:
    """For each text its filters, an array of (filters, 256) bytes; no filters for the empty text.

    ranks: of entropy bins, the rarest first, from measure_rarity() or usual_ranks().
    """
    blobs = [t.encode() for t in texts]
    out: list[np.ndarray] = [np.zeros((0, FILTER_BITS // 8), dtype=np.uint8)] * len(texts)
    docs, hashes = _features(blobs, ranks)
    if not len(docs):
        return out
    owners, begin, counts = np.unique(docs, return_index=True, return_counts=True)
    ordinal = np.arange(len(docs)) - np.repeat(begin, counts)
    n_filters = -(-counts // QUOTA)
    base = np.concatenate([[0], np.cumsum(n_filters)])
    slot = np.repeat(base[:-1], counts) + ordinal // QUOTA
    bits = np.zeros(int(base[-1]) * FILTER_BITS, dtype=bool)
    for k in range(HASHES):
        bits[slot * FILTER_BITS + ((hashes >> np.uint64(11 * k)) & np.uint64(FILTER_BITS - 1)).astype(np.int64)] = True
    packed = np.packbits(bits.reshape(-1, FILTER_BITS), axis=1)
    for k, o in enumerate(owners.tolist()):
        out[o] = packed[base[k] : base[k + 1]]
    return out


def likeness(a: np.ndarray, b: np.ndarray) -> float:
    """Mean over the shorter digest's filters of the best normalised overlap; 1 for two empty ones."""
    if not len(a) or not len(b):
        return float(len(a) == len(b))
    if len(a) > len(b):
        a, b = b, a
    wide_a, wide_b = a.view(np.uint64), b.view(np.uint64)
    ones_a, ones_b = np.bitwise_count(wide_a).sum(axis=1), np.bitwise_count(wide_b).sum(axis=1)
    total = 0.0
    for row, n in zip(wide_a, ones_a.tolist(), strict=True):
        shared = np.bitwise_count(row & wide_b).sum(axis=1)
        most = np.minimum(n, ones_b)
        chance = n * ones_b / FILTER_BITS
        score = np.where(most > chance, (shared - chance) / np.maximum(most - chance, 1e-9), 0)
        total += float(np.clip(score, 0, 1).max())
    return total / len(a)


def fingerprint_text(digest: np.ndarray) -> str:
    """The digest as text: base64 of its filters."""
    return base64.b64encode(digest.tobytes()).decode()


def parse_fingerprint(text: str) -> np.ndarray:
    return np.frombuffer(base64.b64decode(text), dtype=np.uint8).reshape(-1, FILTER_BITS // 8)


def fingerprint_documents(
    docs: DataFrame, id_column: str = "doc_id", text_column: str = "text", ranks: np.ndarray | None = None
) -> DataFrame:
    """The id and fingerprint of every row. A null text counts as empty and has an empty fingerprint.

    ranks: of entropy bins; measured over these texts where not given. Digests compare only
    where they come from the same ranks.
    """
    kind = docs.schema[id_column].dataType
    ranks = measure_rarity(docs, text_column) if ranks is None else ranks

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch, texts in text_slices(batches, "text", 1_000_000):
            made = [fingerprint_text(d) for d in digests(texts, ranks)]
            yield pa.RecordBatch.from_arrays([single_column(batch, "id"), pa.array(made, pa.string())], names=["id", "fingerprint"])

    schema = T.StructType([T.StructField("id", kind), T.StructField("fingerprint", T.StringType())])
    source = docs.select(F.col(id_column).alias("id"), F.col(text_column).alias("text"))
    return source.mapInArrow(run, schema).withColumnRenamed("id", id_column)


def _range_starts(docs: DataFrame, parts: int) -> list[int]:
    """Ids that cut the rows into about equal ranges; a bounded number of quantiles."""
    if parts < 2:
        return []
    cuts = docs.where("id is not null").approxQuantile("id", [i / parts for i in range(1, parts)], 0.2 / parts)
    return sorted({int(c) for c in cuts})


def edit_sensitivity(
    docs: DataFrame,
    id_column: str = "doc_id",
    text_column: str = "text",
    range_bytes: int = 24_000_000,
    ranks: np.ndarray | None = None,
) -> DataFrame:
    """Fingerprints of every text and of its edited form, with their likeness.

    The edited text is the text with its last half replaced by the start of the next document's,
    next in descending id (then by text hash among repeated ids, null ids last; after the last
    comes the first). Rows: the id, n_chars, edited_sha256, fingerprint, edited_fingerprint,
    near_edited, near_next. A null text counts as empty. Every row stays, and a table of one row is its own next.
    Rows are dealt once into ranges of ids; a range's first row also goes to the range before
    it, so that each task reads its rows in order and holds two of them at a time. ranks: of
    entropy bins, measured over all these texts where not given. Working memory is that of two
    texts and of blocks of half a megabyte, however long a text is.
    """
    spark = docs.sparkSession
    ranks = measure_rarity(docs, text_column) if ranks is None else ranks
    source = docs.select(F.col(id_column).cast("long").alias("id"), F.coalesce(F.col(text_column), F.lit("")).alias("text"))
    source = source.withColumn("tie", F.xxhash64("text"))
    size = source.agg(F.sum(F.length("text")).alias("n")).first().n or 0
    starts = _range_starts(source, min(MAX_RANGES, -(-size // range_bytes)))
    last = len(starts)
    cuts = np.array(starts, dtype=np.int64)

    @F.pandas_udf("int")
    def above(ids: pd.Series) -> pd.Series:
        return pd.Series(last - np.searchsorted(cuts, ids.to_numpy(dtype=np.int64), side="right")).astype("int32")

    # Range 0 holds the highest ids, the last range the lowest and the null ids.
    source = source.withColumn("range", above(F.coalesce("id", F.lit(-(2**63)))))
    order = F.struct(F.coalesce("id", F.lit(-(2**63))), "tie")
    # One row a range: its first in descending order.
    firsts = {r["range"]: r.top for r in source.groupBy("range").agg(F.max(order).alias("top")).collect()}
    filled = sorted(firsts)
    heads = [(firsts[r][0], firsts[r][1], filled[k - 1]) for k, r in enumerate(filled)]  # also for the range before
    keys = spark.createDataFrame(heads or [(0, 0, -1)], "head_id long, tie long, to_range int")
    # A head may be many equal rows; one copy of it is enough.
    match = (F.coalesce("id", F.lit(-(2**63))) == F.col("head_id")) & (source.tie == keys.tie)
    copies = source.join(F.broadcast(keys), match).groupBy("to_range").agg(F.first("id").alias("id"), F.first("text").alias("text"), F.first(source.tie).alias("tie"))
    rows = source.select("range", "id", "text", "tie", F.lit(0).alias("copy"))
    rows = rows.unionByName(copies.select(F.col("to_range").alias("range"), "id", "text", "tie", F.lit(1).alias("copy")))
    dealt = rows.repartitionById(max(1, last + 1), F.col("range")).sortWithinPartitions("range", "copy", F.desc_nulls_last("id"), F.desc("tie"))
    names = ["id", "n_chars", "edited_sha256", "fingerprint", "edited_fingerprint", "near_edited", "near_next"]

    def compare(rows: list[tuple]) -> pa.RecordBatch:
        """Rows (range, copy, id, text) in order, the last of which only serves as the next."""
        texts = [r[3] for r in rows]
        edited = [t[: len(t) - len(t) // 2] + texts[k + 1][: len(t) // 2] for k, t in enumerate(texts[:-1])]
        own = digests(texts, ranks)
        changed = digests(edited, ranks)
        picked = [k for k, r in enumerate(rows[:-1]) if not r[1]]
        columns = [
            pa.array([rows[k][2] for k in picked], pa.int64()),
            pa.array([len(texts[k]) for k in picked], pa.int64()),
            pa.array([hashlib.sha256(edited[k].encode()).hexdigest() for k in picked], pa.string()),
            pa.array([fingerprint_text(own[k]) for k in picked], pa.string()),
            pa.array([fingerprint_text(changed[k]) for k in picked], pa.string()),
            pa.array([likeness(own[k], changed[k]) for k in picked], pa.float64()),
            pa.array([likeness(own[k], own[k + 1]) for k in picked], pa.float64()),
        ]
        return pa.RecordBatch.from_arrays(columns, names=names)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[tuple] = []
        size = 0
        for batch in batches:
            values = [single_column(batch, c).to_pylist() for c in ("range", "copy", "id", "text")]
            for row in zip(*values, strict=True):
                held.append(row)
                size += len(row[3])
                if size > 1_000_000 and len(held) > 1:
                    yield compare(held)
                    held, size = held[-1:], len(row[3])
        if len(held) > 1:
            yield compare(held)

    schema = "id long, n_chars long, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double"
    return dealt.select("range", "copy", "id", "text").mapInArrow(run, schema).withColumnRenamed("id", id_column)
