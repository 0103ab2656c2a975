"""Stupid-backoff scores of all documents against the n-gram counts of all other documents.

The relational plan is in backoff_joins: count tables by hash, joined to exploded n-grams,
summed per document. Here is the same plan with rows packed, for corpora where that is less to
shuffle: documents are dealt into blocks; each block sends its distinct n-gram hashes and counts
to the hash bucket that owns them; a bucket adds up the count table of its n-grams and answers
each block with totals in the order of the question; each block then scores its documents. A
packed n-gram takes 6 bytes of a shuffle, a row of the joins 28. But packed rows number blocks
times buckets, so that above a number of blocks the joins run.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from vecquant.llm import backoff_joins
from vecquant.llm.common import saved
from vecquant.llm.ngrams import BACKOFF, ngram_keys


def _planes(values: np.ndarray) -> bytes:
    """Sorted integers as the byte planes of their steps, which compress well."""
    return np.diff(values, prepend=np.uint64(0)).view(np.uint8).reshape(-1, 8).T.tobytes()


def _from_planes(raw: bytes) -> np.ndarray:
    steps = np.frombuffer(raw, dtype=np.uint8).reshape(8, -1).T
    return np.cumsum(np.ascontiguousarray(steps).view(np.uint64).ravel(), dtype=np.uint64)


def _counts_to_bytes(values: np.ndarray) -> bytes:
    return values.astype("<u8").view(np.uint8).reshape(-1, 8).T.tobytes()


def _counts_from_bytes(raw: bytes) -> np.ndarray:
    planes = np.frombuffer(raw, dtype=np.uint8).reshape(8, -1).T
    return np.ascontiguousarray(planes).view("<u8").ravel().astype(np.int64)


def _bounds(keys: np.ndarray, buckets: int) -> np.ndarray:
    """Where each bucket's part of the sorted keys begins; buckets are equal ranges of hashes."""
    edges = np.array([(k << 64) // buckets for k in range(buckets)], dtype=np.uint64)
    return np.append(np.searchsorted(keys, edges), len(keys))


def _own_counts(key: np.ndarray, doc: np.ndarray, values: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """For each n-gram: its place among the sorted distinct keys, and its count in its document."""
    order = np.argsort(key, kind="stable")  # documents stay in order within equal keys
    k, d = key[order], doc[order]
    new = np.ones(len(k), dtype=bool)
    new[1:] = (k[1:] != k[:-1]) | (d[1:] != d[:-1])
    cuts = np.flatnonzero(new)
    own = np.repeat(np.diff(np.append(cuts, len(k))), np.diff(np.append(cuts, len(k))))
    back = np.empty(len(k), dtype=np.int64)
    back[order] = own
    return np.searchsorted(values, key), back


def score_block(texts: list[str], order: int, totals: dict[str, np.ndarray], leave_out: bool) -> dict[str, np.ndarray]:
    """Sums over each text's words: log_sum, and how many words fell to their own or to no count.

    totals: sorted distinct keys and their counts. The size of the corpus enters later.
    """
    sizes, keys, owners = ngram_keys(texts, order)
    n_texts, m = len(texts), int(sizes.sum())
    ends = np.cumsum(sizes)
    place_in_text = np.arange(m) - np.repeat(ends - sizes, sizes)
    counts = []
    for key, doc in zip(keys, owners, strict=True):
        at, own = _own_counts(key, doc, totals["keys"])
        counts.append(totals["counts"][at] - (own if leave_out else 0))
    log_sum = np.zeros(m)
    open_ = np.ones(m, dtype=bool)
    doc = owners[0]
    for n in range(order, 1, -1):
        # The n-gram that ends at each word, and its first n - 1 words.
        last = np.flatnonzero(place_in_text >= n - 1)
        whole = counts[n - 1]
        context = counts[0][last - 1] if n == 2 else _context(counts[n - 2], place_in_text, n, last)
        good = (whole > 0) & (context > 0) & open_[last]
        spot = last[good]
        log_sum[spot] = np.log10(whole[good] / context[good]) + (order - n) * np.log10(BACKOFF)
        open_[spot] = False
    single = open_ & (counts[0] > 0)
    log_sum[single] = np.log10(counts[0][single]) + (order - 1) * np.log10(BACKOFF)
    unseen = open_ & ~single
    log_sum[unseen] = order * np.log10(BACKOFF)
    return {
        "n_tokens": sizes,
        "log_sum": np.bincount(doc, weights=log_sum, minlength=n_texts),
        "n_single": np.bincount(doc[single], minlength=n_texts),
        "n_unseen": np.bincount(doc[unseen], minlength=n_texts),
    }


def _context(shorter: np.ndarray, place_in_text: np.ndarray, n: int, last: np.ndarray) -> np.ndarray:
    """Counts of the (n-1)-grams that end one word before each of these words."""
    index = np.full(len(place_in_text), -1)
    ends = np.flatnonzero(place_in_text >= n - 2)
    index[ends] = np.arange(len(ends))
    return shorter[index[last - 1]]


def score_documents(
    docs: DataFrame,
    id_column: str = "doc_id",
    text_column: str = "text",
    order: int = 2,
    block_chars: int = 8_000_000,
    least_blocks: int = 64,
    most_blocks: int = 10_000,
) -> DataFrame:
    """The id, n_tokens, log10_score (sum over words), mean_log10_score of every row.

    Scores and rows as backoff_joins.score_documents has them, to which this is the same plan with n-grams
    packed by block and bucket; a pair of them costs a row, so that over most_blocks blocks
    (80 GB of characters) the joins themselves run. Memory of a task: a few times block_chars.
    """
    source = docs.select(F.col(id_column).alias("id"), F.coalesce(F.col(text_column), F.lit("")).alias("text"))
    size = source.agg(F.sum(F.length("text")).alias("n")).first().n or 0
    # Enough blocks to spread a small table over tasks; they only set how rows are dealt.
    blocks = max(least_blocks, -(-size // block_chars))
    if blocks > most_blocks:
        return backoff_joins.score_documents(docs, id_column, text_column, order)
    return _packed(docs, id_column, source, order, int(blocks))


def _packed(docs: DataFrame, id_column: str, source: DataFrame, order: int, blocks: int, leave_out: bool = True) -> DataFrame:
    # Equal rows are dealt apart, so that no number of copies fills a block.
    kind = docs.schema[id_column].dataType
    dealt = source.withColumn("block", F.pmod(F.xxhash64(F.col("id"), F.xxhash64("text"), F.monotonically_increasing_id()), F.lit(blocks)).cast("int"))

    def ask(table: pa.Table) -> pa.Table:
        texts = table["text"].to_pylist()
        _, keys, _ = ngram_keys(texts, order)
        values, counts = np.unique(np.concatenate(keys), return_counts=True)
        cuts = _bounds(values, blocks)
        rows = [(k, a, b) for k, (a, b) in enumerate(zip(cuts, cuts[1:], strict=False)) if b > a]
        block = table["block"][0].as_py()
        return pa.table(
            {
                "bucket": pa.array([k for k, _, _ in rows], pa.int32()),
                "block": pa.array([block] * len(rows), pa.int32()),
                "keys": pa.array([_planes(values[a:b]) for _, a, b in rows], pa.binary()),
                "counts": pa.array([_counts_to_bytes(counts[a:b]) for _, a, b in rows], pa.binary()),
            }
        )

    def answer(table: pa.Table) -> pa.Table:
        parts = [_from_planes(x) for x in table["keys"].to_pylist()]
        counts = np.concatenate([_counts_from_bytes(x) for x in table["counts"].to_pylist()])
        joined = np.concatenate(parts)
        values, place = np.unique(joined, return_inverse=True)
        totals = np.bincount(place, weights=counts).astype(np.int64)[place]
        ends = np.cumsum([len(p) for p in parts])
        replies = [_counts_to_bytes(x) for x in np.split(totals, ends[:-1])]
        return pa.table({"block": table["block"], "bucket": table["bucket"], "totals": pa.array(replies, pa.binary())})

    def score(texts: pa.Table, replies: pa.Table) -> pa.Table:
        found = texts["text"].to_pylist()
        _, keys, _ = ngram_keys(found, order)
        values = np.unique(np.concatenate(keys))
        ranked = sorted(zip(replies["bucket"].to_pylist(), replies["totals"].to_pylist(), strict=True))
        counts = np.concatenate([np.zeros(0, dtype=np.int64), *(_counts_from_bytes(x) for _, x in ranked)])
        sums = score_block(found, order, {"keys": values, "counts": counts}, leave_out)
        columns = {"id": texts["id"], **{k: pa.array(sums[k].astype(np.float64 if k == "log_sum" else np.int64)) for k in SUMS}}
        return pa.table(columns)

    # The same columns on both sides, so that texts are dealt once.
    asked = dealt.groupBy("block").applyInArrow(ask, "bucket int, block int, keys binary, counts binary")
    replies = asked.groupBy("bucket").applyInArrow(answer, "block int, bucket int, totals binary")
    schema = T.StructType([T.StructField("id", kind), T.StructField("n_tokens", T.LongType()), T.StructField("log_sum", T.DoubleType()), T.StructField("n_single", T.LongType()), T.StructField("n_unseen", T.LongType())])
    sums = saved(dealt.groupBy("block").cogroup(replies.groupBy("block")).applyInArrow(score, schema))
    corpus = sums.agg(F.sum("n_tokens").alias("n")).first().n or 0
    others = F.greatest(F.lit(corpus) - (F.col("n_tokens") if leave_out else F.lit(0)), F.lit(1))
    total = F.col("log_sum") - F.col("n_single") * F.log10(others) - F.col("n_unseen") * F.log10(others + 1)
    mean = F.col("log10_score") / F.nullif(F.col("n_tokens"), F.lit(0))
    rows = sums.select(F.col("id").alias(id_column), "n_tokens", total.alias("log10_score"))
    return rows.withColumn("mean_log10_score", mean)


SUMS = ("n_tokens", "log_sum", "n_single", "n_unseen")


def oracle_sql(order: int = 2) -> str:
    """The scores of order 2 by plain joins, for DuckDB."""
    if order != 2:
        raise ValueError("the SQL is for order 2")
    upper, lower = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
    return f"""
        WITH listed AS (
            SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), '{upper}', '{lower}'), '[^\\x20\\x09-\\x0D]+') AS ws
            FROM documents),
        word AS (SELECT doc_id, unnest(ws) AS w, unnest(range(len(ws))) AS i FROM listed),
        pair AS (SELECT doc_id, w, i, lag(w) OVER (PARTITION BY doc_id ORDER BY i) AS p FROM word),
        c1 AS (SELECT w, count(*) AS n FROM word GROUP BY w),
        o1 AS (SELECT doc_id, w, count(*) AS n FROM word GROUP BY doc_id, w),
        c2 AS (SELECT p, w, count(*) AS n FROM pair WHERE p IS NOT NULL GROUP BY p, w),
        o2 AS (SELECT doc_id, p, w, count(*) AS n FROM pair WHERE p IS NOT NULL GROUP BY doc_id, p, w),
        total AS (SELECT sum(len(ws)) AS n FROM listed),
        own AS (SELECT doc_id, len(ws) AS n FROM listed),
        counted AS (
            SELECT pair.doc_id, greatest(total.n - own.n, 1) AS others, c1.n - o1.n AS single,
                coalesce(cp.n - op.n, 0) AS context, coalesce(c2.n - o2.n, 0) AS whole
            FROM pair CROSS JOIN total JOIN own USING (doc_id) JOIN c1 ON c1.w = pair.w
            JOIN o1 ON o1.doc_id = pair.doc_id AND o1.w = pair.w
            LEFT JOIN c1 AS cp ON cp.w = pair.p LEFT JOIN o1 AS op ON op.doc_id = pair.doc_id AND op.w = pair.p
            LEFT JOIN c2 ON c2.p = pair.p AND c2.w = pair.w
            LEFT JOIN o2 ON o2.doc_id = pair.doc_id AND o2.p = pair.p AND o2.w = pair.w),
        scored AS (
            SELECT doc_id, CASE WHEN whole > 0 AND context > 0 THEN log10(whole / context)
                WHEN single > 0 THEN log10({BACKOFF} * single / others)
                ELSE log10({BACKOFF} * {BACKOFF} / (others + 1)) END AS s FROM counted)
        SELECT own.doc_id, own.n AS n_tokens, round(coalesce(sum(s), 0), 4) AS log10_score,
            round(sum(s) / nullif(own.n, 0), 4) AS mean_log10_score
        FROM own LEFT JOIN scored USING (doc_id) GROUP BY own.doc_id, own.n"""
