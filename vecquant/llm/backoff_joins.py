"""Stupid-backoff scores by joins of count tables with exploded n-grams.

Every document is exploded into a row for each distinct n-gram of the longest length, with how
often it stands there and the shorter n-grams it may back off to. The rows are dealt by the
n-gram's hash; the count table is their sum by n-gram, on the same partitions, and joins back
to them. What a row still needs, the count of one shorter n-gram, comes from a second join, and
sums per document end it. Each document's own words are left out of its counts.

The most frequent n-grams never travel: a bounded table of their counts goes to every task,
which settles their rows where it reads them. It is chosen from a sample of documents and
counted over all of them, so it only decides where a row is settled, not what it says. That
leaves no n-gram with very many rows to one task, and every step is in proportion to the input.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from vecquant.llm.common import saved, single_column, text_slices
from vecquant.llm.ngrams import BACKOFF, ngram_keys

#: Scores are added up as integers of this unit, so that sums don't depend on their order.
UNIT = 1 << 32
#: Entries of the tables of frequent n-grams: of the shorter lengths, and of the longest.
SHORT_TABLE, LONG_TABLE = 1 << 18, 1 << 19
#: One document in this many is looked at for candidates of the second table.
SAMPLE = 8
_SLICE = 2_000_000


def _runs(key: np.ndarray, doc: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Of each (n-gram, document): a place, its count; and the count at every place."""
    order = np.argsort(key, kind="stable")  # documents stay in order within equal keys
    k, d = key[order], doc[order]
    new = np.ones(len(k), dtype=bool)
    new[1:] = (k[1:] != k[:-1]) | (d[1:] != d[:-1])
    cuts = np.flatnonzero(new)
    counts = np.diff(np.append(cuts, len(k)))
    everywhere = np.empty(len(k), dtype=np.int64)
    everywhere[order] = np.repeat(counts, counts)
    return order[cuts], counts, everywhere


class Table:
    """Counts of frequent n-grams by sorted hashes."""

    def __init__(self, keys: np.ndarray, counts: np.ndarray) -> None:
        order = np.argsort(keys)
        self.keys, self.counts = keys[order], counts[order]

    def find(self, keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Places of the keys, and whether they are there."""
        if not len(self.keys):
            return np.zeros(len(keys), dtype=np.int64), np.zeros(len(keys), dtype=bool)
        at = np.minimum(np.searchsorted(self.keys, keys), len(self.keys) - 1)
        return at, self.keys[at] == keys


def _names(order: int) -> list[str]:
    """The shorter n-grams that a row may need, in the order it asks: x{n} is the context of length n, g{n} the n-gram itself."""
    return [f"x{order}", *(name for n in range(order - 1, 0, -1) for name in ([f"g{n}", f"x{n}"] if n > 1 else [f"g{n}"]))]


def _explode(texts: list[str], order: int, short: Table, long: Table) -> dict[str, np.ndarray]:
    """Rows of a slice: doc, key, m, rest, and (value, own) of every name; m = 0 marks a document's own row.

    own > 0: value is the hash of an n-gram to be looked up. own = 0: value is its count without
    the document. rest: the count of the longest n-gram without the document, null (-1) if open.
    A document's row has its settled score in rest, words in the first value, and words settled
    by their own count or by none in the first two owns.
    """
    sizes, keys, owners = ngram_keys(texts, order)
    total, docs = int(sizes.sum()), len(texts)
    doc = owners[0]
    place = np.arange(total) - np.repeat(np.cumsum(sizes) - sizes, sizes)
    counted = [_runs(k, o) for k, o in zip(keys, owners, strict=True)]
    # Where the n-gram of each length that ends at a word is listed.
    index = []
    for n in range(1, order + 1):
        spot = np.full(total, -1)
        ends = np.flatnonzero(place >= n - 1)
        spot[ends] = np.arange(len(ends))
        index.append(spot)
    ends = np.flatnonzero(place >= order - 1)
    first, often, _ = counted[order - 1]
    word = np.concatenate([ends[first], np.flatnonzero(place < order - 1)])  # the last word of each row's n-gram
    begins = len(word) - len(first)
    key = np.concatenate([keys[order - 1][first], np.zeros(begins, dtype=np.uint64)])
    m = np.concatenate([often, np.ones(begins, dtype=np.int64)])
    at, known = long.find(key)
    known[len(first) :] = False
    rest = np.where(known, long.counts[at] - m if len(long.keys) else 0, -1)
    rest[len(first) :] = 0  # too near the start of the text for an n-gram of that length
    value, own = {}, {}
    for name in _names(order):
        n = int(name[1:]) - (name[0] == "x")
        there = place[word] - (name[0] == "x") >= n - 1
        spot = index[n - 1][np.maximum(word - (name[0] == "x"), 0)]
        spot = np.where(there, spot, 0)
        hashed = keys[n - 1][spot] if len(keys[n - 1]) else np.zeros(len(word), dtype=np.uint64)
        counts = counted[n - 1][2][spot] if len(keys[n - 1]) else np.zeros(len(word), dtype=np.int64)
        spot_in, hit = short.find(hashed)
        rest_of = short.counts[spot_in] - counts if len(short.keys) else counts
        settled = hit | ~there
        value[name] = np.where(there, np.where(hit, rest_of, hashed.view(np.int64)), 0)
        own[name] = np.where(settled, 0, counts)
    done, score, single, unseen = _settle(order, rest, value, own)
    row_doc = doc[word]
    gone = np.flatnonzero(done)
    fixed = np.rint(score[gone] * UNIT).astype(np.int64) * m[gone]
    sums = {"s": np.zeros(docs, dtype=np.int64), "u": np.zeros(docs, dtype=np.int64), "v": np.zeros(docs, dtype=np.int64)}
    np.add.at(sums["s"], row_doc[gone], fixed)
    sums["u"] = np.bincount(row_doc[gone], weights=(single * m)[gone], minlength=docs).astype(np.int64)
    sums["v"] = np.bincount(row_doc[gone], weights=(unseen * m)[gone], minlength=docs).astype(np.int64)
    left = np.flatnonzero(~done)
    names = _names(order)
    out = {"doc": np.concatenate([np.arange(docs), row_doc[left]]), "m": np.concatenate([np.zeros(docs, dtype=np.int64), m[left]])}
    mixed = (np.arange(docs, dtype=np.uint64) + np.uint64(1)) * np.uint64(0x9E3779B97F4A7C15)
    out["key"] = np.concatenate([mixed, key[left]]).view(np.int64)
    out["rest"] = np.concatenate([sums["s"], rest[left]])
    for k, name in enumerate(names):
        head = (sizes, sums["u"]) if k == 0 else (np.zeros(docs, dtype=np.int64), sums["v"] if k == 1 else np.zeros(docs, dtype=np.int64))
        out[name] = np.concatenate([head[0], value[name][left]])
        out[f"o{name}"] = np.concatenate([head[1], own[name][left]])
    return out


def _settle(order: int, rest: np.ndarray, value: dict[str, np.ndarray], own: dict[str, np.ndarray]) -> tuple[np.ndarray, ...]:
    """Which rows can be scored without a lookup; their scores (without the corpus size), and which fell to one word or to none."""
    n_rows = len(rest)
    done, score = np.zeros(n_rows, dtype=bool), np.zeros(n_rows)
    single, unseen = np.zeros(n_rows, dtype=bool), np.zeros(n_rows, dtype=bool)
    open_ = rest >= 0
    whole = rest
    with np.errstate(divide="ignore", invalid="ignore"):
        for n in range(order, 0, -1):
            if n < order:
                open_ &= own[f"g{n}"] == 0
                whole = value[f"g{n}"]
            seen = open_ & (whole > 0)
            if n == 1:
                single, unseen = seen, open_ & ~seen
                score[seen] = np.log10(whole[seen]) + (order - 1) * np.log10(BACKOFF)
                score[unseen] = order * np.log10(BACKOFF)
                done |= open_
                break
            now = seen & (own[f"x{n}"] == 0)
            score[now] = np.log10(whole[now] / value[f"x{n}"][now]) + (order - n) * np.log10(BACKOFF)
            done |= now
            open_ &= ~seen
    return done, score, single, unseen


def _outcome(order: int, n: int) -> str:
    """SQL of a row's state from length n on: score, single, unseen, and the name it has to look up (else null)."""
    state = lambda score, single=0, unseen=0, need="null": f"named_struct('score', CAST({score} AS DOUBLE), 'single', {single}, 'unseen', {unseen}, 'need', CAST({need} AS STRING))"
    fall = (order - n) * np.log10(BACKOFF)
    whole = "rest" if n == order else f"g{n}"
    if n == 1:
        body = f"IF({whole} > 0, {state(f'log10({whole}) + {float(fall)!r}D', single=1)}, {state(f'{float(order * np.log10(BACKOFF))!r}D', unseen=1)})"
    else:
        context = f"IF(ox{n} > 0, {state('0D', need=chr(39) + f'x{n}' + chr(39))}, {state(f'log10({whole} / x{n}) + {float(fall)!r}D')})"
        body = f"IF({whole} > 0, {context}, {_outcome(order, n - 1)})"
    return body if n == order else f"IF(og{n} > 0, {state('0D', need=chr(39) + f'g{n}' + chr(39))}, {body})"


def _frequent(counts: DataFrame, most: int) -> tuple[np.ndarray, np.ndarray]:
    """At most `most` n-grams of highest count, to the driver: those from a count on that so many reach."""
    step = F.floor(F.log2("n") * 8).cast("int")
    found, cut = 0, None
    for row in counts.groupBy(step.alias("step")).agg(F.count("*").alias("grams")).orderBy(F.desc("step")).collect():
        found += row.grams
        if found > most:
            break
        cut = row.step
    if cut is None:
        return np.zeros(0, dtype=np.uint64), np.zeros(0, dtype=np.int64)
    rows = counts.where(step >= cut).select("gram", "n").toPandas()
    return rows["gram"].to_numpy(dtype=np.int64).view(np.uint64), rows["n"].to_numpy(dtype=np.int64)


def score_documents(docs: DataFrame, id_column: str = "doc_id", text_column: str = "text", order: int = 2) -> DataFrame:
    """The id, n_tokens, log10_score (sum over words), mean_log10_score of every row.

    A word's score is the count of the longest n-gram (up to order, 2 or more) that ends in it
    over the count of that n-gram without the word; each shorter length costs a factor 0.4. A
    word that occurs nowhere else scores 0.4 ** order over the other words plus one. A row's own
    words don't count for it. Counts are of all rows, repeated ones too. A text without words
    (null, empty) has 0 tokens, score 0 and a null mean. Ties don't arise. Every row stays; other
    columns are ignored; an empty table gives no rows. Texts of any length are taken whole; a
    task holds a few times its longest text. Rows have to come in the same order when they are
    read again, as those of files do.
    """
    if order < 2:
        raise ValueError("order has to be 2 at least")
    spark = docs.sparkSession
    kind = docs.schema[id_column].dataType
    source = docs.select(F.monotonically_increasing_id().alias("doc"), F.col(id_column).alias("id"), F.coalesce(F.col(text_column), F.lit("")).alias("text"))

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Counts of shorter n-grams by slice, and of the longest ones of sampled documents (sampled = 1)."""
        for batch, texts in text_slices(batches, "text", _SLICE):
            _, keys, owners = ngram_keys(texts, order)
            gram, n = np.unique(np.concatenate(keys[:-1]), return_counts=True)
            chosen = single_column(batch, "doc").to_numpy().view(np.uint64) * np.uint64(0x9E3779B97F4A7C15) >> np.uint64(32)
            more, often = np.unique(keys[-1][(chosen % np.uint64(SAMPLE) == 0)[owners[-1]]], return_counts=True)
            columns = [np.concatenate([gram, more]).view(np.int64), np.concatenate([n, often]).astype(np.int64), np.repeat([0, 1], [len(gram), len(more)]).astype(np.int8)]
            yield pa.RecordBatch.from_arrays([pa.array(c) for c in columns], names=["gram", "n", "sampled"])

    texts_only = source.select("doc", "text")
    counted = texts_only.mapInArrow(count, "gram long, n long, sampled tinyint").groupBy("gram", "sampled").agg(F.sum("n").alias("n"))
    counted = saved(counted.where("sampled = 0 or n > 1"))
    lower = counted.where("sampled = 0").select("gram", "n")
    short = spark.sparkContext.broadcast(Table(*_frequent(lower, SHORT_TABLE)))
    candidates = spark.sparkContext.broadcast(np.sort(_frequent(counted.where("sampled = 1"), LONG_TABLE)[0]))

    def exact(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Counts of the candidates over all documents of a task."""
        table = Table(candidates.value, candidates.value)
        total = np.zeros(len(table.keys), dtype=np.int64)
        for _, texts in text_slices(batches, "text", _SLICE):
            at, hit = table.find(ngram_keys(texts, order)[1][-1])
            total += np.bincount(at[hit], minlength=len(total))
        used = np.flatnonzero(total)
        yield pa.RecordBatch.from_arrays([pa.array(table.keys[used].view(np.int64)), pa.array(total[used])], names=["gram", "n"])

    rows = texts_only.mapInArrow(exact, "gram long, n long").groupBy("gram").agg(F.sum("n").alias("n")).toPandas()
    long = spark.sparkContext.broadcast(Table(rows["gram"].to_numpy(dtype=np.int64).view(np.uint64), rows["n"].to_numpy(dtype=np.int64)))
    names = _names(order)
    columns = ["doc", "key", "m", "rest", *(c for n in names for c in (n, f"o{n}"))]

    def explode(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch, texts in text_slices(batches, "text", _SLICE):
            made = _explode(texts, order, short.value, long.value)
            made["doc"] = single_column(batch, "doc").to_numpy()[made["doc"]]
            ids = pa.concat_arrays([single_column(batch, "id"), pa.nulls(len(made["m"]) - len(texts), single_column(batch, "id").type)])
            arrays = [pa.array(made[c], pa.int32() if c == "m" or c[0] == "o" else pa.int64()) for c in columns]
            yield pa.RecordBatch.from_arrays([ids, *arrays], names=["id", *columns])

    fields = [T.StructField("id", kind)] + [T.StructField(c, T.IntegerType() if c == "m" or c[0] == "o" else T.LongType()) for c in columns]
    dealt = source.mapInArrow(explode, T.StructType(fields)).repartition("key")
    # Every column is named, so that the count table reads the rows from the same exchange.
    mine = (F.col("m") > 0) & (F.col("rest") < 0) & (F.xxhash64("id", *columns) >= F.lit(-(2**63)))
    table = dealt.groupBy("key").agg(F.sum(F.when(mine, F.col("m")).otherwise(0)).alias("whole"))
    joined = dealt.join(table, "key")
    is_doc = F.col("m") == 0
    rest = F.when(is_doc | (F.col("rest") >= 0), F.col("rest")).otherwise(F.col("whole") - F.col("m"))
    state = joined.withColumn("rest", rest).withColumn("o", F.when(is_doc, None).otherwise(F.expr(_outcome(order, order))))
    sums = _collect(state, order, is_doc)
    for _ in range(2 * (order - 1) - 1):
        # Each round looks up one shorter n-gram of the rows that are still open.
        waiting = sums.where("need is not null")
        wanted = F.coalesce(*[F.when(F.col("need") == n, F.col(n)) for n in names])
        found = waiting.withColumn("gram", wanted).join(lower.withColumnRenamed("n", "c"), "gram")
        for n in names:
            mine = F.col("need") == n
            found = found.withColumns({n: F.when(mine, F.col("c") - F.col(f"o{n}")).otherwise(F.col(n)), f"o{n}": F.when(mine, 0).otherwise(F.col(f"o{n}"))})
        state = found.select("id", "doc", "m", "rest", *columns[4:]).withColumn("o", F.expr(_outcome(order, order)))
        more = _collect(state, order, F.lit(False), keep=False)
        sums = more.unionByName(sums.where("need is null"))
        if order > 2:
            sums = saved(sums)
    whole = sums.groupBy("doc").agg(F.max("id").alias("id"), *[F.sum(c).alias(c) for c in ("s", "u", "v", "t")])
    whole = saved(whole)
    corpus = whole.agg(F.sum("t").alias("n")).first().n or 0
    others = F.greatest(F.lit(corpus) - F.col("t"), F.lit(1))
    score = F.col("s") / UNIT - F.col("u") * F.log10(others) - F.col("v") * F.log10(others + 1)
    out = whole.select(F.col("id").alias(id_column), F.col("t").alias("n_tokens"), score.alias("log10_score"))
    return out.withColumn("mean_log10_score", F.col("log10_score") / F.nullif(F.col("n_tokens"), F.lit(0)))


def _collect(state: DataFrame, order: int, is_doc: Column, keep: bool = True) -> DataFrame:
    """Settled rows summed by document, open ones (need not null) with what they still ask."""
    names = _names(order)
    need = F.col("o.need")
    open_ = [F.when(need.isNotNull(), F.col(c)).alias(c) for c in ("m", "rest", *(c for n in names for c in (n, f"o{n}")))]
    fixed = F.round(F.col("o.score") * UNIT).cast("long") * F.col("m")
    rows = state.select(
        "id", "doc", need.alias("need"), *open_,
        F.when(is_doc, F.col("rest")).when(need.isNull(), fixed).otherwise(0).alias("s"),
        F.when(is_doc, F.col(f"o{names[0]}")).when(need.isNull(), F.col("o.single") * F.col("m")).otherwise(0).cast("long").alias("u"),
        F.when(is_doc, F.col(f"o{names[1]}")).when(need.isNull(), F.col("o.unseen") * F.col("m")).otherwise(0).cast("long").alias("v"),
        F.when(is_doc, F.col(names[0])).otherwise(0).alias("t"),
    )
    by = ["doc", "need", "m", "rest", *(c for n in names for c in (n, f"o{n}"))]
    out = rows.groupBy(*by).agg(F.max("id").alias("id"), *[F.sum(c).alias(c) for c in ("s", "u", "v", "t")])
    return saved(out) if keep else out
