"""Quality rules: fixed repeat and length rules, then distance to language references.

A reference is the mean distribution of character classes and of common words over all
documents of a language that pass the fixed rules. A document is kept if the Jensen-Shannon
distances (base 2, 0 to 1) to the reference of its own language, and their sum, are within
limits; each is looked at only where the document is long enough for its histogram to mean
something. A language of few documents borrows from the main language nearest to the document.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from vecquant.llm.common import saved, single_column
from vecquant.llm.textstats import CLASSES, common_word_list, text_statistics

#: Shares are summed as integers of this unit, so that sums don't depend on their order.
_UNIT = 1_000_000


#: Languages whose means go to tasks by value; the means of more are joined to the documents.
SMALL_TABLE = 4_096


@dataclass(frozen=True)
class RuleLimits:
    """The rules' parameters.

    The three distance limits were set on the labelled documents of the given sf0.1 tables, a
    little above the largest distances of documents labelled good. prior_documents: as how many
    documents the nearest reference counts in a language's own mean.
    """

    min_words: int = 50
    max_repeat_percent: int = 50
    class_limit: float = 0.26
    word_limit: float = 0.335
    total_limit: float = 0.45
    min_class_chars: int = 200
    min_common_words: int = 100
    prior_documents: float = 20.0
    nearest_of: int = 64


def base_failed(limits: RuleLimits = RuleLimits()) -> Column:
    """Too few words, or too many of them in repeated windows."""
    short = F.col("n_words") < limits.min_words
    return short | (100 * F.col("n_repeat_words") > limits.max_repeat_percent * F.col("n_words"))


def _shares(batch: pa.RecordBatch) -> tuple[np.ndarray, np.ndarray]:
    """Distributions of classes and of common words (with all other words last) per row."""
    n = batch.num_rows
    classes = single_column(batch, "class_counts").flatten().to_numpy(zero_copy_only=False).reshape(n, -1).astype(float)
    common = single_column(batch, "common_counts").flatten().to_numpy(zero_copy_only=False).reshape(n, -1).astype(float)
    words = single_column(batch, "n_words").to_numpy(zero_copy_only=False)
    common = np.column_stack([common, words - common.sum(axis=1)])
    return tuple(x / np.maximum(1, x.sum(axis=1, keepdims=True)) for x in (classes, common))


def _bins() -> tuple[int, int]:
    """Numbers of class bins and of word bins."""
    return len(CLASSES), len(common_word_list()) + 1


def language_sums(stats: DataFrame, limits: RuleLimits = RuleLimits()) -> DataFrame:
    """language, n, sums: added-up distributions (classes, then common words) over the rows that pass the fixed rules.

    A task adds up its own rows; a language costs it one row a bin, whatever share of the rows it has.
    """
    width = sum(_bins()) + 1

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums: dict[str, np.ndarray] = {}

        def out() -> pa.RecordBatch:
            names = [k for k in sums for _ in range(width)]
            bins = list(range(width)) * len(sums)
            values = np.concatenate([*sums.values(), np.zeros(0, dtype=np.int64)])
            return pa.RecordBatch.from_arrays([pa.array(names, pa.string()), pa.array(bins, pa.int32()), pa.array(values)], names=["language", "bin", "value"])

        for batch in batches:
            if not batch.num_rows:
                continue
            units = np.rint(np.column_stack(_shares(batch)) * _UNIT).astype(np.int64)
            units = np.column_stack([units, np.ones(len(units), dtype=np.int64)])
            languages = np.array(single_column(batch, "language").to_pylist(), dtype=object)
            for name in set(languages):
                part = units[languages == name].sum(axis=0)
                sums[name] = sums[name] + part if name in sums else part
            if len(sums) > 1000:
                yield out()
                sums.clear()
        yield out()

    parts = stats.where(~base_failed(limits)).select("language", "n_words", "class_counts", "common_counts")
    totals = parts.mapInArrow(run, "language string, bin int, value long").groupBy("language", "bin").agg(F.sum("value").alias("value"))
    entries = F.array_sort(F.collect_list(F.struct("bin", "value")))
    by_language = totals.groupBy("language").agg(entries.alias("e"))
    return by_language.select("language", F.col("e")[width - 1]["value"].alias("n"), F.slice(F.col("e")["value"], 1, width - 1).alias("sums"))


def jensen_shannon(p: np.ndarray, q: np.ndarray) -> np.ndarray:
    """Distance, base 2, of each row of p to each row of q."""
    p, q = p[:, None, :], q[None, :, :]
    m = (p + q) / 2
    with np.errstate(divide="ignore", invalid="ignore"):
        left = np.where(p > 0, p * np.log2(p / m), 0).sum(axis=2)
        right = np.where(q > 0, q * np.log2(q / m), 0).sum(axis=2)
    return np.sqrt(np.clip((left + right) / 2, 0, 1))


def _paired(p: np.ndarray, q: np.ndarray) -> np.ndarray:
    """Distance, base 2, of each row of p to the same row of q."""
    m = (p + q) / 2
    with np.errstate(divide="ignore", invalid="ignore"):
        both = np.where(p > 0, p * np.log2(p / m), 0).sum(axis=1) + np.where(q > 0, q * np.log2(q / m), 0).sum(axis=1)
    return np.sqrt(np.clip(both / 2, 0, 1))


def quality_rules(
    docs: DataFrame,
    id_column: str = "doc_id",
    text_column: str = "text",
    language_column: str = "lang",
    limits: RuleLimits = RuleLimits(),
) -> DataFrame:
    """Counts, distances and verdict of every row.

    Rows: the id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed,
    kept, class_distance, word_distance (both to the one reference of the document's language;
    null where the document is too short or no document passes the fixed rules) and
    nearest_language. A null text has no words and so fails; a null language counts as "und", a
    language of its own. Ties of nearest references go to the language with more documents, then
    by name. Every row stays, repeated ones too; an empty table gives no rows; other columns are
    ignored. A text is counted whole; working memory is a few times that of the longest text.
    """
    language = F.coalesce(F.col(language_column), F.lit("und"))
    source = docs.select(F.col(id_column).alias("id"), F.col(text_column).alias("text"), language.alias("language"))
    stats = saved(text_statistics(source, "text", ("id", "language")))
    judged = judge(stats, language_sums(stats, limits), limits).withColumnRenamed("id", id_column)
    counts = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words"]
    return judged.select(id_column, *counts, "base_failed", "kept", "class_distance", "word_distance", "nearest_language")


def keep_clean(
    docs: DataFrame, text_column: str = "text", language_column: str = "lang", limits: RuleLimits = RuleLimits()
) -> DataFrame:
    """The rows whose document the rules keep, with their own columns.

    Two passes over the texts: one sums up the references, one judges each row where it is read,
    so that no text moves between tasks.
    """
    places = [f"c{i}" for i in range(len(docs.columns))]
    source = docs.toDF(*places).withColumns(
        {"text": F.col(places[docs.columns.index(text_column)]), "language": F.coalesce(F.col(places[docs.columns.index(language_column)]), F.lit("und"))}
    )
    sums = language_sums(text_statistics(source, "text", ("language",)), limits)
    judged = judge(text_statistics(source, "text", (*places, "language")), sums, limits)
    return judged.where("kept").select(*places).toDF(*docs.columns)


def _distances(
    shares: tuple[np.ndarray, np.ndarray], own: np.ndarray, weight: np.ndarray, main: np.ndarray, limits: RuleLimits
) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Class and word distance of each row to its reference, and the place of the nearest main reference.

    own: each row's language mean, as weight documents. main: means of the main languages.
    """
    n_classes, _ = _bins()
    n = len(weight)
    by_class, by_word, nearest = np.empty(n), np.empty(n), np.empty(n, dtype=np.int64)
    step = max(1, 1_000_000 // main.size)
    for a in range(0, n, step):
        some = slice(a, min(n, a + step))
        classes, words = shares[0][some], shares[1][some]
        both = jensen_shannon(classes, main[:, :n_classes]) + jensen_shannon(words, main[:, n_classes:])
        nearest[some] = both.argmin(axis=1)
        share = (weight[some] / (weight[some] + limits.prior_documents))[:, None]
        mean = share * own[some] + (1 - share) * main[nearest[some]]
        by_class[some] = _paired(classes, mean[:, :n_classes])
        by_word[some] = _paired(words, mean[:, n_classes:])
    return by_class, by_word, nearest


def judge(stats: DataFrame, sums: DataFrame, limits: RuleLimits, small_table: int = SMALL_TABLE) -> DataFrame:
    """Statistics with distances, base_failed and kept; every column of stats stays.

    A document's reference is the mean of its language, in which the nearest of the
    nearest_of languages with most documents counts as prior_documents documents: a language
    with many documents is judged by itself, one with few by the language it is most like, and
    there is no size at which a rule sets in.
    """
    sums = saved(sums)
    top = sums.orderBy(F.desc("n"), "language").limit(limits.nearest_of).collect()
    names = [r.language for r in top]
    width, kept_columns = sum(_bins()), stats.columns
    main = np.array([r.sums for r in top], dtype=float).reshape(-1, width) / _UNIT / np.array([[r.n] for r in top], dtype=float).reshape(-1, 1)
    known: dict[str, tuple[int, np.ndarray]] | None = None
    source = stats
    if sums.limit(small_table + 1).count() <= small_table:
        known = {r.language: (r.n, np.array(r.sums, dtype=float) / _UNIT / r.n) for r in sums.collect()}
    else:
        own = sums.select(F.col("language").alias("own_language"), F.col("n").alias("own_n"), F.col("sums").alias("own_sums"))
        source = stats.join(own, stats.language == own.own_language, "left").drop("own_language")
    nothing = (0, np.zeros(width))

    def means(batch: pa.RecordBatch) -> tuple[np.ndarray, np.ndarray]:
        if known is not None:
            found = [known.get(x, nothing) for x in single_column(batch, "language").to_pylist()]
            return np.array([m for _, m in found]), np.array([n for n, _ in found], dtype=float)
        weight = np.nan_to_num(single_column(batch, "own_n").to_numpy(zero_copy_only=False).astype(float))
        rows = [x or nothing[1] for x in single_column(batch, "own_sums").to_pylist()]
        return np.array(rows, dtype=float) / _UNIT / np.maximum(weight, 1)[:, None], weight

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            n = batch.num_rows
            if not n:
                continue
            by_class, by_word, nearest = np.full(n, np.nan), np.full(n, np.nan), [None] * n
            if names:
                by_class, by_word, places = _distances(_shares(batch), *means(batch), main, limits)
                nearest = [names[k] for k in places.tolist()]
                by_class[single_column(batch, "n_chars").to_numpy() < limits.min_class_chars] = np.nan
                by_word[single_column(batch, "n_words").to_numpy() < limits.min_common_words] = np.nan
            columns = [single_column(batch, c) for c in kept_columns]
            columns += [pa.array(by_class, from_pandas=True), pa.array(by_word, from_pandas=True), pa.array(nearest, pa.string())]
            yield pa.RecordBatch.from_arrays(columns, names=schema.names)

    schema = T.StructType([*stats.schema.fields, T.StructField("class_distance", T.DoubleType()), T.StructField("word_distance", T.DoubleType()), T.StructField("nearest_language", T.StringType())])
    rows = source.mapInArrow(run, schema)
    by_class, by_word = F.coalesce("class_distance", F.lit(0.0)), F.coalesce("word_distance", F.lit(0.0))
    far = (by_class > limits.class_limit) | (by_word > limits.word_limit) | (by_class + by_word > limits.total_limit)
    failed = base_failed(limits)
    return rows.withColumns({"base_failed": failed, "kept": ~failed & ~far})
