"""Counts of characters, words, lines and repeats of whole texts, over Arrow batches.

All counting is vectorized over slices of joined texts: bytes are mapped to classes and
counted per document, words are hashed once, and repeated windows are found by sorting hashes.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from vecquant.llm.common import single_column, text_slices

#: Character classes in the order of class_counts; non-ASCII characters count by their first byte.
CLASSES = ("lower", "upper", "digit", "space", "line", "stop", "mark", "symbol", "other", "wide")
_TAIL = len(CLASSES)

#: Frequent function words of the languages at hand.
COMMON_WORDS = {
    "en": "the of and to in is was for on that by with this as be are from it or at not have",
    "de": "der die und in den von zu das mit sich des auf für ist im dem nicht ein eine als",
    "fr": "de la le et les des en un du une que est pour qui dans par sur pas au plus avec",
    "es": "de la que el en y los se del las un por con no una su para es al lo como",
}


def _class_table() -> np.ndarray:
    table = np.full(256, CLASSES.index("other"), dtype=np.int64)
    for name, chars in {
        "lower": "abcdefghijklmnopqrstuvwxyz",
        "upper": "ABCDEFGHIJKLMNOPQRSTUVWXYZ",
        "digit": "0123456789",
        "space": " \t\x0b\x0c\r",
        "line": "\n",
        "stop": ".,;:?",
        "mark": "!\"'()-",
        "symbol": "#*$%&|<>",
    }.items():
        for c in chars:
            table[ord(c)] = CLASSES.index(name)
    table[0x80:0xC0] = _TAIL
    table[0xC0:] = CLASSES.index("wide")
    return table


_CLASS_OF = _class_table()


def common_word_list() -> list[str]:
    """The distinct common words, sorted."""
    return sorted({w for words in COMMON_WORDS.values() for w in words.split()})


def _common_lookup() -> tuple[np.ndarray, np.ndarray]:
    """Sorted hashes of the common words, also capitalized, and each one's place in the list."""
    pairs = [(hash(form.encode()), i) for i, w in enumerate(common_word_list()) for form in {w, w.capitalize(), w.upper()}]
    pairs.sort()
    return np.array([h for h, _ in pairs], dtype=np.int64), np.array([i for _, i in pairs], dtype=np.int64)


def repeated_window_words(hashes: np.ndarray, doc: np.ndarray, n_docs: int, width: int = 3) -> np.ndarray:
    """Per document, the words that lie in windows of `width` words found twice or more in it."""
    n = len(hashes) - width + 1
    if n < 2:
        return np.zeros(n_docs, dtype=np.int64)
    h = hashes.view(np.uint64)
    with np.errstate(over="ignore"):
        key = doc[:n].astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)
        for k in range(width):
            key = (key ^ h[k : n + k]) * np.uint64(0xFF51AFD7ED558CCD)
            key ^= key >> np.uint64(32)
    inside = np.flatnonzero(doc[:n] == doc[width - 1 :])
    key = key[inside]
    order = np.argsort(key)
    ranked = key[order]
    same = ranked[1:] == ranked[:-1]
    twice = np.zeros(len(ranked), dtype=bool)
    twice[1:] |= same
    twice[:-1] |= same
    starts = inside[order[twice]]
    covered = np.zeros(len(hashes), dtype=bool)
    for k in range(width):
        covered[starts + k] = True
    return np.bincount(doc[covered], minlength=n_docs)


def _repeated_lines(text: str) -> tuple[int, int]:
    """Lines with a word that equal an earlier line, and lines with a word."""
    seen: set[str] = set()
    repeats = full = 0
    for line in text.split("\n"):
        if line.strip(" \t\x0b\x0c\r"):
            full += 1
            if line in seen:
                repeats += 1
            seen.add(line)
    return repeats, full


def count_texts(texts: list[str]) -> dict[str, np.ndarray]:
    """The counts of every text, as arrays in the order of the texts."""
    n = len(texts)
    blobs = [t.encode() for t in texts]
    raw = np.frombuffer(b"".join(blobs), dtype=np.uint8)
    sizes = np.array([len(b) for b in blobs], dtype=np.int64)
    width = _TAIL + 1
    slot = np.repeat(np.arange(n, dtype=np.int64) * width, sizes) + _CLASS_OF[raw]
    classes = np.bincount(slot, minlength=n * width).reshape(n, width)
    words = [b.split() for b in blobs]
    n_words = np.array([len(w) for w in words], dtype=np.int64)
    flat = [w for ws in words for w in ws]
    hashes = np.fromiter(map(hash, flat), dtype=np.int64, count=len(flat))
    doc = np.repeat(np.arange(n, dtype=np.int64), n_words)
    known, place = _common_lookup()
    at = np.minimum(np.searchsorted(known, hashes), len(known) - 1)
    hit = known[at] == hashes
    n_common = len(common_word_list())
    common = np.bincount(doc[hit] * n_common + place[at[hit]], minlength=n * n_common).reshape(n, n_common)
    lines = np.array([_repeated_lines(t) for t in texts], dtype=np.int64).reshape(n, 2)
    chars = sizes - classes[:, _TAIL]
    blank = classes[:, CLASSES.index("space")] + classes[:, CLASSES.index("line")]
    return {
        "n_chars": chars,
        "n_words": n_words,
        "word_chars": chars - blank,
        "n_symbols": classes[:, CLASSES.index("symbol")],
        "n_lines": lines[:, 1],
        "n_dup_lines": lines[:, 0],
        "n_repeat_words": repeated_window_words(hashes, doc, n),
        "class_counts": classes[:, :_TAIL],
        "common_counts": common,
    }


COUNTS = ("n_chars", "n_words", "word_chars", "n_symbols", "n_lines", "n_dup_lines", "n_repeat_words")


def text_statistics(docs: DataFrame, text_column: str = "text", keep: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """The columns to keep, the counts, class_counts and common_counts of every row's text.

    A null text counts as empty. Every row stays, in any number of copies.
    """
    kept = [F.col(c).alias(f"keep{i}") for i, c in enumerate(keep)]
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch, texts in text_slices(batches, "text"):
            found = count_texts(texts)
            columns = [single_column(batch, f"keep{i}") for i in range(len(keep))]
            columns += [pa.array(found[c].astype(np.int64)) for c in COUNTS]
            columns += [_lists(found["class_counts"]), _lists(found["common_counts"])]
            yield pa.RecordBatch.from_arrays(columns, names=[*(f"keep{i}" for i in range(len(keep))), *COUNTS, "class_counts", "common_counts"])

    fields = [T.StructField(f"keep{i}", docs.schema[c].dataType) for i, c in enumerate(keep)]
    fields += [T.StructField(c, T.LongType()) for c in COUNTS]
    fields += [T.StructField(c, T.ArrayType(T.IntegerType())) for c in ("class_counts", "common_counts")]
    source = docs.select(*kept, F.col(text_column).alias("text"))
    rows = source.mapInArrow(run, T.StructType(fields))
    for i, c in enumerate(keep):
        rows = rows.withColumnRenamed(f"keep{i}", c)
    return rows


def _lists(values: np.ndarray) -> pa.Array:
    flat = pa.array(np.ascontiguousarray(values, dtype=np.int32).ravel())
    return pa.ListArray.from_arrays(np.arange(len(values) + 1, dtype=np.int32) * values.shape[1], flat)
