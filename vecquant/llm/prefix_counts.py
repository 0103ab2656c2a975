"""Exact token counts of every prefix, by dynamic programming over bytes.

For a byte-level vocabulary whose ranks follow its merges, the encoding of a prefix ends in the
one token that (a) is a suffix of the prefix and (b) stays unmerged behind the last token of
what precedes it. So one pass over the bytes of a split word gives the last token, and the
count, of each of its prefixes. Counts of words add up to counts of texts; they answer how many
tokens a cut text has, or how long a cut a budget allows, with no further encoding.
"""

from __future__ import annotations

import json
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from vecquant.llm import bpe
from vecquant.llm.common import single_column, text_slices


_SPACE = regex.compile(r"\s+")
#: Characters of a stretch of a long text, and of the longest words that are remembered.
_STRETCH, _CACHED_CHARS = 1 << 20, 256


class PrefixCounter:
    """Counts of prefixes for one vocabulary definition of the tokenizers library."""

    def __init__(self, definition: str, cache_entries: int = 600_000) -> None:
        spec = json.loads(definition)
        self._library = Tokenizer.from_str(definition)
        self._alphabet = bpe.byte_alphabet()
        self._token = {token: i for i, token in enumerate(bpe.byte_table(definition))}
        self._special = [t["content"] for t in spec.get("added_tokens", [])]
        for content in self._special:
            self._token.pop(content.encode(), None)
        self._longest = max(map(len, self._token))
        # Tokens by their bytes from last to first; a node's token is kept under -1.
        self._suffixes: dict = {}
        for token in self._token:
            node = self._suffixes
            for b in reversed(token):
                node = node.setdefault(b, {})
            node[-1] = token
        self._split = regex.compile(bpe.SPLIT_PATTERN)
        self._special_split = regex.compile("(" + "|".join(map(regex.escape, self._special)) + ")") if self._special else None
        self._pairs: dict[tuple[bytes, bytes], bool] = {}
        self._words: dict[str, int] = {}
        self._parts: dict[str, int] = {}
        self._limit = cache_entries

    def _stays(self, left: bytes, right: bytes) -> bool:
        """Whether encoding the two tokens' bytes together gives just these two."""
        known = self._pairs.get((left, right))
        if known is None:
            shown = "".join(self._alphabet[b] for b in left + right)
            made = self._library.model.tokenize(shown)
            known = len(made) == 2 and len(made[0].value) == len(left)
            if len(self._pairs) > self._limit:
                self._pairs.clear()
            self._pairs[left, right] = known
        return known

    def _last_tokens(self, raw: bytes) -> Iterator[int]:
        """Counts of all prefixes of one split word, by the last token of each.

        Only the last tokens of as many prefixes as the longest token has bytes are held.
        """
        tokens, longest, pairs, suffixes = self._token, self._longest, self._pairs, self._suffixes
        last: list[bytes] = [b""]
        counts = [0]
        gone = 0  # prefixes that no token reaches back to any more
        for end in range(1, len(raw) + 1):
            if end <= longest and raw[:end] in tokens:
                last.append(raw[:end])
                counts.append(1)
                yield 1
                continue
            node, at, count = suffixes, end - 1, 0
            while at > 0 and (node := node.get(raw[at])) is not None:
                right = node.get(-1)
                if right is not None:
                    pair = (last[at - gone], right)
                    if pairs[pair] if pair in pairs else self._stays(*pair):
                        count = counts[at - gone] + 1
                        break
                at -= 1
            last.append(right)
            counts.append(count)
            yield count
            if len(last) > 16 * longest:
                drop = len(last) - longest
                del last[:drop], counts[:drop]
                gone += drop

    def _final(self, raw: bytes) -> int:
        """Count of one whole split word."""
        count = 0
        for count in self._last_tokens(raw):  # noqa: B007
            pass
        return count

    def _word(self, text: str) -> np.ndarray:
        """Counts of the byte prefixes of a text without special strings."""
        parts: list[np.ndarray] = [np.zeros(0, dtype=np.int64)]
        base = 0
        for match in self._split.finditer(text):
            part = match.group()
            raw = part.encode()
            counts = np.fromiter(self._last_tokens(raw), dtype=np.int64, count=len(raw))
            if len(part) == 3 and part in bpe.CONTRACTIONS:  # of "'re" the prefix "'r" is a mark and a letter
                counts[1] = 2
            parts.append(counts + base)
            base = int(parts[-1][-1])
        plain = np.concatenate(parts)
        ends = plain.copy()
        # A prefix that ends in white space has that whole run as one word.
        seen = at = 0
        for run in _SPACE.finditer(text):
            at += len(text[seen : run.start()].encode())
            raw = run.group().encode()
            ends[at : at + len(raw)] = np.fromiter(self._last_tokens(raw), dtype=np.int64, count=len(raw)) + (plain[at - 1] if at else 0)
            at, seen = at + len(raw), run.end()
        return ends

    def _sum(self, text: str) -> int:
        """Count of a text without special strings: the last prefix of each of its split words."""
        parts, total = self._parts, 0
        for match in self._split.finditer(text):
            part = match.group()
            n = parts.get(part)
            if n is None:
                n = self._final(part.encode())
                if len(part) <= _CACHED_CHARS:
                    if len(parts) > self._limit:
                        parts.clear()
                    parts[part] = n
            total += n
        return total

    def counts(self, text: str) -> np.ndarray:
        """Token count of every byte prefix of the text, shortest first.

        Prefixes that end inside a character count the tokens of those bytes.
        """
        if self._special_split is None:
            return self._word(text)
        out, base = [np.zeros(0, dtype=np.int64)], 0
        for k, part in enumerate(self._special_split.split(text)):
            if k % 2:
                ends = self._word(part) + base
                ends[-1] = base + 1
                out.append(ends)
                base += 1
            elif part:
                out.append(self._word(part) + base)
                base = int(out[-1][-1])
        return np.concatenate(out)

    def total(self, text: str) -> int:
        """Count of the whole text: the last prefix of each word between single spaces."""
        if not text:
            return 0
        if any(s in text for s in self._special):
            # Odd parts are special strings, a token each; what is between them stands alone.
            return sum(1 if k % 2 else self.total(part) for k, part in enumerate(self._special_split.split(text)))
        known, total, start = self._words, 0, 0
        while start < len(text):
            # A long text is taken in stretches, each up to a place that no split word crosses.
            cut = bpe.CUT.search(text, start + _STRETCH) if len(text) - start > 2 * _STRETCH else None
            stop = cut.start() if cut else len(text)
            first, *rest = bpe.words_of(text[start:stop] if start or cut else text)
            total += self._sum(first)
            for w in rest:
                n = known.get(w)
                if n is None:
                    n = self._sum(" " + w)
                    if len(w) <= _CACHED_CHARS:
                        if len(known) > self._limit:
                            known.clear()
                        known[w] = n
                total += n
            start = stop
        return total

    def cut(self, text: str, budget: int) -> int:
        """Characters of the longest prefix of the text that has at most budget tokens."""
        counts = self.counts(text)
        fits = 0
        ends = np.cumsum([len(c.encode()) for c in text]) if text else np.zeros(0, dtype=np.int64)
        good = np.flatnonzero(counts[ends - 1] <= budget) if len(ends) else ends
        if len(good):
            fits = int(good[-1]) + 1
        return fits


def count_tokens(
    docs: DataFrame,
    definition_path: str,
    id_column: str = "doc_id",
    text_column: str = "text",
    limit: int = 1024,
    keep_prefixes: bool = False,
) -> DataFrame:
    """Bytes, tokens and whether the limit is passed, for every text.

    With keep_prefixes also prefix_tokens: the count at each byte prefix. A null text counts as
    empty: 0 bytes, 0 tokens. Time and, without keep_prefixes, the working memory beside the text
    are linear in its length and bounded by a stretch, one word of any length included. Strings of special tokens inside texts count as one token, as the
    library's default has it. Other columns are ignored, repeated rows stay.
    """
    with open(definition_path, encoding="utf-8") as file:
        definition = file.read()
    shipped, vocabulary = docs.sparkSession.sparkContext.broadcast(definition), bpe.digest(definition)
    kind = docs.schema[id_column].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counter = bpe.per_worker("prefix counts", vocabulary, lambda: PrefixCounter(shipped.value))
        for batch, texts in text_slices(batches, "text"):
            n_bytes = pa.array([len(t.encode()) for t in texts], pa.int64())
            if keep_prefixes:
                prefixes = [counter.counts(t) for t in texts]
                n_tokens = [int(p[-1]) if len(p) else 0 for p in prefixes]
            else:
                n_tokens = [counter.total(t) for t in texts]
            columns = [single_column(batch, "id"), n_bytes, pa.array(n_tokens, pa.int64())]
            columns.append(pa.array([n > limit for n in n_tokens], pa.bool_()))
            names = ["id", "n_bytes", "n_tokens", "over_limit"]
            if keep_prefixes:
                columns.append(pa.array(prefixes, pa.list_(pa.int64())))
                names.append("prefix_tokens")
            yield pa.RecordBatch.from_arrays(columns, names=names)

    schema = f"id {kind}, n_bytes long, n_tokens long, over_limit boolean" + ", prefix_tokens array<long>" * keep_prefixes
    rows = docs.select(F.col(id_column).alias("id"), F.col(text_column).alias("text")).mapInArrow(run, schema)
    return rows.withColumnRenamed("id", id_column)


def truncate_to_budget(
    docs: DataFrame, definition_path: str, budget: int, id_column: str = "doc_id", text_column: str = "text"
) -> DataFrame:
    """The longest prefix (whole characters) of every text with at most budget tokens."""
    with open(definition_path, encoding="utf-8") as file:
        definition = file.read()
    shipped, vocabulary = docs.sparkSession.sparkContext.broadcast(definition), bpe.digest(definition)
    kind = docs.schema[id_column].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        counter = bpe.per_worker("prefix counts", vocabulary, lambda: PrefixCounter(shipped.value))
        for batch, texts in text_slices(batches, "text"):
            cut = [t[: counter.cut(t, budget)] for t in texts]
            yield pa.RecordBatch.from_arrays([single_column(batch, "id"), pa.array(cut, pa.string())], names=["id", "text"])

    rows = docs.select(F.col(id_column).alias("id"), F.col(text_column).alias("text"))
    return rows.mapInArrow(run, f"id {kind}, text string").withColumnRenamed("id", id_column).withColumnRenamed("text", text_column)
