"""Byte-level BPE over texts with the tokenizers library and a bounded cache of pieces.

A text is cut before every single space that a non-space character follows. No match of
the byte-level split pattern crosses such a place: words carry at most one leading space and
runs of white space give up their last space to the word behind. Each piece therefore has the
same ids wherever it stands, and pieces that recur are encoded once per worker.
"""

from __future__ import annotations

import base64
import hashlib
import json
import re
import sys
from array import array
from collections.abc import Callable

import numpy as np
from tokenizers import Tokenizer

#: The split pattern of the byte-level vocabulary and its contractions.
SPLIT_PATTERN = r"""'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"""
CONTRACTIONS = ("'s", "'t", "'re", "'ve", "'m", "'ll", "'d")
_ODD_SPACE = re.compile(r" (?:\s|$)")
CUT = re.compile(r" (?=\S)")


def byte_alphabet() -> list[str]:
    """Character that stands for each byte: printable Latin-1 for itself, the rest from U+0100 on."""
    shown = [*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)]
    table = {b: chr(b) for b in shown}
    for b in range(256):
        table.setdefault(b, chr(0x100 + len(table) - len(shown)))
    return [table[b] for b in range(256)]


def read_ranks(path: str) -> dict[bytes, int]:
    """Token bytes to rank, from a file of base64 tokens and numbers."""
    ranks = {}
    with open(path, "rb") as lines:
        for line in lines:
            if line.strip():
                token, rank = line.split()
                ranks[base64.b64decode(token)] = int(rank)
    return ranks


def _last_merge(ranks: dict[bytes, int], token: bytes) -> tuple[bytes, bytes]:
    """The two tokens whose merge makes this token, found by merging with lower ranks only."""
    own, parts = ranks[token], [token[i : i + 1] for i in range(len(token))]
    while len(parts) > 2:
        best = min(range(len(parts) - 1), key=lambda i: ranks.get(parts[i] + parts[i + 1], own))
        if ranks.get(parts[best] + parts[best + 1], own) >= own:
            raise ValueError(f"no merges lead to the token {token!r}")
        parts[best : best + 2] = [parts[best] + parts[best + 1]]
    return parts[0], parts[1]


def tokenizer_json(ranks: dict[bytes, int]) -> str:
    """A tokenizers model, without special tokens, that encodes as these ranks do."""
    alphabet = byte_alphabet()
    shown = lambda token: "".join(alphabet[b] for b in token)
    merges = [
        [shown(x) for x in _last_merge(ranks, token)]
        for token, _ in sorted(ranks.items(), key=lambda x: x[1])
        if len(token) > 1
    ]
    level = {"type": "ByteLevel", "add_prefix_space": False, "trim_offsets": False, "use_regex": True}
    model = {
        "type": "BPE", "dropout": None, "unk_token": None, "continuing_subword_prefix": None,
        "end_of_word_suffix": None, "fuse_unk": False, "byte_fallback": False,
        "vocab": {shown(t): r for t, r in ranks.items()}, "merges": merges,
    }
    return json.dumps(
        {
            "version": "1.0", "truncation": None, "padding": None, "added_tokens": [], "normalizer": None,
            "pre_tokenizer": level, "post_processor": None, "decoder": level, "model": model,
        }
    )


def byte_table(definition: str) -> list[bytes]:
    """Bytes of every id, by the reversed byte alphabet; special tokens stand for their text."""
    spec = json.loads(definition)
    back = {c: b for b, c in enumerate(byte_alphabet())}
    vocab = spec["model"]["vocab"]
    special = {t["id"]: t["content"].encode() for t in spec.get("added_tokens", [])}
    table = [b""] * (1 + max([*vocab.values(), *special]))
    for token, number in vocab.items():
        table[number] = special[number] if number in special else bytes(back[c] for c in token)
    for number, content in special.items():
        table[number] = content
    return table


def words_of(text: str) -> list[str]:
    """Cut at single spaces that a non-space character follows; joined by spaces, they are the text."""
    return text.split(" ") if _ODD_SPACE.search(text) is None else CUT.split(text)


class _Library:
    """Encodes with the tokenizers library."""

    def __init__(self, definition: str) -> None:
        self._model = Tokenizer.from_str(definition)

    def __call__(self, text: str) -> np.ndarray:
        return np.array(self._model.encode(text, add_special_tokens=False).ids, dtype="<u4")


class PieceEncoder:
    """Ids of texts by the library, with the ids of pieces kept in a bounded cache."""

    def __init__(self, definition: str, cache_entries: int = 700_000) -> None:
        self.whole = _Library(definition)
        self._special = [t["content"] for t in json.loads(definition).get("added_tokens", [])]
        self._width = np.array([len(x) for x in byte_table(definition)], dtype=np.int64)
        self._cache: dict[str, bytes] = {}
        self._limit = cache_entries

    def _learn(self, words: list[str]) -> None:
        """Encode new words, each with a space before it, in calls over many words.

        In the joined text each word starts with its space, so that no token spans two of them.
        """
        cache = self._cache
        for start in range(0, len(words), 2000):
            some = words[start : start + 2000]
            sizes = np.array([len(w.encode()) + 1 for w in some], dtype=np.int64)
            ids = self.whole(" " + " ".join(some))
            own = np.searchsorted(np.cumsum(sizes), np.cumsum(self._width[ids]), side="left")
            bounds = (4 * np.searchsorted(own, np.arange(len(some) + 1))).tolist()
            raw = ids.tobytes()
            for k, w in enumerate(some):
                cache[w] = raw[bounds[k] : bounds[k + 1]]

    def _ids(self, texts: list[str]) -> list[bytes]:
        out: list[bytes] = []
        for start in range(0, len(texts), 500):
            cut = [words_of(t) for t in texts[start : start + 500]]
            new = set().union(*[w[1:] for w in cut]).difference(self._cache)
            if len(self._cache) + len(new) > self._limit:
                self._cache.clear()
                new = set().union(*[w[1:] for w in cut])
            # Words that end in white space would meet the next one's space.
            loose = {w for w in new if not w or w != w.strip()}
            for w in loose:
                self._cache[w] = self.whole(" " + w).tobytes()
            self._learn(list(new - loose))
            get = self._cache.__getitem__
            for words in cut:
                head = self.whole(words[0]).tobytes() if words[0] else b""
                out.append(head + b"".join(map(get, words[1:])))
        return out

    def encode(self, texts: list[str]) -> list[bytes]:
        """Ids of each text as little-endian unsigned 32-bit integers.

        Texts that hold the string of a special token are encoded whole.
        """
        odd = {i for i, t in enumerate(texts) if any(s in t for s in self._special)}
        plain = iter(self._ids([t for i, t in enumerate(texts) if i not in odd]))
        return [self.whole(t).tobytes() if i in odd else next(plain) for i, t in enumerate(texts)]


class RankedEncoder:
    """Ids of one text at a time through tiktoken, over a vocabulary of the tokenizers library.

    The library itself encodes texts that hold a special token's string, as its default has it.
    """

    def __init__(self, definition: str) -> None:
        import tiktoken

        self._special = [t["content"] for t in json.loads(definition).get("added_tokens", [])]
        self._definition = definition
        self._library: _Library | None = None
        table = byte_table(definition)
        ranks = {t: i for i, t in enumerate(table) if t and t.decode("utf-8", "replace") not in self._special}
        model = tiktoken.Encoding("ranked", pat_str=SPLIT_PATTERN, mergeable_ranks=ranks, special_tokens={})
        self._ordinary = model.encode_ordinary

    def encode(self, text: str) -> bytes:
        """Ids as little-endian unsigned 32-bit integers."""
        for s in self._special:
            if s in text:  # rare, so the library is made at first need
                self._library = self._library or _Library(self._definition)
                return self._library(text).tobytes()
        ids = array("I", self._ordinary(text))
        if sys.byteorder == "big":
            ids.byteswap()
        return ids.tobytes()


def digest(definition: str) -> str:
    """Short name of a vocabulary definition, by its content."""
    return hashlib.sha256(definition.encode()).hexdigest()[:16]


_KEPT: dict[str, tuple[str, object]] = {}


def per_worker(role: str, vocabulary: str, make: Callable[[], object]) -> object:
    """One object a worker process and role, made anew whenever the vocabulary's digest changes."""
    known = _KEPT.get(role)
    if known is None or known[0] != vocabulary:
        known = _KEPT[role] = (vocabulary, make())
    return known[1]
