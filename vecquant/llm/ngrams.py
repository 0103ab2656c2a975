"""Hashes of the n-grams of texts, and the backoff factor."""

from __future__ import annotations

import numpy as np
import xxhash

BACKOFF = 0.4
_MIX = np.uint64(0x9E3779B97F4A7C15)


def tokens(text: str) -> list[bytes]:
    """Words between white space, A-Z lower-cased."""
    return text.encode().lower().split()


def ngram_keys(texts: list[str], order: int) -> tuple[np.ndarray, list[np.ndarray], list[np.ndarray]]:
    """Words per text; for each length 1..order the n-grams' hashes, and each one's document."""
    words = [tokens(t) for t in texts]
    sizes = np.array([len(w) for w in words], dtype=np.int64)
    hash_ = xxhash.xxh3_64_intdigest
    first = np.fromiter((hash_(w) for ws in words for w in ws), dtype=np.uint64, count=int(sizes.sum()))
    doc = np.repeat(np.arange(len(texts)), sizes)
    keys, owners = [first], [doc]
    with np.errstate(over="ignore"):
        for n in range(2, order + 1):
            m = max(0, len(first) - n + 1)
            inside = np.flatnonzero(doc[:m] == doc[n - 1 :]) if m else np.zeros(0, dtype=np.int64)
            key = np.full(len(inside), n, dtype=np.uint64)
            for k in range(n):
                key = (key ^ first[inside + k]) * _MIX
                key ^= key >> np.uint64(31)
            keys.append(key)
            owners.append(doc[inside])
    return sizes, keys, owners
