"""Words and shingles of whole texts as 64-bit numbers, vectorised."""

from __future__ import annotations

import numpy as np
import xxhash

_ODD = (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0xD6E8FEB86659FD93, 0xA0761D6478BD642F)


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective scrambling of 64-bit numbers."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> np.uint64(27))
    x = x * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def words_of(text: str | None) -> list[bytes]:
    """Words [^\\x20\\x09-\\x0D]+ with A-Z lowered: just what bytes.lower and bytes.split take."""
    return (text or "").encode("utf-8", "surrogatepass").lower().split()


#: Lower case for A-Z; other ASCII than letters and digits separates.
_PLAIN = bytes(b + 32 if 65 <= b <= 90 else b if b > 127 or 48 <= b <= 57 or 97 <= b <= 122 else 32 for b in range(256))


def plain_words(text: str | None) -> list[bytes]:
    """Words without punctuation, lower-cased."""
    return (text or "").encode("utf-8", "surrogatepass").translate(_PLAIN).split()


_hash = xxhash.xxh3_64_intdigest


def word_hashes(words: list[bytes]) -> np.ndarray:
    return np.fromiter(map(_hash, words), np.uint64, len(words))


def grams(hashes: np.ndarray, n: int) -> np.ndarray:
    """The n-grams at each position; empty if there are fewer than n words."""
    m = len(hashes) - n + 1
    if m <= 0:
        return hashes[:0]
    out = np.zeros(m, np.uint64)
    for i in range(n):
        out = mix(out * np.uint64(_ODD[i % len(_ODD)]) + hashes[i : i + m] + np.uint64(i))
    return out


def shingle_set(text: str | None, n: int) -> np.ndarray:
    """Distinct n-word shingles, sorted; with fewer words the whole sequence as one; none without words."""
    words = words_of(text)
    if not words:
        return np.zeros(0, np.uint64)
    hashes = word_hashes(words)
    return np.unique(grams(hashes, min(n, len(words))))
