"""Hashes of words and word shingles in numpy, equal in every process."""

from __future__ import annotations

import numpy as np
import xxhash

#: Lower-cases A to Z and leaves every other byte.
LOWER = bytes(b + 32 if 65 <= b <= 90 else b for b in range(256))
BASE = 0x9E3779B97F4A7C15


def mixed(z: np.ndarray) -> np.ndarray:
    """Finaliser of a 64-bit hash (splitmix64), element by element."""
    z = (z ^ (z >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    z = (z ^ (z >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return z ^ (z >> np.uint64(31))


def word_hashes(text: str | None) -> np.ndarray:
    """64-bit hashes of the lower-cased words of a whole text. bytes.split() splits at space and tab to carriage return, as a word ends."""
    if not text:
        return np.empty(0, np.uint64)
    digest = xxhash.xxh3_64_intdigest
    return np.array([digest(w) for w in text.encode("utf-8", "surrogatepass").translate(LOWER).split()], np.uint64)


def shingle_set(text: str | None, words: int) -> np.ndarray:
    """Distinct hashes of the word shingles of a text, sorted; a shorter text is one shingle as a whole."""
    h = word_hashes(text)
    if not len(h):
        return h
    width = min(words, len(h))
    z = np.full(len(h) - width + 1, width, np.uint64)
    for k in range(width):
        z = z * np.uint64(BASE) + h[k : len(h) - width + 1 + k]
    return np.unique(mixed(z))
