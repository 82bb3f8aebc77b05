"""Word and shingle primitives shared by the training-data operators.

A *word* is a maximal run of bytes outside ``\\x20 \\x09-\\x0D`` of the UTF-8
text, which is what ``bytes.split()`` cuts; words become 64-bit hashes, and an
n-word shingle becomes a 64-bit polynomial of its word hashes, so every later
step is numpy on integers.  Two different shingles collide with a probability
of about 2**-64 per pair.
"""

from __future__ import annotations

import numpy as np
import xxhash

_HASH = xxhash.xxh3_64_intdigest
_ODD = np.uint64(0x9E3779B97F4A7C15)
_MIX_A = np.uint64(0xBF58476D1CE4E5B9)
_MIX_B = np.uint64(0x94D049BB133111EB)
#: Distinct words remembered by one Python worker; the table starts anew when full.
WORD_MEMORY = 60_000

class _Memory(dict):
    def __missing__(self, word: bytes) -> int:
        value = _HASH(word)
        if len(self) >= WORD_MEMORY:
            self.clear()
        self[word] = value
        return value


_memory = _Memory()


def split_words(text: str | None, lower: bool = False) -> list[bytes]:
    """Words of a text as bytes; ``lower`` folds A-Z only."""
    if not text:
        return []
    raw = text.encode("utf-8", "surrogatepass")
    return (raw.lower() if lower else raw).split()


def hash_words(words: list[bytes]) -> np.ndarray:
    """One uint64 for each word."""
    return np.fromiter(map(_memory.__getitem__, words), dtype=np.uint64, count=len(words))


def mix(h: np.ndarray) -> np.ndarray:
    """Finaliser that spreads entropy over all 64 bits."""
    h = (h ^ (h >> np.uint64(30))) * _MIX_A
    h = (h ^ (h >> np.uint64(27))) * _MIX_B
    return h ^ (h >> np.uint64(31))


def window_hashes(hashes: np.ndarray, width: int) -> np.ndarray:
    """Hash of every run of ``width`` consecutive words, in order of position."""
    count = len(hashes) - width + 1
    if count <= 0:
        return np.empty(0, np.uint64)
    out = np.zeros(count, np.uint64)
    for j in range(width):
        out *= _ODD
        out += hashes[j : j + count]
    return mix(out)


def shingle_set(text: str | None, width: int = 5) -> np.ndarray:
    """Sorted distinct shingle hashes of the lower-cased text.

    A text of fewer than ``width`` words is one shingle of all its words; a text
    without words has the empty set.
    """
    words = split_words(text, lower=True)
    if not words:
        return np.empty(0, np.uint64)
    hashes = hash_words(words)
    if len(words) < width:
        return window_hashes(np.append(hashes, np.uint64(len(words))), len(words) + 1)
    return np.unique(window_hashes(hashes, width))


def set_digest(shingles: np.ndarray) -> bytes:
    """128-bit name of a shingle set."""
    return xxhash.xxh3_128_digest(shingles.tobytes())


def overlap(a: np.ndarray, b: np.ndarray) -> int:
    """Size of the intersection of two sorted distinct arrays."""
    if len(a) > len(b):
        a, b = b, a
    if not len(a):
        return 0
    at = np.searchsorted(b, a)
    at[at == len(b)] = 0
    return int((b[at] == a).sum())
