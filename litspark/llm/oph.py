"""One-permutation MinHash with optimal densification, and its bands.

One hash per shingle serves all bins: the top bits choose the bin, the smallest
hash of a bin is its value.  An empty bin borrows the value of a bin chosen by a
hash of (its own number, attempt), the same for every set, until it finds one
that is filled, so equal bins keep the collision probability of the resemblance.
"""

from __future__ import annotations

import numpy as np

from litspark.llm.words import mix

BINS = 128
ROWS = 4
_TOP = np.uint64(64 - 7)


def _probes(attempt: int) -> np.ndarray:
    """For each bin the bin that it asks on this attempt."""
    seeds = np.arange(BINS, dtype=np.uint64) + np.uint64(BINS * (attempt + 1))
    return (mix(seeds * np.uint64(0xD6E8FEB86659FD93)) >> _TOP).astype(np.int64)


def signatures(sets: list[np.ndarray]) -> np.ndarray:
    """Densified signatures (len(sets) x BINS); a row of an empty set is all zero."""
    out = np.zeros((len(sets), BINS), np.uint64)
    filled = np.zeros((len(sets), BINS), bool)
    for i, s in enumerate(sets):
        if len(s):
            bins = (s >> _TOP).astype(np.int64)
            first = np.ones(len(s), bool)
            first[1:] = bins[1:] != bins[:-1]
            out[i, bins[first]] = s[first]
            filled[i, bins[first]] = True
    rows, cols = np.nonzero(~filled & filled.any(axis=1, keepdims=True))
    attempt = 0
    while len(rows):
        asked = _probes(attempt)[cols]
        found = filled[rows, asked]
        out[rows[found], cols[found]] = out[rows[found], asked[found]]
        rows, cols = rows[~found], cols[~found]
        attempt += 1
    return out


def band_hashes(signature: np.ndarray, rows: int = ROWS) -> np.ndarray:
    """One uint64 for each band of ``rows`` neighbouring bins."""
    shaped = signature.reshape(len(signature), -1, rows)
    out = np.arange(shaped.shape[1], dtype=np.uint64)[None, :].repeat(len(signature), 0)
    for r in range(rows):
        out = mix(out * np.uint64(0x9E3779B97F4A7C15) + shaped[:, :, r])
    return out
