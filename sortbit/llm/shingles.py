"""Word-shingle sets of texts and their min-wise signatures."""

from __future__ import annotations

import numpy as np
import pyarrow as pa

from .bytewords import LOWER, SpanHash, distinct, mix, text_bytes, windows, words

WORDS = 5


def shingle_sets(column: pa.Array, width: int = WORDS) -> list[np.ndarray]:
    """Each text's distinct shingle hashes, sorted. A-Z counts as lower case.

    A text of fewer words than `width` has its whole word sequence as one shingle; one
    without words, or null, has none.
    """
    data, offsets = text_bytes(column)
    starts, ends, text = words(data, offsets)
    hashes = SpanHash(LOWER[data]).of(starts, ends)
    whole, at = windows(hashes, text, width)
    n = len(offsets) - 1
    owner = text[at] if len(at) else at
    counts = np.bincount(text, minlength=n)
    low = np.searchsorted(owner, np.arange(n + 1))
    first_word = np.searchsorted(text, np.arange(n))
    out = []
    for i in range(n):
        if counts[i] >= width:
            out.append(distinct(whole[low[i] : low[i + 1]]))
        elif counts[i]:
            h = np.array([counts[i]], np.uint64)
            for x in hashes[first_word[i] : first_word[i] + counts[i]]:
                h = mix(h * np.uint64(0x9E3779B97F4A7C15) + x)
            out.append(h)
        else:
            out.append(np.zeros(0, np.uint64))
    return out


def fingerprint(shingles: np.ndarray) -> bytes:
    """128 bits of a set: two independent sums of its members' mixed hashes."""
    a = mix(shingles ^ np.uint64(0xA0761D6478BD642F)).sum(dtype=np.uint64)
    b = mix(shingles ^ np.uint64(0xE7037ED1A0B428DB)).sum(dtype=np.uint64)
    return np.array([a, b], "<u8").tobytes()


class MinWise:
    """`size` hash functions; a signature holds each one's least value (its upper 32 bits) over a set."""

    def __init__(self, size: int, seed: int = 5):
        rng = np.random.default_rng(seed)
        self.odd = rng.integers(0, 1 << 63, size, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
        self.add = rng.integers(0, 1 << 63, size, dtype=np.uint64)

    def signatures(self, sets: list[np.ndarray]) -> np.ndarray:
        """One row for each set; the sets may not be empty."""
        out = np.empty((len(sets), len(self.odd)), np.uint32)
        if not sets:
            return out
        values = np.concatenate(sets)
        bounds = np.concatenate(([0], np.cumsum([len(s) for s in sets])[:-1]))
        values = mix(values)
        for k, (m, c) in enumerate(zip(self.odd, self.add, strict=True)):
            h = ((values ^ c) * m) >> np.uint64(32)
            out[:, k] = np.minimum.reduceat(h.astype(np.uint32), bounds)
        return out


def similar(a: np.ndarray, b: np.ndarray, percent: int) -> bool:
    """100 * intersection >= percent * union, for two sorted distinct arrays that are not empty."""
    small, large = (a, b) if len(a) <= len(b) else (b, a)
    if 100 * len(small) < percent * len(large):
        return False
    at = np.searchsorted(large, small)
    at[at == len(large)] = 0
    both = int((large[at] == small).sum())
    return 100 * both >= percent * (len(a) + len(b) - both)
