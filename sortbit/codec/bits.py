"""Words, bits and runs of one bitmap in numpy."""

from __future__ import annotations

import numpy as np

FULL = np.uint32(0xFFFFFFFF)


def n_words(n_rows: int) -> int:
    return -(-n_rows // 32)


def bits_of(words: np.ndarray, n_rows: int) -> np.ndarray:
    """0/1 for each row; row i is bit i % 32 of word i // 32."""
    return np.unpackbits(np.ascontiguousarray(words, "<u4").view(np.uint8), bitorder="little")[:n_rows]


def words_of(bits: np.ndarray) -> np.ndarray:
    padded = np.zeros(n_words(len(bits)) * 32, np.uint8)
    padded[: len(bits)] = bits
    return np.packbits(padded, bitorder="little").view("<u4").astype(np.uint32)


def positions(numbers: np.ndarray, values: np.ndarray) -> np.ndarray:
    """Positions of the set bits of non-zero words, given by number and value."""
    at = np.flatnonzero(np.unpackbits(np.ascontiguousarray(values, "<u4").view(np.uint8), bitorder="little"))
    return np.asarray(numbers, np.int64)[at // 32] * 32 + at % 32


def runs(kinds: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Starts and lengths of the runs of equal values."""
    if not len(kinds):
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    starts = np.concatenate(([0], np.flatnonzero(kinds[1:] != kinds[:-1]) + 1))
    return starts, np.diff(np.concatenate((starts, [len(kinds)])))


def kinds_of(words: np.ndarray, full: int) -> np.ndarray:
    """0: all zeros, 1: all ones, 2: anything else."""
    return np.where(words == 0, 0, np.where(words == full, 1, 2)).astype(np.uint8)
