"""Logical operations on compressed bitmaps, as merges of their non-zero words.

Costs follow the non-zero words of the operands. What can be all ones (NOT, XNOR) masks
the last word to the table's rows.
"""

from __future__ import annotations

import numpy as np

from .codec import marker32
from .codec.bits import FULL, n_words

Sparse = tuple[np.ndarray, np.ndarray]  # word numbers, non-zero values

EMPTY: Sparse = (np.zeros(0, np.int64), np.zeros(0, np.uint32))


def load(payload: bytes, n_rows: int) -> Sparse:
    return marker32.nonzero(payload, n_rows)


def store(x: Sparse, n_rows: int) -> bytes:
    return marker32.from_nonzero(*x, n_rows)


def _clean(numbers: np.ndarray, values: np.ndarray) -> Sparse:
    held = values != 0
    return numbers[held], values[held]


def bm_and(a: Sparse, b: Sparse) -> Sparse:
    numbers, i, j = np.intersect1d(a[0], b[0], assume_unique=True, return_indices=True)
    return _clean(numbers, a[1][i] & b[1][j])


def _merge(a: Sparse, b: Sparse, op) -> Sparse:
    numbers = np.union1d(a[0], b[0])
    x, y = np.zeros(len(numbers), np.uint32), np.zeros(len(numbers), np.uint32)
    x[np.searchsorted(numbers, a[0])] = a[1]
    y[np.searchsorted(numbers, b[0])] = b[1]
    return _clean(numbers, op(x, y))


def bm_or(a: Sparse, b: Sparse) -> Sparse:
    return _merge(a, b, np.bitwise_or)


def bm_xor(a: Sparse, b: Sparse) -> Sparse:
    return _merge(a, b, np.bitwise_xor)


def bm_andnot(a: Sparse, b: Sparse) -> Sparse:
    values = a[1].copy()
    _, i, j = np.intersect1d(a[0], b[0], assume_unique=True, return_indices=True)
    values[i] &= ~b[1][j]
    return _clean(a[0], values)


def bm_not(a: Sparse, n_rows: int) -> Sparse:
    numbers = np.arange(n_words(n_rows))
    values = np.full(len(numbers), FULL, np.uint32)
    if n_rows % 32:
        values[-1] = (1 << n_rows % 32) - 1
    values[a[0]] &= ~a[1]
    return _clean(numbers, values)


def bm_xnor(a: Sparse, b: Sparse, n_rows: int) -> Sparse:
    return bm_not(bm_xor(a, b), n_rows)


def bm_and_many(parts: list[Sparse]) -> Sparse:
    """The fewest words first; ends at the first empty result."""
    parts = sorted(parts, key=lambda p: len(p[0]))
    out = parts[0]
    for p in parts[1:]:
        if not len(out[0]):
            break
        out = bm_and(out, p)
    return out


def bm_or_many(parts: list[Sparse]) -> Sparse:
    if not parts:
        return EMPTY
    numbers = np.concatenate([p[0] for p in parts])
    values = np.concatenate([p[1] for p in parts])
    order = np.argsort(numbers, kind="stable")
    numbers, values = numbers[order], values[order]
    if not len(numbers):
        return EMPTY
    first = np.flatnonzero(np.concatenate(([True], numbers[1:] != numbers[:-1])))
    return numbers[first], np.bitwise_or.reduceat(values, first)


def bm_count(a: Sparse) -> int:
    return int(np.bitwise_count(a[1]).sum())


def bm_positions(a: Sparse) -> np.ndarray:
    bits = np.unpackbits(np.ascontiguousarray(a[1], "<u4").view(np.uint8), bitorder="little").reshape(-1, 32)
    word, bit = np.nonzero(bits)
    return a[0][word] * 32 + bit


def positions_and(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """The same AND on lists of set positions."""
    return np.intersect1d(a, b, assume_unique=True)
