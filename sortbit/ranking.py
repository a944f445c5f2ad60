"""Ordinals of k-of-L codes and back, in numpy, for what tasks do inside a block."""

from __future__ import annotations

from math import comb

import numpy as np


def _choose(size: int, r: int) -> np.ndarray:
    """C(m, r) for m = 0 .. size."""
    return np.array([min(comb(m, r), (1 << 63) - 1) for m in range(size + 1)], np.int64)


def _ascending(i: int, allocation: str) -> bool:
    return allocation == "alpha" or i % 2 == 1


def positions_of(ordinals: np.ndarray, size: int, k: int, allocation: str = "alpha") -> np.ndarray:
    """One row of k ascending positions for each ordinal."""
    rest = np.asarray(ordinals, np.int64).copy()
    if k == 1 and allocation == "alpha":
        return rest[:, None]
    after, out = np.zeros(len(rest), np.int64), np.empty((len(rest), k), np.int64)
    for i in range(k):
        c = _choose(size, k - i)
        if _ascending(i, allocation):
            m = np.searchsorted(c, c[size - after] - rest, side="left")
            rest -= c[size - after] - c[m]
        else:
            m = np.searchsorted(c, rest, side="right")
            rest -= c[m - 1]
        out[:, i] = size - m
        after = out[:, i] + 1
    return out


def ordinals_of(positions: np.ndarray, size: int, allocation: str = "alpha") -> np.ndarray:
    """The ordinal of each row of ascending positions."""
    n, k = positions.shape
    out, after = np.zeros(n, np.int64), np.zeros(n, np.int64)
    for i in range(k):
        c, p = _choose(size, k - i), positions[:, i]
        out += c[size - after] - c[size - p] if _ascending(i, allocation) else c[size - 1 - p]
        after = p + 1
    return out
