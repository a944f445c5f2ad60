"""Uncompressed words."""

from __future__ import annotations

import numpy as np

from .bits import n_words


def encode(words: np.ndarray, n_rows: int) -> bytes:
    return np.ascontiguousarray(words, "<u4").tobytes()


def decode(payload: bytes, n_rows: int) -> np.ndarray:
    return np.frombuffer(payload, "<u4").astype(np.uint32)


def size_words(words: np.ndarray, n_rows: int) -> int:
    return n_words(n_rows)


def nonzero_size(numbers: np.ndarray, values: np.ndarray, n_rows: int) -> int:
    """Every word counts, so it needs none of them."""
    return 4 * n_words(n_rows)
