"""The sorted positions of the set bits."""

from __future__ import annotations

import numpy as np

from .bits import bits_of, positions, words_of


def encode(words: np.ndarray, n_rows: int) -> bytes:
    return np.flatnonzero(bits_of(words, n_rows)).astype("<u4").tobytes()


def decode(payload: bytes, n_rows: int) -> np.ndarray:
    bits = np.zeros(n_rows, np.uint8)
    bits[np.frombuffer(payload, "<u4")] = 1
    return words_of(bits)


def size_words(words: np.ndarray, n_rows: int) -> int:
    return len(encode(words, n_rows)) // 4


def nonzero_size(numbers: np.ndarray, values: np.ndarray, n_rows: int) -> int:
    return len(from_nonzero(numbers, values, n_rows))


def from_nonzero(numbers: np.ndarray, values: np.ndarray, n_rows: int) -> bytes:
    return positions(numbers, values).astype("<u4").tobytes()
