"""Bit runs as pairs (count, value)."""

from __future__ import annotations

import numpy as np

from .bits import bits_of, positions, runs, words_of


def encode(words: np.ndarray, n_rows: int) -> bytes:
    bits = bits_of(words, n_rows)
    starts, lengths = runs(bits)
    return np.column_stack([lengths, bits[starts]]).astype("<u4").tobytes()


def decode(payload: bytes, n_rows: int) -> np.ndarray:
    pairs = np.frombuffer(payload, "<u4").reshape(-1, 2)
    return words_of(np.repeat(pairs[:, 1], pairs[:, 0]).astype(np.uint8))


def size_words(words: np.ndarray, n_rows: int) -> int:
    return len(encode(words, n_rows)) // 4


def nonzero_size(numbers: np.ndarray, values: np.ndarray, n_rows: int) -> int:
    return len(from_nonzero(numbers, values, n_rows))


def from_nonzero(numbers: np.ndarray, values: np.ndarray, n_rows: int) -> bytes:
    """The payload of sparse words; cost and memory follow the set bits, not the rows."""
    pos = positions(numbers, values)
    first = np.ones(len(pos), bool)
    first[1:] = pos[1:] != pos[:-1] + 1
    starts = pos[first]
    ends = starts + np.diff(np.append(np.flatnonzero(first), len(pos)))
    edges = np.append(np.column_stack([starts, ends]).ravel(), n_rows)  # where the value changes, from 0 on
    lengths = np.diff(edges, prepend=0)
    pairs = np.column_stack([lengths, np.arange(len(edges)) % 2])
    return pairs[lengths > 0].astype("<u4").tobytes()
