"""The marker format on 64-bit words: 1 bit clean type, 32 bits clean count, 31 bits literal count."""

from __future__ import annotations

import numpy as np

from .bits import kinds_of, n_words, runs

CLEAN_MAX, LITERAL_MAX = (1 << 32) - 1, (1 << 31) - 1
FULL64 = np.uint64(0xFFFFFFFFFFFFFFFF)


def _wide(words: np.ndarray) -> np.ndarray:
    padded = np.zeros(len(words) + len(words) % 2, "<u4")
    padded[: len(words)] = words
    return padded.view("<u8")


def encode(words: np.ndarray, n_rows: int) -> bytes:
    wide = _wide(np.asarray(words, np.uint32))
    starts, lengths = runs(kinds_of(wide, int(FULL64)))
    out, clean, kind = [], 0, 0
    for start, length in zip(starts.tolist(), lengths.tolist(), strict=True):
        if wide[start] in (0, FULL64):
            if clean:
                out.append(np.array([kind | clean << 1], np.uint64))
            clean, kind = length, int(wide[start] != 0)
        else:
            out += [np.array([kind | clean << 1 | length << 33], np.uint64), wide[start : start + length]]
            clean = kind = 0
    if clean:
        out.append(np.array([kind | clean << 1], np.uint64))
    return np.concatenate(out).astype("<u8").tobytes() if out else b""


def decode(payload: bytes, n_rows: int) -> np.ndarray:
    stream, n = np.frombuffer(payload, "<u8"), n_words(n_rows)
    out, at, to = np.zeros((n + 1) // 2, np.uint64), 0, 0
    while at < len(stream):
        m = int(stream[at])
        clean, literals = m >> 1 & CLEAN_MAX, m >> 33
        if m & 1:
            out[to : to + clean] = FULL64
        to += clean
        out[to : to + literals] = stream[at + 1 : at + 1 + literals]
        to, at = to + literals, at + 1 + literals
    return out.astype("<u8").view("<u4")[:n].astype(np.uint32)


def size_words(words: np.ndarray, n_rows: int) -> int:
    """In 64-bit words."""
    return len(encode(words, n_rows)) // 8


def nonzero_size(numbers: np.ndarray, values: np.ndarray, n_rows: int) -> int:
    return len(from_nonzero(numbers, values, n_rows))


def from_nonzero(numbers: np.ndarray, values: np.ndarray, n_rows: int) -> bytes:
    words = np.zeros(n_words(n_rows), np.uint32)
    words[numbers] = values
    return encode(words, n_rows)
