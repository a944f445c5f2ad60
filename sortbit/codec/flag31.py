"""31-bit groups: a literal word has its top bit set; a fill word holds the type and a 30-bit count."""

from __future__ import annotations

import numpy as np

from .bits import bits_of, kinds_of, n_words, positions, runs, words_of

FULL31, FILL_MAX = 0x7FFFFFFF, (1 << 30) - 1


def _groups(words: np.ndarray, n_rows: int) -> np.ndarray:
    bits = bits_of(words, n_rows)
    padded = np.zeros(-(-n_rows // 31) * 31, np.uint32)
    padded[: len(bits)] = bits
    return (padded.reshape(-1, 31) << np.arange(31, dtype=np.uint32)).sum(axis=1, dtype=np.uint32)


def encode(words: np.ndarray, n_rows: int) -> bytes:
    groups = _groups(words, n_rows)
    out: list[np.ndarray] = []
    for start, length in zip(*(x.tolist() for x in runs(kinds_of(groups, FULL31))), strict=True):
        if groups[start] in (0, FULL31):
            kind = int(groups[start] != 0)
            while length:
                part = min(length, FILL_MAX)
                out.append(np.array([kind << 30 | part], np.uint32))
                length -= part
        else:
            out.append(groups[start : start + length] | np.uint32(1 << 31))
    return np.concatenate(out).astype("<u4").tobytes() if out else b""


def decode(payload: bytes, n_rows: int) -> np.ndarray:
    parts = []
    for w in np.frombuffer(payload, "<u4").tolist():
        if w >> 31:
            parts.append(np.array([w & FULL31], np.uint32))
        else:
            parts.append(np.full(w & FILL_MAX, FULL31 if w >> 30 & 1 else 0, np.uint32))
    groups = np.concatenate(parts) if parts else np.zeros(0, np.uint32)
    bits = ((groups[:, None] >> np.arange(31, dtype=np.uint32)) & 1).astype(np.uint8).ravel()[:n_rows]
    return words_of(bits)


def size_words(words: np.ndarray, n_rows: int) -> int:
    return len(encode(words, n_rows)) // 4


def nonzero_size(numbers: np.ndarray, values: np.ndarray, n_rows: int) -> int:
    return len(from_nonzero(numbers, values, n_rows))


def from_nonzero(numbers: np.ndarray, values: np.ndarray, n_rows: int) -> bytes:
    """The payload of sparse words; cost and memory follow the set bits, not the rows."""
    total = -(-n_rows // 31)
    if not len(numbers) or total > FILL_MAX:
        words = np.zeros(n_words(n_rows), np.uint32)
        words[numbers] = values
        return encode(words, n_rows)
    pos = positions(numbers, values)
    group = pos // 31
    first = np.flatnonzero(np.append(True, group[1:] != group[:-1]))
    group, bits = group[first], np.bitwise_or.reduceat(np.uint32(1) << (pos % 31).astype(np.uint32), first)
    ones = bits == FULL31
    head = ~ones  # each literal, and each run of ones
    head |= np.append(True, ~ones[:-1] | (group[1:] != group[:-1] + 1))
    at = np.flatnonzero(head)
    length = np.diff(np.append(at, len(group)))
    start = group[at]
    gap = np.diff(np.append(start, total)) - length  # zeros behind each
    item = np.where(ones[at], 1 << 30 | length, bits[at] | np.uint32(1 << 31))
    out = np.append(start[0], np.column_stack([item, gap]).ravel())
    held = np.append(start[0] > 0, np.column_stack([np.ones(len(at), bool), gap > 0]).ravel())
    return out[held].astype("<u4").tobytes()
