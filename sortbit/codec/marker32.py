"""Marker words and literals: 1 bit clean type, 16 bits clean count, 15 bits literal count, then the literals."""

from __future__ import annotations

import numpy as np

from .bits import FULL, kinds_of, n_words, runs

CLEAN_MAX, LITERAL_MAX = 65535, 32767


def encode(words: np.ndarray, n_rows: int) -> bytes:
    words = np.asarray(words, np.uint32)
    starts, lengths = runs(kinds_of(words, int(FULL)))
    out: list[np.ndarray] = []
    clean, kind = 0, 0  # clean words that wait for their marker

    def marker(literals: np.ndarray) -> None:
        nonlocal clean, kind
        out.append(np.array([kind | clean << 1 | len(literals) << 17], np.uint32))
        out.append(literals)
        clean = kind = 0

    for start, length in zip(starts.tolist(), lengths.tolist(), strict=True):
        first = words[start]
        if first in (0, FULL):
            if clean:
                marker(words[:0])
            kind = int(first != 0)
            while length > CLEAN_MAX:
                clean = CLEAN_MAX
                left = kind
                marker(words[:0])
                kind, length = left, length - CLEAN_MAX
            clean = length
        else:
            literals = words[start : start + length]
            for at in range(0, length, LITERAL_MAX):
                marker(literals[at : at + LITERAL_MAX])
    if clean:
        marker(words[:0])
    return np.concatenate(out).astype("<u4").tobytes() if out else b""


def decode(payload: bytes, n_rows: int) -> np.ndarray:
    stream = np.frombuffer(payload, "<u4")
    out, at, to = np.zeros(n_words(n_rows), np.uint32), 0, 0
    while at < len(stream):
        m = int(stream[at])
        clean, literals = m >> 1 & CLEAN_MAX, m >> 17
        if m & 1:
            out[to : to + clean] = FULL
        to += clean
        out[to : to + literals] = stream[at + 1 : at + 1 + literals]
        to, at = to + literals, at + 1 + literals
    return out


def size_words(words: np.ndarray, n_rows: int) -> int:
    return len(encode(words, n_rows)) // 4


def nonzero(payload: bytes, n_rows: int) -> tuple[np.ndarray, np.ndarray]:
    """Numbers and values of the non-zero words, without touching the zeros."""
    stream = np.frombuffer(payload, "<u4")
    numbers, values, at, to = [], [], 0, 0
    while at < len(stream):
        m = int(stream[at])
        clean, literals = m >> 1 & CLEAN_MAX, m >> 17
        if m & 1:
            numbers.append(np.arange(to, to + clean))
            values.append(np.full(clean, FULL, np.uint32))
        to += clean
        numbers.append(np.arange(to, to + literals))
        values.append(stream[at + 1 : at + 1 + literals].astype(np.uint32))
        to, at = to + literals, at + 1 + literals
    if not numbers:
        return np.zeros(0, np.int64), np.zeros(0, np.uint32)
    return np.concatenate(numbers), np.concatenate(values)


def from_nonzero(numbers: np.ndarray, values: np.ndarray, n_rows: int) -> bytes:
    """The payload of sparse words; cost and memory follow the non-zero words, not the rows."""
    out: list[np.ndarray] = []
    total, at = n_words(n_rows), 0

    def fill(count: int, kind: int, literals: np.ndarray) -> None:
        while count > CLEAN_MAX:
            out.append(np.array([kind | CLEAN_MAX << 1], np.uint32))
            count -= CLEAN_MAX
        first = literals[:LITERAL_MAX]
        if count or len(first):
            out.append(np.array([kind | count << 1 | len(first) << 17], np.uint32))
            out.append(first)
        for i in range(LITERAL_MAX, len(literals), LITERAL_MAX):
            part = literals[i : i + LITERAL_MAX]
            out.append(np.array([len(part) << 17], np.uint32))
            out.append(part)

    ones = values == FULL
    breaks = np.flatnonzero((np.diff(numbers) != 1) | (ones[1:] != ones[:-1])) + 1 if len(numbers) else np.zeros(0, np.int64)
    waiting, kind = 0, 0
    for start, end in zip(np.concatenate(([0], breaks)).tolist(), np.concatenate((breaks, [len(numbers)])).tolist(), strict=True):
        if start == end:
            continue
        gap = int(numbers[start]) - at
        if gap:
            if waiting:
                fill(waiting, kind, values[:0])
            waiting, kind = gap, 0
        if ones[start]:
            if waiting:
                fill(waiting, kind, values[:0])
            waiting, kind = end - start, 1
        else:
            fill(waiting, kind, values[start:end])
            waiting, kind = 0, 0
        at = int(numbers[end - 1]) + 1
    if waiting:
        fill(waiting, kind, values[:0])
    if at < total:
        fill(total - at, 0, values[:0])
    return np.concatenate(out).astype("<u4").tobytes() if out else b""


def nonzero_size(numbers: np.ndarray, values: np.ndarray, n_rows: int) -> int:
    return len(from_nonzero(numbers, values, n_rows))
