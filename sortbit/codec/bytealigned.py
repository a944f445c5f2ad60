"""Runs of bytes: a head byte 0-126 announces so many + 1 literal bytes, 128-191 zero bytes, 192-255 bytes of ones."""

from __future__ import annotations

import numpy as np

from .bits import kinds_of, n_words, runs


def encode(words: np.ndarray, n_rows: int) -> bytes:
    data = np.ascontiguousarray(words, "<u4").view(np.uint8)
    out = bytearray()
    for start, length in zip(*(x.tolist() for x in runs(kinds_of(data, 0xFF))), strict=True):
        kind = data[start]
        clean = kind in (0, 0xFF)
        most = 64 if clean else 127
        for at in range(start, start + length, most):
            part = min(most, start + length - at)
            out.append((0x80 if kind == 0 else 0xC0) + part - 1 if clean else part - 1)
            if not clean:
                out += data[at : at + part].tobytes()
    return bytes(out)


def decode(payload: bytes, n_rows: int) -> np.ndarray:
    out, at = bytearray(), 0
    while at < len(payload):
        head = payload[at]
        at += 1
        if head < 0x80:
            out += payload[at : at + head + 1]
            at += head + 1
        else:
            out += (b"\xff" if head >= 0xC0 else b"\x00") * ((head & 0x3F) + 1)
    return np.frombuffer(bytes(out), "<u4").astype(np.uint32)[: n_words(n_rows)]


def size_words(words: np.ndarray, n_rows: int) -> int:
    return -(-len(encode(words, n_rows)) // 4)


def _sparse_runs(numbers: np.ndarray, values: np.ndarray, n_rows: int) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(lengths, most bytes of a piece, head of a piece less its length) of the runs (zeros, others, zeros, others, ..., zeros), and the literal bytes."""
    data = np.ascontiguousarray(values, "<u4").view(np.uint8)
    held = np.flatnonzero(data)
    at, data, total = np.asarray(numbers, np.int64)[held // 4] * 4 + held % 4, data[held], 4 * n_words(n_rows)
    ones = data == 0xFF
    head = np.ones(len(at), bool)
    head[1:] = (at[1:] != at[:-1] + 1) | (ones[1:] != ones[:-1])
    first = np.flatnonzero(head)
    length = np.diff(np.append(first, len(at)))
    gap = np.diff(np.append(at[first], total), prepend=0)
    gap[1:] -= length
    lengths = np.append(np.column_stack([gap[:-1], length]).ravel(), gap[-1])
    most, base = np.full(len(lengths), 64), np.full(len(lengths), 0x80)
    most[1::2], base[1::2] = np.where(ones[first], 64, 127), np.where(ones[first], 0xC0, 0)
    return lengths, most, base, data[~ones]


def nonzero_size(numbers: np.ndarray, values: np.ndarray, n_rows: int) -> int:
    """Summed over the runs, as zeros alone take a byte for each 64 that the bitmap has."""
    lengths, most, _, literals = _sparse_runs(numbers, values, n_rows)
    return int((-(-lengths // most)).sum()) + len(literals)


def from_nonzero(numbers: np.ndarray, values: np.ndarray, n_rows: int) -> bytes:
    """The payload of sparse words; only the payload itself grows with the rows."""
    lengths, most, base, literals = _sparse_runs(numbers, values, n_rows)
    pieces = -(-lengths // most)
    owner = np.repeat(np.arange(len(lengths)), pieces)
    size = most[owner]
    some = pieces > 0
    size[np.cumsum(pieces)[some] - 1] = (lengths - (pieces - 1) * most)[some]
    end = np.cumsum(1 + np.where(base[owner] == 0, size, 0))
    heads = np.append(0, end)[: len(end)]
    total = int(end[-1]) if len(end) else 0
    out, is_head = np.empty(total, np.uint8), np.zeros(total, bool)
    out[heads], is_head[heads] = base[owner] + size - 1, True
    out[~is_head] = literals
    return out.tobytes()
