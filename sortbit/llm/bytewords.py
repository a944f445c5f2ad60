"""Words, lines and their hashes for a whole batch of texts at once, on the UTF-8 bytes.

Separators are ASCII, so cutting bytes cuts the same words as cutting characters. A
span's hash is a polynomial of per-byte random 64-bit values, taken from running sums
(mod 2**64) and mixed; equal spans have equal hashes wherever they stand.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

_rng = np.random.default_rng(20240501)
_VALUE = _rng.integers(1, 1 << 63, 256, dtype=np.uint64)
_P = np.uint64(0x9E3779B97F4A7C15)
_P_INVERSE = np.uint64(pow(0x9E3779B97F4A7C15, -1, 1 << 64))

SPACE = np.zeros(256, bool)
SPACE[[0x20, *range(0x09, 0x0E)]] = True
LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32


def mix(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser: every input bit moves every output bit."""
    x = x.astype(np.uint64, copy=True)
    x ^= x >> np.uint64(30)
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


def text_bytes(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """The bytes of all texts, one after another, and n + 1 offsets. A null counts as empty."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    column = column.cast(pa.large_string())
    if column.null_count:
        column = pc.fill_null(column, "")
    offsets = np.frombuffer(column.buffers()[1], np.int64)[column.offset : column.offset + len(column) + 1]
    raw = column.buffers()[2]
    data = np.frombuffer(raw, np.uint8)[offsets[0] : offsets[-1]] if raw is not None and len(raw) else np.zeros(0, np.uint8)
    return data, offsets - offsets[0]


def spans(inside: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Starts and ends of the maximal runs of `inside` bytes that no text's end cuts, and each run's text."""
    n = len(inside)
    if not n:
        return (np.zeros(0, np.int64),) * 3
    edge = np.zeros(n + 1, bool)
    edge[offsets] = True
    before = np.empty(n, bool)
    before[0] = False
    before[1:] = inside[:-1]
    after = np.empty(n, bool)
    after[-1] = False
    after[:-1] = inside[1:]
    starts = np.flatnonzero(inside & (~before | edge[:-1]))
    ends = np.flatnonzero(inside & (~after | edge[1:])) + 1
    return starts, ends, np.searchsorted(offsets, starts, side="right") - 1


def words(data: np.ndarray, offsets: np.ndarray):
    return spans(~SPACE[data], offsets)


class SpanHash:
    """Hashes of any spans of the given bytes."""

    def __init__(self, data: np.ndarray):
        n = len(data)
        self.down = _powers(_P_INVERSE, n + 1)
        self.sums = np.zeros(n + 1, np.uint64)
        if n:
            np.cumsum(_VALUE[data] * _powers(_P, n), out=self.sums[1:])

    def of(self, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
        return mix((self.sums[ends] - self.sums[starts]) * self.down[starts] + (ends - starts).astype(np.uint64))


_power_tables: dict[int, np.ndarray] = {}


def _powers(base: np.uint64, n: int) -> np.ndarray:
    """base ** 0 .. n - 1; the longest table so far is kept while it is of ordinary size."""
    table = _power_tables.get(int(base))
    if table is None or len(table) < n:
        size = max(n, 1 << 12)
        table = np.empty(size, np.uint64)
        table[0], have = 1, 1
        while have < size:
            more = min(have, size - have)
            table[have : have + more] = table[:more] * np.uint64(pow(int(base), have, 1 << 64))
            have += more
        if size <= 1 << 22:
            _power_tables[int(base)] = table
    return table[:n]


def windows(hashes: np.ndarray, text: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray]:
    """A hash for each window of `width` words that lies in one text, and where it begins."""
    n = len(hashes) - width + 1
    if n <= 0:
        return np.zeros(0, np.uint64), np.zeros(0, np.int64)
    whole = np.zeros(n, np.uint64)
    for i in range(width):
        whole *= np.uint64(0xD6E8FEB86659FD93)
        whole += hashes[i : i + n]
    at = np.flatnonzero(text[:n] == text[width - 1 :])
    return mix(whole[at]), at


def per_text(text: np.ndarray, n: int, weights: np.ndarray | None = None) -> np.ndarray:
    return np.bincount(text, weights=weights, minlength=n).astype(np.int64)


def count_inside(flags: np.ndarray, offsets: np.ndarray) -> np.ndarray:
    """How many set flags each text has."""
    sums = np.concatenate(([0], np.cumsum(flags, dtype=np.int64)))
    return sums[offsets[1:]] - sums[offsets[:-1]]


def distinct(x: np.ndarray) -> np.ndarray:
    """The sorted distinct values; sorting beats numpy's hashing for long arrays."""
    x = np.sort(x)
    first = np.ones(len(x), bool)
    first[1:] = x[1:] != x[:-1]
    return x[first]
