"""Marker-format payloads of many bitmaps in one pass of numpy."""

from __future__ import annotations

import numpy as np

from .bits import FULL, n_words
from .marker32 import CLEAN_MAX, LITERAL_MAX, from_nonzero


def payloads(edges: np.ndarray, numbers: np.ndarray, values: np.ndarray, n_rows: int) -> tuple[np.ndarray, np.ndarray]:
    """(stream, offsets in words): bitmap i has the non-zero words edges[i] : edges[i + 1], at least one.

    Equal to marker32.from_nonzero on each; runs too long for one marker go through it one by one.
    """
    total, n = n_words(n_rows), len(numbers)
    if not n:
        return np.zeros(0, np.uint32), np.zeros(len(edges), np.int64)
    head = np.zeros(n, bool)
    head[edges[:-1]] = True
    ones = values == FULL
    new = head.copy()
    new[1:] |= (numbers[1:] != numbers[:-1] + 1) | (ones[1:] != ones[:-1])
    start = np.flatnonzero(new)
    length = np.diff(np.append(start, n))
    first, full, lead = numbers[start], ones[start], head[start]
    end = first + length
    gap = first.copy()
    gap[1:] -= np.where(lead[1:], 0, end[:-1])
    last = np.append(lead[1:], True)
    left = np.where(last, total - end, 0)
    if max(int(gap.max()), int(left.max()), int(length[full].max(initial=0))) > CLEAN_MAX or int(length[~full].max(initial=0)) > LITERAL_MAX:
        parts = [np.frombuffer(from_nonzero(numbers[a:b], values[a:b], n_rows), "<u4") for a, b in zip(edges[:-1], edges[1:], strict=True)]
        return np.concatenate(parts), np.concatenate(([0], np.cumsum([len(p) for p in parts])))
    behind = np.zeros(len(start), bool)  # literals right behind ones share their marker
    behind[1:] = ~full[1:] & full[:-1] & ~lead[1:] & (gap[1:] == 0)
    shared = np.append(behind[1:], False)
    size = np.where(full, (gap > 0).astype(np.int64) + ~shared, 1 + length) + (left > 0)
    at = np.concatenate(([0], np.cumsum(size)))
    out, at, ends = np.zeros(int(at[-1]), np.uint32), at[:-1], at[1:]
    waits = full & (gap > 0)
    out[at[waits]] = gap[waits] << 1
    alone = full & ~shared
    out[at[alone] + (gap[alone] > 0)] = 1 | length[alone] << 1
    clean = np.where(behind, np.append(0, length[:-1]), gap)
    out[at[~full]] = behind[~full] | clean[~full] << 1 | length[~full] << 17
    place = np.repeat(at + 1 - start, length) + np.arange(n)
    out[place[~ones]] = values[~ones]
    out[ends[left > 0] - 1] = left[left > 0] << 1
    return out, np.append(at[lead], len(out))
