"""General-purpose LZ77 compression of the plain words.

The payload is one zlib stream. Pieces of PIECE words are compressed on their own, so pieces of
zeros are alike and compressed once; pieces with few words are matched with the byte before
alone, which is quicker and mostly smaller there. A bitmap of one piece is what zlib.compress
makes of it.
"""

from __future__ import annotations

import zlib
from functools import lru_cache

import numpy as np

from .bits import n_words

#: Words of a piece: 128 KiB.
PIECE = 1 << 15
#: A piece has few words where fewer than one in so many is not zero.
FEW = 16
_BASE = 65521


def _piece(data: bytes, last: bool, few: bool) -> bytes:
    c = zlib.compressobj(6, zlib.DEFLATED, -15, 8, zlib.Z_RLE if few else zlib.Z_DEFAULT_STRATEGY)
    return c.compress(data) + c.flush(zlib.Z_FINISH if last else zlib.Z_FULL_FLUSH)


@lru_cache(64)
def _zeros(words: int, last: bool) -> bytes:
    return _piece(bytes(4 * words), last, True)


def _adler_of_zeros(adler: int, n: int) -> int:
    """The checksum after n more bytes of zeros."""
    low = adler & 0xFFFF
    return ((adler >> 16) + n * low) % _BASE << 16 | low


def from_nonzero(numbers: np.ndarray, values: np.ndarray, n_rows: int) -> bytes:
    """The payload of sparse words; cost follows the pieces with non-zero words."""
    total = n_words(n_rows)
    if total <= PIECE:
        words = np.zeros(total, "<u4")
        words[numbers] = values
        return zlib.compress(words.tobytes(), 6)
    pieces = -(-total // PIECE)
    numbers = np.asarray(numbers, np.int64)
    held, first = np.unique(numbers // PIECE, return_index=True)
    out, adler, at = [b"\x78\x9c"], 1, 0
    edges = [*first.tolist(), len(numbers)]
    for i, a, b in zip([*held.tolist(), pieces], edges, [*edges[1:], len(numbers)], strict=True):
        if at < i:  # zeros up to the next piece with words, or to the end
            whole = i - at - (i == pieces)
            out.append(_zeros(PIECE, False) * whole)
            if i == pieces:
                out.append(_zeros(total - (pieces - 1) * PIECE, True))
            adler = _adler_of_zeros(adler, 4 * (min(i * PIECE, total) - at * PIECE))
        if i < pieces:
            size = min(PIECE, total - i * PIECE)
            words = np.zeros(size, "<u4")
            words[numbers[a:b] - i * PIECE] = values[a:b]
            data = words.tobytes()
            out.append(_piece(data, i == pieces - 1, (b - a) * FEW < size))
            adler = zlib.adler32(data, adler)
        at = i + 1
    out.append(adler.to_bytes(4, "big"))
    return b"".join(out)


def nonzero_size(numbers: np.ndarray, values: np.ndarray, n_rows: int) -> int:
    return len(from_nonzero(numbers, values, n_rows))


def encode(words: np.ndarray, n_rows: int) -> bytes:
    words = np.asarray(words, np.uint32)
    at = np.flatnonzero(words)
    return from_nonzero(at, words[at], 32 * len(words))


def decode(payload: bytes, n_rows: int) -> np.ndarray:
    return np.frombuffer(zlib.decompress(payload), "<u4").astype(np.uint32)


def size_words(words: np.ndarray, n_rows: int) -> int:
    return -(-len(encode(words, n_rows)) // 4)
