import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from sortbit import bitops
from sortbit.codec import CODECS, marker32
from sortbit.codec.bits import bits_of, n_words, words_of

rng = np.random.default_rng(5)
SMALL = [(rng.random(n) < p).astype(np.uint8) for n in (1, 31, 32, 33, 62, 64, 1000) for p in (0, 0.03, 0.5, 0.97, 1)]
RUN = np.zeros(32 * 200_000, np.uint8)
RUN[32 * 70_000 : 32 * 140_000] = 1
LITERALS = (rng.random(32 * 70_000) < 0.5).astype(np.uint8)


@pytest.mark.parametrize("codec", CODECS)
def test_round_trip(codec):
    c = CODECS[codec]
    cases = [np.zeros(0, np.uint8), *SMALL] + ([] if codec in ("runlength", "bytealigned") else [RUN, LITERALS])
    for bits in cases:
        w = words_of(bits)
        assert np.array_equal(c.decode(c.encode(w, len(bits)), len(bits)), w)


def test_marker_limits():
    assert marker32.size_words(np.zeros(65535, np.uint32), 65535 * 32) == 1
    assert marker32.size_words(np.zeros(65536, np.uint32), 65536 * 32) == 2
    assert marker32.size_words(np.full(32767, 5, np.uint32), 32767 * 32) == 32768
    assert marker32.size_words(np.full(32768, 5, np.uint32), 32768 * 32) == 32770


def test_worst_case_expansion():
    w = words_of(LITERALS)
    assert marker32.size_words(w, len(LITERALS)) <= len(w) * (1 + 1 / 32767) + 2
    assert CODECS["flag31"].size_words(w, len(LITERALS)) <= len(w) * 32 / 31 + 1


def test_run_length_pairs():
    payload = CODECS["runlength"].encode(words_of(np.array([1, 1, 1, 1, 0, 0, 0, 0], np.uint8)), 8)
    assert np.frombuffer(payload, "<u4").tolist() == [4, 1, 4, 0]


def test_sparse_encoder_writes_the_same_bytes():
    for bits in [*SMALL, RUN, LITERALS]:
        w = words_of(bits)
        payload = marker32.encode(w, len(bits))
        numbers, values = marker32.nonzero(payload, len(bits))
        assert np.array_equal(numbers, np.flatnonzero(w)) and np.array_equal(values, w[w != 0])
        assert marker32.from_nonzero(numbers, values, len(bits)) == payload


def test_many_payloads_at_once_are_those_of_each():
    from sortbit.codec.marker32_many import payloads

    for n, p, m in ((1000, 0.02, 40), (1000, 0.5, 9), (1000, 0.99, 9), (32 * 70_000, 0.7, 2), (32 * 70_000, 1, 1), (33, 0.1, 20)):
        each = [words_of((rng.random(n) < p).astype(np.uint8)) for _ in range(m)]
        if n > 1000:
            each[0][5:69_000] = 0  # a clean run beyond one marker
        each = [w for w in each if w.any()]
        edges = np.concatenate(([0], np.cumsum([np.count_nonzero(w) for w in each])))
        stream, offsets = payloads(edges, np.concatenate([np.flatnonzero(w) for w in each]), np.concatenate([w[w != 0] for w in each]), n)
        got = [stream[a:b].astype("<u4").tobytes() for a, b in zip(offsets[:-1], offsets[1:], strict=True)]
        assert got == [marker32.encode(w, n) for w in each]


@settings(max_examples=60, deadline=None)
@given(st.integers(1, 400), st.integers(0, 1 << 32), st.sampled_from([0.01, 0.5, 0.99]))
def test_operations(n, seed, p):
    r = np.random.default_rng(seed)
    a, b = (r.random(n) < p).astype(np.uint8), (r.random(n) < 0.5).astype(np.uint8)
    x, y = (bitops.load(marker32.encode(words_of(v), n), n) for v in (a, b))

    def plain(sparse):
        w = np.zeros(n_words(n), np.uint32)
        w[sparse[0]] = sparse[1]
        return bits_of(w, n)

    assert np.array_equal(plain(bitops.bm_and(x, y)), a & b)
    assert np.array_equal(plain(bitops.bm_or(x, y)), a | b)
    assert np.array_equal(plain(bitops.bm_xor(x, y)), a ^ b)
    assert np.array_equal(plain(bitops.bm_andnot(x, y)), a & ~b & 1)
    assert np.array_equal(plain(bitops.bm_not(x, n)), 1 - a)
    assert np.array_equal(plain(bitops.bm_xnor(x, y, n)), 1 - (a ^ b))
    assert bitops.bm_count(x) == a.sum()
    assert np.array_equal(bitops.bm_positions(x), np.flatnonzero(a))
    assert np.array_equal(bitops.positions_and(np.flatnonzero(a), np.flatnonzero(b)), np.flatnonzero(a & b))
    assert np.array_equal(plain(bitops.bm_or_many([x, y, x])), a | b)
    assert np.array_equal(bitops.bm_positions(bitops.bm_not(bitops.bm_and(x, y), n)), bitops.bm_positions(bitops.bm_or(bitops.bm_not(x, n), bitops.bm_not(y, n))))


@pytest.mark.parametrize("codec", CODECS)
def test_sizes_of_sparse_words_are_those_of_the_payloads(codec):
    c = CODECS[codec]
    some = np.zeros(32 * 70_001 - 7, np.uint8)
    some[[5, 6, 7, 31, 32, 1_500_000, 1_500_031]] = 1
    some[2_000_000:2_000_400] = 1
    for bits in [*SMALL, some] + ([] if codec in ("runlength", "bytealigned") else [RUN, LITERALS]):
        w = words_of(bits)
        at, payload = np.flatnonzero(w), c.encode(w, len(bits))
        assert c.nonzero_size(at, w[at], len(bits)) == len(payload)
        if codec != "plain":
            assert c.from_nonzero(at, w[at], len(bits)) == payload


def test_deflate_is_one_stream_of_the_plain_words():
    import zlib

    for bits in (RUN, LITERALS, np.zeros(32 * 70_001, np.uint8)):
        w = words_of(bits)
        assert zlib.decompress(CODECS["deflate"].encode(w, len(bits))) == w.astype("<u4").tobytes()
    w = words_of(LITERALS[: 32 * 30_000])
    assert CODECS["deflate"].encode(w, 32 * 30_000) == zlib.compress(w.astype("<u4").tobytes(), 6)
