from itertools import combinations
from math import comb

import pytest
from pyspark.sql import functions as F

from sortbit.codes import assign_codes, assign_hierarchy, bitmaps_needed, effective_k, gray_direction, gray_key, ordinals, unrank


def gray_rank(positions, size):
    value, parity = 0, 0
    for i in range(size):
        parity ^= i in positions
        value = 2 * value + parity
    return value


@pytest.mark.parametrize(("n", "size"), [(91, 9), (1240, 15), (99800, 41), (1478, 16), (1382, 16), (1355, 15), (1378, 16), (1345, 15), (200, 10), (100, 9), (400, 12), (526, 13), (537, 13), (536, 13)])
def test_bitmaps_needed_for_four(n, size):
    assert bitmaps_needed(n, 4) == size


def test_two_of_n():
    assert bitmaps_needed(6, 2) == 4
    assert bitmaps_needed(2_000_000, 2) == 2001


def test_k_is_limited():
    assert [effective_k(n, 4) for n in (5, 6, 21, 22, 85, 86)] == [1, 2, 2, 3, 3, 4]


@pytest.mark.parametrize(("size", "k"), [(4, 2), (6, 3), (7, 4), (5, 1)])
def test_unrank_is_both_orders(spark, size, k):
    d = spark.range(comb(size, k)).orderBy("id")
    codes = list(combinations(range(size), k))
    assert [tuple(r[0]) for r in d.select(unrank(F.col("id"), size, k)).collect()] == codes
    assert [tuple(r[0]) for r in d.select(unrank(F.col("id"), size, k, "gray")).collect()] == sorted(codes, key=lambda c: gray_rank(c, size))


def test_codes_are_distinct_and_null_comes_first(spark):
    df = spark.createDataFrame([(v,) for v in [None, 3, 1, 2, 5, 4, 6, 7, 1]], "v int")
    rows = assign_codes(df, "v", 2).orderBy("ord").collect()
    assert rows[0].value is None and [r.value for r in rows[1:]] == [1, 2, 3, 4, 5, 6, 7]
    assert len({tuple(r.bits) for r in rows}) == len(rows) and all(len(r.bits) == 2 for r in rows)
    assert assign_codes(df.where("v > 100"), "v", 2).count() == 0


def test_text_order(spark):
    df = spark.createDataFrame([(2,), (10,)], "v int")
    assert [r.value for r in assign_codes(df, "v", value_order="text").orderBy("ord").collect()] == [10, 2]


def test_ordinals_by_partitions(spark, monkeypatch):
    from sortbit import codes

    monkeypatch.setattr(codes, "SMALL_DICTIONARY", 10)
    got = ordinals(spark.range(1000).select((F.col("id") * 7 % 1000).alias("value")), F.col("value").asc()).collect()
    assert sorted((r.value, r.ord) for r in got) == [(i, i) for i in range(1000)]


def test_gray_key_sorts_any_bit_rows(spark):
    size = 6
    rows = [([i for i in range(size) if b >> i & 1],) for b in range(1 << size)]
    got = spark.createDataFrame(rows, "bits array<int>").orderBy(gray_key(F.col("bits"), size)).collect()
    seen = [tuple(r.bits) for r in got]
    assert seen == sorted(seen, key=lambda c: gray_rank(c, size))
    assert all(len(set(a) ^ set(b)) == 1 for a, b in zip(seen, seen[1:]))


def test_directions_flip_with_odd_weights():
    assert gray_direction([1, 2, 3]) == [True, False, False]
    assert gray_direction([2, 2]) == [True, True]


def test_hierarchy_codes_restart_in_each_parent(spark):
    df = spark.createDataFrame([("ca", "mtl"), ("ca", "tor"), ("fr", "par")], "country string, city string")
    assert sorted(map(tuple, assign_hierarchy(df, ["country", "city"]).collect())) == [("ca", "mtl", 0, 0), ("ca", "tor", 0, 1), ("fr", "par", 1, 0)]


def test_numpy_ranking_inverts_and_equals_the_expressions(spark):
    import numpy as np
    from pyspark.sql import functions as F

    from sortbit.codes import unrank
    from sortbit.ranking import ordinals_of, positions_of

    for size, k in ((6, 1), (9, 2), (9, 3), (10, 4)):
        for allocation in ("alpha", "gray"):
            n = comb(size, k)
            codes = positions_of(np.arange(n), size, k, allocation)
            assert np.array_equal(ordinals_of(codes, size, allocation), np.arange(n))
            got = [r[0] for r in spark.range(n).orderBy("id").select(unrank(F.col("id"), size, k, allocation)).collect()]
            assert got == codes.tolist()


def test_unranking_halves_instead_of_trying_every_position(spark):
    plan = spark.range(3)
    for allocation in ("alpha", "gray"):
        code = plan.select(unrank(F.col("id") + 900_000, 1500, 2, allocation).alias("code"))
        text = code._jdf.queryExecution().toString()
        assert "sequence(" not in text and "filter(" not in text
    size, n = 1500, 1_124_250  # all pairs of 1500
    got = spark.createDataFrame([(0,), (1498,), (1499,), (n - 1,)], "id long").select(unrank(F.col("id"), size, 2).alias("c")).collect()
    assert [list(r.c) for r in got] == [[0, 1], [0, 1499], [1, 2], [1498, 1499]]
