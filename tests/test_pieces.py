"""Sizes by pieces against the sizes of words as rows."""

import pytest
from pyspark.sql import functions as F

from sortbit import catalogue, pieces, trials
from sortbit.codes import bitmaps_needed, unrank
from sortbit.words import sizes_marker32, to_words

GRIDS = ["blocks_by_k_p_frequent", "factor_k4_p_dominant"]


@pytest.mark.parametrize("name", GRIDS)
def test_grid_equals_its_sql(same, name):
    same(name, catalogue.queries()[name], catalogue.oracle_sql()[name])


def test_grid_with_merged_dictionaries_equals_its_sql(same, monkeypatch):
    """Dictionaries beyond the broadcast's limit."""
    monkeypatch.setattr(pieces, "BROADCAST", 100)
    monkeypatch.setattr(trials, "BROADCAST", 100)
    same("order_by_k_p_rare", catalogue.queries()["order_by_k_p_rare"], catalogue.oracle_sql()["order_by_k_p_rare"])


@pytest.mark.parametrize(("most", "parts"), [(7, 1), (100, 5), (1 << 20, 3)])
def test_pieces_that_cut_words_and_runs(spark, most, parts):
    """Pieces that end inside words and inside runs of ones; a column of one value, a sorted one and a mixed one."""
    n, values = 5003, {"one": 1, "sorted": 3, "mixed": 40}
    facts = spark.range(0, n, 1, parts).select(F.col("id").alias("pos"), F.lit(0).alias("ord_one"), F.floor(F.col("id") * 3 / n).cast("int").alias("ord_sorted"), ((F.col("id") * 7919) % 1009 % 40).cast("int").alias("ord_mixed"))
    codes = [(c, k, bitmaps_needed(v, k), [f"k={k}"]) for c, v in values.items() for k in (1, 2, 4)]
    got = pieces.code_sizes([(facts, codes)], values, n, most)
    want = None
    for c, k, size, (design,) in codes:
        one = facts.select(F.lit(design).alias("design"), F.lit(c).alias("attr"), F.explode(unrank(F.col(f"ord_{c}"), size, k)).alias("bitmap_id"), "pos")
        want = one if want is None else want.unionByName(one)
    by = ("design", "attr", "bitmap_id")
    rows = lambda df: sorted(map(tuple, df.select(*by, "c_words", "n_words").collect()))
    assert rows(got) == rows(sizes_marker32(to_words(want, by=by), n, by=by))


def test_long_runs_need_more_markers():
    """Runs and gaps beyond one marker, met from pieces: zeros, words, ones and zeros again."""
    import numpy as np

    zeros, words, ones, tail = 70_000, 40_000, 140_000, 66_000
    positions = np.concatenate([(zeros + np.arange(words)) * 32, (zeros + words) * 32 + np.arange(ones * 32)])
    rows, step = [], 1 << 20
    for start in range(0, (zeros + words + ones + tail) * 32, step):
        # facts that the bitmap lacks have another
        has = np.isin(np.arange(start, start + step), positions)
        rows.append(pieces.summary(start, np.where(has, 0, 1)[:, None], 2))
    rows = [np.concatenate(x) for x in zip(*rows, strict=True)]
    at = np.lexsort((rows[1], rows[0]))
    key, total = pieces.merged([x[at] for x in rows], zeros + words + ones + tail)
    assert total[key.tolist().index(0)] == 2 + words + 1 + 3 + 2


def test_packing_keeps_the_order(spark):
    """Ordinals that do not fit one number are packed in several."""
    sizes = {"a": 1 << 30, "b": 1 << 31, "c": 1 << 20, "d": 3}
    groups = pieces.packing(list(sizes), sizes)
    assert groups == [["a", "b"], ["c", "d"]]
    df = spark.range(200).select(*[(F.xxhash64("id", F.lit(c)) % n).cast("int").alias(f"ord_{c}") for c, n in sizes.items()]).select(*[F.abs(f"ord_{c}").alias(f"ord_{c}") for c in sizes])
    got = list(map(tuple, pieces.place_sorted(df, list(sizes), sizes).orderBy("pos").select(df.columns).collect()))
    assert got == sorted(map(tuple, df.collect()))


@pytest.mark.parametrize(("kind", "value"), [("double", "if(id % 40 = 1, double('NaN'), id % 97 - 48D)"), ("string", "concat('v', id % 97)"), ("date", "date_add(date '1990-01-01', cast(id % 97 as int))")])
def test_ranks_of_a_sort(spark, monkeypatch, kind, value):
    """Nulls, NaN, and a value that fills several partitions of the sort."""
    hot = {"double": "-0.5D", "string": "'v5'", "date": "date '1990-01-06'"}[kind]
    facts = spark.range(0, 4000, 1, 3).selectExpr(f"case when id % 50 = 0 then null when id % 10 < 8 then {hot} else {value} end as v", "cast(id * 7919 % 1013 as int) as other")
    written, write = [], pieces.materialise
    monkeypatch.setattr(pieces, "materialise", lambda df: written.append(write(df)) or written[-1])
    spark.conf.set("spark.sql.adaptive.coalescePartitions.enabled", "false")
    try:
        df, n = pieces.ranked(facts, "v", ["other"])
        got = df.withColumn("want", F.expr("dense_rank() over (order by v asc nulls first) - 1")).orderBy("pos").collect()
    finally:
        spark.conf.unset("spark.sql.adaptive.coalescePartitions.enabled")
    assert [r.pos for r in got] == list(range(4000))
    assert all(r.ord_v == r.want for r in got)
    assert [(r.ord_v, r.other) for r in got] == sorted((r.ord_v, r.other) for r in got)
    assert n == facts.distinct().select("v").distinct().count()
    assert written[0].where(f"v = {hot}").select(F.shiftright("__at", 33)).distinct().count() > 1


def test_large_dictionaries_are_not_joined(spark):
    """Their values are ranked by one sort, in the order of the columns from the last one, and only dictionaries below the limit are looked up."""
    facts = spark.range(0, 3000, 1, 3).selectExpr("id % 7 as a", "if(id % 11 = 0, null, id * 7919 % 1009) as b", "cast(id as string) as key")
    df, sizes, order = pieces.with_ordinals(facts, ["a", "b"], [], 100)
    assert sizes == {"a": 7, "b": 1010} and order == ["b", "a"] and set(df.columns) == {"pos", "ord_a", "ord_b"}
    assert "SortMergeJoin" not in df._jdf.queryExecution().executedPlan().toString()
    got = list(map(tuple, df.orderBy("pos").select("ord_b", "ord_a").collect()))
    want = facts.selectExpr("cast(dense_rank() over (order by b asc nulls first) - 1 as int) as b", "cast(a as int) as a")
    assert got == sorted(map(tuple, want.collect()))


def test_records_of_a_group_are_one_row():
    """Bitmaps of a group share a row, and come back from it, parts of words too."""
    import numpy as np

    start, positions = 40, (np.arange(1000) * 7919 % 500)[:, None]
    rows = pieces.summary(start, positions, 500)
    group, records = pieces.grouped(start, rows, 100)
    assert group.tolist() == [0, 1, 2, 3, 4]
    back = pieces.opened(group, np.full(5, start >> 5), records, 100)
    order = np.lexsort((rows[1], rows[0]))
    keep = np.where(rows[4] == 0, 0, 1)  # only then last_start counts
    for i, (x, y) in enumerate(zip(rows, back, strict=True)):
        assert np.array_equal((x * keep if i == 3 else x)[order], y * keep[order] if i == 3 else y)
