import pytest
from pyspark.sql import functions as F

from sortbit.advise import advise_order, vertical_groups
from sortbit.index import IndexSpec, build_index, load_index
from sortbit.measure import external_sort_plan, index_words, bitmap_sizes
from sortbit.optimum import edge_rows, metric_tour_order, optimal_order, path_cost
from sortbit.predicate import And, Eq, In, IsNull, Not, Or, Range, normalise, parse
from sortbit.roworder import GrayCode, Lexicographic, place_rows

FACTS = [(1, 1, 1, 2), (2, 2, 1, 1), (3, 1, 2, 10), (4, 1, 1, 3), (5, 1, 3, 1), (1, 2, 1, 2), (6, 2, 1, 1)]


@pytest.fixture(scope="module")
def facts(spark):
    return spark.createDataFrame([(i, *f) for i, f in enumerate(FACTS)], "i int, city int, vehicle int, colour int, qty int")


def test_seven_facts(facts):
    index = build_index(facts, ["city", "vehicle"], Lexicographic(("i",)))
    at = lambda p: sorted(r.i for r in index.fetch(p).collect())
    assert at(Eq("city", 1)) == [0, 5]
    assert at(Eq("vehicle", 2)) == [1, 5, 6]
    assert at(And((Eq("city", 1), Eq("vehicle", 2)))) == [5]
    assert index.count(Eq("city", 99)) == 0 and index.count(Not(Eq("city", 99))) == 7


@pytest.mark.parametrize("codec", ["marker32", "flag31", "deflate"])
@pytest.mark.parametrize("k", [1, 2, 3])
def test_index_answers_as_a_scan(spark, k, codec):
    df = spark.range(500).select("id", F.when(F.col("id") % 11 == 0, None).otherwise(F.col("id") % 37).alias("a"), (F.col("id") % 7).alias("b"))
    index = build_index(df, ["a", "b"], Lexicographic(("a", "b")), IndexSpec(k=k, codec=codec, block_rows=64))
    for p, sql in [
        (Eq("a", 5), "a = 5"),
        (In("a", (1, 2, 3)), "a in (1, 2, 3)"),
        (Range("a", 3, 9), "a between 3 and 9"),
        (IsNull("a"), "a is null"),
        (parse("NOT (a = 5 OR b = 2) AND b >= 1"), "not (coalesce(a, -1) = 5 or b = 2) and b >= 1"),
        (parse("a <> 4"), "a <> 4"),
        (Or((Eq("a", 1), Not(Eq("b", 3)))), "coalesce(a, -1) = 1 or b <> 3"),
    ]:
        want = sorted(r.id for r in df.where(sql).collect())
        assert sorted(r.id for r in index.fetch(p).collect()) == want, sql
        assert index.count(p) == len(want)


def test_saved_index(spark, facts, tmp_path):
    build_index(facts, ["city"], Lexicographic(("city",))).save(str(tmp_path / "x"))
    assert load_index(spark, str(tmp_path / "x"), ["city"]).count(Eq("city", 1)) == 2


def test_rebuilding_gives_equal_payloads(facts):
    rows = lambda: sorted((r.block_id, r.attr, r.bitmap_id, bytes(r.payload)) for r in build_index(facts, ["city", "colour"], Lexicographic(("city", "colour", "i"))).rows.collect())
    assert rows() == rows()


def test_empty_table(facts):
    index = build_index(facts.where("i < 0"), ["city"], Lexicographic(("city",)))
    assert index.count(Eq("city", 1)) == 0 and index.fetch(Eq("city", 1)).count() == 0


def test_parser_and_normal_form():
    assert parse("a = 1 AND (b = 'x''y' OR c IS NOT NULL)") == And((Eq("a", 1), Or((Eq("b", "x'y"), Not(IsNull("c"))))))
    assert normalise(Not(And((Eq("a", 1), Not(Eq("b", 2)))))) == Or((Not(Eq("a", 1)), Eq("b", 2)))
    with pytest.raises(ValueError):
        parse("a = ")


def test_gray_order_of_nine_rows(spark):
    bits = ["011", "011", "101", "101", "110", "110", "111", "111", "111"]
    df = spark.createDataFrame([([int(x) for x in b],) for b in bits], "r array<int>").select([F.col("r")[i].alias(f"c{i}") for i in range(3)])
    set_bits = F.filter(F.transform(F.array("c0", "c1", "c2"), lambda x, i: F.when(x == 1, i)), lambda x: x.isNotNull())
    from sortbit.codes import gray_key

    got = ["".join(map(str, r)) for r in df.orderBy(gray_key(set_bits, 3)).collect()]
    assert got == ["011"] * 2 + ["110"] * 2 + ["111"] * 3 + ["101"] * 2


@pytest.mark.parametrize("k", [1, 2, 3])
def test_gray_ranks_sort_as_gray_bits(spark, k):
    df = spark.range(300).select((F.col("id") * 7 % 23).alias("a"), (F.col("id") * 5 % 29).alias("b"))
    fast, slow = ([(r.a, r.b) for r in place_rows(df, GrayCode(("a", "b"), k, generic=g)).orderBy("pos").collect()] for g in (False, True))
    assert fast == slow


def test_sorting_shrinks_the_index(spark):
    df = spark.range(3000).select((F.hash("id") % 50).alias("a"), (F.hash(F.col("id") + 1) % 7).alias("b"))
    total = lambda order: index_words(bitmap_sizes(df, order, ["a", "b"])).where("attr = 'total'").first().c_words
    from sortbit.roworder import Shuffled

    shuffled = total(Shuffled((F.col("a"), F.col("b"))))  # equal rows have equal keys, so even this order groups them
    assert total(Lexicographic(("b", "a"))) < shuffled and total(Lexicographic(("a", "b"))) < shuffled


def test_advice(spark):
    df = spark.range(3200).select((F.col("id") % 3).alias("few"), (F.col("id") % 100).alias("often"), F.col("id").alias("unique"))
    assert advise_order(df, ["few", "often", "unique"], "asc") == ["few", "often", "unique"]
    assert advise_order(df, ["few", "often", "unique"], "frequency") == ["often", "few", "unique"]
    assert sorted(advise_order(df, ["few", "often", "unique"], "model")) == ["few", "often", "unique"]
    assert vertical_groups(list("abcde"), 2) == [["a", "b"], ["c", "d"], ["e"]]


def test_tiny_optima():
    path = edge_rows(4, [(0, 1), (2, 3), (1, 2)])
    assert path_cost(optimal_order(path)) == 2 * (3 - 1)
    apart = edge_rows(4, [(0, 1), (2, 3)])
    assert path_cost(optimal_order(apart)) == 4
    rows = ["0000", "1111", "0001", "1110", "0011"]
    assert sorted(metric_tour_order(rows)) == sorted(rows) and path_cost(metric_tour_order(rows)) <= 2 * path_cost(optimal_order(rows)) + 4


def test_sort_plan():
    assert external_sort_plan(1000, 100, 10) == {"runs": 10, "ahead": 9, "passes": 2, "two_pass_capacity": 10000}


def test_range_codes(spark):
    df = spark.range(400).select("id", F.when(F.col("id") % 13 == 0, None).otherwise(F.col("id") % 31).alias("a"))
    index = build_index(df, ["a"], Lexicographic(("a",)), IndexSpec(style="range", block_rows=64))
    for p, sql in [(Eq("a", 5), "a = 5"), (In("a", (0, 7, 30)), "a in (0, 7, 30)"), (Range("a", 3, 9), "a between 3 and 9"), (Range("a", None, 0), "a <= 0"), (IsNull("a"), "a is null"), (Not(Range("a", 3, None)), "a < 3 or a is null")]:
        assert sorted(r.id for r in index.fetch(p).collect()) == sorted(r.id for r in df.where(sql).collect()), sql
    assert len(index.explain(Range("a", 3, 9))["bitmaps"]) == 2


def test_functions_on_payloads(spark):
    from sortbit import udfs

    df = spark.range(100).select("id", (F.col("id") % 3).alias("a"), (F.col("id") % 5).alias("b"))
    rows = build_index(df, ["a", "b"], Lexicographic(("id",))).rows
    rows.createOrReplaceTempView("index_rows")
    udfs.register(spark)
    pair = "from index_rows x join index_rows y on x.attr = 'a' and x.bitmap_id = 1 and y.attr = 'b' and y.bitmap_id = 2"
    got = spark.sql("select " + ", ".join(f"bm_count(bm_{op}(x.payload, y.payload, x.n_rows), x.n_rows) as {op}" for op in ("and", "or", "xor", "andnot", "xnor")) + f", bm_count(bm_not(x.payload, x.n_rows), x.n_rows) as no {pair}").first()
    one, two = {i for i in range(100) if i % 3 == 1}, {i for i in range(100) if i % 5 == 2}
    assert tuple(got) == (len(one & two), len(one | two), len(one ^ two), len(one - two), 100 - len(one ^ two), 100 - len(one))
    at = spark.sql("select pos from index_rows x, lateral bm_positions(x.payload, x.n_rows) where x.attr = 'a' and x.bitmap_id = 1")
    assert {r.pos for r in at.collect()} == one


def test_lookups_of_the_rivals(spark):
    from sortbit.baselines import hash_index, hash_lookup, scan, value_index

    df = spark.range(500).select("id", (F.col("id") * 7 % 41).alias("v"))
    want = sorted(r.id for r in scan(df, "v = 9").collect())
    assert sorted(r.id for r in value_index(df, "v", ["id"]).where("value = 9").collect()) == want
    assert sorted(r.id for r in hash_lookup(hash_index(df, "v", ["id"], 8), 9, 8).collect()) == want


def test_synthetic_data_and_trends(spark):
    from sortbit.datagen import add_dependent, permute_columns, uniform_table, zipf_table
    from sortbit.roworder import Grouped, Shuffled

    u = add_dependent(uniform_table(spark, 2000, 2), ["a1", "a2"], 2)
    assert u.agg(F.max("a1"), F.min("a1")).first()[0] <= 99 and u.columns == ["id", "a1", "a2", "b1", "b2"]
    assert u.exceptAll(add_dependent(uniform_table(spark, 2000, 2), ["a1", "a2"], 2)).count() == 0
    assert sorted(permute_columns(["a", "b", "c"], 4)) == ["a", "b", "c"]
    z = zipf_table(spark, 2000, 1, 1.0, 500).persist()
    total = lambda o: index_words(bitmap_sizes(z, o, ["z1"], 2)).where("attr = 'total'").first().c_words
    shuffled, grouped, lex = total(Shuffled((F.col("id"),))), total(Grouped(("z1",))), total(Lexicographic(("z1",)))
    assert lex < grouped < shuffled


def test_streaming_histogram(spark, tmp_path):
    from sortbit.stream import streaming_histogram

    df = spark.createDataFrame([("2024-01-01 00:10:00", "a"), ("2024-01-01 00:20:00", "a"), ("2024-01-01 01:10:00", "b")], "ts string, v string").withColumn("ts", F.col("ts").cast("timestamp"))
    df.write.parquet(str(tmp_path / "in"))
    q = streaming_histogram(spark.readStream.schema(df.schema).parquet(str(tmp_path / "in")), "ts", "v").writeStream.format("memory").queryName("hist").outputMode("complete").trigger(availableNow=True).start()
    q.awaitTermination()
    assert sorted((r.value, r.freq) for r in spark.table("hist").collect()) == [("a", 2), ("b", 1)]
