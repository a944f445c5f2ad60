"""Engine paths that the catalogue's queries do not tell apart."""

import pytest
from pyspark.sql import functions as F

from sortbit import words as words_of
from sortbit.advise import advise_order, best_order, predicted_words, vertical_projections
from sortbit.codes import assign_hierarchy
from sortbit.hierarchy import build_hierarchy
from sortbit.index import IndexSpec, build_index, load_index
from sortbit.measure import bitmap_sizes, hamming_path, index_words, placed_bits, run_stats
from sortbit.predicate import Eq, Range
from sortbit.roworder import Lexicographic, NoOrder, PartitionSorted


@pytest.fixture(scope="module")
def table(spark):
    return spark.range(900).select("id", F.when(F.col("id") % 11 == 0, None).otherwise(F.col("id") * 7 % 61).alias("a"), (F.col("id") % 7).alias("b"))


def test_naive_build_makes_the_same_rows(table):
    rows = lambda naive: sorted((r.block_id, r.attr, r.bitmap_id, bytes(r.payload)) for r in build_index(table, ["a", "b"], Lexicographic(("a", "id")), IndexSpec(k=2, block_rows=128, cut="table"), naive=naive).rows.collect())
    assert rows(True) == rows(False)


def test_plan_of_a_query_reads_no_facts(table):
    index = build_index(table, ["a", "b"], Lexicographic(("a",)), IndexSpec(block_rows=128))
    facts = index.facts.inputFiles()[0].rpartition("/")[0].rpartition("/")[2]
    for p in (Eq("a", 5), ~Eq("b", 3), Range("a", 3, 40)):
        assert facts not in index.count_by_block(p)._jdf.queryExecution().toString()
        assert facts not in index.where(p)._jdf.queryExecution().toString()


def test_saved_spec_is_used(spark, table, tmp_path):
    build_index(table, ["a"], Lexicographic(("a",)), IndexSpec(k=2, codec="marker64", block_rows=100)).save(str(tmp_path / "x"))
    index = load_index(spark, str(tmp_path / "x"))
    assert index.spec.codec == "marker64" and index.count(Eq("a", 9)) == table.where("a = 9").count()
    assert index.fetch(Range("a", 3, 30)).count() == table.where("a between 3 and 30").count()


def test_leaves_of_many_codes_decode_rows(table, monkeypatch):
    from sortbit import index as module

    monkeypatch.setattr(module, "MANY_CODES", 5)
    index = build_index(table, ["a"], Lexicographic(("a",)), IndexSpec(k=3, block_rows=1 << 20))
    tree, named = index.plan(Range("a", 3, 30))
    assert index._bitmaps("a", named[tree]) is None
    block = module._Block(index.rows.toArrow(), index.spec, index.plans)
    from sortbit import bitops

    assert len(bitops.bm_positions(block.leaf("a", named[tree]))) == table.where("a between 3 and 30").count()


def test_runs_across_stretches(table, monkeypatch):
    def measures():
        bits, n = placed_bits(table, Lexicographic(("b", "a")), ["a", "b"])
        return sorted(map(tuple, run_stats(bits, n).collect())), sorted(map(tuple, hamming_path(bits, n).collect())), sorted(map(tuple, index_words(bitmap_sizes(table, Lexicographic(("b", "a")), ["a", "b"])).collect()))

    whole = measures()
    monkeypatch.setattr(words_of, "CHUNK", 2)
    assert measures() == whole


def test_groups_of_several_columns(table):
    index = build_index(table, ["a", "b"], NoOrder(), IndexSpec(k=2, block_rows=100))
    got = {(r.a, r.b): r.n for r in index.group_counts(["a", "b"], Range("b", 1, 4)).collect()}
    assert got == {(r.a, r.b): r["count"] for r in table.where("b between 1 and 4").groupBy("a", "b").count().collect()}


def test_hierarchy_shares_positions(spark):
    df = spark.createDataFrame([("x", "p"), ("x", "q"), ("y", "r"), ("y", "s"), ("y", "t"), ("z", "u"), ("x", "p")], "top string, low string")
    h = build_hierarchy(df, ["top", "low"])
    assert h.bitmaps() == {"top": 3, "low": 3}
    codes = {(r.top, r.low): (r.code_1, r.code_2) for r in assign_hierarchy(df, ["top", "low"]).collect()}
    assert codes["x", "q"][1] == codes["y", "s"][1] == 1
    assert h.index.count(h.at("x", "p")) == 2 and h.index.count(h.at("y")) == 3 and h.index.count(h.at("x", "r")) == 0
    assert {attr for attr, _ in h.index.explain(h.at("y"))["bitmaps"]} == {"code_1"}


def test_blocks_sorted_in_place_need_no_exchange(table):
    plan = PartitionSorted(("a", "b")).apply(table)._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan and "Sort" in plan


def test_greedy_advice(table):
    frequencies = {"few": [(1000, 3)], "often": [(30, 100)], "unique": [(1, 3000)]}
    best = best_order(frequencies, 3000, ["few", "often", "unique"])
    from itertools import permutations

    assert predicted_words(frequencies, 3000, best) == min(predicted_words(frequencies, 3000, list(o)) for o in permutations(frequencies))
    assert sorted(advise_order(table, ["a", "b"], "model", k=3)) == ["a", "b"]
    parts = vertical_projections(table, ["id"], ["a", "b"], 1)
    assert [g for g, _ in parts] == [["b"], ["a"]] and parts[1][1].columns == ["id", "a"]


def test_trends_of_synthetic_sweeps(spark):
    from sortbit import datagen
    from sortbit.io import materialise
    from sortbit.trials import Design, sweep

    def totals(df, cols, n):
        designs = [Design(o, o, cols, 2) for o in ("shuffle", "grouped", "lex", "gray")]
        return {r.design: r.w for r in sweep(df, designs, n).groupBy("design").agg(F.sum("c_words").alias("w")).collect()}

    zipf = totals(materialise(datagen.zipf_table(spark, 3000, 1, 2.0, 500)), ("z1",), 3000)
    assert zipf["lex"] <= zipf["grouped"] < zipf["shuffle"] and zipf["gray"] <= zipf["lex"] * 1.01
    assert zipf["lex"] < 0.35 * zipf["shuffle"]
    uniform = totals(materialise(datagen.add_dependent(datagen.uniform_table(spark, 3000, 1), ["a1"], 1)), ("a1", "b1"), 3000)
    assert abs(uniform["grouped"] / uniform["shuffle"] - 1) < 0.05 and 0.5 < uniform["lex"] / uniform["shuffle"] < 0.7
