"""Queries about answers from indexes: worked examples, roll-ups, groups, rivals, streams, functions and further measures."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import baselines, codes, measure, profile, stream, udfs
from .hierarchy import build_hierarchy
from .index import IndexSpec, build_index
from .io import compact, concat_blocks, read_table, shared_dir, write_sorted
from .predicate import Eq, Range, parse
from .registry import register
from .roworder import GrayCode, Lexicographic, NoOrder, PartitionSorted
from .words import to_words
from .workloads import PROJECTIONS


def _path(spark: SparkSession, name: str) -> str:
    return f"{shared_dir(spark)}/{name}-{uuid.uuid4().hex}"


def _lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read_table(spark, sf_dir, "lineitem")


# ---------------------------------------------------------------- worked examples

#: Rows of a block of the predicates' example.
_BLOCK = 1 << 18


def _two_predicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Non-zero words of the bits of two predicates and of their AND, over the orders by key."""
    facts = read_table(spark, sf_dir, "orders").select("o_orderkey", "o_orderstatus", "o_orderpriority")
    index = build_index(facts, ["o_orderstatus", "o_orderpriority"], Lexicographic(("o_orderkey",)), IndexSpec(block_rows=_BLOCK, cut="table"))
    out = None
    for name, p in (("status", Eq("o_orderstatus", "F")), ("priority", Eq("o_orderpriority", "1-URGENT")), ("both", parse("o_orderstatus = 'F' AND o_orderpriority = '1-URGENT'"))):
        one = index.where(p).select(F.lit(name).alias("predicate"), (F.col("block_id") * _BLOCK + F.col("pos")).alias("pos"))
        out = one if out is None else out.unionByName(one)
    return to_words(out, by=("predicate",))


register("example_seven_facts", _two_predicates, """WITH o AS (SELECT *, row_number() OVER (ORDER BY o_orderkey) - 1 AS pos FROM orders),
    bit AS (SELECT 'status' AS predicate, pos FROM o WHERE o_orderstatus = 'F' UNION ALL SELECT 'priority', pos FROM o WHERE o_orderpriority = '1-URGENT'
        UNION ALL SELECT 'both', pos FROM o WHERE o_orderstatus = 'F' AND o_orderpriority = '1-URGENT')
    SELECT predicate, pos // 32 AS word_no, sum(1::BIGINT << (pos % 32)::INT)::BIGINT AS bits FROM bit GROUP BY ALL""")


def _bit_text(bits, size: int):
    return F.array_join(F.transform(F.sequence(F.lit(0), F.lit(size - 1)), lambda i: F.array_contains(bits, i.cast("int")).cast("int").cast("string")), "")


def _two_of(allocation: str):
    """The codes of two bitmaps of l_linenumber's values as bit rows."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        d = codes.assign_codes(_lines(spark, sf_dir), "l_linenumber", 2, allocation, limit_k=False)
        size = d.select("n_bitmaps").first()[0]
        return d.select(F.col("value").cast("bigint").alias("value"), "freq", _bit_text(F.col("bits"), size).alias("code"))

    return run


def _two_of_sql(order: str) -> str:
    return f"""WITH h AS (SELECT l_linenumber::BIGINT AS value, count(*)::BIGINT AS freq, row_number() OVER (ORDER BY l_linenumber) - 1 AS ord FROM lineitem GROUP BY l_linenumber),
        size AS (SELECT min(m) AS l FROM (SELECT unnest(range(2, 200)) AS m) WHERE m * (m - 1) // 2 >= (SELECT count(*) FROM h)), num AS (SELECT i FROM (SELECT unnest(range(200)) AS i), size WHERE i < l),
        code AS (SELECT row_number() OVER (ORDER BY {order}) - 1 AS ord, repeat('0', a.i::INT) || '1' || repeat('0', (b.i - a.i - 1)::INT) || '1' || repeat('0', (l - b.i - 1)::INT) AS code FROM num a JOIN num b ON a.i < b.i, size)
        SELECT value, freq, code FROM h JOIN code USING (ord)"""


register("example_six_codes", _two_of("alpha"), _two_of_sql("a.i, b.i"))
register("example_gray_codes", _two_of("gray"), _two_of_sql("-a.i, b.i"))

_FLAGS = ("l_returnflag = 'R'", "l_linestatus = 'O'", "l_quantity >= 25")


def _bit_rows(gray: bool):
    """The bit rows of three predicates over the facts, in lexicographic or Gray order."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        rows = _lines(spark, sf_dir).select(F.concat(*[F.expr(f"string(int({p}))") for p in _FLAGS]).alias("bits"))
        at = F.filter(F.transform(F.split("bits", ""), lambda x, i: F.when(x == "1", i)), lambda x: x.isNotNull())
        groups = rows.groupBy("bits").agg(F.count("*").alias("n")).withColumn("key", codes.gray_key(at, 3))
        return codes.ordinals(groups, F.col("key" if gray else "bits").asc(), "place").select("place", "bits", "n")

    return run


def _bit_rows_sql(order: str) -> str:
    one = lambda p: f"({p})::INT"
    return f"""WITH r AS (SELECT {', '.join(f'{one(p)} AS b{i}' for i, p in enumerate(_FLAGS))} FROM lineitem), g AS (SELECT b0, b1, b2, count(*)::BIGINT AS n FROM r GROUP BY ALL)
        SELECT row_number() OVER (ORDER BY {order}) - 1 AS place, concat(b0, b1, b2) AS bits, n FROM g"""


register("example_nine_rows_lex", _bit_rows(False), _bit_rows_sql("b0, b1, b2"))
register("example_nine_rows_gray", _bit_rows(True), _bit_rows_sql("4 * b0 + 2 * xor(b0, b1) + xor(xor(b0, b1), b2)"))

_MEASURED = ("l_returnflag", "l_linenumber", "l_discount", "l_quantity", "l_shipdate", "l_suppkey", "l_partkey")


def _lengths(spark: SparkSession, sf_dir: str) -> DataFrame:
    """k and bitmaps of the fact table's columns, for each k asked."""
    lines = _lines(spark, sf_dir)
    n = {c: profile.value_counts(lines, c).count() for c in _MEASURED}
    asked = [(c, n[c], k, *codes.plan_codes(n[c], k)) for c in _MEASURED for k in (1, 2, 3, 4)]
    return spark.createDataFrame(asked, "attr string, n_values bigint, asked bigint, k bigint, bitmaps bigint")


register("code_lengths", _lengths, f"""WITH a AS (SELECT attr, n::BIGINT AS n_values, k::BIGINT AS asked FROM ({' UNION ALL '.join(f"SELECT '{c}' AS attr, count(*) AS n FROM (SELECT DISTINCT {c} FROM lineitem)" for c in _MEASURED)}), (SELECT unnest([1, 2, 3, 4]) AS k)),
    e AS (SELECT *, CASE WHEN n_values <= 5 THEN 1 WHEN n_values <= 21 THEN least(asked, 2) WHEN n_values <= 85 THEN least(asked, 3) ELSE asked END::BIGINT AS k FROM a),
    m AS (SELECT unnest(range(1, 6000))::HUGEINT AS m)
    SELECT attr, n_values, asked, k, (CASE k WHEN 1 THEN n_values WHEN 2 THEN (SELECT min(m) FROM m WHERE m * (m - 1) // 2 >= n_values) WHEN 3 THEN (SELECT min(m) FROM m WHERE m * (m - 1) * (m - 2) // 6 >= n_values)
        ELSE (SELECT min(m) FROM m WHERE m * (m - 1) * (m - 2) * (m - 3) // 24 >= n_values) END)::BIGINT AS bitmaps FROM e""")


def _plans(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Plans to sort the orders and the facts, whose keys are counted."""
    rows = []
    for table, key in (("orders", "o_orderkey"), ("lineitem", "l_orderkey")):
        n = read_table(spark, sf_dir, table).where(F.col(key) >= 0).count()
        for memory, reserve in ((100, 10), (1000, 0), (1 << 20, 1 << 10)):
            p = measure.external_sort_plan(n, memory, reserve)
            rows.append((table, n, memory, reserve, p["runs"], p["ahead"], p["two_pass_capacity"]))
    return spark.createDataFrame(rows, "source string, n bigint, memory bigint, reserve bigint, runs bigint, ahead bigint, two_pass_capacity bigint")


register("external_sort_plans", _plans, """SELECT source, n, m AS memory, x AS reserve, ((n + m - 1) // m)::BIGINT AS runs, greatest(0, (m - x) // ((n + m - 1) // m))::BIGINT AS ahead, (m * m)::BIGINT AS two_pass_capacity
    FROM (SELECT 'orders' AS source, count(*)::BIGINT AS n FROM orders WHERE o_orderkey >= 0 UNION ALL SELECT 'lineitem', count(*)::BIGINT FROM lineitem WHERE l_orderkey >= 0), (VALUES (100::BIGINT, 10::BIGINT), (1000, 0), (1048576, 1024)) v(m, x)""")


# ---------------------------------------------------------------- roll-ups, groups, bins


def _customers(spark: SparkSession, sf_dir: str) -> DataFrame:
    t = lambda n: read_table(spark, sf_dir, n)
    places = t("nation").join(F.broadcast(t("region")), F.col("n_regionkey") == F.col("r_regionkey")).select("n_nationkey", "n_name", "r_name")
    return t("customer").join(F.broadcast(places), F.col("c_nationkey") == F.col("n_nationkey")).select("c_custkey", "r_name", "n_name")


_PLACES = "customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey"
register("rollup_nation", lambda spark, sf_dir: build_hierarchy(_customers(spark, sf_dir), ["r_name", "n_name"], spec=IndexSpec(block_rows=512)).roll_up(1), f"SELECT r_name, count(*)::BIGINT AS n FROM {_PLACES} GROUP BY r_name")
register("hierarchy_customers", lambda spark, sf_dir: build_hierarchy(_customers(spark, sf_dir), ["r_name", "n_name"], [1, 2], IndexSpec(block_rows=512)).roll_up(2), f"SELECT r_name, n_name, count(*)::BIGINT AS n FROM {_PLACES} GROUP BY ALL")


def _one_nation(spark: SparkSession, sf_dir: str) -> DataFrame:
    h = build_hierarchy(_customers(spark, sf_dir), ["r_name", "n_name"], spec=IndexSpec(block_rows=512))
    region, nation = h.paths.orderBy("n_name").select("r_name", "n_name").first()
    return h.index.fetch(h.at(region, nation)).select("c_custkey", "n_name")


register("hierarchy_fetch", _one_nation, f"SELECT c_custkey, n_name FROM {_PLACES} WHERE n_name = (SELECT min(n_name) FROM nation)")


def _dates(depth: int):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        day = F.col("l_shipdate")
        df = _lines(spark, sf_dir).select(F.year(day).cast("bigint").alias("y"), F.month(day).cast("bigint").alias("m"), F.dayofmonth(day).cast("bigint").alias("d"))
        return build_hierarchy(df, ["y", "m", "d"], [1, 2, 2], IndexSpec(block_rows=16384)).roll_up(depth)

    return run


register("rollup_year", _dates(1), "SELECT year(l_shipdate) AS y, count(*)::BIGINT AS n FROM lineitem GROUP BY ALL")
register("rollup_month", _dates(2), "SELECT year(l_shipdate) AS y, month(l_shipdate) AS m, count(*)::BIGINT AS n FROM lineitem GROUP BY ALL")


def _frequent(spark: SparkSession, sf_dir: str, **spec):
    p = PROJECTIONS["p_frequent"]
    return build_index(p.load(spark, sf_dir), p.names, p.order("desc"), IndexSpec(**({"block_rows": 16384} | spec)))


_GROUPED = "SELECT l_returnflag AS value, count(*)::BIGINT AS n FROM lineitem WHERE l_suppkey BETWEEN 20 AND 60 GROUP BY l_returnflag"
for _style, _k in (("equality", 1), ("equality", 2), ("range", 1)):
    register(f"group_count_where_{_style}_k{_k}", lambda spark, sf_dir, s=_style, k=_k: _frequent(spark, sf_dir, style=s, k=k).group_count("l_returnflag", Range("l_suppkey", 20, 60)), _GROUPED)
register("group_count_suppkey_k2", lambda spark, sf_dir: _frequent(spark, sf_dir, k=2).group_count("l_suppkey", Eq("l_returnflag", "R")), "SELECT l_suppkey AS value, count(*)::BIGINT AS n FROM lineitem WHERE l_returnflag = 'R' GROUP BY l_suppkey")
register("count_index_only", lambda spark, sf_dir: _frequent(spark, sf_dir).count_by_block(parse("l_returnflag = 'R' AND NOT l_suppkey = 7")).agg(F.sum("n").alias("n")), "SELECT count(*)::BIGINT AS n FROM lineitem WHERE l_returnflag = 'R' AND l_suppkey <> 7")
for _k in ({"l_returnflag": 1, "l_suppkey": 2, "l_shipdate": 3},):
    register("where_k_by_column", lambda spark, sf_dir, k=_k: _frequent(spark, sf_dir, k=k).fetch(parse("l_returnflag = 'R' AND l_suppkey IN (3, 5, 8)")).groupBy("l_suppkey").agg(F.count("*").alias("n")), "SELECT l_suppkey, count(*)::BIGINT AS n FROM lineitem WHERE l_returnflag = 'R' AND l_suppkey IN (3, 5, 8) GROUP BY l_suppkey")


def _wide(style: str, k: int):
    """A range of more values than a leaf evaluates one by one, where the table has so many."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        index = build_index(_lines(spark, sf_dir).select("l_orderkey", "l_linenumber"), ["l_orderkey"], Lexicographic(("l_orderkey",)), IndexSpec(k=k, style=style, block_rows=16384))
        return index.fetch(Range("l_orderkey", 100, 40_000)).groupBy("l_linenumber").agg(F.count("*").alias("n"))

    return run


for _style, _k in (("equality", 1), ("equality", 3), ("range", 1)):
    register(f"range_orderkey_{_style}_k{_k}", _wide(_style, _k), "SELECT l_linenumber, count(*)::BIGINT AS n FROM lineitem WHERE l_orderkey BETWEEN 100 AND 40000 GROUP BY l_linenumber")


def _quantile_bins(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bins of equal frequency; the two bins at the range's ends are checked again on the facts."""
    df = read_table(spark, sf_dir, "orders").select("o_orderkey", "o_totalprice")
    edges = codes.quantile_edges(df, "o_totalprice", 20)
    index = build_index(codes.bin_by_edges(df, "o_totalprice", edges, "bin"), ["bin"], Lexicographic(("bin",)), IndexSpec(block_rows=8192))
    return index.fetch(Range("bin", *codes.bins_of_range(edges, 25_000, 77_000))).where("o_totalprice between 25000 and 77000").select("o_orderkey", "o_totalprice")


def _month_bins(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bins by an expression: the month of a date."""
    df = read_table(spark, sf_dir, "orders").select("o_orderkey", "o_orderdate", F.trunc("o_orderdate", "month").alias("bin"))
    index = build_index(df, ["bin"], Lexicographic(("bin",)), IndexSpec(block_rows=8192))
    found = index.fetch(Range("bin", "1995-03-01", "1995-06-01")).where("o_orderdate >= timestamp_ntz'1995-03-15 00:00:00' and o_orderdate < timestamp_ntz'1995-06-10 00:00:00'")
    return found.select("o_orderkey")


register("bin_price_quantiles", _quantile_bins, "SELECT o_orderkey, o_totalprice FROM orders WHERE o_totalprice BETWEEN 25000 AND 77000")
register("bin_month", _month_bins, "SELECT o_orderkey FROM orders WHERE o_orderdate >= TIMESTAMP '1995-03-15' AND o_orderdate < TIMESTAMP '1995-06-10'")


# ---------------------------------------------------------------- builds and storage


def _reused(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Histograms are written once; the build reads them."""
    p, at = PROJECTIONS["p_gen"], _path(spark, "histograms")
    df = p.load(spark, sf_dir)
    profile.save_histograms(df, p.names, at)
    index = build_index(df, p.names, p.order("desc"), IndexSpec(block_rows=16384), histograms=profile.load_histograms(spark, at, p.names))
    return index.group_count("l_discount").select(F.round(F.col("value") * 100).cast("bigint").alias("percent"), "n")


register("histogram_reuse", _reused, "SELECT round(l_discount * 100)::BIGINT AS percent, count(*)::BIGINT AS n FROM lineitem GROUP BY ALL")


def _naive(naive: bool):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        index = build_index(_lines(spark, sf_dir).select("l_linenumber", "l_discount"), ["l_linenumber", "l_discount"], Lexicographic(("l_discount", "l_linenumber")), IndexSpec(block_rows=1 << 30), naive=naive)
        return index.rows.where("attr <> ''").select("attr", F.col("bitmap_id").cast("bigint").alias("bitmap_id"), F.col("n_set").alias("n"))

    return run


_EACH = "SELECT 'l_linenumber' AS attr, dense_rank() OVER (ORDER BY l_linenumber) - 1 AS bitmap_id, count(*)::BIGINT AS n FROM lineitem GROUP BY l_linenumber UNION ALL SELECT 'l_discount', dense_rank() OVER (ORDER BY l_discount) - 1, count(*)::BIGINT FROM lineitem GROUP BY l_discount"
register("build_naive", _naive(True), _EACH)
register("build_sparse", _naive(False), _EACH)


def _stored(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Saved, loaded with its own spec, and asked."""
    at = _path(spark, "index")
    _frequent(spark, sf_dir, codec="flag31", k=2).save(at)
    from .index import load_index

    return load_index(spark, at).group_count("l_suppkey", Eq("l_returnflag", "A"))


register("saved_index", _stored, "SELECT l_suppkey AS value, count(*)::BIGINT AS n FROM lineitem WHERE l_returnflag = 'A' GROUP BY l_suppkey")
register("block_sort_in_place", lambda spark, sf_dir: build_index(_lines(spark, sf_dir).select("l_returnflag", "l_suppkey"), ["l_returnflag", "l_suppkey"], PartitionSorted(("l_suppkey", "l_returnflag")), IndexSpec(block_rows=16384)).group_count("l_suppkey", Eq("l_returnflag", "N")), "SELECT l_suppkey AS value, count(*)::BIGINT AS n FROM lineitem WHERE l_returnflag = 'N' GROUP BY l_suppkey")


def _pruned(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The rival of sorted files: row-group statistics prune the scan."""
    at = _path(spark, "sorted")
    write_sorted(_lines(spark, sf_dir).select("l_partkey", "l_orderkey", "l_linenumber"), at, ["l_partkey"])
    return baselines.scan(spark.read.parquet(at), "l_partkey = 77").groupBy("l_orderkey", "l_linenumber").agg(F.count("*").alias("n"))


register("baseline_sorted_files", _pruned, "SELECT l_orderkey, l_linenumber, count(*)::BIGINT AS n FROM lineitem WHERE l_partkey = 77 GROUP BY ALL")


def _merged(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Many small files as few, then counted."""
    many, few = _path(spark, "many"), _path(spark, "few")
    read_table(spark, sf_dir, "orders").select("o_orderkey", "o_orderstatus").repartition(40).write.parquet(many)
    compact(spark, many, few)
    return profile.value_counts(spark.read.parquet(few), "o_orderstatus")


def _concatenated(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Two sorted blocks, one after the other."""
    df = read_table(spark, sf_dir, "orders").select("o_orderkey", "o_orderstatus")
    halves = [df.where(F.col("o_orderkey") % 2 == r).orderBy("o_orderstatus") for r in (0, 1)]
    return concat_blocks(halves).groupBy(F.col("block_id").cast("bigint").alias("block_id"), "o_orderstatus").agg(F.count("*").alias("n"))


register("compact_files", _merged, "SELECT o_orderstatus AS value, count(*)::BIGINT AS freq FROM orders GROUP BY 1")
register("concat_blocks", _concatenated, "SELECT o_orderkey % 2 AS block_id, o_orderstatus, count(*)::BIGINT AS n FROM orders GROUP BY ALL")


# ---------------------------------------------------------------- measures


def _sizes(name: str, spark: SparkSession, sf_dir: str, order: str) -> DataFrame:
    p = PROJECTIONS[name]
    return measure.bitmap_sizes(p.load(spark, sf_dir), p.order(order), p.names)


def register_measures(bits_sql, sizes_sql, words_sql, by_attr: str) -> None:
    """The measures' queries, with the catalogue's pieces of SQL."""

    for p in ("p_gen", "p_rare"):
        size = lambda o, p=p: f"({bits_sql(p, o)}, {sizes_sql(32)} SELECT coalesce(attr, 'total') AS attr, sum(c_words) AS c FROM size GROUP BY ROLLUP (attr))"
        register(f"order_effect_{p}", lambda spark, sf_dir, p=p: measure.order_effect(_sizes(p, spark, sf_dir, "asc"), _sizes(p, spark, sf_dir, "desc")), f"SELECT a.attr, a.c::DOUBLE / b.c::DOUBLE AS ratio FROM {size('asc')} a JOIN {size('desc')} b USING (attr)")
        register(f"sort_reach_{p}", lambda spark, sf_dir, p=p: measure.sort_reach(_sizes(p, spark, sf_dir, "asc"), _sizes(p, spark, sf_dir, "shuffle")), f"SELECT a.attr, a.c::DOUBLE / b.c::DOUBLE < 0.95 AS reached FROM {size('asc')} a JOIN {size('shuffle')} b USING (attr) WHERE a.attr <> 'total'")
    for k in (1, 2, 4):

        def run(spark: SparkSession, sf_dir: str, k=k) -> DataFrame:
            p = PROJECTIONS["p_gen"]
            bits, n = measure.placed_bits(p.load(spark, sf_dir), p.order("desc"), p.names, k)
            return measure.density(to_words(bits), n)

        register(f"density_k{k}", run, f"{bits_sql('p_gen', 'desc', k)} SELECT attr, count(*)::BIGINT AS true_bits, (count(DISTINCT bitmap_id) * any_value(n))::BIGINT AS all_bits FROM bit, total GROUP BY attr")
    register("expansion_p_gen_shuffle", lambda spark, sf_dir: measure.expansion(_sizes("p_gen", spark, sf_dir, "shuffle")), f"{bits_sql('p_gen', 'shuffle')}, {sizes_sql(32)} SELECT attr, max(c_words::DOUBLE / n_words::DOUBLE) AS expansion FROM size GROUP BY attr")

    def overhead(spark: SparkSession, sf_dir: str) -> DataFrame:
        p = PROJECTIONS["p_gen"]
        bits, n = measure.placed_bits(p.load(spark, sf_dir), p.order("asc"), p.names)
        return measure.marker_overhead(to_words(bits), n)

    up = lambda x, m: f"(({x}) + {m - 1}) // {m}"
    clean = lambda m: f"""SELECT attr, sum({up('len', m)}) AS c FROM run WHERE ones = 1 GROUP BY attr UNION ALL SELECT attr, sum({up('g', m)}) FROM gap GROUP BY attr
        UNION ALL SELECT attr, sum({up('t', m)}) FROM (SELECT attr, any_value((n + 31) // 32) - 1 - max(word_no) AS t FROM gap, total GROUP BY attr, bitmap_id) GROUP BY attr"""  # noqa: E731
    register("marker_overhead_p_gen", overhead, f"""{bits_sql('p_gen', 'asc')}, {sizes_sql(32)}, a AS (SELECT attr, sum(c)::BIGINT AS clean_marks FROM ({clean(65535)}) GROUP BY attr),
        b AS (SELECT attr, sum(c)::BIGINT AS clean_fills FROM ({clean((1 << 30) - 1)}) GROUP BY attr) SELECT attr, clean_marks, clean_fills FROM a JOIN b USING (attr)""")

    def shares(spark: SparkSession, sf_dir: str) -> DataFrame:
        df = _lines(spark, sf_dir)
        counts = profile.value_counts(df, "l_quantity").select(F.col("value").cast("bigint").alias("value"), F.col("freq").alias("n"))
        return measure.selectivity(counts, df.count())

    register("selectivity_quantity", shares, "SELECT l_quantity::BIGINT AS value, count(*)::BIGINT AS n, count(*)::DOUBLE / (SELECT count(*) FROM lineitem)::DOUBLE AS share FROM lineitem GROUP BY ALL")

    def words_read(spark: SparkSession, sf_dir: str) -> DataFrame:
        """Words that an equality query on each value reads, by column: leading columns read fewer."""
        sizes = _sizes("p_gen", spark, sf_dir, "desc")
        return sizes.groupBy("attr").agg(F.min("c_words").alias("least_words"), F.max("c_words").alias("most_words"), F.sum("c_words").alias("all_words"))

    register("words_read_p_gen", words_read, f"{bits_sql('p_gen', 'desc')}, {sizes_sql(32)} SELECT attr, min(c_words) AS least_words, max(c_words) AS most_words, sum(c_words)::BIGINT AS all_words FROM size GROUP BY attr")
    for p in ("p_gen", "p_near_unique"):
        register(f"words_{p}_asc", lambda spark, sf_dir, p=PROJECTIONS[p]: to_words(measure.placed_bits(p.load(spark, sf_dir), p.order("asc"), p.names)[0]).select("attr", F.col("bitmap_id").cast("bigint").alias("bitmap_id"), "word_no", "bits"), f"{bits_sql(p, 'asc')}, {words_sql(32)} SELECT * FROM word")

    def generic(spark: SparkSession, sf_dir: str) -> DataFrame:
        p = PROJECTIONS["p_gen"]
        return measure.index_words(measure.bitmap_sizes(p.load(spark, sf_dir), GrayCode(tuple(reversed(p.names)), 2, generic=True), p.names, 2))

    register("size_gray_generic_k2_p_gen_desc", generic, f"{bits_sql('p_gen', 'gray_desc', 2)}, {sizes_sql(32)} {by_attr}")

    def as_stored(spark: SparkSession, sf_dir: str) -> DataFrame:
        return measure.index_words(measure.bitmap_sizes(read_table(spark, sf_dir, "nation").coalesce(1), NoOrder(), ["n_regionkey"]))

    register("size_as_stored_nation", as_stored, "SELECT unnest(['n_regionkey', 'total']) AS attr, 5::BIGINT AS n_bitmaps, 10::BIGINT AS c_words, 5::BIGINT AS plain_words")


# ---------------------------------------------------------------- functions, the data source


def _or_agg(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rows with the first or the second flag: aggregates over the bitmaps of each block, in SQL."""
    udfs.register(spark)
    view = f"rows_{uuid.uuid4().hex}"
    _frequent(spark, sf_dir).rows.createOrReplaceTempView(view)
    per_block = f"""SELECT block_id, bm_count(any_row, n_rows) AS n_or, bm_count(every_row, n_rows) AS n_and
        FROM (SELECT block_id, n_rows, bm_or_agg(payload, n_rows) AS any_row, bm_and_agg(payload, n_rows) AS every_row FROM {view} WHERE attr = 'l_returnflag' AND bitmap_id < 2 GROUP BY block_id, n_rows)"""
    return spark.sql(f"SELECT sum(n_or) AS n_or FROM ({per_block})")


register("aggregate_functions", _or_agg, "SELECT count(*)::BIGINT AS n_or FROM (SELECT dense_rank() OVER (ORDER BY l_returnflag) AS s FROM lineitem) WHERE s <= 2")


def _code_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Codes of three of l_quantity's values, from the table function, beside the values."""
    udfs.register(spark)
    view = f"values_{uuid.uuid4().hex}"
    values = codes.ordinals(profile.value_counts(_lines(spark, sf_dir), "l_quantity"), F.col("value").asc_nulls_first())
    values.createOrReplaceTempView(view)
    k, size = codes.plan_codes(n := values.count(), 3)
    return spark.sql(f"SELECT bigint(value) AS value, freq, array_join(transform(bits, b -> string(b)), ',') AS code FROM {view} JOIN code_table({n}, {size}, {k}, 'gray') USING (ord)")


register("code_table", _code_table, """WITH h AS (SELECT l_quantity::BIGINT AS value, count(*)::BIGINT AS freq, row_number() OVER (ORDER BY l_quantity) - 1 AS ord FROM lineitem GROUP BY l_quantity),
    size AS (SELECT min(m) AS l FROM (SELECT unnest(range(3, 200)) AS m) WHERE m * (m - 1) * (m - 2) // 6 >= (SELECT count(*) FROM h)), num AS (SELECT i FROM (SELECT unnest(range(200)) AS i), size WHERE i < l),
    code AS (SELECT row_number() OVER (ORDER BY -a.i, b.i, -c.i) - 1 AS ord, concat_ws(',', a.i, b.i, c.i) AS code FROM num a JOIN num b ON a.i < b.i JOIN num c ON b.i < c.i)
    SELECT value, freq, code FROM h JOIN code USING (ord)""")


def _source(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Positions of some values, read through the data source; joined to the facts for their column."""
    from .source import register_source

    register_source(spark)
    at = _path(spark, "index")
    index = _frequent(spark, sf_dir)
    index.save(at)
    found = spark.read.format("sortbit").option("attr", "l_suppkey").load(at).where("ord between 4 and 9")
    return index.facts.join(found, ["block_id", "pos"]).groupBy("l_suppkey").agg(F.count("*").alias("n"))


register("data_source_positions", _source, "SELECT l_suppkey, count(*)::BIGINT AS n FROM (SELECT l_suppkey, dense_rank() OVER (ORDER BY l_suppkey) - 1 AS o FROM lineitem) WHERE o BETWEEN 4 AND 9 GROUP BY l_suppkey")


# ---------------------------------------------------------------- streams


def _event_files(spark: SparkSession, sf_dir: str, parts: int, *cols: str) -> tuple[DataFrame, str]:
    """Events as a stream of `parts` files, and a folder for what it writes."""
    root = _path(spark, "stream")
    events = read_table(spark, sf_dir, "events").select(*cols)
    events.repartition(parts).write.parquet(f"{root}/in")
    return spark.readStream.schema(events.schema).option("maxFilesPerTrigger", 1).parquet(f"{root}/in"), root


def _appended(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Asked batch by batch, without compaction."""
    source, root = _event_files(spark, sf_dir, 3, "event_type", "user_id")
    stream.append_blocks(source, ["event_type", "user_id"], f"{root}/out", f"{root}/state", IndexSpec(block_rows=2048)).awaitTermination()
    return stream.appended_index(spark, f"{root}/out").fetch(Range("user_id", 10, 20)).groupBy("event_type").agg(F.count("*").alias("n"))


register("stream_appended_events", _appended, "SELECT event_type, count(*)::BIGINT AS n FROM events WHERE user_id BETWEEN 10 AND 20 GROUP BY event_type")


def _dictionary(spark: SparkSession, sf_dir: str) -> DataFrame:
    """New values take the next ordinals: as many as there are values, without gaps."""
    source, root = _event_files(spark, sf_dir, 3, "user_id")
    stream.grow_dictionary(source, "user_id", f"{root}/dict", f"{root}/state").awaitTermination()
    return stream.read_dictionary(spark, f"{root}/dict").agg(F.countDistinct("value").alias("n_values"), F.countDistinct("ord").alias("n_ordinals"), F.max("ord").alias("last"))


register("stream_dictionary", _dictionary, "SELECT count(DISTINCT user_id) AS n_values, count(DISTINCT user_id) AS n_ordinals, count(DISTINCT user_id) - 1 AS last FROM events")


def _windows(**how):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        source, _ = _event_files(spark, sf_dir, 1, "ts", "event_type")
        name = f"w{uuid.uuid4().hex}"
        hist = stream.streaming_histogram(source, "ts", "event_type", late="3650 days", **how)
        out = hist.select(F.unix_timestamp("window.start").alias("begins"), F.unix_timestamp("window.end").alias("ends"), "value", "freq")
        out.writeStream.format("memory").queryName(name).outputMode("complete").trigger(availableNow=True).start().awaitTermination()
        return spark.table(name)

    return run


_HOURS = "epoch(time_bucket(INTERVAL 1 HOUR, ts))::BIGINT"
register("stream_windows_tumbling", _windows(), f"SELECT {_HOURS} AS begins, {_HOURS} + 3600 AS ends, event_type AS value, count(*)::BIGINT AS freq FROM events GROUP BY ALL")
register("stream_windows_sliding", _windows(window="2 hours", slide="1 hour"), f"SELECT {_HOURS} - h * 3600 AS begins, {_HOURS} - h * 3600 + 7200 AS ends, event_type AS value, count(*)::BIGINT AS freq FROM events, (SELECT unnest([0, 1]) AS h) GROUP BY ALL")


def _unrepeated(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every event twice in one file; the second of each goes."""
    root = _path(spark, "stream")
    events = read_table(spark, sf_dir, "events").select("ts", "event_id", "event_type")
    events.unionByName(events).coalesce(1).write.parquet(f"{root}/in")
    source = spark.readStream.schema(events.schema).parquet(f"{root}/in")
    once = stream.without_repeats(source, "ts", ["event_id"], "3650 days")
    once.writeStream.format("parquet").option("path", f"{root}/out").option("checkpointLocation", f"{root}/state").trigger(availableNow=True).start().awaitTermination()
    return spark.read.parquet(f"{root}/out").groupBy("event_type").agg(F.count("*").alias("n"))


register("stream_dedup", _unrepeated, "SELECT event_type, count(*)::BIGINT AS n FROM events GROUP BY event_type")
