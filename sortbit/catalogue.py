"""The driver's queries over the given tables, each with DuckDB SQL where SQL can express it."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import answers, baselines, codes, measure, profile, stream, udfs
from .advise import advise_order
from .codes import numbered
from .index import IndexSpec, build_index
from .io import flatten_pairs, read_flat, read_table, shared_dir
from .predicate import Eq, Not, Range, Xor, parse
from .registry import Query, oracle_sql, queries, register
from .roworder import Lexicographic
from .trials import code_ctes, gray_sql
from .words import to_words
from .workloads import PROJECTIONS

__all__ = ["oracle_sql", "queries"]

# ---------------------------------------------------------------- SQL pieces


def placed_sql(name: str, order: str, k: int = 1, gray_codes: bool = False) -> str:
    """CTEs up to `coded`: each row's pos, each column's ordinal and, for k > 1, its code bits_<col>."""
    p = PROJECTIONS[name]
    ords = ", ".join(f"dense_rank() OVER (ORDER BY {n}) - 1 AS ord_{n}" for n in p.names)
    columns = p.names if order.endswith("asc") else p.names[::-1]
    base, source = f"base AS ({p.select_sql()}), ranked AS (SELECT *, {ords} FROM base)", "ranked"
    if k > 1 or order.startswith("gray"):
        base += ", " + code_ctes(p.names, k, "ranked", gray_codes)[0]
        base += f", full_code AS (SELECT * FROM ranked{''.join(f' JOIN code_{n} USING (ord_{n})' for n in p.names)})"
        source = "full_code"
    if order.startswith("blocks"):
        cut = f"SELECT *, floor((row_number() OVER (ORDER BY {p.shuffle_sql()}) - 1) * {int(order[6:])} / count(*) OVER ()) AS block_no FROM {source}"
        return base + f", coded AS (SELECT *, row_number() OVER (ORDER BY block_no, {', '.join(columns)}) - 1 AS pos FROM ({cut}))"
    by = p.shuffle_sql() if order == "shuffle" else p.grouped_sql() if order == "grouped" else gray_sql(columns, k) if order.startswith("gray") else ", ".join(columns)
    return base + f", coded AS (SELECT *, row_number() OVER (ORDER BY {by}) - 1 AS pos FROM {source})"


def bits_sql(name: str, order: str, k: int = 1, gray_codes: bool = False) -> str:
    """CTEs up to `bit` (attr, bitmap_id, pos) and `total` (n)."""
    p = PROJECTIONS[name]
    one = lambda n: f"unnest(bits_{n})" if k > 1 else f"ord_{n}"
    parts = " UNION ALL ".join(f"SELECT '{n}' AS attr, {one(n)} AS bitmap_id, pos FROM coded" for n in p.names)
    return f"WITH {placed_sql(name, order, k, gray_codes)}, bit AS ({parts}), total AS (SELECT count(*) AS n FROM coded)"


def words_sql(width: int) -> str:
    return f"word AS (SELECT attr, bitmap_id, pos // {width} AS word_no, sum(1::BIGINT << (pos % {width})::INT)::BIGINT AS bits FROM bit GROUP BY ALL)"


def sizes_sql(width: int) -> str:
    """CTEs up to `size` (attr, bitmap_id, c_words, n_words); 32: marker format, 31: flag format."""
    full, clean, lits = (1 << width) - 1, (65535 if width == 32 else (1 << 30) - 1), (32767 if width == 32 else 1 << 62)
    up = lambda x, m: f"(({x}) + {m - 1}) // {m}"
    start = "+ max(CASE WHEN word_no = 0 AND ones = 0 THEN 1 ELSE 0 END)" if width == 32 else ""
    literal = f"len + {up('len', lits)} - 1" if width == 32 else "len"
    return f"""{words_sql(width)},
        typed AS (SELECT *, (bits = {full})::INT AS ones FROM word),
        run AS (SELECT attr, bitmap_id, ones, count(*) AS len FROM (
            SELECT *, word_no - row_number() OVER (PARTITION BY attr, bitmap_id, ones ORDER BY word_no) AS g FROM typed) GROUP BY attr, bitmap_id, ones, g),
        per_run AS (SELECT attr, bitmap_id, sum(CASE WHEN ones = 0 THEN {literal} ELSE {up('len', clean)} END) AS c FROM run GROUP BY ALL),
        gap AS (SELECT attr, bitmap_id, word_no, ones, word_no - coalesce(lag(word_no) OVER (PARTITION BY attr, bitmap_id ORDER BY word_no), -1) - 1 AS g FROM typed),
        per_gap AS (SELECT attr, bitmap_id, sum({up('g', clean)}) + {up(f'any_value((n + {width - 1}) // {width}) - 1 - max(word_no)', clean)} {start} AS c
            FROM gap, total GROUP BY attr, bitmap_id),
        size AS (SELECT attr, bitmap_id, (a.c + b.c)::BIGINT AS c_words, ((n + 31) // 32)::BIGINT AS n_words
            FROM per_run a JOIN per_gap b USING (attr, bitmap_id), total)"""


_TOTALS = """SELECT coalesce(attr, 'total') AS attr, count(*)::BIGINT AS n_bitmaps, sum(c_words)::BIGINT AS c_words, sum(n_words)::BIGINT AS plain_words
        FROM size GROUP BY ROLLUP (attr)"""


# ---------------------------------------------------------------- sizes under row orders, codes and codecs


def _size(name: str, order: str, k: int = 1, allocation: str = "alpha", codec: str = "marker32") -> Query:
    p = PROJECTIONS[name]
    return lambda spark, sf_dir: measure.index_words(measure.bitmap_sizes(p.load(spark, sf_dir), p.order(order, k), p.names, k, allocation, codec))


def _with_bits(name: str, order: str, f, k: int = 1) -> Query:
    p = PROJECTIONS[name]
    return lambda spark, sf_dir: f(*measure.placed_bits(p.load(spark, sf_dir), p.order(order, k), p.names, k))


for _p in PROJECTIONS:
    for _o in ("shuffle", "grouped", "asc", "desc"):
        register(f"size_{_p}_{_o}", _size(_p, _o), f"{bits_sql(_p, _o)}, {sizes_sql(32)} {_TOTALS}")
for _p in ("p_gen", "p_near_unique", "p_rare", "p_frequent"):
    register(f"size_k2_{_p}_desc", _size(_p, "desc", 2), f"{bits_sql(_p, 'desc', 2)}, {sizes_sql(32)} {_TOTALS}")
    register(f"size_lexgray_k2_{_p}_desc", _size(_p, "desc", 2, "gray"), f"{bits_sql(_p, 'desc', 2, True)}, {sizes_sql(32)} {_TOTALS}")
    register(f"size_gray_{_p}_desc", _size(_p, "gray_desc"), f"{bits_sql(_p, 'gray_desc')}, {sizes_sql(32)} {_TOTALS}")
    register(f"size_gray_k2_{_p}_desc", _size(_p, "gray_desc", 2), f"{bits_sql(_p, 'gray_desc', 2)}, {sizes_sql(32)} {_TOTALS}")
    register(f"size_flag31_{_p}_desc", _size(_p, "desc", codec="flag31"), f"{bits_sql(_p, 'desc')}, {sizes_sql(31)} {_TOTALS}")
    for _k in (3, 4):
        register(f"size_k{_k}_{_p}_desc", _size(_p, "desc", _k), f"{bits_sql(_p, 'desc', _k)}, {sizes_sql(32)} {_TOTALS}")
for _p in ("p_gen", "p_frequent"):
    for _b in (1, 5, 10, 500):
        register(f"size_blocks{_b}_{_p}", _size(_p, f"blocks{_b}"), f"{bits_sql(_p, f'blocks{_b}')}, {sizes_sql(32)} {_TOTALS}")
    for _o in ("shuffle", "desc"):
        register(f"hamming_{_p}_{_o}", _with_bits(_p, _o, measure.hamming_path), f"""{bits_sql(_p, _o)},
            near AS (SELECT *, lag(pos) OVER w AS a, lead(pos) OVER w AS z FROM bit WINDOW w AS (PARTITION BY attr, bitmap_id ORDER BY pos))
            SELECT attr, sum((pos > 0 AND pos - 1 IS DISTINCT FROM a)::INT + (pos < n - 1 AND pos + 1 IS DISTINCT FROM z)::INT)::BIGINT AS changes FROM near, total GROUP BY attr""")
        register(f"runs_{_p}_{_o}", _with_bits(_p, _o, measure.run_stats), f"""{bits_sql(_p, _o)},
            near AS (SELECT *, lag(pos) OVER (PARTITION BY attr, bitmap_id ORDER BY pos) AS a FROM bit),
            per AS (SELECT attr, bitmap_id, count(*) FILTER (WHERE a IS NULL OR pos - a <> 1) AS r, max((pos = 0)::INT) + max((pos = n - 1)::INT) AS ends FROM near, total GROUP BY ALL)
            SELECT attr, sum(r)::BIGINT AS one_runs, sum(r + 1 - ends)::BIGINT AS zero_runs FROM per GROUP BY attr""")
        register(f"word_stats_{_p}_{_o}", _with_bits(_p, _o, lambda bits, n: measure.word_stats(to_words(bits))), f"""{bits_sql(_p, _o)}, {words_sql(32)}
            SELECT attr, sum(bit_count(bits))::BIGINT AS true_bits, count(*)::BIGINT AS nonzero_words, count(*) FILTER (WHERE bits <> 4294967295)::BIGINT AS dirty_words
            FROM word GROUP BY attr""")
for _p in ("p_near_unique", "p_dominant"):
    register(f"bitmap_factor_{_p}_desc", lambda spark, sf_dir, p=PROJECTIONS[_p]: measure.bitmap_factor(measure.bitmap_sizes(p.load(spark, sf_dir), p.order("desc"), p.names)),
             f"{bits_sql(_p, 'desc')}, {sizes_sql(32)} SELECT attr, bitmap_id, n_words - c_words AS saved, n_words AS plain_words FROM size")


# ---------------------------------------------------------------- profiles and codes


def _profile(spark: SparkSession, sf_dir: str) -> DataFrame:
    return profile.column_profile(read_table(spark, sf_dir, "lineitem"), ["l_linenumber", "l_partkey", "l_suppkey", "l_returnflag", "l_orderkey"])


register("profile_lineitem", _profile, " UNION ALL ".join(
    f"SELECT '{c}' AS attr, count(*)::BIGINT AS ndv, sum(f)::BIGINT AS n, max(f)::BIGINT AS max_freq, coalesce(sum(f) FILTER (WHERE f >= 32), 0)::BIGINT AS rows_in_frequent FROM (SELECT {c}, count(*) AS f FROM lineitem GROUP BY {c})"
    for c in ("l_linenumber", "l_partkey", "l_suppkey", "l_returnflag", "l_orderkey")))
register("hist_lineitem_quantity", lambda spark, sf_dir: profile.value_counts(read_table(spark, sf_dir, "lineitem"), "l_quantity"), "SELECT l_quantity AS value, count(*)::BIGINT AS freq FROM lineitem GROUP BY l_quantity")


def _codes(k: int, allocation: str) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        d = codes.assign_codes(read_table(spark, sf_dir, "lineitem"), "l_shipdate", k, allocation)
        return d.select("ord", "n_bitmaps", F.array_join(F.transform("bits", lambda b: b.cast("string")), ",").alias("code"))

    return run


def _codes_sql(k: int, gray: bool) -> str:
    a = "abcd"[:k]
    joined = " ".join([f"num {a[0]}", *[f"JOIN num {y} ON {x}.i < {y}.i" for x, y in zip(a, a[1:])]])
    order = ", ".join(f"{'-' if gray and j % 2 == 0 else ''}{x}.i" for j, x in enumerate(a))
    count = {1: "m", 2: "m * (m - 1) / 2", 3: "m * (m - 1) * (m - 2) / 6", 4: "m * (m - 1) * (m - 2) * (m - 3) / 24"}[k]
    return f"""WITH card AS (SELECT count(DISTINCT l_shipdate) AS n FROM lineitem),
        size AS (SELECT min(m) AS l FROM (SELECT unnest(range({k}, 3000)) AS m), card WHERE {count} >= n),
        num AS (SELECT i FROM (SELECT unnest(range(0, 3000)) AS i), size WHERE i < l),
        code AS (SELECT row_number() OVER (ORDER BY {order}) - 1 AS ord, concat_ws(',', {', '.join(f'{x}.i' for x in a)}) AS code FROM {joined})
        SELECT ord, l::INT AS n_bitmaps, code FROM code, size, card WHERE ord < n"""


for _k in (1, 2, 3, 4):
    register(f"codes_alpha_k{_k}", _codes(_k, "alpha"), _codes_sql(_k, False))
    if _k > 1:
        register(f"codes_gray_k{_k}", _codes(_k, "gray"), _codes_sql(_k, True))


# ---------------------------------------------------------------- payloads and queries through the index


def _index(spark: SparkSession, sf_dir: str, name: str, spec: IndexSpec, order: str = "desc"):
    p = PROJECTIONS[name]
    return build_index(p.load(spark, sf_dir), p.names, p.order(order), spec)


def _payload_words(name: str, codec: str = "marker32") -> Query:
    p = PROJECTIONS[name]

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        sizes = measure.payload_sizes(p.load(spark, sf_dir), p.order("desc"), p.names, codec=codec)
        return sizes.groupBy("attr").agg(F.count("*").alias("n_bitmaps"), F.sum("n_words").alias("stored_words"))

    return run


for _p in ("p_gen", "p_frequent"):
    for _c, _w in (("marker32", 32), ("flag31", 31)):
        register(f"payload_{_c}_{_p}", _payload_words(_p, _c), f"{bits_sql(_p, 'desc')}, {sizes_sql(_w)} SELECT attr, count(*)::BIGINT AS n_bitmaps, sum(c_words)::BIGINT AS stored_words FROM size GROUP BY attr")
    register(f"payload_runlength_{_p}", _payload_words(_p, "runlength"), f"""{bits_sql(_p, 'desc')},
        near AS (SELECT *, lag(pos) OVER (PARTITION BY attr, bitmap_id ORDER BY pos) AS a FROM bit),
        per AS (SELECT attr, bitmap_id, count(*) FILTER (WHERE a IS NULL OR pos - a <> 1) AS r, max((pos = 0)::INT) + max((pos = n - 1)::INT) AS ends FROM near, total GROUP BY ALL)
        SELECT attr, count(*)::BIGINT AS n_bitmaps, sum(2 * (2 * r + 1 - ends))::BIGINT AS stored_words FROM per GROUP BY attr""")
    register(f"payload_bytealigned_{_p}", _payload_words(_p, "bytealigned"))
    register(f"payload_deflate_{_p}", _payload_words(_p, "deflate"))
    register(f"payload_plain_{_p}", _payload_words(_p, "plain"), f"{bits_sql(_p, 'desc')}, {sizes_sql(32)} SELECT attr, count(*)::BIGINT AS n_bitmaps, sum(n_words)::BIGINT AS stored_words FROM size GROUP BY attr")
    register(f"payload_poslist_{_p}", _payload_words(_p, "poslist"), f"{bits_sql(_p, 'desc')} SELECT attr, count(DISTINCT bitmap_id)::BIGINT AS n_bitmaps, count(*)::BIGINT AS stored_words FROM bit GROUP BY attr")

#: Name: projection, predicate for the index, the same for SQL.
PREDICATES = {
    "and": ("p_gen", "l_linenumber = 3 AND l_discount = 0.05", None),
    "or": ("p_gen", "l_linenumber = 3 OR l_discount = 0.05", None),
    "andnot": ("p_gen", "l_linenumber = 3 AND NOT l_discount = 0.05", None),
    "not": ("p_gen", "NOT l_linenumber = 3", None),
    "xor": ("p_gen", Xor(Eq("l_linenumber", 3), Eq("l_discount", 0.05)), "(l_linenumber = 3) <> (l_discount = 0.05)"),
    "xnor": ("p_gen", Not(Xor(Eq("l_linenumber", 3), Eq("l_discount", 0.05))), "(l_linenumber = 3) = (l_discount = 0.05)"),
    "in": ("p_frequent", "l_suppkey IN (3, 14, 15, 92, 65) AND l_returnflag = 'R'", None),
    "range": ("p_gen", "l_partkey BETWEEN 100 AND 250 AND l_discount <= 0.02", None),
    "miss": ("p_gen", "l_partkey = -5", None),
}


def _fetch(name: str, predicate, spec: IndexSpec) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        found = _index(spark, sf_dir, name, spec).fetch(parse(predicate) if isinstance(predicate, str) else predicate)
        return found.groupBy(*PROJECTIONS[name].names).agg(F.count("*").alias("n"))

    return run


for _n, (_p, _pred, _sql) in PREDICATES.items():
    for _k in (1, 2) if _n in ("and", "range", "not") else (1,):
        _cols = ", ".join(PROJECTIONS[_p].names)
        register(f"where_{_n}_k{_k}", _fetch(_p, _pred, IndexSpec(k=_k, block_rows=8192)), f"SELECT {_cols}, count(*)::BIGINT AS n FROM {PROJECTIONS[_p].source_sql()} WHERE {_sql or _pred} GROUP BY {_cols}")


def _twelve(name: str, col: str, k: int, order: str = "desc") -> Query:
    """Twelve equality queries, the values at evenly spaced ranks of frequency, counted from the index alone."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        index = _index(spark, sf_dir, name, IndexSpec(k=k, block_rows=16384), order)
        return index.equality_counts(col, pick_values(index.dicts[col], 12)).select(F.col("value").alias(col), "n")

    return run


def pick_values(codes_: DataFrame, n: int) -> list:
    """n values at evenly spaced ranks of (frequency, value): the first of each of n equal parts."""
    ranked = numbered(codes_.select("freq", "value").orderBy("freq", "value"), "rank")
    total = ranked.count()
    starts = [i * (total // n) + min(i, total % n) for i in range(min(n, total))]  # the first parts are longer by one
    return [r[0] for r in ranked.where(F.col("rank").isin(starts)).orderBy("rank").select("value").collect()]


def _twelve_sql(col: str) -> str:
    return f"""WITH h AS (SELECT {col}, count(*) AS n FROM lineitem GROUP BY 1), t AS (SELECT *, ntile(12) OVER (ORDER BY n, {col}) AS tile FROM h)
        SELECT {col}, n::BIGINT AS n FROM t QUALIFY row_number() OVER (PARTITION BY tile ORDER BY n, {col}) = 1"""


for _k in (1, 2, 3, 4):
    register(f"eq_partkey_12_k{_k}", _twelve("p_gen", "l_partkey", _k), _twelve_sql("l_partkey"))
    register(f"eq_shipdate_12_k{_k}", _twelve("p_frequent", "l_shipdate", _k), _twelve_sql("l_shipdate"))
for _o in ("shuffle", "blocks5", "blocks10", "blocks500"):
    register(f"eq_partkey_12_{_o}", _twelve("p_gen", "l_partkey", 1, _o), _twelve_sql("l_partkey"))
register("group_count_returnflag", lambda spark, sf_dir: _index(spark, sf_dir, "p_frequent", IndexSpec(block_rows=8192)).group_count("l_returnflag"), "SELECT l_returnflag AS value, count(*)::BIGINT AS n FROM lineitem GROUP BY l_returnflag")


def _join_index(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Facts indexed by an attribute of a joined dimension."""
    t = lambda n: read_table(spark, sf_dir, n)
    star = t("orders").join(t("customer"), F.col("o_custkey") == F.col("c_custkey")).join(F.broadcast(t("nation")), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(t("region")), F.col("n_regionkey") == F.col("r_regionkey"))
    star = star.select("o_orderkey", "r_name", "o_orderpriority")
    index = build_index(star, ["r_name", "o_orderpriority"], Lexicographic(("r_name", "o_orderpriority")), IndexSpec(block_rows=8192))
    return index.fetch(parse("r_name = 'ASIA' AND NOT o_orderpriority = '1-URGENT'")).groupBy("o_orderpriority").agg(F.count("*").alias("n"))


register("join_index_region", _join_index, """SELECT o_orderpriority, count(*)::BIGINT AS n FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey
    JOIN region ON n_regionkey = r_regionkey WHERE r_name = 'ASIA' AND o_orderpriority <> '1-URGENT' GROUP BY 1""")


def _bins(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Binned bitmaps: the bins that meet a range are read, then the facts are checked again."""
    df = codes.bin_values(read_table(spark, sf_dir, "orders").select("o_orderkey", "o_totalprice"), "o_totalprice", 0, 10000.0, "bin")
    index = build_index(df, ["bin"], Lexicographic(("bin",)), IndexSpec(block_rows=8192))
    return index.fetch(Range("bin", 2, 7)).where("o_totalprice between 25000 and 77000").select("o_orderkey", "o_totalprice")


register("bin_price", _bins, "SELECT o_orderkey, o_totalprice FROM orders WHERE o_totalprice BETWEEN 25000 AND 77000")


def _hierarchy(spark: SparkSession, sf_dir: str) -> DataFrame:
    df = read_table(spark, sf_dir, "nation").join(read_table(spark, sf_dir, "region"), F.col("n_regionkey") == F.col("r_regionkey"))
    return codes.assign_hierarchy(df, ["r_name", "n_name"])


register("hierarchy_nation", _hierarchy, """SELECT r_name, n_name, dense_rank() OVER (ORDER BY r_name) - 1 AS code_1, dense_rank() OVER (PARTITION BY r_name ORDER BY n_name) - 1 AS code_2
    FROM nation JOIN region ON n_regionkey = r_regionkey""")


# ---------------------------------------------------------------- advice, generators, relations around the methods


def _advice(name: str, strategy: str) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        p = PROJECTIONS[name]
        order = advise_order(p.load(spark, sf_dir), p.names, strategy)
        return spark.createDataFrame([(i, c) for i, c in enumerate(order)], "place bigint, attr string")

    return run


for _p in ("p_gen", "p_rare", "p_frequent"):
    for _s in ("asc", "desc"):
        _cards = " UNION ALL ".join(f"SELECT '{c}' AS attr, count(DISTINCT {c}) AS n FROM {PROJECTIONS[_p].table}" for c in PROJECTIONS[_p].names)
        _by = "n, attr" if _s == "asc" else "n DESC, attr DESC"
        register(f"advise_{_s}_{_p}", _advice(_p, _s), f"SELECT row_number() OVER (ORDER BY {_by}) - 1 AS place, attr FROM ({_cards})")
    _often = " UNION ALL ".join(f"SELECT '{c}' AS attr, count(*) AS n, 4 * coalesce(sum(f) FILTER (WHERE f >= 32), 0) >= sum(f) AS often FROM (SELECT count(*) AS f FROM {PROJECTIONS[_p].table} GROUP BY {c})" for c in PROJECTIONS[_p].names)
    register(f"advise_frequency_{_p}", _advice(_p, "frequency"), f"SELECT row_number() OVER (ORDER BY often DESC, CASE WHEN often THEN -n ELSE n END, CASE WHEN often THEN attr END DESC, attr) - 1 AS place, attr FROM ({_often})")
    register(f"advise_model_{_p}", _advice(_p, "model"))


def _flat(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The source as a delimited file, read back and profiled."""
    df = read_table(spark, sf_dir, "nation")
    path = f"{shared_dir(spark)}/flat-{uuid.uuid4().hex}"
    df.write.csv(path, sep="|")
    return profile.value_counts(read_flat(spark, path, df.schema, "|"), "n_regionkey")


register("flat_nation", _flat, "SELECT n_regionkey AS value, count(*)::BIGINT AS freq FROM nation GROUP BY 1")
register("pairs_documents", lambda spark, sf_dir: flatten_pairs(read_table(spark, sf_dir, "documents").select("source", "text"), F.split("text", "\n"), "line").groupBy("source").agg(F.count("*").alias("facts"), F.countDistinct("line").alias("lines")),
         "SELECT source, count(*)::BIGINT AS facts, count(DISTINCT line)::BIGINT AS lines FROM (SELECT source, unnest(string_split(text, chr(10))) AS line FROM documents) GROUP BY source")
_oracles = oracle_sql()
register("scan_and", lambda spark, sf_dir: read_table(spark, sf_dir, "lineitem").where("l_linenumber = 3 and l_discount = 0.05").groupBy("l_linenumber", "l_discount", "l_partkey").agg(F.count("*").alias("n")), _oracles["where_and_k1"])


def _stream_blocks(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events appended batch by batch as sorted blocks, then asked through the compacted index."""
    events = read_table(spark, sf_dir, "events").select("event_type", "user_id")
    root = f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}"
    events.repartition(3).write.parquet(f"{root}/in")
    source = spark.readStream.schema(events.schema).option("maxFilesPerTrigger", 1).parquet(f"{root}/in")
    stream.append_blocks(source, ["event_type", "user_id"], f"{root}/out", f"{root}/state", IndexSpec(block_rows=2048)).awaitTermination()
    index = stream.compact(spark, f"{root}/out", ["event_type", "user_id"], IndexSpec(block_rows=2048))
    return index.fetch(Range("user_id", 10, 20)).groupBy("event_type").agg(F.count("*").alias("n"))


register("stream_blocks_events", _stream_blocks, "SELECT event_type, count(*)::BIGINT AS n FROM events WHERE user_id BETWEEN 10 AND 20 GROUP BY event_type")


# ---------------------------------------------------------------- range codes, rivals, functions on payloads, gains


def _range_code(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = PROJECTIONS["p_frequent"]
    index = build_index(p.load(spark, sf_dir), ["l_returnflag", "l_suppkey"], p.order("desc"), IndexSpec(style="range", block_rows=16384))
    return index.fetch(parse("l_suppkey BETWEEN 20 AND 40 AND NOT l_returnflag = 'R'")).groupBy("l_suppkey", "l_returnflag").agg(F.count("*").alias("n"))


register("range_code_suppkey", _range_code, "SELECT l_suppkey, l_returnflag, count(*)::BIGINT AS n FROM lineitem WHERE l_suppkey BETWEEN 20 AND 40 AND l_returnflag <> 'R' GROUP BY ALL")
_LOOKED_UP = "SELECT l_orderkey, l_linenumber, count(*)::BIGINT AS n FROM lineitem WHERE l_partkey = 77 GROUP BY ALL"
_count_lines = lambda df: df.groupBy("l_orderkey", "l_linenumber").agg(F.count("*").alias("n"))
register("baseline_value_index", lambda spark, sf_dir: _count_lines(baselines.value_index(read_table(spark, sf_dir, "lineitem"), "l_partkey", ["l_orderkey", "l_linenumber"]).where("value = 77")), _LOOKED_UP)
register("baseline_hash_index", lambda spark, sf_dir: _count_lines(baselines.hash_lookup(baselines.hash_index(read_table(spark, sf_dir, "lineitem"), "l_partkey", ["l_orderkey", "l_linenumber"]), 77)), _LOOKED_UP)
register("baseline_scan", lambda spark, sf_dir: _count_lines(baselines.scan(read_table(spark, sf_dir, "lineitem"), "l_partkey = 77")), _LOOKED_UP)


def _payload_functions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Counts of two columns' bitmaps under every function on payloads, for all pairs of values."""
    f = udfs.functions()
    index = _index(spark, sf_dir, "p_gen", IndexSpec(block_rows=16384))
    side = lambda attr, name: index.rows.where(F.col("attr") == attr).select("block_id", F.col("bitmap_id").cast("bigint").alias(name), F.col("payload").alias(f"{name}_bits"))
    every = lambda attr: F.explode(F.sequence(F.lit(0).cast("bigint"), F.lit(index.plans[attr][2] - 1).cast("bigint")))
    # a bitmap that a block lacks is empty there; the two columns have a few dozen pairs of values
    grid = index.rows.where("attr = ''").select("block_id", "n_rows", every("l_linenumber").alias("line")).select("*", every("l_discount").alias("discount"))
    pairs = grid.join(side("l_linenumber", "line"), ["block_id", "line"], "left").join(side("l_discount", "discount"), ["block_id", "discount"], "left")
    held = lambda c: F.coalesce(F.col(c), F.lit(b""))
    counted = pairs.select("line", "discount", *[f["bm_count"](f[f"bm_{op}"](held("line_bits"), held("discount_bits"), "n_rows"), "n_rows").alias(op) for op in ("and", "or", "xor", "andnot", "xnor")], f["bm_count"](f["bm_not"](held("line_bits"), "n_rows"), "n_rows").alias("not"))
    return counted.groupBy("line", "discount").agg(*[F.sum(op).alias(f"n_{op}") for op in ("and", "or", "xor", "andnot", "xnor", "not")])


register("payload_functions", _payload_functions, """WITH r AS (SELECT dense_rank() OVER (ORDER BY l_linenumber) - 1 AS x, dense_rank() OVER (ORDER BY l_discount) - 1 AS y FROM lineitem),
    pair AS (SELECT line, discount FROM (SELECT DISTINCT x AS line FROM r), (SELECT DISTINCT y AS discount FROM r))
    SELECT line, discount, sum((x = line AND y = discount)::INT)::BIGINT AS n_and, sum((x = line OR y = discount)::INT)::BIGINT AS n_or, sum(((x = line) <> (y = discount))::INT)::BIGINT AS n_xor,
        sum((x = line AND y <> discount)::INT)::BIGINT AS n_andnot, sum(((x = line) = (y = discount))::INT)::BIGINT AS n_xnor, sum((x <> line)::INT)::BIGINT AS n_not FROM r, pair GROUP BY ALL""")


def _gain(name: str, order: str) -> Query:
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        p = PROJECTIONS[name]
        df = p.load(spark, sf_dir)
        return measure.relative_gain(measure.bitmap_sizes(df, p.order(order), p.names), measure.bitmap_sizes(df, p.order("shuffle"), p.names))

    return run


def _abstract(bits: DataFrame, n: int) -> DataFrame:
    return measure.abstract_cost_bits(to_words(bits), n)


for _p in ("p_gen", "p_near_unique"):
    _one = lambda o, p=_p: f"({bits_sql(p, o)}, {sizes_sql(32)} {_TOTALS})"
    for _o in ("grouped", "asc", "desc"):
        register(f"gain_{_p}_{_o}", _gain(_p, _o), f"SELECT a.attr, 1 - a.c_words::DOUBLE / b.c_words::DOUBLE AS gain FROM {_one(_o)} a JOIN {_one('shuffle')} b USING (attr)")
    register(f"abstract_cost_{_p}_desc", _with_bits(_p, "desc", _abstract), f"""{bits_sql(_p, 'desc')}, {sizes_sql(32)},
        part AS (SELECT attr, sum(CASE WHEN ones = 0 THEN len ELSE (len + 65534) // 65535 END) AS c FROM run GROUP BY attr
            UNION ALL SELECT attr, sum((g + 65534) // 65535) FROM gap GROUP BY attr
            UNION ALL SELECT attr, sum((t + 65534) // 65535) FROM (SELECT attr, any_value((n + 31) // 32) - 1 - max(word_no) AS t FROM gap, total GROUP BY attr, bitmap_id) GROUP BY attr)
        SELECT attr, (32 * sum(c))::BIGINT AS bits FROM part GROUP BY attr""")


answers.register_measures(bits_sql, sizes_sql, words_sql, _TOTALS)
