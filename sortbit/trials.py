"""The experiments on synthetic tables and the grids over orders, codes and blocks, with their SQL.

A sweep places one small table under many designs (an order and a code) at once: each design
is a branch of one plan, ordered by a window of its own, and all their bitmaps are measured in
one pass. Grids over the given tables place each order by one global sort of the columns'
ordinals and write it; all codes are measured on the written places, by pieces.
"""

from __future__ import annotations

from collections.abc import Iterator
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window
from pyspark.sql import functions as F

from . import datagen
from .codes import gray_direction, ordinals, plan_codes, unrank
from .io import materialise
from .pieces import BROADCAST, code_sizes, code_totals, place_hashed, place_sorted, with_ordinals
from .profile import value_counts
from .registry import register
from .roworder import hash_key, place_rows
from .words import sizes_marker32, to_words
from .workloads import PROJECTIONS, Projection

ORDERS = ("shuffle", "grouped", "lex", "gray", "lexgray")


@dataclass(frozen=True)
class Design:
    """A table's columns under an order and a k; "lexgray" is the lexicographic order over Gray-allocated codes."""

    name: str
    order: str
    cols: tuple[str, ...]
    k: int

    @property
    def allocation(self) -> str:
        return "gray" if self.order == "lexgray" else "alpha"


def _bits(col: str, k: int, allocation: str) -> str:
    return f"{col}__{k}{allocation[0]}"


def coded(df: DataFrame, cols: list[str], ks: list[int]) -> tuple[DataFrame, dict]:
    """df with each column's codes for each k and allocation, and (k, bitmaps) by (column, k asked)."""

    def dictionary(c: str) -> tuple[DataFrame, dict]:
        counts = materialise(value_counts(df, c))
        n = counts.count()
        plans = {(c, k): plan_codes(n, k) for k in ks}
        out = ordinals(counts, F.col("value").asc_nulls_first(), n=n)
        codes = [unrank(F.col("ord"), size, k, a).alias(_bits(c, asked, a)) for (_, asked), (k, size) in plans.items() for a in ("alpha", "gray")]
        return materialise(out.select(F.col("value").alias(f"__{c}"), *codes)), plans

    with ThreadPoolExecutor(8) as pool:
        made = list(pool.map(dictionary, cols))
    plans = {}
    for c, (codes, p) in zip(cols, made, strict=True):
        df = df.join(F.broadcast(codes), F.col(c).eqNullSafe(F.col(f"__{c}"))).drop(f"__{c}")
        plans |= p
    return materialise(df), plans


def _order(design: Design, plans: dict) -> list[Column]:
    cols = design.cols
    if design.order == "shuffle":
        return [hash_key(42, [F.col("id")])]
    if design.order == "grouped":
        return [hash_key(42, [F.col(c) for c in cols]), *map(F.col, cols)]
    if design.order == "gray":
        ks = [plans[c, design.k][0] for c in cols]
        keys = [F.transform(F.col(_bits(c, design.k, "alpha")), lambda p, j: F.when(j % 2 == 0, -p).otherwise(p)) for c in cols]
        return [key.asc() if up else key.desc() for key, up in zip(keys, gray_direction(ks), strict=True)]
    return [F.col(c) for c in cols]


def sweep(df: DataFrame, designs: list[Design], n: int) -> DataFrame:
    """(design, attr, bitmap_id, c_words, n_words) of a table of n rows (with a column id), small enough for one task to sort."""
    df, plans = coded(df, sorted({c for d in designs for c in d.cols}), sorted({d.k for d in designs}))
    out = None
    for d in designs:
        parts = F.array(*[F.struct(F.lit(c).alias("attr"), F.col(_bits(c, d.k, d.allocation)).alias("bits")) for c in d.cols])
        pos = F.row_number().over(Window.partitionBy(F.lit(d.name)).orderBy(*_order(d, plans))) - 1
        placed = df.withColumn("pos", pos.cast("bigint"))  # numbered before anything is exploded
        one = placed.select(F.lit(d.name).alias("design"), "pos", F.explode(parts).alias("x")).select("design", "pos", "x.attr", F.explode("x.bits").alias("bitmap_id"))
        out = one if out is None else out.unionByName(one)
    by = ("design", "attr", "bitmap_id")
    return sizes_marker32(to_words(out, by=by), n, by=by)


# ---------------------------------------------------------------- SQL of the same


def code_ctes(cols: list[str], k: int, source: str = "ranked", gray: bool = False, suffix: str = "") -> tuple[str, str]:
    """CTEs with the codes (ord, bits, k) of each column for a k, limited by its number of values; and the joins' columns."""
    out = []
    for c in cols:
        out.append(f"card_{c}{suffix} AS (SELECT max(ord_{c}) + 1 AS n FROM {source})")
        out.append(f"eff_{c}{suffix} AS (SELECT n, CASE WHEN n <= 5 THEN 1 WHEN n <= 21 THEN least({k}, 2) WHEN n <= 85 THEN least({k}, 3) ELSE {k} END AS k FROM card_{c}{suffix})")
        options = []
        for kk in range(1, k + 1):
            a = "abcd"[:kk]
            count = {1: "m", 2: "m * (m - 1) // 2", 3: "m * (m - 1) * (m - 2) // 6", 4: "m * (m - 1) * (m - 2) * (m - 3) // 24"}[kk]
            out.append(f"num_{c}_{kk}{suffix} AS (SELECT unnest(range(0, (SELECT min(m) FROM (SELECT unnest(range({kk}, {30000 if kk == 1 else 3000})) AS m) WHERE {count} >= (SELECT n FROM eff_{c}{suffix} WHERE k = {kk})))) AS i)")
            joined = " ".join([f"num_{c}_{kk}{suffix} {a[0]}", *[f"JOIN num_{c}_{kk}{suffix} {y} ON {x}.i < {y}.i" for x, y in zip(a, a[1:])]])
            order = ", ".join(f"{'-' if gray and kk > 1 and j % 2 == 0 else ''}{x}.i" for j, x in enumerate(a))
            options.append(f"SELECT row_number() OVER (ORDER BY {order}) - 1 AS ord_{c}, [{', '.join(f'{x}.i' for x in a)}] AS bits_{c}{suffix} FROM {joined}")
        out.append(f"code_{c}{suffix} AS ({' UNION ALL '.join(options)})")
    return ", ".join(out), ", ".join(f"bits_{c}{suffix}" for c in cols)


def gray_sql(cols: list[str], k: int, suffix: str = "") -> str:
    """ORDER BY terms of the Gray order over codes bits_<col>: signs alternate in a code and flip with the weights before it."""
    keys, odd = [], "0"
    for c in cols:
        sign = f"(CASE WHEN ({odd}) % 2 = 0 THEN 1 ELSE -1 END)"
        keys += [f"{sign} * {'-' if j % 2 == 0 else ''}coalesce(bits_{c}{suffix}[{j + 1}], 0)" for j in range(k)]
        odd += f" + len(bits_{c}{suffix})"
    return ", ".join(keys)


SIZE = """typed AS (SELECT *, (bits = 4294967295)::INT AS ones FROM word),
    run AS (SELECT design, attr, bitmap_id, ones, count(*) AS len FROM (
        SELECT *, word_no - row_number() OVER (PARTITION BY design, attr, bitmap_id, ones ORDER BY word_no) AS g FROM typed) GROUP BY design, attr, bitmap_id, ones, g),
    per_run AS (SELECT design, attr, bitmap_id, sum(CASE WHEN ones = 0 THEN len + (len + 32766) // 32767 - 1 ELSE (len + 65534) // 65535 END) AS c FROM run GROUP BY ALL),
    gap AS (SELECT design, attr, bitmap_id, word_no, ones, word_no - coalesce(lag(word_no) OVER (PARTITION BY design, attr, bitmap_id ORDER BY word_no), -1) - 1 AS g FROM typed),
    per_gap AS (SELECT design, attr, bitmap_id, sum((g + 65534) // 65535) + (any_value((n + 31) // 32) - 1 - max(word_no) + 65534) // 65535 + max(CASE WHEN word_no = 0 AND ones = 0 THEN 1 ELSE 0 END) AS c
        FROM gap, total GROUP BY ALL),
    size AS (SELECT design, attr, bitmap_id, (a.c + b.c)::BIGINT AS c_words, ((n + 31) // 32)::BIGINT AS n_words
        FROM per_run a JOIN per_gap b USING (design, attr, bitmap_id), total)"""
WORD = "word AS (SELECT design, attr, bitmap_id, pos // 32 AS word_no, sum(1::BIGINT << (pos % 32)::INT)::BIGINT AS bits FROM bit GROUP BY ALL)"


def sweep_sql(table: str, designs: list[Design]) -> str:
    """CTEs up to `size` (design, attr, bitmap_id, c_words, n_words) for a table given as a SELECT with a column id."""
    cols = sorted({c for d in designs for c in d.cols})
    ords = ", ".join(f"dense_rank() OVER (ORDER BY {c}) - 1 AS ord_{c}" for c in cols)
    ctes, joins = [f"base AS MATERIALIZED ({table})", f"ranked AS MATERIALIZED (SELECT *, {ords} FROM base)"], ""
    for k in sorted({d.k for d in designs}):
        for gray in (False, True):
            if any(d.k == k and (d.allocation == "gray") == gray for d in designs):
                suffix = f"_{k}{'g' if gray else 'a'}"
                ctes.append(code_ctes(cols, k, "ranked", gray, suffix)[0])
                joins += "".join(f" LEFT JOIN code_{c}{suffix} USING (ord_{c})" for c in cols)
    ctes.append(f"coded AS MATERIALIZED (SELECT * FROM ranked{joins})")
    parts = []
    for i, d in enumerate(designs):
        suffix = f"_{d.k}{d.allocation[0]}"
        by = {"shuffle": "md5('42|' || id)", "grouped": f"md5(concat_ws('|', '42', {', '.join(d.cols)})), {', '.join(d.cols)}", "gray": gray_sql(list(d.cols), d.k, f"_{d.k}a")}.get(d.order, ", ".join(d.cols))
        ctes.append(f"placed_{i} AS (SELECT *, row_number() OVER (ORDER BY {by}) - 1 AS pos FROM coded)")
        parts += [f"SELECT '{d.name}' AS design, '{c}' AS attr, unnest(bits_{c}{suffix}) AS bitmap_id, pos FROM placed_{i}" for c in d.cols]
    return f"WITH {', '.join(ctes)}, bit AS ({' UNION ALL '.join(parts)}), total AS (SELECT count(*) AS n FROM base), {WORD}, {SIZE}"


# ---------------------------------------------------------------- synthetic sweeps: gains over d, skew and k, factors by bitmap

ROWS = 5000


def _totals(sizes: DataFrame) -> DataFrame:
    return sizes.groupBy("design").agg(F.sum("c_words").alias("c_words")).select(F.split("design", " ")[0].alias("setting"), F.split("design", " ")[1].alias("row_order"), "c_words")


_TOTALS = " SELECT split_part(design, ' ', 1) AS setting, split_part(design, ' ', 2) AS row_order, sum(c_words)::BIGINT AS c_words FROM size GROUP BY ALL"


def _uniform(spark: SparkSession, n: int, d: int, r: int) -> DataFrame:
    return materialise(datagen.add_dependent(datagen.uniform_table(spark, n, d, r), [f"a{j}" for j in range(1, d + 1)], d))


def _uniform_cols(d: int) -> tuple[str, ...]:
    return tuple(datagen.permute_columns([f"{x}{j}" for x in "ab" for j in range(1, d + 1)]))


def _gain_uniform(d: int, r: int) -> None:
    designs = [Design(f"d={d} {o}", o, _uniform_cols(d), 2) for o in ORDERS]
    register(f"gain_uniform_r{r}_d{d}", lambda spark, sf_dir: _totals(sweep(_uniform(spark, ROWS, d, r), designs, ROWS)), sweep_sql(datagen.uniform_sql(ROWS, d, r), designs) + _TOTALS)


def _zipf_designs(ds, ks) -> list[Design]:
    return [Design(f"{'d=' + str(d) if len(ds) > 1 else 'k=' + str(k)} {o}", o, tuple(f"z{j}" for j in range(1, d + 1)), k) for d in ds for k in ks for o in ORDERS]


def _gain_zipf(name: str, s: float, ds, ks) -> None:
    designs, d = _zipf_designs(ds, ks), max(ds)
    register(name, lambda spark, sf_dir: _totals(sweep(materialise(datagen.zipf_table(spark, ROWS, d, s)), designs, ROWS)), sweep_sql(datagen.zipf_sql(ROWS, d, s), designs) + _TOTALS)


for _r in (1, 2):
    for _d in range(1, 7):
        _gain_uniform(_d, _r)
for _s in (0.5, 1.0, 1.5, 2.0):
    _gain_zipf(f"gain_zipf_s{str(_s).replace('.', '')}", _s, range(1, 7), (2,))
_gain_zipf("gain_zipf_k", 2.0, (2,), (2, 3, 4))

_FACTOR = " SELECT design AS row_order, attr, bitmap_id::BIGINT AS bitmap_id, n_words - c_words AS saved, n_words AS plain_words FROM size"


def _factors(sizes: DataFrame) -> DataFrame:
    return sizes.select(F.col("design").alias("row_order"), "attr", F.col("bitmap_id").cast("bigint").alias("bitmap_id"), (F.col("n_words") - F.col("c_words")).alias("saved"), F.col("n_words").alias("plain_words"))


_four = lambda cols, k=4: [Design(o, o, tuple(cols), k) for o in ("shuffle", "grouped", "lex", "gray")]
_zipf_four, _uniform_six = _four([f"z{j}" for j in range(1, 5)]), _four(["a1", "a2", "a3", "b1", "b2", "b3"])
register("factor_zipf_k4", lambda spark, sf_dir: _factors(sweep(materialise(datagen.zipf_table(spark, 8449, 4, 1.0)), _zipf_four, 8449)), sweep_sql(datagen.zipf_sql(8449, 4, 1.0), _zipf_four) + _FACTOR)
register("factor_uniform_k4", lambda spark, sf_dir: _factors(sweep(_uniform(spark, 20_000, 3, 2), _uniform_six, 20_000)), sweep_sql(datagen.uniform_sql(20_000, 3, 2), _uniform_six) + _FACTOR)


# ---------------------------------------------------------------- grids over the given tables


def _placed_facts(p: Projection, orders: list[str], ks: list[int], facts: DataFrame, values: dict[str, int], order: list[str]) -> Iterator[tuple[str, list[int], DataFrame]]:
    """(order, its ks, facts (pos, ord_<col>...)). Orders by the columns sort packed ordinals; blocks are cut from one shuffle.

    order: the columns that the facts' own pos numbers them by.
    """
    shuffled = None
    for o in orders:
        if o in ("asc", "desc"):
            cols = p.names if o == "asc" else p.names[::-1]
            yield o, ks, facts if cols == order else place_sorted(facts, cols, values)
        elif o == "shuffle" or o.startswith("blocks"):
            if shuffled is None:
                random = p.order("shuffle")
                shuffled = place_hashed(facts, hash_key(random.seed, list(random.key)), p.names, values)
                n = shuffled.count()
            if o == "shuffle":
                yield o, ks, shuffled
            else:
                block = F.floor(F.col("pos") * int(o[6:]) / F.lit(max(1, n))).cast("int")
                yield o, ks, place_sorted(shuffled.withColumn("ord_block", block), ["block", *p.names[::-1]], values | {"block": int(o[6:])})
        else:
            for k in ks if o.startswith("gray") else [None]:
                yield o, ks if k is None else [k], place_rows(facts.drop("pos"), p.order(o, k or 1))


def grid(name: str, orders: list[str], ks: list[int], spark: SparkSession, sf_dir: str, measure=code_sizes) -> DataFrame:
    """What `measure` gives: each order placed once, all codes measured on it. design: order and k."""
    p = PROJECTIONS[name]
    facts = p.load(spark, sf_dir)
    keep = [] if set(orders) <= {"asc", "desc"} else facts.columns
    facts, values, order = with_ordinals(facts, p.names, keep, BROADCAST)
    placed, n = [], None
    for o, some, at in _placed_facts(p, orders, ks, facts, values, order):
        n = at.count() if n is None else n
        codes: dict[tuple[str, int, int], list[str]] = {}
        for c in p.names:
            for k in some:
                codes.setdefault((c, *plan_codes(values[c], k)), []).append(f"{o} k={k}")
        placed.append((at, [(*code, designs) for code, designs in codes.items()]))
    return measure(placed, values, n)


def grid_sql(name: str, orders: list[str], ks: list[int], placed) -> str:
    """CTEs up to `size`. placed(order): the ORDER BY of an order, over the columns and ordinals of `ranked`."""
    p = PROJECTIONS[name]
    ords = ", ".join(f"dense_rank() OVER (ORDER BY {n}) - 1 AS ord_{n}" for n in p.names)
    ctes = [f"base AS ({p.select_sql()})", f"ranked AS (SELECT *, {ords} FROM base)"]
    for k in ks:
        ctes.append(code_ctes(p.names, k, "ranked", False, f"_{k}a")[0])
    parts = []
    for i, o in enumerate(orders):
        if o.startswith("gray"):
            cols = p.names if o.endswith("asc") else p.names[::-1]
            for k in ks:
                joins = "".join(f" LEFT JOIN code_{c}_{k}a USING (ord_{c})" for c in p.names)
                ctes.append(f"at_{i}_{k} AS (SELECT *, row_number() OVER (ORDER BY {gray_sql(cols, k, f'_{k}a')}) - 1 AS pos FROM ranked{joins})")
        else:
            ctes.append(f"at_{i} AS ({placed(o)})")
        for k in ks:
            source = f"at_{i}_{k}" if o.startswith("gray") else f"at_{i}"
            for c in p.names:
                bits = f"unnest(bits_{c}_{k}a)"
                join = "" if o.startswith("gray") else f" JOIN code_{c}_{k}a USING (ord_{c})"
                parts.append(f"SELECT '{o} k={k}' AS design, '{c}' AS attr, {bits} AS bitmap_id, pos FROM {source}{join}")
    return f"WITH {', '.join(ctes)}, bit AS ({' UNION ALL '.join(parts)}), total AS (SELECT count(*) AS n FROM base), {WORD}, {SIZE}"


def _placed_sql(name: str):
    p = PROJECTIONS[name]
    shuffle = p.shuffle_sql()

    def placed(order: str) -> str:
        cols = ", ".join(p.names if order.endswith("asc") else p.names[::-1])
        if order == "shuffle":
            return f"SELECT *, row_number() OVER (ORDER BY {shuffle}) - 1 AS pos FROM ranked"
        if order == "grouped":
            return f"SELECT *, row_number() OVER (ORDER BY {p.grouped_sql()}) - 1 AS pos FROM ranked"
        if order.startswith("blocks"):
            cut = f"SELECT *, floor((row_number() OVER (ORDER BY {shuffle}) - 1) * {int(order[6:])} / count(*) OVER ()) AS block_no FROM ranked"
            return f"SELECT *, row_number() OVER (ORDER BY block_no, {cols}) - 1 AS pos FROM ({cut})"
        return f"SELECT *, row_number() OVER (ORDER BY {cols}) - 1 AS pos FROM ranked"

    return placed


_BY_DESIGN = " SELECT split_part(design, ' ', 1) AS row_order, split_part(design, '=', 2)::BIGINT AS k, attr, count(*)::BIGINT AS n_bitmaps, sum(c_words)::BIGINT AS c_words, sum(n_words)::BIGINT AS plain_words FROM size GROUP BY ALL"


def _by_design(totals: DataFrame) -> DataFrame:
    return totals.select(F.split("design", " ")[0].alias("row_order"), F.split("design", "=")[1].cast("bigint").alias("k"), "attr", "n_bitmaps", "c_words", "plain_words")


def _grid(key: str, name: str, orders: list[str], ks: list[int]) -> None:
    register(key, lambda spark, sf_dir: _by_design(grid(name, orders, ks, spark, sf_dir, code_totals)), grid_sql(name, orders, ks, _placed_sql(name)) + _BY_DESIGN)


for _p in ("p_gen", "p_near_unique", "p_rare", "p_frequent"):
    _grid(f"order_by_k_{_p}", _p, ["asc", "desc"], [1, 2, 3, 4])
for _p in ("p_gen", "p_frequent"):
    _grid(f"blocks_by_k_{_p}", _p, ["blocks1", "blocks5", "blocks10", "blocks500", "shuffle"], [1, 2, 3, 4])
for _p in ("p_near_unique", "p_dominant"):
    _orders = ["shuffle", "grouped", "asc", "gray_asc"]
    register(f"factor_k4_{_p}", lambda spark, sf_dir, p=_p, o=_orders: _factors(grid(p, o, [4], spark, sf_dir)), grid_sql(_p, _orders, [4], _placed_sql(_p)) + _FACTOR)
