"""Synthetic facts whose values depend on the row number and seed alone, so a retried task makes the same rows.

A draw is the first 40 bits of an md5 hash as a whole number, and all steps from it are whole-number
arithmetic: any engine with md5 makes the same tables.
"""

from __future__ import annotations

from random import Random

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: A draw is below 2 ** BITS.
BITS = 40


def draw(seed: int, column: int, at: Column) -> Column:
    """A whole number below 2 ** BITS for each row."""
    text = F.concat_ws("|", F.lit(str(seed)), F.lit(str(column)), at.cast("string"))
    return F.conv(F.substr(F.md5(text), F.lit(1), F.lit(10)), 16, 10).cast("bigint")


def draw_sql(seed: int, column: int, at: str) -> str:
    return f"('0x' || substr(md5('{seed}|{column}|' || {at}), 1, 10))::BIGINT"


def uniform_table(spark: SparkSession, n: int, d: int, r: int = 1, seed: int = 0) -> DataFrame:
    """Column j uniform over 100 * r ** (j - 1) values."""
    cols = [F.shiftright(draw(seed, j, F.col("id")) * (100 * r ** (j - 1)), BITS).alias(f"a{j}") for j in range(1, d + 1)]
    return spark.range(n).select("id", *cols)


def add_dependent(df: DataFrame, cols: list[str], count: int, seed: int = 0) -> DataFrame:
    """Columns that add up some of the others, each with chance 0.2; where none is drawn, uniform over 1..100."""
    for j in range(1, count + 1):
        drawn = [(draw(seed + 1, 100 * j + i, F.col("id")) * 5 < (1 << BITS)).cast("bigint") for i in range(len(cols))]
        total = sum((F.col(c) * p for c, p in zip(cols, drawn, strict=True)), F.lit(0))
        chance = F.shiftright(draw(seed + 2, j, F.col("id")) * 100, BITS) + 1
        df = df.withColumn(f"b{j}", F.when(sum(drawn, F.lit(0)) == 0, chance).otherwise(total).cast("bigint"))
    return df


def uniform_sql(n: int, d: int, r: int = 1, seed: int = 0) -> str:
    """The table of uniform_table with add_dependent over all its columns, in SQL."""
    cols = ", ".join(f"(({draw_sql(seed, j, 'id')} * {100 * r ** (j - 1)}) >> {BITS}) AS a{j}" for j in range(1, d + 1))
    more = []
    for j in range(1, d + 1):
        p = [f"({draw_sql(seed + 1, 100 * j + i, 'id')} * 5 < {1 << BITS})::BIGINT" for i in range(d)]
        total = " + ".join(f"a{i + 1} * {x}" for i, x in enumerate(p))
        more.append(f"CASE WHEN {' + '.join(p)} = 0 THEN (({draw_sql(seed + 2, j, 'id')} * 100) >> {BITS}) + 1 ELSE {total} END AS b{j}")
    return f"SELECT *, {', '.join(more)} FROM (SELECT id, {cols} FROM (SELECT unnest(range({n})) AS id))"


def permute_columns(cols: list[str], seed: int = 0) -> list[str]:
    out = list(cols)
    Random(seed).shuffle(out)
    return out


def zipf_edges(s: float, m: int) -> list[int]:
    """Draws from the edge of rank i on have a rank above i."""
    weights = [1 / rank**s for rank in range(1, m + 1)]
    total, upto, edges = sum(weights), 0.0, []
    for w in weights[:-1]:
        upto += w / total
        edges.append(int(upto * (1 << BITS)))
    return edges


def _rank(u: Column, edges: Column, m: int) -> Column:
    """How many edges are at most u, by halving steps over the sorted edges."""
    def halving(step: int):
        def go(x: Column) -> Column:
            ahead = x["at"] + step
            return F.struct(x["u"].alias("u"), F.when((ahead <= m - 1) & (F.element_at(edges, F.least(ahead, F.lit(m - 1))) <= x["u"]), ahead).otherwise(x["at"]).alias("at"))

        return go

    state = F.struct(u.alias("u"), F.lit(0).alias("at"))
    for i in reversed(range((m - 1).bit_length())):
        state = F.element_at(F.transform(F.array(state), halving(1 << i)), 1)
    return state["at"]


def zipf_table(spark: SparkSession, n: int, d: int, s: float, m: int = 2000, seed: int = 0) -> DataFrame:
    """Columns z1..zd with P(rank) in proportion to 1 / rank ** s over m ranks, the ranks labelled at random."""
    edges = F.array(*[F.lit(x).cast("bigint") for x in zipf_edges(s, m)])
    out = spark.range(n)
    for j in range(1, d + 1):
        out = out.withColumn(f"z{j}", F.shiftright(draw(seed + 7, j, _rank(draw(seed, j, F.col("id")), edges, m)), 9))
    return out


def zipf_sql(n: int, d: int, s: float, m: int = 2000, seed: int = 0) -> str:
    """The table of zipf_table, in SQL."""
    edges = ", ".join(map(str, zipf_edges(s, m)))
    cols = ", ".join(f"({draw_sql(seed + 7, j, f"len([e FOR e IN edges IF e <= {draw_sql(seed, j, 'id')}])")} >> 9) AS z{j}" for j in range(1, d + 1))
    return f"SELECT id, {cols} FROM (SELECT unnest(range({n})) AS id), (SELECT [{edges}] AS edges)"
