"""The experiments' data: projections of the given tables, and the row orders they are compared under."""

from __future__ import annotations

import re
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .io import read_table
from .roworder import BlockSorted, GrayCode, Grouped, Lexicographic, Shuffled


@dataclass(frozen=True)
class Projection:
    """cols: (name, SQL expression), from the least cardinality to the largest; key: SQL expressions that name a row.

    joins: (dimension table, condition), inner.
    """

    table: str
    cols: tuple[tuple[str, str], ...]
    key: tuple[str, ...]
    joins: tuple[tuple[str, str], ...] = ()

    @property
    def names(self) -> list[str]:
        return [n for n, _ in self.cols]

    def load(self, spark: SparkSession, sf_dir: str) -> DataFrame:
        keys = [F.expr(k).alias(f"key_{i}") for i, k in enumerate(self.key)]
        df = read_table(spark, sf_dir, self.table)
        for table, on in self.joins:
            df = df.join(read_table(spark, sf_dir, table), F.expr(on))
        return df.select(*[F.expr(e).alias(n) for n, e in self.cols], *keys)

    def source_sql(self) -> str:
        return self.table + "".join(f" JOIN {t} ON {on}" for t, on in self.joins)

    def select_sql(self) -> str:
        """The projection in DuckDB's words, with the row keys as key_0, key_1, ..."""
        cols = ", ".join(f"{duck(e)} AS {n}" for n, e in self.cols)
        keys = ", ".join(f"{duck(e)} AS key_{i}" for i, e in enumerate(self.key))
        return f"SELECT {cols}, {keys} FROM {self.source_sql()}"

    def shuffle_sql(self) -> str:
        return md5_sql(42, [f"key_{i}" for i in range(len(self.key))])

    def grouped_sql(self) -> str:
        return md5_sql(42, [duck(whole(n)) for n in self.names]) + ", " + ", ".join(self.names)

    def order(self, name: str, k: int = 1):
        """shuffle, grouped, asc, desc, gray_asc, gray_desc, or blocks<B> (the shuffled rows, cut, each block in desc order)."""
        shuffled = Shuffled(tuple(F.col(f"key_{i}") for i in range(len(self.key))))
        columns = tuple(self.names if name.endswith("asc") else reversed(self.names))
        if name == "shuffle":
            return shuffled
        if name == "grouped":
            return Grouped(tuple(self.names), tuple(F.expr(whole(n)) for n in self.names))
        if name.startswith("gray"):
            return GrayCode(columns, k)
        if name.startswith("blocks"):
            return BlockSorted(shuffled, columns, int(name[6:]))
        return Lexicographic(columns)


def duck(expr: str) -> str:
    """A Spark expression of this module in DuckDB's words."""
    return re.sub(r"datediff\((\w+), (date '[^']+')\)", r"date_diff('day', \2, \1)", expr.replace("0.0D", "0.0"))


def md5_sql(seed: int, exprs: list[str]) -> str:
    return f"md5(concat_ws('|', '{seed}', {', '.join(f'cast({e} as varchar)' for e in exprs)}))"


#: Columns whose text differs between engines, and a whole number that stands for the value in hash keys.
WHOLE = {
    "l_discount": "cast(round(l_discount * 100) as bigint)",
    "l_tax": "cast(round(l_tax * 100) as bigint)",
    "l_quantity": "cast(l_quantity as bigint)",
    "value": "cast(round(value * 10000) as bigint)",
    "top_value": "cast(round(top_value * 10000) as bigint)",
    "l_shipdate": "datediff(l_shipdate, date '1990-01-01')",
    "o_orderdate": "datediff(o_orderdate, date '1990-01-01')",
}


def whole(name: str) -> str:
    return WHOLE.get(name, name)


def _same(*names: str) -> tuple[tuple[str, str], ...]:
    return tuple((n, n) for n in names)


_LINE_KEY = ("l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "cast(round(l_extendedprice * 100) as bigint)", "cast(l_quantity as int)")

#: `top_value` keeps the upper 11 % of the values; all others count as 0.
DOMINANT_FROM = 110.0

PROJECTIONS = {
    "p_gen": Projection("lineitem", _same("l_linenumber", "l_discount", "l_partkey"), _LINE_KEY),
    "p_near_unique": Projection("events", _same("event_type", "props", "value"), ("event_id",)),
    "p_dominant": Projection("events", (*_same("event_type", "props"), ("top_value", f"case when value < {DOMINANT_FROM} then 0.0D else value end")), ("event_id",)),
    "p_rare": Projection("lineitem", _same("l_linenumber", "l_shipdate", "l_orderkey"), _LINE_KEY),
    "p_frequent": Projection("lineitem", _same("l_returnflag", "l_suppkey", "l_shipdate"), _LINE_KEY),
    "p_docs": Projection("documents", _same("lang", "source", "n_chars"), ("doc_id",)),
    "p_ten": Projection("lineitem", _same("l_linestatus", "l_returnflag", "l_linenumber", "l_tax", "l_discount", "l_quantity", "l_suppkey", "l_partkey", "l_shipdate", "l_orderkey"), _LINE_KEY),
    "p_ten_real": Projection(
        "orders",
        _same("o_orderstatus", "o_orderpriority", "r_name", "c_mktsegment", "n_name", "o_orderdate", "o_custkey"),
        ("o_orderkey",),
        (("customer", "o_custkey = c_custkey"), ("nation", "c_nationkey = n_nationkey"), ("region", "n_regionkey = r_regionkey")),
    ),
}
