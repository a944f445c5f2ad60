"""Compressed-bitmap functions for DataFrames and SQL: payloads of `marker32` as BINARY columns."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql.functions import pandas_udf, udtf

from . import bitops
from .io import ship
from .ranking import positions_of


def _binary(op):
    def run(a: pd.Series, b: pd.Series, n_rows: pd.Series) -> pd.Series:
        return pd.Series([None if x is None or y is None else bitops.store(op(bitops.load(x, n), bitops.load(y, n), n), n) for x, y, n in zip(a, b, n_rows, strict=True)])

    return pandas_udf(run, "binary")


def functions() -> dict:
    """Name to function: bm_and, bm_or, bm_xor, bm_andnot, bm_xnor (a, b, n_rows), bm_not, bm_count (a, n_rows)."""

    def complement(a: pd.Series, n_rows: pd.Series) -> pd.Series:
        return pd.Series([None if x is None else bitops.store(bitops.bm_not(bitops.load(x, n), n), n) for x, n in zip(a, n_rows, strict=True)])

    def count(a: pd.Series, n_rows: pd.Series) -> pd.Series:
        return pd.Series([None if x is None else bitops.bm_count(bitops.load(x, n)) for x, n in zip(a, n_rows, strict=True)])

    return {
        "bm_and": _binary(lambda a, b, n: bitops.bm_and(a, b)),
        "bm_or": _binary(lambda a, b, n: bitops.bm_or(a, b)),
        "bm_xor": _binary(lambda a, b, n: bitops.bm_xor(a, b)),
        "bm_andnot": _binary(lambda a, b, n: bitops.bm_andnot(a, b)),
        "bm_xnor": _binary(bitops.bm_xnor),
        "bm_not": pandas_udf(complement, "binary"),
        "bm_count": pandas_udf(count, "bigint"),
    }


def _aggregate(many):
    def run(payload: pd.Series, n_rows: pd.Series) -> bytes:
        n = int(n_rows.max())
        return bitops.store(many([bitops.load(x, n) for x in payload if x is not None] or [bitops.EMPTY]), n)

    return pandas_udf(run, "binary")


def aggregates() -> dict:
    """bm_or_agg, bm_and_agg (payload, n_rows): over the bitmaps of a group, all of one block."""
    return {"bm_or_agg": _aggregate(bitops.bm_or_many), "bm_and_agg": _aggregate(bitops.bm_and_many)}


class _CodeTable:
    def eval(self, n: int, size: int, k: int, allocation: str):
        for i, code in enumerate(positions_of(np.arange(n), size, k, allocation).tolist()):
            yield i, code


class _Positions:
    def eval(self, payload: bytes, n_rows: int):
        if payload is not None:
            for p in bitops.bm_positions(bitops.load(payload, n_rows)):
                yield (int(np.int64(p)),)


def register(spark: SparkSession) -> None:
    """For SQL: the functions and aggregates, and the table functions bm_positions(payload, n_rows) -> pos and code_table(n, bitmaps, k, allocation) -> ord, bits."""
    ship(spark)
    for name, f in (functions() | aggregates()).items():
        spark.udf.register(name, f)
    spark.udtf.register("code_table", udtf(_CodeTable, returnType="ord: bigint, bits: array<int>"))
    spark.udtf.register("bm_positions", udtf(_Positions, returnType="pos: bigint"))
