"""Histograms of attribute values, and what follows from them."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

WORD = 32


def histogram(df: DataFrame, cols: list[str]) -> DataFrame:
    """(attr, value as text, freq) for each column, by one scan: rows are stacked, then counted map-side first."""
    stacked = df.select(F.explode(F.array(*[F.struct(F.lit(c).alias("attr"), F.col(c).cast("string").alias("value")) for c in cols])).alias("x"))
    return stacked.groupBy("x.attr", "x.value").agg(F.count("*").alias("freq"))


def value_counts(df: DataFrame, col: str) -> DataFrame:
    """(value, freq) of one column in its own type."""
    return df.groupBy(F.col(col).alias("value")).agg(F.count("*").alias("freq"))


def column_profile(df: DataFrame, cols: list[str]) -> DataFrame:
    """(attr, ndv, n, max_freq, rows_in_frequent): cardinality, rows, top frequency, rows in values seen WORD times or more."""
    h = histogram(df, cols)
    return h.groupBy("attr").agg(
        F.count("*").alias("ndv"),
        F.sum("freq").alias("n"),
        F.max("freq").alias("max_freq"),
        F.sum(F.when(F.col("freq") >= WORD, F.col("freq")).otherwise(F.lit(0))).alias("rows_in_frequent"),
    )


def save_histograms(df: DataFrame, cols: list[str], path: str) -> None:
    """Each column's (value, freq), in a folder of its own, for later builds."""
    for c in cols:
        value_counts(df, c).write.parquet(f"{path}/{c}")


def load_histograms(spark: SparkSession, path: str, cols: list[str]) -> dict[str, DataFrame]:
    return {c: spark.read.parquet(f"{path}/{c}") for c in cols}
