"""The rivals of the bitmap index for equality: a scan, a value-ordered index and a hash index."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .io import shared_dir, write_sorted


def scan(df: DataFrame, condition: str) -> DataFrame:
    return df.where(condition)


def value_index(df: DataFrame, col: str, row: list[str]) -> DataFrame:
    """(value, row keys) in files sorted by value: a lookup reads the row groups whose range holds it."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/values-{uuid.uuid4().hex}"
    write_sorted(df.select(F.col(col).alias("value"), *row), path, ["value"])
    return spark.read.parquet(path)


def hash_index(df: DataFrame, col: str, row: list[str], buckets: int = 64) -> DataFrame:
    """(value, row keys, bucket) in one folder for each bucket of the value's hash."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/hashed-{uuid.uuid4().hex}"
    bucket = F.pmod(F.xxhash64(F.col(col)), F.lit(buckets)).cast("int")
    df.select(F.col(col).alias("value"), *row, bucket.alias("bucket")).repartition("bucket").write.partitionBy("bucket").parquet(path)
    return spark.read.parquet(path)


def hash_lookup(index: DataFrame, value, buckets: int = 64) -> DataFrame:
    """Rows of one value: only its bucket's folder is read."""
    key = F.lit(value).cast(index.schema["value"].dataType)
    bucket = index.sparkSession.range(1).select(F.pmod(F.xxhash64(key), F.lit(buckets)).cast("int")).first()[0]
    return index.where((F.col("bucket") == bucket) & (F.col("value") == key)).drop("bucket")
