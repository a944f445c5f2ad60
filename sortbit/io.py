"""Sources and sinks: tables, delimited files, nested fields, sorted facts and tables written for reuse."""

from __future__ import annotations

import tempfile
import uuid
import zipfile
from pathlib import Path

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import StructType


def ship(spark: SparkSession) -> None:
    """Sends this package's source to the executors, once for each Spark context."""
    sc = spark.sparkContext
    if getattr(sc, "_sortbit_shipped", False):
        return
    root = Path(__file__).resolve().parent
    target = Path(tempfile.mkdtemp(prefix="sortbit-src-")) / "sortbit_src.zip"  # the driver serves it from there
    with zipfile.ZipFile(target, "w", zipfile.ZIP_DEFLATED) as z:
        for p in sorted(root.rglob("*.py")):
            z.write(p, f"{root.name}/{p.relative_to(root)}")
    sc.addPyFile(str(target))
    sc._sortbit_shipped = True


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_flat(spark: SparkSession, path: str, schema: StructType | str, sep: str = ",") -> DataFrame:
    """A delimited file without a header."""
    return spark.read.csv(path, schema=schema, sep=sep)


def flatten_pairs(df: DataFrame, items: Column, name: str) -> DataFrame:
    """One row for each element of a nested field, as facts."""
    return df.withColumn(name, F.explode(items))


def compact(spark: SparkSession, paths: str, out: str, records_per_file: int = 1 << 24) -> None:
    """Many small Parquet files as few large ones."""
    spark.read.parquet(paths).repartition(1 if records_per_file <= 0 else spark.sparkContext.defaultParallelism).write.option("maxRecordsPerFile", records_per_file).mode("errorifexists").parquet(out)


def write_sorted(df: DataFrame, path: str, cols: list[str]) -> None:
    """Range-partitioned, sorted files: their row-group statistics prune later scans."""
    df.repartitionByRange(*cols).sortWithinPartitions(*cols).write.mode("errorifexists").parquet(path)


def concat_blocks(blocks: list[DataFrame]) -> DataFrame:
    """Sorted blocks one after another; block_id numbers them."""
    out = blocks[0].withColumn("block_id", F.lit(0))
    for i, b in enumerate(blocks[1:], 1):
        out = out.unionByName(b.withColumn("block_id", F.lit(i)))
    return out


def shared_dir(spark: SparkSession) -> str:
    """The folder named by spark.checkpoint.dir; only where none is set, one of our own."""
    named = spark.sparkContext.getConf().get("spark.checkpoint.dir") or spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    held = spark.sparkContext._jsc.sc().getCheckpointDir()
    if held.isEmpty():
        spark.sparkContext.setCheckpointDir(tempfile.mkdtemp(prefix="sortbit-tables-"))
        held = spark.sparkContext._jsc.sc().getCheckpointDir()
    return held.get().rstrip("/")


def materialise(df: DataFrame) -> DataFrame:
    """df written once to the shared folder: its physical order and partition numbers are then frozen."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/table-{uuid.uuid4().hex}"
    df.write.parquet(path)
    hadoop = spark._jvm.org.apache.hadoop.fs.Path(path)
    hadoop.getFileSystem(spark._jsc.hadoopConfiguration()).deleteOnExit(hadoop)
    return spark.read.schema(df.schema).parquet(path)
