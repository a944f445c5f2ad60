"""An index that grows by appended blocks, its compaction, and what streams keep up to date beside it."""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W

from .index import BitmapIndex, IndexSpec, build_index, load_index
from .predicate import Predicate
from .roworder import Lexicographic


def append_blocks(stream: DataFrame, cols: list[str], path: str, checkpoint: str, spec: IndexSpec = IndexSpec()):
    """A streaming query that sorts each micro-batch on its own and writes it as an index of its own, dictionaries and spec included.

    Written under batch=<id> with overwrite, so a repeated batch replaces itself. Late rows go to
    the batch they come with: no bit of an earlier block moves.
    """

    def write(batch: DataFrame, batch_id: int) -> None:
        if not batch.isEmpty():
            build_index(batch, cols, Lexicographic(tuple(cols)), spec).save(f"{path}/batch={batch_id}", mode="overwrite")

    return stream.writeStream.foreachBatch(write).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


@dataclass
class AppendedIndex:
    """The indexes of all batches, asked one by one in one plan."""

    batches: list[BitmapIndex]

    def fetch(self, predicate: Predicate) -> DataFrame:
        return reduce(DataFrame.unionByName, [b.fetch(predicate) for b in self.batches])

    def count_by_batch(self, predicate: Predicate) -> DataFrame:
        """(batch, n)."""
        each = [b.count_by_block(predicate).agg(F.coalesce(F.sum("n"), F.lit(0)).alias("n")).select(F.lit(i).alias("batch"), "n") for i, b in enumerate(self.batches)]
        return reduce(DataFrame.unionByName, each)

    def count(self, predicate: Predicate) -> int:
        return self.count_by_batch(predicate).agg(F.sum("n")).first()[0] or 0


def _batches(spark: SparkSession, path: str) -> list[str]:
    """Folders of the batches whose manifest, which is written last, is there."""
    where = spark._jvm.org.apache.hadoop.fs.Path(f"{path}/batch=*/manifest/_SUCCESS")
    found = where.getFileSystem(spark._jsc.hadoopConfiguration()).globStatus(where)
    return sorted(str(f.getPath().getParent().getParent().toString()) for f in found)


def appended_index(spark: SparkSession, path: str) -> AppendedIndex:
    return AppendedIndex([load_index(spark, p) for p in _batches(spark, path)])


def appended_facts(spark: SparkSession, path: str) -> DataFrame:
    """Facts of all batches, in their places."""
    return spark.read.option("basePath", path).parquet(f"{path}/batch=*/facts")


def compact(spark: SparkSession, path: str, cols: list[str], spec: IndexSpec = IndexSpec()) -> BitmapIndex:
    """All batches sorted as one table and indexed anew."""
    facts = appended_facts(spark, path).drop("batch", "block_id", "pos")
    return build_index(facts, cols, Lexicographic(tuple(cols)), spec)


def streaming_histogram(stream: DataFrame, ts: str, col: str, window: str = "1 hour", late: str = "1 hour", slide: str | None = None, session_gap: str | None = None) -> DataFrame:
    """(window, value, freq) over event time; rows later than the watermark are left to the next block.

    Windows tumble, slide by `slide`, or are sessions that end after `session_gap` without a row of their value.
    """
    timed = stream.withColumn("__ts", F.col(ts).cast("timestamp")).withWatermark("__ts", late)
    over = F.session_window("__ts", session_gap).alias("window") if session_gap else F.window("__ts", window, slide)
    return timed.groupBy(over, F.col(col).alias("value")).agg(F.count("*").alias("freq"))


def without_repeats(stream: DataFrame, ts: str, keys: list[str], late: str = "1 hour") -> DataFrame:
    """Rows whose keys were not seen within the watermark."""
    return stream.withColumn("__ts", F.col(ts).cast("timestamp")).withWatermark("__ts", late).dropDuplicatesWithinWatermark(keys).drop("__ts")


def grow_dictionary(stream: DataFrame, col: str, path: str, checkpoint: str):
    """A streaming query that gives each new value of a column the next ordinal, in the order of its batch.

    A batch's values are one file set under batch=<id>, with overwrite, and look at those of earlier
    batches only, so a repeated batch repeats its ordinals. Compaction restores value order.
    """

    def write(batch: DataFrame, batch_id: int) -> None:
        spark, new = batch.sparkSession, batch.select(F.col(col).alias("value")).distinct()
        last = -1
        if batch_id:
            known = read_dictionary(spark, path).where(F.col("batch") < batch_id)
            new = new.join(known.select(F.col("value").alias("__known")), F.col("value").eqNullSafe(F.col("__known")), "left_anti")
            last = known.agg(F.max("ord")).first()[0]
            last = -1 if last is None else last
        # the values that a batch brings for the first time
        numbered = new.select("value", (F.row_number().over(W.orderBy(F.col("value").asc_nulls_first())) + last).cast("bigint").alias("ord"))
        numbered.write.mode("overwrite").parquet(f"{path}/batch={batch_id}")

    return stream.writeStream.foreachBatch(write).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def read_dictionary(spark: SparkSession, path: str) -> DataFrame:
    """(value, ord, batch)."""
    return spark.read.parquet(path)
