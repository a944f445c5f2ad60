"""What the corpus operators share: reading tables, shipping this package to
executors, cutting lineage in the shared folder, and bounded Arrow batches."""

from __future__ import annotations

import os
import uuid
from collections.abc import Iterator

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..io import shared_dir, ship

__all__ = ["Kept", "bounded_sample", "fold_is_held_out", "keep", "limit_threads", "read", "shared_dir", "ship", "text_chunks"]

#: Bytes of text that one vectorised step handles; its numpy arrays take about 40 times as much.
CHUNK_BYTES = 1 << 20


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


class Kept:
    """A table written to the shared folder: it survives lost executors and has no lineage."""

    def __init__(self, df: DataFrame):
        self.spark = df.sparkSession
        self.path = f"{shared_dir(self.spark)}/sortbit-{uuid.uuid4().hex}"
        df.write.parquet(self.path)
        self.df = self.spark.read.schema(df.schema).parquet(self.path)
        self._fs().deleteOnExit(self._hadoop_path())

    def _hadoop_path(self):
        return self.spark._jvm.org.apache.hadoop.fs.Path(self.path)

    def _fs(self):
        return self._hadoop_path().getFileSystem(self.spark._jsc.hadoopConfiguration())

    def drop(self) -> None:
        """Removes the files; for a table that nothing lazy still reads."""
        self._fs().delete(self._hadoop_path(), True)


def keep(df: DataFrame) -> DataFrame:
    """df, written to the shared folder and read again. The files stay until the session ends."""
    return Kept(df).df


def fold_is_held_out(doc_id: Column) -> Column:
    """The fold that no model may learn from: crc32 of the id's decimal text, mod 4, is 2."""
    return F.crc32(doc_id.cast("string").cast("binary")) % 4 == 2


def bounded_sample(df: DataFrame, id_col: str, bound: int, seed: int = 0) -> DataFrame:
    """About `bound` rows at most, picked by a hash of the id, so that a rerun picks the same."""
    rows = df.count()
    if rows <= bound:
        return df
    slots = 1 << 40
    return df.where(F.pmod(F.xxhash64(F.lit(seed), F.col(id_col)), F.lit(slots)) < int(slots * (bound / rows)))


def text_chunks(batches: Iterator[pa.RecordBatch], column: str = "text", limit: int = CHUNK_BYTES) -> Iterator[pa.RecordBatch]:
    """Cuts Arrow batches where their text passes `limit` bytes. One longer text stays whole, alone."""
    for batch in batches:
        if not batch.num_rows:
            continue
        ends = pc.cumulative_sum(pc.fill_null(pc.binary_length(batch.column(column)), 0).cast(pa.int64())).to_numpy()
        at, base = 0, 0
        while at < batch.num_rows:
            stop = max(at + 1, int(ends.searchsorted(base + limit, side="right")))
            yield batch.slice(at, stop - at)
            at, base = stop, int(ends[stop - 1])


def limit_threads() -> None:
    """One thread for each Python worker: Spark hands out the cores."""
    for name in ("OMP_NUM_THREADS", "RAYON_NUM_THREADS", "OPENBLAS_NUM_THREADS"):
        os.environ.setdefault(name, "1")
    os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
