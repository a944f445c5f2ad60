"""A Python data source: spark.read.format("sortbit").option("attr", ...).load(path) reads the positions that a saved index holds for values.

Rows are (block_id, pos, ord) of one column with one bitmap a value. Filters on `ord` are
pushed down to the files, so only the bitmaps that they name are read and decoded; each
row-group range of the index's files is a partition of its own.
"""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, EqualTo, Filter, GreaterThanOrEqual, In, InputPartition, LessThanOrEqual

from . import bitops
from .io import ship


class _Files(InputPartition):
    def __init__(self, path: str):
        self.path = path


class BitmapReader(DataSourceReader):
    def __init__(self, path: str, attr: str):
        self.path, self.attr, self.held = path, attr, []

    def pushFilters(self, filters: list[Filter]):
        """Takes comparisons of `ord` with constants; Spark applies the others."""
        for f in filters:
            if getattr(f, "attribute", None) == ("ord",) and isinstance(f, EqualTo | In | GreaterThanOrEqual | LessThanOrEqual):
                self.held.append(("in", list(f.value)) if isinstance(f, In) else ({EqualTo: "==", GreaterThanOrEqual: ">=", LessThanOrEqual: "<="}[type(f)], f.value))
            else:
                yield f

    def partitions(self):
        import pyarrow.dataset as ds

        return [_Files(f) for f in ds.dataset(f"{self.path}/blocks", format="parquet").files]

    def read(self, partition):
        import pyarrow.dataset as ds

        wanted = ds.field("attr") == self.attr
        for sign, value in self.held:
            at = ds.field("bitmap_id")
            wanted &= at.isin(value) if sign == "in" else at == value if sign == "==" else at >= value if sign == ">=" else at <= value
        table = ds.dataset(partition.path, format="parquet").to_table(columns=["block_id", "bitmap_id", "n_rows", "payload"], filter=wanted)
        for block, b, n_rows, payload in zip(*(table.column(c).to_pylist() for c in ("block_id", "bitmap_id", "n_rows", "payload")), strict=True):
            for pos in bitops.bm_positions(bitops.load(payload, n_rows)).tolist():
                yield block, pos, b


class BitmapSource(DataSource):
    """Options: path (a saved index with the marker32 codec, in a folder that all executors see), attr."""

    @classmethod
    def name(cls) -> str:
        return "sortbit"

    def schema(self) -> str:
        return "block_id bigint, pos bigint, ord bigint"

    def reader(self, schema) -> BitmapReader:
        return BitmapReader(self.options["path"].removeprefix("file:"), self.options["attr"])


def register_source(spark: SparkSession) -> None:
    ship(spark)
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")  # a session setting
    spark.dataSource.register(BitmapSource)
