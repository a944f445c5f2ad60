"""Row orders: how facts are arranged before they are indexed. `apply` returns a sorted frame."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .codes import assign_codes, gray_direction, gray_key, numbered


def hash_key(seed: int, cols: list[Column]) -> Column:
    """A key that a rerun, and another engine, computes alike."""
    return F.md5(F.concat_ws("|", F.lit(str(seed)), *[c.cast("string") for c in cols]))


def _shifted(bits: Column, by: int) -> Column:
    return F.transform(bits, lambda p: p + by)


@dataclass(frozen=True)
class NoOrder:
    """As stored."""

    def apply(self, df: DataFrame) -> DataFrame:
        return df


@dataclass(frozen=True)
class Shuffled:
    """A random permutation that only depends on the seed and each row's key."""

    key: tuple[Column, ...]
    seed: int = 42

    def apply(self, df: DataFrame) -> DataFrame:
        return df.orderBy(hash_key(self.seed, list(self.key)))


@dataclass(frozen=True)
class Grouped:
    """Equal facts together, the groups in random order."""

    cols: tuple[str, ...]
    exprs: tuple[Column, ...] | None = None
    seed: int = 42

    def apply(self, df: DataFrame) -> DataFrame:
        key = hash_key(self.seed, list(self.exprs or map(F.col, self.cols)))
        return df.orderBy(key, *self.cols)


@dataclass(frozen=True)
class Lexicographic:
    cols: tuple[str, ...]

    def apply(self, df: DataFrame) -> DataFrame:
        return df.orderBy(*[F.col(c).asc_nulls_first() for c in self.cols])


@dataclass(frozen=True)
class GrayCode:
    """Rows as Gray codes of their bits over alphabetical codes.

    By default one rank for each value replaces the bits, with directions that flip by the
    weights before the column. generic: by the bits themselves, for any code.
    """

    cols: tuple[str, ...]
    k: int = 1
    generic: bool = False
    limit_k: bool = field(default=True)

    def apply(self, df: DataFrame) -> DataFrame:
        if self.k == 1 and not self.generic:  # one bitmap a value: the columns alternate, and no dictionary is needed
            return df.orderBy(*[F.col(c).desc_nulls_last() if up else F.col(c).asc_nulls_first() for c, up in zip(self.cols, gray_direction([1] * len(self.cols)), strict=True)])
        out, keys, ks, before = df, [], [], 0
        for i, c in enumerate(self.cols):
            codes = assign_codes(df, c, self.k, limit_k=self.limit_k)
            k, n = codes.select("k", "n_bitmaps").first() or (1, 1)
            ks.append(k)
            if self.generic or k > 1:
                ranked = codes.select(F.col("value").alias(f"__v{i}"), F.col("bits").alias(f"__b{i}"))
                out = out.join(ranked, out[c].eqNullSafe(ranked[f"__v{i}"])).drop(f"__v{i}")
                keys.append(_shifted(F.col(f"__b{i}"), before) if self.generic else F.transform(F.col(f"__b{i}"), lambda p, j: F.when(j % 2 == 0, -p).otherwise(p)))
            else:
                keys.append(c)
            before += n
        if self.generic:
            order = [gray_key(F.concat(*keys), before).asc()]
        else:
            order = []
            for key, up in zip(keys, gray_direction(ks), strict=True):
                if isinstance(key, str):
                    order.append(F.col(key).desc_nulls_last() if up else F.col(key).asc_nulls_first())
                else:
                    order.append(key.asc() if up else key.desc())
        return out.orderBy(*order).drop(*[f"__b{i}" for i in range(len(self.cols))])


@dataclass(frozen=True)
class BlockSorted:
    """Equal blocks of consecutive rows, each sorted on its own and left where it is: no merge, no ranges.

    `start` arranges the rows before they are cut. Each block goes to a partition of its own by
    its number. Adds block_id.
    """

    start: object
    cols: tuple[str, ...]
    blocks: int

    def apply(self, df: DataFrame) -> DataFrame:
        at = numbered(self.start.apply(df), "__pos")
        n = max(1, at.count())
        cut = at.withColumn("block_id", F.floor(F.col("__pos") * self.blocks / F.lit(n)).cast("int")).drop("__pos")
        return cut.repartitionById(self.blocks, "block_id").sortWithinPartitions(*[F.col(c).asc_nulls_first() for c in self.cols])


@dataclass(frozen=True)
class PartitionSorted:
    """Block-wise sorting of a table as it is stored: every input partition is a block and is sorted in place, without an exchange."""

    cols: tuple[str, ...]

    def apply(self, df: DataFrame) -> DataFrame:
        return df.sortWithinPartitions(*[F.col(c).asc_nulls_first() for c in self.cols])


def place_rows(df: DataFrame, order, as_: str = "pos") -> DataFrame:
    """Facts with their position (from 0) in a row order: one sort, then prefix sums over partitions."""
    return numbered(order.apply(df), as_)
