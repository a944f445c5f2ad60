"""Hierarchical codes: each level has bitmaps of its own for a value's place inside its parent.

Values of different parents share the positions of the level below, so a level needs as many
codes as the largest family has members. A value is the AND of the bitmaps of its path; a
level above it is read from the bitmaps of that level and those before it alone.
"""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .codes import assign_hierarchy
from .index import BROADCAST_VALUES, BitmapIndex, IndexSpec, build_index
from .io import materialise
from .predicate import And, Eq, Predicate
from .roworder import Lexicographic


@dataclass
class HierarchyIndex:
    """paths: (levels..., code_1, code_2, ...)."""

    levels: list[str]
    paths: DataFrame
    index: BitmapIndex

    @property
    def codes(self) -> list[str]:
        return [f"code_{i + 1}" for i in range(len(self.levels))]

    def bitmaps(self) -> dict[str, int]:
        """How many bitmaps each level has."""
        return {level: self.index.plans[c][2] for level, c in zip(self.levels, self.codes, strict=True)}

    def at(self, *values) -> Predicate:
        """The predicate of a path, or of its beginning."""
        depth = len(values)
        held = F.lit(True)
        for level, v in zip(self.levels, values, strict=False):
            held &= F.col(level).eqNullSafe(F.lit(v))
        found = self.paths.where(held).select(*self.codes[:depth]).distinct().first()
        parts = tuple(Eq(c, found[c] if found else -1) for c in self.codes[:depth])
        return And(parts) if depth > 1 else parts[0]

    def roll_up(self, depth: int, predicate: Predicate | None = None) -> DataFrame:
        """(levels up to depth..., n): facts of each path, from the bitmaps of those levels."""
        codes, levels = self.codes[:depth], self.levels[:depth]
        counted = self.index.group_count(codes[0], predicate).withColumnRenamed("value", codes[0]) if depth == 1 else self.index.group_counts(codes, predicate)
        return self.paths.select(*levels, *codes).distinct().join(counted, codes).select(*levels, "n")


def build_hierarchy(df: DataFrame, levels: list[str], ks: list[int] | None = None, spec: IndexSpec = IndexSpec()) -> HierarchyIndex:
    """ks: bitmaps for each code, by level."""
    paths = materialise(assign_hierarchy(df, levels))
    codes = [f"code_{i + 1}" for i in range(len(levels))]
    lookup = paths.select(*[F.col(level).alias(f"__l{i}") for i, level in enumerate(levels)], *codes)
    on = [F.col(level).eqNullSafe(F.col(f"__l{i}")) for i, level in enumerate(levels)]
    both = df.join(F.broadcast(lookup) if paths.count() <= BROADCAST_VALUES else lookup, on).drop(*[f"__l{i}" for i in range(len(levels))])
    spec = replace(spec, k=dict(zip(codes, ks or [1] * len(codes), strict=True)))
    return HierarchyIndex(levels, paths, build_index(both, codes, Lexicographic(tuple(codes)), spec))
