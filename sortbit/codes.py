"""Codes: which bitmaps stand for a value.

A value's ordinal in value order is unranked to k of L positions by counting with
binomials, in closed form and in plain expressions, so dictionaries of any size are coded
in parallel. "alpha" order takes position tuples in ascending order; "gray" order takes
the first position descending, the second ascending, and so on, which is the Gray order
of the bit rows of weight k.
"""

from __future__ import annotations

from math import comb

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W

from .io import materialise
from .profile import value_counts

#: Up to so many values, at most so many bitmaps a value.
K_LIMITS = [(5, 1), (21, 2), (85, 3)]
#: Dictionaries up to this size get their ordinals by one window; larger ones by range partitions.
SMALL_DICTIONARY = 1_000_000


def bitmaps_needed(n_values: int, k: int) -> int:
    """The least L with C(L, k) >= n_values."""
    size = k
    while comb(size, k) < n_values:
        size += 1
    return size


def effective_k(n_values: int, k: int) -> int:
    for limit, most in K_LIMITS:
        if n_values <= limit:
            return min(k, most)
    return k


def unrank(ordinal: Column, size: int, k: int, allocation: str = "alpha") -> Column:
    """The array of k ascending positions for an ordinal from 0."""
    if allocation not in ("alpha", "gray"):
        raise ValueError(f"no such allocation: {allocation}")
    state = F.struct(ordinal.cast("bigint").alias("rest"), F.lit(0).alias("next"), F.array().cast("array<int>").alias("bits"))
    for i in range(k):
        choose = F.array(*[F.lit(comb(n, k - i)).cast("bigint") for n in range(size + 1)])
        state = _let(state, _next_position(choose, size, allocation == "alpha" or i % 2 == 1))
    return state["bits"]


def _next_position(choose: Column, size: int, ascending: bool):
    """The step that takes one more position: the greatest whose predecessors' codes do not pass the rest."""
    c = lambda n: F.element_at(choose, (n + 1).cast("int"))

    def before(s: Column, q: Column) -> Column:
        free = F.lit(size) - s["next"]
        return c(free) - c(free - q) if ascending else c(free - q - 1)

    def step(s: Column) -> Column:
        # the codes before a gap only grow (ascending) or shrink with it, so halving finds the number of gaps that pass
        passes = (lambda q: before(s, q) <= s["rest"]) if ascending else (lambda q: before(s, q) > s["rest"])
        halves = F.array(*[F.lit(1 << i) for i in reversed(range(size.bit_length()))])
        q = F.aggregate(halves, F.lit(0), lambda found, half: F.when(found + half <= F.lit(size) - s["next"], F.when(passes(found + half - 1), found + half).otherwise(found)).otherwise(found))
        q = q - 1 if ascending else q
        return _let(F.struct(q.alias("q"), s["rest"].alias("rest"), s["next"].alias("next"), s["bits"].alias("bits")), taken)

    def taken(x: Column) -> Column:
        return F.struct((x["rest"] - before(x, x["q"])).alias("rest"), (x["next"] + x["q"] + 1).alias("next"), F.concat(x["bits"], F.array((x["next"] + x["q"]).cast("int"))).alias("bits"))

    return step


def _let(value: Column, f) -> Column:
    return F.element_at(F.transform(F.array(value), f), 1)


def ordinals(values: DataFrame, order: Column, as_: str = "ord", n: int | None = None) -> DataFrame:
    """values with dense ordinals from 0 in the given order; n: their number, where it is known.

    Beyond SMALL_DICTIONARY rows: range partitions, counted, with prefix sums over the partitions.
    """
    n = values.limit(SMALL_DICTIONARY + 1).count() if n is None else n
    if n <= SMALL_DICTIONARY:
        return values.withColumn(as_, (F.row_number().over(W.orderBy(order)) - 1).cast("bigint"))
    return numbered(values.orderBy(order), as_)


def numbered(ordered: DataFrame, as_: str) -> DataFrame:
    """Rows numbered from 0 in the order of a sorted frame: local numbers plus the rows of earlier partitions."""
    tagged = materialise(ordered.withColumn("__at", F.monotonically_increasing_id()))
    part = F.shiftright("__at", 33)
    counts = tagged.groupBy(part.alias("__part")).agg(F.count("*").alias("__n"))
    before = F.coalesce(F.sum("__n").over(W.orderBy("__part").rowsBetween(W.unboundedPreceding, -1)), F.lit(0))
    offsets = counts.select("__part", before.alias("__before"))  # one row for each partition
    local = F.col("__at").bitwiseAND(F.lit((1 << 33) - 1))
    return tagged.withColumn("__part", part).join(F.broadcast(offsets), "__part").withColumn(as_, F.col("__before") + local).drop("__at", "__part", "__before")


def plan_codes(n_values: int, k: int, limit_k: bool = True) -> tuple[int, int]:
    """(k, bitmaps) of a column of so many values."""
    k = effective_k(n_values, k) if limit_k else k
    return k, bitmaps_needed(max(n_values, 1), k)


def assign_codes(df: DataFrame, col: str, k: int = 1, allocation: str = "alpha", limit_k: bool = True, value_order: str = "native", counts: DataFrame | None = None) -> DataFrame:
    """Dict: (attr, value, freq, ord, k, n_bitmaps, bits). Null comes first; value_order "text" sorts by the text form.

    counts: the column's histogram (value, freq), where it is already written.
    """
    counts = materialise(value_counts(df, col)) if counts is None else counts
    n = counts.count()
    k, size = plan_codes(n, k, limit_k)
    key = F.col("value").cast("string") if value_order == "text" else F.col("value")
    coded = ordinals(counts, key.asc_nulls_first(), n=n)
    bits = F.array(F.col("ord").cast("int")) if k == 1 else unrank(F.col("ord"), size, k, allocation)
    return coded.select(F.lit(col).alias("attr"), "value", "freq", "ord", F.lit(k).alias("k"), F.lit(size).alias("n_bitmaps"), bits.alias("bits"))


def gray_direction(ks: list[int]) -> list[bool]:
    """For each column: ascending in its codes' Gray rank? It flips where the weights before it add to an odd number."""
    return [sum(ks[:i]) % 2 == 0 for i in range(len(ks))]


def gray_key(bits: Column, n_bitmaps: int) -> Column:
    """An array that sorts like the bit row does as a Gray code: signs alternate, a sentinel closes it."""
    signed = F.transform(bits, lambda p, i: F.when(i % 2 == 0, -p).otherwise(p))
    end = F.when(F.size(bits) % 2 == 0, F.lit(-n_bitmaps)).otherwise(F.lit(n_bitmaps))
    return F.concat(signed, F.array(end))


def assign_hierarchy(df: DataFrame, levels: list[str]) -> DataFrame:
    """One row for each path of level values, with a code for each level inside its parent: (levels..., code_1, code_2, ...)."""
    out = df.select(*levels).distinct()
    for i, level in enumerate(levels):
        w = W.partitionBy(*levels[:i]).orderBy(level) if i else W.orderBy(level)
        out = out.withColumn(f"code_{i + 1}", (F.dense_rank().over(w) - 1).cast("bigint"))
    return out


def bin_values(df: DataFrame, col: str, low: float, width: float, as_: str) -> DataFrame:
    """Equal-width bins: the bin of low + i * width and up to the next is i."""
    return df.withColumn(as_, F.floor((F.col(col) - low) / width).cast("bigint"))


def bin_by_edges(df: DataFrame, col: str, edges: list, as_: str) -> DataFrame:
    """Bins between sorted edges: as many edges as are at most the value. A null has no bin."""
    at = sum((F.when(F.col(col) >= F.lit(e), F.lit(1)).otherwise(F.lit(0)) for e in edges), F.lit(0))
    return df.withColumn(as_, F.when(F.col(col).isNotNull(), at).cast("bigint"))


def quantile_edges(df: DataFrame, col: str, bins: int, accuracy: int = 10_000) -> list:
    """Edges that cut a column into bins of about equal numbers of rows."""
    return df.select(F.percentile_approx(col, [i / bins for i in range(1, bins)], accuracy)).first()[0] or []


def bins_of_range(edges: list, low, high) -> tuple[int, int]:
    """The first and the last bin that a range meets; facts of these two are checked again."""
    return sum(e <= low for e in edges), sum(e <= high for e in edges)
