"""Cost measures of an index over placed facts, computed as relations; only `payload_sizes` builds payloads, one at a time."""

from __future__ import annotations

from collections.abc import Iterator
from concurrent.futures import ThreadPoolExecutor

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .codec import CODECS
from .codes import assign_codes
from .io import ship
from .roworder import place_rows
from .words import bit_runs, segments, sizes_flag31, sizes_marker32, to_bitrows, to_words


def dictionaries(df: DataFrame, cols: list[str], k: int | dict[str, int] = 1, allocation: str = "alpha") -> dict[str, DataFrame]:
    """k: bitmaps for each value, for all columns or by column."""
    of = lambda c: k.get(c, 1) if isinstance(k, dict) else k
    with ThreadPoolExecutor(8) as pool:
        return dict(zip(cols, pool.map(lambda c: assign_codes(df, c, of(c), allocation), cols), strict=True))


def placed_bits(df: DataFrame, order, cols: list[str], k: int | dict[str, int] = 1, allocation: str = "alpha") -> tuple[DataFrame, int]:
    """BitRows of the whole table as one block, and its number of rows."""
    placed = place_rows(df, order).select("pos", *cols)  # written already, with its row numbers' parts
    return to_bitrows(placed, dictionaries(df, cols, k, allocation)), placed.count()


def bitmap_sizes(df: DataFrame, order, cols: list[str], k: int | dict[str, int] = 1, allocation: str = "alpha", codec: str = "marker32") -> DataFrame:
    """(attr, bitmap_id, c_words, n_words)."""
    bits, n = placed_bits(df, order, cols, k, allocation)
    return sizes_flag31(bits, n) if codec == "flag31" else sizes_marker32(to_words(bits), n)


def _encoded(codec: str, n: int):
    """Words sorted by bitmap and number to each bitmap's size; a bitmap may go on over many batches, but not over partitions."""
    size = CODECS[codec].nonzero_size

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, numbers, values = None, [], []

        def closed() -> tuple[int, int, int]:
            return *held, -(-size(np.concatenate(numbers), np.concatenate(values), n) // 4)

        def batch(rows: list[tuple[int, int, int]]) -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(zip(*rows, strict=True), (pa.int32(), pa.int32(), pa.int64()), strict=True)], ["column", "bitmap_id", "n_words"])

        for b in batches:
            if not b.num_rows:
                continue
            column, bitmap, number, bits = (b.column(c).to_numpy() for c in ("column", "bitmap_id", "word_no", "bits"))
            bits = bits.astype(np.uint32)
            edges = np.flatnonzero((column[1:] != column[:-1]) | (bitmap[1:] != bitmap[:-1])) + 1
            out = []
            for x, y in zip([0, *edges.tolist()], [*edges.tolist(), len(bits)], strict=True):
                key = (int(column[x]), int(bitmap[x]))
                if key != held:
                    if held is not None:
                        out.append(closed())
                    held, numbers, values = key, [], []
                numbers.append(number[x:y])
                values.append(bits[x:y])
            if out:
                yield batch(out)
        if held is not None:
            yield batch([closed()])

    return run


def payload_sizes(df: DataFrame, order, cols: list[str], k: int | dict[str, int] = 1, allocation: str = "alpha", codec: str = "marker32") -> DataFrame:
    """(attr, bitmap_id, n_words) of the whole table as one block: what each payload takes.

    The words of one bitmap meet in one task, and the payload is made of the non-zero ones; its
    length alone leaves the task. Bitmaps are spread over all tasks, no task sees the table.
    """
    ship(df.sparkSession)
    bits, n = placed_bits(df, order, cols, k, allocation)
    names = F.array(*map(F.lit, cols))
    words = to_words(bits).select((F.array_position(names, F.col("attr")) - 1).cast("int").alias("column"), F.col("bitmap_id").cast("int").alias("bitmap_id"), "word_no", "bits")
    sizes = words.repartition("column", "bitmap_id").sortWithinPartitions("column", "bitmap_id", "word_no").mapInArrow(_encoded(codec, n), "column int, bitmap_id int, n_words long")
    return sizes.select(F.element_at(names, F.col("column") + 1).alias("attr"), "bitmap_id", "n_words")


def index_words(sizes: DataFrame) -> DataFrame:
    """(attr, n_bitmaps, c_words, plain_words) for each column and in total."""
    by = sizes.rollup("attr").agg(F.count("*").alias("n_bitmaps"), F.sum("c_words").alias("c_words"), F.sum("n_words").alias("plain_words"))
    return by.withColumn("attr", F.coalesce("attr", F.lit("total")))


def relative_gain(sizes: DataFrame, base: DataFrame) -> DataFrame:
    """(attr, gain): 1 - size / size under the base."""
    return index_words(sizes).join(index_words(base).select("attr", F.col("c_words").alias("base")), "attr").select("attr", (1 - F.col("c_words") / F.col("base")).alias("gain"))


def bitmap_factor(sizes: DataFrame) -> DataFrame:
    """(attr, bitmap_id, saved, plain_words): a bitmap's factor 1 - C / N is saved / plain_words."""
    return sizes.select("attr", F.col("bitmap_id").cast("bigint").alias("bitmap_id"), (F.col("n_words") - F.col("c_words")).alias("saved"), F.col("n_words").alias("plain_words"))


def word_stats(words: DataFrame) -> DataFrame:
    """(attr, true_bits, nonzero_words, dirty_words) for each column."""
    full = (1 << 32) - 1
    return words.groupBy("attr").agg(
        F.sum(F.bit_count("bits")).cast("bigint").alias("true_bits"),
        F.count("*").alias("nonzero_words"),
        F.sum(F.when(F.col("bits") == full, F.lit(0)).otherwise(F.lit(1))).cast("bigint").alias("dirty_words"),
    )


def run_stats(bits: DataFrame, n: int) -> DataFrame:
    """(attr, one_runs, zero_runs): runs of set bits and of bits not set, over all bitmaps of a column; each is a pair of the run-length codec."""
    per = bit_runs(to_words(bits), n, ["attr", "bitmap_id"])
    return per.groupBy("attr").agg(F.sum("one_runs").alias("one_runs"), F.sum("zero_runs").alias("zero_runs"))


def hamming_path(bits: DataFrame, n: int) -> DataFrame:
    """(attr, changes): bits that differ between neighbouring rows, summed.

    A run of set bits changes one bit where it begins and one where it ends, but at the table's ends.
    """
    per = bit_runs(to_words(bits), n, ["attr", "bitmap_id"])
    return per.groupBy("attr").agg(F.sum(2 * F.col("one_runs") - F.col("first_bit") - F.col("last_bit")).cast("bigint").alias("changes"))


def abstract_cost_bits(words: DataFrame, n: int) -> DataFrame:
    """(attr, bits): a word for each clean run and each dirty word."""
    s = segments(words, -(-n // 32), (1 << 32) - 1, ["attr", "bitmap_id"])
    return s.groupBy("attr").agg((32 * F.sum(F.col("literals") + F.col("one_marks") + F.col("zero_marks"))).cast("bigint").alias("bits"))


def density(words: DataFrame, n: int) -> DataFrame:
    """(attr, true_bits, all_bits): set bits, and bits of the column's bitmaps; their ratio is the density."""
    return words.groupBy("attr").agg(F.sum(F.bit_count("bits")).cast("bigint").alias("true_bits"), (F.countDistinct("bitmap_id") * n).cast("bigint").alias("all_bits"))


def expansion(sizes: DataFrame) -> DataFrame:
    """(attr, expansion): the largest ratio of compressed to plain words among a column's bitmaps."""
    return sizes.groupBy("attr").agg(F.max(F.col("c_words") / F.col("n_words")).alias("expansion"))


def marker_overhead(words: DataFrame, n: int) -> DataFrame:
    """(attr, clean_marks, clean_fills): words that hold clean runs in the marker format, and by fills of up to 2^30 words."""
    s = segments(words, -(-n // 32), (1 << 32) - 1, ["attr", "bitmap_id"])
    return s.groupBy("attr").agg(F.sum(F.col("one_marks") + F.col("zero_marks")).cast("bigint").alias("clean_marks"), F.sum(F.col("one_fills") + F.col("zero_fills")).cast("bigint").alias("clean_fills"))


def order_effect(one: DataFrame, other: DataFrame) -> DataFrame:
    """(attr, ratio) of two orders' words, such as ascending by descending."""
    return index_words(one).join(index_words(other).select("attr", F.col("c_words").alias("other")), "attr").select("attr", (F.col("c_words") / F.col("other")).alias("ratio"))


def sort_reach(sizes: DataFrame, unsorted: DataFrame, below: float = 0.95) -> DataFrame:
    """(attr, reached): whether sorting takes a column below so much of its unsorted size."""
    return order_effect(sizes, unsorted).where("attr <> 'total'").select("attr", (F.col("ratio") < below).alias("reached"))


def selectivity(counts: DataFrame, n: int) -> DataFrame:
    """counts with the share of the table that each query selects."""
    return counts.withColumn("share", F.col("n") / F.lit(n))


def index_mib(words: int) -> float:
    return words * 4 / (1 << 20)


def directory_bytes(n_bitmaps: int, n_blocks: int) -> int:
    return 4 * n_bitmaps * n_blocks


def gray_key_bytes(k: int, n_cols: int, n_bitmaps: int) -> tuple[int, int]:
    """Bytes of a row's sort key: by positions, and as a dense bit row."""
    return 4 * k * n_cols, -(-n_bitmaps // 8)


def external_sort_plan(n: int, memory: int, reserve: int = 0) -> dict[str, int]:
    """Runs, records read ahead from each run in the merge, passes, and the most that two passes sort."""
    runs = -(-n // memory)
    passes, left = 1, runs
    while left > 1:
        left = -(-left // max(2, memory - reserve))
        passes += 1
    return {"runs": runs, "ahead": max(0, (memory - reserve) // max(1, runs)), "passes": passes, "two_pass_capacity": memory * memory}
