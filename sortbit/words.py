"""Bits, words and segments of placed rows as relations, all in built-in operators.

BitRows (attr, bitmap_id, pos) -> Words (attr, bitmap_id, word_no, bits): non-zero words only
-> Sizes (attr, bitmap_id, ...): what each codec needs, without building payloads.
"""

from __future__ import annotations

from collections.abc import Mapping

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W

#: Fixed values of the marker format: longest clean run and longest literal run of one marker.
CLEAN_MAX, LITERAL_MAX = 65535, 32767
#: Fixed value of the flag format: longest run of one fill word.
FILL_MAX = (1 << 30) - 1


def to_bitrows(placed: DataFrame, dicts: Mapping[str, DataFrame], pos: str = "pos", keep: tuple[str, ...] = ()) -> DataFrame:
    """(attr, bitmap_id, pos): k rows for each fact and column. Large dictionaries join by merge, small ones as Spark decides."""
    out = None
    for col, codes in dicts.items():
        lookup = codes.select(F.col("value").alias("__value"), "bits")
        joined = placed.select(F.col(pos).alias("pos"), F.col(col).alias("__key"), *keep).join(lookup, F.col("__key").eqNullSafe(F.col("__value")))
        rows = joined.select(F.lit(col).alias("attr"), F.explode("bits").alias("bitmap_id"), "pos", *keep)
        out = rows if out is None else out.unionByName(rows)
    return out


def to_words(bitrows: DataFrame, word_bits: int = 32, by: tuple[str, ...] = ("attr", "bitmap_id")) -> DataFrame:
    """Non-zero words: bits are ORed map-side before the shuffle."""
    bit = F.expr(f"shiftleft(1L, cast(pos % {word_bits} as int))")
    return bitrows.groupBy(*by, F.floor(F.col("pos") / word_bits).cast("bigint").alias("word_no")).agg(F.bit_or(bit).alias("bits"))


#: Words of one bitmap that one task looks at together; only the edges of these stretches meet again.
CHUNK = 1 << 16


def _up(x: Column, most: int) -> Column:
    return F.floor((x + (most - 1)) / most).cast("bigint")


def _chunk() -> Column:
    return F.floor(F.col("word_no") / CHUNK).cast("bigint")


def runs_of_words(words: DataFrame, full: int, by: list[str]) -> DataFrame:
    """(by..., chunk, run, start, len, ones, gap, edge): runs of words of one kind (ones: 0 or 1) in each stretch.

    gap: zero words between the run and the one before it in its stretch. edge: the first and
    the last run of a stretch, which may go on in the next one.
    """
    w = W.partitionBy(*by, "chunk").orderBy("word_no")
    typed = words.withColumn("chunk", _chunk()).withColumn("ones", (F.col("bits") == full).cast("int"))
    before = F.struct("word_no", "ones")
    typed = typed.withColumn("before", F.lag(before).over(w))
    new = F.coalesce(((F.col("word_no") != F.col("before.word_no") + 1) | (F.col("ones") != F.col("before.ones"))).cast("int"), F.lit(1))
    gap = F.coalesce(F.col("word_no") - F.col("before.word_no") - 1, F.lit(0))
    numbered = typed.select(*by, "chunk", "word_no", "ones", gap.alias("gap"), F.sum(new).over(w).alias("run"))
    runs = numbered.groupBy(*by, "chunk", "run").agg(F.min("word_no").alias("start"), F.count("*").alias("len"), F.any_value("ones").alias("ones"), F.sum("gap").alias("gap"))
    last = F.max("run").over(W.partitionBy(*by, "chunk"))
    return runs.withColumn("edge", (F.col("run") == 1) | (F.col("run") == last))


def joined_edges(edges: DataFrame, by: list[str]) -> DataFrame:
    """Edge runs with those they go on in put together: (by..., start, len, ones, gap to the stretch before)."""
    w = W.partitionBy(*by).orderBy("start")
    end = F.col("start") + F.col("len")
    seen = edges.select(*by, "chunk", "start", "len", "ones", F.lag(F.struct(end.alias("end"), F.col("ones"), F.col("chunk"))).over(w).alias("p"))
    goes_on = (F.col("start") == F.col("p.end")) & (F.col("ones") == F.col("p.ones"))
    across = F.coalesce(F.col("chunk") != F.col("p.chunk"), F.lit(True))
    gap = F.when(across, F.col("start") - F.coalesce(F.col("p.end"), F.lit(0))).otherwise(F.lit(0))
    seen = seen.withColumn("gap", gap).withColumn("group", F.sum(F.when(F.coalesce(goes_on, F.lit(False)), 0).otherwise(1)).over(w))
    return seen.groupBy(*by, "group").agg(F.min("start").alias("start"), F.sum("len").alias("len"), F.any_value("ones").alias("ones"), F.sum("gap").alias("gap"))


def segments(words: DataFrame, n_words: int, full: int, by: list[str]) -> DataFrame:
    """(by..., literals, literal_marks, one_marks, one_fills, zero_marks, zero_fills, one_words, starts_literal) of each bitmap.

    marks count markers (runs cut at CLEAN_MAX or LITERAL_MAX words), fills the same by FILL_MAX.
    Runs are found in stretches of CHUNK words, so a bitmap is no single task however long it is;
    what passes from one stretch to the next is one or two rows of each.
    """
    runs = runs_of_words(words, full, by)
    whole = runs.where(~F.col("edge")).select(*by, "start", "len", "ones", "gap")
    # the gap before a run inside a stretch is known there, for edge runs too
    inside = runs.where("edge").select(*by, "start", F.lit(0).cast("bigint").alias("len"), F.lit(-1).alias("ones"), "gap")
    outer = joined_edges(runs.where("edge"), by).select(*by, "start", "len", "ones", "gap")
    every = whole.unionByName(inside).unionByName(outer)
    lit, one = F.col("ones") == 0, F.col("ones") == 1
    add = lambda held, x: F.sum(F.when(held, x).otherwise(F.lit(0)))
    out = every.groupBy(*by).agg(
        add(lit, F.col("len")).alias("literals"),
        add(lit, _up(F.col("len"), LITERAL_MAX) - 1).alias("literal_marks"),
        add(one, _up(F.col("len"), CLEAN_MAX)).alias("one_marks"),
        add(one, _up(F.col("len"), FILL_MAX)).alias("one_fills"),
        add(one, F.col("len")).alias("one_words"),
        F.sum(_up(F.col("gap"), CLEAN_MAX)).alias("zero_marks"),
        F.sum(_up(F.col("gap"), FILL_MAX)).alias("zero_fills"),
        F.max(F.when(lit & (F.col("start") == 0), 1).otherwise(0)).alias("starts_literal"),
        F.max(F.when(F.col("ones") >= 0, F.col("start") + F.col("len"))).alias("end"),
    )
    tail = F.lit(n_words) - F.col("end")
    return out.withColumn("zero_marks", F.col("zero_marks") + _up(tail, CLEAN_MAX)).withColumn("zero_fills", F.col("zero_fills") + _up(tail, FILL_MAX)).drop("end")


def bit_runs(words: DataFrame, n_rows: int, by: list[str], word_bits: int = 32) -> DataFrame:
    """(by..., one_runs, zero_runs, first_bit, last_bit) of each bitmap: runs of set bits, and of bits not set, among n_rows."""
    w = W.partitionBy(*by, "chunk").orderBy("word_no")
    top = F.expr(f"cast(shiftright(bits, {word_bits - 1}) & 1 as int)")
    low = F.expr("cast(bits & 1 as int)")
    seen = words.withColumn("chunk", _chunk()).withColumn("p", F.lag(F.struct("word_no", top.alias("top"))).over(w))
    starts = F.expr(f"bit_count(bits & ~(shiftleft(bits, 1) & {(1 << word_bits) - 1}L))")
    goes_on = F.when((F.col("p.word_no") == F.col("word_no") - 1) & (F.col("p.top") == 1) & (low == 1), 1).otherwise(0)
    last = (n_rows - 1) // word_bits
    at_end = F.expr(f"cast(shiftright(bits, {(n_rows - 1) % word_bits}) & 1 as int)") if n_rows else F.lit(0)
    per = seen.groupBy(*by, "chunk").agg(
        F.sum(starts - goes_on).cast("bigint").alias("runs"),
        F.min_by(F.struct("word_no", low.alias("bit")), "word_no").alias("first"),
        F.max_by(F.struct("word_no", top.alias("bit")), "word_no").alias("last"),
        F.max(F.when(F.col("word_no") == 0, low).otherwise(0)).alias("first_bit"),
        F.max(F.when(F.col("word_no") == last, at_end).otherwise(0)).alias("last_bit"),
    )
    p = F.lag("last").over(W.partitionBy(*by).orderBy("chunk"))
    joined = F.when((p["word_no"] == F.col("first.word_no") - 1) & (p["bit"] == 1) & (F.col("first.bit") == 1), 1).otherwise(0)
    per = per.withColumn("joined", joined)
    out = per.groupBy(*by).agg((F.sum("runs") - F.sum("joined")).cast("bigint").alias("one_runs"), F.max("first_bit").alias("first_bit"), F.max("last_bit").alias("last_bit"))
    return out.withColumn("zero_runs", (F.col("one_runs") + 1 - F.col("first_bit") - F.col("last_bit")).cast("bigint"))


def sizes_marker32(words: DataFrame, n_rows: int, by: tuple[str, ...] = ("attr", "bitmap_id")) -> DataFrame:
    """(by..., c_words, n_words): compressed and plain 32-bit words of each bitmap."""
    n_words = -(-n_rows // 32)
    s = segments(words, n_words, (1 << 32) - 1, list(by))
    total = F.col("literals") + F.col("literal_marks") + F.col("one_marks") + F.col("zero_marks") + F.col("starts_literal")
    return s.select(*by, total.cast("bigint").alias("c_words"), F.lit(n_words).cast("bigint").alias("n_words"))


def sizes_flag31(bitrows: DataFrame, n_rows: int, by: tuple[str, ...] = ("attr", "bitmap_id")) -> DataFrame:
    n_groups = -(-n_rows // 31)
    s = segments(to_words(bitrows, 31, by), n_groups, (1 << 31) - 1, list(by))
    total = F.col("literals") + F.col("one_fills") + F.col("zero_fills")
    return s.select(*by, total.cast("bigint").alias("c_words"), F.lit(-(-n_rows // 32)).cast("bigint").alias("n_words"))
