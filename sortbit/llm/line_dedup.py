"""Line deduplication by a suffix array over line ids, made by distributed prefix doubling.

Every line gets an id, and the corpus is the sequence of all documents' line ids; a suffix
ends with its text. Prefix doubling ranks the suffixes by their first 1, 2, 4, ... lines: the
distinct pairs of two halves' ranks are sorted across the cluster, and their places are the
next ranks. A suffix whose prefix no other shares is settled and leaves the rounds. Suffixes
of one rank are a longest-common-prefix interval of the suffix array: they agree in that many
lines at least. An interval of any length w between two rounds is ranked by the pair of its
first and its last 2**k lines, which overlap. Each interval carries its first position (by id,
then line number).

A line is deleted when it lies in a repeated run of consecutive lines, `min_chars` characters
long at least (each line counts its end), that also occurs, line for line, at an earlier
position. The array is ranked as deep as that asks for: a maximal repeated run of such length
is the union of the shortest blocks of that length that begin or end at its lines, so the
intervals of those blocks show it whole, however long it is. Blocks that overlap or touch are
merged into runs, text by text. As each line counts at least one character, no block has more
than `min_chars` lines, and the rounds end after log2(min_chars) of them.

Line ids are 128-bit hashes. All steps are DataFrame operations; character offsets are one
running sum for each text, so a text costs in proportion to its lines. A line that many
positions share is joined by broadcast, apart from the others (`hot_rows`).

A null text stays null, an empty text has one empty line. Lines end at \\n alone. Where all
lines of a text go, the text becomes empty. Rows that repeat an id and its text are one
document, and all get its result; different texts under one id are documents of their own, in
the order of their hashes. Rows without an id stay as they are. No rows: no rows.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window as W

from .base import Kept, keep

#: Shorter runs are left where they are: greetings, numbers and other lines of a word or two.
MIN_CHARS = 20
#: Positions from which one key is joined apart from the others.
HOT_ROWS = 1_000_000


def numbered_lines(docs: DataFrame) -> DataFrame:
    """(id, line, h1, h2, start, n, total): each line's number, hashes, offset and length with its end, and its text's length."""
    each = docs.where("id is not null and text is not null").select("id", (F.length("text") + 1).alias("total"), F.posexplode(F.split("text", "\n")).alias("line", "s"))
    each = each.select("id", "total", "line", F.xxhash64("s").alias("h1"), F.xxhash64(F.lit(7), "s").alias("h2"), (F.length("s") + 1).alias("n"))
    upto = F.sum("n").over(W.partitionBy("id").orderBy("line").rowsBetween(W.unboundedPreceding, 0))
    return each.withColumn("start", upto - F.col("n"))


def ranked(rows: DataFrame, by: list[str], hot_rows: int = HOT_ROWS) -> DataFrame:
    """rows whose `by` columns recur, with `rank`, their place in the order of those columns, and `first`, the least of their positions."""
    groups = rows.groupBy(*by).agg(F.min("position").alias("first"), F.count("*").alias("times")).where("times > 1")
    named = keep(groups.orderBy(*by).withColumn("rank", F.monotonically_increasing_id()))
    hot = named.where(F.col("times") >= hot_rows).drop("times")  # at most one in `hot_rows` of the rows
    if hot.isEmpty():
        return rows.join(named.drop("times"), by)
    often = rows.join(F.broadcast(hot), by)
    rest = rows.join(F.broadcast(hot.select(*by)), by, "left_anti").join(named.where(F.col("times") < hot_rows).drop("times"), by)
    return often.unionByName(rest)


def _shortest_blocks(lines: DataFrame, min_chars: int) -> DataFrame:
    """(id, line, w), distinct: blocks of w lines from `line` that reach min_chars and no longer would without their last, or first, line.

    lines: the repeated ones alone; a block with any other line repeats nowhere.
    """
    ahead = W.partitionBy("id").orderBy("start").rangeBetween(0, min_chars - 1)
    back = W.partitionBy("id").orderBy("end").rangeBetween(1 - min_chars, 0)
    seen = lines.select("id", "line", F.col("start").cast("long").alias("start"), (F.col("start") + F.col("n")).cast("long").alias("end"), "n")
    seen = seen.withColumn("w1", F.count("*").over(ahead)).withColumn("to", F.max("line").over(ahead)).withColumn("chars1", F.sum("n").over(ahead))
    seen = seen.withColumn("w2", F.count("*").over(back)).withColumn("from", F.min("line").over(back)).withColumn("chars2", F.sum("n").over(back))
    one = seen.where((F.col("to") - F.col("line") + 1 == F.col("w1")) & (F.col("chars1") >= min_chars)).select("id", "line", F.col("w1").alias("w"))
    two = seen.where((F.col("line") - F.col("from") + 1 == F.col("w2")) & (F.col("chars2") >= min_chars)).select("id", F.col("from").alias("line"), F.col("w2").alias("w"))
    return one.union(two).distinct()


def repeated_blocks(docs: DataFrame, min_chars: int = MIN_CHARS, hot_rows: int = HOT_ROWS) -> DataFrame:
    """(id, first_line, last_line): blocks that occur at an earlier position too. docs: id (whole numbers, none twice), text."""
    rows = Kept(numbered_lines(docs))
    most = rows.df.agg(F.max("line"), F.min("id"), F.max("id")).first()
    lines_bits = max(1, int(most[0] or 0) + 1).bit_length() + 1  # twice the longest text, so that no block reaches the next one
    low = int(most[1] or 0)
    fits = (int(most[2] or 0) - low).bit_length() + lines_bits <= 62
    kind = "bigint" if fits else "decimal(38,0)"
    position = (F.col("id").cast(kind) - F.lit(low).cast(kind)) * F.lit(1 << lines_bits).cast(kind) + F.col("line").cast(kind)

    lines = Kept(ranked(rows.df.withColumn("position", position.cast(kind)), ["h1", "h2"], hot_rows).drop("h1", "h2", "total"))
    rows.drop()
    blocks = keep(_shortest_blocks(lines.df, min_chars))
    level = Kept(lines.df.select("id", "line", "position", "rank", "first"))
    lines.drop()
    single = blocks.where("w = 1").join(level.df.where("first < position"), ["id", "line"])
    parts = [keep(single.select("id", F.col("line").alias("first_line"), F.col("line").alias("last_line")))]
    longest = blocks.agg(F.max("w")).first()[0] or 1
    length = 1
    while length < longest:
        # intervals of length + 1 .. 2 * length lines, by the ranks of their first and last `length` lines
        suffixes = level.df
        left = suffixes.select("id", "line", "position", F.col("rank").alias("left"))
        right = suffixes.select("id", (F.col("line") + length).alias("end"), F.col("rank").alias("right"))
        some = blocks.where((F.col("w") > length) & (F.col("w") <= 2 * length))
        pairs = Kept(some.join(left, ["id", "line"]).withColumn("end", F.col("line") + F.col("w")).join(right, ["id", "end"]).select("id", "line", "w", "position", "left", "right"))
        later = ranked(pairs.df, ["w", "left", "right"], hot_rows).where("first < position")
        parts.append(keep(later.select("id", F.col("line").alias("first_line"), (F.col("line") + F.col("w") - 1).cast("int").alias("last_line"))))
        pairs.drop()
        if 2 * length >= longest:
            break
        ahead = W.partitionBy("id").orderBy("line").rangeBetween(length, length)
        doubled = suffixes.select("id", "line", "position", F.col("rank").alias("left"), F.first("rank").over(ahead).alias("right")).where("right is not null")
        level = Kept(ranked(doubled, ["left", "right"], hot_rows).select("id", "line", "position", "rank", "first"))
        length *= 2
    out = parts[0]
    for part in parts[1:]:
        out = out.unionByName(part)
    return out


def kept_ranges(blocks: DataFrame) -> DataFrame:
    """(id, gone): for each text the runs to delete, as merged ranges [first, last] of its blocks, in order."""
    seen = W.partitionBy("id").orderBy("first_line", "last_line")
    before = F.max("last_line").over(seen.rowsBetween(W.unboundedPreceding, -1))
    new = F.when(F.col("first_line") <= before + 1, 0).otherwise(1)
    islands = blocks.distinct().withColumn("new", new).withColumn("island", F.sum("new").over(seen.rowsBetween(W.unboundedPreceding, 0)))
    merged = islands.groupBy("id", "island").agg(F.min("first_line").alias("first"), F.max("last_line").alias("last"))
    return merged.groupBy("id").agg(F.sort_array(F.collect_list(F.struct("first", "last"))).alias("gone"))


def without(lines: Column, gone: Column) -> Column:
    """lines without the ranges of `gone`: the slices between them, in one pass."""
    starts = F.concat(F.array(F.lit(0)), F.transform(gone, lambda g: g["last"] + 1))
    ends = F.concat(F.transform(gone, lambda g: g["first"]), F.array(F.size(lines)))
    return F.flatten(F.transform(F.arrays_zip(starts.alias("s"), ends.alias("e")), lambda r: F.slice(lines, r["s"] + 1, r["e"] - r["s"])))


def deduplicate_lines(docs: DataFrame, min_chars: int = MIN_CHARS, id_col: str = "doc_id", count_as: str | None = None, hot_rows: int = HOT_ROWS) -> DataFrame:
    """docs with later copies of repeated line runs deleted from `text`; all their columns.

    count_as: a further column with the number of deleted lines.
    """
    plain = docs.select(F.col(f"`{id_col}`").cast("long").alias("id"), "text")
    twice = not plain.where("id is not null").groupBy("id").count().where("count > 1").isEmpty()
    if twice:  # ids of our own, one for each id and text, in the same order
        at = plain.where("id is not null").select("id", F.xxhash64("text").alias("h"), "text").dropDuplicates(["id", "h"])
        unique = keep(at.orderBy("id", "h").withColumn("key", F.monotonically_increasing_id()))
        plain = unique.select(F.col("key").alias("id"), "text")
    found = keep(kept_ranges(repeated_blocks(plain, min_chars, hot_rows)))
    gone = found.select(F.col("id").alias("__id"), F.col("gone").alias("__gone"))
    on = docs[id_col].cast("long") == F.col("__id")
    if twice:
        gone = gone.join(unique.select(F.col("key").alias("__id"), F.col("id").alias("__of"), F.col("h").alias("__h")), "__id")
        on = (docs[id_col].cast("long") == F.col("__of")) & (F.xxhash64(docs["text"]) == F.col("__h"))
    # the ranges grow with the corpus, so the join is a merge at every size
    joined = docs.join(gone.hint("merge"), on, "left")
    text = F.when(F.col("__gone").isNull(), F.col("text")).otherwise(F.array_join(without(F.split("text", "\n"), F.col("__gone")), "\n"))
    out = [text.alias("text") if c == "text" else F.col(f"`{c}`") for c in docs.columns]
    if count_as:
        n = F.aggregate("__gone", F.lit(0), lambda a, g: (a + g["last"] - g["first"] + 1).cast("int"))
        out.append(F.coalesce(n, F.lit(0)).cast("long").alias(count_as))
    return joined.select(*out)
