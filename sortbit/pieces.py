"""Compressed sizes of many codes over placed facts, without their words as rows.

A task takes the facts it holds as pieces of consecutive positions, packs the words of every
bitmap of a piece and keeps a record for each bitmap: its first and its last run of words, and what
all between them takes. Only these records meet again, so a bitmap costs one for each piece that
it has bits in, not one for each word. A word that two pieces share is put together then. Records
travel as bytes, one row for those of a piece and a group of bitmaps.
"""

from __future__ import annotations

from collections.abc import Iterator
from concurrent.futures import ThreadPoolExecutor

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import LongType, StructType
from pyspark.sql.window import Window as W

from .codes import numbered, ordinals
from .io import materialise, ship
from .profile import value_counts
from .ranking import positions_of
from .words import CLEAN_MAX, LITERAL_MAX

#: Facts of a piece: with the spare word below, a position in it takes 18 bits.
PIECE = (1 << 18) - 64
#: Columns' ordinals share a number of up to so many bits.
PACKED_BITS = 62
#: Dictionaries of up to about so many values are broadcast to the facts; values of larger ones are ranked by a sort of the facts.
BROADCAST = 1 << 18
#: Records that a group of bitmaps has at most, where no partition is smaller than a piece, and its bitmaps at most.
GROUP, GROUP_BITMAPS = 1 << 18, 1 << 12
#: Bits of a bitmap's number in `key`, and of a group's in `group`.
_BITMAP = 40
_FULL = (1 << 32) - 1
#: 32-bit numbers of a record: bitmap from its group's first one, words from the piece's first one.
_FIELDS = 7


# ---------------------------------------------------------------- ordinals, packed in the order of a sort


def with_ordinals(df: DataFrame, cols: list[str], keep: list[str], most: int = BROADCAST) -> tuple[DataFrame, dict[str, int], list[str]]:
    """Columns to keep and each column's ordinal ord_<col> (null first), the numbers of values, and the columns that `pos`, if any, numbers the facts by."""
    about = df.agg(*[F.approx_count_distinct(c).alias(c) for c in cols]).first()
    few = [c for c in cols if about[c] <= most]

    def lookup(c: str) -> tuple[DataFrame, int]:
        table = materialise(ordinals(value_counts(df, c), F.col("value").asc_nulls_first(), n=about[c]).select(F.col("value").alias(f"__{c}"), F.col("ord").cast("int").alias(f"ord_{c}")))
        return table, table.count()

    with ThreadPoolExecutor(max(1, len(few))) as pool:
        tables = dict(zip(few, pool.map(lookup, few), strict=True))
    sizes, order = {c: n for c, (_, n) in tables.items()}, []
    for c, (table, _) in tables.items():
        df = df.join(F.broadcast(table), F.col(c).eqNullSafe(F.col(f"__{c}"))).drop(f"__{c}")
    for c in (c for c in cols if c not in few):
        known = [o for o in reversed(cols) if o in sizes]
        groups, order = packing(known, sizes), [c, *known]
        rest = list(dict.fromkeys([*keep, *[x for x in cols if x not in sizes and x != c]]))
        df, size = ranked(df.select(*dict.fromkeys([c, *rest]), *packed(groups, sizes)), c, [f"packed_{i}" for i in range(len(groups))])
        df = df.select(*rest, "pos", f"ord_{c}", *unpacked(groups, sizes))
        sizes[c] = size
    return df, {c: sizes[c] for c in cols}, order


def ranked(df: DataFrame, col: str, then: list[str]) -> tuple[DataFrame, int]:
    """df, written once in the order of a column (null first) and of others, with its rows' numbers `pos` and ord_<col>; the number of values.

    Ranks are counted inside the sort's partitions, also where one value fills several of them.
    """
    ship(df.sparkSession)
    ordered = df.select(col, *[c for c in df.columns if c != col]).orderBy(F.col(col).asc_nulls_first(), *then)
    local = ordered.mapInArrow(_ranks, StructType([*ordered.schema.fields]).add("__rank", LongType()))
    tagged = materialise(local.withColumn("__at", F.monotonically_increasing_id()))
    part, by = F.shiftright("__at", 33), W.orderBy("__part")
    parts = tagged.groupBy(part.alias("__part")).agg(F.count("*").alias("n"), (F.max("__rank") + 1).alias("values"), F.min_by(col, "__at").alias("first"), F.max_by(col, "__at").alias("last"))
    goes_on = F.lag("n").over(by).isNotNull() & F.lag("last").over(by).eqNullSafe(F.col("first"))  # a value that the partition before ends with
    parts = parts.withColumn("new", F.col("values") - goes_on.cast("int"))
    upto = by.rowsBetween(W.unboundedPreceding, 0)
    offsets = materialise(parts.select("__part", "new", (F.sum("n").over(upto) - F.col("n")).alias("__rows"), (F.sum("new").over(upto) - F.col("values")).alias("__ranks")))  # one row for each partition
    size = offsets.agg(F.sum("new")).first()[0] or 0
    row = F.col("__at").bitwiseAND(F.lit((1 << 33) - 1))
    joined = tagged.withColumn("__part", part).join(F.broadcast(offsets.drop("new")), "__part")
    return joined.select(*df.columns, (F.col("__rows") + row).alias("pos"), (F.col("__ranks") + F.col("__rank")).cast("int").alias(f"ord_{col}")), size


def _ranks(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows sorted by their first column, with the dense rank of its value from 0."""
    rank, last = 0, None
    for b in batches:
        if not b.num_rows:
            continue
        value = b.column(0)
        both = pa.concat_arrays([value[:1] if last is None else last, value])
        old, new = both[:-1], both[1:]
        differ = pc.fill_null(pc.not_equal(old, new), pc.xor(pc.is_null(old), pc.is_null(new)))
        if pa.types.is_floating(value.type):
            differ = pc.and_not(differ, pc.fill_null(pc.and_(pc.is_nan(old), pc.is_nan(new)), False))
        ranks = rank + np.cumsum(differ.to_numpy(zero_copy_only=False), dtype=np.int64)
        rank, last = int(ranks[-1]), value[-1:]
        yield pa.RecordBatch.from_arrays([*b.columns, pa.array(ranks)], [*b.schema.names, "__rank"])


def packing(cols: list[str], sizes: dict[str, int], most: int = 1 << PACKED_BITS) -> list[list[str]]:
    """The columns in groups whose numbers of values have a product of at most `most`; each group is one number."""
    groups, held = [], most + 1
    for c in cols:
        if held * max(sizes[c], 1) > most:
            groups.append([])
            held = 1
        groups[-1].append(c)
        held *= max(sizes[c], 1)
    return groups


def packed(groups: list[list[str]], sizes: dict[str, int]) -> list[Column]:
    """Numbers that sort like the ordinals, columns in the order of the groups."""
    out = []
    for i, group in enumerate(groups):
        number = F.lit(0).cast("bigint")
        for c in group:
            number = number * max(sizes[c], 1) + F.col(f"ord_{c}")
        out.append(number.alias(f"packed_{i}"))
    return out


def unpacked(groups: list[list[str]], sizes: dict[str, int]) -> list[Column]:
    out = []
    for i, group in enumerate(groups):
        rest = f"packed_{i}"
        for c in reversed(group):
            out.append(F.expr(f"cast({rest} % {max(sizes[c], 1)}L as int)").alias(f"ord_{c}"))
            rest = f"({rest} div {max(sizes[c], 1)}L)"
    return out


def place_sorted(facts: DataFrame, cols: list[str], sizes: dict[str, int]) -> DataFrame:
    """(pos, ord_<col>...) in the lexicographic order of the columns, by a sort of their packed ordinals."""
    groups = packing(cols, sizes)
    slim = facts.select(*packed(groups, sizes))
    return numbered(slim.orderBy(*slim.columns), "pos").select("pos", *unpacked(groups, sizes))


def place_hashed(facts: DataFrame, key: Column, cols: list[str], sizes: dict[str, int]) -> DataFrame:
    """The same in the order of a hash in hexadecimal digits, which sorts as its bytes do."""
    groups = packing(cols, sizes)
    slim = facts.select(F.unhex(key).alias("hash"), *packed(groups, sizes))
    return numbered(slim.orderBy("hash").drop("hash"), "pos").select("pos", *unpacked(groups, sizes))


# ---------------------------------------------------------------- pieces


def _cost(length: np.ndarray, ones: np.ndarray) -> np.ndarray:
    """Words of a run: markers for each CLEAN_MAX words of ones; else the words, with a marker more from every LITERAL_MAX."""
    return np.where(ones, -(-length // CLEAN_MAX), length - (-length // LITERAL_MAX) - 1)


def _shared(keys: np.ndarray, at: np.ndarray, count: np.ndarray) -> np.ndarray:
    """The bits of words, each of so many keys from its place on."""
    before = np.cumsum(count) - count
    every = np.repeat(at - before, count) + np.arange(count.sum())
    return np.add.reduceat(np.int64(1) << (keys[every] & 31).astype(np.int64), before)


def summary(start: int, positions: np.ndarray, size: int) -> list[np.ndarray]:
    """(bitmap, start, first, last_start, last, between, bits) of a piece whose first fact is at `start`.

    positions: for each fact its bitmaps, of `size`. Lengths of runs of ones are negative; last: 0, where the first run is
    the last. bits: 0, but of words that the piece does not hold whole.
    """
    n, k = positions.shape
    low = start & 31
    shift = (low + n + 32).bit_length()  # leaves a word free, so no run goes on from one bitmap to the next
    kind = np.uint32 if size.bit_length() + shift <= 32 else np.uint64
    keys = np.arange(low, low + n, dtype=kind)[:, None] | (positions.astype(kind) << kind(shift))
    keys = keys.reshape(-1)
    keys.sort()
    word = keys >> kind(5)
    at = np.flatnonzero(np.concatenate([[True], word[1:] != word[:-1]]))
    count = np.diff(at, append=len(word))
    word = word[at].astype(np.int64)
    shift -= 5
    within = (1 << shift) - 1
    parted = np.zeros(len(word), bool)
    if low:
        parted |= (word & within) == 0
    if (low + n) & 31:
        parted |= (word & within) == (low + n - 1) >> 5
    out = []
    if parted.any():
        w = word[parted]
        none = np.zeros(len(w), np.int64)
        out.append([w >> shift, (start >> 5) + (w & within), none, none, none, none, _shared(keys, at[parted], count[parted])])
        word, count = word[~parted], count[~parted]
    if len(word):
        ones = count == 32
        at = np.flatnonzero(np.concatenate([[True], (word[1:] != word[:-1] + 1) | (ones[1:] != ones[:-1])]))
        length, ones, word = np.diff(at, append=len(word)), ones[at], word[at]
        bitmap = word >> shift
        new = np.concatenate([[True], bitmap[1:] != bitmap[:-1]])
        cost = _cost(length, ones)
        gap = np.zeros(len(word), np.int64)
        gap[1:] = np.where(new[1:], 0, word[1:] - word[:-1] - length[:-1])
        x = np.flatnonzero(new)
        y = np.append(x[1:], len(word)) - 1
        signed = np.where(ones, -length, length)
        between = np.add.reduceat(cost + -(-gap // CLEAN_MAX), x) - cost[x] - np.where(x == y, 0, cost[y])
        out.append([bitmap[x], (start >> 5) + (word[x] & within), signed[x], (start >> 5) + (word[y] & within), np.where(x == y, 0, signed[y]), between, np.zeros(len(x), np.int64)])
    return [np.concatenate(c) for c in zip(*out, strict=True)]


def grouped(start: int, rows: list[np.ndarray], size: int) -> tuple[np.ndarray, pa.Array]:
    """A piece's `summary` as (group of `size` bitmaps, its records in bytes)."""
    bitmap, at, first, last_start, last, between, bits = rows
    order = np.argsort(bitmap, kind="stable")
    group = bitmap[order] // size
    base = start >> 5
    fields = (bitmap % size, at - base, first, np.where(last == 0, 0, last_start - base), last, between, bits)
    records = np.empty((len(order), _FIELDS), np.uint32)
    for i, x in enumerate(fields):
        records[:, i] = x[order] & _FULL
    cut = np.flatnonzero(np.concatenate([[True], group[1:] != group[:-1]]))
    ends = (np.append(cut, len(order)) * (4 * _FIELDS)).astype(np.int32)
    return group[cut], pa.Array.from_buffers(pa.binary(), len(cut), [None, pa.py_buffer(ends), pa.py_buffer(records)])


def _pieces(codes: list[tuple[int, int, int, int, int]], columns: int, most: int, group: int):
    """Batches (pos, ordinals...) to rows (group, start, records). codes: (number, column, its number of values, k, bitmaps)."""
    tables = {}

    def of(ords: np.ndarray, values: int, k: int, size: int) -> np.ndarray:
        if k == 1 or values > most:
            return positions_of(ords, size, k)
        if (values, k) not in tables:
            tables[values, k] = positions_of(np.arange(values), size, k)
        return tables[values, k][ords]

    def close(start: int, parts: list[list[np.ndarray]]) -> Iterator[pa.RecordBatch]:
        ords = [np.concatenate([p[i] for p in parts]) for i in range(columns)]
        for number, column, values, k, size in codes:
            groups, records = grouped(start, summary(start, of(ords[column], values, k, size), size), group)
            yield pa.RecordBatch.from_arrays([pa.array(groups + (number << _BITMAP)), pa.array(np.full(len(groups), start >> 5)), records], ["group", "start", "records"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        start, n, parts = 0, 0, []
        for b in batches:
            pos, *ords = (b.column(i).to_numpy() for i in range(columns + 1))
            x = 0
            for y in [*(np.flatnonzero(np.diff(pos) != 1) + 1).tolist(), len(pos)]:
                while x < y:
                    if n and (n == most or pos[x] != start + n):
                        yield from close(start, parts)
                        n, parts = 0, []
                    start = start if n else int(pos[x])
                    z = min(y, x + most - n)
                    parts.append([o[x:z] for o in ords])
                    n, x = n + z - x, z
        if n:
            yield from close(start, parts)

    return run


# ---------------------------------------------------------------- bitmaps from their pieces


def merged(rows: list[np.ndarray], n_words: int) -> tuple[np.ndarray, np.ndarray]:
    """(key, start, first, last_start, last, between, bits) of whole bitmaps, sorted by key and start, to (key, compressed words)."""
    key, start, first, last_start, last, between, bits = rows
    at = np.flatnonzero(np.concatenate([[True], (key[1:] != key[:-1]) | (start[1:] != start[:-1])]))
    bits = np.bitwise_or.reduceat(bits, at)  # a word's parts have one start
    key, start, last_start, last, between = (x[at] for x in (key, start, last_start, last, between))
    first = np.where(bits == 0, first[at], np.where(bits == _FULL, -1, 1))

    held = np.column_stack([np.ones(len(key), bool), last != 0]).reshape(-1)
    row = np.repeat(np.arange(len(key)), 2)[held]
    start = np.column_stack([start, last_start]).reshape(-1)[held]
    length = np.column_stack([first, last]).reshape(-1)[held]
    ones, length, of = length < 0, np.abs(length), key[row]
    end = start + length
    same = np.concatenate([[False], of[1:] == of[:-1]])
    before = np.where(same, np.concatenate([[0], end[:-1]]), 0)
    inside = np.concatenate([[False], row[1:] == row[:-1]])  # the gap between a row's runs is counted in it
    gap = np.where(inside, 0, start - before)
    goes_on = same & (start == before) & np.concatenate([[False], ones[1:] == ones[:-1]])
    runs = np.flatnonzero(~goes_on)
    cost = np.zeros(len(of), np.int64)
    cost[runs] = _cost(np.add.reduceat(length, runs), ones[runs])
    cost += -(-gap // CLEAN_MAX)
    x = np.flatnonzero(~same)
    y = np.append(x[1:], len(of)) - 1
    total = np.add.reduceat(cost, x) + -(-(n_words - end[y]) // CLEAN_MAX) + ((start[x] == 0) & ~ones[x])
    return of[x], total + np.add.reduceat(between, np.flatnonzero(np.concatenate([[True], key[1:] != key[:-1]])))


def opened(group: np.ndarray, base: np.ndarray, records: pa.Array, size: int) -> list[np.ndarray]:
    """What `merged` takes, of rows with whole groups."""
    each = pc.binary_length(records).to_numpy() // (4 * _FIELDS)
    table = np.frombuffer(b"".join(records.to_pylist()), np.int32).reshape(-1, _FIELDS)
    bitmap, at, first, last_start, last, between, bits = (table[:, i].astype(np.int64) for i in range(_FIELDS))
    group, base = np.repeat(group, each), np.repeat(base, each)
    key = (group >> _BITMAP << _BITMAP) | ((group & ((1 << _BITMAP) - 1)) * size + bitmap)
    start = base + at
    order = np.lexsort((start, key))
    return [x[order] for x in (key, start, first, base + last_start, last, between, bits & _FULL)]


def _merged(n_words: int, size: int, totals: bool):
    """Rows (group, start, records), sorted, to (key, c_words), or to (code's number, n_bitmaps, c_words) of some bitmaps."""

    def out(held: list[pa.RecordBatch]) -> pa.RecordBatch:
        group, base = (np.concatenate([b.column(i).to_numpy() for b in held]) for i in range(2))
        key, words = merged(opened(group, base, pa.concat_arrays([b.column(2) for b in held]), size), n_words)
        if not totals:
            return pa.RecordBatch.from_arrays([pa.array(key), pa.array(words)], ["key", "c_words"])
        number = key >> _BITMAP
        at = np.flatnonzero(np.concatenate([[True], number[1:] != number[:-1]]))
        return pa.RecordBatch.from_arrays([pa.array(x) for x in (number[at], np.diff(at, append=len(key)), np.add.reduceat(words, at))], ["number", "n_bitmaps", "c_words"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, n = [], 0  # batches, and their bytes
        for b in batches:
            group = b.column(0).to_numpy()
            x = 0
            for y in [*(np.flatnonzero(np.diff(group)) + 1).tolist(), len(group)]:
                if x == y:
                    continue
                if n > 4 * _FIELDS * GROUP and held[-1].column(0)[-1].as_py() != group[x]:
                    yield out(held)
                    held, n = [], 0
                held.append(b.slice(x, y - x))
                n += pc.sum(pc.binary_length(held[-1].column(2))).as_py()
                x = y
        if held:
            yield out(held)

    return run


def _measured(placed: list[tuple[DataFrame, list[tuple[str, int, int, list[str]]]]], values: dict[str, int], n: int, most: int, totals: bool) -> tuple[DataFrame, list[tuple[str, list[str]]]]:
    """What `_merged` gives, and each code's column and designs."""
    cols, names, out = list(values), [], None
    size = max(1, min(GROUP_BITMAPS, GROUP // max(1, -(-n // most))))
    for facts, codes in placed:
        ship(facts.sparkSession)
        numbers = [(len(names) + i, cols.index(c), values[c], k, bitmaps) for i, (c, k, bitmaps, _) in enumerate(codes)]
        names += [(c, designs) for c, _, _, designs in codes]
        one = facts.select("pos", *[f"ord_{c}" for c in cols]).mapInArrow(_pieces(numbers, len(cols), most, size), "group long, start long, records binary")
        out = one if out is None else out.unionByName(one)
    schema = "number long, n_bitmaps long, c_words long" if totals else "key long, c_words long"
    return out.repartition("group").sortWithinPartitions("group", "start").mapInArrow(_merged(-(-n // 32), size, totals), schema), names


def _named(number: Column, names: list[tuple[str, list[str]]]) -> list[Column]:
    """design (a row for each) and attr of a code's number."""
    which = (number + 1).cast("int")
    return [F.explode(F.element_at(F.array(*[F.array(*map(F.lit, d)) for _, d in names]), which)).alias("design"), F.element_at(F.array(*[F.lit(c) for c, _ in names]), which).alias("attr")]


def code_sizes(placed: list[tuple[DataFrame, list[tuple[str, int, int, list[str]]]]], values: dict[str, int], n: int, most: int = PIECE) -> DataFrame:
    """(design, attr, bitmap_id, c_words, n_words) of tables of n facts, in the marker format.

    placed: facts (pos, ord_<col>...) under an order, each with its codes: (column, k, bitmaps, names of the designs with it).
    """
    sizes, names = _measured(placed, values, n, most, False)
    bitmap = F.col("key").bitwiseAND(F.lit((1 << _BITMAP) - 1)).cast("int")
    return sizes.select(*_named(F.shiftright("key", _BITMAP), names), bitmap.alias("bitmap_id"), "c_words", F.lit(-(-n // 32)).cast("bigint").alias("n_words"))


def code_totals(placed: list[tuple[DataFrame, list[tuple[str, int, int, list[str]]]]], values: dict[str, int], n: int, most: int = PIECE) -> DataFrame:
    """(design, attr, n_bitmaps, c_words, plain_words): the sums of `code_sizes`, begun where bitmaps are put together."""
    parts, names = _measured(placed, values, n, most, True)
    sums = parts.groupBy("number").agg(F.sum("n_bitmaps").alias("n_bitmaps"), F.sum("c_words").alias("c_words"))
    return sums.select(*_named(F.col("number"), names), "n_bitmaps", "c_words", (F.col("n_bitmaps") * F.lit(-(-n // 32))).cast("bigint").alias("plain_words"))
