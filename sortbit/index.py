"""Building, storing and asking compressed bitmap indexes.

A build joins each column's ordinals to the facts, sorts once and writes the facts once, with
their block and their position in it. Blocks are cut inside the sort's partitions, so no row
is counted or numbered across the table. One task then turns a block's ordinals into payloads
in numpy; bitmaps that are absent from a block are not stored.

The index is a relation (block_id, attr, bitmap_id, upto, n_rows, n_words, n_set, payload), in
files sorted by attr and bitmap_id. A query reads the bitmaps that it names by a pushed-down
filter, and each block's own row (attr "", bitmap -1) only where rows without any named bitmap
may hold. The facts are read by `fetch` alone, and then only the blocks with hits.
"""

from __future__ import annotations

import datetime
import decimal
import json
import math
from concurrent.futures import ThreadPoolExecutor
from dataclasses import asdict, dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import bitops
from .codec import CODECS
from .codec.bits import n_words
from .codec.marker32_many import payloads
from .codes import assign_codes, numbered, plan_codes
from .io import materialise, ship
from .predicate import And, Eq, In, IsNull, Not, Or, Predicate, Range, Xor, leaves, normalise
from .profile import value_counts
from .ranking import ordinals_of, positions_of

#: Dictionaries up to this many values are sent to the executors for coding; larger ones are joined by a merge.
BROADCAST_VALUES = 1 << 20
#: Dictionaries up to this many values are held by the driver after the first query that asks them; others are asked by a job.
HELD_VALUES = 100_000
#: Codes that one leaf evaluates one by one; where it names more, a block's rows are decoded instead.
MANY_CODES = 4096
#: Blocks with hits that `fetch` names to the scan of the facts.
NAMED_BLOCKS = 10_000

ROWS = "block_id long, attr string, bitmap_id int, upto int, n_rows long, n_words long, n_set long, payload binary"


@dataclass(frozen=True)
class IndexSpec:
    """k: bitmaps for each value, for all columns or by column.

    style "range": a bitmap holds the rows whose ordinal is at most its own, up to the next ordinal
    of the block (`upto`), so a range is one bitmap without another; k and allocation play no part.
    cut "table": blocks of exactly block_rows rows, also across the sort's partitions; a table of one block is always one.
    block_bytes: rows of a block by bytes, from the columns' default widths, instead of block_rows.
    """

    k: int | dict[str, int] = 1
    allocation: str = "alpha"
    codec: str = "marker32"
    block_rows: int = 1 << 20
    limit_k: bool = True
    style: str = "equality"
    cut: str = "partition"
    block_bytes: int | None = None

    def k_of(self, col: str) -> int:
        return 1 if self.style == "range" else self.k.get(col, 1) if isinstance(self.k, dict) else self.k

    def rows_of(self, df: DataFrame) -> int:
        if self.block_bytes is None:
            return self.block_rows
        return max(32, self.block_bytes // max(1, df._jdf.schema().defaultSize()))


def _packed(ids: np.ndarray, pos: np.ndarray, style: str) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(bitmaps, edges, word numbers, words) of bits (bitmap, position), both in rising order of bitmap, then position."""
    word = pos // 32
    new = np.ones(len(ids), bool)
    new[1:] = (ids[1:] != ids[:-1]) | (word[1:] != word[:-1])
    first = np.flatnonzero(new)
    values = np.bitwise_or.reduceat(np.uint32(1) << (pos % 32).astype(np.uint32), first)
    numbers, owner = word[first], ids[first]
    edges = np.concatenate(([0], np.flatnonzero(owner[1:] != owner[:-1]) + 1, [len(owner)]))
    bitmaps = owner[edges[:-1]]
    if style == "range":  # each bitmap adds its bits to those before it
        held, some = np.zeros(int(numbers.max()) + 1, np.uint32), []
        for a, b in zip(edges[:-1], edges[1:], strict=True):
            held[numbers[a:b]] |= values[a:b]
            at = np.flatnonzero(held)
            some.append((at, held[at]))
        edges = np.concatenate(([0], np.cumsum([len(x) for x, _ in some])))
        numbers, values = np.concatenate([x for x, _ in some]), np.concatenate([x for _, x in some])
    return bitmaps, edges, numbers, values


def _block_builder(attrs: list[str], plans: dict[str, tuple[int, int, int]], spec: IndexSpec, naive: bool):
    """One block's facts (pos, and each column's ordinal) to index rows."""

    def build(table: pa.Table) -> pa.Table:
        block = table.column("block_id")[0].as_py()
        pos = table.column("pos").to_numpy()
        by_pos = np.argsort(pos, kind="stable")
        pos, n_rows = pos[by_pos], len(pos)
        parts = [_rows(block, [""], np.array([-1]), np.array([-1]), n_rows, np.zeros(1, np.int64), pa.array([b""], pa.binary()))]
        for i, attr in enumerate(attrs):
            ordinals = table.column(f"__o{i}").to_numpy()[by_pos]
            n_values, k, size = plans[attr]
            codes = positions_of(ordinals, size, k, spec.allocation) if k > 1 else ordinals[:, None]
            if naive:
                found = [_packed(np.full(int(hit.sum()), b), pos[hit], "equality") for b in range(size) if (hit := (codes == b).any(axis=1)).any()]
                bitmaps, numbers, values = (np.concatenate([f[j] for f in found]) for j in (0, 2, 3))
                edges = np.concatenate(([0], np.cumsum([len(f[2]) for f in found])))
            else:
                ids, at = codes.reshape(-1), np.repeat(pos, codes.shape[1])
                order = np.argsort(ids, kind="stable")
                bitmaps, edges, numbers, values = _packed(ids[order], at[order], spec.style)
            n_set = np.add.reduceat(np.bitwise_count(values).astype(np.int64), edges[:-1])
            upto = np.append(bitmaps[1:] - 1, n_values - 1) if spec.style == "range" else bitmaps
            if spec.codec == "marker32":
                stream, offsets = payloads(edges, numbers, values, n_rows)
                held = pa.Array.from_buffers(pa.binary(), len(bitmaps), [None, pa.py_buffer((offsets * 4).astype(np.int32)), pa.py_buffer(stream.astype("<u4"))])
            else:
                encoded = []
                for a, b in zip(edges[:-1].tolist(), edges[1:].tolist(), strict=True):
                    words = np.zeros(n_words(n_rows), np.uint32)
                    words[numbers[a:b]] = values[a:b]
                    encoded.append(CODECS[spec.codec].encode(words, n_rows))
                held = pa.array(encoded, pa.binary())
            parts.append(_rows(block, [attr], bitmaps, upto, n_rows, n_set, held))
        return pa.concat_tables(parts)

    return build


def _rows(block: int, attr: list[str], bitmaps: np.ndarray, upto: np.ndarray, n_rows: int, n_set: np.ndarray, held: pa.Array) -> pa.Table:
    n = len(bitmaps)
    widths = np.diff(np.frombuffer(held.buffers()[1], np.int32)[: n + 1])
    return pa.table(
        {
            "block_id": np.full(n, block, np.int64),
            "attr": pa.array(attr * n, pa.string()),
            "bitmap_id": bitmaps.astype(np.int32),
            "upto": upto.astype(np.int32),
            "n_rows": np.full(n, n_rows, np.int64),
            "n_words": (-(-widths // 4)).astype(np.int64),
            "n_set": n_set.astype(np.int64),
            "payload": held,
        }
    )


def _cut(ordered: DataFrame, rows: int, across: bool) -> DataFrame:
    """Adds block_id and pos. The blocks of a partition are numbered from that partition's own range of numbers.

    across: blocks go on over the partitions' ends; the rows are then numbered by prefix sums over the partitions.
    """
    if across:
        at = numbered(ordered, "__row")
        return at.withColumn("block_id", F.floor(F.col("__row") / rows).cast("bigint")).withColumn("pos", F.col("__row") % rows).drop("__row")
    at = ordered.withColumn("__at", F.monotonically_increasing_id())
    local = F.col("__at").bitwiseAND(F.lit((1 << 33) - 1))
    block = F.shiftright("__at", 33) * F.lit((1 << 33) // rows + 1) + F.floor(local / rows)
    return materialise(at.withColumn("block_id", block.cast("bigint")).withColumn("pos", local % rows).drop("__at"))


def build_index(df: DataFrame, cols: list[str], order, spec: IndexSpec = IndexSpec(), histograms: dict[str, DataFrame] | None = None, naive: bool = False) -> BitmapIndex:
    """histograms: (value, freq) by column, where they are already written. naive: every bitmap looks at every row."""
    ship(df.sparkSession)

    def dictionary(c: str) -> tuple[DataFrame, tuple[int, int, int], int]:
        counts = histograms[c] if histograms and c in histograms else materialise(value_counts(df, c))
        n, n_rows = counts.agg(F.count("*"), F.coalesce(F.sum("freq"), F.lit(0))).first()
        return assign_codes(df, c, spec.k_of(c), spec.allocation, spec.limit_k, counts=counts), (n, *plan_codes(n, spec.k_of(c), spec.limit_k)), n_rows

    with ThreadPoolExecutor(8) as pool:
        made = dict(zip(cols, pool.map(dictionary, cols), strict=True))
    dicts, plans, n_rows = {c: x[0] for c, x in made.items()}, {c: x[1] for c, x in made.items()}, made[cols[0]][2]
    coded = df
    for i, c in enumerate(cols):
        lookup = dicts[c].select(F.col("value").alias("__v"), F.col("ord").cast("int").alias(f"__o{i}"))
        lookup = F.broadcast(lookup) if plans[c][0] <= BROADCAST_VALUES else lookup.hint("merge")
        coded = coded.join(lookup, F.col(f"`{c}`").eqNullSafe(F.col("__v"))).drop("__v")
    codes = [f"__o{i}" for i in range(len(cols))]
    per_block = spec.rows_of(df)
    facts = _cut(order.apply(coded), per_block, spec.cut == "table" or n_rows <= per_block)
    rows = facts.select("block_id", "pos", *codes).groupBy("block_id").applyInArrow(_block_builder(cols, plans, spec, naive), ROWS)
    return BitmapIndex(facts.drop(*codes), dicts, materialise(rows.sortWithinPartitions("attr", "bitmap_id", "block_id")), spec, plans)


def _spans(ordinals: list[int]) -> list[tuple[int, int]]:
    out: list[tuple[int, int]] = []
    for o in sorted(set(ordinals)):
        if out and out[-1][1] == o - 1:
            out[-1] = (out[-1][0], o)
        else:
            out.append((o, o))
    return out


class _Block:
    """The bitmaps of one block that a query has read."""

    def __init__(self, table: pa.Table, spec: IndexSpec, plans: dict):
        self.n_rows = int(table.column("n_rows")[0].as_py())
        self.spec, self.plans, self.held = spec, plans, {}
        for attr, b, upto, payload in zip(*(table.column(c).to_pylist() for c in ("attr", "bitmap_id", "upto", "payload")), strict=True):
            if attr:
                self.held.setdefault(attr, {})[b] = (upto, payload)

    def load(self, payload: bytes) -> bitops.Sparse:
        if self.spec.codec == "marker32":
            return bitops.load(payload, self.n_rows)
        words = CODECS[self.spec.codec].decode(payload, self.n_rows)
        at = np.flatnonzero(words)
        return at, words[at]

    def bitmap(self, attr: str, b: int) -> bitops.Sparse:
        found = self.held.get(attr, {}).get(b)
        return self.load(found[1]) if found else bitops.EMPTY

    def upto(self, attr: str, j: int) -> bitops.Sparse:
        """The rows whose ordinal is at most j, where bitmaps are cumulative."""
        for b, (last, payload) in self.held.get(attr, {}).items():
            if b <= j <= last:
                return self.load(payload)
        return bitops.EMPTY

    def ordinals(self, attr: str) -> np.ndarray:
        """Each row's ordinal, from all bitmaps of an attribute."""
        n_values, k, size = self.plans[attr]
        out = np.zeros(self.n_rows, np.int64)
        if self.spec.style == "range":
            seen = np.zeros(self.n_rows, bool)
            for b, (_, payload) in sorted(self.held.get(attr, {}).items()):
                at = bitops.bm_positions(self.load(payload))
                out[at[~seen[at]]] = b
                seen[at] = True
            return out
        each = [(bitops.bm_positions(self.load(p)), b) for b, (_, p) in sorted(self.held.get(attr, {}).items())]
        pos, ids = np.concatenate([p for p, _ in each]), np.concatenate([np.full(len(p), b) for p, b in each])
        bits = ids[np.argsort(pos, kind="stable")].reshape(self.n_rows, k)
        return ordinals_of(bits, size, self.spec.allocation) if k > 1 else bits[:, 0]

    def leaf(self, attr: str, spans: list[tuple[int, int]]) -> bitops.Sparse:
        n_values, k, size = self.plans[attr]
        if self.spec.style == "range":
            return bitops.bm_or_many([bitops.bm_andnot(self.upto(attr, b), self.upto(attr, a - 1)) for a, b in spans])
        if k == 1:
            lows = np.array([a for a, _ in spans])
            ends = np.array([b for _, b in spans])
            named = [b for b in self.held.get(attr, {}) if (i := int(np.searchsorted(lows, b, side="right")) - 1) >= 0 and b <= ends[i]] if spans else []
            return bitops.bm_or_many([self.bitmap(attr, b) for b in named])
        if sum(b - a + 1 for a, b in spans) <= MANY_CODES:
            codes = positions_of(_each(spans), size, k, self.spec.allocation)
            loaded = {b: self.bitmap(attr, b) for b in np.unique(codes).tolist()}
            return bitops.bm_or_many([bitops.bm_and_many([loaded[b] for b in bits]) for bits in codes.tolist()])
        ordinals = self.ordinals(attr)
        hit = np.zeros(self.n_rows, bool)
        for a, b in spans:
            hit |= (ordinals >= a) & (ordinals <= b)
        at = np.flatnonzero(hit)
        word, first = np.unique(at // 32, return_index=True)
        return (word, np.bitwise_or.reduceat(np.uint32(1) << (at % 32).astype(np.uint32), first)) if len(at) else bitops.EMPTY

    def value(self, p: Predicate, named: dict) -> bitops.Sparse:
        if isinstance(p, And):
            parts = [self.value(x, named) for x in p.parts if not isinstance(x, Not)]
            out = bitops.bm_and_many(parts) if parts else bitops.bm_not(bitops.EMPTY, self.n_rows)
            for x in p.parts:
                if isinstance(x, Not):
                    out = bitops.bm_andnot(out, self.value(x.part, named))
            return out
        if isinstance(p, Or):
            return bitops.bm_or_many([self.value(x, named) for x in p.parts])
        if isinstance(p, Xor):
            return bitops.bm_xor(self.value(p.left, named), self.value(p.right, named))
        if isinstance(p, Not):
            return bitops.bm_not(self.value(p.part, named), self.n_rows)
        return self.leaf(p.col, named[p])


def _each(spans: list[tuple[int, int]]) -> np.ndarray:
    return np.concatenate([np.arange(a, b + 1) for a, b in spans]) if spans else np.zeros(0, np.int64)


def _holds_without(p: Predicate) -> bool:
    """Whether rows in none of the named bitmaps hold."""
    if isinstance(p, And):
        return all(map(_holds_without, p.parts))
    if isinstance(p, Or):
        return any(map(_holds_without, p.parts))
    if isinstance(p, Xor):
        return _holds_without(p.left) != _holds_without(p.right)
    return not _holds_without(p.part) if isinstance(p, Not) else False


#: Types whose equality and order Python and Spark share.
_PLAIN = (bool, int, str, datetime.date, datetime.datetime, decimal.Decimal)


@dataclass
class BitmapIndex:
    """plans: (values, k, bitmaps) of each column."""

    facts: DataFrame
    dicts: dict[str, DataFrame]
    rows: DataFrame
    spec: IndexSpec
    plans: dict[str, tuple[int, int, int]]
    _held: dict[str, dict] = field(default_factory=dict, repr=False)

    def save(self, path: str, mode: str = "errorifexists") -> None:
        """Facts, dictionaries, the index, and last a manifest with the spec."""
        self.facts.write.mode(mode).parquet(f"{path}/facts")
        self.rows.sortWithinPartitions("attr", "bitmap_id", "block_id").write.mode(mode).parquet(f"{path}/blocks")
        for c, d in self.dicts.items():
            d.write.mode(mode).parquet(f"{path}/dict/{c}")
        manifest = json.dumps({"spec": asdict(self.spec), "plans": self.plans})
        self.facts.sparkSession.createDataFrame([(manifest,)], "value string").coalesce(1).write.mode(mode).text(f"{path}/manifest")

    def _ordinals(self, leaf: Predicate) -> list[tuple[int, int]]:
        """The ordinals that a leaf names, as spans: in value order a range of values is one."""
        if self.plans[leaf.col][0] <= HELD_VALUES and isinstance(leaf, Eq | In):
            asked = [leaf.value] if isinstance(leaf, Eq) else list(leaf.values)
            if leaf.col not in self._held:
                self._held[leaf.col] = {r[0]: r[1] for r in self.dicts[leaf.col].select("value", "ord").collect()}
            held = self._held[leaf.col]
            kinds = {type(v) for v in held if v is not None}
            plain = all((type(v) in _PLAIN or (type(v) is float and math.isfinite(v))) and (type(v) in kinds or ({type(v)} | kinds <= {int, float})) for v in asked)
            if plain:
                return _spans([held[v] for v in asked if v in held])
        value, table = F.col("value"), self.dicts[leaf.col]
        if isinstance(leaf, Range):
            held = value.isNotNull()
            if leaf.low is not None:
                held &= value >= F.lit(leaf.low)
            if leaf.high is not None:
                held &= value <= F.lit(leaf.high)
            low, high = table.where(held).agg(F.min("ord"), F.max("ord")).first()
            return [] if low is None else [(low, high)]
        if isinstance(leaf, Eq):
            held = value == F.lit(leaf.value)
        elif isinstance(leaf, In):
            held = value.isin(*leaf.values)
        elif isinstance(leaf, IsNull):
            held = value.isNull()
        else:
            raise TypeError(f"no such predicate: {leaf}")
        return _spans([r[0] for r in table.where(held).select("ord").collect()])  # at most the values that the leaf lists

    def plan(self, predicate: Predicate) -> tuple[Predicate, dict[Predicate, list[tuple[int, int]]]]:
        """The normal form, and for each leaf the ordinals that it names."""
        tree = normalise(predicate)
        return tree, {leaf: self._ordinals(leaf) for leaf in dict.fromkeys(leaves(tree))}

    def _bitmaps(self, col: str, spans: list[tuple[int, int]]) -> list[int] | None:
        """The bitmaps to read for some ordinals; None: all of the column. With range codes: the ordinals to look up."""
        _, k, size = self.plans[col]
        if self.spec.style == "range":
            return sorted({j for a, b in spans for j in (a - 1, b) if j >= 0})
        if sum(b - a + 1 for a, b in spans) > MANY_CODES:
            return None
        return np.unique(positions_of(_each(spans), size, k, self.spec.allocation)).tolist()

    def _named(self, col: str, spans: list[tuple[int, int]]) -> Column:
        """The index rows that some ordinals of a column need."""
        at = F.col("attr") == col
        if not spans:
            return F.lit(False)
        if self.spec.style == "range":
            held = F.lit(False)
            for j in self._bitmaps(col, spans):
                held |= (F.col("bitmap_id") <= j) & (F.col("upto") >= j)
            return at & held
        if self.plans[col][1] == 1 and len(spans) <= 64:
            held = F.lit(False)
            for a, b in spans:
                held |= F.col("bitmap_id").between(a, b) if a < b else F.col("bitmap_id") == a
            return at & held
        bits = self._bitmaps(col, spans)
        return at if bits is None else at & F.col("bitmap_id").isin(bits)

    def explain(self, predicate: Predicate) -> dict:
        """The normal form, the bitmaps that are read (col, bitmap), and whether blocks without any of them are."""
        tree, named = self.plan(predicate)
        bitmaps = set()
        for p, spans in named.items():
            bits = self._bitmaps(p.col, spans)
            bitmaps |= {(p.col, b) for b in (range(self.plans[p.col][2]) if bits is None else bits)}
        return {"predicate": tree, "bitmaps": sorted(bitmaps), "every_block": _holds_without(tree)}

    def _evaluated(self, predicate: Predicate | None, schema: str, result, besides: list[str] | None = None) -> DataFrame:
        """result(block_id, block, its rows that hold) for each block that may have some. besides: columns to read whole."""
        tree, named = self.plan(predicate) if predicate is not None else (None, {})
        held = F.lit(False)
        for p, spans in named.items():
            held |= self._named(p.col, spans)
        if tree is None or _holds_without(tree):
            held |= F.col("attr") == ""
        if besides is not None:
            held |= F.col("attr").isin(besides)
        spec, plans = self.spec, self.plans
        ship(self.rows.sparkSession)

        def run(table: pa.Table) -> pa.Table:
            block = _Block(table, spec, plans)
            return result(table.column("block_id")[0].as_py(), block, block.value(tree, named) if tree is not None else bitops.bm_not(bitops.EMPTY, block.n_rows))

        return self.rows.where(held).select("block_id", "attr", "bitmap_id", "upto", "n_rows", "payload").groupBy("block_id").applyInArrow(run, schema)

    def where(self, predicate: Predicate) -> DataFrame:
        """(block_id, pos) of the facts that hold."""

        def result(number: int, block: _Block, found: bitops.Sparse) -> pa.Table:
            pos = bitops.bm_positions(found)
            return pa.table({"block_id": np.full(len(pos), number, np.int64), "pos": pos.astype(np.int64)})

        return self._evaluated(predicate, "block_id long, pos long", result)

    def count_by_block(self, predicate: Predicate) -> DataFrame:
        """(block_id, n) of the blocks that may have hits, from the index alone. One leaf on single bitmaps is a sum of their stored counts."""
        tree, named = self.plan(predicate)
        negated = isinstance(tree, Not)
        leaf = tree.part if negated else tree
        if leaf in named and self.plans[leaf.col][1] == 1:
            held = F.when(F.col("attr") == "", F.lit(0)).otherwise(F.col("n_set"))
            if self.spec.style == "range":
                held = F.lit(0)
                for a, b in named[leaf]:
                    for j, sign in ((b, 1), (a - 1, -1)):
                        held += F.when((F.col("bitmap_id") <= j) & (F.col("upto") >= j) & (F.col("attr") != ""), sign * F.col("n_set")).otherwise(F.lit(0))
            wanted = self._named(leaf.col, named[leaf])
            if negated:
                wanted, held = wanted | (F.col("attr") == ""), F.when(F.col("attr") == "", F.col("n_rows")).otherwise(-held)
            return self.rows.where(wanted).groupBy("block_id").agg(F.sum(held).cast("bigint").alias("n"))
        return self._evaluated(predicate, "block_id long, n long", lambda number, block, found: pa.table({"block_id": [number], "n": [bitops.bm_count(found)]}))

    def count(self, predicate: Predicate) -> int:
        return self.count_by_block(predicate).agg(F.sum("n")).first()[0] or 0

    def equality_counts(self, col: str, values: list, repeats: int = 1) -> DataFrame:
        """(value, n) of several equality queries on one column, answered `repeats` times inside one job."""
        spans = {i: self._ordinals(Eq(col, v)) for i, v in enumerate(values)}
        spec, plans = self.spec, self.plans

        def run(table: pa.Table) -> pa.Table:
            block = _Block(table, spec, plans)
            n = []
            for _ in range(repeats):
                n = [bitops.bm_count(block.leaf(col, spans[i])) for i in spans]
            return pa.table({"i": pa.array(list(spans), pa.int64()), "n": pa.array(n, pa.int64())})

        named = self._named(col, _spans([o for s in spans.values() for a, b in s for o in range(a, b + 1)]))
        found = self.rows.where(named).select("block_id", "attr", "bitmap_id", "upto", "n_rows", "payload").groupBy("block_id").applyInArrow(run, "i long, n long")
        asked = self.rows.sparkSession.createDataFrame(list(enumerate(values)), ["i", "value"])
        return asked.join(found.groupBy("i").agg(F.sum("n").alias("n")), "i", "left").select("value", F.coalesce("n", F.lit(0)).alias("n"))

    def fetch(self, predicate: Predicate) -> DataFrame:
        """The facts that hold, by a semi-join on their places; blocks without hits are left out of the scan."""
        found = materialise(self.where(predicate))
        hit = [r[0] for r in found.select("block_id").distinct().limit(NAMED_BLOCKS + 1).collect()]
        facts = self.facts if len(hit) > NAMED_BLOCKS else self.facts.where(F.col("block_id").isin(hit))
        return facts.join(found, ["block_id", "pos"], "left_semi").drop("block_id", "pos")

    def group_count(self, col: str, predicate: Predicate | None = None) -> DataFrame:
        """(value, n) of one column, for the rows that hold, from the index alone."""
        if predicate is None and self.plans[col][1] == 1 and self.spec.style == "equality":
            counted = self.rows.where(F.col("attr") == col).groupBy(F.col("bitmap_id").cast("bigint").alias("ord")).agg(F.sum("n_set").alias("n"))
            return self.dicts[col].select("value", "ord").join(counted, "ord").select("value", "n")
        return self.group_counts([col], predicate).withColumnRenamed(col, "value")

    def group_counts(self, cols: list[str], predicate: Predicate | None = None) -> DataFrame:
        """(cols..., n) of the combinations of values that occur, for the rows that hold, from the index alone."""

        def result(number: int, block: _Block, found: bitops.Sparse) -> pa.Table:
            at = bitops.bm_positions(found)
            each = np.column_stack([block.ordinals(c)[at] for c in cols]) if len(at) else np.zeros((0, len(cols)), np.int64)
            kinds, n = np.unique(each, axis=0, return_counts=True)
            return pa.table({f"o{i}": kinds[:, i].astype(np.int64) for i in range(len(cols))} | {"n": n.astype(np.int64)})

        names = [f"o{i}" for i in range(len(cols))]
        out = self._evaluated(predicate, ", ".join(f"{o} long" for o in names) + ", n long", result, besides=cols).groupBy(*names).agg(F.sum("n").alias("n"))
        for o, c in zip(names, cols, strict=True):
            out = out.join(self.dicts[c].select(F.col("ord").alias(o), F.col("value").alias(c)), o)
        return out.select(*cols, "n")

    def sizes(self) -> DataFrame:
        """(attr, n_bitmaps, stored_words): what the payloads take."""
        return self.rows.where("attr <> ''").groupBy("attr").agg(F.countDistinct("bitmap_id").alias("n_bitmaps"), F.sum("n_words").alias("stored_words"))

    def density(self) -> DataFrame:
        """(attr, true_bits, all_bits) over the column's whole bitmaps, absent ones included."""
        n = self.rows.where("attr = ''").agg(F.coalesce(F.sum("n_rows"), F.lit(0)).alias("n"))
        per = self.rows.where("attr <> ''").groupBy("attr").agg(F.sum("n_set").alias("true_bits"))
        sizes = F.create_map(*[F.lit(x) for c, (_, _, size) in self.plans.items() for x in (c, size)])
        return per.join(F.broadcast(n)).select("attr", "true_bits", (F.element_at(sizes, F.col("attr")) * F.col("n")).cast("bigint").alias("all_bits"))


def load_index(spark: SparkSession, path: str, cols: list[str] | None = None) -> BitmapIndex:
    """cols: only these columns' dictionaries."""
    saved = json.loads(spark.read.text(f"{path}/manifest").first()[0])
    plans = {c: tuple(p) for c, p in saved["plans"].items()}
    dicts = {c: spark.read.parquet(f"{path}/dict/{c}") for c in cols or plans}
    return BitmapIndex(spark.read.parquet(f"{path}/facts"), dicts, spark.read.parquet(f"{path}/blocks"), IndexSpec(**saved["spec"]), plans)
