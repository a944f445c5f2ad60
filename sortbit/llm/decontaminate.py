"""Benchmark decontamination by greedy string tiling.

A document and a benchmark item that share a seed (a run of `seed` equal tokens) are
compared: the longest common runs that overlap no earlier tile are marked as tiles, again
and again, down to `seed` tokens. Common runs are found by hashes of all windows of one
length (Karp-Rabin), the length falling from the longest seen; matches are confirmed on
the tokens. An item is leaked into a document when its tiles cover at least `coverage` of
its tokens, in whatever order the document holds them.

The seed join has two routes with equal results. While the benchmark's text is at most
`broadcast_bytes`, it goes to every executor and one pass over the documents does all.
Beyond that, seeds of both sides are joined by a shuffle, and each pair found gets its two
texts by joins on their ids.

Tokens are runs of letters and digits (and any byte beyond ASCII), A-Z in lower case. An
item with fewer than `seed` tokens is compared as one whole seed of its own length. Null
and empty texts have no token: such an item leaks nowhere and such a document holds none.
Items with equal tokens all get their own rows. No benchmark: no rows.
"""

from __future__ import annotations

from collections import defaultdict

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .base import keep, ship, text_chunks
from .bytewords import LOWER, SpanHash, distinct, mix, spans, text_bytes, windows

SEED = 5
COVERAGE = 0.5

_INSIDE = np.zeros(256, bool)
_INSIDE[[*range(48, 58), *range(65, 91), *range(97, 123), *range(128, 256)]] = True


def token_hashes(column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """A hash for each token of all texts, and the token range of each text."""
    data, offsets = text_bytes(column)
    starts, ends, text = spans(_INSIDE[data], offsets)
    bounds = np.searchsorted(text, np.arange(len(offsets)))
    return SpanHash(LOWER[data]).of(starts, ends), bounds


def runs(tokens: np.ndarray, width: int) -> np.ndarray:
    return windows(tokens, np.zeros(len(tokens), np.int8), width)[0]


class _Side:
    """One text's tokens, which of them no tile has marked yet, and hashes of all its windows of a length."""

    def __init__(self, tokens: np.ndarray):
        self.tokens, self.free = tokens, np.ones(len(tokens), bool)
        up = np.full(len(tokens), _BASE, np.uint64)
        up[:1] = 1
        self.sums = np.concatenate((np.zeros(1, np.uint64), np.cumsum(tokens * np.cumprod(up), dtype=np.uint64)))
        down = np.full(len(tokens) + 1, _BASE_INVERSE, np.uint64)
        down[0] = 1
        self.down = np.cumprod(down)

    def windows(self, length: int) -> tuple[np.ndarray, np.ndarray]:
        """Starts of the unmarked windows, and their hashes."""
        if len(self.free) < length:
            return np.zeros(0, np.int64), np.zeros(0, np.uint64)
        sums = np.concatenate(([0], np.cumsum(self.free)))
        at = np.flatnonzero(sums[length:] - sums[:-length] == length)
        return at, mix((self.sums[at + length] - self.sums[at]) * self.down[at])


_BASE = np.uint64(0xD6E8FEB86659FD93)
_BASE_INVERSE = np.uint64(pow(0xD6E8FEB86659FD93, -1, 1 << 64))


def tiles(doc: np.ndarray, item: np.ndarray, least: int) -> list[tuple[int, int, int]]:
    """Greedy tiles (start in doc, start in item, length), the longest first; equal lengths in the document's order."""
    a, b = _Side(doc), _Side(item)
    found: list[tuple[int, int, int]] = []
    high = min(len(doc), len(item))
    while high >= least and _common(a, b, least):
        low = least
        while low < high:  # a common run of some length holds one of every shorter length
            middle = (low + high + 1) // 2
            low, high = (middle, high) if _common(a, b, middle) else (low, middle - 1)
        starts, hashes = b.windows(low)
        by_hash = defaultdict(list)
        for j, h in zip(starts.tolist(), hashes.tolist(), strict=True):
            by_hash[h].append(j)
        at, seen = a.windows(low)
        hits = np.isin(seen, hashes)
        for i, h in zip(at[hits].tolist(), seen[hits].tolist(), strict=True):
            if not a.free[i : i + low].all():
                continue
            for j in by_hash[h]:
                if b.free[j : j + low].all() and np.array_equal(doc[i : i + low], item[j : j + low]):
                    found.append((i, j, low))
                    a.free[i : i + low] = b.free[j : j + low] = False
                    break
        high = low - 1
    return found


def _common(a: _Side, b: _Side, length: int) -> bool:
    x, y = a.windows(length)[1], b.windows(length)[1]
    return bool(len(x) and len(y) and np.isin(x, y).any())


class Benchmark:
    """The items' tokens and a sorted table of their seeds."""

    def __init__(self, ids: list, texts: pa.Array, seed: int):
        hashes, bounds = token_hashes(texts)
        self.seed, self.ids = seed, ids
        self.tokens = [hashes[a:b] for a, b in zip(bounds[:-1], bounds[1:], strict=True)]
        by_width = defaultdict(list)
        for k, t in enumerate(self.tokens):
            if len(t):
                width = min(seed, len(t))
                by_width[width].append((runs(t, width), k))
        self.tables = {}
        for width, found in by_width.items():
            h = np.concatenate([x for x, _ in found])
            k = np.concatenate([np.full(len(x), k) for x, k in found])
            order = np.argsort(h, kind="stable")
            self.tables[width] = (h[order], k[order])

    def candidates(self, hashes: np.ndarray, bounds: np.ndarray) -> np.ndarray:
        """Distinct (text, item) pairs with a seed in common."""
        pairs = []
        text = np.repeat(np.arange(len(bounds) - 1), np.diff(bounds))
        for width, (table, owner) in self.tables.items():
            w, at = windows(hashes, text, width)
            low, high = np.searchsorted(table, w, "left"), np.searchsorted(table, w, "right")
            hit = np.flatnonzero(high > low)
            counts = (high - low)[hit]
            place = np.repeat(low[hit] - np.concatenate(([0], np.cumsum(counts)[:-1])), counts) + np.arange(counts.sum()) if len(hit) else hit
            pairs.append(np.repeat(text[at[hit]], counts) * np.int64(len(self.ids)) + owner[place])
        pairs = distinct(np.concatenate(pairs)) if pairs else np.zeros(0, np.int64)
        return np.column_stack([pairs // max(1, len(self.ids)), pairs % max(1, len(self.ids))])


def _covered(doc: np.ndarray, item: np.ndarray, seed: int) -> tuple[int, int]:
    found = tiles(doc, item, min(seed, len(item)))
    return len(found), sum(n for _, _, n in found)


def contaminated(docs: DataFrame, benchmark: DataFrame, seed: int = SEED, coverage: float = COVERAGE, broadcast_bytes: int = 32 << 20) -> DataFrame:
    """(doc_id, item_id, n_tiles, covered_tokens, item_tokens, coverage) for every leaked pair.

    docs: doc_id, text; benchmark: item_id, text.
    """
    ship(docs.sparkSession)
    docs, items = docs.select("doc_id", "text"), benchmark.select("item_id", "text").where(F.col("text").isNotNull())
    size = items.agg(F.coalesce(F.sum(F.octet_length("text") + 64), F.lit(0))).first()[0]
    schema = f"doc_id {docs.schema['doc_id'].dataType.simpleString()}, item_id {items.schema['item_id'].dataType.simpleString()}, n_tiles int, covered_tokens int, item_tokens int, coverage double"
    if size <= broadcast_bytes:
        rows = items.orderBy("item_id").collect()
        shared = docs.sparkSession.sparkContext.broadcast(([r[0] for r in rows], [r[1] for r in rows]))

        def search(batches):
            ids, texts = shared.value
            bench = Benchmark(ids, pa.array(texts, pa.large_string()), seed)
            for batch in text_chunks(batches):
                hashes, bounds = token_hashes(batch.column("text"))
                found = []
                for i, k in bench.candidates(hashes, bounds).tolist():
                    n, covered = _covered(hashes[bounds[i] : bounds[i + 1]], bench.tokens[k], seed)
                    total = len(bench.tokens[k])
                    if covered >= coverage * total:
                        found.append((i, ids[k], n, covered, total, covered / total))
                if found:
                    columns = list(zip(*found, strict=True))
                    yield _result(batch.column("doc_id").take(pa.array(columns[0])), columns[1:], schema_types)

        schema_types = _arrow_types(items)
        return docs.mapInArrow(search, schema)
    return _by_shuffle(docs, items, seed, coverage, schema)


def _arrow_types(items: DataFrame) -> list[pa.DataType]:
    from pyspark.sql.pandas.types import to_arrow_type

    return [to_arrow_type(items.schema["item_id"].dataType), pa.int32(), pa.int32(), pa.int32(), pa.float64()]


def _result(doc_ids: pa.Array, columns, types) -> pa.RecordBatch:
    names = ["doc_id", "item_id", "n_tiles", "covered_tokens", "item_tokens", "coverage"]
    return pa.record_batch([doc_ids, *(pa.array(c, t) for c, t in zip(columns, types, strict=True))], names)


def _seeds(df: DataFrame, id_col: str, widths: list[int], own: bool, seed: int) -> DataFrame:
    """(id, width, seed hash), distinct within a text. own: each text has one width, min(seed, its tokens)."""
    kind = df.schema[id_col].dataType.simpleString()

    def run(batches):
        for batch in text_chunks(batches):
            hashes, bounds = token_hashes(batch.column("text"))
            ids, width_of, out = [], [], []
            for i, (a, b) in enumerate(zip(bounds[:-1], bounds[1:], strict=True)):
                for width in [min(seed, int(b - a))] if own else widths:
                    if width and b - a >= width:
                        h = distinct(runs(hashes[a:b], width))
                        out.append(h.view(np.int64))
                        ids.append(np.full(len(h), i))
                        width_of.append(np.full(len(h), width, np.int32))
            if out:
                yield pa.record_batch({id_col: batch.column(id_col).take(pa.array(np.concatenate(ids))), "width": pa.array(np.concatenate(width_of)), "h": pa.array(np.concatenate(out))})

    return df.mapInArrow(run, f"{id_col} {kind}, width int, h long")


def _by_shuffle(docs: DataFrame, items: DataFrame, seed: int, coverage: float, schema: str) -> DataFrame:
    item_seeds = keep(_seeds(items, "item_id", [], True, seed))
    widths = [r[0] for r in item_seeds.select("width").distinct().collect()]  # at most `seed` numbers
    pairs = keep(_seeds(docs, "doc_id", widths, False, seed).join(item_seeds, ["width", "h"]).select("doc_id", "item_id").distinct())
    both = pairs.join(docs, "doc_id").join(items.withColumnRenamed("text", "item_text"), "item_id")
    types = _arrow_types(items)

    def compare(batches):
        for batch in text_chunks(batches):
            doc, at = token_hashes(batch.column("text"))
            item, of = token_hashes(batch.column("item_text"))
            found = []
            for i in range(batch.num_rows):
                total = int(of[i + 1] - of[i])
                n, covered = _covered(doc[at[i] : at[i + 1]], item[of[i] : of[i + 1]], seed)
                if covered >= coverage * total:
                    found.append((i, n, covered, total, covered / total))
            if found:
                columns = list(zip(*found, strict=True))
                at_rows = pa.array(columns[0])
                yield _result(batch.column("doc_id").take(at_rows), [batch.column("item_id").take(at_rows), *columns[1:]], types)

    return both.select("doc_id", "item_id", "text", "item_text").mapInArrow(compare, schema)


def clean(docs: DataFrame, benchmark: DataFrame, **how) -> DataFrame:
    """docs without the documents into which an item leaked; all their columns."""
    leaked = contaminated(docs, benchmark, **how).select("doc_id").distinct()
    return docs.join(leaked, "doc_id", "left_anti").select(docs.columns)
