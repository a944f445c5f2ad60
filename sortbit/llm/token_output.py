"""Token ids as packed binary matrices.

Documents longer than a row are cut, without loss, into full rows and a rest; the rests
go to rows by best-fit decreasing: in order of size, each goes to the fullest row that
still holds it, found by a segment tree over the free capacities. Each partition packs its
own documents in windows of a bounded number of tokens; nothing is shuffled.

An output row is one row of the matrix: `input_ids` (little-endian unsigned, padded with
`pad_id` to the width), `position_ids` (the same kind; from 0 in every segment, and 0 in
the padding), `cu_seqlens` (0 and each segment's end, so the last is the row's tokens),
and each segment's document and first token. A null or empty text is its end id alone.
"""

from __future__ import annotations

from collections import defaultdict

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame

from .base import ship
from .packing import SEQUENCES
from .tokens import VOCABULARY, encode


class CapacityTree:
    """A segment tree over capacities 0 .. width: the least capacity, not below a size, that some bin has."""

    def __init__(self, width: int):
        self.leaves = 1 << width.bit_length()
        self.count = [0] * (2 * self.leaves)

    def change(self, capacity: int, by: int) -> None:
        node = self.leaves + capacity
        while node:
            self.count[node] += by
            node >>= 1

    def least_from(self, size: int) -> int | None:
        node = self.leaves + size
        if self.count[node]:
            return size
        while node > 1:
            if not node & 1 and self.count[node + 1]:
                node += 1
                while node < self.leaves:
                    node = 2 * node if self.count[2 * node] else 2 * node + 1
                return node - self.leaves
            node >>= 1
        return None


def best_fit_decreasing(sizes: list[int], width: int) -> list[list[int]]:
    """Bins as lists of item numbers; no size may pass the width."""
    tree, free = CapacityTree(width), defaultdict(list)
    bins: list[list[int]] = []
    for i in sorted(range(len(sizes)), key=lambda i: (-sizes[i], i)):
        capacity = tree.least_from(sizes[i])
        if capacity is None:
            capacity, b = width, len(bins)
            bins.append([])
        else:
            b = free[capacity].pop()
            tree.change(capacity, -1)
        bins[b].append(i)
        free[capacity - sizes[i]].append(b)
        tree.change(capacity - sizes[i], 1)
    return bins


def pack_tokens(docs: DataFrame, width: int = 2048, end_id: int = 50256, pad_id: int = 0, id_bytes: int = 2, vocabulary: str = VOCABULARY, window_tokens: int = 1 << 21, id_col: str = "doc_id") -> DataFrame:
    ship(docs.sparkSession)
    kind = docs.schema[id_col].dataType.simpleString()
    dtype = np.dtype(f"<u{id_bytes}")
    if width > np.iinfo(dtype).max or end_id > np.iinfo(dtype).max:
        raise ValueError("id_bytes is too small for these ids and this width")
    schema = f"sequence_id long, n_tokens int, input_ids binary, position_ids binary, cu_seqlens array<int>, doc_ids array<{kind}>, starts array<long>"
    names = ["sequence_id", "n_tokens", "input_ids", "position_ids", "cu_seqlens", "doc_ids", "starts"]

    def run(batches):
        number = TaskContext.get().partitionId() * SEQUENCES
        whole, rests, held = [], [], 0
        arrow_kind = None
        steps = np.arange(width, dtype=dtype)

        def flush() -> pa.RecordBatch:
            nonlocal number, held
            rows = whole + [[rests[i] for i in b] for b in best_fit_decreasing([len(r[2]) for r in rests], width)]
            ids, places, ends, owners, starts = [], [], [], [], []
            for segments in rows:
                row, place = np.full(width, pad_id, dtype), np.zeros(width, dtype)
                end = [0]
                for _, _, part in segments:
                    row[end[-1] : end[-1] + len(part)] = part
                    place[end[-1] : end[-1] + len(part)] = steps[: len(part)]
                    end.append(end[-1] + len(part))
                ids.append(row.tobytes())
                places.append(place.tobytes())
                ends.append(end)
                owners.append([s[0] for s in segments])
                starts.append([s[1] for s in segments])
            out = pa.record_batch([pa.array(np.arange(number, number + len(rows))), pa.array([e[-1] for e in ends], pa.int32()), pa.array(ids, pa.binary()), pa.array(places, pa.binary()), pa.array(ends, pa.list_(pa.int32())), pa.array(owners, pa.list_(arrow_kind)), pa.array(starts, pa.list_(pa.int64()))], names)
            number += len(rows)
            held = 0
            whole.clear()
            rests.clear()
            return out

        for table in batches:
            arrow_kind = table.column(0).type
            for name, text in zip(table.column(0).to_pylist(), table.column(1), strict=True):
                ids = np.append(encode(text.as_py(), vocabulary), np.uint32(end_id)).astype(dtype)
                cut = len(ids) // width * width
                whole += [[(name, at, ids[at : at + width])] for at in range(0, cut, width)]
                if cut < len(ids):
                    rests.append((name, cut, ids[cut:]))
                held += len(ids)
                if held >= window_tokens:
                    yield flush()
        if held:
            yield flush()

    return docs.select(id_col, "text").mapInArrow(run, schema)


def write_matrices(packed: DataFrame, path: str) -> None:
    """The packed rows as Parquet files at any path that Spark writes to."""
    packed.write.parquet(path)


def matrix(rows: list, width: int, id_bytes: int = 2) -> tuple[np.ndarray, np.ndarray]:
    """The id and position matrices of some collected rows."""
    dtype = np.dtype(f"<u{id_bytes}")
    join = lambda name: np.frombuffer(b"".join(bytes(r[name]) for r in rows), dtype).reshape(len(rows), width)
    return join("input_ids"), join("position_ids")
