"""Vector bin packing of examples into training sequences, by the dot-product heuristic.

A sequence has three limits at once: tokens, segments (examples or pieces of them) and
loss-bearing tokens. A bin takes, again and again, the waiting example that fits and has
the largest dot product of its demand with what the bin has left, both as shares of the
limits. With `cut`, an example may be cut anywhere; then the last gap of a bin is filled
by a piece of the example that would fit least badly, so only a bin whose segments or loss
run out before its tokens keeps padding, and a partition's last tokens go to sequences of
a power of two, which need no padding. Without `cut`, examples stay whole, and one beyond
a limit is an error of the caller's data, returned in a bin of its own.

Each partition packs its own rows with a bounded number waiting; nothing is shuffled.
Sequence numbers hold the partition number, so a rerun of a lost task gives the same rows.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .base import ship
from .tokens import VOCABULARY, encode

#: Sequences one partition can number.
SEQUENCES = 1 << 33


@dataclass(frozen=True)
class Limits:
    tokens: int = 2048
    segments: int = 256
    loss: int = 2048


@dataclass
class Piece:
    key: object
    start: int
    length: int


class VectorPacker:
    """Holds the waiting examples and yields full bins, each a list of pieces."""

    def __init__(self, limits: Limits, cut: bool, waiting: int = 1024):
        self.limits, self.cut, self.waiting = limits, cut, waiting
        self.scale = 1.0 / np.array([limits.tokens, limits.segments, limits.loss])
        self.need = np.zeros((2 * waiting, 3), np.int64)  # tokens, segments, loss of each slot
        self.keys: list = [None] * (2 * waiting)
        self.start = np.zeros(2 * waiting, np.int64)
        self.n = 0

    def add(self, key, tokens: int, loss: int) -> Iterator[list[Piece]]:
        if self.cut:
            start = 0
            step = min(self.limits.tokens, self.limits.loss)
            while tokens - start > step:
                yield [Piece(key, start, step)]
                start += step
            tokens, loss = tokens - start, max(0, loss - start)
        elif tokens > self.limits.tokens or loss > self.limits.loss:
            yield [Piece(key, 0, tokens)]
            return
        else:
            start = 0
        if self.n == len(self.keys):
            while self.n > self.waiting:
                yield self.bin()
        i = self.n
        self.need[i], self.keys[i], self.start[i] = (tokens, 1, loss), key, start
        self.n += 1

    def finish(self) -> Iterator[list[Piece]]:
        while self.n:
            yield self.bin()

    def bin(self) -> list[Piece]:
        left = np.array([self.limits.tokens, self.limits.segments, self.limits.loss])
        if self.cut and (total := int(self.need[: self.n, 0].sum())) < left[0]:
            left[0] = 1 << max(0, total.bit_length() - 1)
        pieces: list[Piece] = []
        while self.n and left.min() > 0:
            need = self.need[: self.n]
            fits = (need <= left).all(axis=1)
            if self.cut and left[1] == 1:
                fits &= need[:, 0] == left[0]
            if fits.any():
                i = int(np.where(fits, (need * self.scale) @ (left * self.scale), -1).argmax())
                pieces.append(Piece(self.keys[i], int(self.start[i]), int(need[i, 0])))
                left -= need[i]
                self._remove(i)
            elif self.cut:
                gap = int(min(left[0], left[2]))
                long = need[:, 0] > gap
                i = int(np.where(long, need[:, 0], -1).argmax()) if long.any() else int(need[:, 0].argmax())
                take = min(gap, int(need[i, 0]))
                pieces.append(Piece(self.keys[i], int(self.start[i]), take))
                self.start[i] += take
                self.need[i, 0] -= take
                self.need[i, 2] = max(0, self.need[i, 2] - take)
                left -= np.array([take, 1, take])
                if not self.need[i, 0]:
                    self._remove(i)
            else:
                break
        return pieces

    def _remove(self, i: int) -> None:
        last = self.n - 1
        self.need[i], self.keys[i], self.start[i] = self.need[last], self.keys[last], self.start[last]
        self.keys[last], self.n = None, last


def pack_documents(docs: DataFrame, limits: Limits = Limits(), end_id: int = 1, vocabulary: str = VOCABULARY, waiting: int = 1024, id_col: str = "doc_id") -> DataFrame:
    """One row for each piece of each document; every token bears loss, and each document ends in `end_id`.

    A null or empty text is the end id alone. Columns: the id, start, length, ids_crc32 (of the
    piece's ids as little-endian unsigned 32-bit numbers), doc_tokens, sequence_id, offset.
    """
    ship(docs.sparkSession)
    kind = docs.schema[id_col].dataType
    schema = f"{id_col} {kind.simpleString()}, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"

    def run(batches):
        packer, number = VectorPacker(limits, True, waiting), TaskContext.get().partitionId() * SEQUENCES
        rows: list[tuple] = []

        def emit(pieces: list[Piece]) -> None:
            nonlocal number
            offset = 0
            for p in pieces:
                name, ids = p.key
                rows.append((name, p.start, p.length, zlib.crc32(ids[p.start : p.start + p.length].tobytes()), len(ids), number, offset))
                offset += p.length
            number += 1

        def batch() -> pa.RecordBatch:
            columns = list(zip(*rows, strict=True)) or [()] * 7
            rows.clear()
            return pa.record_batch([pa.array(columns[0], arrow_kind), *(pa.array(c, pa.int64()) for c in columns[1:])], names)

        names, arrow_kind = [id_col, "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset"], None
        for table in batches:
            arrow_kind = table.column(0).type
            for name, text in zip(table.column(0).to_pylist(), table.column(1), strict=True):
                ids = np.append(encode(text.as_py(), vocabulary), np.uint32(end_id)).astype("<u4")
                for pieces in packer.add((name, ids), len(ids), len(ids)):
                    emit(pieces)
                if len(rows) >= 10_000:
                    yield batch()
        for pieces in packer.finish():
            emit(pieces)
        if rows:
            yield batch()

    return docs.select(id_col, "text").mapInArrow(run, schema)


def pack_conversations(turns: DataFrame, limits: Limits = Limits(), loss_role: str = "assistant", end_id: int = 1, vocabulary: str = VOCABULARY) -> DataFrame:
    """Packs whole conversations (conv_id, turn, role, text); only the turns of `loss_role` bear loss.

    Each turn ends in `end_id`. One row for each conversation: conv_id, tokens, loss_tokens,
    sequence_id, offset, fits (false: alone in a sequence because it passes a limit).
    """
    ship(turns.sparkSession)
    kind = turns.schema["conv_id"].dataType.simpleString()

    def count(batches):
        for t in batches:
            n = [1 + len(encode(x.as_py(), vocabulary)) for x in t.column("text")]
            loss = [k if r == loss_role else 0 for k, r in zip(n, t.column("role").to_pylist(), strict=True)]
            yield pa.record_batch({"conv_id": t.column("conv_id"), "tokens": pa.array(n, pa.int64()), "loss_tokens": pa.array(loss, pa.int64())})

    def run(batches):
        packer, number = VectorPacker(limits, False), TaskContext.get().partitionId() * SEQUENCES
        rows: list[tuple] = []

        def emit(pieces: list[Piece]) -> None:
            nonlocal number
            offset = 0
            for p in pieces:
                conv, tokens, loss = p.key
                rows.append((conv, tokens, loss, number, offset, tokens <= limits.tokens and loss <= limits.loss))
                offset += tokens
            number += 1

        for t in batches:
            for key in zip(*(c.to_pylist() for c in t.columns), strict=True):
                for pieces in packer.add(key, key[1], key[2]):
                    emit(pieces)
        for pieces in packer.finish():
            emit(pieces)
        columns = list(zip(*rows, strict=True)) or [()] * 6
        types = [pa.int64()] * 5 + [pa.bool_()]
        yield pa.record_batch([pa.array(c, x) for c, x in zip(columns, types, strict=True)], ["conv_id", "tokens", "loss_tokens", "sequence_id", "offset", "fits"])

    counted = turns.select("conv_id", "role", "text").mapInArrow(count, f"conv_id {kind}, tokens long, loss_tokens long")
    whole = counted.groupBy("conv_id").agg(F.sum("tokens").alias("tokens"), F.sum("loss_tokens").alias("loss_tokens"))
    return whole.select(F.col("conv_id").cast("long"), "tokens", "loss_tokens").mapInArrow(run, "conv_id long, tokens long, loss_tokens long, sequence_id long, offset long, fits boolean")
