"""Cost-balanced packing of token sequences.

A piece of n tokens costs linear * n + quadratic * n * n, as attention does. Pieces are taken in descending cost, and
each goes to the cheapest sequence that still has room for it; a piece that fits in none is cut to the room left in the
cheapest one. Every Spark partition packs its own rows in groups of a bounded number of sequences, so nothing is
shuffled, no group grows with the data, and a lost task is redone alone with the same result.

Rows: a null text is empty; every document ends with one id of its own, so even an empty text has a piece. Repeated
rows are packed each. An empty table gives no rows. Other columns are ignored.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame

from .common import lean, rank_encoding, token_ids

SCHEMA = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long, sequence_tokens long, sequence_cost double"


@dataclass(frozen=True)
class CostModel:
    linear: float = 1.0
    quadratic: float = 1.0 / 1024

    def of(self, lengths):
        return self.linear * lengths + self.quadratic * lengths * lengths


def room_sizes(total: int, room: int) -> np.ndarray:
    """Sequence lengths that hold total tokens without padding: full ones, then the powers of two of what is left."""
    left = total % room
    tail = [1 << b for b in range(left.bit_length() - 1, -1, -1) if left >> b & 1]
    return np.array([room] * (total // room) + tail, dtype=np.int64)


def balance(lengths: np.ndarray, rooms: np.ndarray, cost: CostModel) -> list[tuple[int, int, int, int, int]]:
    """Deals pieces of the given lengths to sequences whose rooms hold just as much in all.

    Returns (piece, from, length, sequence, offset) rows.
    """
    room, used, spent = rooms.astype(np.int64).copy(), np.zeros(len(rooms), np.int64), np.zeros(len(rooms))
    rows = []
    for i in np.argsort(-cost.of(lengths.astype(float)), kind="stable"):
        at, left = 0, int(lengths[i])
        while left:
            fits = np.where(room >= left, spent, np.inf)
            s = int(fits.argmin())
            if fits[s] == np.inf:  # no sequence has room for all of it
                s = int(np.where(room > 0, spent, np.inf).argmin())
            n = min(left, int(room[s]))
            rows.append((int(i), at, n, s, int(used[s])))
            room[s] -= n
            used[s] += n
            spent[s] += cost.of(float(n))
            at, left = at + n, left - n
    return rows


class Packer:
    """Takes documents one by one and gives out packed groups of at most `group` sequences."""

    def __init__(self, room: int, group: int, cost: CostModel, first_id: int):
        self.room, self.group, self.cost, self.next_id = room, group, cost, first_id
        self.pieces: list[tuple[object, int, int, np.ndarray]] = []  # document, start, its tokens, ids
        self.held = 0

    def add(self, doc: object, ids: np.ndarray) -> Iterator[list[tuple]]:
        for at in range(0, len(ids), self.room):
            self.pieces.append((doc, at, len(ids), ids[at : at + self.room]))
            self.held += len(self.pieces[-1][3])
            if self.held >= self.room * self.group:
                yield self.give(self.held // self.room * self.room)

    def give(self, total: int) -> list[tuple]:
        over, later = self.held - total, []
        while over:  # what is above whole sequences waits for the next group
            doc, at, n, ids = self.pieces.pop()
            cut = max(0, len(ids) - over)
            later.append((doc, at + cut, n, ids[cut:]))
            over -= len(ids) - cut
            if cut:
                self.pieces.append((doc, at, n, ids[:cut]))
        rooms = room_sizes(total, self.room)
        rows, spent = [], np.zeros(len(rooms))
        for i, at, n, s, offset in balance(np.array([len(p[3]) for p in self.pieces], dtype=np.int64), rooms, self.cost):
            doc, start, tokens, ids = self.pieces[i]
            rows.append((doc, start + at, n, zlib.crc32(ids[at : at + n].tobytes()), tokens, s, offset, int(rooms[s])))
            spent[s] += self.cost.of(float(n))
        rows = [(*r[:5], self.next_id + r[5], r[6], r[7], float(spent[r[5]])) for r in rows]
        self.next_id += len(rooms)
        self.pieces, self.held = later[::-1], sum(len(p[3]) for p in later)
        return rows

    def rest(self) -> list[tuple]:
        return self.give(self.held) if self.held else []


def as_batch(rows: list[tuple]) -> pa.RecordBatch:
    kinds = [pa.int64()] * 8 + [pa.float64()]
    names = [x.split()[0] for x in SCHEMA.split(", ")]
    return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)], names=names)


def pack(docs: DataFrame, ranks: str, pattern: str, room: int = 1024, end_id: int = 0, group: int = 1024, cost: CostModel = CostModel()) -> DataFrame:
    """Packs the texts of docs (doc_id, text); ranks is the path of the token ranks. See SCHEMA for the rows."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoding = rank_encoding(ranks, pattern)
        packer = Packer(room, group, cost, TaskContext.get().partitionId() << 40)
        for batch in batches:
            for doc, text in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                for rows in packer.add(doc, token_ids(encoding, text.as_py(), end_id)):
                    yield as_batch(rows)
        if rows := packer.rest():
            yield as_batch(rows)

    return docs.select("doc_id", "text").mapInArrow(lean(run), SCHEMA)
