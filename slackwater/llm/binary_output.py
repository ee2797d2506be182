"""Packed token-id matrices by best-fit decreasing.

Documents longer than a row are split without loss. Pieces go in descending length, each to the row whose free room is
least but enough; a segment tree over the free room finds it in logarithmic time. Rows come out as little-endian id
matrices with cumulative segment lengths and the places where positions restart. Each Spark partition packs groups of
a bounded number of pieces: no shuffle, bounded memory, and a lost task is redone alone.

Rows: a null text is empty and holds the closing id alone; repeated rows are packed each; an empty table gives no rows;
other columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import lean, rank_encoding, token_ids

SCHEMA = pa.schema([("sequence_id", pa.int64()), ("n_tokens", pa.int32()), ("n_padding", pa.int32()), ("doc_ids", pa.list_(pa.int64())), ("starts", pa.list_(pa.int64())), ("cu_seqlens", pa.list_(pa.int32())), ("position_resets", pa.list_(pa.int32())), ("ids", pa.binary())])
SPARK_SCHEMA = "sequence_id long, n_tokens int, n_padding int, doc_ids array<long>, starts array<long>, cu_seqlens array<int>, position_resets array<int>, ids binary"


class RoomTree:
    """Rows by their free room: the leaves are rooms 0 to size, the inner nodes count the rows below them."""

    def __init__(self, size: int):
        self.width = 1 << size.bit_length()
        self.count = [0] * (2 * self.width)
        self.rows: list[list[int]] = [[] for _ in range(size + 1)]

    def put(self, room: int, row: int) -> None:
        self.rows[room].append(row)
        at = room + self.width
        while at:
            self.count[at] += 1
            at >>= 1

    def take(self, least: int) -> tuple[int, int] | None:
        """Removes and returns (room, row) with the smallest room of at least `least`."""
        at = least + self.width
        if not self.count[at]:
            while at > 1 and (at & 1 or not self.count[at + 1]):
                at >>= 1
            if at <= 1:
                return None
            at += 1
            while at < self.width:
                at = 2 * at if self.count[2 * at] else 2 * at + 1
        room = at - self.width
        while at:
            self.count[at] -= 1
            at >>= 1
        return room, self.rows[room].pop()


def best_fit(lengths: list[int], room: int) -> list[list[int]]:
    """Rows of piece numbers; every length is between 1 and room."""
    tree, rows = RoomTree(room), []
    for i in sorted(range(len(lengths)), key=lambda i: -lengths[i]):
        if found := tree.take(lengths[i]):
            free, row = found
            rows[row].append(i)
        else:
            free, row = room, len(rows)
            rows.append([i])
        tree.put(free - lengths[i], row)
    return rows


def matrices(docs: DataFrame, ranks: str, pattern: str, room: int = 1024, end_id: int = 50256, pad_id: int = 0, group: int = 8192, width: str = "<u2") -> DataFrame:
    """One row for each packed sequence. ids: `room` ids of type `width`, padded with pad_id; starts: the place of each
    piece in its document; cu_seqlens: 0, then the end of each piece; position_resets: where positions start from 0."""

    def give(pieces: list[tuple[object, int, np.ndarray]], first_id: int) -> pa.RecordBatch:
        out: list[list] = [[] for _ in SCHEMA]
        for k, row in enumerate(best_fit([len(p[2]) for p in pieces], room)):
            ends = np.cumsum([0, *(len(pieces[i][2]) for i in row)]).tolist()
            ids = np.full(room, pad_id, dtype=width)
            ids[: ends[-1]] = np.concatenate([pieces[i][2] for i in row])
            for to, value in zip(out, (first_id + k, ends[-1], room - ends[-1], [pieces[i][0] for i in row], [pieces[i][1] for i in row], ends, ends[:-1], ids.tobytes()), strict=True):
                to.append(value)
        return pa.RecordBatch.from_arrays([pa.array(x, f.type) for x, f in zip(out, SCHEMA, strict=True)], schema=SCHEMA)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoding = rank_encoding(ranks, pattern)
        if np.iinfo(width).max < encoding.max_token_value:
            raise ValueError(f"{width} can't hold every id")
        pieces, next_id = [], TaskContext.get().partitionId() << 40
        for batch in batches:
            for doc, text in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                ids = token_ids(encoding, text.as_py(), end_id)
                pieces += [(doc, at, ids[at : at + room]) for at in range(0, len(ids), room)]
                while len(pieces) >= group:
                    yield (rows := give(pieces[:group], next_id))
                    next_id, pieces = next_id + len(rows), pieces[group:]
        if pieces:
            yield give(pieces, next_id)

    return docs.select("doc_id", "text").mapInArrow(lean(run), SPARK_SCHEMA)


def write_matrices(packed: DataFrame, path: str) -> None:
    """Parquet files of packed rows; the id matrix is the column ids, read back with numpy.frombuffer."""
    packed.write.mode("overwrite").parquet(path)


def digest(packed: DataFrame) -> DataFrame:
    """The packed rows with the padding fraction, for reports; ids stay as they are."""
    return packed.withColumn("fill", F.col("n_tokens") / (F.col("n_tokens") + F.col("n_padding")))
