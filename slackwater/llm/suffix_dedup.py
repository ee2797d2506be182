"""Suffix-array dedup with run-length indexes: removes what a long byte string repeats that starts earlier.

1. Phrases. Every window of `length` bytes has an anchor, its least 32-byte gram by hash, so equal windows have equal
   anchors at equal places. Consecutive windows of one anchor form a phrase; its content and place make a name. A task
   drops its own repeats, found by name and compared byte by byte, before rows are dealt out by anchor, so a passage in
   a third of all documents is one row from each task. Anchors that a sample shows in many different phrases (the edge
   of such a passage) give their windows one by one, dealt out by a hash of all their bytes.
2. Indexes. The phrases of an anchor that has more than one go, with their bytes, to the shard of the anchor. A shard
   builds the run-compressed Burrows-Wheeler transform of its phrases and keeps what the ends of runs say: the place
   before and after each in the order of suffixes, and how long they match. All else follows by steps from the nearest
   sample. It streams the matching statistic of every place, and where that is `length` or more, walks the equal places
   by the samples; all but the earliest are marks.
3. Marks meet their documents; covered bytes go.

Windows never cross documents. Hashes decide only what meets: marks rest on bytes. A shard reads its rows in the order
of anchors and works in blocks of bounded bytes; an anchor whose phrases exceed a block is split by the bytes around it,
which equal windows share.

Rows: a null text is empty (and comes back empty); rows equal in doc_id and text count as one document and share its result; rows with one
doc_id and different texts are ordered by a hash of the text; null doc_ids come first; an empty table gives no rows.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import lean, packed_bytes, scratch
from .simhash import ranges

GRAM = 32
FIRST = -(1 << 63)
"""Stands for a null doc_id in keys."""
_random = np.random.default_rng(20240229)
_BYTES = _random.integers(0, 1 << 63, 256, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_ODD = [np.uint64(x) for x in (0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0xD6E8FEB86659FD93, 0xA0761D6478BD642F)]


def gram_hashes(data: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of all 32-byte and of all 64-byte grams, by doubling."""
    h, size, out = _BYTES[data], 1, []
    while size < 64:
        h = h[:-size] * _ODD[0] + h[size:] * _ODD[1]
        h ^= h >> np.uint64(31)
        size *= 2
        if size >= 32:
            out.append(h * _ODD[3] ^ h >> np.uint64(29))
    return out[0], out[1]


def window_least(x: np.ndarray, width: int) -> np.ndarray:
    """The least of each `width` values in a row, by doubling."""
    size = 1
    while 2 * size <= width:
        x = np.minimum(x[:-size], x[size:])
        size *= 2
    return x if size == width else np.minimum(x[: len(x) - (width - size)], x[width - size :])


def phrases(data: np.ndarray, offsets: np.ndarray, length: int, hot: np.ndarray | None = None) -> tuple[np.ndarray, ...]:
    """Of texts laid end to end: text number, start in it, windows, place of the anchor, anchor hash and name.

    hot: sorted anchor hashes. Their windows come one by one, with a hash of the whole window in the place of the
    anchor's, so that only equal windows meet.
    """
    none = tuple(np.zeros(0, np.int64) for _ in range(4)) + (np.zeros(0, np.uint64), np.zeros(0, np.uint32))
    counts = np.maximum(np.diff(offsets) - length + 1, 0)
    if not counts.sum():
        return none
    h32, h64 = gram_hashes(data)
    at = np.arange(len(h32), dtype=np.uint64)
    low = np.uint64((1 << 24) - 1)
    anchor = (window_least(h32 & ~low | at, length - GRAM + 1) & low).astype(np.int64)
    starts = ranges(offsets[:-1][counts > 0], offsets[:-1][counts > 0] + counts[counts > 0])
    anchor = anchor[starts]
    first = np.flatnonzero(np.concatenate([[True], anchor[1:] != anchor[:-1]]))
    n = np.diff(np.concatenate([first, [len(starts)]]))
    a, q = starts[first], anchor[first]
    size = n + length - 1
    name = h64[a] * _ODD[0] + h64[a + (size - 64) // 2] * _ODD[1] + h64[a + size - 64] * _ODD[2] + n.astype(np.uint64) * _ODD[3] + (q - a).astype(np.uint64) * _ODD[4]
    name ^= name >> np.uint64(32)
    name *= _ODD[2]
    off, key, name = q - a, h32[q], (name >> np.uint64(32)).astype(np.uint32)
    if hot is not None and len(hot):
        warm = hot[np.minimum(np.searchsorted(hot, key), len(hot) - 1)] == key
        each = ranges(a[warm], a[warm] + n[warm])
        x, y = h64[each], h64[each + length - 64]
        w1, w2 = x * _ODD[3] + y * _ODD[4], x * _ODD[1] + y * _ODD[2]
        w1, w2 = (w1 ^ w1 >> np.uint64(29)) * _ODD[0], (w2 ^ w2 >> np.uint64(31)) * _ODD[3]
        whole = np.ones(len(each), np.int64)
        a, n, off, key, name = (np.concatenate([c[~warm], d]) for c, d in zip((a, n, off, key, name), (each, whole, 0 * whole, w1 ^ w1 >> np.uint64(32), (w2 >> np.uint64(32)).astype(np.uint32)), strict=True))
    text = np.searchsorted(offsets, a, side="right") - 1
    return text, a - offsets[text], n, off, key, name


def fill(names: list[str], kinds: list[pa.DataType], columns: list) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds, strict=True)], names=names)


@dataclass
class Rows:
    """Phrases as columns: key of the anchor, name, document, text hash, start, windows, place of the anchor."""

    key: np.ndarray
    name: np.ndarray
    doc: np.ndarray
    tie: np.ndarray
    start: np.ndarray
    n: np.ndarray
    off: np.ndarray

    def of(self, at: np.ndarray) -> Rows:
        return Rows(*(getattr(self, f)[at] for f in Rows.__annotations__))

    def ordered(self) -> np.ndarray:
        return np.lexsort((self.start, self.tie, self.doc, self.name, self.key))

    @staticmethod
    def join(parts: list[Rows]) -> Rows:
        return Rows(*(np.concatenate([getattr(p, f) for p in parts]) for f in Rows.__annotations__))

    def __len__(self) -> int:
        return len(self.key)


DEALT = "key long, name long, doc long, at long"


def dealt(rows: Rows) -> list[np.ndarray]:
    """Four longs: the name is joined by the text hash, the start by the other numbers."""
    return [rows.key.view(np.int64), (rows.name.astype(np.uint64) << np.uint64(32) | rows.tie.astype(np.uint64)).view(np.int64), rows.doc, rows.start << 16 | rows.n << 8 | rows.off << 1]


def spans(doc: np.ndarray, tie: np.ndarray, start: np.ndarray, n: np.ndarray) -> tuple[np.ndarray, ...]:
    """Joins marks that touch."""
    order = np.lexsort((start, tie, doc))
    doc, tie, start, n = doc[order], tie[order], start[order], n[order]
    new = np.concatenate([[True], (doc[1:] != doc[:-1]) | (tie[1:] != tie[:-1]) | (start[1:] != start[:-1] + n[:-1])]) if len(doc) else np.zeros(0, bool)
    first = np.flatnonzero(new)
    return doc[first], tie[first], start[first], np.add.reduceat(n, first) if len(first) else n


def equal_bytes(data: np.ndarray, a: np.ndarray, b: np.ndarray, size: np.ndarray, most: int = 1 << 20) -> np.ndarray:
    """Whether the `size` bytes at a and at b are the same, about `most` bytes at a time."""
    out, ends, i = np.ones(len(a), bool), np.cumsum(size), 0
    while i < len(a):
        j = max(i + 1, int(np.searchsorted(ends, (ends[i - 1] if i else 0) + most, side="right")))
        differ = data[ranges(a[i:j], a[i:j] + size[i:j])] != data[ranges(b[i:j], b[i:j] + size[i:j])]
        out[i:j] = ~np.logical_or.reduceat(differ, np.concatenate([[0], np.cumsum(size[i:j])[:-1]]))
        i = j
    return out


def find_phrases(length: int, hot: np.ndarray | None = None, block: int = 1 << 18, most: int = 1 << 20, held: int = 200_000):
    """Rows of DEALT for a partition of (doc, tie, text): its phrases without its own repeats, and marks for those.

    A mark has an odd `at`; its key is any number, so that marks are dealt out evenly.
    """

    def blocks(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple]:
        for batch in batches:
            doc, tie = (batch.column(c).to_numpy(zero_copy_only=False) for c in (0, 1))
            data, offsets = packed_bytes(batch.column(2))
            i = 0
            while i < len(doc):
                j = max(i + 1, int(np.searchsorted(offsets, offsets[i] + block, side="right")) - 1)
                if j == i + 1:  # one text, however long, in parts that share a window less one byte
                    for at in range(int(offsets[i]), max(int(offsets[j]) - length, int(offsets[i])) + 1, most):
                        end = min(int(offsets[j]), at + most + length - 1)
                        yield doc[i:j], tie[i:j], data[at:end], np.array([0, end - at]), at - int(offsets[i])
                else:
                    yield doc[i:j], tie[i:j], data[offsets[i] : offsets[j]], offsets[i : j + 1] - offsets[i], 0
                i = j

    def give(parts: list[tuple[Rows, np.ndarray, np.ndarray]]) -> Iterator[pa.RecordBatch]:
        """parts: phrases, where each begins, and the bytes that they begin in."""
        rows, data = Rows.join([p[0] for p in parts]), np.concatenate([p[2] for p in parts])
        begin = np.concatenate([p[1] + shift for p, shift in zip(parts, np.cumsum([0, *(len(p[2]) for p in parts)]), strict=False)])
        order = rows.ordered()
        rows, begin = rows.of(order), begin[order]
        again = np.concatenate([[False], (rows.key[1:] == rows.key[:-1]) & (rows.name[1:] == rows.name[:-1])])
        first = np.flatnonzero(~again)[np.cumsum(~again) - 1]
        at = np.flatnonzero(again)
        again[at] = equal_bytes(data, begin[at], begin[first[at]], rows.n[at] + length - 1)
        # a row that is there twice (equal doc_id and text) is no copy of itself
        same = np.concatenate([[False], (rows.doc[1:] == rows.doc[:-1]) & (rows.tie[1:] == rows.tie[:-1]) & (rows.start[1:] == rows.start[:-1])])
        yield fill(["key", "name", "doc", "at"], [pa.int64()] * 4, dealt(rows.of(~again)))
        doc, tie, start, n = spans(*(x[again & ~same] for x in (rows.doc, rows.tie, rows.start, rows.n)))
        mixed = (start.astype(np.uint64) * _ODD[0] + doc.view(np.uint64) * _ODD[1]).view(np.int64)
        yield fill(["key", "name", "doc", "at"], [pa.int64()] * 4, [mixed, n << 32 | tie, doc, start << 16 | 1])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        parts, count = [], 0
        for doc, tie, data, offsets, shift in blocks(batches):
            text, start, n, off, key, name = phrases(data, offsets, length, hot)
            if len(text):
                parts.append((Rows(key, name, doc[text], tie[text], start + shift, n, off), offsets[text] + start, data))
                count += len(text)
            if count >= held:
                yield from give(parts)
                parts, count = [], 0
        if parts:
            yield from give(parts)

    return run


def key_groups(batches: Iterator[pa.RecordBatch], most: int) -> Iterator[pa.Table]:
    """Rows that come in the order of the column key, as tables of about `most` bytes that hold all rows of their keys."""
    held, size = [], 0
    for batch in batches:
        if not batch.num_rows:
            continue
        key = batch.column("key").to_numpy(zero_copy_only=False)
        if held and size >= most and key[0] != held[-1].column("key")[-1].as_py():
            yield pa.Table.from_batches(held)
            held, size = [], 0
        if size + batch.nbytes >= most and key[0] != key[-1]:  # up to where its last key begins
            cut = int(np.flatnonzero(key != key[-1])[-1]) + 1
            yield pa.Table.from_batches([*held, batch.slice(0, cut)])
            batch, held, size = batch.slice(cut), [], 0
        held.append(batch)
        size += batch.nbytes
    if held:
        yield pa.Table.from_batches(held)


NOTES = "doc long, tie long, start long, n long, off long, key long"
"""off: the place of the anchor, and above it, from bit 8 on, the name."""


def settle(batches: Iterator[pa.RecordBatch], most: int = 1 << 24) -> Iterator[pa.RecordBatch]:
    """Rows of NOTES for dealt phrases in the order of keys: marks (key null), and phrases that need an index."""
    names, kinds = ["doc", "tie", "start", "n", "off", "key"], [pa.int64()] * 6
    for table in key_groups(batches, most):
        key, name, doc, at = (table.column(k).to_numpy() for k in range(4))
        tie, mark = name & 0xFFFFFFFF, at & 1 == 1
        found = spans(doc[mark], tie[mark], at[mark] >> 16, name[mark] >> 32)
        yield fill(names, kinds, [*found, np.zeros(len(found[0]), np.int64), pa.nulls(len(found[0]), pa.int64())])
        key, name, doc, tie, at = (x[~mark] for x in (key, name, doc, tie, at))
        twin = np.concatenate([[False], key[1:] == key[:-1]]) if len(key) else np.zeros(0, bool)
        asked = twin | np.concatenate([twin[1:], [False]]) if len(key) else twin  # anchors that are alone match nothing
        at = at[asked]
        yield fill(names, kinds, [doc[asked], tie[asked], at >> 16, at >> 8 & 255, (name[asked] >> 32 & 0xFFFFFFFF) << 8 | at >> 1 & 127, key[asked]])


class RunLengthIndex:
    """The run-compressed Burrows-Wheeler transform of phrases, each with an end of its own below all bytes.

    Rows are the sorted suffixes; row i is the empty suffix of phrase i. heads and begins are the runs' bytes (plus 1;
    0 before a phrase's start, always a run by itself) and first rows. A place is phrase * width + offset. In the order
    of places, up_from are the places of the runs' first rows, up_to the places of the rows before them and up_match
    how many bytes those two share; down_from are the places of the runs' last rows, down_to those of the rows after.
    These samples say the same of every other place: its neighbour is as far behind the neighbour of the nearest sample
    before it as it is behind that sample, and they share as many bytes less. Nothing is kept for each row.

    times: how often each phrase is there. Copies lengthen the runs; places are those of the first.
    """

    def __init__(self, data: np.ndarray, offsets: np.ndarray, length: int, times: np.ndarray | None = None):
        if length < 7:
            raise ValueError("length is 7 or more")
        self.length, self.size = length, np.diff(offsets)
        self.width = int(self.size.max(initial=0)) + 1
        rows, before = self._sorted(data)
        change = np.concatenate([[True], (before[1:] != before[:-1]) | (before[1:] == 0)])
        at = np.flatnonzero(change)
        ends = np.concatenate([[0], np.cumsum(np.ones(len(rows), np.int64) if times is None else times[rows // self.width])])
        self.rows, self.begins, self.heads = int(ends[-1]), ends[at], before[at]
        self.by_head = np.argsort(self.heads, kind="stable")  # the order in which what they begin is sorted
        first, last = rows[at], rows[np.append(at[1:], len(rows))[: len(at)] - 1]
        above = np.append(-1, last[:-1])  # the first row has none
        match = np.zeros(len(first), np.int64)
        match[1:] = self._common(data, offsets, first[1:], above[1:])
        order = np.argsort(first)
        self.up_from, self.up_to, self.up_match = first[order], above[order], match[order]
        order = np.argsort(last)
        self.down_from, self.down_to = last[order], np.append(first[1:], -1)[order]

    def _sorted(self, data: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The places of all rows, and the byte (plus 1) before each, by prefix doubling."""
        m = len(self.size)
        text = np.zeros((m, self.width + 7), np.uint16)
        inside = np.arange(self.width)[None, :] < self.size[:, None]
        text[:, : self.width][inside] = data.astype(np.uint16) + 1
        key = np.zeros((m, self.width), np.uint64)
        for j in range(7):
            key = key << np.uint64(9) | text[:, j : j + self.width]
        places = np.flatnonzero(inside.ravel())
        rank, depth, values = np.zeros((m, self.width), np.uint32), 7, key.ravel()[places]
        del key
        while True:
            order = np.argsort(values)
            ordered = values[order]
            number = np.cumsum(np.concatenate([[1], ordered[1:] != ordered[:-1]]), dtype=np.uint32) if len(order) else np.zeros(0, np.uint32)
            rank.ravel()[places[order]] = number
            if depth >= self.width or len(number) == 0 or number[-1] == len(number):
                break
            values, depth = self._pair(rank, depth).ravel()[places], 2 * depth
        # equal ends are in the order of their phrases
        order = np.argsort(rank.ravel()[places].astype(np.uint64) << np.uint64(32) | np.arange(len(places), dtype=np.uint64))
        rows = np.concatenate([np.arange(m) * self.width + self.size, places[order]])  # the empty suffixes come first
        before = text[:, : self.width].ravel()[rows - 1]
        before[rows % self.width == 0] = 0
        return rows, before

    def _common(self, data: np.ndarray, offsets: np.ndarray, a: np.ndarray, b: np.ndarray, step: int = 16) -> np.ndarray:
        """How many bytes two places share, at most to the end of the phrase that ends first."""
        most = np.minimum(self.size[a // self.width] - a % self.width, self.size[b // self.width] - b % self.width)
        a, b = offsets[a // self.width] + a % self.width, offsets[b // self.width] + b % self.width
        out, open_ = np.zeros(len(a), np.int64), np.flatnonzero(most > 0)
        ahead = np.arange(step)
        padded = np.append(data, np.zeros(step, np.uint8))
        while len(open_):
            at = out[open_]
            differ = padded[(a[open_] + at)[:, None] + ahead] != padded[(b[open_] + at)[:, None] + ahead]
            n = np.where(differ.any(axis=1), differ.argmax(axis=1), step)
            out[open_] = np.minimum(at + n, most[open_])
            open_ = open_[(n == step) & (at + step < most[open_])]
        return out

    def _pair(self, rank: np.ndarray, shift: int) -> np.ndarray:
        key = rank.astype(np.uint64) << np.uint64(32)
        if shift < self.width:
            key[:, : self.width - shift] |= rank[:, shift:].astype(np.uint64)
        return key

    def above(self, place: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The places of the rows before those of the given places, and how many bytes they share."""
        k = np.searchsorted(self.up_from, place, side="right") - 1
        behind = place - self.up_from[k]
        return np.where(self.up_to[k] < 0, -1, self.up_to[k] + behind), np.maximum(self.up_match[k] - behind, 0)

    def below(self, place: np.ndarray) -> np.ndarray:
        """The places of the rows after those of the given places; -1 after the last."""
        k = np.searchsorted(self.down_from, place, side="right") - 1
        return np.where(self.down_to[k] < 0, -1, self.down_to[k] + place - self.down_from[k])

    def statistics(self, place: np.ndarray) -> np.ndarray:
        """How long the text at each of the given places is found again at any other place."""
        after = self.below(place)
        return np.maximum(self.above(place)[1], np.where(after < 0, 0, self.above(np.maximum(after, 0))[1]))

    def stream(self) -> tuple[np.ndarray, np.ndarray]:
        """Phrase and offset of every place from which `length` bytes match an earlier place.

        Runs whose first row shares `length` bytes with the row before begin stretches of places that do. The rows of
        equal windows are walked from the first down, all such groups at once, and all but the earliest place count.
        """
        long = np.flatnonzero(self.up_match >= self.length)
        end = np.minimum(self.up_from[long] + self.up_match[long] - self.length + 1, np.append(self.up_from[1:], np.iinfo(np.int64).max)[long])
        linked = ranges(self.up_from[long], end)
        top, _ = self.above(linked)
        at = np.unique(top[self.above(top)[1] < self.length])
        group, least, seen = np.arange(len(at)), at.copy(), [(np.arange(len(at)), at)]
        while len(at):
            at = self.below(at)
            more = at >= 0
            more[more] = self.above(at[more])[1] >= self.length
            at, group = at[more], group[more]
            least[group] = np.minimum(least[group], at)
            seen.append((group, at))
        group, at = (np.concatenate(x) for x in zip(*seen, strict=True))
        found = np.sort(at[at != least[group]])
        return found // self.width, found % self.width

    def count(self, pattern: bytes) -> int:
        """How often the pattern occurs, by backward search over the runs."""
        lo, hi = 0, self.rows
        for byte in reversed(pattern):
            lo, hi = (self._before(byte + 1, x) for x in (lo, hi))
        return max(0, hi - lo)

    def _before(self, head: int, row: int) -> int:
        """Where the rows that start with head and go on with the suffixes before `row` end."""
        runs = self.by_head[np.searchsorted(self.heads[self.by_head], head) : np.searchsorted(self.heads[self.by_head], head, side="right")]
        lengths = np.diff(np.concatenate([self.begins, [self.rows]]))
        smaller = int(lengths[self.heads < head].sum())
        begins = self.begins[runs]
        return smaller + int(np.clip(row - begins, 0, lengths[runs]).sum())


def index_blocks(rows: Rows, data: np.ndarray, offsets: np.ndarray, length: int, most: int, times: np.ndarray) -> Iterator[tuple[Rows, np.ndarray, np.ndarray, np.ndarray]]:
    """Blocks of up to `most` bytes that hold all phrases of their anchors. rows are sorted by key, document and start;
    offsets say where in data each begins, times how often its bytes are there.

    An anchor with more than that is split. All its windows hold the anchor; those with much room before it also share
    what stands there with their equals, the others what stands after it: so windows are dealt by a hash of those
    bytes, which makes a longer anchor, until a part fits or nothing is left to tell windows apart.
    """
    held: list[tuple[np.ndarray, np.ndarray, np.ndarray]] = []  # rows, first window, windows
    size = 0

    def bytes_in(n: np.ndarray) -> int:
        return int((n + length - 1).sum())

    def cut() -> tuple[Rows, np.ndarray, np.ndarray, np.ndarray]:
        at, lo, n = (np.concatenate(x) for x in zip(*held, strict=True))
        begin = offsets[at] + lo
        part = rows.of(at)
        part.start, part.n = part.start + lo, n
        return part, data[ranges(begin, begin + n + length - 1)], np.concatenate([[0], np.cumsum(n + length - 1)]), times[at]

    def split(at: np.ndarray, lo: np.ndarray, n: np.ndarray, before: int, after: int) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
        """before, after: how far the common bytes reach around the start of the anchor."""
        room = length - before - after
        if bytes_in(n) <= most:
            yield at, lo, n
        elif room <= 0:  # all windows are equal: any two at a time will do, the first among them
            step = max(1, most // length - 1)
            for i in range(1, len(at), step):
                pick = np.concatenate([[0], np.arange(i, min(len(at), i + step))])
                yield at[pick], lo[pick], n[pick]
        else:
            left = (room + 1) // 2
            # windows that start at least before + left bytes ahead of the anchor
            ahead = np.clip(rows.off[at] - before - left - lo + 1, 0, n)
            for first, count, reach, take, new in ((lo, ahead, -before - left, left, (before + left, after)), (lo + ahead, n - ahead, after, room - left + 1, (before, after + room - left + 1))):
                has = count > 0
                if not has.any():
                    continue
                a, f, c = at[has], first[has], count[has]
                begin = offsets[a] + rows.off[a] + reach
                tell = data[begin[:, None] + np.arange(take)].astype(np.uint64) @ _BYTES[:take]
                order = np.argsort(tell, kind="stable")
                for part in np.split(order, np.flatnonzero(np.diff(tell[order])) + 1):
                    yield from split(a[part], f[part], c[part], *new)

    edges = np.concatenate([[0], np.flatnonzero(rows.key[1:] != rows.key[:-1]) + 1, [len(rows)]])
    for i, j in zip(edges[:-1].tolist(), edges[1:].tolist(), strict=True):
        at = np.arange(i, j)
        for part in split(at, np.zeros(len(at), np.int64), rows.n[at], 0, GRAM):
            if held and size + bytes_in(part[2]) > most:
                yield cut()
                held, size = [], 0
            held.append(part)
            size += bytes_in(part[2])
    if held:
        yield cut()


MARKS = "doc long, tie long, start long, n long"


def match(length: int, most: int = 1 << 20):
    """Marks for phrases with their bytes, in the order of keys.

    Of phrases with the same bytes the index sorts one, the first, and knows how many there are; the matching statistics
    of the others reach to their ends.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for table in key_groups(batches, most):
            key, doc, tie, start, n, off = (table.column(c).to_numpy() for c in ("key", "doc", "tie", "start", "n", "off"))
            data, offsets = packed_bytes(table.column("bytes"))
            rows = Rows(key, off >> 8, doc, tie, start, n, off & 255)
            order = rows.ordered()
            rows, begin = rows.of(order), offsets[:-1][order]
            known = np.concatenate([[False], (rows.key[1:] == rows.key[:-1]) & (rows.name[1:] == rows.name[:-1])])
            first = np.flatnonzero(~known)[np.cumsum(~known) - 1]
            at = np.flatnonzero(known)
            known[at] = (rows.n[at] == rows.n[first[at]]) & (rows.off[at] == rows.off[first[at]])
            at = np.flatnonzero(known)
            known[at] = equal_bytes(data, begin[at], begin[first[at]], rows.n[at] + length - 1)
            itself = known & (rows.doc == rows.doc[first]) & (rows.tie == rows.tie[first]) & (rows.start == rows.start[first])
            copies = rows.of(np.flatnonzero(known & ~itself))
            found = [(copies.doc, copies.tie, copies.start, copies.n)]
            times = np.bincount(first[known & ~itself], minlength=len(first)) + 1
            kept = np.flatnonzero(~known)
            kept = kept[np.lexsort((rows.start[kept], rows.tie[kept], rows.doc[kept], rows.key[kept]))]
            rows, begin, times = rows.of(kept), begin[kept], times[kept]
            alone = np.concatenate([[True], rows.key[1:] != rows.key[:-1]])
            several = ~(alone & np.concatenate([alone[1:], [True]]))  # what only has copies of itself matches nothing else
            rows, begin, times = rows.of(several), begin[several], times[several]
            for part, bytes_, ends, count in index_blocks(rows, data, begin, length, most, times) if len(rows) else ():
                phrase, place = RunLengthIndex(bytes_, ends, length, count).stream()
                found.append((part.doc[phrase], part.tie[phrase], part.start[phrase] + place, np.ones(len(phrase), np.int64)))
            yield fill(["doc", "tie", "start", "n"], [pa.int64()] * 4, spans(*(np.concatenate(x) for x in zip(*found, strict=True))))

    return run


ASKED = "doc long, tie long, start long, n long, off long, key long, bytes binary"


def take_bytes(length: int, most: int = 1 << 20):
    """The bytes of the phrases that a partition of (doc, tie, text, asked) is asked for, about `most` bytes at a time."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            data, offsets = packed_bytes(batch.column(2))
            asked = batch.column(3)
            flat = asked.flatten()
            at = np.repeat(np.arange(batch.num_rows), np.diff(np.asarray(asked.offsets)))
            start, n, off, key = (flat.field(c).to_numpy() for c in range(4))
            begin, size = offsets[at] + start, n + length - 1
            doc, tie = (batch.column(c).to_numpy()[at] for c in (0, 1))
            ends = np.concatenate([[0], np.cumsum(size)])
            i = 0
            while i < len(at):
                j = max(i + 1, int(np.searchsorted(ends, ends[i] + most, side="right")) - 1)
                chunk = pa.Array.from_buffers(pa.binary(), j - i, [None, pa.py_buffer((ends[i : j + 1] - ends[i]).astype(np.int32)), pa.py_buffer(np.ascontiguousarray(data[ranges(begin[i:j], begin[i:j] + size[i:j])]))])
                yield fill(["doc", "tie", "start", "n", "off", "key"], [pa.int64()] * 6, [x[i:j] for x in (doc, tie, start, n, off, key)]).append_column("bytes", chunk)
                i = j

    return run


def keyed(docs: DataFrame) -> DataFrame:
    """docs with the keys doc and tie, and no null text."""
    text = F.coalesce("text", F.lit(""))
    return docs.withColumns({"doc": F.coalesce("doc_id", F.lit(FIRST)).cast("long"), "tie": F.xxhash64(text).bitwiseAND(0xFFFFFFFF), "text": text})


def hot_anchors(texts: DataFrame, length: int, every: int = 64, least: int = 8, most: int = 10_000) -> np.ndarray:
    """The anchors, `most` at most, that have `least` different phrases or more among one in `every` of the texts. They
    are dealt out in another way, with the same results: which they are is a matter of balance alone."""
    some = texts.filter(F.pmod(F.xxhash64("tie", "doc"), F.lit(every)) == 0).mapInArrow(lean(find_phrases(length)), DEALT).filter("at % 2 = 0")
    names = some.groupBy("key").agg(F.countDistinct(F.shiftrightunsigned("name", 32)).alias("n")).filter(F.col("n") >= least)
    rows = names.orderBy(F.desc("n"), "key").limit(most).select("key").collect()
    return np.sort(np.array([r["key"] for r in rows], np.int64).view(np.uint64))


def repeats(docs: DataFrame, length: int = 100) -> DataFrame:
    """keyed(docs) with marked: the (start, n) of the windows of each text that match an earlier place, or null."""
    if not 64 <= length <= 112:
        raise ValueError("length is from 64 to 112: three grams of 64 bytes must cover a phrase")
    texts = keyed(docs)
    narrow = texts.select("doc", "tie", "text")
    notes = scratch(narrow.mapInArrow(lean(find_phrases(length, hot_anchors(narrow, length))), DEALT).repartition("key").sortWithinPartitions("key").mapInArrow(lean(settle), NOTES))
    asked = notes.filter("key is not null").groupBy("doc", "tie").agg(F.collect_list(F.struct("start", "n", "off", "key")).alias("asked"))
    # doc_id goes along so that both joins deal out the same rows, and Spark does it once
    found = texts.select("doc_id", "text", "doc", "tie").join(asked, ["doc", "tie"]).select("doc", "tie", "text", "asked", "doc_id")
    found = found.mapInArrow(lean(take_bytes(length)), ASKED).repartition("key").sortWithinPartitions("key").mapInArrow(lean(match(length)), MARKS)
    marks = notes.filter("key is null").select("doc", "tie", "start", "n").unionByName(found)
    marks = marks.groupBy("doc", "tie").agg(F.collect_list(F.struct("start", "n")).alias("marked"))
    return texts.join(marks, ["doc", "tie"], "left")


def covered(marks, length: int) -> list[tuple[int, int]]:
    """The byte ranges that windows cover, joined and in order."""
    out: list[tuple[int, int]] = []
    for start, n in sorted(marks):
        end = start + n - 1 + length
        if out and start <= out[-1][1]:
            out[-1] = (out[-1][0], max(end, out[-1][1]))
        else:
            out.append((start, end))
    return out


MADE = T.StructType([T.StructField(n, t) for n, t in (("n_bytes", T.LongType()), ("n_removed", T.LongType()), ("n_spans", T.LongType()), ("kept_sha256", T.StringType()), ("kept_text", T.StringType()))])
TAKEN = ("doc", "tie", "marked", *MADE.names)


def dedup(docs: DataFrame, length: int = 100) -> DataFrame:
    """docs (doc_id, text and any others; those named as in TAKEN are replaced) with the columns MADE. kept_text leaves
    out what remains of characters that were cut in two; kept_sha256 is of the remaining bytes themselves."""
    kept = [c for c in docs.columns if c not in TAKEN]
    df = repeats(docs.select(*kept), length).select(*kept, "marked")
    text_at, marks_at = kept.index("text"), len(kept)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out: list[list] = [[] for _ in MADE]
            for text, marks in zip(batch.column(text_at), batch.column(marks_at), strict=True):
                rest = text.as_py()
                data = rest.encode("utf-8", "surrogatepass")
                n, gone = len(data), []
                if marks.is_valid and len(marks):
                    flat = marks.values
                    gone = covered(zip(flat.field(0).to_pylist(), flat.field(1).to_pylist(), strict=True), length)
                    ends = [0, *(x for span in gone for x in span), n]
                    data = b"".join(data[a:b] for a, b in zip(ends[::2], ends[1::2], strict=True))
                    rest = data.decode("utf-8", "ignore")
                for to, value in zip(out, (n, n - len(data), len(gone), hashlib.sha256(data).hexdigest(), rest), strict=True):
                    to.append(value)
            batch = batch.drop_columns("marked")
            for name, values in zip(MADE.names, out, strict=True):
                batch = batch.append_column(name, pa.array(values, pa.string() if name.startswith("kept") else pa.int64()))
            yield batch

    return df.mapInArrow(lean(run), T.StructType([*df.drop("marked").schema.fields, *MADE.fields]))
