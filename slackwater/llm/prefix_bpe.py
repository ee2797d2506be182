"""Byte-level BPE by prefix dynamic programming.

For each prefix of a byte string, the encoding of that prefix ends in exactly one token. Token t may end a prefix if
it follows the last token p of the shorter prefix without change, that is if p and t, joined, encode to p and t again.
Storing that last token for each prefix makes appends exact (go on from the table) and lets the encoding be read
backward from any prefix. Texts are first cut by the pre-token pattern; pre-tokens never share tokens, so an edit
re-encodes only the pre-tokens that it touches.

Rows: a null text is empty; the empty text has no ids; repeated rows are encoded each; other columns are ignored.
"""

from __future__ import annotations

import hashlib
from bisect import bisect_left
from collections.abc import Iterator
from functools import lru_cache

import pyarrow as pa
import regex
from pyspark.sql import DataFrame

from .common import lean, ranks_of

SCHEMA = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string"


class PrefixEncoder:
    """Tables of last tokens over a vocabulary of byte ranks. kept: how many pairs and pre-tokens memory may hold."""

    def __init__(self, ranks: dict[bytes, int], kept: int = 800_000, shared: int = 10):
        self.ranks, self.kept, self.shared = ranks, kept, shared
        self.tails: dict[bytes, bytes] = {}  # the last token of each short prefix
        self.bytes_of = {i: b for b, i in ranks.items()}
        self.longest = max(map(len, ranks))
        self.sound: dict[bytes, bool] = {}
        self.split: dict[bytes, tuple[bytes, bytes] | None] = {}
        self.pairs: dict[tuple[bytes, bytes], bool] = {}
        self.known: dict[bytes, tuple[int, str, bytes]] = {}

    def merged(self, data: bytes, until: int = 1) -> list[bytes]:
        """Plain merging of the lowest rank first, until so many parts are left: the last merge of a token shows how
        it splits."""
        parts = [data[i : i + 1] for i in range(len(data))]
        while len(parts) > until:
            best, at = min((self.ranks.get(parts[i] + parts[i + 1], 1 << 60), i) for i in range(len(parts) - 1))
            if best == 1 << 60:
                break
            parts[at : at + 2] = [parts[at] + parts[at + 1]]
        return parts

    def halves(self, token: bytes) -> tuple[bytes, bytes] | None:
        """The two parts whose merge makes the token; None for a single byte."""
        if token not in self.split:
            self.split[token] = tuple(self.merged(token, 2)) if len(token) > 1 else None
        return self.split[token]

    def stands(self, token: bytes) -> bool:
        """Whether a token's bytes encode to that token."""
        good = self.sound.get(token)
        if good is None:
            good = self.sound[token] = self.merged(token) == [token]
        return good

    def follows(self, last: bytes, token: bytes) -> bool:
        """Whether last and token side by side stay as they are.

        Undoes the merges next to the border, latest first. They stay if no pair of parts that ever met at the border
        would have merged before the parts grew on.
        """
        key = (last, token)
        good = self.pairs.get(key)
        if good is not None:
            return good
        if len(self.pairs) >= self.kept:
            self.pairs.clear()
        ranks, a, b, good = self.ranks, last, token, True
        before, tie = 1 << 60, True  # the merge that was undone last; a tie of ranks goes to the left place
        while True:
            across = ranks.get(a + b)
            if across is not None and (across < before or across == before and tie):
                good = False
                break
            left, right = self.halves(a), self.halves(b)
            if left is None and right is None:
                break
            if right is None or left is not None and ranks[a] > ranks[b]:
                before, tie, a = ranks[a], False, left[1]
            else:
                before, tie, b = ranks[b], True, right[0]
        self.pairs[key] = good
        return good

    def extend(self, data: bytes, table: list[bytes]) -> list[bytes]:
        """Goes on with the table of last tokens until it covers all prefixes of data; table[i] ends prefix i + 1."""
        ranks, longest, stands, follows, pairs = self.ranks, self.longest, self.stands, self.follows, self.pairs
        for end in range(len(table) + 1, len(data) + 1):
            for start in range(max(0, end - longest), end):
                token = data[start:end]
                if token in ranks:
                    if not start:
                        good = stands(token)
                    elif (good := pairs.get((table[start - 1], token))) is None:
                        good = follows(table[start - 1], token)
                    if good:
                        table.append(token)
                        break
            else:
                raise ValueError(f"no token ends {data[:end]!r}")
        return table

    def read(self, table: list[bytes], end: int | None = None) -> list[int]:
        """The ids of the prefix of `end` bytes, from the last one backward."""
        out, at = [], len(table) if end is None else end
        while at:
            out.append(self.ranks[table[at - 1]])
            at -= len(table[at - 1])
        return out[::-1]

    def table_of(self, data: bytes) -> list[bytes]:
        """The table of data; short prefixes, which many pre-tokens share, are looked up."""
        tails, table = self.tails, []
        for end in range(1, min(len(data), self.shared) + 1):
            last = tails.get(data[:end])
            if last is None:
                break
            table.append(last)
        known = len(table)
        self.extend(data, table)
        if len(tails) >= self.kept:
            tails.clear()
        for end in range(known + 1, min(len(data), self.shared) + 1):
            tails[data[:end]] = table[end - 1]
        return table

    def encode_piece(self, data: bytes) -> list[int]:
        if data in self.ranks and self.stands(data):
            return [self.ranks[data]]
        return self.read(self.table_of(data))

    def decode(self, ids: list[int]) -> bytes:
        return b"".join(self.bytes_of[i] for i in ids)

    def piece(self, text: str) -> tuple[int, str, bytes]:
        """How many ids a pre-token has, the ids in decimal, and the bytes that they decode to."""
        found = self.known.get(text)
        if found is None:
            if len(self.known) >= self.kept:
                self.known.clear()
            ids = self.encode_piece(text.encode())
            found = self.known[text] = (len(ids), " ".join(map(str, ids)), self.decode(ids))
        return found


class EditableText:
    """A text with its pre-tokens and their tables; appends and edits re-encode only what they touch."""

    def __init__(self, encoder: PrefixEncoder, pattern: str, text: str = ""):
        self.encoder, self.pattern, self.text = encoder, regex.compile(pattern), text
        self.starts: list[int] = []
        self.tables: list[list[bytes]] = []
        self.redone = 0  # pre-tokens encoded by the last call
        self._fill(0, len(text), 0)

    def _table(self, piece: str, old: str = "", table: list[bytes] | None = None) -> list[bytes]:
        self.redone += 1
        if table and piece.startswith(old):  # an append inside the pre-token goes on from its table
            return self.encoder.extend(piece.encode(), list(table))
        return self.encoder.extend(piece.encode(), [])

    def _fill(self, start: int, after: int, shift: int, old: str = "") -> None:
        """Re-cuts from a pre-token start until a cut past `after` meets an old one (old places are shifted)."""
        keep = bisect_left(self.starts, start)
        tail_starts, tail_tables = [s + shift for s in self.starts[keep:]], self.tables[keep:]
        self.starts, self.tables, self.redone = self.starts[:keep], self.tables[:keep], 0
        first, seen = tail_tables[0] if tail_tables else None, {s: i for i, s in enumerate(tail_starts) if s >= after}
        for m in self.pattern.finditer(self.text, start):
            if m.start() in seen and m.start() > start:
                i = seen[m.start()]
                self.starts += tail_starts[i:]
                self.tables += tail_tables[i:]
                return
            piece = m.group()
            self.tables.append(self._table(piece, old, first) if m.start() == start and old else self._table(piece))
            self.starts.append(m.start())

    def replace(self, start: int, stop: int, new: str) -> None:
        """Puts new in the place of the characters from start to stop."""
        keep = max(0, bisect_left(self.starts, start) - 1)
        # a match that ends where the edit starts may look at the first changed character
        while keep > 0 and self.starts[keep] >= start:
            keep -= 1
        at = self.starts[keep] if self.starts else 0
        old = self.text[at : self.starts[keep + 1] if keep + 1 < len(self.starts) else len(self.text)] if self.starts else ""
        self.text = self.text[:start] + new + self.text[stop:]
        self._fill(at, start + len(new), len(new) - (stop - start), old)

    def append(self, new: str) -> None:
        self.replace(len(self.text), len(self.text), new)

    def ids(self) -> list[int]:
        return [i for t in self.tables for i in self.encoder.read(t)]


@lru_cache(maxsize=2)
def encoder_of(path: str) -> PrefixEncoder:
    return PrefixEncoder(ranks_of(path))


def encode(docs: DataFrame, ranks: str, pattern: str) -> DataFrame:
    """Encodes and decodes every text of docs (doc_id, text); see SCHEMA."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder, cut = encoder_of(ranks), regex.compile(pattern)
        known, piece = encoder.known, encoder.piece
        for batch in batches:
            rows = []
            for doc, text in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                pieces = [known.get(w) or piece(w) for w in cut.findall(text.as_py() or "")]
                rows.append((doc, sum(p[0] for p in pieces), hashlib.sha256(" ".join([p[1] for p in pieces]).encode()).hexdigest(), hashlib.sha256(b"".join([p[2] for p in pieces])).hexdigest()))
            columns = list(zip(*rows, strict=True)) or [()] * 4
            yield pa.RecordBatch.from_arrays([pa.array(columns[0], pa.int64()), pa.array(columns[1], pa.int64()), pa.array(columns[2], pa.string()), pa.array(columns[3], pa.string())], names=["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    return docs.select("doc_id", "text").mapInArrow(lean(run), SCHEMA)
