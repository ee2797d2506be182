"""Incremental queries: batches make states, states merge, merged states finish into answers."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources.tables import STREAM_KEYS, last_key, new_folder, slot_range, table

Frames = dict[str, DataFrame]


@dataclass(frozen=True)
class IncrementalQuery:
    """prepare: a batch of the streams and the static tables to a state, one row for each group of keys.

    merge says how each state column combines (sum, min, max, or distinct for sets of rows); finish turns the merged
    state into the answer, and alone may order, limit or divide. States are exact: sums are decimals or longs, so any
    split into batches gives the same answer.
    """

    name: str
    streams: tuple[str, ...]
    statics: tuple[str, ...]
    keys: tuple[str, ...]
    merge: dict[str, str]
    prepare: Callable[[Frames, Frames], DataFrame]
    finish: Callable[[DataFrame], DataFrame]

    def combine(self, states: DataFrame) -> DataFrame:
        states = states.select(*self.keys, *self.merge)
        if not self.merge:
            return states.distinct()
        kinds = dict(states.dtypes)
        how = {"sum": F.sum, "min": F.min, "max": F.max, "hll": F.hll_union_agg}
        return states.groupBy(*self.keys).agg(*(how[m](c).cast(kinds[c]).alias(c) for c, m in self.merge.items()))

    def one_shot(self, spark: SparkSession, sf_dir: str) -> DataFrame:
        streams = {s: table(spark, sf_dir, s) for s in self.streams}
        return self.finish(self.combine(self.prepare(streams, self.static_tables(spark, sf_dir))))

    def static_tables(self, spark: SparkSession, sf_dir: str) -> Frames:
        return {s: table(spark, sf_dir, s) for s in self.statics}


class StateStore:
    """States as parquet files, one folder for each query, level and batch. Writing a batch again replaces it, so a
    batch that is retried leaves the store as it was."""

    def __init__(self, spark: SparkSession, root: str | None = None):
        self.spark, self.root = spark, root or new_folder(spark)
        self.written: dict[tuple[str, int], list[int]] = {}

    def path(self, query: str, level: int, batch: int) -> str:
        return f"{self.root}/query_id={query}/level={level}/batch_no={batch}"

    def write(self, query: str, batch: int, level: int, state: DataFrame) -> None:
        state.write.mode("overwrite").parquet(self.path(query, level, batch))
        done = self.written.setdefault((query, level), [])
        if batch not in done:
            done.append(batch)

    def read(self, query: str, level: int, batches: list[int] | None = None) -> DataFrame:
        batches = self.written[query, level] if batches is None else batches
        return self.spark.read.parquet(*(self.path(query, level, b) for b in batches))

    def compact(self, query: IncrementalQuery, level: int, batches: list[int], to_batch: int) -> None:
        """Merges states of one level into a state of the next."""
        self.write(query.name, to_batch, level + 1, query.combine(self.read(query.name, level, batches)))


def premerge_points(n_batches: int, fraction: float) -> list[int]:
    """The batches (from 1) after which states are merged ahead; never the last one."""
    if not 0 < fraction < 1:
        return []
    step = fraction * n_batches
    points = {-(-round(k * step * 1e9) // 10**9) for k in range(1, int(1 / fraction) + 2)}
    return sorted(p for p in points if 0 < p < n_batches)


def run_batch(spark: SparkSession, sf_dir: str, query: IncrementalQuery, lo: int, hi: int, n_slots: int, last: int) -> DataFrame:
    """The state of slots lo to hi - 1. All streams are cut at the same keys, so partners are in the same batch."""
    streams = {s: slot_range(table(spark, sf_dir, s), STREAM_KEYS[s], lo, hi, n_slots, last) for s in query.streams}
    return query.combine(query.prepare(streams, query.static_tables(spark, sf_dir)))


def run_batched(spark: SparkSession, sf_dir: str, query: IncrementalQuery, cuts: list[int], n_slots: int, premerge: float | None = None, store: StateStore | None = None) -> DataFrame:
    """Runs a query in batches that end at the given slots, and merges once at the end or also ahead."""
    store, last = store or StateStore(spark), last_key(spark, sf_dir, query.streams[0])
    points, waiting, merged = premerge_points(len(cuts), premerge or 0), [], []
    for i, (lo, hi) in enumerate(zip([0, *cuts], cuts), 1):
        store.write(query.name, i, 0, run_batch(spark, sf_dir, query, lo, hi, n_slots, last))
        waiting.append(i)
        if i in points:  # only what came since the last merge
            store.compact(query, 0, waiting, i)
            merged.append(i)
            waiting = []
    parts = [store.read(query.name, 0, waiting)] if waiting else []
    parts += [store.read(query.name, 1, merged)] if merged else []
    states = parts[0]
    for more in parts[1:]:
        states = states.unionByName(more)
    return query.finish(query.combine(states))


def tree_merge(query: IncrementalQuery, store: StateStore, fan_in: int = 8) -> DataFrame:
    """Merges the states of a query level by level, fan_in at a time: no merge reads more than fan_in states."""
    level = 0
    while len(batches := store.written[query.name, level]) > fan_in:
        for k in range(0, len(batches), fan_in):
            store.compact(query, level, batches[k : k + fan_in], k // fan_in + 1)
        level += 1
    return query.finish(query.combine(store.read(query.name, level)))
