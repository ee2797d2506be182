"""Runs a plan over real tables: batch by batch on a clock, states to the store, merges, answers."""

from __future__ import annotations

import time
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession

from ..plans.escalate import Plan
from ..plans.model import QuerySpec
from ..sources.tables import last_key
from .nodes import ResizeLedger
from .repository import IncrementalQuery, StateStore, premerge_points, run_batch

RUN_LOG = "query_id string, batch_no int, started double, ended double, lo int, hi int, nodes int, met boolean"


class VirtualClock:
    """Time that moves as told."""

    def __init__(self, now: float = 0.0):
        self.now = now

    def move_to(self, at: float) -> None:
        self.now = max(self.now, at)


class WallClock(VirtualClock):
    """Time that passes."""

    def __init__(self):
        self.began = time.monotonic()

    @property
    def now(self) -> float:
        return time.monotonic() - self.began

    def move_to(self, at: float) -> None:
        time.sleep(max(0.0, at - self.now))


@dataclass
class Dispatcher:
    """One batch at a time, in the order of the plan. Queries may join and leave between batches; then it plans again.

    plan_from(specs, done): a Plan for what is left. n_slots: the work units of every stream.
    """

    spark: SparkSession
    sf_dir: str
    queries: dict[str, IncrementalQuery]
    n_slots: int
    plan_from: object
    premerge: float | None = None
    clock: VirtualClock = field(default_factory=VirtualClock)
    ledger: ResizeLedger = field(default_factory=ResizeLedger)
    specs: dict[str, QuerySpec] = field(default_factory=dict)
    log: list[tuple] = field(default_factory=list)
    answers: dict[str, DataFrame] = field(default_factory=dict)
    replans: list[tuple[float, str]] = field(default_factory=list)

    def __post_init__(self):
        self.store = StateStore(self.spark)
        self.done: dict[str, int] = {}
        self.count: dict[str, int] = {}
        self.waiting: dict[str, list[int]] = {}
        self.merged: dict[str, list[int]] = {}
        self.plan: Plan | None = None
        self.last = {}

    def add_query(self, spec: QuerySpec) -> None:
        self.specs[spec.query_id] = spec
        self.done[spec.query_id], self.count[spec.query_id] = 0, 0
        self.waiting[spec.query_id], self.merged[spec.query_id] = [], []
        self._replan("query added")

    def remove_query(self, query_id: str) -> None:
        self.specs.pop(query_id)
        self._replan("query removed")

    def _replan(self, why: str) -> None:
        self.replans.append((self.clock.now, why))
        self.plan = self.plan_from(list(self.specs.values()), dict(self.done), self.clock.now) if self.specs else None

    def step(self) -> bool:
        """Runs the next batch of the plan; False when nothing is left."""
        if not self.specs or self.plan is None or not self.plan.entries:
            return False
        entry = self.plan.entries.pop(0)
        spec, query = self.specs[entry.query_id], self.queries[entry.query_id]
        idle = self.plan.entries[0].start if self.plan.entries else None
        self.ledger.want(self.clock.now, entry.nodes, idle)
        self.clock.move_to(entry.start)
        now = self.clock.now
        name, lo = query.name, self.done[spec.query_id]
        hi = min(self.n_slots, lo + entry.units)
        stream = query.streams[0]
        if stream not in self.last:  # one scan for each stream, not for each batch
            self.last[stream] = last_key(self.spark, self.sf_dir, stream)
        key = self.last[stream]
        self.count[name] += 1
        number = self.count[name]
        self.store.write(name, number, 0, run_batch(self.spark, self.sf_dir, query, lo, hi, self.n_slots, key))
        self.waiting[name].append(number)
        self.done[name] = hi
        if self.premerge and number in premerge_points(-(-spec.total // entry.units), self.premerge) and hi < self.n_slots:
            self.store.compact(query, 0, self.waiting[name], number)
            self.merged[name].append(number)
            self.waiting[name] = []
        started = max(entry.start, now)
        self.clock.move_to(started + entry.free - entry.start)
        if hi >= spec.total:
            parts = ([self.store.read(name, 0, self.waiting[name])] if self.waiting[name] else []) + ([self.store.read(name, 1, self.merged[name])] if self.merged[name] else [])
            states = parts[0] if len(parts) == 1 else parts[0].unionByName(parts[1])
            self.answers[name] = query.finish(query.combine(states))
            del self.specs[name]
        ended = self.clock.now
        self.log.append((name, number, started, ended, lo, hi, entry.nodes, ended <= spec.deadline + 1e-9))
        return True

    def run(self) -> dict[str, DataFrame]:
        while self.step():
            pass
        return self.answers

    def run_log(self) -> DataFrame:
        return self.spark.createDataFrame(self.log, RUN_LOG)
