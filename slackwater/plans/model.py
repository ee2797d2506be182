"""What the planner knows: queries, arrivals, time laws, the ladder of cluster sizes and the tariff."""

from __future__ import annotations

import bisect
import math
from dataclasses import dataclass, field, replace


@dataclass(frozen=True)
class Arrivals:
    """Cumulative units over time, linear between knots (time, units)."""

    knots: tuple[tuple[float, float], ...]

    @staticmethod
    def uniform(start: float, end: float, total: float) -> Arrivals:
        return Arrivals(((start, 0.0), (end, float(total))))

    @staticmethod
    def pieces(parts: list[tuple[float, float, float]]) -> Arrivals:
        """parts: (from, to, units a second), in order; nothing arrives between parts."""
        knots, units = [], 0.0
        for begin, end, rate in parts:
            if not knots or knots[-1][0] < begin:
                knots.append((float(begin), units))
            units += (end - begin) * rate
            knots.append((float(end), units))
        return Arrivals(tuple(knots))

    @staticmethod
    def counted(counts: dict[int, int], slices: int, window: float, units: float) -> Arrivals:
        """So many units over a window of equal slices, shared out as the counts of the slices, which start at 1."""
        total, knots, seen = sum(counts.values()), [(0.0, 0.0)], 0
        for i in range(1, slices + 1):
            seen += counts.get(i, 0)
            knots.append((window * i / slices, units * seen / total))
        return Arrivals(tuple(knots))

    @property
    def total(self) -> float:
        return self.knots[-1][1]

    def at(self, time: float) -> float:
        """Units that have arrived by a time."""
        i = bisect.bisect_right(self.knots, (time, math.inf))
        if i == 0:
            return 0.0
        if i == len(self.knots):
            return self.total
        (t0, u0), (t1, u1) = self.knots[i - 1], self.knots[i]
        return u0 + (u1 - u0) * (time - t0) / (t1 - t0) if t1 > t0 else u1

    def when(self, units: float) -> float:
        """The earliest time at which so many units have arrived; infinity if they never do."""
        if units <= self.knots[0][1]:
            return self.knots[0][0]
        if units > self.total + 1e-9:
            return math.inf
        i = bisect.bisect_left([u for _, u in self.knots], units - 1e-9)
        (t0, u0), (t1, u1) = self.knots[i - 1], self.knots[i]
        return t0 + (t1 - t0) * min(1.0, (units - u0) / (u1 - u0)) if u1 > u0 else t1

    def scaled(self, k: float) -> Arrivals:
        """k times the units in the same time."""
        return Arrivals(tuple((t, u * k) for t, u in self.knots))

    def sooner(self, k: float) -> Arrivals:
        """The same total, at k times the rate."""
        t0 = self.knots[0][0]
        return Arrivals(tuple((t0 + (t - t0) / k, u) for t, u in self.knots))


@dataclass(frozen=True)
class TimeLaw:
    """Seconds of a batch: b0 + bn * units + bnp * units / nodes + bp / nodes; of a merge: piecewise linear in the
    number of states, with m0 + ms * states + (mp0 + mp * states) / nodes on each segment (up to, m0, ms, mp0, mp)."""

    b0: float
    bn: float
    bnp: float
    bp: float = 0.0
    merges: tuple[tuple[float, float, float, float, float], ...] = ((math.inf, 0.0, 0.0, 0.0, 0.0),)

    def batch(self, nodes: int, units: float) -> float:
        return self.b0 + self.bn * units + (self.bnp * units + self.bp) / nodes

    def batches(self, nodes: int, units: float, count: int) -> float:
        return count * (self.b0 + self.bp / nodes) + units * (self.bn + self.bnp / nodes)

    def merge(self, nodes: int, states: int) -> float:
        if states <= 1:
            return 0.0
        _, m0, ms, mp0, mp = next(x for x in self.merges if states <= x[0])
        return m0 + ms * states + (mp0 + mp * states) / nodes

    def units_within(self, nodes: int, seconds: float) -> int:
        """The most whole units that a batch of so many seconds can hold."""
        rate = self.bn + self.bnp / nodes
        return max(0, math.floor((seconds - self.b0 - self.bp / nodes) / rate + 1e-9)) if rate > 0 else 0

    def with_session(self, seconds: float = 25.0) -> TimeLaw:
        """Every batch starts a session of its own."""
        return replace(self, b0=self.b0 + seconds)

    @staticmethod
    def planted(per_unit: float, share: float, overhead: float, merge_each: float = 0.0, merge_fixed: float = 0.0) -> TimeLaw:
        """A law whose work is parallel to the given share."""
        return TimeLaw(overhead, (1 - share) * per_unit, share * per_unit, 0.0, ((math.inf, merge_fixed * (1 - share), merge_each * (1 - share), merge_fixed * share, merge_each * share),))


@dataclass(frozen=True)
class QuerySpec:
    query_id: str
    window_start: float
    window_end: float
    deadline: float
    total: int
    law: TimeLaw
    arrivals: Arrivals | None = None
    streams: tuple[str, ...] = ()
    mode: str = "pessimistic"

    @property
    def arriving(self) -> Arrivals:
        return self.arrivals or Arrivals.uniform(self.window_start, self.window_end, self.total)


LADDER = (2, 4, 10, 14, 20, 24, 30)
"""Fixed values: workers of each configuration; the last two are beyond the measured ones."""


@dataclass(frozen=True)
class Tariff:
    """Dollars a node-hour for the instance and the service, the least seconds billed, and nodes that always run."""

    instance_h: float = 0.202
    service_h: float = 0.048
    min_s: float = 60.0
    fixed_nodes: int = 1

    @property
    def per_second(self) -> float:
        return (self.instance_h + self.service_h) / 3600

    def scaled(self, k: float) -> Tariff:
        """Another price of the instance, such as 0.28 for a savings plan that is 72 % lower."""
        return replace(self, instance_h=self.instance_h * k)

    def bill(self, timeline: list[tuple[float, float, int]]) -> float:
        """Money of (from, to, nodes) spans in order. Each node is billed from when it is acquired until it is
        released, min_s at least; the node acquired last is released first."""
        if not timeline:
            return 0.0
        since: list[float] = []
        seconds = 0.0
        for begin, _, nodes in timeline:
            while len(since) > nodes:
                seconds += max(self.min_s, begin - since.pop())
            since += [begin] * (nodes - len(since))
        end = timeline[-1][1]
        seconds += sum(max(self.min_s, end - s) for s in since)
        return (seconds + self.fixed_nodes * max(self.min_s, end - timeline[0][0])) * self.per_second


@dataclass
class Entry:
    """A batch of the plan. free is when the cluster is free again: after the final merge if this was the last batch."""

    query_id: str
    units: int
    ready: float
    start: float
    end: float
    free: float
    nodes: int
    pending: int
    laxity: float
    premerge_s: float = 0.0
    final: bool = False


@dataclass
class SimResult:
    feasible: bool
    entries: list[Entry] = field(default_factory=list)
    failed: str = ""
    failed_laxity: float = 0.0
    failed_start: float = 0.0
