"""Planner cases: a worked example, thirteen queries with staggered deadlines, ads, release and varying rates."""

from __future__ import annotations

from ..plans.model import Arrivals, QuerySpec, TimeLaw

UNITS, WINDOW = 4500, 4500.0
NAMES = ("tpch_q1", "tpch_q3", "tpch_q4", "tpch_q6", "tpch_q9", "tpch_q10", "tpch_q12", "tpch_q14", "tpch_q19", "custom_1", "custom_2", "custom_3", "custom_4")
# Planted laws: seconds a unit on one node, and a batch's overhead in units' worth of that on two nodes, from 10 to 114.
PER_UNIT = (0.1, 0.15, 0.115, 0.07, 0.175, 0.135, 0.12, 0.08, 0.09, 0.04, 0.075, 0.07, 0.045)
OVERHEAD = (30, 60, 40, 20, 114, 70, 10, 25, 35, 15, 50, 30, 15)
SHARE = 0.95
STAGGER = 0.5
"""Between deadlines, in times of the single batch on 20 nodes."""


def law(per_unit: float, overhead: float, merge_each: float = 0.05, merge_fixed: float = 2.0) -> TimeLaw:
    return TimeLaw.planted(per_unit, SHARE, overhead * per_unit * (1 - SHARE + SHARE / 2), merge_each, merge_fixed)


def thirteen(deadline: float = 1.0, rate: float = 1.0, arrivals: Arrivals | None = None, units: int = UNITS) -> list[QuerySpec]:
    """All queries over one window; deadlines are staggered by half of each query's single batch on 20 nodes, and
    shrink with `deadline`. rate: multiples of the units in the same window."""
    total, at, out = round(units * rate), WINDOW, []
    for name, per_unit, overhead in zip(NAMES, PER_UNIT, OVERHEAD, strict=True):
        x = law(per_unit, overhead)
        at += STAGGER * x.batch(20, units)
        out.append(QuerySpec(name, 0.0, WINDOW, WINDOW + (at - WINDOW) * deadline, total, x, arrivals.scaled(total / arrivals.total) if arrivals else None))
    return out


def small(count: int = 3, units: int = 240, deadline: float = 1.0) -> list[QuerySpec]:
    """A few of the thirteen with fewer units: quick to plan."""
    at, out = float(units), []
    for name, per_unit, overhead in list(zip(NAMES, PER_UNIT, OVERHEAD, strict=True))[:count]:
        x = law(4 * per_unit, overhead / 4)
        at += x.batch(20, units)
        out.append(QuerySpec(name, 0.0, float(units), units + (at - units) * deadline, units, x))
    return out


def measured(arrivals: dict[str, Arrivals], units: int = 240) -> list[QuerySpec]:
    """The queries of small(), one for each stream whose arrivals (of so many units) are given; laws go round."""
    at, out = float(units), []
    for i, name in enumerate(sorted(arrivals)):
        x = law(4 * PER_UNIT[i % len(NAMES)], OVERHEAD[i % len(NAMES)] / 4)
        at += x.batch(20, units)
        out.append(QuerySpec(name, 0.0, float(units), at, units, x, arrivals[name]))
    return out


def example() -> tuple[QuerySpec, QuerySpec]:
    """Twelve units, one a second from 1 to 12, due at 16: two units a second at 1, or four at 2.5 dollars a second."""
    first = Arrivals(((0.0, 0.0), (12.0, 12.0)))
    make = lambda rate: QuerySpec("example", 1.0, 12.0, 16.0, 12, TimeLaw(0.0, 1.0 / rate, 0.0), first)
    return make(2.0), make(4.0)


def ads(deadline: float = 1.0, rate: float = 1.0) -> list[QuerySpec]:
    x = law(0.1, 60)
    return [QuerySpec("ad_views", 0.0, 3750.0, 3750.0 + x.batch(20, 3750) * 4 * deadline, round(3750 * rate), x)]


def release(run: int) -> list[QuerySpec]:
    """Two queries with windows apart (run 1), or one whose window starts late (run 2)."""
    third = QuerySpec("tpch_q3", 0.0, 1000.0, 1040.0, 1000, law(0.6, 60))
    sixth = QuerySpec("tpch_q6", 1500.0, 2500.0, 2540.0, 1000, law(0.05, 20))
    return [third, sixth] if run == 1 else [sixth]


def profiles() -> dict[str, Arrivals]:
    """Rates over the window: even; two levels; slow, then a burst to the same total; a larger total; a late step."""
    return {
        "uniform": Arrivals.uniform(0.0, WINDOW, UNITS),
        "peak": Arrivals.pieces([(0, 1500, 0.5), (1500, 3000, 2.0), (3000, 4500, 0.5)]),
        "slow_burst": Arrivals.pieces([(0, 4200, 0.5), (4200, 4500, 8.0)]),
        "larger": Arrivals.pieces([(0, 3000, 2.0), (3000, 4500, 3.0)]),
        "late_step": Arrivals.pieces([(0, 3000, 1.0), (3000, 4500, 2.5)]),
    }
