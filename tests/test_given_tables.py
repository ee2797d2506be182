"""Planner queries read the given tables: whole, in Spark's tasks, and their answers follow what is in them."""

from collections import Counter
from datetime import datetime, timedelta

import pytest
from slackwater import registry
from slackwater.experiments import plan_queries
from slackwater.plans import sizing
from slackwater.plans.model import Arrivals, Tariff
from slackwater.workloads import specs as cases


def reads(spark, sf, name):
    return {path.rsplit("/", 1)[1] for path in registry.QUERIES[name](spark, sf).inputFiles()}


def count(spark, sf, table):
    return spark.read.parquet(f"{sf}/{table}.parquet").count()


def test_array_plan_has_all_lines(spark, sf):
    assert reads(spark, sf, "array_plan") == {"lineitem.parquet"}
    assert sum(r.units for r in registry.QUERIES["array_plan"](spark, sf).collect()) == count(spark, sf, "lineitem")


def days(spark, sf):
    return {str(r.day) for r in spark.read.parquet(f"{sf}/events.parquet").selectExpr("to_date(ts) as day").distinct().collect()}


def test_autoscale_timeline_has_every_day(spark, sf):
    assert reads(spark, sf, "autoscale_timeline") == {"events.parquet"}
    spans = {}
    for r in registry.QUERIES["autoscale_timeline"](spark, sf).collect():
        spans.setdefault(r.case_id, []).append((r.t_from, r.t_to, r.nodes))
    assert set(spans) == days(spark, sf)
    for rows in map(sorted, spans.values()):
        assert rows[0][0] == 0 and rows[-1][1] > cases.WINDOW / 2
        assert all(a[1] == pytest.approx(b[0]) and a[2] != b[2] for a, b in zip(rows, rows[1:], strict=False))
    assert len({tuple(x) for x in spans.values()}) > 1  # days differ


def test_counted_arrivals():
    found = Arrivals.counted({1: 3, 4: 1}, 4, 40.0, 8)
    assert found.knots == ((0.0, 0.0), (10.0, 6.0), (20.0, 6.0), (30.0, 6.0), (40.0, 8.0))
    assert (found.when(6), found.when(7), found.when(8), found.total) == (10.0, 35.0, 40.0, 8.0)


def test_backward_plans_take_all_events(spark, sf):
    assert reads(spark, sf, "backward_example") == {"events.parquet"}
    plans = {}
    for r in registry.QUERIES["backward_example"](spark, sf).collect():
        plans.setdefault((r.day, r.event_type, r.config), []).append(r)
    events = spark.read.parquet(f"{sf}/events.parquet").selectExpr("cast(to_date(ts) as string) as day", "event_type").groupBy("day", "event_type").count().collect()
    n = {(r["day"], r["event_type"]): r["count"] for r in events}
    assert all(sum(r.units for r in rows) == n[key[:2]] for key, rows in plans.items())
    assert all(r.start >= 0 and r.money == {2: 6.0, 4: 7.5}[r.config] for rows in plans.values() for r in rows)
    assert {key[:2] for key in plans if key[2] == 4} == set(n)


def test_base_sizes_of_all_suppliers(spark, sf):
    assert reads(spark, sf, "base_size_grid") == {"lineitem.parquet"}
    found = registry.QUERIES["base_size_grid"](spark, sf).collect()
    assert sum(r.total for r in found) == count(spark, sf, "lineitem")
    laws = [s.law for s in cases.thirteen()]
    assert all(r.base_units == sizing.base_size(r.total, laws[r.l_suppkey % 13]) for r in found)


def test_batch_sizes_of_all_suppliers(spark, sf):
    assert reads(spark, sf, "batch_size_grid") == {"lineitem.parquet"}
    found = registry.QUERIES["batch_size_grid"](spark, sf).collect()
    assert sum(r.total for r in found if r.factor == 1) == count(spark, sf, "lineitem")
    assert all((r.n_batches - 1) * r.batch_units < r.total <= r.n_batches * r.batch_units for r in found)


def test_batched_times_of_all_lines(spark, sf):
    assert reads(spark, sf, "batched_time_grid") == {"lineitem.parquet"}
    found = registry.QUERIES["batched_time_grid"](spark, sf).collect()
    assert sum(r.units for r in found if (r.share, r.procs) == (1.0, 1)) == count(spark, sf, "lineitem")
    assert all(r.seconds == pytest.approx(((1 - r.share) + r.share / r.procs) * 0.12 * r.units + 8.75, abs=1e-6) for r in found)


def test_bills_of_all_users(spark, sf):
    assert reads(spark, sf, "bill_timeline") == {"events.parquet"}
    holds = {}
    for r in sorted(spark.read.parquet(f"{sf}/events.parquet").collect(), key=lambda r: r.ts):
        begin = (r.ts - datetime(2024, 1, 1)) // timedelta(seconds=1)
        held = holds.setdefault(r.user_id, {})
        held[begin] = max(held.get(begin, 0), 1 + int(r.value // 50))
    wanted = {}
    for user, held in holds.items():
        spans = []
        for a, b in zip(sorted(held), [*sorted(held)[1:], float("inf")], strict=True):
            spans += [(a, min(b, a + 600), held[a])] + ([(a + 600, b, 0)] if a + 600 < b < float("inf") else [])
        wanted[user] = Tariff().bill(spans)
    found = {r.case_id: r.money for r in registry.QUERIES["bill_timeline"](spark, sf).collect()}
    assert found == {user: pytest.approx(paid, abs=1e-6) for user, paid in wanted.items()}


def day_specs(spark, sf):
    """The batches of each day as sizes of a query, all arrivals at the ends of slices."""
    rows = spark.read.parquet(f"{sf}/events.parquet").selectExpr("cast(to_date(ts) as string) as day", "cast(floor(hour(ts) / 2) as int) + 1 as slice").collect()
    found = {}
    for r in rows:
        found.setdefault(r.day, Counter())[r.slice] += 1
    return found


def day_run(counts, rung, since):
    """When the boosted end starts, and when all is merged."""
    one, clock, total, boosted = plan_queries.ONE, 0.0, sum(counts.values()), None
    for i, s in enumerate(sorted(counts), 1):
        clock = max(clock, s * 4500 / 12 / 8)
        boosted = clock if i == since else boosted
        clock += one.law.batch(rung if i >= since else 2, 4500 * counts[s] / total)
    return boosted, clock + one.law.merge(rung, len(counts))


def test_lattice_of_every_day(spark, sf):
    assert reads(spark, sf, "boost_lattice_single") == {"events.parquet"}
    counts, found = day_specs(spark, sf), registry.QUERIES["boost_lattice_single"](spark, sf).collect()
    assert len(found) == len({(r.day, r.rung, r.since) for r in found}) == sum(6 * len(c) for c in counts.values())
    assert all(r.feasible == (day_run(counts[r.day], r.rung, r.since)[1] <= plan_queries.DAY_DUE) for r in found)
    assert {r.feasible for r in found} == {True, False}


def test_boost_chosen_on_every_day(spark, sf):
    assert reads(spark, sf, "boost_chosen") == {"events.parquet"}
    wanted = {}
    for day, c in day_specs(spark, sf).items():
        tries = ((n, k) for n in plan_queries.LADDER[1:] for k in range(len(c), 0, -1))
        wanted[day] = next(((n, k) for n, k in tries if day_run(c, n, k)[1] <= plan_queries.DAY_DUE), None)
    found = {r.day: (r.nodes, r.since) for r in registry.QUERIES["boost_chosen"](spark, sf).collect()}
    assert found == {day: x for day, x in wanted.items() if x}


def test_caps_of_all_suppliers(spark, sf):
    assert reads(spark, sf, "cap_size_grid") == {"lineitem.parquet"}
    found = registry.QUERIES["cap_size_grid"](spark, sf).collect()
    assert sum(r.total for r in found) == count(spark, sf, "lineitem")
    laws = [s.law for s in cases.thirteen()]
    for r in found:
        seconds = lambda x, r=r: laws[r.l_suppkey % 13].batch(2, x)
        assert r.cap_units == 1 or seconds(r.cap_units) < seconds(r.total) / 2
        assert seconds(r.cap_units + 1) >= seconds(r.total) / 2 - 1e-9


def test_cost_ratio_of_every_day(spark, sf):
    assert reads(spark, sf, "cost_ratio") == {"events.parquet"}
    wanted = {}
    for day, c in day_specs(spark, sf).items():
        due, bill, ladder = plan_queries.DAY_DUE, Tariff().bill, plan_queries.LADDER
        ends = {n: day_run(c, n, 1)[1] for n in ladder}
        fixed = [bill([(0.0, ends[n], n)]) for n in ladder if ends[n] <= due]
        tries = ((n, *day_run(c, n, k)) for n in ladder for k in range(len(c), 0, -1))
        elastic = next((bill([(0.0, begin, 2), (begin, stop, n)]) for n, begin, stop in tries if stop <= due), None)
        if fixed and elastic:
            wanted[day] = pytest.approx(min(fixed) / elastic, abs=1e-6)
    assert {r.case_id: r.ratio for r in registry.QUERIES["cost_ratio"](spark, sf).collect()} == wanted != {}


def test_deadline_first_plan_of_every_day(spark, sf):
    assert reads(spark, sf, "deadline_first_plan") == {"events.parquet"}
    rows = spark.read.parquet(f"{sf}/events.parquet").selectExpr("cast(to_date(ts) as string) as day", "event_type", "hour(ts) + 1 as slice").collect()
    counts, plans = {}, {}
    for r in rows:
        counts.setdefault(r.day, {}).setdefault(r.event_type, Counter())[r.slice] += 1
    for r in registry.QUERIES["deadline_first_plan"](spark, sf).collect():
        plans.setdefault(r.case_id, []).append(r)
    assert set(plans) == set(counts)
    for day, plan in plans.items():
        plan, clock, left = sorted(plan, key=lambda r: r.seq), 0.0, dict.fromkeys(counts[day], 240)
        due = {s.query_id: s.deadline for s in cases.measured(dict.fromkeys(left))}
        for r in plan:
            c, done = counts[day][r.query_id], 240 - left[r.query_id] + r.units
            there = sum(n for s, n in c.items() if s * 10 <= r.start) + c[int(r.start // 10) + 1] * (r.start % 10) / 10
            assert done <= there * 240 / sum(c.values()) + 1e-4 and r.start == pytest.approx(max(clock, r.ready), abs=1e-5)
            left[r.query_id], clock = left[r.query_id] - r.units, r.end
            assert left[r.query_id] == r.pending_after
            ready = [x.query_id for x in plan[r.seq + 1 :] if x.ready <= r.start - 1e-5]
            assert all(due[r.query_id] <= due[q] for q in ready)
        assert not any(left.values())
