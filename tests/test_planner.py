"""Laws, sizes, plans, escalation, trimming, sweep, rates, baselines."""

import itertools
import math
import random

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from slackwater.baselines import models
from slackwater.plans import backward, sizing, sweep
from slackwater.plans.escalate import attempt, escalate, lattice, next_start, timeline
from slackwater.plans.forward import Start, simulate
from slackwater.plans.model import Arrivals, QuerySpec, Tariff, TimeLaw
from slackwater.plans.trim import idle_gaps, idle_spans, long_gaps, no_input_spans, trim
from slackwater.run import rate
from slackwater.run.nodes import ResizeLedger
from slackwater.run.repository import premerge_points
from slackwater.workloads import specs as cases

LAWS = st.builds(TimeLaw, st.floats(0, 50), st.floats(0, 1), st.floats(0.01, 1), st.floats(0, 5))


@settings(max_examples=150, deadline=None)
@given(LAWS, st.integers(1, 500))
def test_base_size_is_the_least(law, n):
    fits = lambda x: -(-n // x) * law.batch(2, x) <= 2 * law.batch(2, n) * (1 + 1e-12)
    assert sizing.base_size(n, law) == next(x for x in range(1, n + 1) if fits(x))


@settings(max_examples=60, deadline=None)
@given(LAWS, st.floats(5, 500))
def test_cap_is_below_the_longest(law, longest):
    cap = sizing.cap_size(law, longest)
    assert cap == 1 or law.batch(2, cap) < longest
    assert law.batch(2, cap + 1) >= longest - 1e-6


def test_sizes_span_the_published_range():
    found = sizing.sizes(cases.thirteen(), 2)
    assert min(found.values()) == found["tpch_q12"] == 20
    assert max(found.values()) == found["tpch_q9"] and 200 <= found["tpch_q9"] <= 230


def test_worked_example():
    slow, fast = cases.example()
    a, b = backward.plan_backward(slow, 2, 1.0), backward.plan_backward(fast, 4, 2.5)
    assert (a.batches, a.seconds, a.money) == ([(10.0, 4), (12.0, 8)], 6.0, 6.0)
    assert (b.batches, b.seconds, b.money) == ([(13.0, 12)], 3.0, 7.5)


@settings(max_examples=60, deadline=None)
@given(st.integers(5, 400), st.floats(0.05, 3), st.floats(0, 5), st.floats(1, 200))
def test_backward_plans_hold(total, per_unit, overhead, slack):
    spec = QuerySpec("q", 0.0, float(total), total + slack, total, TimeLaw.planted(per_unit, 0.9, overhead, 0.1, 0.5))
    plan = backward.plan_backward(spec, 4, 1.0)
    if plan:
        done, free = 0, 0.0
        for start, units in plan.batches:
            done += units
            assert start >= spec.arriving.when(done) - 1e-6 and start >= free - 1e-6
            free = start + spec.law.batch(4, units)
        assert done == total and free + spec.law.merge(4, len(plan.batches)) <= spec.deadline + 1e-6


def naive(specs, size, nodes, policy="laxity"):
    """The same rules, looked at afresh for every batch."""
    left, done, clock, out = {s.query_id: s.total for s in specs}, {s.query_id: 0 for s in specs}, 0.0, []
    by_id = {s.query_id: s for s in specs}
    count = {s.query_id: -(-s.total // size[s.query_id]) for s in specs}
    while any(left.values()):
        choice = []
        for q, n in left.items():
            if n:
                s = by_id[q]
                ready = s.arriving.when(s.total - n + min(size[q], n))
                rest = sum(s.law.batch(nodes, min(size[q], n - k * size[q])) for k in range(-(-n // size[q]))) + s.law.merge(nodes, count[q])
                begin = max(clock, ready)
                order = s.deadline - begin - rest if policy == "laxity" else s.deadline
                choice.append(((0.0 if ready <= clock else ready), round(order, 9), q, begin, s.deadline - begin - rest))
        _, _, q, begin, laxity = min(choice)
        if laxity < -1e-9:
            return False, out
        units = min(size[q], left[q])
        left[q] -= units
        done[q] += 1
        clock = begin + by_id[q].law.batch(nodes, units)
        out.append((q, units, round(begin, 6)))
        if not left[q]:
            clock += by_id[q].law.merge(nodes, count[q])
    return True, out


@pytest.mark.parametrize("policy", ["laxity", "deadline"])
@pytest.mark.parametrize("nodes", [2, 4, 20])
def test_simulation_equals_naive_one(policy, nodes):
    for factor, d in itertools.product((1, 2, 4, 8), (1.0, 0.5)):
        s = cases.small(4, deadline=d)
        size = sizing.sizes(s, factor)
        found = simulate(s, size, nodes, Start.of(s), policy)
        assert (found.feasible, [(e.query_id, e.units, round(e.start, 6)) for e in found.entries]) == naive(s, size, nodes, policy)


def check_plan(plan, specs):
    done, free, end = {s.query_id: 0 for s in specs}, 0.0, {}
    by_id = {s.query_id: s for s in specs}
    for e in plan.entries:
        done[e.query_id] += e.units
        assert e.start >= by_id[e.query_id].arriving.when(done[e.query_id]) - 1e-6
        assert e.start >= free - 1e-9 and e.laxity >= -1e-9
        free = end[e.query_id] = e.free
    assert all(done[s.query_id] == s.total and end[s.query_id] <= s.deadline + 1e-6 for s in specs)


@pytest.mark.parametrize("reset", [True, False])
@pytest.mark.parametrize("stride", [1, 10])
def test_escalated_plans_hold(reset, stride):
    for d, f in itertools.product((1.0, 0.6, 0.4), (1, 2, 4, 8)):
        s = cases.small(4, deadline=d)
        plan = escalate(s, sizing.sizes(s, f), 2, stride=stride, reset_prefix=reset)
        if plan.feasible:
            check_plan(plan, s)


def test_lattice_order_equals_serial_search():
    for d, f in ((0.6, 8), (0.6, 4), (0.4, 2), (1.0, 16)):
        s = cases.small(4, deadline=d)
        size = sizing.sizes(s, f)
        plan = escalate(s, size, 2)
        base, tries = lattice(s, size, 2)
        if base.feasible:
            assert plan.passes == 1
            continue
        first = next(((n, at) for n, at in tries if attempt(s, size, base, n, at).feasible), None)
        assert plan.feasible == (first is not None)
        if first:
            assert [e.start for e in attempt(s, size, base, *first).entries] == [e.start for e in plan.entries]


def test_parallel_lattice(spark):
    s = cases.small(3, deadline=0.6)
    size = sizing.sizes(s, 8)
    plan = escalate(s, size, 2)
    assert not simulate(s, size, 2, Start.of(s)).feasible
    found = sweep.parallel_escalate(spark, s, size, 2)
    assert (found is not None) == plan.feasible and (not found or found[0] == plan.max_nodes)


def test_tiny_case_against_all_assignments():
    law = TimeLaw(1.0, 0.1, 2.0)
    s = [QuerySpec("a", 0.0, 6.0, 12.0, 6, law), QuerySpec("b", 0.0, 6.0, 15.0, 6, law)]
    size, ladder = {"a": 3, "b": 3}, (1, 2, 4)
    plan = escalate(s, size, 1, ladder)
    assert plan.feasible
    check_plan(plan, s)
    best = math.inf
    for rungs in itertools.product(ladder, repeat=4):
        state, entries, ok = Start.of(s), [], True
        for r in rungs:
            found = simulate(s, size, r, state.after(entries), strict=False)
            if not found.entries:
                break
            entries.append(found.entries[0])
        ends = {e.query_id: e.free for e in entries}
        ok = len(entries) == 4 and all(ends[x.query_id] <= x.deadline for x in s)
        if ok:
            best = min(best, Tariff().bill(timeline(entries, 1)))
    assert best <= plan.money + 1e-12 and plan.money <= 3 * best  # regret, not optimality


def test_stride():
    assert [next_start(a, 10) for a in (25, 10, 9, 1)] == [15, 0, 8, 0]


def test_trim_never_raises_money():
    for d, f in itertools.product((1.0, 0.6), (2, 4, 8, 16)):
        s = cases.small(4, deadline=d)
        size = sizing.sizes(s, f)
        plan = escalate(s, size, 2)
        after = trim(plan, s, size, 2)
        assert after.feasible == plan.feasible
        if plan.feasible:
            assert after.money <= plan.money + 1e-12
            check_plan(after, s)
            if plan.max_nodes == 2:
                assert [e.nodes for e in after.entries] == [e.nodes for e in plan.entries]


def test_idle_spans():
    s = cases.release(1)
    assert no_input_spans(s, 2600.0) == [(1000.0, 1500.0), (2500.0, 2600.0)]
    assert no_input_spans(s[1:], 2500.0) == [(0.0, 1500.0)]
    entries = escalate(s, sizing.sizes(s, 2), 2).entries
    assert idle_gaps(entries) and long_gaps(entries, 1.0)
    spans = idle_spans(s, entries)
    assert spans and all(1000 <= a < b <= 1500 for a, b in spans)
    assert min(n for _, _, n in timeline(entries, 2, 0.0, spans)) == 1


def test_elastic_is_never_dearer_than_fixed():
    for d in (1.0, 0.6):
        s = cases.small(4, deadline=d)
        fixed = [p.money for f in (2, 4, 8) for n in (2, 4, 10, 14, 20) if (p := models.fixed_nodes(s, f, n)).feasible]
        elastic = [p.money for f in (2, 4, 8) for n in (2, 4, 10, 14, 20) if (p := sweep.plan_cell(s, f, n, stride=1)).feasible]
        assert min(elastic) <= min(fixed) + 1e-9


def test_shape_of_the_published_tables():
    """Which factor wins, and how money and nodes move with rate and deadline."""
    cell = lambda d, f, n=2, k=1: sweep.plan_cell(cases.thirteen(d, k), f, n)
    assert cell(1.0, 2).max_nodes == 2 < cell(1.0, 1).max_nodes
    assert cell(1.0, 2).money < cell(1.0, 1).money
    assert [round(cell(1.0, 2, n).money, 2) for n in (2, 4, 10, 14, 20)] == sorted(round(cell(1.0, 2, n).money, 2) for n in (2, 4, 10, 14, 20))
    best = {k: min((p.money, f) for f in (2, 4, 8, 16, 32) if (p := cell(1.0, f, 2, k)).feasible) for k in (1, 2, 4)}
    assert best[1][0] < best[2][0] < best[4][0] and best[1][1] <= best[2][1]
    tight = min(p.money for f in (2, 4, 8) if (p := cell(0.3, f)).feasible)
    assert tight >= best[1][0] - 1e-9


def test_bill_by_hand():
    t = Tariff(instance_h=3600.0, service_h=0.0, min_s=60.0, fixed_nodes=1)
    assert t.bill([(0.0, 100.0, 2)]) == pytest.approx(300.0)
    assert t.bill([(0.0, 100.0, 2), (100.0, 110.0, 3), (110.0, 200.0, 2)]) == pytest.approx(600.0 + 60.0)
    assert t.bill([(0.0, 10.0, 1)]) == pytest.approx(120.0)
    assert Tariff().bill([(0.0, 4512.0, 2)]) == pytest.approx(0.94, abs=0.001)
    assert Tariff().scaled(0.28).bill([(0.0, 3600.0, 1)]) == pytest.approx(2 * (0.202 * 0.28 + 0.048))


def test_bill_frame_equals_plan_bill(spark):
    from slackwater.costs import money

    rnd = random.Random(4)
    spans, at = [], 0.0
    for _ in range(40):
        step = rnd.uniform(5, 200)
        spans.append((at, at + step, rnd.randint(1, 9)))
        at += step
    frame = spark.createDataFrame([("x", *s) for s in spans], "case_id string, t_from double, t_to double, nodes int")
    assert money.bill(frame).first()["money"] == pytest.approx(Tariff().bill(spans))


def test_headroom():
    s = cases.small(3)
    plan = sweep.plan_cell(s, 4, 4)
    room = rate.headroom(plan, s)
    assert room >= 1.0 and rate.holds(plan, s, room) and not rate.holds(plan, s, room + 0.05)


def test_revised_arrivals():
    a = Arrivals.uniform(0.0, 100.0, 100)
    assert rate.revise(a, 2.0, 50.0, "optimistic").total == 100 and rate.revise(a, 2.0, 50.0, "optimistic").when(100) == 75.0
    assert rate.revise(a, 2.0, 50.0, "pessimistic").total == 150 and rate.revise(a, 2.0, 50.0, "pessimistic").when(150) == 100.0
    assert rate.revise(a, 0.5, 50.0, "optimistic").total == 75
    assert rate.revise(a, 0.5, 50.0, "pessimistic").total == 100 and rate.revise(a, 0.5, 50.0, "pessimistic").when(100) == 150.0


def test_replanning_saves_the_deadlines():
    from slackwater.experiments.drivers import varying_rates

    class Rows:
        def createDataFrame(self, rows, schema):
            return rows

    found = {(r[0], r[1], r[2]): r for r in varying_rates(Rows())}
    for profile in ("slow_burst", "larger", "late_step"):
        assert found[profile, True, 0.0][4] == 0 and found[profile, True, 0.0][3] > 0
        assert found[profile, False, 0.0][4] == 13
    assert found["slow_burst", True, 360.0][4] > 0


def test_baselines_do_worse():
    s = cases.thirteen()
    plan = min((p for f in (2, 4, 8) if (p := sweep.plan_cell(s, f, 2)).feasible), key=lambda p: p.money)
    assert [len(models.unsized_laxity(s, n).missed) > 0 for n in (2, 4, 10)] == [True] * 3
    assert models.threshold_autoscale(s).money > 2 * plan.money
    assert models.micro_batch_model(s).money > 5 * plan.money
    late = models.single_batch(s)
    assert late is None or late.max_nodes >= 20
    assert models.smallest_fixed(s, [2, 4, 8]).money >= plan.money - 1e-9


def test_premerge_lowers_the_end():
    assert premerge_points(20, 0.25) == [5, 10, 15] and premerge_points(3, 0.25) == [1, 2] and premerge_points(1, 0.25) == []
    law = cases.law(0.2, 10, merge_each=1.0)
    s = [QuerySpec("q", 0.0, 400.0, 520.0, 400, law)]
    end = {f: simulate(s, {"q": 20}, 2, Start.of(s), premerge=f, strict=False).entries[-1].free for f in (None, 0.25)}
    assert end[0.25] < end[None]


def test_ledger():
    ledger = ResizeLedger(lead_s=360.0)
    ledger.want(0.0, 10)
    assert ledger.log[-1] == (0.0, 360.0, 0, 10, "add") and ledger.there(360.0) == 10
    ledger.want(500.0, 2, idle_until=1000.0)
    assert ledger.requested == 10
    ledger.want(500.0, 0, idle_until=1300.0)
    assert ledger.requested == ledger.fewest == 1


def test_edges():
    law = TimeLaw(1.0, 0.0, 1.0)
    one = [QuerySpec("q", 0.0, 1.0, 5.0, 1, law)]
    assert escalate(one, {"q": 1}, 2).feasible
    none = [QuerySpec("q", 0.0, 1.0, 1.0, 1, law)]
    plan = escalate(none, {"q": 1}, 2)
    assert not plan.feasible and plan.entries == [] and plan.failed == "q" and plan.failed_laxity < 0
    assert escalate([], {}, 2).feasible
    tied = [QuerySpec(q, 0.0, 4.0, 50.0, 4, law) for q in "ab"]
    assert [e.query_id for e in simulate(tied, {"a": 2, "b": 2}, 2, Start.of(tied)).entries][0] == "a"
    assert timeline([], 2) == [] and Tariff().bill([]) == 0.0


def test_headroom_counts_from_the_start_of_the_plan():
    s = [QuerySpec("q", 0.0, 600.0, 700.0, 600, cases.law(0.2, 20))]
    size, start = sizing.sizes(s, 2), Start.of(s, 560.0)
    plan = escalate(s, size, 2, start=start)
    assert plan.feasible
    room = rate.headroom(plan, s, start=560.0)
    assert rate.holds(plan, s, room, 560.0) and not rate.holds(plan, s, room + 0.05, 560.0)
    assert room < rate.headroom(plan, s, start=0.0)  # what counting from the start of the run would say


def test_release_study_gives_nodes_back():
    def spans(run):
        s = cases.release(run)
        plan = escalate(s, sizing.sizes(s, 2), 2)
        return plan, timeline(plan.entries, 2, 0.0, idle_spans(s, plan.entries, 300.0))

    plan, held = spans(1)
    assert plan.max_nodes > 2 and any(n == 1 and a >= 1000 and b <= 1700 for a, b, n in held)  # boosted, then given back
    plan, held = spans(2)
    assert held[0][0] == 0.0 and held[0][2] == 1 and held[0][1] >= 1500 and held[1][2] == 2


def test_plans_made_in_a_run_are_trimmed():
    s = cases.release(1)
    size = sizing.sizes(s, 2)
    start = Start.of(s, 20.0)
    plain = sweep.plan_cell(s, 2, 2, stride=1, trimmed=False, start=start)
    cut = sweep.plan_cell(s, 2, 2, stride=1, start=start)
    assert cut.feasible and cut.money <= plain.money and size
