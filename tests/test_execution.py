"""Batches, states, merges, late rows and streams on real rows."""

import random

import pytest
from pyspark.sql import functions as F
from slackwater.operators import relational
from slackwater.plans import sweep
from slackwater.plans.model import QuerySpec, TimeLaw
from slackwater.run.dispatcher import Dispatcher
from slackwater.run.late import late_join
from slackwater.run.repository import StateStore, run_batch, run_batched, tree_merge
from slackwater.sources.tables import last_key, late_lines, read_table, slot_range, slotted, table
from slackwater.workloads.catalog import WORKLOADS

N = 60


def answer(df):
    return sorted(map(str, df.collect()))


@pytest.mark.parametrize("name", ["tpch_q1", "tpch_q3", "tpch_q9", "custom_2", "ad_views_windowed"])
def test_any_split_gives_the_same_answer(spark, sf, name):
    rnd, q = random.Random(name), WORKLOADS[name]
    wanted = answer(q.one_shot(spark, sf))
    for b in (1, 3, 7):
        cuts = sorted(rnd.sample(range(1, N), b - 1)) + [N]
        assert answer(run_batched(spark, sf, q, cuts, N)) == wanted
        assert answer(run_batched(spark, sf, q, cuts, N, premerge=0.25)) == wanted


def test_empty_batches_are_harmless(spark, sf):
    q = WORKLOADS["custom_4"]
    assert answer(run_batched(spark, sf, q, [0, 0, N, N], N)) == answer(q.one_shot(spark, sf))


def test_retried_batch_leaves_the_store_as_it_was(spark, sf):
    q, store, last = WORKLOADS["tpch_q1"], StateStore(spark), last_key(spark, sf, "lineitem")
    for batch, (lo, hi) in enumerate(((0, 20), (20, N)), 1):
        for _ in range(2):
            store.write(q.name, batch, 0, run_batch(spark, sf, q, lo, hi, N, last))
    assert store.written[q.name, 0] == [1, 2]
    assert answer(q.finish(q.combine(store.read(q.name, 0)))) == answer(q.one_shot(spark, sf))


def test_tree_merge(spark, sf):
    q, store, last = WORKLOADS["custom_3"], StateStore(spark), last_key(spark, sf, "lineitem")
    for b in range(9):
        store.write(q.name, b + 1, 0, run_batch(spark, sf, q, b * N // 9, (b + 1) * N // 9, N, last))
    assert answer(tree_merge(q, store, fan_in=2)) == answer(q.one_shot(spark, sf))


def test_slots_cover_and_align(spark, sf):
    last = last_key(spark, sf, "orders")
    orders, lines = slotted(table(spark, sf, "orders"), "o_orderkey", N, last), slotted(table(spark, sf, "lineitem"), "l_orderkey", N, last)
    assert lines.join(orders, F.col("l_orderkey") == F.col("o_orderkey")).filter(lines["slot"] != orders["slot"]).isEmpty()
    for lo, hi in ((0, 1), (7, 30), (30, N)):
        assert slot_range(orders, "o_orderkey", lo, hi, N, last).count() == orders.filter(F.col("slot").between(lo, hi - 1)).count()
    plan = slot_range(table(spark, sf, "orders"), "o_orderkey", 7, 30, N, last)._jdf.queryExecution().toString()
    assert "PushedFilters: [IsNotNull(o_orderkey), GreaterThanOrEqual(o_orderkey" in plan


def test_late_rows_find_their_partners_once(spark, sf):
    last = last_key(spark, sf, "orders")
    orders = slotted(table(spark, sf, "orders"), "o_orderkey", N, last).withColumn("ob", F.floor(F.col("slot") / 10)).select("o_orderkey", "ob")
    lines = late_lines(table(spark, sf, "lineitem"), N, last).select("l_orderkey", F.floor(F.col("slot") / 10).alias("lb"), F.floor(F.col("event_slot") / 10).alias("eb"))
    on, total = F.col("l_orderkey") == F.col("o_orderkey"), 0
    for b in range(6):
        total += late_join(orders.filter(F.col("ob") == b), lines.filter(F.col("lb") == b), orders.filter(F.col("ob") < b), lines.filter(F.col("lb") < b), F.lit(False), F.col("eb") < b, on).count()
    every = table(spark, sf, "lineitem").count()
    assert total == every > lines.join(orders, on & (F.col("ob") == F.col("lb"))).count()


def test_dispatcher_runs_a_plan(spark, sf):
    law = TimeLaw.planted(0.2, 0.95, 2.0, 0.05, 0.5)
    specs = [QuerySpec(n, 0.0, N, N + 40.0, N, law) for n in ("tpch_q6", "custom_4")]
    plans = []

    def plan_from(live, done, now):
        plans.append(len(live))
        return sweep.plan_cell(live, 2, 2)

    d = Dispatcher(spark, sf, WORKLOADS, N, plan_from, premerge=0.5)
    for s in specs:
        d.add_query(s)
    answers = d.run()
    assert plans == [1, 2] and set(answers) == {"tpch_q6", "custom_4"}
    for n, df in answers.items():
        assert answer(df) == answer(WORKLOADS[n].one_shot(spark, sf))
    assert all(r.met for r in d.run_log().collect()) and d.ledger.log


def test_dispatcher_lets_queries_leave(spark, sf):
    law = TimeLaw.planted(0.2, 0.95, 2.0)
    d = Dispatcher(spark, sf, WORKLOADS, N, lambda live, done, now: sweep.plan_cell(live, 2, 2))
    for n in ("custom_1", "custom_4"):
        d.add_query(QuerySpec(n, 0.0, N, N + 40.0, N, law))
    d.remove_query("custom_1")
    assert set(d.run()) == {"custom_4"} and [w for _, w in d.replans] == ["query added", "query added", "query removed"]


def test_static_join_prunes_columns(spark, sf):
    plan = WORKLOADS["tpch_q14"].one_shot(spark, sf)._jdf.queryExecution().toString()
    assert "ReadSchema: struct<p_partkey:bigint,p_type:string>" in plan and "l_tax" not in plan.split("Physical Plan")[-1]


def test_asof_join(spark):
    left = spark.createDataFrame([("a", 1.0), ("a", 5.0), ("b", 2.0)], "k string, t double")
    right = spark.createDataFrame([("a", 0.5, 7), ("a", 5.0, 9), ("b", 3.0, 1)], "k string, t double, v int")
    assert sorted((r.k, r.t, r.v) for r in relational.asof_join(left, right, "t", "v", ("k",)).collect() if r.v) == [("a", 1.0, 7), ("a", 5.0, 9)]


def test_readers_want_schemas(spark, tmp_path):
    for fmt in ("json", "csv"):
        with pytest.raises(ValueError):
            read_table(spark, str(tmp_path), fmt)
    spark.range(5).write.orc(f"{tmp_path}/o")
    assert read_table(spark, f"{tmp_path}/o", "orc").count() == 5


def test_fits_bear_noise(spark):
    from slackwater.costs import fit
    from slackwater.experiments.plan_queries import PLANTED, planted

    found = {r.query_id: r for r in fit.fit_batch_time(planted(spark, 0.05), "share").collect()}
    for q, _, share, c in PLANTED:
        assert found[q].bn + found[q].bnp == pytest.approx(c, rel=0.1)
        assert found[q].bnp / (found[q].bn + found[q].bnp) == pytest.approx(share, rel=0.1)
    assert all(r.within_25 for r in fit.model_error(planted(spark, 0.05), fit.fit_batch_time(planted(spark), "share")).collect())


def test_calibration_measures(spark, sf):
    from slackwater.costs import fit

    job = lambda units: table(spark, sf, "lineitem").limit(int(units)).groupBy("l_returnflag").count()
    rows = fit.calibrate(spark, "q", job, [100.0, 1000.0], 8, 1).collect()
    assert [r.units for r in rows] == [100.0, 1000.0] and all(r.seconds > 0 for r in rows)
