"""Plans at rest, and the two ways to use them: compute a plan and keep it, or execute one that was kept."""

from __future__ import annotations

import argparse
import json
import threading
from collections.abc import Callable
from dataclasses import asdict

from pyspark.sql import DataFrame, SparkSession

from ..run.dispatcher import Dispatcher
from .backward import choose_config
from .escalate import Plan
from .model import LADDER, Entry, QuerySpec, Tariff
from .sweep import plan_cell

ROW = "plan_id string, seq int, entry string"


def publish(spark: SparkSession, plan_id: str, plan: Plan, path: str) -> None:
    """Writes a plan; an older one of the same id is replaced."""
    rows = [(plan_id, i, json.dumps(asdict(e))) for i, e in enumerate(plan.entries)]
    spark.createDataFrame(rows, ROW).coalesce(1).write.mode("overwrite").parquet(f"{path}/{plan_id}")


def load(spark: SparkSession, plan_id: str, path: str) -> Plan:
    rows = spark.read.schema(ROW).parquet(f"{path}/{plan_id}").orderBy("seq").collect()
    return Plan(True, [Entry(**json.loads(r["entry"])) for r in rows])


def compute(spark: SparkSession, specs: list[QuerySpec], path: str, plan_id: str = "plan", factors=(1, 2, 4, 8), initials=LADDER[:5], tariff: Tariff = Tariff(), **rules) -> Plan | None:
    """The cheapest plan of a grid, kept under plan_id."""
    plans = [p for f in factors for n in initials if (p := plan_cell(specs, f, n, tariff=tariff, **rules)).feasible]
    best = min(plans, key=lambda p: p.money, default=None)
    if best:
        publish(spark, plan_id, best, path)
    return best


def compute_single(spec: QuerySpec, ladder=LADDER, tariff: Tariff = Tariff()):
    """The plan of one query by itself, from its deadline backward."""
    return choose_config(spec, {n: (n + tariff.fixed_nodes) * tariff.per_second for n in ladder}, ladder)


def execute(spark: SparkSession, sf_dir: str, specs: list[QuerySpec], queries: dict, n_slots: int, path: str, plan_id: str = "plan", **options) -> dict[str, DataFrame]:
    """Runs a kept plan."""
    dispatcher = Dispatcher(spark, sf_dir, queries, n_slots, lambda *_: None, **options)
    for s in specs:
        dispatcher.add_query(s)
    dispatcher.plan = load(spark, plan_id, path)
    return dispatcher.run()


class Background:
    """Plans while batches run: in a thread whose Spark jobs, if any, go to a scheduler pool of their own."""

    def __init__(self, spark: SparkSession, plan: Callable[[], Plan | None], pool: str = "planning"):
        self.result: Plan | None = None

        def work() -> None:
            spark.sparkContext.setLocalProperty("spark.scheduler.pool", pool)
            self.result = plan()

        self.thread = threading.Thread(target=work, daemon=True)
        self.thread.start()

    def done(self) -> bool:
        return not self.thread.is_alive()

    def wait(self) -> Plan | None:
        self.thread.join()
        return self.result


def main(arguments: list[str] | None = None) -> None:
    """compute or execute a plan of catalogued queries with planted laws over a folder of tables."""
    from ..workloads.catalog import WORKLOADS
    from ..workloads.specs import small

    parser = argparse.ArgumentParser(description=main.__doc__)
    parser.add_argument("mode", choices=("compute", "execute"))
    parser.add_argument("--tables", default="/root/testdata/sf0.001")
    parser.add_argument("--plans", required=True)
    parser.add_argument("--queries", type=int, default=3)
    parser.add_argument("--deadline", type=float, default=1.0)
    given = parser.parse_args(arguments)
    spark = SparkSession.builder.getOrCreate()
    specs = small(given.queries, deadline=given.deadline)
    if given.mode == "compute":
        plan = compute(spark, specs, given.plans)
        print(f"{len(plan.entries)} batches, {plan.money:.4f} dollars, {plan.max_nodes} nodes at most" if plan else "no plan meets all deadlines")
    else:
        for name, df in execute(spark, given.tables, specs, WORKLOADS, specs[0].total, given.plans).items():
            print(name)
            df.show(5)


if __name__ == "__main__":
    main()
