"""The sweep over batch-size factors and first cluster sizes; every candidate is planned by itself, in parallel."""

from __future__ import annotations

import math
import time
from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .escalate import Plan, attempt, escalate, lattice
from .forward import Start
from .model import LADDER, QuerySpec, Tariff
from .sizing import sizes
from .trim import trim

SUMMARY = "case_id string, factor double, initial_nodes int, feasible boolean, money double, max_nodes int, passes int, planning_s double, failed string, failed_laxity double"
ENTRIES = "case_id string, factor double, initial_nodes int, seq int, query_id string, units long, ready double, start double, end double, nodes int, pending_after long, laxity double, is_premerge boolean, is_final boolean"


def plan_cell(specs: list[QuerySpec], factor: float, initial_nodes: int, ladder=LADDER, stride: int = 10, tariff: Tariff = Tariff(), longest_s: float = math.inf, trimmed: bool = True, reset_prefix: bool | str = True, start: Start | None = None, **rules) -> Plan:
    size = sizes(specs, factor, longest_s)
    if reset_prefix == "both":
        tries = [plan_cell(specs, factor, initial_nodes, ladder, stride, tariff, longest_s, trimmed, r, start, **rules) for r in (True, False)]
        return min((p for p in tries if p.feasible), key=lambda p: p.money, default=tries[0])
    plan = escalate(specs, size, initial_nodes, ladder, stride, reset_prefix, tariff, start, **rules)
    return trim(plan, specs, size, initial_nodes, ladder, tariff, stride=stride, start=start, **rules) if trimmed else plan


def entry_rows(plan: Plan) -> list[tuple]:
    return [(i, e.query_id, e.units, e.ready, e.start, e.end, e.nodes, e.pending, e.laxity, e.premerge_s > 0, e.final) for i, e in enumerate(plan.entries)]


def grid(spark: SparkSession, cases: list[str], factors: list[float], initials: list[int]) -> DataFrame:
    """All candidates, each in a partition of its own."""
    rows = [(c, float(f), n) for c in cases for f in factors for n in initials]
    return spark.createDataFrame(rows, "case_id string, factor double, initial_nodes int").repartition(len(rows), "case_id", "factor", "initial_nodes")


def sweep(spark: SparkSession, cases: dict[str, list[QuerySpec]], factors: list[float], initials: list[int], **options) -> DataFrame:
    """One row of SUMMARY for each candidate, with its entries as an array."""
    names = ENTRIES.split(", ")[3:]

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            for case, factor, initial in frame.itertuples(index=False):
                began = time.perf_counter()
                plan = plan_cell(cases[case], factor, int(initial), **options)
                row = (case, factor, int(initial), plan.feasible, plan.money if plan.feasible else None, plan.max_nodes, plan.passes, time.perf_counter() - began, plan.failed, plan.failed_laxity)
                keys = [n.split()[0] for n in names]
                yield pd.DataFrame([(*row, [dict(zip(keys, e, strict=True)) for e in entry_rows(plan)])], columns=[*(x.split()[0] for x in SUMMARY.split(", ")), "entries"])

    return grid(spark, list(cases), factors, initials).mapInPandas(run, f"{SUMMARY}, entries array<struct<{', '.join(n.replace(' ', ': ', 1) for n in names)}>>")


def choose(summary: DataFrame) -> DataFrame:
    """The cheapest feasible candidate of each case: then the smaller factor, fewer first nodes, fewer nodes at most."""
    best = F.struct(F.round("money", 6).alias("a"), "factor", "initial_nodes", "max_nodes")
    rest = F.struct(*summary.columns)
    return summary.filter("feasible").groupBy("case_id").agg(F.min_by(rest, best).alias("x")).select("x.*")


def entries_of(summary: DataFrame) -> DataFrame:
    return summary.select("case_id", "factor", "initial_nodes", F.inline("entries"))


def case_table(summary: DataFrame) -> DataFrame:
    """money:nodes by case and factor (rows) and first nodes (columns)."""
    text = F.when(F.col("feasible"), F.concat_ws(":", F.format_number("money", 2), F.col("max_nodes"))).otherwise("-")
    return summary.groupBy("case_id", "factor").pivot("initial_nodes").agg(F.first(text)).orderBy("case_id", "factor")


def parallel_escalate(spark: SparkSession, specs: list[QuerySpec], size: dict[str, int], initial_nodes: int, ladder=LADDER, **rules) -> tuple[int, int] | None:
    """The whole lattice of (nodes, start) tried in parallel; the first that holds in the order of a stride of one."""
    base, tries = lattice(specs, size, initial_nodes, ladder, **rules)
    if base.feasible:
        return initial_nodes, 0
    if not tries:
        return None

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            yield pd.DataFrame([(o, n, at) for o, n, at in frame.itertuples(index=False) if attempt(specs, size, base, int(n), int(at), **rules).feasible], columns=["o", "nodes", "at"])

    rows = [(i, n, at) for i, (n, at) in enumerate(tries)]
    df = spark.createDataFrame(rows, "o int, nodes int, at int").repartition(min(len(rows), 4 * spark.sparkContext.defaultParallelism))
    found = df.mapInPandas(run, "o int, nodes int, at int").agg(F.min_by(F.struct("nodes", "at"), "o").alias("x")).first()["x"]
    return (found["nodes"], found["at"]) if found else None
