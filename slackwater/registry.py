"""All registered queries but those of optional parts, with their SQL oracles."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from .experiments import data_queries, plan_queries
from .run.repository import IncrementalQuery, run_batched
from .workloads.catalog import WORKLOADS
from .workloads.oracles import ORACLES as WORKLOAD_ORACLES

N_SLOTS = 120
CUTS = [18, 60, 61, 120]
"""Ends of four uneven batches."""


def _one_shot(q: IncrementalQuery) -> Callable[[SparkSession, str], DataFrame]:
    return q.one_shot


def _batched(q: IncrementalQuery, premerge: float | None) -> Callable[[SparkSession, str], DataFrame]:
    return lambda spark, sf_dir: run_batched(spark, sf_dir, q, CUTS, N_SLOTS, premerge)


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}
for _name, _q in WORKLOADS.items():
    for _suffix, _f in (("", _one_shot(_q)), ("_batched", _batched(_q, None)), ("_premerged", _batched(_q, 0.5))):
        QUERIES[_name + _suffix], ORACLES[_name + _suffix] = _f, WORKLOAD_ORACLES[_name]
for _part in (data_queries, plan_queries):
    QUERIES |= _part.QUERIES
    ORACLES |= _part.ORACLES
