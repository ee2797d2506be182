"""Vectorised functions for laws that are no plain expression, and the sampling and observation around calibration."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Observation
from pyspark.sql import functions as F

from ..plans.model import TimeLaw


def merge_seconds(law: TimeLaw):
    """A pandas UDF (nodes, states) to the seconds of a piecewise law's merge."""
    table = np.array(law.merges)

    @F.pandas_udf("double")
    def seconds(nodes: pd.Series, states: pd.Series) -> pd.Series:
        row = table[np.searchsorted(table[:, 0], states.to_numpy())]
        return pd.Series(np.where(states <= 1, 0.0, row[:, 1] + row[:, 2] * states + (row[:, 3] + row[:, 4] * states) / nodes))

    return seconds


def merge_money(law: TimeLaw, nodes: Column, states: Column, price: float, fixed_nodes: int = 1) -> Column:
    """Dollars of a final merge."""
    return merge_seconds(law)(nodes, states) * (nodes + fixed_nodes) * F.lit(price)


def calibration_slice(df: DataFrame, fraction: float, seed: int = 7) -> DataFrame:
    """A sample of rows to time a query on; answers never come from samples."""
    return df.sample(fraction=fraction, seed=seed)


def stratified_slice(df: DataFrame, key: str, fractions: dict, seed: int = 7) -> DataFrame:
    return df.sampleBy(key, fractions, seed)


def observed(df: DataFrame, name: str, *metrics: Column) -> tuple[DataFrame, Observation]:
    """Counts that come with a run for free: rows of a state, bytes, anything an aggregate can say."""
    watch = Observation(name)
    return df.observe(watch, F.count("*").alias("n"), *metrics), watch
