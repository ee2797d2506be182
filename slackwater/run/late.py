"""Late rows: a stream-to-stream join that is exact although some rows come in later batches than their partners."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame


def late_join(left: DataFrame, right: DataFrame, history_left: DataFrame, history_right: DataFrame, late_left: Column, late_right: Column, on: Column, how=lambda l, r, on: l.join(r, on)) -> DataFrame:
    """The pairs that a batch completes: its rows with each other, and its late rows with what came before. A pair
    comes out once, in the batch of its later row. Rows on time never match history, so only late ones look there."""
    new = how(left, right, on)
    return new.unionByName(how(left.filter(late_left), history_right, on)).unionByName(how(history_left, right.filter(late_right), on))


def naive_join(left: DataFrame, right: DataFrame, on: Column) -> DataFrame:
    """Only rows of the same batch meet: late rows lose their partners."""
    return left.join(right, on)
