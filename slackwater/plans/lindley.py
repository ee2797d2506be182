"""A fixed order of batches on one cluster as running sums and maxima: start and end without a loop.

end_i = W_i + max over j <= i of (ready_j - W_(j-1)), with W the running work.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def lindley(batches: DataFrame, by: tuple[str, ...] = (), order: str = "seq", ready: str = "ready", work: str = "work") -> DataFrame:
    """Adds start and end to rows of (by..., seq, ready, work)."""
    w = Window.partitionBy(*by).orderBy(order) if by else Window.orderBy(order)
    upto = w.rowsBetween(Window.unboundedPreceding, 0)
    df = batches.withColumn("_w", F.sum(work).over(upto)).withColumn("_lead", F.max(F.col(ready) - (F.col("_w") - F.col(work))).over(upto))
    return df.withColumns({"end": F.col("_w") + F.col("_lead"), "start": F.col("_w") + F.col("_lead") - F.col(work)}).drop("_w", "_lead")


def pending_after(batches: DataFrame, total: Column, by: tuple[str, ...] = (), order: str = "seq") -> DataFrame:
    w = (Window.partitionBy(*by).orderBy(order) if by else Window.orderBy(order)).rowsBetween(Window.unboundedPreceding, 0)
    return batches.withColumn("pending", total - F.sum("units").over(w))


def laxity(batches: DataFrame, deadline: Column, merge_s: Column, by: tuple[str, ...] = (), order: str = "seq", work: str = "work") -> DataFrame:
    """What is left at each start after all work still to do."""
    w = (Window.partitionBy(*by).orderBy(order) if by else Window.orderBy(order)).rowsBetween(0, Window.unboundedFollowing)
    return batches.withColumn("laxity", deadline - F.col("start") - F.sum(work).over(w) - merge_s)


def first_violation(batches: DataFrame, by: tuple[str, ...] = (), order: str = "seq") -> DataFrame:
    bad = batches.filter("laxity < 0")
    return (bad.groupBy(*by) if by else bad).agg(F.min(order).alias(order))
