"""Table functions and SQL functions over plans."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

from ..run.repository import premerge_points


@udtf(returnType="batch_no: int")
class PremergePoints:
    """The batches after which states are merged ahead."""

    def eval(self, n: int, fraction: float):
        for p in premerge_points(n, fraction):
            yield (p,)


def register(spark: SparkSession) -> None:
    """premerge_points(n, fraction) as a table function, node_seconds_money(s, nodes) as a SQL function."""
    spark.udtf.register("premerge_points", PremergePoints)
    spark.sql("create or replace temporary function node_seconds_money(s double, nodes int) returns double return s * (nodes + 1) * 0.25D / 3600")
