"""Joins, windows, sets and reports around the methods."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def stream_static_join(stream: DataFrame, static: DataFrame, on: Column | str, how: str = "inner") -> DataFrame:
    """A batch against a stored relation. The optimiser broadcasts the stored side only below its size threshold; a
    larger one is shuffled, or read from buckets if it was written in them."""
    return stream.join(static, on, how)


def aligned_join(left: DataFrame, right: DataFrame, left_key: str, right_key: str, lo: int, hi: int) -> DataFrame:
    """Two streams of one batch: both sides are cut to the same keys before they meet."""
    cut = lambda df, k: df.filter((F.col(k) >= lo) & (F.col(k) < hi))
    return cut(left, left_key).join(cut(right, right_key), F.col(left_key) == F.col(right_key))


def salted_join(left: DataFrame, right: DataFrame, key: str, salts: int = 16) -> DataFrame:
    """An equi-join whose hot keys are spread: left rows take a salt, right rows come once for each."""
    a = left.withColumn("_salt", F.pmod(F.xxhash64(*left.columns), F.lit(salts)))
    b = right.withColumn("_salt", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(salts - 1).cast("long"))))
    return a.join(b, [key, "_salt"]).drop("_salt")


def asof_join(left: DataFrame, right: DataFrame, time: str, value: str, by: tuple[str, ...] = ()) -> DataFrame:
    """Each left row with the last value of the right at or before its time, by a union and a running last."""
    w = Window.partitionBy(*by).orderBy(time, "_left").rowsBetween(Window.unboundedPreceding, 0)
    both = left.withColumns({value: F.lit(None).cast(dict(right.dtypes)[value]), "_left": F.lit(1)}).unionByName(right.select(*by, time, value).withColumn("_left", F.lit(0)), allowMissingColumns=True)
    return both.withColumn(value, F.last(value, ignorenulls=True).over(w)).filter("_left = 1").drop("_left")


def gaps(spans: DataFrame, by: tuple[str, ...], lo: str, hi: str) -> DataFrame:
    """Times that no span covers, between the first start and the last end: a running maximum of ends."""
    w = Window.partitionBy(*by).orderBy(lo)
    reach = F.max(hi).over(w.rowsBetween(Window.unboundedPreceding, -1))
    return spans.withColumn("_reach", reach).filter(F.col(lo) > F.col("_reach")).select(*by, F.col("_reach").alias("t_from"), F.col(lo).alias("t_to"))


def sessions(events: DataFrame, user: str, seconds: Column, gap_s: float) -> DataFrame:
    """Users' sessions as islands of events no further than gap_s apart."""
    w = Window.partitionBy(user).orderBy("_s")
    df = events.withColumn("_s", seconds)
    df = df.withColumn("_new", F.coalesce((F.col("_s") - F.lag("_s").over(w) >= gap_s).cast("int"), F.lit(1))).withColumn("_k", F.sum("_new").over(w))
    return df.groupBy(user, "_k").agg(F.count("*").alias("n"), F.min("_s").alias("first_s"), F.max("_s").alias("last_s")).drop("_k")


def ranks(df: DataFrame, by: tuple[str, ...], order: list[Column]) -> DataFrame:
    """Every ranking of rows within their group."""
    w = Window.partitionBy(*by).orderBy(*order)
    every = {"row_number": F.row_number(), "rank": F.rank(), "dense_rank": F.dense_rank(), "percent_rank": F.percent_rank(), "cume_dist": F.cume_dist(), "ntile": F.ntile(4)}
    return df.withColumns({k: f.over(w) for k, f in every.items()})


def grouping_sets(df: DataFrame, columns: tuple[str, ...], sets: list[tuple[str, ...]], *aggs: Column) -> DataFrame:
    return df.groupingSets([[F.col(c) for c in s] for s in sets], *columns).agg(*aggs)


def plan_diff(old: DataFrame, new: DataFrame) -> DataFrame:
    """Entries that a new plan drops and adds."""
    return old.exceptAll(new).withColumn("change", F.lit("dropped")).unionByName(new.exceptAll(old).withColumn("change", F.lit("added")))
