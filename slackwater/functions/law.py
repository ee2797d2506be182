"""The time laws, money and arrivals as Column expressions and small frames."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F


def parallel_time(serial_s: Column, share: Column, procs: Column, overhead_s: Column | None = None) -> Column:
    """A job whose share can run in parallel, on procs processors."""
    t = ((1 - share) + share / procs) * serial_s
    return t if overhead_s is None else t + overhead_s


def batched_time(units: Column, per_unit_s: Column, share: Column, procs: Column, parallel_overhead_s: Column, batch_overhead_s: Column) -> Column:
    return parallel_time(units * per_unit_s, share, procs, parallel_overhead_s + batch_overhead_s)


def law_time(units: Column, nodes: Column, b0="b0", bn="bn", bnp="bnp", bp="bp") -> Column:
    return F.col(b0) + F.col(bn) * units + (F.col(bnp) * units + F.col(bp)) / nodes


def node_price(instance_h: float = 0.202, service_h: float = 0.048) -> float:
    return (instance_h + service_h) / 3600


def uniform(spark: SparkSession, rate: float, start: int, end: int) -> DataFrame:
    return spark.range(start, end).select(F.col("id").cast("int").alias("slot"), F.lit(float(rate)).alias("units"))


def piecewise(spark: SparkSession, parts: list[tuple[int, int, float]]) -> DataFrame:
    """Slots with the rate of their part."""
    rows = spark.createDataFrame([(a, b, float(r)) for a, b, r in parts], "a int, b int, units double")
    return rows.select(F.explode(F.sequence("a", F.col("b") - 1)).alias("slot"), "units")


def from_table(slots: DataFrame) -> DataFrame:
    """Rows of a slotted stream counted by slot: pre-aggregated, so the running sum sees one row for each slot."""
    return slots.groupBy("slot").agg(F.count("*").cast("double").alias("units"))


def cumulative(arrivals: DataFrame) -> DataFrame:
    w = Window.orderBy("slot").rowsBetween(Window.unboundedPreceding, 0)
    return arrivals.withColumn("cum_units", F.sum("units").over(w))


def available_at(cumulated: DataFrame, asked: DataFrame) -> DataFrame:
    """For each m, the first slot by which m units are there; slots that reach it are ranked as an as-of search: the
    asked amounts are merged into the ordered totals, and each takes the next slot after it."""
    marks = cumulated.select(F.col("cum_units").alias("x"), F.col("slot"), F.lit(None).cast("double").alias("m"))
    both = marks.unionByName(asked.select(F.col("m").alias("x"), F.lit(None).cast("int").alias("slot"), "m"))
    ahead = Window.orderBy("x", F.col("m").isNull().cast("int")).rowsBetween(0, Window.unboundedFollowing)
    return both.withColumn("slot", F.first("slot", ignorenulls=True).over(ahead)).filter("m is not null").select("m", "slot")


def trailing_rate(arrivals: DataFrame, slots: int = 180) -> DataFrame:
    w = Window.orderBy("slot").rangeBetween(-(slots - 1), 0)
    return arrivals.select("slot", (F.sum("units").over(w) / F.lit(slots)).alias("rate"))


def revised_total(mode: Column, expected: Column, measured: Column, total: Column) -> Column:
    """The total to plan for. optimistic: more speed brings the same total sooner, less speed a smaller one;
    pessimistic: more speed lasts and brings a larger total, less speed brings the same one later."""
    ratio = measured / expected
    return F.when(mode == "optimistic", F.least(F.lit(1.0), ratio) * total).otherwise(F.greatest(F.lit(1.0), ratio) * total)


def joint_rate(arrivals: DataFrame) -> DataFrame:
    """The most that any stream's rate is above its expected one, slot by slot."""
    return arrivals.groupBy("slot").agg(F.max(F.col("units") / F.col("expected")).alias("ratio"))
