"""Measures over plans and runs, as frames."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def plan_metrics(entries: DataFrame) -> DataFrame:
    """Nodes at most, batches, and the time from the first start to the last end, by case."""
    return entries.groupBy("case_id").agg(F.max("nodes").alias("max_nodes"), F.count("*").alias("n_batches"), (F.max("end") - F.min("start")).alias("duration"))


def deadline_report(ended: DataFrame, deadlines: DataFrame) -> DataFrame:
    """Whether each query's last end met its deadline, and how late it was."""
    last = ended.groupBy("query_id").agg(F.max("end").alias("ended"))
    late = F.greatest(F.col("ended") - F.col("deadline"), F.lit(0.0))
    return last.join(deadlines, "query_id").select("query_id", "ended", "deadline", (late == 0).alias("met"), late.alias("lateness"))


def planning_report(log: DataFrame) -> DataFrame:
    """Passes, seconds and plans by reason, with totals."""
    return log.rollup("reason").agg(F.sum("passes").alias("passes"), F.sum("planning_s").alias("planning_s"), F.count("*").alias("n_plans"))


def size_range(batch_sizes: DataFrame) -> DataFrame:
    return batch_sizes.groupBy("factor").agg(F.min("batch_units").alias("least"), F.max("batch_units").alias("most"))


def regret(runs: DataFrame) -> DataFrame:
    """How far chosen runs cost above the best of their case: how many in each bucket. runs: case_id, money, chosen."""
    over = F.col("money") / F.min("money").over(Window.partitionBy("case_id")) - 1
    bucket = F.when(F.col("over") <= 1e-9, "best").when(F.col("over") <= 0.05, "5%").when(F.col("over") <= 0.10, "10%").when(F.col("over") <= 0.18, "18%").otherwise("above")
    return runs.withColumn("over", over).filter("chosen").groupBy(bucket.alias("bucket")).agg(F.count("*").alias("n"))


def cost_ratio(a: DataFrame, b: DataFrame) -> DataFrame:
    """money of a over money of b, case by case."""
    return a.select("case_id", F.col("money").alias("a")).join(b.select("case_id", F.col("money").alias("b")), "case_id").select("case_id", (F.col("a") / F.col("b")).alias("ratio"))


def sim_vs_actual(rows: DataFrame) -> DataFrame:
    """The gap of actual to simulated money, relative to simulated."""
    return rows.select("case_id", "simulated", "actual", ((F.col("actual") - F.col("simulated")) / F.col("simulated")).alias("gap"))


def node_timeline(entries: DataFrame) -> DataFrame:
    """Spans of equal nodes: gaps and islands over the changes."""
    w = Window.partitionBy("case_id").orderBy("start")
    change = F.coalesce((F.lag("nodes").over(w) != F.col("nodes")).cast("int"), F.lit(1))
    return entries.withColumn("change", change).withColumn("k", F.sum("change").over(w)).groupBy("case_id", "k", "nodes").agg(F.min("start").alias("t_from"), F.max("end").alias("t_to")).select("case_id", "t_from", "t_to", "nodes")
