"""Money over timelines and plans, as frames."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..plans.model import Tariff


def bill(timeline: DataFrame, tariff: Tariff = Tariff()) -> DataFrame:
    """money by case_id over (case_id, t_from, t_to, nodes) rows.

    Node k is held in the spans with at least k nodes; spans of one node that touch are one acquisition (islands), and
    each is billed min_s at least. The fixed nodes are billed over the whole span.
    """
    held = timeline.select("case_id", "t_from", "t_to", F.explode(F.sequence(F.lit(1), F.col("nodes"))).alias("k"))
    order = Window.partitionBy("case_id", "k").orderBy("t_from")
    islands = held.withColumn("new", (F.col("t_from") > F.coalesce(F.lag("t_to").over(order), F.lit(float("-inf")))).cast("int")).withColumn("island", F.sum("new").over(order))
    spans = islands.groupBy("case_id", "k", "island").agg((F.max("t_to") - F.min("t_from")).alias("s"))
    node_s = spans.groupBy("case_id").agg(F.sum(F.greatest("s", F.lit(tariff.min_s))).alias("node_s"))
    span = timeline.groupBy("case_id").agg((F.max("t_to") - F.min("t_from")).alias("span"))
    fixed = F.greatest("span", F.lit(tariff.min_s)) * tariff.fixed_nodes
    return span.join(node_s, "case_id").select("case_id", ((F.col("node_s") + fixed) * F.lit(tariff.per_second)).alias("money"))


def query_money(entries: DataFrame, merges: DataFrame, tariff: Tariff = Tariff()) -> DataFrame:
    """Money by query over batches (query_id, nodes, seconds), plus the final merge of each (same columns)."""
    each = entries.unionByName(merges).withColumn("money", F.col("seconds") * (F.col("nodes") + tariff.fixed_nodes) * F.lit(tariff.per_second))
    return each.groupBy("query_id").agg(F.sum("money").alias("money"))
