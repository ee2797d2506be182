"""Resize requests: additions go out ahead of need, releases only for idle times that are worth it."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

LEAD_S, RELEASE_S, PATIENCE = 360.0, 90.0, 2


def plan_requests(timeline: DataFrame, lead_s: float = LEAD_S) -> DataFrame:
    """requested_at, needed_at, from_nodes, to_nodes, kind of every change in (case_id, t_from, t_to, nodes) rows."""
    w = Window.partitionBy("case_id").orderBy("t_from")
    df = timeline.withColumn("from_nodes", F.coalesce(F.lag("nodes").over(w), F.lit(0))).filter("nodes <> from_nodes")
    add = F.col("nodes") > F.col("from_nodes")
    return df.select("case_id", F.when(add, F.col("t_from") - lead_s).otherwise(F.col("t_from")).alias("requested_at"), F.col("t_from").alias("needed_at"), "from_nodes", F.col("nodes").alias("to_nodes"), F.when(add, "add").otherwise("release").alias("kind"))


def release_filter(timeline: DataFrame, lead_s: float = LEAD_S, patience: float = PATIENCE) -> DataFrame:
    """The timeline without dips that are shorter than patience * lead_s: nodes stay through them."""
    w = Window.partitionBy("case_id").orderBy("t_from")
    before, after = F.lag("nodes").over(w), F.lead("nodes").over(w)
    short = (F.col("nodes") < before) & (F.col("nodes") < after) & (F.col("t_to") - F.col("t_from") < patience * lead_s)
    return timeline.withColumn("kept", F.when(short, F.least(before, after)).otherwise(F.col("nodes"))).select("case_id", "t_from", "t_to", F.col("kept").alias("nodes"))


@dataclass
class ResizeLedger:
    """What has been asked of the cluster, and what it has: asked for at once, there after a delay."""

    lead_s: float = LEAD_S
    release_s: float = RELEASE_S
    fewest: int = 1
    requested: int = 0
    log: list[tuple[float, float, int, int, str]] = field(default_factory=list)

    def want(self, now: float, nodes: int, idle_until: float | None = None) -> None:
        """Asks for more nodes; gives nodes back only if they would idle for twice the lead."""
        nodes = max(nodes, self.fewest)
        if nodes > self.requested:
            self.log.append((now, now + self.lead_s, self.requested, nodes, "add"))
            self.requested = nodes
        elif nodes < self.requested and idle_until is not None and idle_until - now >= PATIENCE * self.lead_s:
            self.log.append((now, now + self.release_s, self.requested, nodes, "release"))
            self.requested = nodes

    def there(self, now: float) -> int:
        """Nodes that a request of the past has brought by now."""
        return max((to for at, needed, _, to, kind in self.log if (needed if kind == "add" else at) <= now), default=0) if not self.log else next((to for _, needed, _, to, kind in reversed(self.log) if needed <= now), self.log[0][2])
