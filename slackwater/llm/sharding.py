"""Sharding by a k-d tree over metadata.

The tree starts with all rows and splits at distributed weighted medians: a node that stands for k shards is cut along
its widest dimension (source, language, length, place in the table) where floor(k / 2) / k of its bytes lie to the left,
until every leaf is one shard of the target bytes. Medians come from histograms that are refined until the bucket that
holds the cut is negligible; only those histograms, of a fixed size, reach the driver. Sources and languages have their
dense rank among all values as their place, so that an axis is as wide as the share of its values that a node spans.
Equal texts are one unit with one place and stay together; a group that no shard can hold is dealt out by document.

Rows: a null text has the size of its row alone; null metadata sort first; repeated rows each have a slot of their own;
an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import scratch, spread

AXES = ("by_source", "by_language", "by_length", "by_place")
BITS = 31  # of an axis; 31 more below them order the units of one value


@dataclass
class Node:
    shards: int
    bytes: int = 0
    axis: str = ""
    cut: int = 0
    left: Node | None = None
    right: Node | None = None


def route(node: Node, names: dict[int, int]) -> Column:
    """The number (in names) of the leaf that a row falls in."""
    if node.left is None:
        return F.lit(names[id(node)])
    return F.when(F.col(node.axis) <= node.cut, route(node.left, names)).otherwise(route(node.right, names))


def leaves(node: Node) -> list[Node]:
    return [node] if node.left is None else leaves(node.left) + leaves(node.right)


def dense_ranks(values: DataFrame, name: str, buckets: int = 1024) -> DataFrame:
    """The distinct values of a column, each with a rank from 0 without gaps, and their number. Values are numbered within
    buckets by hash; only the sizes of those meet in one place."""
    each = scratch(values.select(name).distinct().withColumn("bucket", F.pmod(F.xxhash64(name), F.lit(buckets))))
    sizes = each.groupBy("bucket").agg(F.count("*").alias("n"))
    order = Window.orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    sizes = sizes.select("bucket", F.coalesce(F.sum("n").over(order), F.lit(0)).alias("shift"), F.sum("n").over(Window.partitionBy(F.lit(1))).alias("count"))
    return each.withColumn("at", F.row_number().over(Window.partitionBy("bucket").orderBy(name)) - 1).join(F.broadcast(sizes), "bucket").select(name, (F.col("at") + F.col("shift")).alias("rank"), "count")


def placed(docs: DataFrame, shards: int, row_bytes: int) -> tuple[DataFrame, int]:
    """A narrow table with the place of every row on each axis, and the bytes of all rows."""
    text = F.coalesce(F.col("text"), F.lit(""))
    rows = scratch(docs.select("doc_id", (F.octet_length(text) + row_bytes).cast("long").alias("size"), F.crc32(F.encode(text, "utf-8")).alias("text_crc32"), F.xxhash64(text).alias("key"), "source", "lang"))
    every, longest, last = rows.agg(F.sum("size"), F.max("size"), F.max("doc_id")).first()
    group = scratch(rows.groupBy("key").agg(F.sum("size").alias("group_bytes"), F.min(F.struct("doc_id", "source", "lang")).alias("first")))
    # by document: into so many parts that each is a fiftieth of a shard or so, or one document
    parts = F.when(F.col("group_bytes") > (every or 0) / shards, F.ceil(F.col("group_bytes") * shards * 50 / F.lit(float(max(1, every or 0))))).otherwise(1)
    part = F.when(parts > 1, F.pmod(spread("doc_id", "size"), parts)).otherwise(F.lit(0))
    top = 1 << BITS
    unit = F.pmod(F.xxhash64("key", part), F.lit(top))
    share = lambda c, most: F.least(F.floor(c * (top - 1) / F.lit(float(max(1, most or 1)))), F.lit(top - 1))
    axes = {
        **{f"by_{c}": F.floor(F.col(f"{c}_rank") * (top - 1) / F.greatest(F.col(f"{c}_count") - 1, F.lit(1))).cast("long") for c in ("source", "language")},
        "by_length": share(F.log2(F.col("size").cast("double")), int((longest or 1).bit_length())),
        "by_place": share(F.greatest(F.coalesce(F.col("first.doc_id"), F.lit(0)), F.lit(0)).cast("double"), last),
    }
    for c, name in (("source", "source"), ("language", "lang")):
        ranks = dense_ranks(group.select(F.coalesce(f"first.{name}", F.lit("")).alias(name)), name)
        group = group.withColumn(name, F.coalesce(f"first.{name}", F.lit(""))).join(ranks.select(name, F.col("rank").alias(f"{c}_rank"), F.col("count").alias(f"{c}_count")), name)
    joined = rows.select("doc_id", "size", "text_crc32", "key").join(group, "key")
    return scratch(joined.select("doc_id", "size", "text_crc32", *((F.coalesce(axes[a], F.lit(0)).cast("long") * top + unit).alias(a) for a in AXES))), every or 0


def grow(rows: DataFrame, shards: int, every: int, buckets: int = 2048, slack: float = 0.001) -> Node:
    """The tree. slack: the share of a shard that a bucket may hold when the search for a cut ends."""
    root = Node(shards, every)
    fine = max(1.0, every / shards * slack)
    while open_nodes := [n for n in leaves(root) if n.shards > 1]:
        names = {id(n): i for i, n in enumerate(leaves(root))}
        at = rows.withColumn("leaf", route(root, names)).filter(F.col("leaf").isin([names[id(n)] for n in open_nodes]))
        spans = {r["leaf"]: r for r in at.groupBy("leaf").agg(F.sum("size").alias("bytes"), *(f(a).alias(f"{k}_{a}") for a in AXES for k, f in (("lo", F.min), ("hi", F.max)))).collect()}
        search = {}
        for n in open_nodes:
            if s := spans.get(names[id(n)]):
                n.axis = max(AXES, key=lambda a: (s[f"hi_{a}"] >> BITS) - (s[f"lo_{a}"] >> BITS))
                # what lies left of the range searched, the range, and the bytes wanted on the left
                search[names[id(n)]] = [n, 0, s[f"lo_{n.axis}"], s[f"hi_{n.axis}"], s["bytes"] * (n.shards // 2) / n.shards]
            else:  # fewer units than shards: the rest stay empty
                n.axis = AXES[0]
        going = set(search)
        while going:
            value = F.lit(None).cast("long")
            for i in going:
                n, _, lo, hi, _ = search[i]
                step = (hi - lo) // buckets + 1
                value = F.when((F.col("leaf") == i) & F.col(n.axis).between(lo, hi), F.floor((F.col(n.axis) - lo) / step).cast("long")).otherwise(value)
            found: dict[int, dict[int, int]] = {i: {} for i in going}
            for r in at.withColumn("bucket", value).filter("bucket is not null").groupBy("leaf", "bucket").agg(F.sum("size").alias("bytes")).collect():
                found[r["leaf"]][r["bucket"]] = r["bytes"]
            for i in list(going):
                n, before, lo, hi, want = search[i]
                step = (hi - lo) // buckets + 1
                b = 0
                for b in sorted(found[i]):
                    if before + found[i][b] >= want:
                        break
                    before += found[i][b]
                here = found[i].get(b, 0)
                lo, hi = lo + b * step, min(hi, lo + (b + 1) * step - 1)
                if step == 1 or here <= fine or lo == hi:
                    n.cut = hi if before + here - want <= want - before else lo - 1
                    going.discard(i)
                search[i][1:4] = before, lo, hi
        for n in open_nodes:
            n.left, n.right = Node(n.shards // 2), Node(n.shards - n.shards // 2)
    return root


def shard(docs: DataFrame, shards: int = 40, row_bytes: int = 16, slot_rows: int = 1000) -> DataFrame:
    """One row for each row of docs (doc_id, text, source, lang) with its shard and its slot there."""
    rows, every = placed(docs, shards, row_bytes)
    root = grow(rows, shards, every)
    names = {id(n): i for i, n in enumerate(leaves(root))}
    # slots are numbered within small buckets of a shard, then shifted by what the buckets before hold
    parts = max(1, rows.count() // (slot_rows * shards))
    dealt = rows.select("doc_id", "size", "text_crc32", route(root, names).alias("shard"), F.pmod(spread("doc_id", "text_crc32"), F.lit(parts)).alias("part"))
    before = Window.partitionBy("shard").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    shift = dealt.groupBy("shard", "part").agg(F.count("*").alias("n")).select("shard", "part", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("shift"))
    numbered = dealt.withColumn("slot", F.row_number().over(Window.partitionBy("shard", "part").orderBy("doc_id", "text_crc32", "size")) - 1)
    return numbered.join(shift, ["shard", "part"]).select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), F.col("shard").cast("int").alias("shard"), (F.col("slot") + F.col("shift")).cast("long").alias("slot"), F.lit(None).cast("int").alias("grown_shard"))
