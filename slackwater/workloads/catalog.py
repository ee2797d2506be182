"""The query workloads: nine decision-support queries, four counts, ad views, and counts over texts."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..run.repository import Frames, IncrementalQuery


def one() -> Column:
    return F.lit(1).cast("decimal(1,0)")


def money(name: str) -> Column:
    return F.col(name).cast("decimal(18,2)")


def fraction(name: str) -> Column:
    return F.col(name).cast("decimal(4,2)")


def exact(c: Column) -> Column:
    return c.cast("decimal(38,6)")


def revenue() -> Column:
    return exact(money("l_extendedprice") * (one() - fraction("l_discount")))


def plain(*numbers: str):
    """Finishes a state whose decimals become doubles."""

    def finish(state: DataFrame) -> DataFrame:
        return state.select(*(F.col(c).cast("double").alias(c) if c in numbers else F.col(c) for c in state.columns))

    return finish


def same(state: DataFrame) -> DataFrame:
    return state


def q1(s: Frames, _: Frames) -> DataFrame:
    df = s["lineitem"].filter("l_shipdate <= timestamp_ntz'2001-08-01'")
    price, disc = money("l_extendedprice"), fraction("l_discount")
    return df.groupBy("l_returnflag", "l_linestatus").agg(
        F.sum(exact(money("l_quantity"))).alias("sum_qty"),
        F.sum(exact(price)).alias("sum_base"),
        F.sum(exact(price * (one() - disc))).alias("sum_disc"),
        F.sum(exact(price * (one() - disc) * (one() + fraction("l_tax")))).alias("sum_charge"),
        F.sum(exact(disc)).alias("total_disc"),
        F.count("*").alias("n"),
    )


def q1_finish(state: DataFrame) -> DataFrame:
    d = lambda c: F.col(c).cast("double")
    return state.select("l_returnflag", "l_linestatus", *(d(c).alias(c) for c in ("sum_qty", "sum_base", "sum_disc", "sum_charge")), (d("sum_qty") / F.col("n")).alias("avg_qty"), (d("sum_base") / F.col("n")).alias("avg_price"), (d("total_disc") / F.col("n")).alias("avg_disc"), "n")


def q3(s: Frames, t: Frames) -> DataFrame:
    buyers = t["customer"].filter("c_mktsegment = 'BUILDING'").select("c_custkey")
    orders = s["orders"].filter("o_orderdate < timestamp_ntz'1998-03-15'").join(buyers, F.col("o_custkey") == F.col("c_custkey"), "left_semi")
    lines = s["lineitem"].filter("l_shipdate > timestamp_ntz'1998-03-15'").select("l_orderkey", "l_extendedprice", "l_discount")
    return lines.join(orders, F.col("l_orderkey") == F.col("o_orderkey")).groupBy("l_orderkey", "o_orderdate", "o_orderpriority").agg(F.sum(revenue()).alias("revenue"))


def q3_finish(state: DataFrame) -> DataFrame:
    return plain("revenue")(state.orderBy(F.desc("revenue"), "o_orderdate", "l_orderkey").limit(10))


def q4(s: Frames, _: Frames) -> DataFrame:
    orders = s["orders"].filter("o_orderdate >= timestamp_ntz'1997-07-01' and o_orderdate < timestamp_ntz'1997-10-01'")
    late = s["lineitem"].select("l_orderkey", "l_shipdate")
    found = orders.join(late, (F.col("l_orderkey") == F.col("o_orderkey")) & (F.col("l_shipdate") > F.col("o_orderdate") + F.expr("interval 90 days")), "left_semi")
    return found.groupBy("o_orderpriority").agg(F.count("*").alias("n"))


def q6(s: Frames, _: Frames) -> DataFrame:
    df = s["lineitem"].filter("l_shipdate >= timestamp_ntz'1997-01-01' and l_shipdate < timestamp_ntz'1998-01-01' and l_quantity < 24").filter(fraction("l_discount").between(F.lit("0.05").cast("decimal(4,2)"), F.lit("0.07").cast("decimal(4,2)")))
    return df.agg(F.sum(exact(money("l_extendedprice") * fraction("l_discount"))).alias("revenue"))


def q9(s: Frames, t: Frames) -> DataFrame:
    part = t["part"].filter(F.col("p_name").contains("red")).select("p_partkey", "p_retailprice")
    seller = t["supplier"].join(t["nation"], F.col("s_nationkey") == F.col("n_nationkey")).select("s_suppkey", "n_name")
    df = s["lineitem"].join(part, F.col("l_partkey") == F.col("p_partkey")).join(seller, F.col("l_suppkey") == F.col("s_suppkey")).join(s["orders"].select("o_orderkey", "o_orderdate"), F.col("l_orderkey") == F.col("o_orderkey"))
    gain = exact(money("l_extendedprice") * (one() - fraction("l_discount"))) - exact(F.lit("0.6").cast("decimal(2,1)") * money("p_retailprice") * money("l_quantity"))
    return df.groupBy("n_name", F.year("o_orderdate").alias("o_year")).agg(F.sum(exact(gain)).alias("profit"))


def q10(s: Frames, t: Frames) -> DataFrame:
    orders = s["orders"].filter("o_orderdate >= timestamp_ntz'1997-10-01' and o_orderdate < timestamp_ntz'1998-01-01'").select("o_orderkey", "o_custkey")
    lines = s["lineitem"].filter("l_returnflag = 'R'").select("l_orderkey", "l_extendedprice", "l_discount")
    buyer = t["customer"].join(t["nation"], F.col("c_nationkey") == F.col("n_nationkey")).select("c_custkey", "c_name", "c_acctbal", "n_name")
    df = lines.join(orders, F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_custkey").agg(F.sum(revenue()).alias("revenue"))
    return df.join(buyer, F.col("o_custkey") == F.col("c_custkey")).select("c_custkey", "c_name", "c_acctbal", "n_name", "revenue")


def q10_finish(state: DataFrame) -> DataFrame:
    return plain("revenue")(state.orderBy(F.desc("revenue"), "c_custkey").limit(20))


def q12_rows(orders: DataFrame, lines: DataFrame) -> DataFrame:
    lines = lines.filter("l_returnflag in ('A', 'R') and l_shipdate >= timestamp_ntz'1997-01-01' and l_shipdate < timestamp_ntz'1998-01-01'")
    return lines.join(orders, (F.col("l_orderkey") == F.col("o_orderkey")) & (F.col("l_shipdate") > F.col("o_orderdate")))


def q12_counts(rows: DataFrame) -> DataFrame:
    urgent = F.col("o_orderpriority").isin("1-URGENT", "2-HIGH")
    return rows.groupBy("l_returnflag").agg(F.sum(F.when(urgent, 1).otherwise(0)).alias("high"), F.sum(F.when(urgent, 0).otherwise(1)).alias("low"))


def q12(s: Frames, _: Frames) -> DataFrame:
    return q12_counts(q12_rows(s["orders"].select("o_orderkey", "o_orderdate", "o_orderpriority"), s["lineitem"].select("l_orderkey", "l_shipdate", "l_returnflag")))


def q14(s: Frames, t: Frames) -> DataFrame:
    lines = s["lineitem"].filter("l_shipdate >= timestamp_ntz'1997-09-01' and l_shipdate < timestamp_ntz'1997-10-01'")
    df = lines.join(t["part"].select("p_partkey", "p_type"), F.col("l_partkey") == F.col("p_partkey"))
    promo = F.when(F.col("p_type") == "PROMO", revenue()).otherwise(F.lit(0).cast("decimal(38,6)"))
    return df.agg(F.sum(promo).alias("promo"), F.sum(revenue()).alias("every"))


def q14_finish(state: DataFrame) -> DataFrame:
    return state.select((100 * F.col("promo").cast("double") / F.col("every").cast("double")).alias("promo_pct"))


def q19(s: Frames, t: Frames) -> DataFrame:
    df = s["lineitem"].join(t["part"].select("p_partkey", "p_brand", "p_size"), F.col("l_partkey") == F.col("p_partkey"))
    cases = (("Brand#12", 1, 11, 5), ("Brand#23", 10, 20, 10), ("Brand#3", 20, 30, 15))
    hit = F.lit(False)
    for brand, lo, hi, size in cases:
        hit = hit | ((F.col("p_brand") == brand) & F.col("l_quantity").between(lo, hi) & F.col("p_size").between(1, size))
    return df.filter(hit).agg(F.sum(revenue()).alias("revenue"), F.count("*").alias("n"))


def counted(stream: str, *keys: str):
    return lambda s, _: s[stream].groupBy(*keys).agg(F.count("*").alias("n"))


def ad_rows(events: DataFrame, part: DataFrame) -> DataFrame:
    ads = part.filter("p_partkey < 100").select(F.col("p_partkey").alias("ad_id"), F.col("p_brand").alias("campaign"))
    views = events.filter("event_type = 'view'").select("ts", F.get_json_object("props", "$.k").cast("long").alias("ad_id"))
    return views.join(ads, "ad_id")


def ad_views(s: Frames, t: Frames) -> DataFrame:
    return ad_rows(s["events"], t["part"]).groupBy("campaign").agg(F.count("*").alias("n"))


def ad_views_windowed(s: Frames, t: Frames) -> DataFrame:
    return ad_rows(s["events"], t["part"]).groupBy("campaign", F.date_format("ts", "yyyy-MM-dd").alias("day")).agg(F.count("*").alias("n"))


SUM = "sum"
WORKLOADS = {
    q.name: q
    for q in (
        IncrementalQuery("tpch_q1", ("lineitem",), (), ("l_returnflag", "l_linestatus"), dict.fromkeys(("sum_qty", "sum_base", "sum_disc", "sum_charge", "total_disc", "n"), SUM), q1, q1_finish),
        IncrementalQuery("tpch_q3", ("orders", "lineitem"), ("customer",), ("l_orderkey", "o_orderdate", "o_orderpriority"), {"revenue": SUM}, q3, q3_finish),
        IncrementalQuery("tpch_q4", ("orders", "lineitem"), (), ("o_orderpriority",), {"n": SUM}, q4, same),
        IncrementalQuery("tpch_q6", ("lineitem",), (), (), {"revenue": SUM}, q6, plain("revenue")),
        IncrementalQuery("tpch_q9", ("orders", "lineitem"), ("part", "supplier", "nation"), ("n_name", "o_year"), {"profit": SUM}, q9, plain("profit")),
        IncrementalQuery("tpch_q10", ("orders", "lineitem"), ("customer", "nation"), ("c_custkey", "c_name", "c_acctbal", "n_name"), {"revenue": SUM}, q10, q10_finish),
        IncrementalQuery("tpch_q12", ("orders", "lineitem"), (), ("l_returnflag",), {"high": SUM, "low": SUM}, q12, same),
        IncrementalQuery("tpch_q14", ("lineitem",), ("part",), (), {"promo": SUM, "every": SUM}, q14, q14_finish),
        IncrementalQuery("tpch_q19", ("lineitem",), ("part",), (), {"revenue": SUM, "n": SUM}, q19, plain("revenue")),
        IncrementalQuery("custom_1", ("orders",), (), (), {"n": SUM}, counted("orders"), same),
        IncrementalQuery("custom_2", ("lineitem",), (), ("l_partkey",), {"n": SUM}, counted("lineitem", "l_partkey"), same),
        IncrementalQuery("custom_3", ("lineitem",), (), ("l_suppkey",), {"n": SUM}, counted("lineitem", "l_suppkey"), same),
        IncrementalQuery("custom_4", ("orders",), (), ("o_orderpriority",), {"n": SUM}, counted("orders", "o_orderpriority"), same),
        IncrementalQuery("ad_views", ("events",), ("part",), ("campaign",), {"n": SUM}, ad_views, same),
        IncrementalQuery("ad_views_windowed", ("events",), ("part",), ("campaign", "day"), {"n": SUM}, ad_views_windowed, same),
    )
}
