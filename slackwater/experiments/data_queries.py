"""Registered queries over the given tables: states, late joins, arrivals, joins, windows, scalars."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..baselines.microbatch import micro_batch
from ..functions import law
from ..operators import relational
from ..run.late import late_join, naive_join
from ..run.repository import IncrementalQuery, run_batch, run_batched
from ..sources.tables import ad_map, last_key, late_lines, slot_range, slotted, table
from ..workloads.catalog import WORKLOADS, ad_rows, q12_counts
from ..workloads.oracles import ORACLES as WORKLOAD_ORACLES

N_SLOTS = 120
QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def registered(sql: str | None = None):
    def add(f):
        QUERIES[f.__name__] = f
        if sql:
            ORACLES[f.__name__] = sql
        return f

    return add


ORDER_SLOT = f"floor(o_orderkey::double * {N_SLOTS} / ((select max(o_orderkey) from orders) + 1))::int"
LINE_SLOT = f"floor(l_orderkey::double * {N_SLOTS} / ((select max(o_orderkey) from orders) + 1))::int"
ARRIVING = f"(select slot, count(*)::double as units from (select {ORDER_SLOT} as slot from orders) group by slot)"


def batch_no(slot) -> F.Column:
    """Four uneven batches of slots."""
    return F.when(slot < 18, 1).when(slot < 60, 2).when(slot < 61, 3).otherwise(4)


BATCH_SQL = "case when slot < 18 then 1 when slot < 60 then 2 when slot < 61 then 3 else 4 end"


def order_slots(spark: SparkSession, sf_dir: str) -> DataFrame:
    return slotted(table(spark, sf_dir, "orders"), "o_orderkey", N_SLOTS, last_key(spark, sf_dir, "orders"))


@registered(f"select {BATCH_SQL} as batch_no, l_suppkey, count(*) as n from (select *, {LINE_SLOT} as slot from lineitem) group by all")
def custom_3_states(spark, sf_dir):
    """The states of all batches in one job: the batch is one more key."""
    lines = slotted(table(spark, sf_dir, "lineitem"), "l_orderkey", N_SLOTS, last_key(spark, sf_dir, "lineitem"))
    return lines.groupBy(batch_no(F.col("slot")).alias("batch_no"), "l_suppkey").agg(F.count("*").alias("n"))


@registered(
    f"""select {BATCH_SQL} as batch_no, l_returnflag, l_linestatus, sum(l_quantity::decimal(18,2))::double as sum_qty,
    sum(l_extendedprice::decimal(18,2) * (1 - l_discount::decimal(4,2)))::double as sum_disc, count(*) as n
    from (select *, {LINE_SLOT} as slot from lineitem) where l_shipdate <= timestamp '2001-08-01' group by all"""
)
def tpch_q1_states(spark, sf_dir):
    q = WORKLOADS["tpch_q1"]
    state = None
    for b, (lo, hi) in enumerate(((0, 18), (18, 60), (60, 61), (61, N_SLOTS)), 1):  # each batch reads its own keys alone
        lines = slot_range(table(spark, sf_dir, "lineitem"), "l_orderkey", lo, hi, N_SLOTS, last_key(spark, sf_dir, "lineitem"))
        part = q.prepare({"lineitem": lines}, {}).withColumn("batch_no", F.lit(b))
        state = part if state is None else state.unionByName(part)
    return state.select("batch_no", "l_returnflag", "l_linestatus", F.col("sum_qty").cast("double").alias("sum_qty"), F.col("sum_disc").cast("double").alias("sum_disc"), "n")


def _late_parts(spark, sf_dir, batches: int = 4):
    last, width = last_key(spark, sf_dir, "orders"), N_SLOTS // batches
    orders = order_slots(spark, sf_dir).select("o_orderkey", "o_orderdate", "o_orderpriority", F.floor(F.col("slot") / width).alias("o_batch"))
    lines = late_lines(table(spark, sf_dir, "lineitem"), N_SLOTS, last)
    lines = lines.filter("l_returnflag in ('A', 'R') and l_shipdate >= timestamp_ntz'1997-01-01' and l_shipdate < timestamp_ntz'1998-01-01'")
    lines = lines.select("l_orderkey", "l_shipdate", "l_returnflag", F.floor(F.col("slot") / width).alias("l_batch"), F.floor(F.col("event_slot") / width).alias("l_event"))
    return orders, lines, (F.col("l_orderkey") == F.col("o_orderkey")) & (F.col("l_shipdate") > F.col("o_orderdate"))


Q12_SQL = """select l_returnflag, sum(case when o_orderpriority in ('1-URGENT', '2-HIGH') then 1 else 0 end)::bigint as high,
    sum(case when o_orderpriority in ('1-URGENT', '2-HIGH') then 0 else 1 end)::bigint as low from lineitem join orders on l_orderkey = o_orderkey
    where l_returnflag in ('A', 'R') and l_shipdate > o_orderdate and l_shipdate >= timestamp '1997-01-01' and l_shipdate < timestamp '1998-01-01'"""


@registered(Q12_SQL + " group by all")
def late_join_q12(spark, sf_dir, batches: int = 4, latest: int = 3):
    """Batch by batch, late lines go to the orders of earlier batches; all pairs come out once. A line is `latest` slots
    late at most: a batch and the history that it needs are ranges of keys, which the scans skip by."""
    last, width, out = last_key(spark, sf_dir, "orders"), N_SLOTS // batches, None
    cut = lambda name, key, lo, hi: slot_range(table(spark, sf_dir, name), key, lo, hi, N_SLOTS, last)
    on = (F.col("l_orderkey") == F.col("o_orderkey")) & (F.col("l_shipdate") > F.col("o_orderdate"))
    for b in range(batches):
        lo, hi = b * width, (b + 1) * width
        before = max(0, lo - latest)
        orders = lambda a, z: cut("orders", "o_orderkey", a, z).select("o_orderkey", "o_orderdate", "o_orderpriority")
        lines = late_lines(cut("lineitem", "l_orderkey", before, hi), N_SLOTS, last).filter((F.col("slot") >= lo) & (F.col("slot") < hi))
        lines = lines.filter("l_returnflag in ('A', 'R') and l_shipdate >= timestamp_ntz'1997-01-01' and l_shipdate < timestamp_ntz'1998-01-01'")
        pairs = late_join(orders(lo, hi), lines, orders(before, lo), lines.limit(0), F.lit(False), F.col("event_slot") < lo, on)
        out = pairs if out is None else out.unionByName(pairs)
    return q12_counts(out)


@registered(
    Q12_SQL
    + f""" and floor({ORDER_SLOT} / 30) = floor((case when (l_orderkey * 7 + l_linenumber) % 20 = 0
    then least({LINE_SLOT} + 1 + l_linenumber % 3, {N_SLOTS - 1}) else {LINE_SLOT} end) / 30) group by all"""
)
def late_naive_q12(spark, sf_dir):
    """Only pairs of one batch: what is lost without the late join."""
    orders, lines, on = _late_parts(spark, sf_dir)
    return q12_counts(naive_join(orders, lines, on & (F.col("o_batch") == F.col("l_batch"))))


@registered(f"select slot, units, sum(units) over (order by slot) as cum_units from {ARRIVING}")
def arrivals_cumulative(spark, sf_dir):
    return law.cumulative(law.from_table(order_slots(spark, sf_dir)))


ASKED = (1.0, 10.0, 100.0, 777.0, 1200.0, 1400.0)


@registered(f"select m, min(slot)::int as slot from (values {', '.join(f'({m}::double)' for m in ASKED)}) t(m) join (select slot, sum(units) over (order by slot) as c from {ARRIVING}) on c >= m group by m")
def available_at(spark, sf_dir):
    asked = spark.createDataFrame([(m,) for m in ASKED], "m double")
    return law.available_at(law.cumulative(law.from_table(order_slots(spark, sf_dir))), asked)


@registered(f"select m, slot from (values {', '.join(f'({m}::double)' for m in ASKED)}) t(m) asof join (select slot, sum(units) over (order by slot) as c from {ARRIVING}) s on m <= s.c")
def asof_available(spark, sf_dir):
    asked = spark.createDataFrame([(m,) for m in ASKED], "m double")
    cum = law.cumulative(law.from_table(order_slots(spark, sf_dir)))
    return asked.join(cum, F.col("cum_units") >= F.col("m")).groupBy("m").agg(F.min("slot").alias("slot"))


@registered(f"select slot, round(sum(units) over (order by slot range between 9 preceding and current row) / 10, 6) as rate from {ARRIVING}")
def trailing_rate(spark, sf_dir):
    return law.trailing_rate(law.from_table(order_slots(spark, sf_dir)), 10).select("slot", F.round("rate", 6).alias("rate"))


@registered("select count(*) as n from orders where not exists (select 1 from lineitem where l_orderkey = o_orderkey)")
def orders_without_lines(spark, sf_dir):
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey")
    return table(spark, sf_dir, "orders").join(lines, F.col("l_orderkey") == F.col("o_orderkey"), "left_anti").agg(F.count("*").alias("n"))


@registered("select count(*) as n from orders where exists (select 1 from lineitem where l_orderkey = o_orderkey and l_shipdate > o_orderdate + interval 90 days)")
def orders_late_lines(spark, sf_dir):
    on = (F.col("l_orderkey") == F.col("o_orderkey")) & (F.col("l_shipdate") > F.col("o_orderdate") + F.expr("interval 90 days"))
    return table(spark, sf_dir, "orders").join(table(spark, sf_dir, "lineitem").select("l_orderkey", "l_shipdate"), on, "left_semi").agg(F.count("*").alias("n"))


@registered("select count(*) as n, count(l_orderkey) as matched from orders left join lineitem on l_orderkey = o_orderkey")
def orders_left_lines(spark, sf_dir):
    return table(spark, sf_dir, "orders").join(table(spark, sf_dir, "lineitem"), F.col("l_orderkey") == F.col("o_orderkey"), "left").agg(F.count("*").alias("n"), F.count("l_orderkey").alias("matched"))


@registered("select s_name, count(*) as n from lineitem join supplier on l_suppkey = s_suppkey group by all")
def salted_join(spark, sf_dir):
    """A hot supplier's lines would be spread over the salts."""
    lines = table(spark, sf_dir, "lineitem").select(F.col("l_suppkey").alias("k"), "l_orderkey", "l_linenumber")
    sellers = table(spark, sf_dir, "supplier").select(F.col("s_suppkey").alias("k"), "s_name")
    return relational.salted_join(lines, sellers, "k").groupBy("s_name").agg(F.count("*").alias("n"))


@registered("select p_brand as campaign, strftime(time_bucket(interval 1 day, ts), '%Y-%m-%d') as day, count(*) as n from events join part on json_extract_string(props, '$.k')::bigint = p_partkey where event_type = 'view' and p_partkey < 100 group by all")
def tumbling_views(spark, sf_dir):
    rows = ad_rows(table(spark, sf_dir, "events"), table(spark, sf_dir, "part"))
    return rows.groupBy("campaign", F.window("ts", "1 day").alias("w")).agg(F.count("*").alias("n")).select("campaign", F.date_format("w.start", "yyyy-MM-dd").alias("day"), "n")


@registered(
    """select epoch(w)::bigint as window_start, count(*) as n from (select unnest([time_bucket(interval 6 hour, ts), time_bucket(interval 6 hour, ts) - interval 6 hour]) as w
    from events) group by w"""
)
def sliding_events(spark, sf_dir):
    """Windows of twelve hours every six."""
    df = table(spark, sf_dir, "events").select(F.col("ts").cast("timestamp").alias("ts"))
    return df.groupBy(F.window("ts", "12 hours", "6 hours").alias("w")).agg(F.count("*").alias("n")).select(F.unix_timestamp("w.start").alias("window_start"), "n")


@registered(
    """with e as (select user_id, epoch(ts) as s, case when epoch(ts) - lag(epoch(ts)) over w < 43200 then 0 else 1 end as new from events window w as (partition by user_id order by ts)),
    k as (select user_id, s, sum(new) over (partition by user_id order by s rows unbounded preceding) as k from e)
    select user_id, count(*) as n, count(distinct k) as n_sessions from k group by user_id"""
)
def session_users(spark, sf_dir):
    """Events and sessions of each user; half a day without events ends a session."""
    df = table(spark, sf_dir, "events").select("user_id", F.col("ts").cast("timestamp").alias("ts"))
    return df.groupBy("user_id", F.session_window("ts", "12 hours")).agg(F.count("*").alias("n")).groupBy("user_id").agg(F.sum("n").alias("n"), F.count("*").alias("n_sessions"))


@registered(
    """with e as (select user_id, epoch(ts)::double as s, case when epoch(ts) - lag(epoch(ts)) over w < 43200 then 0 else 1 end as new from events window w as (partition by user_id order by ts)),
    k as (select user_id, s, sum(new) over (partition by user_id order by s rows unbounded preceding) as k from e)
    select user_id, count(*) as n, min(s) as first_s, max(s) as last_s from k group by user_id, k"""
)
def session_islands(spark, sf_dir):
    """The same sessions as gaps and islands over seconds."""
    seconds = F.unix_micros(F.col("ts").cast("timestamp")) / 1e6
    return relational.sessions(table(spark, sf_dir, "events").select("user_id", "ts"), "user_id", seconds, 43200.0)


@registered("select json_extract_string(props, '$.k')::bigint as k, count(*) as n, sum(value::decimal(18,2))::double as total from events group by all")
def json_props(spark, sf_dir):
    df = table(spark, sf_dir, "events").select(F.from_json("props", "k bigint")["k"].alias("k"), F.col("value").cast("decimal(18,2)").alias("v"))
    return df.groupBy("k").agg(F.count("*").alias("n"), F.sum("v").cast("double").alias("total"))


@registered(
    """select p_brand, regexp_extract(p_brand, '([0-9]+)', 1)::int as number, upper(min(p_name)) as first_name, max(length(p_name))::int as longest,
    count(*) as n from part where p_type like 'S%' group by p_brand"""
)
def brand_strings(spark, sf_dir):
    df = table(spark, sf_dir, "part").filter(F.col("p_type").like("S%"))
    return df.groupBy("p_brand").agg(F.regexp_extract(F.first("p_brand"), "([0-9]+)", 1).cast("int").alias("number"), F.upper(F.min("p_name")).alias("first_name"), F.max(F.length("p_name")).alias("longest"), F.count("*").alias("n"))


@registered(
    """select year(o_orderdate)::int as y, quarter(o_orderdate)::int as q, count(*) as n, max(date_diff('day', timestamp '1995-01-01', o_orderdate))::int as days,
    min(dayofweek(o_orderdate)::int + 1)::int as dow from orders group by all"""
)
def date_parts(spark, sf_dir):
    df = table(spark, sf_dir, "orders")
    return df.groupBy(F.year("o_orderdate").alias("y"), F.quarter("o_orderdate").alias("q")).agg(F.count("*").alias("n"), F.max(F.datediff("o_orderdate", F.lit("1995-01-01").cast("date"))).alias("days"), F.min(F.dayofweek("o_orderdate")).alias("dow"))


@registered("select event_type, count(distinct user_id) as n from events group by all")
def distinct_users_batched(spark, sf_dir):
    """Exact distinct counts from states that are sets of rows."""
    q = IncrementalQuery("distinct_users", ("events",), (), ("event_type", "user_id"), {}, lambda s, _: s["events"].select("event_type", "user_id").distinct(), lambda s: s.groupBy("event_type").agg(F.count("*").alias("n")))
    return run_batched(spark, sf_dir, q, [20, 70, 120], N_SLOTS)


@registered()
def hll_users(spark, sf_dir):
    """Approximate distinct counts from mergeable sketches."""
    q = IncrementalQuery("hll_users", ("events",), (), ("event_type",), {"users": "hll"}, lambda s, _: s["events"].groupBy("event_type").agg(F.hll_sketch_agg("user_id", 14).alias("users")), lambda s: s.select("event_type", F.hll_sketch_estimate("users").alias("n")))
    return run_batched(spark, sf_dir, q, [20, 70, 120], N_SLOTS)


@registered()
def kll_order_price(spark, sf_dir):
    """Quantiles of prices from mergeable sketches of batches."""
    orders = order_slots(spark, sf_dir).withColumn("batch_no", batch_no(F.col("slot")))
    states = orders.groupBy("batch_no", "o_orderpriority").agg(F.kll_sketch_agg_double("o_totalprice").alias("s"))
    merged = states.groupBy("o_orderpriority").agg(F.kll_merge_agg_double("s").alias("s"))
    return merged.select("o_orderpriority", F.kll_sketch_get_quantile_double("s", F.lit(0.5)).alias("median"))


@registered("select lang, source, count(*) as n, sum(n_chars)::bigint as chars from documents group by all")
def text_counts(spark, sf_dir):
    """Incremental counts over texts, merged from four batches."""
    docs = table(spark, sf_dir, "documents").select("doc_id", "lang", "source", "n_chars")
    states = docs.groupBy((F.col("doc_id") % 4).alias("batch_no"), "lang", "source").agg(F.count("*").alias("n"), F.sum("n_chars").alias("chars"))
    return states.groupBy("lang", "source").agg(F.sum("n").alias("n"), F.sum("chars").alias("chars"))


@registered("select role, count(*) as n, count(distinct conv_id) as n_convs, max(turn)::bigint as last_turn from conversations group by role")
def turn_counts(spark, sf_dir):
    return table(spark, sf_dir, "conversations").groupBy("role").agg(F.count("*").alias("n"), F.countDistinct("conv_id").alias("n_convs"), F.max("turn").cast("long").alias("last_turn"))


@registered("select o_orderpriority, o_orderstatus, count(*) as n, sum(o_totalprice::decimal(18,2))::double as total from orders group by rollup (o_orderpriority, o_orderstatus)")
def cost_rollup(spark, sf_dir):
    return table(spark, sf_dir, "orders").rollup("o_orderpriority", "o_orderstatus").agg(F.count("*").alias("n"), F.sum(F.col("o_totalprice").cast("decimal(18,2)")).cast("double").alias("total"))


@registered("select l_returnflag, l_linestatus, count(*) as n from lineitem group by cube (l_returnflag, l_linestatus)")
def cost_cube(spark, sf_dir):
    return table(spark, sf_dir, "lineitem").cube("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"))


@registered("select l_returnflag, l_linestatus, count(*) as n from lineitem group by grouping sets ((l_returnflag), (l_linestatus), ())")
def cost_sets(spark, sf_dir):
    return relational.grouping_sets(table(spark, sf_dir, "lineitem"), ("l_returnflag", "l_linestatus"), [("l_returnflag",), ("l_linestatus",), ()], F.count("*").alias("n"))


@registered("select event_type, sum(case when d = 1 then 1 else 0 end)::bigint as first_day, sum(case when d = 2 then 1 else 0 end)::bigint as second_day from (select event_type, day(ts) as d from events) group by event_type")
def case_pivot(spark, sf_dir):
    df = table(spark, sf_dir, "events").select("event_type", F.dayofmonth("ts").alias("d"))
    return df.groupBy("event_type").pivot("d", [1, 2]).agg(F.count(F.lit(1))).select("event_type", F.coalesce("1", F.lit(0)).alias("first_day"), F.coalesce("2", F.lit(0)).alias("second_day"))


@registered("select o_orderpriority, count(*) as n from orders join lineitem on l_orderkey = o_orderkey group by all")
def aligned_join(spark, sf_dir):
    """The aligned join over all slots, batch by batch; counts of batches add up."""
    orders, lines = table(spark, sf_dir, "orders"), table(spark, sf_dir, "lineitem")
    least, most = orders.agg(F.min("o_orderkey"), F.max("o_orderkey")).first()
    cuts = [least + (most + 1 - least) * slot // N_SLOTS for slot in (0, 18, 60, 61, N_SLOTS)]
    states = [relational.aligned_join(orders, lines, "o_orderkey", "l_orderkey", lo, hi).groupBy("o_orderpriority").agg(F.count("*").alias("n")) for lo, hi in zip(cuts, cuts[1:])]
    every = states[0]
    for state in states[1:]:
        every = every.unionByName(state)
    return every.groupBy("o_orderpriority").agg(F.sum("n").alias("n"))


@registered(
    """select o_orderkey, row_number() over w as row_number, rank() over w as rank, dense_rank() over w as dense_rank, percent_rank() over w as percent_rank, cume_dist() over w as cume_dist,
    ntile(4) over w as ntile from orders window w as (partition by o_orderstatus order by o_orderkey)"""
)
def order_ranks(spark, sf_dir):
    ranked = relational.ranks(table(spark, sf_dir, "orders"), ("o_orderstatus",), [F.col("o_orderkey")])
    return ranked.select("o_orderkey", *(F.col(c).cast("long").alias(c) for c in ("row_number", "rank", "dense_rank")), "percent_rank", "cume_dist", F.col("ntile").cast("long").alias("ntile"))


@registered("select o_custkey, count(*) as n from orders group by o_custkey")
def bucketed_orders(spark, sf_dir):
    """All orders in buckets of their customers; the count reads them without a shuffle."""
    import uuid

    from ..sources.sinks import write_bucketed

    name = f"orders_by_customer_{uuid.uuid4().hex[:8]}"
    write_bucketed(table(spark, sf_dir, "orders").select("o_custkey", "o_orderkey"), name, 8, "o_custkey")
    return spark.table(name).groupBy("o_custkey").agg(F.count("*").alias("n"))


@registered("select p_partkey as ad_id, p_brand as campaign from part where p_partkey < 100")
def ad_campaigns(spark, sf_dir):
    """The ad map, through a CSV copy with a schema."""
    from ..sources.tables import new_folder, read_table

    path = new_folder(spark)
    ad_map(spark, sf_dir).write.csv(path, header=True)
    return read_table(spark, path, "csv", "ad_id long, campaign string", header=True)


def _stream_files(spark, sf_dir, slots: int = 8) -> str:
    """Events as JSON files, a folder of slots, for a file source."""
    from ..sources.tables import new_folder

    path = new_folder(spark)
    events = slotted(table(spark, sf_dir, "events"), "event_id", slots, last_key(spark, sf_dir, "events"))
    events.withColumn("ts", F.date_format("ts", "yyyy-MM-dd'T'HH:mm:ss.SSSSSS")).repartitionByRange(slots, "slot").write.json(path)
    return path


@registered(ORACLES["tumbling_views"])
def streaming_views(spark, sf_dir):
    """Views per campaign and day by a streaming aggregation, run intermittently until its files are read."""
    from ..streaming.views import views_by_day

    return views_by_day(spark, _stream_files(spark, sf_dir), ad_map(spark, sf_dir))


@registered("select event_type, count(*) as n, sum(value::decimal(18,2))::double as total from events group by all")
def stateful_rate(spark, sf_dir):
    """Running counts and sums of each event type in arbitrary state."""
    from ..streaming.views import running_totals

    return running_totals(spark, _stream_files(spark, sf_dir))


@registered("select count(*) as n from orders join lineitem on l_orderkey = o_orderkey")
def stream_stream_lines(spark, sf_dir):
    """Orders and lines as two streams, joined by key within watermarks."""
    from ..streaming.views import join_streams

    return join_streams(spark, table(spark, sf_dir, "orders"), table(spark, sf_dir, "lineitem"))


@registered("select count(*) as n from (select distinct event_id from events)")
def stream_dedup(spark, sf_dir):
    """Files sent twice count once."""
    from ..streaming.views import distinct_events

    return distinct_events(spark, _stream_files(spark, sf_dir))


@registered("select o_orderpriority, count(*) as n from orders group by all")
def intermittent_stream(spark, sf_dir):
    """A stream that is run once for each planned batch; each run's state goes to the store."""
    from ..streaming.views import intermittent_counts

    return intermittent_counts(spark, table(spark, sf_dir, "orders"), 4)


@registered(WORKLOAD_ORACLES["ad_views"])
def micro_batch_ads(spark, sf_dir):
    """Ad views by the streaming baseline."""
    return micro_batch(spark, sf_dir, WORKLOADS["ad_views"])[0]


@registered(WORKLOAD_ORACLES["tpch_q6"])
def micro_batch_q6(spark, sf_dir):
    return micro_batch(spark, sf_dir, WORKLOADS["tpch_q6"])[0]


@registered()
def state_sizes(spark, sf_dir):
    """Rows and bytes of the states of four batches, and the share of the rows read that they have, by workload."""
    from ..sources.tables import STREAM_KEYS

    rows = []
    for name, q in WORKLOADS.items():
        stream = q.streams[-1]
        last = last_key(spark, sf_dir, q.streams[0])
        for b, (lo, hi) in enumerate(((0, 30), (30, 60), (60, 90), (90, N_SLOTS)), 1):
            state = run_batch(spark, sf_dir, q, lo, hi, N_SLOTS, last)
            n, size = state.agg(F.count("*"), F.sum(F.octet_length(F.to_json(F.struct(*state.columns))))).first()
            read = slot_range(table(spark, sf_dir, stream), STREAM_KEYS[stream], lo, hi, N_SLOTS, last).count()
            rows.append((name, b, n, size or 0, n / max(1, read)))
    return spark.createDataFrame(rows, "query_id string, batch_no int, n_rows long, n_bytes long, share double")
