"""The workloads in plain SQL, one shot each."""

REV = "(l_extendedprice::decimal(18,2) * (1 - l_discount::decimal(4,2)))"
ORACLES = {
    "tpch_q1": """select l_returnflag, l_linestatus, sum(l_quantity::decimal(18,2))::double as sum_qty,
        sum(l_extendedprice::decimal(18,2))::double as sum_base, sum(l_extendedprice::decimal(18,2) * (1 - l_discount::decimal(4,2)))::double as sum_disc,
        sum((l_extendedprice::decimal(18,2) * (1 - l_discount::decimal(4,2))) * (1 + l_tax::decimal(4,2)))::double as sum_charge,
        sum(l_quantity::decimal(18,2))::double / count(*) as avg_qty, sum(l_extendedprice::decimal(18,2))::double / count(*) as avg_price,
        sum(l_discount::decimal(4,2))::double / count(*) as avg_disc, count(*) as n
        from lineitem where l_shipdate <= timestamp '2001-08-01' group by all""",
    "tpch_q3": f"""select l_orderkey, o_orderdate, o_orderpriority, sum({REV})::double as revenue from lineitem, orders, customer
        where l_orderkey = o_orderkey and o_custkey = c_custkey and c_mktsegment = 'BUILDING' and o_orderdate < timestamp '1998-03-15'
        and l_shipdate > timestamp '1998-03-15' group by all order by sum({REV}) desc, o_orderdate, l_orderkey limit 10""",
    "tpch_q4": """select o_orderpriority, count(*) as n from orders where o_orderdate >= timestamp '1997-07-01' and o_orderdate < timestamp '1997-10-01'
        and exists (select 1 from lineitem where l_orderkey = o_orderkey and l_shipdate > o_orderdate + interval 90 days) group by all""",
    "tpch_q6": """select sum(l_extendedprice::decimal(18,2) * l_discount::decimal(4,2))::double as revenue from lineitem
        where l_shipdate >= timestamp '1997-01-01' and l_shipdate < timestamp '1998-01-01' and l_discount::decimal(4,2) between 0.05 and 0.07 and l_quantity < 24""",
    "tpch_q9": f"""select n_name, year(o_orderdate)::int as o_year, sum({REV} - 0.6 * p_retailprice::decimal(18,2) * l_quantity::decimal(18,2))::double as profit
        from lineitem, orders, part, supplier, nation where l_orderkey = o_orderkey and l_partkey = p_partkey and l_suppkey = s_suppkey
        and s_nationkey = n_nationkey and p_name like '%red%' group by all""",
    "tpch_q10": f"""select c_custkey, c_name, c_acctbal, n_name, sum({REV})::double as revenue from lineitem, orders, customer, nation
        where l_orderkey = o_orderkey and o_custkey = c_custkey and c_nationkey = n_nationkey and l_returnflag = 'R'
        and o_orderdate >= timestamp '1997-10-01' and o_orderdate < timestamp '1998-01-01' group by all order by sum({REV}) desc, c_custkey limit 20""",
    "tpch_q12": """select l_returnflag, sum(case when o_orderpriority in ('1-URGENT', '2-HIGH') then 1 else 0 end)::bigint as high,
        sum(case when o_orderpriority in ('1-URGENT', '2-HIGH') then 0 else 1 end)::bigint as low from lineitem join orders on l_orderkey = o_orderkey
        where l_returnflag in ('A', 'R') and l_shipdate > o_orderdate and l_shipdate >= timestamp '1997-01-01' and l_shipdate < timestamp '1998-01-01' group by all""",
    "tpch_q14": f"""select 100 * sum(case when p_type = 'PROMO' then {REV} else 0 end)::double / sum({REV})::double as promo_pct from lineitem join part on l_partkey = p_partkey
        where l_shipdate >= timestamp '1997-09-01' and l_shipdate < timestamp '1997-10-01'""",
    "tpch_q19": f"""select sum({REV})::double as revenue, count(*) as n from lineitem join part on l_partkey = p_partkey
        where (p_brand = 'Brand#12' and l_quantity between 1 and 11 and p_size between 1 and 5)
        or (p_brand = 'Brand#23' and l_quantity between 10 and 20 and p_size between 1 and 10)
        or (p_brand = 'Brand#3' and l_quantity between 20 and 30 and p_size between 1 and 15)""",
    "custom_1": "select count(*) as n from orders",
    "custom_2": "select l_partkey, count(*) as n from lineitem group by all",
    "custom_3": "select l_suppkey, count(*) as n from lineitem group by all",
    "custom_4": "select o_orderpriority, count(*) as n from orders group by all",
    "ad_views": """select p_brand as campaign, count(*) as n from events join part on json_extract_string(props, '$.k')::bigint = p_partkey
        where event_type = 'view' and p_partkey < 100 group by all""",
    "ad_views_windowed": """select p_brand as campaign, strftime(ts, '%Y-%m-%d') as day, count(*) as n from events join part on json_extract_string(props, '$.k')::bigint = p_partkey
        where event_type = 'view' and p_partkey < 100 group by all""",
}
