"""Relational operators around the methods: one statement each, for both engines.

Table names in braces stand for the given tables.  Where the engines spell a
function differently the second text is DuckDB's.
"""

from __future__ import annotations

import re

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ngramlake.sources.tables import table

#: name: statement, or statement and DuckDB's own form
STATEMENTS: dict[str, str | tuple[str, str]] = {
    "rel_agg_flags": "select l_returnflag, l_linestatus, round(sum(l_quantity), 2) as qty, round(sum(l_extendedprice * (1 - l_discount)), 2) as revenue, round(avg(l_discount), 6) as discount, count(*) as n from {lineitem} where l_shipdate <= timestamp '1998-09-02 00:00:00' group by l_returnflag, l_linestatus",
    "rel_top_orders": "select o_orderkey, o_orderdate, round(sum(l_extendedprice * (1 - l_discount)), 2) as revenue from {orders} join {lineitem} on l_orderkey = o_orderkey group by o_orderkey, o_orderdate order by revenue desc, o_orderkey limit 20",
    "rel_market_share": "select n_name, o_orderpriority, round(sum(l_extendedprice), 2) as total from {lineitem} join {orders} on l_orderkey = o_orderkey join {customer} on o_custkey = c_custkey join {nation} on c_nationkey = n_nationkey join {region} on n_regionkey = r_regionkey where r_name = 'ASIA' group by n_name, o_orderpriority",
    "rel_promo_ratio": "select round(100 * sum(case when p_type like 'PROMO%' then l_extendedprice * (1 - l_discount) else 0 end) / sum(l_extendedprice * (1 - l_discount)), 6) as promo from {lineitem} join {part} on l_partkey = p_partkey",
    "rel_anti_join": "select s_suppkey, s_name from {supplier} s where not exists (select 1 from {lineitem} l where l.l_suppkey = s.s_suppkey and l.l_quantity > 49)",
    "rel_semi_join": "select c_custkey from {customer} c where exists (select 1 from {orders} o where o.o_custkey = c.c_custkey and o.o_totalprice > 300000)",
    "rel_customers_no_orders": "select c_mktsegment, count(*) as n from {customer} left join {orders} on o_custkey = c_custkey where o_orderkey is null group by c_mktsegment",
    "rel_full_join": "select coalesce(a.k, b.k) as k, a.n as na, b.n as nb from (select l_suppkey % 50 as k, count(*) as n from {lineitem} group by 1) a full join (select s_suppkey % 70 as k, count(*) as n from {supplier} group by 1) b on a.k = b.k",
    "rel_percentiles": "select l_returnflag, percentile_cont(0.5) within group (order by l_quantity) as p50, percentile_cont(0.95) within group (order by l_quantity) as p95 from {lineitem} group by l_returnflag",
    "rel_asof_join": "select event_id, user_id, max(case when event_type = 'error' then ts end) over (partition by user_id order by ts, event_id rows between unbounded preceding and current row) as last_error from {events}",
    "rel_range_join": "select b.name, count(*) as n, round(sum(e.value), 4) as total from {events} e join (select 'low' as name, -1e9 as lo, 10.0 as hi union all select 'mid', 10.0, 50.0 union all select 'high', 50.0, 1e9) b on e.value >= b.lo and e.value < b.hi group by b.name",
    "rel_interval_join": "select a.event_type as a, b.event_type as b, count(*) as n from {events} a join {events} b on a.user_id = b.user_id and b.ts > a.ts and b.ts <= a.ts + interval 30 minutes group by a.event_type, b.event_type",
    "rel_grouping_sets": "select l_returnflag, l_linestatus, count(*) as n, grouping(l_returnflag) as g from {lineitem} group by grouping sets ((l_returnflag, l_linestatus), (l_returnflag), ())",
    "rel_cube": "select o_orderstatus, o_orderpriority, count(*) as n from {orders} group by cube (o_orderstatus, o_orderpriority)",
    "rel_rollup": "select r_name, n_name, count(*) as n from {customer} join {nation} on c_nationkey = n_nationkey join {region} on n_regionkey = r_regionkey group by rollup (r_name, n_name)",
    "rel_rank_windows": "select o_custkey, o_orderkey, row_number() over w as rn, rank() over w as rk, dense_rank() over w as dr, ntile(4) over w as nt from {orders} window w as (partition by o_custkey order by o_totalprice desc, o_orderkey)",
    "rel_offset_windows": "select event_id, lag(event_id) over w as before, lead(event_id) over w as after, first_value(event_id) over w as first from {events} window w as (partition by user_id order by ts, event_id)",
    "rel_frames": "select event_id, round(avg(value) over (partition by user_id order by ts, event_id rows between 4 preceding and current row), 6) as moving, count(*) over (partition by user_id order by ts, event_id rows between unbounded preceding and current row) as so_far from {events}",
    "rel_set_ops": "select n_nationkey as k from {nation} intersect select c_nationkey from {customer} union all (select s_nationkey from {supplier} except select n_nationkey from {nation} where n_regionkey = 1)",
    "rel_pivot": "select l_returnflag, sum(case when l_linestatus = 'F' then 1 else 0 end) as f, sum(case when l_linestatus = 'O' then 1 else 0 end) as o from {lineitem} group by l_returnflag",
    "rel_scalar_subquery": "select p_partkey from {part} where p_retailprice > (select avg(p_retailprice) * 1.2 from {part})",
    "rel_correlated": "select o_orderkey from {orders} o where o_totalprice > (select avg(i.o_totalprice) * 1.5 from {orders} i where i.o_custkey = o.o_custkey)",
    "rel_recursive": "with recursive step(n, orders, qty) as (select l_linenumber, count(*), round(sum(l_quantity), 2) from {lineitem} group by l_linenumber), t(n, f, orders, qty) as (select n, cast(1 as bigint), orders, qty from step where n = 1 union all select s.n, t.f * s.n, s.orders, s.qty from t join step s on s.n = t.n + 1) select n, f, orders, qty from t",
    "rel_distinct_aggs": "select l_shipdate is null as missing, count(distinct l_partkey) as parts, count(distinct l_suppkey) as suppliers from {lineitem} group by 1",
    "rel_regression": "select round(regr_slope(l_extendedprice, l_quantity), 4) as slope, round(corr(l_extendedprice, l_quantity), 6) as r from {lineitem}",
    "fn_strings": "select p_partkey, upper(p_name) as up, substring(p_name, 2, 3) as mid, length(p_brand) as n, replace(p_type, ' ', '_') as t, lpad(cast(p_size as varchar(9)), 4, '0') as padded, reverse(p_brand) as back, md5(p_name) as digest from {part}",
    "fn_dates": "select o_orderkey, year(o_orderdate) as y, month(o_orderdate) as m, date_trunc('month', o_orderdate) as first from {orders}",
    "fn_math": "select s_suppkey, round(ln(abs(s_acctbal) + 1), 6) as l, round(sqrt(abs(s_acctbal)), 6) as r, sign(s_acctbal) as g, greatest(s_acctbal, 0) as pos from {supplier}",
    "fn_conditional": "select c_custkey, coalesce(nullif(c_mktsegment, 'BUILDING'), 'none') as seg, case when c_acctbal < 0 then 'debt' when c_acctbal < 5000 then 'some' else 'rich' end as band from {customer}",
    "fn_json": ("select event_id, cast(get_json_object(props, '$.k') as bigint) as k from {events}", "select event_id, cast(json_extract_string(props, '$.k') as bigint) as k from {events}"),
    "fn_arrays": ("select doc_id, size(w) as n, element_at(w, 1) as first, size(array_distinct(w)) as types, array_contains(w, 'the') as has from (select doc_id, split(text, ' ') as w from {documents})", "select doc_id, len(w)::INT as n, w[1] as first, len(list_distinct(w))::INT as types, list_contains(w, 'the') as has from (select doc_id, string_split(text, ' ') as w from {documents})"),
    "win_tumbling": ("select window(ts, '1 hour').start as start, event_type, count(*) as n from {events} group by window(ts, '1 hour'), event_type", "select date_trunc('hour', ts) as start, event_type, count(*) as n from {events} group by 1, 2"),
    "win_sliding": ("select window(ts, '1 hour', '30 minutes').start as start, count(*) as n from {events} group by window(ts, '1 hour', '30 minutes')", "select start, count(*) as n from (select unnest([time_bucket(interval 30 minutes, ts), time_bucket(interval 30 minutes, ts) - interval 30 minutes]) as start from {events}) group by 1"),
    "win_sessions": ("select user_id, session_window(ts, '30 minutes').start as start, count(*) as n from {events} group by user_id, session_window(ts, '30 minutes')", "select user_id, min(ts) as start, count(*) as n from (select *, sum(new) over (partition by user_id order by ts, event_id) as s from (select *, case when ts >= lag(ts) over (partition by user_id order by ts, event_id) + interval 30 minutes then 1 else 0 end as new from {events})) group by user_id, s"),
}


def _tables(statement: str) -> list[str]:
    return sorted(set(re.findall(r"\{(\w+)\}", statement)))


def _query(statement: str):
    def run(spark: SparkSession, sf: str) -> DataFrame:
        return spark.sql(statement, **{t: table(spark, sf, t) for t in _tables(statement)})

    return run


def dedup_in_day(spark: SparkSession, sf: str) -> DataFrame:
    """First event of each user, type and day."""
    e = table(spark, sf, "events").withColumn("day", F.date_trunc("day", "ts"))
    return e.groupBy("user_id", "event_type", "day").agg(F.min_by("event_id", F.struct("ts", "event_id")).alias("event_id"))


QUERIES = {k: _query(v if isinstance(v, str) else v[0]) for k, v in STATEMENTS.items()} | {"rel_dedup_in_day": dedup_in_day}
ORACLES = {k: (v if isinstance(v, str) else v[1]).replace("{", "").replace("}", "") for k, v in STATEMENTS.items()} | {
    "rel_dedup_in_day": "select user_id, event_type, date_trunc('day', ts) as day, first(event_id order by ts, event_id) as event_id from events group by 1, 2, 3"
}
