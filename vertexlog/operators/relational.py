"""Batch operators around the methods, as SQL over given tables and graphs.

In a text, ``{name}`` is a table or a graph (``g_...``) and ``///`` is integer division.
"""

from __future__ import annotations

import re

from pyspark.sql import DataFrame, SparkSession

from vertexlog.plans import oracles
from vertexlog.sources.graphs import GRAPHS
from vertexlog.sources.tables import load

ORDER = "partition by user_id order by ts"

TEXTS: dict[str, str] = {
    # scans, projections, filters
    "scan_edges_pruned": "select l_partkey as src, l_suppkey as dst from {lineitem} where l_shipdate >= timestamp '1996-01-01 00:00:00' and l_quantity > 25",
    "seek_range": "select src, dst, w from {g_trade} where src >= 1000 and src < 1200",
    "edge_program_project": "select dst, w * 2 + src as val from {g_partseq} where w > 100000",
    "arith_damping": "select p_partkey as v, cast(15 + (85 * p_size) /// 100 as bigint) as val from {part}",
    # joins
    "expand_active": "select e.src, e.dst from {g_trade} e join (select c_custkey as v from {customer} where c_acctbal > 9000) a on e.src = a.v",
    "band_edges": "select a.event_id as src, b.event_id as dst from {events} a join {events} b on a.user_id = b.user_id and b.event_id > a.event_id and b.event_id <= a.event_id + 200 and abs(a.value - b.value) < 10",
    "interval_edges": "select a.event_id as src, b.event_id as dst from {events} a join {events} b on a.user_id = b.user_id and b.ts > a.ts and b.ts <= a.ts + interval 10 minutes",
    "edges_intersect": "select src, dst from {g_copurchase} intersect select src, dst from {g_partseq}",
    "edges_except": "select src, dst from {g_partseq} except select dst, src from {g_partseq}",
    "edges_intersect_all": "select src, dst from {g_partseq} intersect all select dst, src from {g_partseq}",
    "edges_except_all": "select src, dst from {g_partseq} except all select dst, src from {g_partseq}",
    "vertices_union": "select src as v from {g_partseq} union select dst as v from {g_partseq}",
    "vertices_union_all": "select v, count(*) as n from (select src as v from {g_dialog} union all select dst as v from {g_dialog}) t group by v",
    # aggregation
    "distinct_dst": "select count(distinct dst) as dsts, count(*) as m, count(distinct src) as srcs from {g_partseq}",
    "filtered_aggregate": "select src as v, count(*) filter (where w > 500000) as heavy, cast(sum(w) as bigint) as total from {g_partseq} group by src",
    "reach_rollup": "select n_regionkey, n_nationkey, count(*) as customers, cast(sum(deg) as bigint) as edges from {customer} join {nation} on c_nationkey = n_nationkey join (select src, count(*) as deg from {g_trade} group by src) d on d.src = c_custkey group by rollup(n_regionkey, n_nationkey)",
    "reach_cube": "select n_regionkey, c_mktsegment, count(*) as customers from {customer} join {nation} on c_nationkey = n_nationkey group by cube(n_regionkey, c_mktsegment)",
    "rank_grouping_sets": "select n_regionkey, c_mktsegment, cast(sum(deg) as bigint) as edges from {customer} join {nation} on c_nationkey = n_nationkey join (select src, count(*) as deg from {g_trade} group by src) d on d.src = c_custkey group by grouping sets ((n_regionkey), (c_mktsegment), ())",
    "degree_hist": "select deg, count(*) as n from (select src, count(*) as deg from {g_trade} group by src) t group by deg",
    # windows
    "page_runs": "select user_id as v, count(*) as runs from (select user_id, event_type, lag(event_type) over (partition by user_id order by ts) as before from {events}) t where before is null or before <> event_type group by user_id",
    "degree_percentile": "select v, deg, round(percent_rank() over (partition by region order by deg), 9) as pr, round(cume_dist() over (partition by region order by deg), 9) as cd, cast(ntile(4) over (partition by region order by deg, v) as int) as quarter from (select c_custkey as v, n_regionkey as region, count(*) as deg from {customer} join {nation} on c_nationkey = n_nationkey join {g_trade} on src = c_custkey group by c_custkey, n_regionkey) t",
    "range_frame_value": "select event_id, cast(count(*) over (partition by user_id order by event_id range between 500 preceding and current row) as bigint) as recent, first_value(event_id) over (partition by user_id order by event_id rows between 2 preceding and current row) as third, last_value(event_id) over (partition by user_id order by event_id rows between current row and 1 following) as following_id, nth_value(event_id, 2) over (partition by user_id order by event_id rows between unbounded preceding and unbounded following) as second_id from {events}",
    "rank_top_region": "select region, v, deg from (select n_regionkey as region, c_custkey as v, count(*) as deg, row_number() over (partition by n_regionkey order by count(*) desc, c_custkey) as place from {customer} join {nation} on c_nationkey = n_nationkey join {g_trade} on src = c_custkey group by n_regionkey, c_custkey) t where place <= 3",
    # sort and limit: the feature is the top of an order
    "top_degree": "select src as v, count(*) as deg from {g_kron} group by src order by deg desc, v limit 20",
    "limit_offset": "select src as v, count(*) as deg from {g_kron} group by src order by deg desc, v limit 10 offset 5",
    # strings, dates, maths, nulls
    "string_pack": "select p_partkey as v, upper(trim(p_brand)) as brand, cast(length(p_name) as bigint) as name_length, substring(p_type, 1, 5) as kind, concat(lpad(cast(p_size as string), 4, '0'), '-', p_brand) as tag, md5(p_name) as digest, replace(p_name, ' ', '_') as slug from {part}",
    "edges_per_day": "select cast(date_trunc('day', ts) as date) as day, count(*) as n, cast(sum(case when event_type = 'purchase' then 1 else 0 end) as bigint) as purchases from {events} group by 1",
    "order_lag_days": "select o_orderkey as v, cast(datediff({DAY}cast(o_orderdate as date), cast(l_first as date)) as bigint) as days, cast(extract(year from o_orderdate) as int) as year, cast(extract(month from o_orderdate) as int) as month from {orders} join (select l_orderkey, min(l_shipdate) as l_first from {lineitem} group by l_orderkey) f on l_orderkey = o_orderkey",
    "safe_out_share": "select p_partkey as v, coalesce(round(o.n / nullif(i.n, 0), 9), -1.0) as share, case when o.n is null then 'no out' when i.n is null then 'no in' else 'both' end as kind, try_cast(p_brand as int) as brand_number, greatest(coalesce(o.n, 0), coalesce(i.n, 0)) as most, least(coalesce(o.n, 0), coalesce(i.n, 0)) as fewest from {part} left join (select src, count(*) as n from {g_partseq} where w > 900000 group by src) o on o.src = p_partkey left join (select dst, count(*) as n from {g_partseq} where w > 900000 group by dst) i on i.dst = p_partkey",
    "root_sample": "select v from (select distinct src as v from {g_trade}) t where (v * 48271 + 11) % 2147483647 % 100 < 5",
    "math_functions": "select p_partkey as v, round(ln(p_retailprice), 6) as logarithm, cast(floor(p_retailprice) as bigint) as whole, cast(ceil(p_retailprice) as bigint) as up, abs(p_size - 25) as gap, p_partkey % 7 as slot, cast(power(2, p_size % 10) as bigint) as two from {part}",
    "exists_active": "select c_custkey as v from {customer} where exists (select 1 from {orders} where o_custkey = c_custkey and o_totalprice > 300000)",
    "not_in_visited": "select p_partkey as v from {part} where p_partkey not in (select dst from {g_partseq} where w < 200000)",
    "scalar_subquery": "select src as v, count(*) as deg from {g_partseq} group by src having count(*) > (select avg(n) from (select count(*) as n from {g_partseq} group by src) t)",
}

#: Where the two dialects differ in more than integer division.
OTHER = {
    "order_lag_days": (TEXTS["order_lag_days"].replace("{DAY}", ""), TEXTS["order_lag_days"].replace("{DAY}cast(o_orderdate as date), cast(l_first as date)", "'day', cast(l_first as date), cast(o_orderdate as date)")),
}


def _inputs(text: str) -> list[str]:
    return sorted(set(re.findall(r"\{(\w+)\}", text)))


def run(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    text = OTHER[name][0] if name in OTHER else TEXTS[name]
    frames = {x: GRAPHS[x[2:]](spark, sf_dir).edges if x.startswith("g_") else load(spark, sf_dir, x) for x in _inputs(text)}
    return spark.sql(text.replace("///", "div"), **frames)


def oracle(name: str) -> str:
    text = OTHER[name][1] if name in OTHER else TEXTS[name]
    graphs = [x for x in _inputs(text) if x.startswith("g_")]
    head = "with " + ", ".join(f"{x} as materialized ({oracles.GRAPHS[x[2:]]})" for x in graphs) + " " if graphs else ""
    return head + re.sub(r"\{(\w+)\}", r"\1", text.replace("///", "//"))
