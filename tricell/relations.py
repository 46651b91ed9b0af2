"""Relational operators around the methods, as SQL that any engine runs.

`RELATIONS` holds one text for Spark and for the engine that it is compared
with; where their dialects part, `DUCK` has the other text.
"""

from __future__ import annotations

import re
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()

_EDGES = "select distinct l_orderkey as u, l_partkey as v from lineitem"
_CLASS = "select l_orderkey % 4 as k_lo, l_partkey % 4 as k_hi, count(*) as n from lineitem group by l_orderkey % 4, l_partkey % 4"

RELATIONS: dict[str, str] = {
    # scans, projections, filters
    "scan_lineitem": "select l_orderkey, l_partkey, l_suppkey from lineitem",
    "filter_low_edges": "select distinct l_orderkey, l_partkey from lineitem where l_quantity between 10 and 20 and l_returnflag in ('A', 'R') and l_linestatus <> 'O'",
    "project_roles": "select l_orderkey * 3 as a, l_partkey * 3 + 1 as b, l_suppkey * 3 + 2 as c from lineitem",
    "case_role": "select l_orderkey, case when l_orderkey < l_partkey then 'low' when l_orderkey = l_partkey then 'loop' else 'high' end as role from lineitem",
    "filter_pattern": "select p_partkey, p_brand from part where p_brand like 'Brand#1%' or p_brand is null",
    # joins
    "join_broadcast": "select s_suppkey, n_name from supplier join nation on s_nationkey = n_nationkey",
    "join_sort_merge": "select /*+ MERGE(orders) */ l_orderkey, l_partkey, o_custkey from lineitem join orders on l_orderkey = o_orderkey",
    "join_shuffle_hash": "select /*+ SHUFFLE_HASH(orders) */ l_orderkey, l_suppkey, o_custkey from lineitem join orders on l_orderkey = o_orderkey",
    "join_theta": "select x.s_suppkey as lo, y.s_suppkey as hi from supplier x join supplier y on x.s_suppkey < y.s_suppkey",
    "join_left_outer": "select p_partkey, count(l_orderkey) as deg from part left join lineitem on p_partkey = l_partkey group by p_partkey",
    "join_right_outer": "select o_orderkey, c_custkey from orders right join customer on o_custkey = c_custkey",
    "join_full_outer": "select x.k as left_key, y.k as right_key from (select distinct l_partkey % 50 as k from lineitem) x full join (select distinct l_suppkey + 20 as k from lineitem) y on x.k = y.k",
    "join_semi": "select c_custkey from customer where exists (select 1 from orders where o_custkey = c_custkey)",
    "join_anti": "select c_custkey from customer where not exists (select 1 from orders where o_custkey = c_custkey)",
    "join_cross_cells": "select x.k * 16 + y.k * 4 + z.k as cell from (select distinct l_partkey % 4 as k from lineitem) x cross join (select distinct l_partkey % 4 as k from lineitem) y cross join (select distinct l_partkey % 4 as k from lineitem) z",
    "join_null_safe": "select x.k, count(*) as n from (select case when l_suppkey % 7 = 0 then null else l_suppkey % 7 end as k from lineitem) x join (select case when s_suppkey % 7 = 0 then null else s_suppkey % 7 end as k from supplier) y on x.k is not distinct from y.k group by x.k",
    "join_three_tables": "select r_name, count(*) as suppliers from supplier join nation on s_nationkey = n_nationkey join region on n_regionkey = r_regionkey group by r_name",
    "join_lateral": "select o_orderkey, t.v from orders, lateral (select o_custkey % 3 as v) t",
    # aggregates
    "agg_count_distinct": "select l_suppkey, count(distinct l_partkey) as parts, count(distinct l_orderkey) as orders_n from lineitem group by l_suppkey",
    "agg_moments": "select l_suppkey, round(avg(l_quantity), 6) as mean, round(var_pop(l_quantity), 4) as variance, round(stddev_samp(l_quantity), 4) as spread, min(l_quantity) as least, max(l_quantity) as most from lineitem group by l_suppkey",
    "agg_rollup_classes": f"select k_lo, k_hi, cast(sum(n) as bigint) as n from ({_CLASS}) group by rollup (k_lo, k_hi)",
    "agg_cube_classes": f"select k_lo, k_hi, cast(sum(n) as bigint) as n from ({_CLASS}) group by cube (k_lo, k_hi)",
    "agg_grouping_sets": f"select k_lo, k_hi, cast(sum(n) as bigint) as n from ({_CLASS}) group by grouping sets ((k_lo), (k_hi), ())",
    "agg_percentiles": "select percentile(deg, 0.5) as median, percentile(deg, 0.9) as p90, percentile(deg, 0.99) as p99 from (select l_partkey, count(distinct l_orderkey) as deg from lineitem group by l_partkey)",
    "agg_filtered": "select l_suppkey, count(*) filter (where l_returnflag = 'R') as returned, count(*) as n from lineitem group by l_suppkey",
    "agg_max_by": "select l_suppkey, max_by(l_partkey, l_orderkey * 1000000 + l_partkey) as last_part from lineitem group by l_suppkey",
    "agg_having": "select l_partkey, count(*) as n from lineitem group by l_partkey having count(*) > 30",
    "degree_histogram": f"select deg, count(*) as vertices from (select u, count(*) as deg from ({_EDGES}) group by u) group by deg",
    "agg_bool": "select l_suppkey, bool_and(l_quantity > 0) as all_positive, bool_or(l_quantity >= 50) as any_full from lineitem group by l_suppkey",
    "pivot_classes": "select l_returnflag, cast(sum(case when l_linestatus = 'O' then 1 else 0 end) as bigint) as o, cast(sum(case when l_linestatus = 'F' then 1 else 0 end) as bigint) as f from lineitem group by l_returnflag",
    # windows
    "window_ranks": "select c_custkey, c_nationkey, row_number() over w as rn, rank() over w as rk, dense_rank() over w as dr, round(percent_rank() over w, 6) as pr, round(cume_dist() over w, 6) as cd from customer window w as (partition by c_nationkey order by c_custkey)",
    "window_ntile_batches": "select s_suppkey, ntile(4) over (partition by s_nationkey order by s_suppkey) as batch from supplier",
    "window_lag_events": "select event_id, lag(event_id) over w as before_id, lead(event_id) over w as after_id, first_value(event_id) over w as first_id from events window w as (partition by user_id order by ts, event_id)",
    "window_running_edges": "select l_suppkey, l_partkey, cast(sum(n) over (partition by l_suppkey order by l_partkey rows between unbounded preceding and current row) as bigint) as running from (select l_suppkey, l_partkey, count(*) as n from lineitem group by l_suppkey, l_partkey)",
    "window_range_frame": "select k, d, count(*) over (partition by k order by d range between 5 preceding and current row) as near from (select l_suppkey as k, l_partkey as d, count(*) as n from lineitem group by l_suppkey, l_partkey)",
    "window_nth": "select distinct o_custkey, nth_value(o_orderkey, 2) over (partition by o_custkey order by o_orderkey rows between unbounded preceding and unbounded following) as second_order from orders",
    # sort, limit, top-k
    "topk_vertices": "select l_partkey, count(distinct l_orderkey) as deg from lineitem group by l_partkey order by deg desc, l_partkey limit 20",
    "topk_offset": "select l_suppkey, count(*) as n from lineitem group by l_suppkey order by n desc, l_suppkey limit 10 offset 5",
    "topk_per_group": "select s, p, n from (select l_suppkey as s, l_partkey as p, count(*) as n, row_number() over (partition by l_suppkey order by count(*) desc, l_partkey) as rn from lineitem group by l_suppkey, l_partkey) where rn <= 3",
    # set operations
    "set_union": "select l_partkey as id from lineitem union select l_suppkey from lineitem",
    "set_union_all": "select s_suppkey as id from supplier union all select c_custkey from customer",
    "set_intersect": "select l_partkey as id from lineitem intersect select l_suppkey from lineitem",
    "set_except": "select l_partkey as id from lineitem except select l_suppkey from lineitem",
    "set_except_all": "select l_partkey % 10 as id from lineitem except all select p_partkey % 10 from part",
    "set_intersect_all": "select l_partkey % 10 as id from lineitem intersect all select p_partkey % 10 from part",
    # strings, dates, numbers
    "str_keys": "select distinct concat('s', cast(l_suppkey as varchar(20))) as a, concat(substring(l_returnflag, 1, 1), '#', lower(l_linestatus)) as b, length(l_returnflag) as n from lineitem",
    "date_order_months": "select date_trunc('month', o_orderdate) as month_start, count(*) as n from orders group by date_trunc('month', o_orderdate)",
    "math_colour_arith": "select p_partkey, cast(floor(sqrt(p_partkey)) as bigint) as root, cast(ceil(p_partkey / 7.0) as bigint) as up, p_partkey % 8 + 1 as colour, round(ln(p_partkey + 1), 6) as lg, round(power(p_partkey, 1.5), 2) as work from part",
    "math_bits": "select p_partkey, bit_count(p_partkey) as ones, p_partkey & 7 as low, p_partkey | 8 as up from part",
    # subqueries, common table expressions
    "subquery_scalar": "select l_partkey, count(*) as n from lineitem group by l_partkey having count(*) > (select avg(k) from (select count(*) as k from lineitem group by l_partkey))",
    "cte_wedges": f"with e as ({_EDGES}), d as (select v, count(*) as deg from e group by v) select cast(sum(deg * (deg - 1) / 2) as bigint) as wedges from d",
    "sql_view_triangles": "with e as (select distinct l_suppkey * 3 as a, ascii(l_returnflag) * 3 + 1 as b, ascii(l_linestatus) * 3 + 2 as c from lineitem) select count(*) as triangles from (select distinct a, b from e) x join (select distinct b, c from e) y on x.b = y.b join (select distinct a, c from e) z on z.a = x.a and z.c = y.c",
    # events
    "join_asof": "select event_id, max(case when event_type = 'purchase' then event_id end) over (partition by user_id order by ts, event_id rows between unbounded preceding and 1 preceding) as last_purchase from events",
}

#: Texts of the other dialect, for names above or for queries that only it words differently.
DUCK: dict[str, str] = {
    "join_sort_merge": "select l_orderkey, l_partkey, o_custkey from lineitem join orders on l_orderkey = o_orderkey",
    "join_shuffle_hash": "select l_orderkey, l_suppkey, o_custkey from lineitem join orders on l_orderkey = o_orderkey",
    "agg_percentiles": "select quantile_cont(deg, 0.5) as median, quantile_cont(deg, 0.9) as p90, quantile_cont(deg, 0.99) as p99 from (select l_partkey, count(distinct l_orderkey) as deg from lineitem group by l_partkey)",
    "math_bits": "select p_partkey, cast(bit_count(p_partkey) as integer) as ones, p_partkey & 7 as low, p_partkey | 8 as up from part",
    "str_keys": "select distinct concat('s', cast(l_suppkey as varchar)) as a, concat(substring(l_returnflag, 1, 1), '#', lower(l_linestatus)) as b, cast(length(l_returnflag) as integer) as n from lineitem",
}

_WORD = re.compile(r"(from|join|,)(\s+)(" + "|".join(TABLES) + r")\b")


def relation_query(text: str) -> Callable[[SparkSession, str], DataFrame]:
    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        used = {m[2] for m in _WORD.findall(text)}
        marked = _WORD.sub(r"\1\2{\3}", text)
        return spark.sql(marked, **{t: spark.read.parquet(f"{sf_dir}/{t}.parquet").alias(t) for t in used})

    return query
