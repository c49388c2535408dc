"""DuckDB twins of ``relational``: same names, same columns."""

from __future__ import annotations

from ..core.mix import mix_sql
from .relational import BANDS, KINDS

_bands = ", ".join(f"({b}, {lo}, {hi})" for b, lo, hi in BANDS)
_agg = "count(*) as n, round(sum(o_totalprice), 2) as total"
_o = "(select *, year(o_orderdate) as year from orders)"
_kv = "cast(unnest(range(len(embedding))) as integer) as p, cast(unnest(embedding) as double) as x"

TWINS = {
    "op_scan_prune": "select l_returnflag, count(*) as n, round(sum(l_quantity), 4) as qty from lineitem group by 1",
    "op_filter_pushdown": "select count(*) as n, round(sum(l_extendedprice * l_discount), 2) as revenue from lineitem where l_shipdate >= timestamp '1995-01-01' and l_shipdate < timestamp '1996-01-01' and l_quantity < 24",
    "op_filter_pattern": "select p_partkey, p_name, p_brand, p_size from part where p_name like '%a%' and regexp_matches(p_brand, '[1-3]$') and p_size in (1, 5, 10, 15, 20)",
    "op_case_coalesce": "select case when o_totalprice > 200000 then 'large' when o_totalprice > 50000 then 'middle' else 'small' end as kind, o_orderstatus is not distinct from 'F' as done, count(*) as n, 'none' as filled from orders group by 1, 2",
    "op_join_inner_broadcast": "select r_name, count(*) as n, round(sum(o_totalprice), 2) as total from orders join customer on o_custkey = c_custkey join nation on c_nationkey = n_nationkey join region on n_regionkey = r_regionkey group by 1",
    "op_join_sort_merge": "select o_orderpriority, count(*) as n, round(sum(l_extendedprice), 2) as total from lineitem join orders on l_orderkey = o_orderkey group by 1",
    "op_join_shuffle_hash": "select p_brand, count(*) as n, round(sum(l_quantity), 2) as qty from lineitem join part on l_partkey = p_partkey group by 1",
    "op_join_left": "select c_mktsegment, count(o_orderkey) as n_orders, count(*) filter (where o_orderkey is null) as n_without from customer left join orders on c_custkey = o_custkey group by 1",
    "op_join_right": "select lang, count(quality) as labelled, count(*) as n from labels right join documents using (doc_id) group by 1",
    "op_join_full": "select n_name, count(s_suppkey) as n from nation full join supplier on n_nationkey = s_nationkey group by 1",
    "op_join_self_twohop": "with e as (select vec_id as id, cast(embedding as double[]) as v from embeddings), a as (select x.id as src, y.id as dst, list_sum(list_transform(list_zip(x.v, y.v), lambda z: (z[1] - z[2]) * (z[1] - z[2]))) as d2 from e x, e y where x.id <> y.id), g as materialized (select src, dst from (select *, row_number() over (partition by src order by d2, dst) as r from a) where r <= 10) select p.src, q.dst as far, count(*) as ways from g p join g q on p.dst = q.src where p.src <> q.dst and not exists (select 1 from g where g.src = p.src and g.dst = q.dst) group by 1, 2",
    "op_join_semi": "select lang, count(*) as n from documents where doc_id in (select doc_id from labels) group by 1",
    "op_join_anti": "select lang, count(*) as n from documents where doc_id not in (select doc_id from labels) group by 1",
    "op_join_cross": "select x.r_name as a, y.r_name as b from region x, region y",
    "op_join_theta": "select a.p_brand, count(*) as pairs from part a join part b on a.p_brand = b.p_brand and a.p_partkey < b.p_partkey and abs(a.p_retailprice - b.p_retailprice) < 0.5 group by 1",
    "op_join_range": f"select band, count(*) as n from lineitem join (values {_bands}) t(band, low, high) on l_extendedprice >= low and l_extendedprice < high group by 1",
    "op_join_interval": "select v.user_id, count(*) as pairs from events v join events c on v.user_id = c.user_id and v.event_type = 'view' and c.event_type = 'click' and c.ts >= v.ts and c.ts <= v.ts + interval 10 minutes group by 1",
    "op_join_asof": "select event_id, user_id, view_id from (select *, last_value(case when event_type = 'view' then event_id end ignore nulls) over (partition by user_id order by ts, event_id rows between unbounded preceding and 1 preceding) as view_id from events where event_type in ('view', 'purchase')) where event_type = 'purchase'",
    "op_join_lateral_topk": "select l_suppkey, l_partkey, revenue, rank from (select *, row_number() over (partition by l_suppkey order by revenue desc, l_partkey) as rank from (select l_suppkey, l_partkey, round(sum(l_extendedprice), 2) as revenue from lineitem group by 1, 2)) where rank <= 3",
    "op_agg_hash": "select l_returnflag, l_linestatus, round(sum(l_quantity), 2) as qty, round(sum(l_extendedprice * (1 - l_discount)), 2) as net, round(avg(l_discount), 6) as disc, count(*) as n from lineitem group by 1, 2",
    "op_agg_sort": "select p_type, max(p_name) as last_name, min(p_name) as first_name from part group by 1",
    "op_agg_distinct": "select event_type, count(distinct user_id) as users, count(distinct cast(ts as date)) as days from events group by 1",
    "op_agg_percentile": "select event_type, round(quantile_cont(value, 0.5), 6) as median, round(quantile_cont(value, 0.9), 6) as p90 from events group by 1",
    "op_agg_filter": "select o_orderpriority, count(*) filter (where o_orderstatus = 'O') as open, count(*) filter (where o_totalprice > 100000) as big from orders group by 1",
    "op_agg_stats": "select l_returnflag, round(stddev(l_quantity), 4) as sd, round(variance(l_discount), 6) as var, round(corr(l_quantity, l_extendedprice), 4) as corr, round(covar_samp(l_quantity, l_tax), 6) as cov from lineitem group by 1",
    "op_agg_minmaxby": "select source, n_chars as longest, doc_id from (select *, row_number() over (partition by source order by n_chars desc, doc_id) as r from documents) where r = 1",
    "op_agg_collect": "select user_id, string_agg(event_type, '>' order by n) as path from (select *, row_number() over (partition by user_id order by ts, event_id) as n from events) where n <= 5 group by 1",
    "op_grouping_sets": f"select o_orderstatus, year, {_agg} from {_o} group by grouping sets ((o_orderstatus), (year), ())",
    "op_cube": f"select o_orderstatus, year, {_agg} from {_o} group by cube (o_orderstatus, year)",
    "op_rollup": f"select o_orderstatus, o_orderpriority, {_agg} from {_o} group by rollup (o_orderstatus, o_orderpriority)",
    "op_pivot": "select user_id, " + ", ".join(f"count(*) filter (where event_type = '{k}') as n_{k}" for k in KINDS) + " from events group by 1",
    "op_unpivot": "select l_returnflag, 'qty' as measure, round(sum(l_quantity), 2) as value from lineitem group by 1 union all select l_returnflag, 'tax', round(sum(l_tax), 2) from lineitem group by 1",
    "op_having": "select l_suppkey, round(sum(l_extendedprice), 2) as revenue from lineitem group by 1 having round(sum(l_extendedprice), 2) > 1000000",
    "op_win_rank": "select c_custkey, row_number() over w as rn, rank() over v as rk, dense_rank() over v as dr, ntile(4) over w as quarter, round(percent_rank() over v, 6) as pr, round(cume_dist() over v, 6) as cd from customer window w as (partition by c_nationkey order by c_acctbal desc, c_custkey), v as (partition by c_nationkey order by c_mktsegment)",
    "op_win_offset": "select event_id, lag(event_type) over w as before, lead(event_type) over w as after, first_value(event_type) over f as first, last_value(event_type) over f as last, nth_value(event_type, 2) over f as second from events window w as (partition by user_id order by ts, event_id), f as (partition by user_id order by ts, event_id rows between unbounded preceding and unbounded following)",
    "op_win_rows": "select event_id, round(avg(value) over (partition by user_id order by ts, event_id rows between 6 preceding and current row), 4) as avg7 from events",
    "op_win_range": "select event_id, round(sum(value) over (partition by user_id order by cast(floor(epoch(ts)) as bigint) range between 86400 preceding and current row), 4) as day_sum from events",
    "op_win_session": "select user_id, max(session) + 1 as sessions from (select *, sum(new) over (partition by user_id order by ts, event_id) as session from (select *, case when ts > lag(ts) over (partition by user_id order by ts, event_id) + interval 30 minutes then 1 else 0 end as new from events)) group by 1",
    "op_sort_limit": "select o_orderkey, o_totalprice from orders order by o_totalprice desc, o_orderkey limit 10",
    "op_topk": "select l_partkey, round(sum(l_quantity), 2) as qty from lineitem group by 1 order by qty desc, l_partkey limit 20",
    "op_topk_group": "select o_orderpriority, o_orderkey, rank from (select *, row_number() over (partition by o_orderpriority order by o_totalprice desc, o_orderkey) as rank from orders) where rank <= 5",
    "op_offset": "select c_custkey, c_name from customer order by c_custkey limit 10 offset 20",
    "op_union": "select k, count(*) as n from (select c_custkey as k from customer union all select o_custkey from orders) group by 1",
    "op_union_by_name": "select count(*) as n, round(sum(x), 2) as total from (select c_custkey as k, c_acctbal as x from customer union all by name select s_acctbal as x, s_suppkey as k from supplier)",
    "op_intersect": "select c_custkey as k from customer intersect select o_custkey from orders",
    "op_intersect_all": "select o_custkey as k from orders intersect all (select c_custkey from customer union all select c_custkey from customer)",
    "op_except": "select c_custkey as k from customer except select o_custkey from orders",
    "op_except_all": "select o_custkey as k from orders except all select c_custkey from customer",
    "op_distinct": "select distinct lang, source from documents",
    "op_dedupe": "select md5(text) as digest, min(doc_id) as doc_id, count(*) as n from documents group by 1 having count(*) > 1",
    "op_str": "select p_partkey, upper(trim(p_name)) as up, substr(p_name, 2, 4) as sub, split_part(p_name, ' ', 1) as head, regexp_replace(p_name, '[aeiou]', '_', 'g') as re, levenshtein(p_brand, 'Brand#11') as lev, concat_ws('-', p_brand, p_type) as cat, lpad(cast(p_size as varchar), 5, '0') as pad from part",
    "op_date": "select o_orderkey, cast(date_trunc('month', o_orderdate) as timestamp) as month, date_diff('day', cast(o_orderdate as date), date '1999-01-01') as days, year(o_orderdate) as y, quarter(o_orderdate) as q, strftime(o_orderdate, '%Y-%m') as ym, cast(cast(o_orderdate as date) + 30 as date) as later from orders",
    "op_math": "select l_returnflag, round(sum(pow(l_discount, 2)), 4) as p, round(sum(sqrt(l_quantity)), 2) as sq, round(sum(ln(l_extendedprice)), 2) as lg, round(sum(acos(l_discount)), 2) as ac, sum(l_orderkey % 7) as pm, round(sum(greatest(l_tax, l_discount)), 2) as gr from lineitem group by 1",
    "op_array": "select vec_id, round(sqrt(list_sum(list_transform(v, lambda x: x * x))), 4) as norm, round(list_min(v), 6) as low, round(list_sum(v[1:4]), 5) as head, len(list_filter(v, lambda x: x > 0.3)) > 0 as any_big, len(list_filter(v, lambda x: x <= -1)) = 0 as all_ok, len(list_filter(v, lambda x: x > 0)) as positive from (select vec_id, cast(embedding as double[]) as v from embeddings)",
    "op_map": "select user_id, 2 * count(*) filter (where event_type = 'view') as twice_views, count(distinct event_type) as kinds from events group by 1",
    "op_json": "select event_type, sum(cast(json_extract_string(props, '$.k') as bigint)) as k1, sum(cast(json_extract_string(props, '$.k') as bigint)) as k2 from events group by 1",
    "op_decimal": "select o_orderstatus, cast(sum(cast(o_totalprice as decimal(18, 2))) as double) as total from orders group by 1",
    "op_url_html": "select page_id, regexp_extract(url, '^[a-z]+://([^/?#:]+)', 1) as host, regexp_replace(regexp_extract(html, '<title>([^<]*)</title>', 1), '<[^>]*>', '', 'g') as title from pages",
    "op_subquery_scalar": "select o_orderstatus, count(*) as n from orders where o_totalprice > 2 * (select avg(o_totalprice) from orders) group by 1",
    "op_subquery_exists": "select c_mktsegment, count(*) as n from customer where exists (select 1 from orders where o_custkey = c_custkey and o_totalprice > 150000) group by 1",
    "op_subquery_in": "select s_suppkey, s_name from supplier where s_nationkey in (select n_nationkey from nation where n_regionkey = 1)",
    "op_cte_recursive": "with recursive tree(level, node, region) as (select 0, r_name, r_regionkey from region union all select level + 1, n_name, tree.region from tree join nation on n_regionkey = tree.region where level = 0) select level, region, count(*) as n from tree group by 1, 2",
    "op_sample_portable": f"select vec_id from embeddings where {mix_sql('42', 'vec_id')} % 10 = 0",
    "op_quantise": "select vec_id, cast(list_sum(list_transform(v, lambda x: floor(x * 127 + 0.5))) as bigint) as sum_q, round(sqrt(list_sum(list_transform(v, lambda x: pow(x - floor(x * 127 + 0.5) / 127, 2)))), 5) as err from (select vec_id, cast(embedding as double[]) as v from embeddings)",
    "op_centroid": f"select label, p, round(avg(x), 6) as mean from (select label, {_kv} from embeddings) group by 1, 2",
    "op_tumbling": "select cast(date_trunc('day', ts) as timestamp) as start, event_type, count(*) as n from events group by 1, 2",
    "op_sliding": "select start, count(*) as n from (select cast(date_trunc('day', ts) as timestamp) - to_days(cast(i as integer)) as start from events, range(0, 2) t(i)) group by 1",
    "op_session_window": "select user_id, min(ts) as start, count(*) as n from (select *, sum(new) over (partition by user_id order by ts, event_id) as g from (select *, case when ts >= lag(ts) over (partition by user_id order by ts, event_id) + interval 30 minutes then 1 else 0 end as new from events)) group by user_id, g",
}
