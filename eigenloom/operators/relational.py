"""The relational surface around the methods: edge lists and small statistics made from the given tables.

Each statement runs as it stands in Spark SQL, with tables as DataFrame parameters, and in DuckDB.
"""

from __future__ import annotations

import re

from pyspark.sql import DataFrame, SparkSession

STATEMENTS: dict[str, str] = {
    "rel_scan_project": "select l_orderkey, l_partkey, l_quantity * 2 as doubled from {lineitem}",
    "rel_filter_predicates": "select l_orderkey, l_partkey, l_quantity from {lineitem} where l_quantity between 10 and 20 and l_returnflag in ('A', 'R') and l_linestatus like 'F%' and l_shipdate is not null",
    "rel_case_cast": "select o_orderkey, case when o_totalprice >= 100000 then 'high' when o_totalprice >= 1000 then 'mid' else 'low' end as band, cast(floor(o_totalprice) as bigint) as whole, coalesce(o_orderpriority, 'none') as priority from {orders}",
    "rel_join_broadcast": "select c_custkey, n_name from {customer} join {nation} on c_nationkey = n_nationkey",
    "rel_join_left": "select c_custkey, count(o_orderkey) as degree from {customer} left join {orders} on c_custkey = o_custkey group by c_custkey",
    "rel_join_right": "select c_custkey, count(o_orderkey) as degree from {orders} right join {customer} on c_custkey = o_custkey group by c_custkey",
    "rel_join_full": "select coalesce(p_partkey, l_partkey) as part, count(l_orderkey) as uses from {part} full join {lineitem} on p_partkey = l_partkey group by coalesce(p_partkey, l_partkey)",
    "rel_join_semi": "select c_custkey from {customer} left semi join (select o_custkey from {orders} where o_totalprice > 1000) o on c_custkey = o_custkey",
    "rel_join_anti": "select p_partkey from {part} left anti join (select l_partkey from {lineitem} where l_quantity >= 49) l on p_partkey = l_partkey",
    "rel_join_cross": "select r_regionkey, n_nationkey, case when r_regionkey = n_regionkey then 1 else 0 end as same from {region} cross join {nation}",
    # The pairs of the theta join counted without making them: customers above a supplier's balance, less those of its own nation. Whole units of balance are added up first; only rows of one unit meet in a window.
    "rel_join_theta": "with e as (select s_suppkey, s_nationkey as k, s_acctbal as v, 0 as n from {supplier} union all select null, c_nationkey, c_acctbal, 1 from {customer}), b as (select *, case when isnan(v) then 9223372036854775807 else floor(v) end as b from e where k is not null and v is not null), "
    "t as (select k, b, sum(n) as n from b group by k, b), own as (select k, b, sum(n) over (partition by k order by b desc) - n as own_above from t), every as (select b, sum(n) over (order by b desc) - n as above from (select b, sum(n) as n from t group by b)), "
    "r as (select s_suppkey, k, b, n, sum(n) over (partition by b order by v desc) - sum(n) over (partition by b, v) as inside, sum(n) over (partition by k, b order by v desc) - sum(n) over (partition by k, b, v) as own_inside from b) "
    "select s_suppkey, cast(sum(above + inside - own_above - own_inside) as bigint) as richer from r join own using (k, b) join every using (b) where r.n = 0 group by s_suppkey having sum(above + inside - own_above - own_inside) > 0",
    "rel_join_range": "select p_partkey, count(*) as close from {part} join {supplier} on floor(p_retailprice / 100) = floor(s_acctbal / 100) and abs(p_retailprice - s_acctbal) <= 50 group by p_partkey",
    "rel_join_multiway": "select s_nationkey as i, c_nationkey as j, cast(count(*) as bigint) as w from {lineitem} join {orders} on l_orderkey = o_orderkey join {customer} on o_custkey = c_custkey join {supplier} on l_suppkey = s_suppkey group by s_nationkey, c_nationkey",
    "rel_agg_hash": "select l_returnflag, l_linestatus, cast(sum(l_quantity) as double) as qty, count(*) as n, cast(max(l_linenumber) as bigint) as last_line from {lineitem} group by l_returnflag, l_linestatus",
    "rel_agg_sort": "select l_suppkey, max(l_returnflag) as flag, min(l_linestatus) as status from {lineitem} group by l_suppkey",
    "rel_agg_distinct": "select l_returnflag, count(distinct l_partkey) as parts, count(distinct l_suppkey) as suppliers from {lineitem} group by l_returnflag",
    "rel_agg_stats": "select l_returnflag, round(avg(l_quantity), 6) as mean, round(stddev_samp(l_quantity), 6) as deviation, round(corr(l_quantity, l_extendedprice), 6) as correlation from {lineitem} group by l_returnflag",
    "rel_agg_having": "select l_partkey, count(*) as uses from {lineitem} group by l_partkey having count(*) >= 35",
    "rel_grouping_sets": "select l_returnflag, l_linestatus, count(*) as n from {lineitem} group by grouping sets ((l_returnflag), (l_linestatus), ())",
    "rel_cube": "select l_returnflag, l_linestatus, count(*) as n from {lineitem} group by cube (l_returnflag, l_linestatus)",
    "rel_rollup": "select l_returnflag, l_linestatus, count(*) as n from {lineitem} group by rollup (l_returnflag, l_linestatus)",
    "win_rank_family": "select o_orderkey, cast(row_number() over w as bigint) as rn, cast(rank() over w as bigint) as rk, cast(dense_rank() over w as bigint) as dr, cast(ntile(4) over w as bigint) as quarter, round(percent_rank() over w, 6) as pr, round(cume_dist() over w, 6) as cd from {orders} window w as (partition by o_custkey order by o_orderdate, o_orderkey)",
    "win_lag_lead": "select event_id, coalesce(lag(user_id) over (partition by event_type order by ts, event_id), -1) as before, coalesce(lead(user_id) over (partition by event_type order by ts, event_id), -1) as after from {events}",
    "win_first_last_nth": "select o_orderkey, first_value(o_orderkey) over w as first_key, last_value(o_orderkey) over w as last_key, coalesce(nth_value(o_orderkey, 2) over w, -1) as second_key from {orders} window w as (partition by o_custkey order by o_orderdate, o_orderkey rows between unbounded preceding and unbounded following)",
    "win_running_rows": "select o_orderkey, count(*) over (partition by o_custkey order by o_orderdate, o_orderkey rows between 2 preceding and current row) as recent from {orders}",
    "sort_global": "select o_custkey as i, cast(count(*) as bigint) as degree from {orders} group by o_custkey order by degree desc, i",
    "sort_topk_degree": "select l_partkey as j, cast(count(*) as bigint) as degree from {lineitem} group by l_partkey order by degree desc, j limit 20",
    "sort_limit_offset": "select l_partkey as j, cast(count(*) as bigint) as degree from {lineitem} group by l_partkey order by degree desc, j limit 10 offset 10",
    "set_union_all": "select s_nationkey as k from {supplier} union all select c_nationkey from {customer}",
    "set_union_distinct": "select s_nationkey as k from {supplier} union select c_nationkey from {customer}",
    "set_intersect": "select l_suppkey as k from {lineitem} where l_quantity > 45 intersect select l_suppkey from {lineitem} where l_quantity < 3",
    "set_intersect_all": "select s_nationkey as k from {supplier} intersect all select c_nationkey from {customer}",
    "set_except": "select p_partkey as k from {part} except select l_partkey from {lineitem} where l_quantity >= 49",
    "set_except_all": "select c_nationkey as k from {customer} except all select s_nationkey from {supplier}",
    "sub_scalar": "select o_orderkey from {orders} where o_totalprice > (select avg(o_totalprice) from {orders})",
    "sub_exists": "select c_custkey from {customer} where exists (select 1 from {orders} where o_custkey = c_custkey and o_orderstatus = 'F')",
    "sub_in": "select p_partkey from {part} where p_partkey in (select l_partkey from {lineitem} where l_quantity >= 50)",
    "sub_correlated": "select n_nationkey, (select count(*) from {customer} where c_nationkey = n_nationkey) as customers from {nation}",
    "cte_with": "with d as (select o_custkey as i, count(*) as degree from {orders} group by o_custkey) select degree, count(*) as vertices from d group by degree",
    "cte_recursive_reach": "with recursive r(node, depth) as (select cast(0 as int), 0 union all select cast((node * 2 + 1) % 25 as int), depth + 1 from r where depth < 12) select distinct n_nationkey from r join {nation} on node = n_nationkey",
    "str_hosts": "select page_id, regexp_extract(url, '^[a-z]+://([^/]+)', 1) as host from {pages}",
    "str_clean": "select page_id, upper(trim(replace(url, 'https://', ''))) as cleaned, cast(length(url) as bigint) as n from {pages}",
    "dt_parts": "select o_orderkey, cast(year(o_orderdate) as bigint) as y, cast(month(o_orderdate) as bigint) as m, cast(day(o_orderdate) as bigint) as d from {orders}",
    "dt_trunc_slices": "select cast(cast(date_trunc('month', o_orderdate) as date) as varchar(10)) as slice, count(*) as n from {orders} group by 1",
    "math_round_bits": "select n_nationkey, cast(n_nationkey & 7 as bigint) as low, cast(n_nationkey | 8 as bigint) as high, round(sqrt(n_nationkey), 6) as root, cast(greatest(n_nationkey, 12) as bigint) as top from {nation}",
    "math_trig_ring": "select n_nationkey, round(2 * cos(2 * pi() * n_nationkey / 25), 6) + 0.0 as value from {nation}",
    "smp_hash_sample": "select l_orderkey, l_partkey from {lineitem} where (l_orderkey * 7919 + l_linenumber) % 97 = 3",
    "degree_histogram": "with d as (select l_partkey, count(*) as degree from (select distinct o_custkey, l_partkey from {lineitem} join {orders} on l_orderkey = o_orderkey) e group by l_partkey) select degree, count(*) as vertices from d group by degree",
    "rel_join_shuffle_hash": "select /*+ shuffle_hash({orders}) */ l_orderkey, l_linenumber, o_custkey from {lineitem} join {orders} on l_orderkey = o_orderkey",
    "rel_join_sort_merge": "select /*+ merge({orders}) */ l_orderkey, l_linenumber, o_orderpriority from {lineitem} join {orders} on l_orderkey = o_orderkey",
    "rel_join_asof": "select event_id, coalesce(last_value(case when event_type = 'error' then event_id end) ignore nulls over (partition by user_id order by ts, event_id rows between unbounded preceding and 1 preceding), -1) as last_error from {events}",
    "rel_agg_approx": "select l_returnflag, abs(approx_count_distinct(l_partkey, 0.01) - count(distinct l_partkey)) <= 0.05 * count(distinct l_partkey) as within from {lineitem} group by l_returnflag",
    "rel_agg_collect": "select o_custkey as i, array_join(sort_array(collect_list(o_orderkey)), ',') as cols from {orders} group by o_custkey",
    "rel_pivot": "select * from (select user_id, event_type from {events}) pivot (count(1) for event_type in ('click', 'error', 'purchase', 'signup', 'view'))",
    "rel_unpivot": "select s_suppkey, kind, amount from (select s_suppkey, cast(s_nationkey as double) as nation, s_acctbal as balance from {supplier}) unpivot (amount for kind in (nation, balance))",
    "win_range_frame": "select o_orderkey, count(*) over (partition by o_custkey order by datediff(o_orderdate, date '1970-01-01') range between 30 preceding and current row) as recent from {orders}",
    "lateral_topn": "select n_nationkey, c_custkey from {nation} join lateral (select c_custkey from {customer} where c_nationkey = n_nationkey order by c_acctbal desc, c_custkey limit 3) on true",
    "str_tokens": "select term, count(*) as n from (select explode(split(lower(text), '[^a-z]+')) as term from {documents}) where term <> '' group by term",
    "str_hrefs": """select path, count(*) as n from (select explode(regexp_extract_all(html, 'href="([^"]*)"', 1)) as path from {pages}) group by path""",
    "dt_interval_shift": "select o_orderkey, cast(cast(o_orderdate + interval '1' month as date) as varchar(10)) as later, cast(cast(o_orderdate - interval '7' day as date) as varchar(10)) as earlier from {orders}",
    "math_tile_keys": "select o_orderkey, shiftright(o_custkey, 8) as tr, shiftright(o_orderkey, 8) as tc, o_custkey & 255 as r, pmod(o_orderkey - 7, 256) as c from {orders}",
    "arr_transform": "select vec_id, round(aggregate(transform(embedding, x -> cast(x as double) * 2 + 1), cast(0 as double), (a, x) -> a + x), 4) + 0.0 as value from {embeddings}",
    "arr_zip_with": "select vec_id, round(aggregate(zip_with(embedding, reverse(embedding), (x, y) -> cast(x as double) * cast(y as double)), cast(0 as double), (a, x) -> a + x), 4) + 0.0 as value from {embeddings}",
    "arr_aggregate": "select vec_id, round(sqrt(aggregate(embedding, cast(0 as double), (a, x) -> a + cast(x as double) * cast(x as double))), 4) as norm from {embeddings}",
    "arr_filter_exists": "select vec_id, cast(size(filter(embedding, x -> x > 0)) as bigint) as positive, exists(embedding, x -> x > 0.3) as any_large from {embeddings}",
    "arr_slice_sequence": "select vec_id, cast(size(slice(embedding, 9, 8)) as bigint) as n, round(aggregate(sequence(9, 16), cast(0 as double), (a, k) -> a + cast(embedding[k - 1] as double)), 4) + 0.0 as total from {embeddings}",
    "arr_posexplode": "select label, cast(place as bigint) as place, sum(case when x > 0 then 1 else 0 end) as positive from {embeddings} lateral view posexplode(embedding) as place, x group by label, place",
    "map_from_entries": "select user_id, cast(size(m) as bigint) as kinds, array_join(sort_array(transform(map_entries(m), e -> concat(e.key, '=', e.value))), ',') as cells from (select user_id, map_from_entries(collect_list(struct(event_type, n))) as m from (select user_id, event_type, count(*) as n from {events} group by user_id, event_type) group by user_id)",
    "map_lookup": "select user_id, coalesce(element_at(m, 'click'), 0) as clicks, coalesce(element_at(m, 'missing'), 0) as missing from (select user_id, map_from_entries(collect_list(struct(event_type, n))) as m from (select user_id, event_type, count(*) as n from {events} group by user_id, event_type) group by user_id)",
    "json_props": "select event_id, cast(get_json_object(props, '$.k') as bigint) as k, cast(from_json(props, 'k int').k as bigint) * 2 as doubled from {events}",
}
#: Where DuckDB spells a statement differently.
IN_DUCKDB = {
    "rel_join_theta": "select s_suppkey, count(*) as richer from supplier join customer on s_acctbal < c_acctbal and s_nationkey <> c_nationkey group by s_suppkey",
    "rel_join_shuffle_hash": "select l_orderkey, l_linenumber, o_custkey from lineitem join orders on l_orderkey = o_orderkey",
    "rel_join_sort_merge": "select l_orderkey, l_linenumber, o_orderpriority from lineitem join orders on l_orderkey = o_orderkey",
    "rel_join_asof": "select e.event_id, coalesce(r.event_id, -1) as last_error from events e asof left join (select * from events where event_type = 'error') r on e.user_id = r.user_id and e.ts > r.ts",
    "rel_agg_approx": "select l_returnflag, true as within from lineitem group by l_returnflag",
    "rel_agg_collect": "select o_custkey as i, string_agg(cast(o_orderkey as varchar), ',' order by o_orderkey) as cols from orders group by o_custkey",
    "rel_pivot": "select user_id, " + ", ".join(f"count_if(event_type = '{k}')::bigint as {k}" for k in ("click", "error", "purchase", "signup", "view")) + " from events group by user_id",
    "rel_unpivot": "select s_suppkey, 'nation' as kind, cast(s_nationkey as double) as amount from supplier union all select s_suppkey, 'balance', s_acctbal from supplier where s_acctbal is not null",
    "win_range_frame": "select o_orderkey, count(*) over (partition by o_custkey order by date_diff('day', date '1970-01-01', cast(o_orderdate as date)) range between 30 preceding and current row) as recent from orders",
    "lateral_topn": "select c_nationkey as n_nationkey, c_custkey from customer qualify row_number() over (partition by c_nationkey order by c_acctbal desc, c_custkey) <= 3",
    "str_tokens": "select term, count(*) as n from (select unnest(regexp_split_to_array(lower(text), '[^a-z]+')) as term from documents) where term <> '' group by term",
    "str_hrefs": """select path, count(*) as n from (select unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) as path from pages) group by path""",
    "math_tile_keys": "select o_orderkey, o_custkey >> 8 as tr, o_orderkey >> 8 as tc, o_custkey & 255 as r, ((o_orderkey - 7) % 256 + 256) % 256 as c from orders",
    "arr_transform": "select vec_id, round(list_sum(list_transform(embedding, lambda x: x::double * 2 + 1)), 4) + 0.0 as value from embeddings",
    "arr_zip_with": "select vec_id, round(list_sum(list_transform(list_zip(embedding, list_reverse(embedding)), lambda p: p[1]::double * p[2]::double)), 4) + 0.0 as value from embeddings",
    "arr_aggregate": "select vec_id, round(sqrt(list_sum(list_transform(embedding, lambda x: x::double * x::double))), 4) as norm from embeddings",
    "arr_filter_exists": "select vec_id, cast(len(list_filter(embedding, lambda x: x > 0)) as bigint) as positive, len(list_filter(embedding, lambda x: x > 0.3)) > 0 as any_large from embeddings",
    "arr_slice_sequence": "select vec_id, cast(len(embedding[9:16]) as bigint) as n, round(list_sum(list_transform(embedding[9:16], lambda x: x::double)), 4) + 0.0 as total from embeddings",
    "arr_posexplode": "select label, place - 1 as place, cast(sum(case when x > 0 then 1 else 0 end) as bigint) as positive from (select label, unnest(embedding) as x, unnest(range(1, len(embedding) + 1)) as place from embeddings) group by 1, 2",
    "map_from_entries": "select user_id, count(*) as kinds, string_agg(event_type || '=' || n, ',' order by event_type || '=' || n) as cells from (select user_id, event_type, count(*) as n from events group by 1, 2) group by 1",
    "map_lookup": "select user_id, cast(count_if(event_type = 'click') as bigint) as clicks, cast(0 as bigint) as missing from events group by 1",
    "json_props": "select event_id, cast(json_extract_string(props, '$.k') as bigint) as k, cast(json_extract_string(props, '$.k') as bigint) * 2 as doubled from events",
    "rel_join_semi": "select c_custkey from customer where c_custkey in (select o_custkey from orders where o_totalprice > 1000)",
    "rel_join_anti": "select p_partkey from part where not exists (select 1 from lineitem where p_partkey = l_partkey and l_quantity >= 49)",
}


def tables_of(statement: str) -> list[str]:
    return sorted(set(re.findall(r"\{(\w+)\}", statement)))


def query(statement: str):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        return spark.sql(statement, **{t: spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in tables_of(statement)})

    return run


def queries() -> dict:
    return {name: query(statement) for name, statement in STATEMENTS.items()}


def oracle_sql() -> dict[str, str]:
    return {name: IN_DUCKDB.get(name) or re.sub(r"\{(\w+)\}", r"\1", statement) for name, statement in STATEMENTS.items()}
