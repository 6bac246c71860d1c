"""Operator coverage in SQL that both engines read; tables stand in braces."""

COVERAGE = {
    "scan_pruned_reads": "select doc_id, lang, n_chars from {documents} where lang = 'en' and n_chars between 500 and 5000",
    "predicate_mix": "select l_orderkey, l_partkey, l_suppkey, l_linenumber, case when l_quantity > 40 then 'many' when l_quantity > 20 then 'some' else 'few' end as size from {lineitem} where l_returnflag in ('A', 'R') and l_discount between 0.02 and 0.05 and l_linestatus like 'O%' and l_returnflag is not distinct from 'A'",
    "join_inner_smj": "select o_orderpriority, count(*) as n from {orders} join {lineitem} on o_orderkey = l_orderkey group by o_orderpriority",
    "join_broadcast": "select n_name, count(*) as n from {customer} join {nation} on c_nationkey = n_nationkey group by n_name",
    "join_semi": "select c_custkey from {customer} where exists (select 1 from {orders} where o_custkey = c_custkey)",
    "join_anti": "select p_partkey from {part} where not exists (select 1 from {lineitem} where l_partkey = p_partkey)",
    "join_left_idle": "select s_suppkey, count(l_orderkey) as lines from {supplier} left join {lineitem} on s_suppkey = l_suppkey and l_quantity > 49 group by s_suppkey",
    "join_full_eadd": "select coalesce(a.k, b.k) as k, coalesce(a.n, 0) as orders, coalesce(b.n, 0) as suppliers from (select c_nationkey as k, count(*) as n from {customer} group by 1) a full join (select s_nationkey as k, count(*) as n from {supplier} group by 1) b on a.k = b.k",
    "join_range_events": "select a.event_id, count(*) as near from {events} a join {events} b on a.user_id = b.user_id and b.ts > a.ts and b.ts <= a.ts + interval '6' hour group by a.event_id",
    "agg_hash": "select l_returnflag, l_linestatus, count(*) as n, min(l_shipdate) as first_ship, max(l_quantity) as most from {lineitem} group by l_returnflag, l_linestatus",
    "agg_distinct": "select l_partkey, count(distinct l_orderkey) as orders, count(distinct l_suppkey) as suppliers from {lineitem} group by l_partkey",
    "agg_min_max_by": "select user_id, min_by(event_id, ts) as first_event, max_by(event_id, ts) as last_event from {events} group by user_id",
    "agg_rollup": "select lang, source, count(*) as n, cast(sum(n_chars) as bigint) as chars from {documents} group by rollup (lang, source)",
    "agg_cube": "select l_returnflag, l_linestatus, count(*) as n from {lineitem} group by cube (l_returnflag, l_linestatus)",
    "agg_grouping_sets": "select o_orderstatus, o_orderpriority, count(*) as n from {orders} group by grouping sets ((o_orderstatus), (o_orderpriority), ())",
    "agg_pivot_sums": "select lang, cast(sum(case when n_chars < 1000 then 1 else 0 end) as bigint) as small, cast(sum(case when n_chars >= 1000 then 1 else 0 end) as bigint) as large from {documents} group by lang",
    "agg_bits_bool": "select l_orderkey, bit_or(l_linenumber) as lines, bool_and(l_quantity > 10) as all_large from {lineitem} group by l_orderkey",
    "win_local_ids": "select s_nationkey as owner, s_suppkey, dense_rank() over (partition by s_nationkey order by s_suppkey) - 1 as lid from {supplier}",
    "win_chain_neighbours": "select o_orderkey, lag(o_orderkey) over (partition by o_custkey order by o_orderdate, o_orderkey) as before, lead(o_orderkey) over (partition by o_custkey order by o_orderdate, o_orderkey) as after from {orders}",
    "win_running_max": "select o_orderkey, max(o_totalprice) over (partition by o_custkey order by o_orderdate, o_orderkey rows between unbounded preceding and current row) as top from {orders}",
    "win_running_sum": "select doc_id, cast(sum(n_chars) over (partition by source order by doc_id rows between unbounded preceding and current row) as bigint) as chars from {documents}",
    "win_range_interval": "select event_id, count(*) over (partition by user_id order by ts range between interval '1' day preceding and current row) as n from {events}",
    "win_rank_family": "select o_orderkey, rank() over (partition by o_orderstatus order by o_totalprice) as r, ntile(4) over (partition by o_orderstatus order by o_totalprice, o_orderkey) as q from {orders}",
    "win_first_last": "select event_id, first_value(event_type) over (partition by user_id order by ts, event_id) as first_type, nth_value(event_type, 2) over (partition by user_id order by ts, event_id rows between unbounded preceding and unbounded following) as second_type from {events}",
    "sort_limit_topk": "select doc_id, n_chars from {documents} order by n_chars desc, doc_id limit 10",
    "sort_group_topk": "select lang, doc_id, n_chars from (select lang, doc_id, n_chars, row_number() over (partition by lang order by n_chars desc, doc_id) as k from {documents}) x where k <= 3",
    "set_union": "select c_nationkey as k from {customer} union select s_nationkey from {supplier}",
    "set_intersect": "select l_suppkey from {lineitem} where l_quantity > 49 intersect select s_suppkey from {supplier} where s_acctbal > 0",
    "set_except": "select o_custkey from {orders} where o_orderstatus = 'O' except select o_custkey from {orders} where o_orderstatus = 'F'",
    "fn_math_bits": "select l_orderkey, l_partkey, l_linenumber, l_orderkey & 255 as low, greatest(l_orderkey, l_partkey) as top, abs(l_orderkey - l_partkey) as gap from {lineitem}",
    "sql_recursive_reach": "with recursive r as (select conv_id, turn from {conversations} where turn = 0 union all select c.conv_id, c.turn from r join {conversations} c on c.conv_id = r.conv_id and c.turn = r.turn + 1) select conv_id, turn from r",
    "join_self_triangle": "select x.l_orderkey as u, y.l_orderkey as v, count(*) as n from (select distinct l_orderkey, l_partkey, l_suppkey from {lineitem}) x join (select distinct l_orderkey, l_partkey, l_suppkey from {lineitem}) y on x.l_partkey = y.l_partkey and x.l_suppkey = y.l_suppkey and x.l_orderkey < y.l_orderkey group by x.l_orderkey, y.l_orderkey",
    "join_shuffle_hash": "select /*+ shuffle_hash(s) */ s_nationkey, count(*) as n from {lineitem} l join {supplier} s on l_suppkey = s_suppkey group by s_nationkey",
    "join_lateral_top1": "select c_custkey, x.o_orderkey from {customer} c cross join lateral (select o_orderkey from {orders} o where o.o_custkey = c.c_custkey order by o_totalprice desc, o_orderkey limit 1) x",
    "agg_distribution": "select o_orderpriority, cast(count(*) filter (where o_totalprice > 1000) as bigint) as large, count(distinct o_custkey) as customers from {orders} group by o_orderpriority",
    "set_intersect_all": "select c_nationkey as k from {customer} intersect all select s_nationkey from {supplier}",
    "set_except_all": "select c_nationkey as k from {customer} except all select s_nationkey from {supplier}",
    "exists_scalar_mask": "select l_orderkey, l_linenumber from {lineitem} where l_quantity > (select avg(l_quantity) from {lineitem}) and l_suppkey in (select s_suppkey from {supplier} where s_acctbal < 0)",
}

#: What Spark runs in place of a text above.  It turns a limit in a lateral subquery into a sort of the whole table and a
#: numbering without an order of its own, and blocks of a shuffle arrive in any order, so the subquery numbers its rows itself.
SPARK = {
    "join_lateral_top1": "select c_custkey, x.o_orderkey from {customer} c cross join lateral (select o_orderkey from (select o_custkey, o_orderkey, row_number() over (partition by o_custkey order by o_totalprice desc, o_orderkey nulls last) as place from {orders}) o where o.place = 1 and o.o_custkey = c.c_custkey) x",
}
