"""DuckDB SQL of the relational operators and functions, by query name."""

from __future__ import annotations

from normgraph.oracles import paper as P
from normgraph.sources import registry

MD = "cast({0} as decimal(18,2))"
GEO = "customer join nation on c_nationkey = n_nationkey join region on n_regionkey = r_regionkey"
EV = "events"
W = "(partition by user_id order by ts, event_id)"
_props = ", ".join(f"('{n}')" for n in sorted({r[2] for r in registry.rows("star") if r[1] == "property"}))
_entries = ", ".join(f"('{k}', '{m}', {sum((r[1], r[2]) == (k, m) for r in registry.rows('star'))})" for k, m in sorted({(r[1], r[2]) for r in registry.rows("star")}))

SQL: dict[str, str] = {
    "op_scan_parquet": "select count(*) as n, min(o_orderkey) as lo, max(o_orderkey) as hi from orders",
    "op_scan_json": "select * from nation",
    "op_scan_csv": "select * from nation",
    "op_scan_orc": "select * from nation",
    "op_scan_text": "select n_name from nation",
    "op_scan_registry": f"with {P.corpus()}, e as (select * from (values {_entries}) v(kind, name, n)), u as (select 'class' as kind, gold_class as name from corpus union all select 'property', gold_pred from corpus), c as (select kind, name, count(*) as n_used from u group by all) select kind, cast(sum(n) as bigint) as n, cast(coalesce(sum(n_used), 0) as bigint) as n_sentences from e left join c using (kind, name) group by kind",
    "op_sink_partitioned": f"select count(*) as n, sum({MD.format('o_totalprice')}) as total from orders where o_orderstatus = 'F'",
    "op_project": "select l_orderkey, l_linenumber, cast(cast(l_extendedprice as decimal(18,2)) * (1 - cast(l_discount as decimal(18,2))) as double) as net, case when l_quantity > 25 then 'big' else 'small' end as size from lineitem",
    "op_filter": "select o_orderkey, o_totalprice, o_orderstatus, o_orderpriority from orders where o_totalprice between 10000 and 200000 and o_orderstatus in ('F', 'O') and o_orderpriority is distinct from '5-LOW'",
    "op_like": "select doc_id from documents where text like '%License%'",
    "op_rlike": "select doc_id from documents where regexp_matches(text, '[Vv]ersion [0-9]')",
    "op_join_inner": f"select o_orderkey, sum({MD.format('l_extendedprice')}) as revenue from orders join lineitem on o_orderkey = l_orderkey group by 1",
    "op_join_merge": "select c_mktsegment, count(*) as n from orders join customer on o_custkey = c_custkey group by 1",
    "op_join_shuffle_hash": "select c_nationkey, count(*) as n from orders join customer on o_custkey = c_custkey group by 1",
    "op_join_broadcast": "select r_name, count(*) as n from supplier join nation on s_nationkey = n_nationkey join region on n_regionkey = r_regionkey group by 1",
    "op_join_left": "select o_orderkey, count(l_orderkey) as k from orders left join lineitem on o_orderkey = l_orderkey group by 1",
    "op_join_right": "select c_custkey, count(o_custkey) as k from orders right join customer on o_custkey = c_custkey group by 1",
    "op_join_full": "select count(d.doc_id) as n_left, count(vec_id) as n_right, count(*) as n from documents d full join embeddings on doc_id = vec_id",
    "op_join_semi": "select lang, count(*) as n from documents where doc_id in (select doc_id from labels) group by 1",
    "op_join_anti": "select o_orderkey from orders where o_orderkey not in (select l_orderkey from lineitem)",
    "op_join_cross": f"select r_name, name from region, (values {_props}) v(name)",
    "op_join_theta": "select a.s_suppkey as a, b.s_suppkey as b from supplier a join supplier b on a.s_nationkey = b.s_nationkey and a.s_suppkey < b.s_suppkey and abs(a.s_acctbal - b.s_acctbal) < 100",
    "op_join_range": "select case when o_totalprice < 50000 then 'small' when o_totalprice < 150000 then 'middle' else 'large' end as name, count(*) as n from orders group by 1",
    "op_join_interval": "select c.event_id as click, p.event_id as purchase from events c join events p on c.user_id = p.user_id and c.event_type = 'click' and p.event_type = 'purchase' and p.ts >= c.ts and p.ts <= c.ts + interval 1 hour",
    "op_join_asof": "select p.event_id as purchase, (select arg_max(c.event_id, (c.ts, c.event_id)) from events c where c.user_id = p.user_id and c.event_type = 'click' and c.ts <= p.ts) as click from events p where event_type = 'purchase'",
    "op_join_self": "select md5(text) as digest, count(*) as n, min(doc_id) as first from documents group by 1 having count(*) > 1",
    "op_agg_basic": f"select l_returnflag, l_linestatus, count(*) as n, sum({MD.format('l_quantity')}) as qty, min(l_extendedprice) as lo, max(l_extendedprice) as hi, round(avg(l_quantity), 6) as mean from lineitem group by all",
    "op_agg_distinct": "select o_orderpriority, count(distinct o_custkey) as customers from orders group by 1",
    "op_agg_filter": "select quality, count(*) filter (toxic = 1) as toxic, count(*) as n from labels group by 1",
    "op_agg_rollup": f"select r_name, n_name, sum({MD.format('c_acctbal')}) as bal, cast(grouping(r_name, n_name) as int) as level from {GEO} group by rollup (r_name, n_name)",
    "op_agg_cube": f"select r_name, c_mktsegment, sum({MD.format('c_acctbal')}) as bal, count(*) as n from {GEO} group by cube (r_name, c_mktsegment)",
    "op_agg_sets": f"select r_name, c_mktsegment, count(*) as n from {GEO} group by grouping sets ((r_name), (c_mktsegment), ())",
    "op_agg_pivot": "select l_returnflag, count(*) filter (l_linestatus = 'F') as n_f, count(*) filter (l_linestatus = 'O') as n_o from lineitem group by 1",
    "op_agg_unpivot": "select c_custkey, 'c_name' as attribute, c_name as value from customer union all select c_custkey, 'c_mktsegment', c_mktsegment from customer",
    "op_agg_percentile": "select event_type, round(quantile_cont(value, 0.5), 9) as median, max(value) as hi from events group by 1",
    "op_agg_approx": "select distinct event_type, true as close from events",
    "op_agg_sketch": "select true as close",
    "op_agg_collect": "select o_custkey, string_agg(distinct o_orderpriority, ',' order by o_orderpriority) as priorities from orders group by 1",
    "op_agg_having": "select l_orderkey, count(*) as n from lineitem group by 1 having count(*) > 5",
    "op_agg_bool": "select c_nationkey, bool_or(c_acctbal < 0) as any_debt, bool_and(c_acctbal < 10000) as all_low from customer group by 1",
    "op_win_rank": "select c_custkey, row_number() over w as rn, rank() over v as rk, dense_rank() over v as dr, ntile(4) over w as nt, round(percent_rank() over v, 9) as pr, round(cume_dist() over v, 9) as cd from customer window w as (partition by c_mktsegment order by c_acctbal desc, c_custkey), v as (partition by c_mktsegment order by c_nationkey)",
    "op_win_lag": f"select event_id, lag(event_id) over w as previous, lead(event_type) over w as next_type from events window w as {W}",
    "op_win_frame_rows": "select event_id, round(avg(value) over (partition by user_id order by ts, event_id rows between 6 preceding and current row), 6) as mean7 from events",
    "op_win_frame_range": "select event_id, count(*) over (partition by user_id order by epoch(date_trunc('second', ts)) range between 86400 preceding and current row) as day_count from events",
    "op_win_value": "select event_id, first_value(event_id) over w as first_id, last_value(event_id) over w as last_id, nth_value(event_id, 2) over w as second_id from events window w as (partition by user_id order by ts, event_id rows between unbounded preceding and unbounded following)",
    "op_win_share": f"with {P.corpus()} select code, count(*) as n, round(count(*) / sum(count(*)) over (), 9) as share from codes group by 1",
    "op_sort": "select s_suppkey, s_acctbal from supplier order by s_acctbal desc, s_suppkey",
    "op_topk": "select c_custkey, c_acctbal from customer order by c_acctbal desc, c_custkey limit 10",
    "op_offset": "select c_custkey, c_acctbal from customer order by c_acctbal desc, c_custkey limit 10 offset 10",
    "op_topk_group": "select o_orderpriority, o_orderkey, row_number() over (partition by o_orderpriority order by o_totalprice desc, o_orderkey) as rn from orders qualify rn <= 3",
    "op_set_union": "select c_nationkey as k from customer union select s_nationkey from supplier",
    "op_set_union_all": "select k, count(*) as n from (select c_nationkey as k from customer union all select s_nationkey from supplier) group by 1",
    "op_set_intersect": "select c_nationkey as k from customer intersect select s_nationkey from supplier",
    "op_set_intersect_all": "select k, count(*) as n from (select c_nationkey as k from customer intersect all select s_nationkey from supplier) group by 1",
    "op_set_except": "select c_nationkey as k from customer where c_nationkey % 2 = 0 except select s_nationkey from supplier where s_nationkey > 20",
    "op_set_except_all": "select k, count(*) as n from (select c_nationkey as k from customer except all select s_nationkey from supplier) group by 1",
    "op_subquery_scalar": "select o_orderkey from orders where o_totalprice > (select avg(o_totalprice) * 1.8 from orders)",
    "op_subquery_correlated": "select c_custkey from customer c where c_acctbal > (select avg(c_acctbal) * 1.9 from customer d where d.c_mktsegment = c.c_mktsegment)",
    "op_subquery_exists": "select distinct o_orderkey from orders join lineitem on l_orderkey = o_orderkey where l_discount > 0.09",
    "op_subquery_in": "select c_custkey from customer where c_nationkey in (select s_nationkey from supplier where s_acctbal < 0)",
    "op_subquery_notin": "select n_name from nation where n_nationkey not in (select s_nationkey from supplier where s_acctbal > 9000)",
    "op_subquery_lateral": "select n_name, max(s_acctbal) as best from nation left join supplier on s_nationkey = n_nationkey group by n_nationkey, n_name",
    "op_cte": "select n, count(*) as customers from (select o_custkey, count(*) as n from orders group by 1) group by 1",
    "op_recursive_override": "with recursive e as (select n_nationkey as src, n_nationkey + 7 as dst from nation where n_nationkey + 7 < 25), r as (select src, dst, 1 as depth from e union all select r.src, e.dst, depth + 1 from r join e on r.dst = e.src where depth < 10) select * from r",
    "op_sample_hash": "select doc_id from documents where cast('0x' || substr(md5('42|s|' || doc_id), 1, 8) as bigint) % 100 < 10",
    "op_distinct_dedup": "select md5(text) as digest, min(doc_id) as doc_id from documents group by 1",
    "op_ngram_contain": r"""with w as (select doc_id, list_filter(string_split_regex(lower(text), '[\x20\x09-\x0D]+'), lambda x: x <> '') as w from documents), b as (select list_filter(string_split_regex(lower(text), '[\x20\x09-\x0D]+'), lambda x: x <> '') as w from benchmark),
 br as (select distinct array_to_string(w[i : i + 7], ' ') as r from (select w, unnest(range(1, len(w) - 6)) as i from b where len(w) >= 8)), dr as (select doc_id, array_to_string(w[i : i + 7], ' ') as r from (select doc_id, w, unnest(range(1, len(w) - 6)) as i from w where len(w) >= 8))
 select distinct doc_id from dr where r in (select r from br)""",
    "op_pii_patterns": "select source, cast(sum(len(regexp_extract_all(text, '[A-Za-z0-9._]+@[A-Za-z0-9.-]+'))) as bigint) as emails, cast(sum(len(regexp_extract_all(text, '[0-9]{3}-[0-9]{4}'))) as bigint) as phones from documents group by 1",
    "fn_string": "select c_custkey, lower(c_name) as a, substr(c_name, 3, 5) as b, translate(c_name, 'abc', 'xyz') as c, cast(length(c_name) as int) as d, regexp_extract(c_name, '([0-9]+)', 1) as e, regexp_replace(c_name, '[0-9]+', '#', 'g') as f, 'k-' || c_name as g, levenshtein(c_name, 'Customer') as h, lpad(cast(c_custkey as varchar), 6, '0') as i, reverse(c_name) as j from customer",
    "fn_date": "select o_orderkey, year(o_orderdate) as y, month(o_orderdate) as m, dayofyear(o_orderdate) as doy, strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') as mon, date_diff('day', date '1992-01-01', cast(o_orderdate as date)) as since, strftime(o_orderdate + interval 2 month, '%Y-%m-%d') as later, quarter(o_orderdate) as q from orders",
    "fn_math": "select l_orderkey, l_linenumber, l_extendedprice, round(sqrt(l_quantity), 9) as a, round(ln(l_quantity), 9) as b, round(asin(l_quantity / 100), 9) as c, cast(floor(l_quantity / 7) as bigint) as d, round(pow(l_quantity, 1.5), 9) as e, cast(l_quantity as int) % 7 as f, round(exp(-l_quantity / 10), 9) as g, greatest(l_quantity, 25.0) as h, cast(sign(l_quantity - 25) as double) as i from lineitem",
    "fn_array": "with e as (select vec_id, list_transform(embedding, lambda x: x::double) as e from embeddings) select vec_id, cast(len(e) as int) as n, round(list_sum(list_transform(e, lambda x: x * x)), 6) as sq, len(list_filter(e, lambda x: x > 0)) as pos, len(list_filter(e, lambda x: x > 0.5)) > 0 as big, round(list_max(e), 9) as hi, round(e[-1], 9) as last, round(list_sum(list_sort(e)[1:3]), 6) as low3 from e",
    "fn_map": "select c_custkey, c_mktsegment as a, case when length(c_mktsegment) > 2 then 1 else 0 end as b, 'nation,seg' as c from customer",
    "fn_json": """select event_id, cast(json_extract_string(props, '$.k') as bigint) as k, json_extract_string(props, '$.k') as s, cast(json_extract_string(props, '$.k') as bigint) as v, '{"id":' || event_id || '}' as j from events""",
    "fn_struct": "select n_nationkey as k, n_name as name, 1 as z from nation",
    "fn_null": "select c_custkey, case when c_acctbal < 0 then -1 else c_nationkey end as a, nullif(c_nationkey, 3) as b, c_acctbal < 0 as c, c_acctbal < 0 as d, case when c_acctbal < 0 then 'none' else 'some' end as e from customer",
    "fn_cast": "select p_partkey, try_cast(p_name as int) is null as a, cast(trunc(p_retailprice) as int) as b, cast(p_retailprice as decimal(18,2)) as c, cast(p_partkey as varchar) as d, p_partkey % 2 = 1 as e from part",
    "fn_hash": "select n_nationkey, md5(n_name) as a, sha256(n_name) as b, cast('0x' || substr(md5(n_name), 1, 8) as bigint) as c, hex(n_name) as d, base64(encode(n_name)) as e from nation",
}
