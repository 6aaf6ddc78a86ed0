"""DuckDB SQL for the relational plans and the batch twins of the streams."""

from __future__ import annotations

from .oracles import CUST, D30, P, num, params, tok

_EVT = f"evt as (select event_id, user_id as id, ts, {num('''(event_type || '|' || hour(ts))''', D30)} as t from events)"
_Z = ", ".join(f"min(h) filter (j = {j}) as z{j}" for j in range(8))
_H = f"hs as (select id, ts, event_id, j, (c1 + c2 * t) % {P} % {D30} as h from evt, params)"

ORACLES = {
    "nation_pairs": "with s as (select distinct c_nationkey as id, c_mktsegment || '|' || floor(c_acctbal / 1000)::BIGINT as t from customer where c_acctbal > 0), f as (select id, count(*) as f from s group by id), a as (select x.id as i, y.id as j, count(*) as a from s x join s y on x.t = y.t and x.id < y.id group by all) select x.id as id1, y.id as id2, round(coalesce(a, 0) / (x.f + y.f - coalesce(a, 0)), 6) as r from f x join f y on x.id < y.id left join a on i = x.id and j = y.id",
    "bit_aggregates": "select l_suppkey, bit_or(l_partkey) as any_bit, bit_and(l_partkey) as all_bits, bit_xor(l_partkey) as parity from lineitem group by l_suppkey",
    "sketch_distinct": "select l_returnflag, count(distinct l_partkey) as n, true as approximate_near, true as hll_near, true as theta_near from lineitem group by l_returnflag",
    "page_of_orders": "select o_orderkey, o_custkey from orders order by o_orderkey limit 50 offset 100",
    "event_type_maps": "with n as (select user_id, event_type, count(*) as n from events group by all) select user_id, count(*)::INT as kinds, coalesce(sum(n) filter (event_type = 'click'), 0)::BIGINT as clicks, coalesce(string_agg(event_type, ',' order by event_type) filter (n >= 3), '') as often, (2 * sum(n))::BIGINT as twice_all from n group by user_id",
    "label_moments": "select lang, round(avg(quality), 6) as mean, round(var_samp(quality), 6) as variance, round(stddev_samp(toxic), 6) as deviation, round(covar_samp(quality, toxic) / nullif(stddev_samp(quality) * stddev_samp(toxic), 0), 6) as correlation from documents join labels using (doc_id) group by lang",
    "binarised_quantities": "select id, count(*) as items from (select o_custkey as id, l_partkey, sum(l_quantity) as v from lineitem join orders on l_orderkey = o_orderkey group by all) where v > 25 group by id",
    "filter_documents": "select doc_id, source, n_chars from documents where lang = 'en' and source in ('src1', 'src2', 'src3') and n_chars between 500 and 2000",
    "filter_pages": "select page_id, url from pages where url like 'https://%' and regexp_matches(url, '/(en|fr)/')",
    "customer_part_sets": f"with {CUST} select id, count(*) as parts, min(t) as least, max(t) as most from cust group by id",
    "labelled_documents": "select lang, quality, toxic, count(*) as n from documents join labels using (doc_id) group by all",
    "semi_labelled": "select doc_id, lang from documents semi join labels using (doc_id)",
    "anti_labelled": "select doc_id, lang from documents anti join labels using (doc_id)",
    "full_outer_labels": "select (d.doc_id is not null)::INT as in_documents, (l.doc_id is not null)::INT as in_labels, count(*) as n from documents d full join labels l using (doc_id) group by all",
    "asof_event": "select p.event_id, floor(epoch(max(v.ts)))::BIGINT as view_at from events p left join events v on v.user_id = p.user_id and v.event_type = 'view' and v.ts <= p.ts where p.event_type = 'purchase' group by p.event_id",
    "interval_events": "select c.event_id as click, e.event_id as error from events c join events e on c.user_id = e.user_id and c.event_type = 'click' and e.event_type = 'error' and floor(epoch(e.ts)) between floor(epoch(c.ts)) and floor(epoch(c.ts)) + 3600",
    "distinct_tokens": f"select lang, count(distinct w) as n from (select lang, unnest({tok('text')}) as w from documents) group by lang",
    "rollup_documents": "select lang, source, count(*) as n, sum(n_chars)::BIGINT as chars from documents group by rollup (lang, source)",
    "cube_labels": "select quality, toxic, count(*) as n from labels group by cube (quality, toxic)",
    "grouping_sets_orders": "select o_orderstatus, o_orderpriority, count(*) as n, round(sum(o_totalprice), 2) as total from orders group by grouping sets ((o_orderstatus), (o_orderpriority), ())",
    "pivot_labels": "select quality, " + ", ".join(f"nullif(count_if(lang = '{x}'), 0)::BIGINT as {x}" for x in ("de", "en", "es", "fr")) + " from documents join labels using (doc_id) group by quality",
    "rank_documents": "select doc_id, rank() over w::INT as rank, dense_rank() over w::INT as dense, round(percent_rank() over w, 6) as share, ntile(4) over (partition by lang order by n_chars, doc_id)::INT as quartile from documents window w as (partition by lang order by n_chars)",
    "event_gaps": "select event_id, (floor(epoch(ts)) - floor(epoch(lag(ts) over w)))::BIGINT as gap, lead(event_type) over w as next_type from events window w as (partition by user_id order by ts, event_id)",
    "running_signature": f"with {params(1)}, {_EVT} select event_id, min((c1 + c2 * t) % {P} % {D30}) over (partition by id order by ts, event_id rows unbounded preceding) as z from evt, params",
    "range_window_events": "select event_id, count(*) over w as n, round(sum(value) over w, 4) as total from (select *, floor(epoch(ts))::BIGINT as s from events) window w as (partition by user_id order by s range between 21600 preceding and current row)",
    "union_texts": "select source, count(*) as n, sum(size)::BIGINT as chars from (select 'documents' as source, length(text) as size from documents union all select 'benchmark', length(text) from benchmark union all select 'conversations', length(text) from conversations) group by source",
    "intersect_parts": " intersect ".join(f"(select l_partkey from lineitem join supplier on l_suppkey = s_suppkey join nation on s_nationkey = n_nationkey where n_regionkey = {r})" for r in (0, 1)),
    "except_parts": "select p_partkey as l_partkey from part except all select distinct l_partkey from lineitem join supplier on l_suppkey = s_suppkey join nation on s_nationkey = n_nationkey where n_regionkey = 0",
    "event_props": "select event_type, json_extract_string(props, '$.k') as k, count(*) as n, round(sum(value), 4) as total from events group by all",
    "profile_events": f"with {_EVT}, c as (select id, count(distinct t) as f from evt group by id) select count(*) as n, (select max(t) + 1 from evt) as d, round(median(f), 6) as nnz_median, round(avg(f), 6) as nnz_mean from c",
    "events_tumbling_signature": f"with {params(8)}, {_EVT}, {_H} select epoch(date_trunc('day', ts))::BIGINT as start, id, {_Z} from hs group by all",
    "events_sliding_signature": f"with {params(8)}, {_EVT}, {_H}, w as (select (epoch(date_trunc('day', ts))::BIGINT - 86400 * k) as start, id, j, h from hs, range(7) r(k)) select start, id, {_Z} from w group by all",
    "events_session_signature": f"""with {params(8)}, {_EVT}, g as (select *, (ts - lag(ts) over w >= interval 30 minutes) is not false as new from evt window w as (partition by id order by ts, event_id)),
s as (select *, count_if(new) over (partition by id order by ts, event_id rows unbounded preceding) as sess from g), hh as (select id, sess, ts, j, (c1 + c2 * t) % {P} % {D30} as h from s, params)
select floor(epoch(min(ts)))::BIGINT as start, floor(epoch(max(ts) + interval 30 minutes))::BIGINT as stop, id, {_Z} from hh group by id, sess""",
}
