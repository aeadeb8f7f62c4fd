"""DuckDB SQL of the drained streams."""

from __future__ import annotations

DAY = "cast(floor(epoch(ts) / 86400) * 86400 as bigint)"
SQL: dict[str, str] = {
    "st_tumbling": f"select {DAY} as start, event_type, count(*) as n from events group by all",
    "st_sliding": f"select start, count(*) as n from (select unnest([{DAY}, {DAY} - 86400]) as start from events) group by 1",
    "st_session": "with g as (select user_id, ts, case when ts >= lag(ts) over (partition by user_id order by ts) + interval 12 hours or lag(ts) over (partition by user_id order by ts) is null then 1 else 0 end as new from events), s as (select *, sum(new) over (partition by user_id order by ts rows unbounded preceding) as sid from g) select user_id, cast(floor(epoch(min(ts))) as bigint) as start, count(*) as n from s group by user_id, sid",
    "st_dedup": "select event_id from events",
    "st_static_join": "select event_id, event_type from events where (event_type = 'purchase' and value > 50) or (event_type = 'error' and value > 10)",
    "st_stream_join": "select c.event_id as click, p.event_id as purchase from events c join events p on c.user_id = p.user_id and c.event_type = 'click' and p.event_type = 'purchase' and p.ts >= c.ts and p.ts <= c.ts + interval 1 hour",
    "st_prohibition": f"select {DAY} as start, user_id, count(*) as n from events where event_type = 'error' group by all having count(*) > 1",
    "st_watermark_late": f"with w as (select {DAY} as start, count(*) as n from events group by 1) select * from w where start + 86400 <= (select epoch(max(ts)) from events) - 3600",
    "st_deadline": """with s as (select user_id, event_id, cast(floor(epoch(ts)) as bigint) as sec from events where event_type = 'signup'),
 o as (select user_id, event_id, event_type, cast(floor(epoch(ts)) as bigint) as sec from events where event_type in ('signup', 'purchase')),
 f as (select s.user_id, s.sec as signup, s.event_id, (select min(o.sec) from o where o.user_id = s.user_id and o.event_type = 'purchase' and (o.sec, o.event_id) > (s.sec, s.event_id)) as bought,
  (select max(o.sec) from o where o.user_id = s.user_id and (o.sec, o.event_id) > (s.sec, s.event_id)) as seen from s)
 select user_id, signup, case when bought <= signup + 604800 then 'kept' else 'missed' end as verdict from f where bought <= signup + 604800 or seen > signup + 604800""",
    "st_deadline_all": """with s as (select user_id, event_id, cast(floor(epoch(ts)) as bigint) as sec from events where event_type = 'signup'),
 b as (select user_id, event_id, cast(floor(epoch(ts)) as bigint) as sec from events where event_type = 'purchase'),
 f as (select s.user_id, s.sec as signup, (select min(b.sec) from b where b.user_id = s.user_id and (b.sec, b.event_id) > (s.sec, s.event_id)) as bought from s)
 select user_id, signup, case when bought <= signup + 604800 then 'kept' when (select max(floor(epoch(ts))) from events) > signup + 604800 then 'missed' else 'open' end as verdict from f""",
    "st_incremental_rules": "select user_id, arg_max(event_id, (ts, event_id)) as event_id, count(*) as n_versions from events group by 1",
}

#: Late rows change nothing.
SQL["st_watermark_late_file"] = SQL["st_watermark_late"]
