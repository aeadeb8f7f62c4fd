"""DuckDB SQL of the function surface."""

from __future__ import annotations

from normgraph.oracles import paper as P
from normgraph.oracles.workloads import FORM0
from normgraph.sources import registry

_al = ", ".join(f"('{a}')" for a in sorted({r[4] for r in registry.rows("star") if r[1] == "property"}))
_props = ", ".join(f"('{c}', '{n}')" for c, n in sorted({(r[5], r[2]) for r in registry.rows("star") if r[1] == "property"}))
_lo, _hi = P.wilson("n", "total")

SQL: dict[str, str] = {
    "udf_scalar": f"select alias, {P.norm('alias')} as norm from (values {_al}) v(alias)",
    "udf_pandas": f"with {FORM0} select distinct formula, true as ok, formula as normal from formulas where ok",
    "udf_grouped_agg": "select event_type, strftime(ts, '%Y-%m-%d') as day, round(max(value) - min(value), 9) as span from events group by all",
    "udf_cogrouped": f"with p as (select * from (values {_props}) v(domain_class, name)) select domain_class, name, 'added' as change from p where name like 'has%' union all select 'Order', 'formerPath', 'removed'",
    "udtf_split": "select * from (values (0, 'One rule must hold'), (1, 'Another may'), (2, 'Done')) v(seq, piece)",
    "udtf_lateral": "select item_id, cast(len(list_filter(string_split_regex(text, '[.!?\n]+'), lambda s: trim(s) <> '')) as bigint) as n from benchmark",
    "sql_surface": f"with {P.corpus()}, c as (select gold_label, count(*) as n from corpus group by 1), t as (select count(*) as total from corpus) select gold_label, n, case when n / 20000.0 <= 0.2 then 'slight' when n / 20000.0 <= 0.4 then 'fair' when n / 20000.0 <= 0.6 then 'moderate' when n / 20000.0 <= 0.8 then 'substantial' else 'almost perfect' end as band, {_lo} as low, {_hi} as high from c, t",
}
