"""DuckDB SQL for the method, measure and workload queries, written apart from the Spark plans."""

from __future__ import annotations

from normgraph.operators.policygen import privacy_rules
from normgraph.sources import registry

H = "cast('0x' || substr(md5('42|{0}|' || {1}), 1, 8) as bigint) % {2}"


def corpus(mix: str = "institution") -> str:
    """CTEs up to ``corpus``."""
    if mix == "privacy":
        vals = ", ".join(f"({i}, '{c}', '{v}', '{o}', '{p}')" for i, (c, v, o, p) in enumerate(privacy_rules()))
        return f"""corpus as (select md5(n_nationkey || '|' || rule) as sent_id, cast(rule as bigint) as o_orderkey, cast(n_nationkey as bigint) as doc_id, rule as seq,
 'Every ' || cls || ' in ' || lower(n_name) || case op when 'O' then ' must ' when 'P' then ' may ' else ' must not ' end || vp || ' under clause ' || (rule + 1) || '.' as text,
 op as gold_label, upper(cls[1]) || cls[2:] as gold_class, prop as gold_pred, 'forall' as gold_quant, 'plain' as structure, cast(null as varchar) as ho_signature, 'privacy' as domain
 from nation, (values {vals}) r(rule, cls, vp, op, prop))"""
    entitled = "shall be entitled to" if mix == "lease" else "may"
    return rf"""codes as (select *, case
 when b < 308 then case when v < 6 then 'O1' when v < 10 then 'O2' when v < 12 then 'O3' when v = 12 then 'O4' when v < 15 then 'O5' when v = 15 then 'O6' when v = 16 then 'O7' when v = 17 then 'O8' when v = 18 then 'O9' else 'OH' || g end
 when b < 383 then case when v < 10 then 'P1' when v < 14 then 'P2' when v < 17 then 'P3' else 'P4' end
 when b < 443 then case when v < 10 then 'F1' when v < 14 then 'F2' when v < 17 then 'F3' else 'F4' end
 else case when v < 14 then 'N1' when v < 17 then 'N2' when v = 17 then 'N3' else 'N4' end end as code
 from (select o_orderkey, o_custkey, lower(coalesce(c_mktsegment, 'general')) as seg, {H.format("class", "o_orderkey", 1663)} as b, {H.format("variant", "o_orderkey", 20)} as v, {H.format("sig", "o_orderkey", 6)} as g
  from orders left join customer on o_custkey = c_custkey)),
corpus as (select md5(o_custkey || '|' || o_orderkey) as sent_id, o_orderkey, o_custkey as doc_id, cast(o_orderkey as integer) as seq,
 case code
 when 'O1' then 'Every customer in the ' || seg || ' segment must ' || case v when 2 then 'places order' when 3 then 'submit order' when 4 then 'place ordr' when 5 then 'frobnicate order' else 'place order' end || ' ' || o_orderkey || '.'
 when 'O2' then 'Each order of the ' || seg || ' segment shall have line item under number ' || o_orderkey || '.'
 when 'O3' then 'A customer in the ' || seg || ' segment may place order with at most ' || o_orderkey || ' units.'
 when 'O4' then 'At least one order of the ' || seg || ' segment must have line item under number ' || o_orderkey || '.'
 when 'O5' then 'Every customer in the ' || seg || ' segment must place order ' || o_orderkey || ' and keep account open.'
 when 'O6' then 'Every customer in the ' || seg || ' segment must place order ' || o_orderkey || repeat(' together with the usual supporting paper copies', 10) || '.'
 when 'O7' then 'If the account is open and when the season begins, because the ' || seg || ' desk asks, every customer must place order ' || o_orderkey || '.'
 when 'O8' then 'Every customer in the ' || seg || ' segment must:' || chr(10) || '- place order ' || o_orderkey || chr(10) || '- keep account open'
 when 'O9' then 'Every customer in the ' || seg || ' segment must place order ' || o_orderkey || ' and shall keep the form and must file it.'
 when 'OH0' then 'Every customer must satisfy every property that the ' || seg || ' desk lists for order ' || o_orderkey || '.'
 when 'OH1' then 'Every customer must belong to any set of buyers that the ' || seg || ' desk forms for order ' || o_orderkey || '.'
 when 'OH2' then 'For every function f the customer must report f(x) for order ' || o_orderkey || ' of the ' || seg || ' desk.'
 when 'OH3' then 'Every customer must apply lambda x to order ' || o_orderkey || ' of the ' || seg || ' desk.'
 when 'OH4' then 'Every customer must transitively approve all orders that depend on order ' || o_orderkey || ' of the ' || seg || ' desk.'
 when 'OH5' then 'Every customer must obey any policy that governs policies of the ' || seg || ' desk on order ' || o_orderkey || '.'
 when 'P1' then 'A customer in the ' || seg || ' segment may place order ' || o_orderkey || '.'
 when 'P2' then 'A customer in the ' || seg || ' segment is permitted to place order ' || o_orderkey || '.'
 when 'P3' then 'A customer in the ' || seg || ' segment may waive negative balance for order ' || o_orderkey || '.'
 when 'P4' then 'A customer in the ' || seg || ' segment {entitled} request refund ' || o_orderkey || '.'
 when 'F1' then 'A customer in the ' || seg || ' segment must not have negative balance on order ' || o_orderkey || '.'
 when 'F2' then 'A customer in the ' || seg || ' segment shall not have negative balance on order ' || o_orderkey || '.'
 when 'F3' then 'A customer in the ' || seg || ' segment may not have negative balance on order ' || o_orderkey || '.'
 when 'F4' then 'A customer in the ' || seg || ' segment is prohibited from having negative balance on order ' || o_orderkey || '.'
 when 'N1' then 'The ' || seg || ' desk lists order ' || o_orderkey || ' in the yearly report.'
 when 'N2' then 'Shipping of order ' || o_orderkey || ' may ' || case v when 14 then 'take some days' when 15 then 'vary' else 'occur late' end || ' in the ' || seg || ' segment.'
 when 'N3' then 'The ' || seg || ' desk opened order ' || o_orderkey || ' in May.'
 else 'The word "must" appears next to order ' || o_orderkey || ' in the ' || seg || ' glossary.' end as text,
 code[1] as gold_label, case when code in ('O2', 'O4') then 'Order' when code[1] <> 'N' then 'Customer' end as gold_class,
 case when code in ('O2', 'O4') then 'hasLineItem' when code = 'P3' then 'waivesNegativeBalance' when code = 'P4' then 'requestsRefund' when code[1] = 'F' then 'hasNegativeBalance'
  when code[1] = 'N' or code like 'OH%' then null else 'placesOrder' end as gold_pred,
 case when code = 'O4' then 'exists' when code[1] <> 'N' then 'forall' end as gold_quant,
 case code when 'O5' then 'compound' when 'O6' then 'very_long' when 'O7' then 'multi_clause' when 'O8' then 'bulleted' when 'O9' then 'multi_modal' else 'plain' end as structure,
 case when code like 'OH%' then ['predicate', 'set', 'function', 'lambda', 'closure', 'meta'][g + 1] end as ho_signature, '{mix}' as domain
 from codes)"""


PADDED = "' ' || regexp_replace(lower(text), '[^a-z]+', ' ', 'g') || ' '"


def cue_op(name: str, t: str = "t") -> str:
    vals = ", ".join(f"('{c}', '{o}')" for c, o in registry.cues(name))
    return f"(select arg_min(op, instr({t}, ' ' || cue || ' ') - 1000000 * len(string_split(cue, ' '))) from (values {vals}) c(cue, op) where contains({t}, ' ' || cue || ' '))"


MAY = """case when contains(t, ' may ') then case when regexp_matches(text, '(in|by|since|of) May[ .,]|May [0-9]') then 'month' when contains(t, ' may not ') then 'prohibition'
 when contains(t, ' at most ') or contains(t, ' no more than ') or contains(t, ' only ') or contains(t, ' up to ') then 'cap'
 when regexp_matches(t, ' may (take|vary|occur|differ|result|cause) ') then 'epistemic' else 'permission' end end"""
QUOTED = """regexp_matches(text, '"(must|shall|may|must not|shall not)"')"""


def labelled(name: str = "english", mode: str = "relabel", guard: bool = True, src: str = "corpus", where: str = "true") -> str:
    """CTEs ``padded`` and ``labelled`` over ``src``."""
    two = [c for c, _ in registry.cues(name) if " " in c]
    left = "t"
    for c in two:
        left = f"replace({left}, ' {c} ', ' | ')"
    found = ", ".join([f"case when contains(t, ' {c} ') then '{o}' end" for c, o in registry.cues(name) if " " in c] + [f"case when contains(rest, ' {c} ') then '{o}' end" for c, o in registry.cues(name) if " " not in c])
    op = "cue_op"
    if mode == "relabel":
        op = "case when cue_op = 'P' and may in ('month', 'epistemic') then 'N' when cue_op = 'P' and may = 'cap' then 'O' else cue_op end"
    elif mode == "drop":
        op = "case when cue_op = 'P' and may in ('month', 'epistemic') then 'N' else cue_op end"
    if guard:
        op = f"case when {QUOTED} then 'N' else {op} end"
    return f"""padded as (select *, {PADDED} as t from {src}),
cued as (select *, {cue_op(name)} as cue_op, {left} as rest, {MAY} as may from padded),
opsed as (select *, list_filter([{found}], lambda x: x is not null) as ops from cued),
labelled as (select * exclude (ops, rest), case when len(ops) = 0 then 0.0 when len(list_distinct(ops)) > 1 then 0.4 when len(ops) > 1 then 0.7 else 1.0 end as confidence, coalesce({op}, 'N') as label from opsed where {where})"""


HAS_CUE = {n: "(" + " or ".join(f"contains(t, ' {c} ')" for c, _ in registry.cues(n)) + ")" for n in ("english", "lease", "surrogate")}
REGEX = """case when regexp_matches(t, ' (must|shall|may) not | prohibited | forbidden ') then 'F' when regexp_matches(t, ' (must|shall|required) ') then 'O'
 when regexp_matches(t, ' (may|permitted|allowed|entitled) ') then 'P' else 'N' end"""
CATEGORY = """case when regexp_matches(text, '\n *[-*] ') then 'bulleted'
 when len(list_filter(string_split(t, ' '), lambda w: w in ('must', 'shall', 'may'))) >= 2 or len(list_filter(string_split(t, ' '), lambda w: w in ('not', 'never'))) >= 2 then 'multi_modal'
 when len(list_filter(string_split_regex(text, '\\s+'), lambda w: w <> '')) >= 60 then 'very_long'
 when len(list_filter(string_split(t, ' '), lambda w: w in ('if', 'when', 'because', 'unless', 'although', 'while'))) >= 2 then 'multi_clause'
 when regexp_matches(t, ' (must|shall|may) .* (and|or) ') then 'compound' end"""
PHRASE = """regexp_replace(regexp_extract(lower(text), '(must not|shall not|may not|shall be entitled to|is permitted to|is prohibited from|must|shall|may) ([a-z]+( [a-z]+){0,2})', 2), ' (on|under|with|for|in|of|to|and|or|together|that|next)( .*)?$', '')"""


def formulas(rules: str = "label <> 'N'", retry: bool = True, fol: str = "formulas") -> str:
    """CTE ``formulas`` over ``labelled``."""
    block = "category is not null and category <> 'compound'" if retry else "category is not null"
    attempt = "case when category = 'compound' or (first_bad) then 1 else 0 end" if retry else "0"
    return f"""lifted as (select sent_id, text, label as op, case when regexp_matches(lower(text), '^(at least one|some) ') then 'exists' else 'forall' end as quant,
  nullif(regexp_extract(lower(text), '(customer|order|supplier|controller|processor|subject)', 1), '') as noun, {PHRASE} as vp, {CATEGORY} as category,
  case when regexp_matches(lower(text), ' (waive|exempt|except|unless) ') then 'base' end as exception_of from labelled where {rules}),
named as (select * exclude (noun), upper(noun[1]) || noun[2:] as cls, string_split(vp, ' ') as vw from lifted),
camel as (select * exclude (vp, vw), vw[1] || array_to_string(list_transform(vw[2:], lambda w: upper(w[1]) || w[2:]), '') as pred from named),
basic as (select *, cls is null or pred in ('', 'predicate', 'action', 'thing') or length(pred) < 2 as weak from camel),
judged as (select *, weak or category is not null as first_bad, weak or ({block}) as bad from basic),
{fol} as (select * exclude (weak, bad, first_bad), not bad as ok, {attempt} as attempt, case when not bad then quant || ' x. ' || cls || '(x) -> ' || op || '(' || pred || '(x))' end as formula from judged)"""


def norm(x: str) -> str:
    return rf"regexp_replace(lower(trim(regexp_replace(regexp_replace(regexp_replace({x}, '^.*[:#/]', ''), '([a-z0-9])([A-Z])', '\1 \2', 'g'), '[_ -]+', ' ', 'g'))), '^([a-z]+[^s ])s( |$)', '\1\2')"


def registry_values(name: str) -> str:
    vals = ", ".join(f"('{r[2]}', '{r[4]}', '{r[5]}')" for r in registry.rows(name) if r[1] == "property")
    return f"reg as (select distinct name, {norm('alias')} as norm, cls as domain_class from (values {vals}) v(name, alias, cls))"


def grounded(name: str = "star", src: str = "formulas") -> str:
    """CTE ``dict (cls, pred, canonical, method)`` over well-formed rows of ``src``."""
    return f"""{registry_values(name)},
dist as (select distinct cls, pred, {norm("pred")} as norm from {src} where ok),
ex as (select dist.*, (select min(name) from reg where reg.name = dist.pred) as e, (select min(name) from reg where reg.norm = dist.norm) as a from dist),
fz as (select cls, pred, arg_min(name, (case when domain_class = cls then 0 else 1 end, -round(sim, 6), length(name), name)) as f from (
  select ex.cls, ex.pred, name, domain_class, 1 - levenshtein(ex.norm, reg.norm) / greatest(length(ex.norm), length(reg.norm)) as sim from ex, reg where e is null and a is null) where sim >= 0.8 group by cls, pred),
frag as (select domain_class, name from (select distinct domain_class, name from reg) qualify row_number() over (partition by domain_class order by name) <= 5),
rp as (select cls, pred, arg_min(name, (-common, length(name), name)) as r from (
  select ex.cls, ex.pred, name, len(list_intersect(string_split(ex.norm, ' '), string_split({norm("name")}, ' '))) as common from ex join frag on domain_class = cls) where common > 0 group by cls, pred),
dict as (select cls, pred, ex.norm, coalesce(e, a, f, r) as canonical, case when e is not null then 'exact' when a is not null then 'alias' when f is not null then 'fuzzy' when r is not null then 'repaired' else 'unresolved' end as method
  from ex left join fz using (cls, pred) left join rp using (cls, pred))"""


SHAPES = """shapes as (
 select md5(sent_id || '|' || coalesce(d.canonical, f.pred) || '|' || op) as shape_id, sent_id, f.cls as target_class, coalesce(d.canonical, f.pred) as path,
  case when op = 'O' and quant = 'forall' then 1 end as min_count, case when op = 'F' then 0 end as max_count, case when op = 'O' and quant = 'exists' then 1 end as q_min,
  case op when 'P' then 'Info' else 'Violation' end as severity, case op when 'O' then 'obligation' when 'P' then 'permission' else 'prohibition' end as deontic, 'formula' as route, exception_of
  from formulas f left join dict d on f.cls = d.cls and f.pred = d.pred where ok
 union all
 select md5(sent_id || '|' || pred || '|' || op), sent_id, coalesce(cls, 'Thing'), pred, case when op = 'O' then 1 end, case when op = 'F' then 0 end, null,
  case op when 'P' then 'Info' else 'Violation' end, case op when 'O' then 'obligation' when 'P' then 'permission' else 'prohibition' end, 'direct', exception_of from formulas where not ok),
valid as (select *, regexp_matches(target_class, '^[A-Z][A-Za-z]*$') and regexp_matches(path, '^[a-z][A-Za-z0-9]*$') as valid from shapes)"""

#: What the second opinion does on rows of conflicting cues.
OPINION = f"""opinion as (select * exclude (label, confidence), case when confidence < 0.5 and {REGEX} <> label then {REGEX} else label end as label, case when confidence < 0.5 and {REGEX} <> label then 0.8 else confidence end as confidence from labelled)"""


def chain(mix: str = "institution", cues: str = "english", reg: str = "star", mode: str = "relabel", guard: bool = True, second: bool = True, retry: bool = True, upto: str = "shapes") -> str:
    """All CTEs of the pipeline, comma-joined, ready after ``with``."""
    parts = [corpus(mix), labelled(cues, mode, guard)]
    if second:
        parts[1] = parts[1].replace("labelled as (", "first_label as (")
        parts.append(OPINION.replace("from labelled", "from first_label").replace("opinion as", "labelled as"))
    if upto == "labelled":
        return ",\n".join(parts)
    parts.append(formulas(retry=retry))
    if upto == "formulas":
        return ",\n".join(parts)
    parts += [grounded(reg), SHAPES]
    return ",\n".join(parts)


def kappa(src: str) -> str:
    """Scalar kappa of ``src (gold, pred, n)``."""
    return f"""(select (po - pe) / (1 - pe) from (select (select sum(n) filter (gold = pred) from {src})::double / (select sum(n) from {src}) as po,
 (select sum(coalesce(g, 0) * coalesce(p, 0)) from (select gold as k, sum(n)::double as g from {src} group by 1) full join (select pred as k, sum(n)::double as p from {src} group by 1) using (k)) / pow((select sum(n) from {src})::double, 2) as pe))"""


def macro(src: str) -> str:
    return f"(select avg(2.0 * tp / (coalesce(n_pred, 0) + n_gold)) from (select gold as k, sum(n) as n_gold, coalesce(sum(n) filter (gold = pred), 0) as tp from {src} group by 1) left join (select pred as k, sum(n) as n_pred from {src} group by 1) using (k))"


def wilson(k: str, n: str) -> tuple[str, str]:
    z = 1.959963984540054
    c = f"(({k}) / cast({n} as double) + {z * z} / (2 * {n})) / (1 + {z * z} / {n})"
    h = f"{z} * sqrt((({k}) / cast({n} as double)) * (1 - ({k}) / cast({n} as double)) / {n} + {z * z} / (4.0 * {n} * {n})) / (1 + {z * z} / {n})"
    return f"greatest(0.0, {c} - {h})", f"least(1.0, {c} + {h})"
