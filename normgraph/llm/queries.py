"""Thin queries of the training-data operators over whole tables, and the SQL of those that have one."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from normgraph.llm import chat, cotraining, decontaminate, encoding, licences, minhash, rules, suffix, tokenfile, toxicity
from normgraph.llm.common import table


def op1_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = licences.search_notices(table(spark, sf_dir, "documents", "doc_id", "text"))
    return found.select("doc_id", "n_words", "n_base", "first_word", "last_word", "base_labels", "labels", "score", F.size("spans").cast("long").alias("n_spans"))


def op2_token_file(spark: SparkSession, sf_dir: str) -> DataFrame:
    shards = tokenfile.write_shards(table(spark, sf_dir, "documents", "doc_id", "text"))
    return tokenfile.read_documents(shards, with_ids=False)


def op3_suffix_repeats(spark: SparkSession, sf_dir: str) -> DataFrame:
    return suffix.repeated_spans(table(spark, sf_dir, "documents", "doc_id", "text"))


def op3_suffix_repeats_all(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Repeats inside one document too, as the pipeline removes them."""
    return suffix.repeated_spans(table(spark, sf_dir, "documents", "doc_id", "text"), suffix.RepeatConfig(across=False))


def op4_bpe_round_trip(spark: SparkSession, sf_dir: str) -> DataFrame:
    return encoding.round_trip(table(spark, sf_dir, "documents", "doc_id", "text"))


def op5_chat_rotation(spark: SparkSession, sf_dir: str) -> DataFrame:
    return chat.digest(chat.rotate(table(spark, sf_dir, "conversations", "conv_id", "turn", "role", "text")))


def op6_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return minhash.near_duplicates(table(spark, sf_dir, "documents", "doc_id", "text"))


def op7_co_training(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents", "doc_id", "text", "lang", "source", "n_chars")
    return cotraining.classify(docs, table(spark, sf_dir, "labels", "doc_id", "quality"))


def op8_line_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return rules.score_documents(table(spark, sf_dir, "documents", "doc_id", "text"), with_text=False)


def op9_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    scored = toxicity.classify(table(spark, sf_dir, "documents", "doc_id", "text"), table(spark, sf_dir, "labels", "doc_id", "toxic"))
    return scored.select("doc_id", (F.crc32(F.col("doc_id").cast("string")) % 5 == 0).alias("held_out"), "score", "predicted")


def op10_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate.find_leaks(table(spark, sf_dir, "documents", "doc_id", "text"), table(spark, sf_dir, "benchmark", "item_id", "text"))


QUERIES = {f.__name__: f for f in (op1_license_scan, op2_token_file, op3_suffix_repeats, op3_suffix_repeats_all, op4_bpe_round_trip, op5_chat_rotation, op6_near_duplicates, op7_co_training, op8_line_rules, op9_toxicity, op10_decontamination)}

_WORDS = r"list_filter(string_split_regex(coalesce(text, ''), '[\x20\x09-\x0D]+'), lambda w: w <> '')"

_OP3 = rf"""
with w as (select doc_id, {_WORDS} as ws from documents where doc_id is not null),
win as (select doc_id, unnest(range(0, len(ws) - 49)) as start, ws from w where len(ws) >= 50),
h as (select doc_id, start, md5(array_to_string(ws[start + 1 : start + 50], ' ')) as h from win),
g as (select h, min((doc_id, start)) as first, min(doc_id) as lo, max(doc_id) as hi from h group by h having min(doc_id) <> max(doc_id)),
hit as (select h.doc_id, h.start, first[1] as first_doc, (first[1] = h.doc_id and first[2] = h.start) as own from h join g using (h)),
cut as (select *, case when lag(start) over o is null or start > lag(start) over o + 50 or own <> lag(own) over o then 1 else 0 end as new from hit window o as (partition by doc_id order by start)),
span as (select *, sum(new) over (partition by doc_id order by start) as span from cut)
select doc_id, cast(min(start) as bigint) as first_word, cast(max(start) + 50 as bigint) as end_word, cast(max(start) + 50 - min(start) as bigint) as n_words,
  arg_min(first_doc, start) as first_doc, bool_and(own) as is_first
from span group by doc_id, span
"""

_OP3_ALL = _OP3.replace(", min(doc_id) as lo, max(doc_id) as hi from h group by h having min(doc_id) <> max(doc_id)", " from h group by h having min((doc_id, start)) <> max((doc_id, start))")

_OP5 = """
with t as (select distinct conv_id, coalesce(turn, -1) as turn, coalesce(role, 'unknown') as role, coalesce(text, '') as text from conversations where conv_id is not null),
p as (select distinct conv_id, role as participant from t),
s as (select t.conv_id, participant, cast(floor(turn / 64) as bigint) as block, turn, role, text, role = participant as mine,
  '<|start|>' || case when role = participant then 'assistant' else 'user name=' || role end || chr(10) as head, text || '<|end|>' || chr(10) as said from t join p using (conv_id)),
o as (select *, coalesce(sum(length(head) + length(said)) over (partition by conv_id, participant, block order by turn, role, text rows between unbounded preceding and 1 preceding), 0) as pos from s),
b as (select conv_id, participant, block, count(*) as n_turns, string_agg(head || said, '' order by turn, role, text) as rendered,
  coalesce(sum(case when mine then length(said) end), 0) as mask_chars,
  coalesce(string_agg(case when mine then cast(cast(pos + length(head) as bigint) as varchar) || '-' || cast(cast(pos + length(head) + length(said) as bigint) as varchar) end, ',' order by turn, role, text), '') as spans
  from o group by all)
select conv_id, participant, block, n_turns,
  cast(coalesce(sum(length(rendered)) over (partition by conv_id, participant order by block rows between unbounded preceding and 1 preceding), 0) as bigint) as char_start,
  cast(length(rendered) as bigint) as n_chars, cast(mask_chars as bigint) as mask_chars, md5(rendered) as rendered_md5, md5(spans) as mask_md5
from b
"""

_OP6 = rf"""
with recursive low as (select doc_id, translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') as text from documents),
w as (select doc_id, {_WORDS} as ws from low),
s as (select distinct doc_id, unnest(case when len(ws) = 0 then [] when len(ws) = 1 then [ws[1]] else list_transform(range(1, len(ws)), lambda i: ws[i] || ' ' || ws[i + 1]) end) as g from w),
n as (select doc_id, count(*) as n from s group by doc_id),
code as (select doc_id, hash(g) as g from s),
pair as (select a.doc_id as a, b.doc_id as b, count(*) as k from code a join code b on a.g = b.g and a.doc_id < b.doc_id group by 1, 2),
link as (select a, b from pair join n x on x.doc_id = a join n y on y.doc_id = b where 100 * k >= 80 * (x.n + y.n - k)),
arc as (select a, b from link union select b, a from link),
reach as (select doc_id as a, doc_id as b from w union select reach.a, arc.b from reach join arc on reach.b = arc.a),
c as (select a as doc_id, min(b) as component_id from reach group by a)
select w.doc_id, coalesce(n.n, 0) as n_shingles, c.component_id, c.component_id = w.doc_id as kept from w join c using (doc_id) left join n using (doc_id)
"""

_SYMBOLS = "#*$%&|<>"
_CHARS = "length(regexp_replace({0}, '[\\x20\\x09-\\x0D]+', '', 'g'))"


def _op8() -> str:
    r = rules.LineRules()
    phrases = " or ".join(f"contains(lower(l), '{p}')" for p in r.boilerplate)
    pipes = "length(l) - length(replace(l, '|', ''))"
    n_words = _WORDS.replace("coalesce(text, '')", "l")
    fails = (
        f"({_CHARS.format('l')} > 0 and (({pipes} >= {r.min_pipes} and {pipes} >= {r.pipe_words} * len({n_words}))"
        f" or length(l) - length(regexp_replace(l, '[{_SYMBOLS}]', '', 'g')) > {r.symbol_share} * {_CHARS.format('l')}"
        f" or (({phrases}) and len({n_words}) <= {r.short_words})))"
    )
    return rf"""
with d as (select doc_id, coalesce(text, '') as text, row_number() over () as id from documents),
w as (select *, {_WORDS} as ws, string_split(text, chr(10)) as ls from d),
win as (select id, unnest(range(1, len(ws) - 6)) as i, ws from w where len(ws) >= 8),
h as (select id, i, array_to_string(ws[i : i + 7], ' ') as g from win),
r as (select id, i from (select id, i, count(*) over (partition by id, g) as n from h) where n > 1),
z as (select id, least(8, coalesce(lead(i) over (partition by id order by i) - i, 8)) as z from r),
rep as (select id, sum(z) as n from z group by id),
ln as (select id, l from (select id, unnest(ls) as l from w)),
dup as (select id, sum(n - 1) as n from (select id, l, count(*) as n from ln where {_CHARS.format("l")} > 0 group by id, l) group by id),
cl as (select id, sum(case when {fails} then 1 else 0 end) as gone, sum(case when {fails} then 0 else {_CHARS.format("l")} end) as left_chars from ln group by id),
a as (select w.doc_id, len(ws) as n_words, {_CHARS.format("text")} as word_chars, length(text) - length(regexp_replace(text, '[{_SYMBOLS}]', '', 'g')) as n_symbols,
  coalesce(dup.n, 0) as n_dup_lines, coalesce(rep.n, 0) as n_repeat_words, coalesce(gone, 0) as n_lines_removed, coalesce(left_chars, 0) as clean_chars
  from w left join rep using (id) left join dup using (id) left join cl using (id)),
b as (select *, n_words < 20 or 100 * n_repeat_words > 30 * n_words as base_failed from a)
select doc_id, cast(n_words as bigint) as n_words, cast(word_chars as bigint) as word_chars, cast(n_symbols as bigint) as n_symbols, cast(n_dup_lines as bigint) as n_dup_lines,
  cast(n_repeat_words as bigint) as n_repeat_words, base_failed, not base_failed and clean_chars >= {1 - r.max_lost} * word_chars as kept,
  cast(n_lines_removed as bigint) as n_lines_removed, cast(clean_chars as bigint) as clean_chars
from b
"""


ORACLES = {"op3_suffix_repeats": _OP3, "op3_suffix_repeats_all": _OP3_ALL, "op5_chat_rotation": _OP5, "op6_near_duplicates": _OP6, "op8_line_rules": _op8()}
