"""Rendered policy corpus: one sentence for each order, with its gold labels, by SQL string functions only.

The class of a sentence follows a hash bucket of the order key, so the corpus is the same whatever the
partitioning; every construct that a later step must recognise is planted with a known count.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from normgraph.sources.tables import table

#: Buckets of the class mix: obligations, permissions and prohibitions among all sentences.
BUCKETS, OBLIGATIONS, PERMISSIONS, PROHIBITIONS = 1663, 308, 75, 60

MIXES = ("institution", "lease", "privacy")

_PRIVACY = (
    # class, verb phrase as rendered, operator, canonical property
    ("controller", "obtain consent", "O", "obtainsConsent"),
    ("controller", "report breach", "O", "notifiesBreach"),
    ("controller", "delete data", "O", "erasesData"),
    ("controller", "limit retention", "O", "limitsRetention"),
    ("controller", "log processing", "O", "recordsProcessing"),
    ("controller", "appoint oficer", "O", "appointsOfficer"),
    ("controller", "sell data", "F", "sellsData"),
    ("controller", "transfer abroad", "F", "transfersAbroad"),
    ("processor", "protect storage", "O", "securesStorage"),
    ("processor", "obey instruction", "O", "followsInstruction"),
    ("processor", "return copy", "O", "returnsCopy"),
    ("processor", "engage other", "F", "engagesOther"),
    ("subject", "ask access", "P", "requestsAccess"),
    ("subject", "withdraw consent", "P", "withdrawsConsent"),
    ("subject", "contest profiling", "P", "objectsProfiling"),
)


def privacy_rules() -> tuple[tuple[str, str, str, str], ...]:
    return _PRIVACY


# A lateral view over a one-element array pins a computed column: the optimiser would push filters on it below
# the projection and write its expression out once for every use.


def _hash(tag: str, mod: int, key: str = "o_orderkey") -> str:
    return f"conv(substring(md5(concat('42|{tag}|', {key})), 1, 8), 16, 10) % {mod}"


def codes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """``(o_orderkey, o_custkey, seg, b, v, g, code)``: what is rendered for each order."""
    table(spark, sf_dir, "orders", "o_orderkey", "o_custkey").createOrReplaceTempView("_pg_orders")
    table(spark, sf_dir, "customer", "c_custkey", "c_mktsegment").createOrReplaceTempView("_pg_customer")
    return spark.sql(f"""
      select *, case
        when b < {OBLIGATIONS} then case when v < 6 then 'O1' when v < 10 then 'O2' when v < 12 then 'O3' when v < 13 then 'O4' when v < 15 then 'O5'
          when v < 16 then 'O6' when v < 17 then 'O7' when v < 18 then 'O8' when v < 19 then 'O9' else concat('OH', g) end
        when b < {OBLIGATIONS + PERMISSIONS} then case when v < 10 then 'P1' when v < 14 then 'P2' when v < 17 then 'P3' else 'P4' end
        when b < {OBLIGATIONS + PERMISSIONS + PROHIBITIONS} then case when v < 10 then 'F1' when v < 14 then 'F2' when v < 17 then 'F3' else 'F4' end
        else case when v < 14 then 'N1' when v < 17 then 'N2' when v < 18 then 'N3' else 'N4' end end as code
      from (select o_orderkey, o_custkey, lower(coalesce(c_mktsegment, 'general')) as seg, b, v, g
        from _pg_orders left join _pg_customer on o_custkey = c_custkey
        lateral view inline(array(named_struct('b', cast({_hash("class", BUCKETS)} as int), 'v', cast({_hash("variant", 20)} as int), 'g', cast({_hash("sig", 6)} as int)))) h as b, v, g)""")


def _texts(mix: str) -> str:
    """CASE from code to sentence; ``k`` is the order number, ``seg`` the segment."""
    entitled = "' segment shall be entitled to request refund '" if mix == "lease" else "' segment may request refund '"
    parts = {
        "O1": "concat('Every customer in the ', seg, ' segment must ', case v when 2 then 'places order' when 3 then 'submit order' when 4 then 'place ordr' when 5 then 'frobnicate order' else 'place order' end, ' ', k, '.')",
        "O2": "concat('Each order of the ', seg, ' segment shall have line item under number ', k, '.')",
        "O3": "concat('A customer in the ', seg, ' segment may place order with at most ', k, ' units.')",
        "O4": "concat('At least one order of the ', seg, ' segment must have line item under number ', k, '.')",
        "O5": "concat('Every customer in the ', seg, ' segment must place order ', k, ' and keep account open.')",
        "O6": "concat('Every customer in the ', seg, ' segment must place order ', k, repeat(' together with the usual supporting paper copies', 10), '.')",
        "O7": "concat('If the account is open and when the season begins, because the ', seg, ' desk asks, every customer must place order ', k, '.')",
        "O8": "concat('Every customer in the ', seg, ' segment must:\\n- place order ', k, '\\n- keep account open')",
        "O9": "concat('Every customer in the ', seg, ' segment must place order ', k, ' and shall keep the form and must file it.')",
        "OH0": "concat('Every customer must satisfy every property that the ', seg, ' desk lists for order ', k, '.')",
        "OH1": "concat('Every customer must belong to any set of buyers that the ', seg, ' desk forms for order ', k, '.')",
        "OH2": "concat('For every function f the customer must report f(x) for order ', k, ' of the ', seg, ' desk.')",
        "OH3": "concat('Every customer must apply lambda x to order ', k, ' of the ', seg, ' desk.')",
        "OH4": "concat('Every customer must transitively approve all orders that depend on order ', k, ' of the ', seg, ' desk.')",
        "OH5": "concat('Every customer must obey any policy that governs policies of the ', seg, ' desk on order ', k, '.')",
        "P1": "concat('A customer in the ', seg, ' segment may place order ', k, '.')",
        "P2": "concat('A customer in the ', seg, ' segment is permitted to place order ', k, '.')",
        "P3": "concat('A customer in the ', seg, ' segment may waive negative balance for order ', k, '.')",
        "P4": f"concat('A customer in the ', seg, {entitled}, k, '.')",
        "F1": "concat('A customer in the ', seg, ' segment must not have negative balance on order ', k, '.')",
        "F2": "concat('A customer in the ', seg, ' segment shall not have negative balance on order ', k, '.')",
        "F3": "concat('A customer in the ', seg, ' segment may not have negative balance on order ', k, '.')",
        "F4": "concat('A customer in the ', seg, ' segment is prohibited from having negative balance on order ', k, '.')",
        "N1": "concat('The ', seg, ' desk lists order ', k, ' in the yearly report.')",
        "N2": "concat('Shipping of order ', k, ' may ', case v when 14 then 'take some days' when 15 then 'vary' else 'occur late' end, ' in the ', seg, ' segment.')",
        "N3": "concat('The ', seg, ' desk opened order ', k, ' in May.')",
        "N4": "concat('The word \"must\" appears next to order ', k, ' in the ', seg, ' glossary.')",
    }
    return "case code " + " ".join(f"when '{c}' then {t}" for c, t in parts.items()) + " end"


def render(spark: SparkSession, sf_dir: str, mix: str = "institution") -> DataFrame:
    """``(sent_id, o_orderkey, doc_id, seq, text, gold_label, gold_class, gold_pred, gold_quant, structure, ho_signature, domain)``."""
    if mix not in MIXES:
        raise ValueError(mix)
    if mix == "privacy":
        return _privacy(spark, sf_dir)
    codes(spark, sf_dir).createOrReplaceTempView("_pg_codes")
    return spark.sql(f"""
      select md5(concat(o_custkey, '|', o_orderkey)) as sent_id, o_orderkey, o_custkey as doc_id, cast(o_orderkey as int) as seq,
        text, substring(code, 1, 1) as gold_label,
        case when code in ('O2', 'O4') then 'Order' when code like 'N%' then null else 'Customer' end as gold_class,
        case when code in ('O2', 'O4') then 'hasLineItem' when code = 'P3' then 'waivesNegativeBalance' when code = 'P4' then 'requestsRefund'
          when code like 'F%' then 'hasNegativeBalance' when code like 'OH%' or code like 'N%' then null else 'placesOrder' end as gold_pred,
        case when code = 'O4' then 'exists' when code like 'N%' then null else 'forall' end as gold_quant,
        case code when 'O5' then 'compound' when 'O6' then 'very_long' when 'O7' then 'multi_clause' when 'O8' then 'bulleted' when 'O9' then 'multi_modal' else 'plain' end as structure,
        case when code like 'OH%' then element_at(array('predicate', 'set', 'function', 'lambda', 'closure', 'meta'), g + 1) end as ho_signature,
        '{mix}' as domain
      from (select *, cast(o_orderkey as string) as k from _pg_codes) lateral view explode(array({_texts(mix)})) t as text""")


def _privacy(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Fifteen data-protection rules, each for every nation."""
    rules = spark.createDataFrame([(i, *r) for i, r in enumerate(_PRIVACY)], "rule int, cls string, vp string, op string, prop string")
    rules.createOrReplaceTempView("_pg_rules")
    table(spark, sf_dir, "nation", "n_nationkey", "n_name").createOrReplaceTempView("_pg_nation")
    return spark.sql("""
      select /*+ broadcast(_pg_rules) */ md5(concat(n_nationkey, '|', rule)) as sent_id, cast(rule as bigint) as o_orderkey, cast(n_nationkey as bigint) as doc_id, rule as seq,
        concat('Every ', cls, ' in ', lower(n_name), case op when 'O' then ' must ' when 'P' then ' may ' else ' must not ' end, vp, ' under clause ', rule + 1, '.') as text,
        op as gold_label, initcap(cls) as gold_class, prop as gold_pred, 'forall' as gold_quant, 'plain' as structure, cast(null as string) as ho_signature, 'privacy' as domain
      from _pg_nation cross join _pg_rules""")
