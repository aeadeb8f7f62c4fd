from __future__ import annotations

import __spark_entry__ as e


def test_every_oracle_has_a_query():
    assert set(e.oracle_sql()) <= set(e.queries())


def test_entry(spark):
    assert e.entry(spark).count() == 38


def test_streams_match_batches(spark, sf):
    q = e.queries()
    assert q["st_dedup"](spark, sf).count() == 1000
    assert q["st_tumbling"](spark, sf).groupBy().sum("n").first()[0] == 1000


def test_triples_agree_with_tables_on_every_shape(spark, sf):
    q = e.queries()
    a, b = (sorted(map(tuple, q[n](spark, sf).select("shape_id", "focus_class", "focus_id", "path", "observed", "severity").collect())) for n in ("wl_validate_triples", "validate_tables"))
    assert a == b
    assert {r[0] for r in a} >= {"S4", "S5", "S7"}


def test_every_signup_has_a_verdict(spark, sf):
    v = e.queries()["st_deadline_all"](spark, sf)
    assert v.count() == spark.read.parquet(f"{sf}/events.parquet").where("event_type = 'signup'").count()
    assert {r["verdict"] for r in v.select("verdict").distinct().collect()} <= {"kept", "missed", "open"}
