"""Sentences to formulas to shapes: worked examples of our own, properties and planted cases."""

from __future__ import annotations

import pytest
from pyspark.sql import functions as F

from normgraph.functions import cues as C
from normgraph.operators import adapter, classify, formalise, policygen, segment, shapes, validate
from normgraph.plans import pipeline, stability
from normgraph.sources.registry import load_registry


def sentences(spark, *texts):
    return spark.createDataFrame([(str(i), t) for i, t in enumerate(texts)], "sent_id string, text string")


def test_worked_examples(spark):
    s = sentences(spark, "Every customer must place order 7.", "A customer may request refund 7.", "A customer must not have negative balance on order 7.", "At least one order must have line item under number 7.")
    r = pipeline.run(spark, s)
    got = {x["sent_id"]: x for x in r.shapes.collect()}
    assert [got[i]["severity"] for i in "0123"] == ["Violation", "Info", "Violation", "Violation"]
    assert [got[i]["path"] for i in "0123"] == ["placesOrder", "requestsRefund", "hasNegativeBalance", "hasLineItem"]
    assert (got["0"]["min_count"], got["2"]["max_count"], got["3"]["q_min"]) == (1, 0, 1)
    assert got["1"]["min_count"] is None and got["1"]["max_count"] is None
    formulas = {x["sent_id"]: x["formula"] for x in r.formulas.collect()}
    assert formulas["0"] == "forall x. Customer(x) -> O(placeOrder(x))"
    assert formulas["3"].startswith("exists x.")


def test_longest_cue_wins(spark):
    s = sentences(spark, "They must not go.", "They must go.", "They may not, they must.", "Nothing here.")
    got = [r["op"] for r in s.select("sent_id", C.operator(C.padded(F.col("text")), "english").alias("op")).orderBy("sent_id").collect()]
    assert got == ["F", "O", "F", None]


@pytest.mark.parametrize(("text", "label"), [("We met in May.", "N"), ("It may take days.", "N"), ("A buyer may order at most 3.", "O"), ("A buyer may not order.", "F"), ("A buyer may order.", "P"), ('The word "must" is short.', "N")])
def test_may_readings(spark, text, label):
    assert classify.label(sentences(spark, text)).first()["label"] == label


def test_split_rules(spark):
    d = spark.createDataFrame([(1, "Staff must:\n- sign in\n- sign out\nDr. Who may wait. The form\nis short; and visitors must register.")], "doc_id int, text string")
    got = [r["text"] for r in segment.sentences(d).orderBy("seq").collect()]
    assert got == ["Staff must:", "- sign in", "- sign out", "Dr. Who may wait.", "The form is short;", "and visitors must register."]


def test_simplify_keeps_tokens(spark):
    s = sentences(spark, "a  must\n b", "", "x\ty")
    assert all(r["ok"] for r in s.select(segment.tokens_preserved(F.col("text"), segment.simplify(F.col("text"))).alias("ok")).collect())


def test_formula_text_round_trip_and_diagnostics():
    for text in ("forall x. Customer(x) -> O(placeOrder(x))", "exists y. Order(y) -> F(!late(y, Monday) & open(y))"):
        found, diagnostics = formalise.parse(text)
        assert not diagnostics
        assert formalise.parse(found.normal())[0].normal() == found.normal()
    assert formalise.parse("forall x. A(x) -> O(p(x)")[1] == ["paren"]
    assert "multi_op" in formalise.parse("forall x. A(x) -> O(P(x))")[1]
    assert "no_op" in formalise.parse("forall x. A(x) -> q(x)")[1]
    assert "free_var" in formalise.parse("forall x. A(x) -> O(p(y))")[1]
    assert "arity0" in formalise.parse("forall x. A(x) -> O(p())")[1]


def test_prohibition_is_negated_obligation(spark):
    op, left = formalise.normalise_op(F.col("op"), F.col("neg"))
    d = spark.createDataFrame([("O", True), ("F", True), ("P", True), ("O", False)], "op string, neg boolean").select(op.alias("op"), left.alias("left"))
    assert [tuple(r) for r in d.collect()] == [("F", False), ("O", False), ("P", True), ("O", False)]


def test_retry_leaves_what_passed(spark, sf):
    r = classify.label(policygen.render(spark, sf)).where("label <> 'N'")
    first = formalise.lift(r)
    second = formalise.retry(first)
    ok = first.where("ok").select("sent_id", "formula")
    assert ok.exceptAll(second.where("attempt = 0").select("sent_id", "formula")).count() == 0
    assert second.count() == first.count()
    assert second.where("ok").count() > first.where("ok").count()


def test_planted_constructs_are_found(spark, sf):
    a = formalise.ho_audit(policygen.render(spark, sf))
    flags = [c for c in a.columns if c.startswith("ho_") and c != "ho_signature"]
    wrong = a.where(F.array_contains(F.array(*[F.col(c) for c in flags]), True) != F.col("ho_signature").isNotNull())
    assert a.where("ho_signature is not null").count() > 0
    assert wrong.count() == 0


def test_class_mix_counts(spark, sf):
    n = {r["gold_label"]: r["count"] for r in policygen.render(spark, sf).groupBy("gold_label").count().collect()}
    assert n == {"O": 316, "P": 69, "F": 52, "N": 1063}


def test_registry_swap_leaves_earlier_stages(spark, sf):
    c = policygen.render(spark, sf)
    a, b = (pipeline.run(spark, c, pipeline.PipelineConfig(registry=x)) for x in ("star", "privacy"))
    digest = lambda d, *cols: stability.digest(d, *cols).first()
    assert digest(a.labelled, "sent_id", "label") == digest(b.labelled, "sent_id", "label")
    assert digest(a.formulas, "sent_id", "formula") == digest(b.formulas, "sent_id", "formula")
    assert digest(a.shapes) != digest(b.shapes)


def test_normal_form_is_idempotent(spark):
    reg = load_registry(spark, "star")
    d = reg.select(adapter.normal_form(F.col("alias")).alias("n")).select("n", adapter.normal_form(F.col("n")).alias("m"))
    assert d.where("n <> m").count() == 0


def test_validators_agree(spark, sf):
    some = tuple(c for c in validate.STAR if c.shape in ("S1", "S2", "S6", "S8"))
    a = validate.validate_tables(spark, sf, some)
    b = validate.validate_triples(validate.triples(spark, sf), some)
    assert a.exceptAll(b).count() == 0 and b.exceptAll(a).count() == 0
    n = {r["shape_id"]: r["count"] for r in a.groupBy("shape_id").count().collect()}
    assert (n["S1"], n["S2"], n["S8"]) == (27, 11, 404)


def test_ablations_move_as_reported(spark, sf):
    c = policygen.render(spark, sf)
    n = {k: pipeline.run(spark, c, cfg) for k, cfg in pipeline.ABLATIONS.items()}
    rules = {k: r.rules.count() for k, r in n.items()}
    assert rules["may_off"] > rules["all_on"]
    assert rules["prefilter_off"] == rules["all_on"]
    assert n["fallback_off"].shapes.count() < n["all_on"].shapes.count()
    assert n["prefilter_off"].candidates.count() > n["all_on"].candidates.count()


def test_empty_and_null_input(spark):
    s = spark.createDataFrame([("1", None), ("2", "")], "sent_id string, text string")
    r = pipeline.run(spark, s)
    assert r.shapes.count() == 0
    assert pipeline.run(spark, s.limit(0)).shapes.count() == 0


def test_prefilter_runs_below_python(spark, sf):
    from normgraph.operators.proposers import ExternalProposer

    d = classify.prefilter(policygen.render(spark, sf).select("sent_id", "text"))
    out = ExternalProposer(lambda texts, cfg: ['{"label": "O", "confidence": 1.0}' if i % 2 else "?" for i, _ in enumerate(texts)]).propose(d)
    plan = out._jdf.queryExecution().optimizedPlan().toString()
    assert plan.index("MapInPandas") < plan.index("Contains")
    assert out.where("label is null").count() > 0


def test_overrides_and_defeat(spark, sf):
    s = pipeline.run(spark, policygen.render(spark, sf)).shapes
    o = shapes.overrides(s)
    assert {tuple(r)[1:] for r in o.collect()} == {("Customer", "hasNegativeBalance")}


def test_external_proposer_in_the_pipeline(spark):
    """Answers of a stand-in model, hints included; what is late or unreadable is no rule."""
    from normgraph.operators.proposers import Decoding, ExternalProposer
    from normgraph.plans import pipeline

    def model(texts, cfg):
        import json
        import time

        if any("slow" in t for t in texts):
            time.sleep(5)
        return ["no json" if "broken" in t else json.dumps({"label": "F" if "hints: must not:F" in t else "O", "confidence": 0.9}) for t in texts]

    rows = [("a", "Every customer must place order 1."), ("b", "A customer must not have negative balance on order 2."), ("c", "The broken customer must place order 3."), ("d", "The slow customer must place order 4.")]
    d = spark.createDataFrame(rows, "sent_id string, text string").repartition(1)
    r = pipeline.run(spark, d, proposer=ExternalProposer(model, batch=1), decoding=Decoding(timeout_s=1.0))
    assert {x["sent_id"]: x["label"] for x in r.labelled.collect()} == {"a": "O", "b": "F", "c": "N", "d": "N"}
    assert {x["sent_id"]: (x["path"], x["deontic"]) for x in r.shapes.collect()} == {"a": ("placesOrder", "obligation"), "b": ("hasNegativeBalance", "prohibition")}
