"""Queries of the methods, measures and experiments over the given tables: name to function of (spark, sf_dir)."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from normgraph.functions import cues as C
from normgraph.functions import metrics as M
from normgraph.functions.pin import pin
from normgraph.operators import adapter, baselines, classify, formalise, nearest, policygen, proposers, segment, shapes, validate
from normgraph.plans import pipeline, profile, stability
from normgraph.sources.registry import load_registry
from normgraph.sources.shared import stored
from normgraph.sources.tables import table

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}


def query(f: Callable[[SparkSession, str], DataFrame]) -> Callable[[SparkSession, str], DataFrame]:
    QUERIES[f.__name__] = f
    return f


def corpus(spark: SparkSession, sf: str, mix: str = "institution") -> DataFrame:
    return policygen.render(spark, sf, mix)


def labelled(spark: SparkSession, sf: str, mix: str = "institution", **kw) -> DataFrame:  # noqa: ANN003
    return classify.label(corpus(spark, sf, mix), **kw)


def _run(spark: SparkSession, sf: str, mix: str = "institution", cfg: pipeline.PipelineConfig = pipeline.PipelineConfig()) -> pipeline.Result:
    return pipeline.run(spark, corpus(spark, sf, mix), cfg)


def _n():  # noqa: ANN202
    return F.count(F.lit(1)).alias("n")


# ---- Stage 1


@query
def policy_corpus(spark, sf):
    return corpus(spark, sf).select("sent_id", "doc_id", "seq", "text", "gold_label", "gold_class", "gold_pred", "gold_quant", "structure", "ho_signature")


@query
def policy_mix_counts(spark, sf):
    out = None
    for m in policygen.MIXES:
        d = corpus(spark, sf, m).groupBy("domain", "gold_label").agg(_n())
        out = d if out is None else out.unionByName(d)
    return out


@query
def seg_sentences(spark, sf):
    p = segment.pieces(table(spark, sf, "documents", "doc_id", "text", "lang"), keep=("lang",))
    return p.groupBy("lang").agg(_n(), F.sum(F.length("raw")).alias("chars"))


@query
def seg_policy_sentences(spark, sf):
    return segment.sentences(corpus(spark, sf).select(F.col("o_orderkey").alias("doc_id"), "text")).groupBy("doc_id").agg(F.count(F.lit(1)).alias("n_sentences"), F.md5(F.array_join(F.transform(F.array_sort(F.collect_list(F.struct("seq", "text"))), lambda x: x["text"]), "|")).alias("digest"))


@query
def seg_spans(spark, sf):
    s = segment.with_spans(table(spark, sf, "documents", "doc_id", "text"))
    back = s.join(table(spark, sf, "documents", "doc_id", "text"), "doc_id").where(F.substring(F.col("text"), F.col("start"), F.col("length")) == F.col("raw"))
    return back.groupBy("doc_id").agg(F.count(F.lit(1)).alias("n_lines"), F.sum("length").cast("long").alias("chars"), F.max("start").cast("long").alias("last_start"))


@query
def seg_boilerplate(spark, sf):
    return segment.repeated_lines(table(spark, sf, "documents", "doc_id", "text"), "doc_id", "text", 5).select("digest", "n_docs", "n_lines")


@query
def seg_stripped(spark, sf):
    return segment.strip_boilerplate(table(spark, sf, "documents", "doc_id", "text"), 5).select("doc_id", F.md5("text").alias("digest"))


@query
def seg_similarity(spark, sf):
    d = table(spark, sf, "conversations", "conv_id", "turn", "text").where("text is not null")
    g = segment.similarity_gate(d.withColumn("simple", segment.simplify(F.col("text"))), "text", "simple")
    g = segment.dual_gate(g.withColumn("self_check", segment.tokens_preserved(F.col("text"), F.col("simple"))))
    return g.groupBy("accepted", "preserved").agg(_n(), F.round(F.min("similarity"), 9).alias("lowest"))


@query
def pages_text(spark, sf):
    return table(spark, sf, "pages", "page_id", "html").select("page_id", F.md5(segment.html_text(F.col("html"))).alias("digest"), F.length(segment.html_text(F.col("html"))).cast("long").alias("n_chars"))


# ---- Stage 2


@query
def prefilter_policy(spark, sf):
    return classify.prefilter(corpus(spark, sf)).groupBy("gold_label").agg(_n())


@query
def prefilter_surrogate(spark, sf):
    p = segment.pieces(table(spark, sf, "documents", "doc_id", "text", "lang").where("lang = 'en'")).select("doc_id", F.col("raw").alias("text"))
    return classify.prefilter(p, "surrogate").groupBy("doc_id").agg(_n())


@query
def prefilter_vacuous(spark, sf):
    """English cues over the given documents: nothing, and said so."""
    p = segment.pieces(table(spark, sf, "documents", "doc_id", "text")).select("doc_id", F.col("raw").alias("text"))
    return p.agg(F.count(F.lit(1)).alias("n_sentences"), F.count_if(C.has_cue(C.padded(F.col("text")), "english")).alias("n_candidates"))


@query
def cue_operator(spark, sf):
    p = segment.pieces(table(spark, sf, "documents", "doc_id", "text", "lang").where("lang = 'en'"))
    t = C.padded(F.col("raw"))
    return p.select(C.operator(t, "surrogate").alias("op"), C.confidence(t, "surrogate").alias("confidence")).groupBy("op", "confidence").agg(_n())


@query
def label_rule(spark, sf):
    return labelled(spark, sf).select("sent_id", "label", "confidence", "cue_op", "may")


@query
def label_rule_lease(spark, sf):
    return labelled(spark, sf, "lease", registry="lease").select("sent_id", "label", "confidence")


@query
def hints(spark, sf):
    d = pin(corpus(spark, sf), t=C.padded(F.col("text")))
    return pin(d.select("sent_id", "t"), hints=F.array_join(C.hints(F.col("t"), "english"), ",")).where("hints <> ''").drop("t")


@query
def second_opinion(spark, sf):
    _, d = pipeline.classify_stage(corpus(spark, sf), pipeline.PipelineConfig())
    return d.groupBy("structure", "adopted", "label").agg(_n())


@query
def may_filter(spark, sf):
    out = None
    for mode in ("relabel", "drop", "off"):
        d = labelled(spark, sf, may_mode=mode).where("may is not null").groupBy("may", "label").agg(_n()).withColumn("mode", F.lit(mode))
        out = d if out is None else out.unionByName(d)
    return out


@query
def corrections(spark, sf):
    """Audit of first labels without disambiguation: permissions that become obligations or prohibitions."""
    off = labelled(spark, sf, may_mode="off").select("sent_id", "gold_label", F.col("label").alias("before"))
    on = labelled(spark, sf).select("sent_id", F.col("label").alias("after"))
    return off.join(on, "sent_id").where("before <> after").groupBy("gold_label", "before", "after").agg(_n())


@query
def confirm(spark, sf):
    r = _run(spark, sf)
    return classify.confirm(r.labelled, r.formulas).groupBy("label").agg(_n())


@query
def regex_baseline(spark, sf):
    return M.confusion(corpus(spark, sf).withColumn("label", baselines.regex_classify(F.col("text"))))


@query
def marker_features(spark, sf):
    return corpus(spark, sf).select("sent_id", *[c.alias(n) for n, c in baselines.marker_features(F.col("text")).items()])


@query
def folds(spark, sf):
    return baselines.folds(corpus(spark, sf).select("sent_id", "gold_label"))


@query
def strat_sample(spark, sf):
    return baselines.stratified(corpus(spark, sf).select("sent_id", "gold_label"), {"O": 28, "P": 12, "F": 10})


@query
def majority_class(spark, sf):
    return baselines.majority_class(corpus(spark, sf))


def ratings(spark, sf, raters=(("r1", 0.9), ("r2", 0.9), ("r3", 0.9))):
    s = strat_sample(spark, sf)
    return baselines.lineup(s, raters).select(F.col("sent_id").alias("item_id"), F.col("model").alias("rater"), "label", "gold_label")


@query
def majority_vote(spark, sf):
    return baselines.majority(ratings(spark, sf))


@query
def noisy_lineup(spark, sf):
    return baselines.lineup(corpus(spark, sf).where("gold_label <> 'N'")).groupBy("model").agg(_n(), F.count_if(F.col("label") == F.col("gold_label")).alias("n_same"))


@query
def proposer_parse_errors(spark, sf):
    e = table(spark, sf, "events", "event_id", "props").select("event_id", F.when(F.col("event_id") % 7 == 0, F.lit("not json")).otherwise(F.format_string('{"label": "O", "confidence": 0.5}')).alias("raw"))
    return proposers.parse_error_rate(e)


# ---- Stage 3


def rules(spark, sf, mix="institution", cues="english"):
    return classify.label(corpus(spark, sf, mix), cues).where("label <> 'N'")


@query
def formula_lift(spark, sf):
    return formalise.lift(rules(spark, sf)).select("sent_id", "op", "quant", "cls", "pred", "exception_of", "ok", "formula")


@query
def formula_check(spark, sf):
    d = formalise.lift(rules(spark, sf)).select(F.explode("diagnostics").alias("diagnostic"))
    return d.groupBy("diagnostic").agg(_n())


@query
def formula_retry(spark, sf):
    r = rules(spark, sf)
    return formalise.retry(formalise.lift(r)).groupBy("attempt", "ok").agg(_n())


@query
def formula_nodes(spark, sf):
    return formalise.nodes(formalise.lift(rules(spark, sf))).groupBy("kind", "name").agg(_n())


@query
def normalise_op(spark, sf):
    d = rules(spark, sf).select(F.col("label").alias("op"), C.padded(F.col("text")).contains(" not ").alias("negated"))
    op, left = formalise.normalise_op(F.when(F.col("negated") & (F.col("op") == "F"), F.lit("O")).otherwise(F.col("op")), F.col("negated"))
    return d.select(F.col("op").alias("was"), op.alias("op"), left.alias("still_negated")).groupBy("was", "op", "still_negated").agg(_n())


@query
def derive_permission(spark, sf):
    return formalise.derive_permissions(formalise.lift(rules(spark, sf)))


@query
def conflicts(spark, sf):
    return formalise.conflicts(formalise.lift(rules(spark, sf)).withColumn("pred", F.when(F.col("pred") == "havingNegativeBalance", "placeOrder").otherwise(F.col("pred"))))


@query
def fallback_categories(spark, sf):
    f = formalise.lift(rules(spark, sf)).where("not ok").withColumn("category", F.coalesce("category", F.lit("misc")))
    return f.groupBy("category").agg(_n())


@query
def ho_audit(spark, sf):
    a = formalise.ho_audit(corpus(spark, sf))
    flags = [c for c in a.columns if c.startswith("ho_") and c != "ho_signature"]
    return a.groupBy("ho_signature").agg(_n(), *[F.sum(F.col(c).cast("int")).alias(c) for c in flags])


@query
def review_queue(spark, sf):
    return formalise.review_queue(formalise.lift(rules(spark, sf))).select("sent_id", "category")


@query
def formula_yield(spark, sf):
    r = rules(spark, sf)
    f = formalise.retry(formalise.lift(r))
    n = f.agg(F.count(F.lit(1)).alias("n_rules"), F.count_if("ok").alias("n_ok"))
    lo, hi = M.wilson(F.col("n_ok"), F.col("n_rules"))
    return n.select("n_rules", "n_ok", (F.col("n_ok") / F.col("n_rules")).alias("share"), lo.alias("low"), hi.alias("high"))


@query
def pred_quality(spark, sf):
    r = rules(spark, sf)
    f = formalise.retry(formalise.lift(r))
    good = F.col("ok") & ~F.col("pred").isin(*formalise.PLACEHOLDERS)
    return f.agg((F.count_if(good) / F.count_if("ok")).alias("conditional"), (F.count_if(good) / F.count(F.lit(1))).alias("unconditional"))


# ---- vocabulary


@query
def reg_aliases(spark, sf):
    out = None
    for name in ("star", "privacy"):
        d = adapter.aliases(load_registry(spark, name)).withColumn("registry", F.lit(name))
        out = d if out is None else out.unionByName(d)
    return out


def _dist(spark, sf, mix="institution", cues="english"):
    r = rules(spark, sf, mix, cues)
    return adapter.dictionary(formalise.retry(formalise.lift(r)))


@query
def ground_exact(spark, sf):
    return adapter.exact(_dist(spark, sf), load_registry(spark, "star")).select("cls", "pred", "norm", "canonical", "method")


@query
def ground_fuzzy(spark, sf):
    reg = load_registry(spark, "star")
    return adapter.fuzzy(adapter.exact(_dist(spark, sf), reg), reg).select("cls", "pred", "canonical", "method")


@query
def ground_repair(spark, sf):
    reg = load_registry(spark, "star")
    return adapter.repair(adapter.fuzzy(adapter.exact(_dist(spark, sf), reg), reg), reg).select("cls", "pred", "canonical", "method")


@query
def ground_dictionary(spark, sf):
    return _run(spark, sf).formulas.where("ok").groupBy("cls", "pred", "path", "method").agg(_n())


@query
def ground_privacy(spark, sf):
    return _run(spark, sf, "privacy", pipeline.PipelineConfig(registry="privacy")).formulas.where("ok").groupBy("cls", "pred", "path", "method").agg(_n())


@query
def closed_set(spark, sf):
    return adapter.select_closed_set(_dist(spark, sf), load_registry(spark, "star"))


@query
def no_grounding(spark, sf):
    return adapter.no_grounding(_dist(spark, sf), load_registry(spark, "star"))


@query
def rag_topk(spark, sf):
    return adapter.retrieve(_dist(spark, sf), load_registry(spark, "star"), 3)


def _gold_pairs(spark, sf, mix, reg):
    """Distinct (cls, pred, gold_pred) of well-formed formulas."""
    c = corpus(spark, sf, mix)
    r = classify.label(c).where("label <> 'N'")
    f = formalise.retry(formalise.lift(r)).where("ok").select("sent_id", "cls", "pred")
    return f.join(c.select("sent_id", "gold_pred"), "sent_id").select("cls", "pred", "gold_pred").distinct()


@query
def rag_misses(spark, sf):
    reg = load_registry(spark, "privacy")
    g = _gold_pairs(spark, sf, "privacy", reg)
    top = adapter.retrieve(g.select("cls", "pred").distinct(), reg, 3)
    hit = g.join(top, ["cls", "pred"]).groupBy("cls", "pred", "gold_pred").agg(F.max((F.col("name") == F.col("gold_pred")).cast("int")).alias("hit"), F.min_by("name", "rank").alias("first"))
    same = adapter.normal_form(F.col("pred")) == adapter.normal_form(F.col("gold_pred"))
    kind = F.when(F.col("first") == F.col("gold_pred"), "correct").when(same, "format_drift").when(F.col("hit") == 1, "near_miss").otherwise("retrieval_miss")
    return hit.groupBy(kind.alias("kind")).agg(_n())


@query
def static_alignment(spark, sf):
    f = _run(spark, sf).formulas.where("ok")
    names = load_registry(spark, "star").where("kind = 'property'").select(F.col("name").alias("pred")).distinct().withColumn("raw", F.lit(1))
    d = f.join(F.broadcast(names), "pred", "left")
    return d.agg(F.count(F.lit(1)).alias("n"), F.count("raw").alias("n_raw"), F.count("path").alias("n_grounded"))


# ---- Stage 4


@query
def shapes_emit(spark, sf):
    return shapes.emit(_run(spark, sf).formulas).select("shape_id", "sent_id", "target_class", "path", "min_count", "max_count", "q_min", "severity", "deontic", "route")


@query
def shapes_direct(spark, sf):
    return shapes.with_validity(shapes.direct(_run(spark, sf).formulas)).groupBy("deontic", "severity", "valid").agg(_n())


@query
def shapes_valid(spark, sf):
    return shapes.with_validity(_run(spark, sf).shapes).groupBy("route", "valid").agg(_n())


@query
def shapes_exists(spark, sf):
    s = _run(spark, sf).shapes
    return s.where("q_min is not null").groupBy("target_class", "path", "q_min").agg(_n())


@query
def overrides(spark, sf):
    o = shapes.overrides(_run(spark, sf).shapes)
    return o.groupBy("overrides_class", "overrides_path").agg(_n())


@query
def shapes_turtle(spark, sf):
    return shapes.to_turtle(shapes.load_valid(_run(spark, sf).shapes)).select("shape_id", F.md5("turtle").alias("digest"))


@query
def triples_customer(spark, sf):
    return validate.triples(spark, sf).groupBy("p", "otype").agg(_n())


@query
def validate_tables(spark, sf):
    return validate.validate_tables(spark, sf)


@query
def validate_triples(spark, sf):
    some = tuple(c for c in validate.STAR if c.shape in ("S1", "S2", "S6", "S8"))
    return validate.validate_triples(validate.triples(spark, sf), some)


@query
def wl_validate_triples(spark, sf):
    """Every shape over the entity graph; the same report as over the tables."""
    return validate.validate_triples(validate.star_triples(spark, sf), validate.STAR)


@query
def defeat(spark, sf):
    """Negative balances are forbidden, except in one market segment."""
    v = validate.validate_tables(spark, sf, tuple(c for c in validate.STAR if c.shape == "S2"))
    ex = table(spark, sf, "customer", "c_custkey", "c_mktsegment").where("c_mktsegment = 'BUILDING'").select(F.lit("Customer").alias("focus_class"), F.col("c_custkey").cast("string").alias("focus_id"), F.lit("hasNegativeBalance").alias("path"))
    return shapes.defeat(v, ex).select("focus_id", "shape_id", "severity")


@query
def entity_report(spark, sf):
    return validate.entity_report(validate.validate_tables(spark, sf))


@query
def rule_browse(spark, sf):
    return shapes.load_valid(_run(spark, sf).shapes).groupBy("deontic", "severity", "target_class").agg(_n())


@query
def rule_trace(spark, sf):
    r = _run(spark, sf)
    return shapes.catalog(r.formulas, shapes.load_valid(r.shapes)).select("sent_id", "op", "formula", "target_class", "path", "severity", "route")


# ---- measures


def _cells(spark, sf):
    return M.confusion(labelled(spark, sf))


@query
def confusion(spark, sf):
    return _cells(spark, sf)


@query
def per_class(spark, sf):
    return M.per_class(_cells(spark, sf))


@query
def accuracy(spark, sf):
    return M.accuracy(_cells(spark, sf))


@query
def cohen_kappa(spark, sf):
    return M.cohen_kappa(_cells(spark, sf)).withColumn("band", M.kappa_band(F.col("kappa")))


@query
def pool_kappa(spark, sf):
    return M.pool_kappa(ratings(spark, sf))


@query
def wilson(spark, sf):
    lo, hi = M.wilson(F.col("k"), F.col("n"))
    return table(spark, sf, "lineitem", "l_linestatus", "l_returnflag").groupBy("l_linestatus").agg(F.count_if(F.col("l_returnflag") == "R").alias("k"), _n()).select("l_linestatus", "k", "n", lo.alias("low"), hi.alias("high"))


@query
def exact_upper(spark, sf):
    return table(spark, sf, "documents", "source").groupBy("source").agg(_n()).select("source", "n", M.exact_upper_zero(F.col("n")).alias("upper"))


def _order_tables(spark: SparkSession, sf: str) -> DataFrame:
    """For each customer: finished orders of high (a) and lower priority (b), and the others likewise (c, d)."""
    high, done = (F.coalesce(x, F.lit(False)) for x in (F.col("o_orderpriority").isin("1-URGENT", "2-HIGH"), F.col("o_orderstatus") == "F"))
    cells = {"a": done & high, "b": done & ~high, "c": ~done & high, "d": ~done & ~high}
    return table(spark, sf, "orders", "o_custkey", "o_orderpriority", "o_orderstatus").groupBy("o_custkey").agg(*[F.count_if(x).alias(n) for n, x in cells.items()])


@query
def fisher(spark, sf):
    return _order_tables(spark, sf).select("o_custkey", "a", "b", "c", "d", F.round(M.fisher(*map(F.col, "abcd")), 12).alias("p"))


@query
def mcnemar(spark, sf):
    """Finished against high priority on a customer's orders: either one without the other."""
    return _order_tables(spark, sf).select("o_custkey", "b", "c", F.round(M.mcnemar(F.col("b"), F.col("c")), 12).alias("p"))


@query
def cohen_h(spark, sf):
    """Null where a customer has no order on one side."""
    p1, p2 = F.try_divide(F.col("a"), F.col("a") + F.col("b")), F.try_divide(F.col("c"), F.col("c") + F.col("d"))
    return _order_tables(spark, sf).select("o_custkey", "a", "b", "c", "d", M.cohen_h(p1, p2).alias("h"), (p1 - p2).alias("risk_difference"))


@query
def binary_labels(spark, sf):
    """Quality label against a length rule; a second, unrelated binary task on the given labels."""
    d = table(spark, sf, "documents", "doc_id", "n_chars").join(table(spark, sf, "labels", "doc_id", "quality"), "doc_id")
    return M.binary(d, F.col("quality") == 1, F.col("n_chars") >= 800)


@query
def mix(spark, sf):
    return M.mix(corpus(spark, sf))


@query
def proxy_agreement(spark, sf):
    d = labelled(spark, sf).withColumn("regex", baselines.regex_classify(F.col("text")))
    cells = M.confusion(d, "regex", "label")
    return M.accuracy(cells).crossJoin(M.cohen_kappa(cells).select("kappa")).crossJoin(M.macro_f1(cells))


@query
def alignment(spark, sf):
    f = _run(spark, sf).formulas.where("ok").join(corpus(spark, sf).select("sent_id", "gold_pred"), "sent_id")
    return f.groupBy("method").agg(_n(), F.count_if(F.col("path") == F.col("gold_pred")).alias("n_gold"))


@query
def tiers(spark, sf):
    """T1 syntax over all shapes; T2 structure and T3 severity over the formula route."""
    s = shapes.with_validity(_run(spark, sf).shapes).join(corpus(spark, sf).select("sent_id", "gold_label"), "sent_id")
    formula = F.col("route") == "formula"
    structure = F.when(F.col("deontic") == "obligation", (F.coalesce("min_count", "q_min") == 1) & F.col("max_count").isNull()).when(F.col("deontic") == "prohibition", F.col("max_count") == 0).otherwise(F.col("min_count").isNull() & F.col("max_count").isNull())
    gold = F.when(F.col("gold_label") == "O", "obligation").when(F.col("gold_label") == "P", "permission").when(F.col("gold_label") == "F", "prohibition")
    return s.agg(F.count(F.lit(1)).alias("n"), F.count_if("valid").alias("t1"), F.count_if(formula).alias("n_formula"), F.count_if(formula & structure).alias("t2"), F.count_if(formula & (F.col("deontic") == gold)).alias("t3"))


@query
def behavioural(spark, sf):
    """T4: violating rows are negative entities, conforming rows positive ones; a tenth of the evidence is hidden."""
    c = table(spark, sf, "customer", "c_custkey", "c_acctbal")
    hidden = baselines.draw(F.col("c_custkey").cast("string"), "hide", 10) == 0
    d = c.select((F.col("c_acctbal") < 0).alias("negative"), ((F.col("c_acctbal") < 0) & ~hidden).alias("flagged"))
    return M.binary(d, F.col("negative"), F.col("flagged")).select("tp", "fp", "fn", "precision", "recall", "f1")


@query
def digest(spark, sf):
    return stability.digest(labelled(spark, sf).select("sent_id", "label"))


@query
def drift(spark, sf):
    a, b = labelled(spark, sf), labelled(spark, sf, may_mode="off")
    return stability.drift(a, b, "sent_id", "label")


@query
def coverage(spark, sf):
    on, off = _run(spark, sf), _run(spark, sf, cfg=pipeline.ABLATIONS["fallback_off"])
    return on.shapes.join(off.shapes.select("shape_id"), "shape_id", "left_anti").groupBy("route").agg(_n())


@query
def profile_summary(spark, sf):
    return profile.summary(table(spark, sf, "events", "event_id", "ts", "value")).select("n", F.round("mean", 6).alias("mean"), F.round("p95", 6).alias("p95"), "peak", F.round("energy_wh", 3).alias("energy_wh"))


@query
def price(spark, sf):
    return profile.price(spark)


# ---- workloads


@query
def wl_funnel_policy(spark, sf):
    """Counts of every step; formulas are written once, and all that follows from them is counted there."""
    c = corpus(spark, sf)
    r = pipeline.run(spark, c)
    formulas = stored(r.formulas, "formulas")
    valid = shapes.with_validity(pipeline.shapes_of(formulas))
    counts = (
        (c, {"sentences": F.lit(True)}),
        (r.candidates, {"candidates": F.lit(True)}),
        (formulas, {"rules": F.lit(True), "formulas": F.col("ok"), "fallback": ~F.col("ok")}),
        (valid, {"shapes": F.lit(True), "valid_shapes": F.col("valid")}),
    )
    out = None
    for df, steps in counts:
        d = df.agg(*[F.count_if(cond).alias(name) for name, cond in steps.items()])
        d = d.select(F.explode(F.array(*[F.struct(F.lit(name).alias("step"), F.col(name).alias("n")) for name in steps])).alias("x")).select("x.*")
        out = d if out is None else out.unionByName(d)
    return out


@query
def wl_validate_emitted(spark, sf):
    """The pipeline's own valid shapes, run over the entity tables."""
    found = validate.validate_shapes(spark, sf, _run(spark, sf).shapes)
    return found.groupBy("focus_class", "path", "deontic", "severity").agg(_n(), F.sum("observed").cast("long").alias("observed"))


@query
def wl_tier4(spark, sf):
    """T4: what each sentence's own shape says of a planted positive and a planted negative entity, by route."""
    d = validate.planted_entities(_run(spark, sf).shapes, corpus(spark, sf))
    neg, hit = F.col("negative"), F.col("flagged")
    n = d.groupBy("route").agg(F.count_if(neg & hit).alias("tp"), F.count_if(~neg & hit).alias("fp"), F.count_if(neg & ~hit).alias("fn"), F.count_if(~neg & ~hit).alias("tn"))
    return n.withColumn("recall", F.col("tp") / (F.col("tp") + F.col("fn"))).withColumn("f1", 2 * F.col("tp") / (2 * F.col("tp") + F.col("fp") + F.col("fn")))


@query
def wl_funnel_documents(spark, sf):
    p = segment.pieces(table(spark, sf, "documents", "doc_id", "text", "lang"), keep=("lang",))
    t = C.padded(F.col("raw"))
    d = p.select("lang", C.operator(t, "surrogate").alias("op"))
    return d.groupBy("lang").agg(_n(), F.count("op").alias("candidates"), *[F.count_if(F.col("op") == o).alias(f"n_{o.lower()}") for o in "OPF"])


@query
def wl_binary(spark, sf):
    d = labelled(spark, sf).withColumn("regex", baselines.regex_classify(F.col("text"))).withColumn("noisy", F.when(baselines.draw(F.col("sent_id"), "binary") < 938, F.col("gold_label") != "N").otherwise(F.col("gold_label") == "N"))
    gold = F.col("gold_label") != "N"
    out = None
    for name, pred in (("rules", F.col("label") != "N"), ("regex", F.col("regex") != "N"), ("simulated", F.col("noisy"))):
        m = M.binary(d, gold, pred).withColumn("method", F.lit(name))
        out = m if out is None else out.unionByName(m)
    return out


@query
def wl_type_accuracy(spark, sf):
    d = labelled(spark, sf).where("gold_label <> 'N'")
    cells = M.confusion(d)
    return M.accuracy(cells).crossJoin(M.cohen_kappa(cells).select("kappa")).crossJoin(M.macro_f1(cells))


@query
def wl_raters(spark, sf):
    """Pairwise kappa of three simulated raters, and of the pool."""
    r = ratings(spark, sf)
    pairs = (("r1", "r2"), ("r1", "r3"), ("r2", "r3"))
    out = M.pool_kappa(r).select(F.lit("pool").alias("pair"), "kappa")
    wide = r.groupBy("item_id").pivot("rater", ["r1", "r2", "r3"]).agg(F.first("label"))
    for a, b in pairs:
        out = out.unionByName(M.cohen_kappa(M.confusion(wide, a, b)).select(F.lit(f"{a}-{b}").alias("pair"), "kappa"))
    return out.withColumn("band", M.kappa_band(F.col("kappa")))


@query
def wl_raters_ci(spark, sf):
    return M.bootstrap_pool_kappa(ratings(spark, sf))


@query
def wl_corrections(spark, sf):
    return corrections(spark, sf)


@query
def wl_logreg(spark, sf):
    cv = baselines.logreg_cv(corpus(spark, sf).where("gold_label <> 'N'").select("sent_id", "text", "gold_label"), weighted=False)
    cells = stored(M.confusion(cv), "cells")
    return M.accuracy(cells).crossJoin(M.cohen_kappa(cells).select("kappa")).crossJoin(M.macro_f1(cells))


@query
def wl_logreg_lease(spark, sf):
    some = lambda m: corpus(spark, sf, m).where("gold_label <> 'N'").select("sent_id", "text", "gold_label")
    cells = M.confusion(baselines.logreg_transfer(some("institution"), some("lease")))
    return M.per_class(cells)


@query
def wl_logreg_lease_cv(spark, sf):
    """The learned baseline by five folds on the lease set alone."""
    cells = stored(M.confusion(baselines.logreg_cv(corpus(spark, sf, "lease").where("gold_label <> 'N'").select("sent_id", "text", "gold_label"), weighted=False)), "cells")
    return M.accuracy(cells).crossJoin(M.cohen_kappa(cells).select("kappa")).crossJoin(M.macro_f1(cells))


@query
def wl_lineup(spark, sf):
    """Simulated models on the sample: accuracy with interval, kappa, macro F1, exact test against the first."""
    s = baselines.lineup(strat_sample(spark, sf))
    first = s.where(F.col("model") == baselines.LINEUP[0][0]).select("sent_id", (F.col("label") == F.col("gold_label")).alias("first_ok"))
    j = s.join(first, "sent_id").withColumn("own_ok", F.col("label") == F.col("gold_label"))
    base = j.groupBy("model").agg(_n(), F.count_if("own_ok").alias("k"), F.count_if(F.col("own_ok") & ~F.col("first_ok")).alias("b"), F.count_if(~F.col("own_ok") & F.col("first_ok")).alias("c"))
    lo, hi = M.wilson(F.col("k"), F.col("n"))
    return base.select("model", "n", "k", lo.alias("low"), hi.alias("high"), "b", "c", M.mcnemar(F.col("b"), F.col("c")).alias("p"))


@query
def wl_pilot(spark, sf):
    """Five simulated models and the gold as a sixth rater: accuracies and the pool's kappa."""
    s = strat_sample(spark, sf)
    p = baselines.lineup(s, baselines.PILOT)
    acc = p.groupBy("model").agg(F.avg((F.col("label") == F.col("gold_label")).cast("double")).alias("value"))
    pool = p.select(F.col("sent_id").alias("item_id"), F.col("model").alias("rater"), "label").unionByName(s.select(F.col("sent_id").alias("item_id"), F.lit("gold").alias("rater"), F.col("gold_label").alias("label")))
    return acc.unionByName(M.pool_kappa(pool).select(F.lit("pool_kappa").alias("model"), F.col("kappa").alias("value")))


@query
def wl_ho_audit(spark, sf):
    """Planted constructs found in the corpus, none in the given documents, with the exact bound of the latter."""
    found = formalise.ho_audit(corpus(spark, sf)).agg(F.count(F.lit(1)).alias("n"), F.count_if(F.col("ho_predicate") | F.col("ho_set") | F.col("ho_function") | F.col("ho_lambda") | F.col("ho_closure") | F.col("ho_meta")).alias("k")).withColumn("carrier", F.lit("policy"))
    p = segment.pieces(table(spark, sf, "documents", "doc_id", "text")).select(F.col("raw").alias("text"))
    docs = formalise.ho_audit(p).agg(F.count(F.lit(1)).alias("n"), F.count_if(F.col("ho_predicate") | F.col("ho_set") | F.col("ho_lambda") | F.col("ho_closure") | F.col("ho_meta")).alias("k")).withColumn("carrier", F.lit("documents"))
    return found.unionByName(docs).withColumn("upper_if_none", F.when(F.col("k") == 0, M.exact_upper_zero(F.col("n"))))


@query
def wl_fallback(spark, sf):
    return fallback_categories(spark, sf)


@query
def wl_tiers(spark, sf):
    return tiers(spark, sf)


@query
def wl_static_alignment(spark, sf):
    return static_alignment(spark, sf)


@query
def wl_transfer(spark, sf):
    """Registry off and on for the privacy rules: one row, with exact test, effect size and intervals."""
    reg = load_registry(spark, "privacy")
    g = _gold_pairs(spark, sf, "privacy", reg)
    d = adapter.repair(adapter.fuzzy(adapter.exact(g.select("cls", "pred").distinct(), reg), reg), reg)
    j = g.join(d, ["cls", "pred"])
    n = j.agg(F.count(F.lit(1)).alias("n"), F.count_if(F.col("pred") == F.col("gold_pred")).alias("k_off"), F.count_if(F.col("canonical") == F.col("gold_pred")).alias("k_on"))
    lo, hi = M.wilson(F.col("k_on"), F.col("n"))
    p_on, p_off = F.col("k_on") / F.col("n"), F.col("k_off") / F.col("n")
    return n.select("n", "k_off", "k_on", (p_on - p_off).alias("risk_difference"), M.cohen_h(p_on, p_off).alias("h"), M.fisher(F.col("k_on"), F.col("n") - F.col("k_on"), F.col("k_off"), F.col("n") - F.col("k_off")).alias("p"), lo.alias("low"), hi.alias("high"))


@query
def wl_grounding3(spark, sf):
    """No grounding, retrieval with the nearest of the top ten, full registry: correct names of the privacy rules."""
    reg = load_registry(spark, "privacy")
    g = _gold_pairs(spark, sf, "privacy", reg)
    preds = g.select("cls", "pred").distinct()
    none = g.select(F.lit("none").alias("method"), (F.col("pred") == F.col("gold_pred")).alias("ok"))
    rag = g.join(adapter.retrieve(preds, reg, 10).where("rank = 1"), ["cls", "pred"]).select(F.lit("retrieval").alias("method"), (F.col("name") == F.col("gold_pred")).alias("ok"))
    full = g.join(adapter.repair(adapter.fuzzy(adapter.exact(preds, reg), reg), reg), ["cls", "pred"]).select(F.lit("registry").alias("method"), F.coalesce(F.col("canonical") == F.col("gold_pred"), F.lit(False)).alias("ok"))
    return none.unionByName(rag).unionByName(full).groupBy("method").agg(_n(), F.count_if("ok").alias("k"))


@query
def wl_embedding_topk(spark, sf):
    """Top ten by cosine among all vectors for every tenth vector: how many share its label."""
    e = table(spark, sf, "embeddings", "vec_id", "embedding", "label")
    top = nearest.top_k(e, e.where("vec_id % 10 = 0"))
    return top.groupBy("q", F.col("ql").cast("int").alias("ql")).agg(F.count_if("hit").alias("hits"), _n())


@query
def wl_ablation(spark, sf):
    """Seven configurations: rules, agreement with the regex, kappa, macro F1, shapes.

    No pattern of the stages tells one number from another, so sentences that differ in their numbers alone go
    through them once, with their count.
    """
    kinds = corpus(spark, sf).groupBy(F.regexp_replace("text", "[0-9]+", "0").alias("text")).agg(F.count(F.lit(1)).alias("weight"))
    c = stored(kinds.select(F.md5("text").alias("sent_id"), "text", "weight", baselines.regex_classify(F.col("text")).alias("regex")), "kinds")
    weights = c.select("sent_id", "weight")
    total = lambda name: F.coalesce(F.sum("weight"), F.lit(0)).alias(name)
    out = None
    for name, cfg in pipeline.ABLATIONS.items():
        r = pipeline.run(spark, c, cfg)
        cells = stored(r.rules.groupBy(F.col("regex").alias("gold"), F.col("label").alias("pred")).agg(F.sum("weight").alias("n")), "cells")
        n_shapes = stored(r.shapes.select("sent_id").join(weights, "sent_id").agg(total("n_shapes")), "shapes")
        calls = r.candidates.agg(total("n_calls"))
        d = M.accuracy(cells).crossJoin(M.cohen_kappa(cells).select("kappa")).crossJoin(M.macro_f1(cells)).crossJoin(n_shapes).crossJoin(calls).withColumn("configuration", F.lit(name))
        out = d if out is None else out.unionByName(d)
    return out


@query
def wl_stability(spark, sf):
    runs = [labelled(spark, sf), labelled(spark, sf).repartition(7), labelled(spark, sf).repartition(3, "label").orderBy(F.col("sent_id").desc())]
    return stability.compare([stability.digest(r, "sent_id", "label", "confidence") for r in runs])


@query
def wl_lease(spark, sf):
    """Lease phrasing under the institutional cues, and under its own."""
    out = None
    for name in ("english", "lease"):
        cells = M.confusion(labelled(spark, sf, "lease", registry=name).where("gold_label <> 'N'"))
        d = M.per_class(cells).withColumn("cues", F.lit(name))
        out = d if out is None else out.unionByName(d)
    return out


@query
def wl_profile(spark, sf):
    return profile_summary(spark, sf)


@query
def wl_browse(spark, sf):
    return shapes.load_valid(_run(spark, sf).shapes).where("deontic = 'prohibition' and severity = 'Violation'").select("shape_id", "target_class", "path", "route")


@query
def wl_trace(spark, sf):
    r = _run(spark, sf)
    return shapes.catalog(r.formulas.where("ok"), r.shapes).where("op = 'F'").select("sent_id", "text", "formula", "path")


@query
def wl_entity_report(spark, sf):
    return validate.entity_report(validate.validate_tables(spark, sf)).where("focus_class = 'Customer'")


@query
def wl_validate(spark, sf):
    return validate.validate_tables(spark, sf).groupBy("shape_id", "severity").agg(_n())


@query
def wl_overrides(spark, sf):
    return shapes.overrides(_run(spark, sf).shapes)


@query
def wl_audit_by_source(spark, sf):
    p = segment.pieces(table(spark, sf, "documents", "doc_id", "text", "source", "lang"), keep=("source", "lang"))
    t = C.padded(F.col("raw"))
    a = p.select("source", "lang", C.has_cue(t, "surrogate").alias("cue"), F.regexp_like(F.lower("raw"), F.lit("transitively|lambda")).alias("ho"))
    return a.groupBy("source", "lang").agg(_n(), F.count_if("cue").alias("candidates"), F.count_if("ho").alias("ho"))
