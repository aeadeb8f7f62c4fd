from __future__ import annotations

import numpy as np
import pytest

import __spark_entry__ as e


def test_topk_takes_ties_and_vectors_without_direction(spark, tmp_path):
    rng = np.random.default_rng(1)
    m = rng.integers(-2, 3, (60, 4)).astype(float)
    m[7] = 0  # no cosine: comes after all that have one
    m[20:45] = m[3]  # more copies than places
    label = [i % 3 for i in range(60)]
    rows = [(i, [float(x) for x in v], label[i]) for i, v in enumerate(m)]
    spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int").repartition(3).write.parquet(f"{tmp_path}/embeddings.parquet")
    got = {r["q"]: (r["ql"], r["hits"], r["n"]) for r in e.queries()["wl_embedding_topk"](spark, str(tmp_path)).collect()}
    norm = np.sqrt((m * m).sum(1))
    want = {}
    for q in range(0, 60, 10):
        cos = {i: round(float(m[q] @ m[i]) / (norm[q] * norm[i]), 6) if norm[q] * norm[i] else -9.0 for i in range(60) if i != q}
        best = sorted(cos, key=lambda i: (-cos[i], i))[:10]
        want[q] = (label[q], sum(label[i] == label[q] for i in best), 10)
    assert got == want


def test_logreg_counts_equal_rows_by_weight(spark):
    """Rows of the same words enter a fit once, with their number; a fit on single rows gives the same labels."""
    from pyspark.ml.classification import LogisticRegression
    from pyspark.sql import functions as F

    from normgraph.operators import baselines

    texts = ("you must pay {}", "you may pay {}", "you must not pay {}", "you shall pay", None)
    rows = [(f"s{i}", t if t is None else t.format(i), "OPF"[(i // 5) % 7 % 3 if i % 4 == 0 else i % 5 % 3]) for i in range(200) for t in (texts[i % 5],)]
    df = spark.createDataFrame(rows, "sent_id string, text string, gold_label string")
    kinds = []
    fit, real = LogisticRegression.fit, LogisticRegression.fit
    LogisticRegression.fit = lambda self, d, *a: kinds.append(d.count()) or fit(self, d, *a)
    try:
        got = {r["sent_id"]: r["label"] for r in baselines.logreg_cv(df, k=2, features=64, max_iter=100).collect()}
    finally:
        LogisticRegression.fit = real
    assert len(got) == 200 and max(kinds) <= 5 * 3
    single = baselines._prepare(baselines.folds(df.fillna("", ["text"]), 2), 64)
    want = {}
    for i in range(2):
        m = LogisticRegression(featuresCol="x", labelCol="y", family="multinomial", maxIter=100, regParam=0.001).fit(single.where(F.col("fold") != i))
        want |= {r["sent_id"]: "OPFN"[int(r["prediction"])] for r in m.transform(single.where(F.col("fold") == i)).collect()}
    assert got == want


@pytest.mark.parametrize("name, mix", [("wl_logreg", "institution"), ("wl_logreg_lease_cv", "lease")])
def test_logreg_fits_every_sentence(spark, sf, monkeypatch, name, mix):
    """Each sentence enters four of the five fits by itself, however often its words repeat, and is scored once."""
    from pyspark.ml.classification import LogisticRegression

    from normgraph.operators import policygen

    seen = []
    fit = LogisticRegression.fit
    monkeypatch.setattr(LogisticRegression, "fit", lambda self, d, *a: seen.append(d.count()) or fit(self, d, *a))
    got = e.queries()[name](spark, sf).collect()
    n = policygen.render(spark, sf, mix).where("gold_label <> 'N'").count()
    assert len(seen) == 5 and sum(seen) == 4 * n and [r["n"] for r in got] == [n]


def test_logreg_keeps_rows_without_a_label(spark):
    from normgraph.operators import baselines

    texts = ("You must pay {}.", "You may pay {}.", "You must not pay {}.", "Paid on day {}.", None)
    rows = [(f"s{i}", t and t.format(i), ("O", "P", "F", None, None)[i % 5]) for i in range(100) for t in (texts[i % 5],)]
    df = spark.createDataFrame(rows, "sent_id string, text string, gold_label string")
    cols = ("sent_id", "fold", "gold_label", "label")
    single, weighted = ({tuple(r[c] for c in cols) for r in baselines.logreg_cv(df, k=2, features=64, weighted=w).collect()} for w in (False, True))
    assert single == weighted and {x[0] for x in single} == {r[0] for r in rows}


def test_ablation_takes_sentences_that_differ_in_numbers_once(spark, sf, monkeypatch):
    from pyspark.sql import functions as F

    from normgraph.operators import policygen
    from normgraph.plans import pipeline

    seen = []

    class Stop(Exception):
        pass

    def run(spark, sentences, cfg):  # noqa: ANN001, ANN202
        seen.append(sentences)
        raise Stop

    texts = policygen.render(spark, sf).select("text", F.regexp_replace("text", "[0-9]+", "0").alias("kind")).cache()
    stages = pipeline.run
    monkeypatch.setattr(pipeline, "run", run)
    try:
        e.queries()["wl_ablation"](spark, sf)
    except Stop:
        pass
    assert seen[0].count() == texts.select("kind").distinct().count() < texts.count() == 1500

    # the stages give a sentence and its kind the same label, formula and path
    extra = [("In May 12 the order 7 may vary.",), ("A customer may place at most 10 orders 2 times.",), ("Each order 5 must:\n- ship 3\n- pay 44",), ('The word "must" stands in line 19.',)]
    both = texts.select("text", "kind").unionByName(spark.createDataFrame(extra, "text string").withColumn("kind", F.regexp_replace("text", "[0-9]+", "0"))).distinct()
    cols = ("op", "quant", "cls", "pred", "exception_of", "ok", "path")

    def outcome(column):  # noqa: ANN001, ANN202
        s = both.select(F.md5("text").alias("sent_id"), F.col(column).alias("text"))
        return {tuple(r) for r in stages(spark, s, pipeline.PipelineConfig(prefilter=False)).formulas.select("sent_id", *cols).collect()}

    assert outcome("text") == outcome("kind")


def test_two_by_two_measures_read_orders(spark, sf):
    q = e.queries()
    orders = [tuple(r) for r in spark.read.parquet(f"{sf}/orders.parquet").select("o_custkey", "o_orderpriority", "o_orderstatus").collect()]
    cells: dict = {}
    for cust, priority, status in orders:
        cells.setdefault(cust, [0, 0, 0, 0])[(status != "F") * 2 + (priority not in ("1-URGENT", "2-HIGH"))] += 1
    for name in ("fisher", "cohen_h"):
        assert {r["o_custkey"]: [r[x] for x in "abcd"] for r in q[name](spark, sf).collect()} == cells
    assert {r["o_custkey"]: [r["b"], r["c"]] for r in q["mcnemar"](spark, sf).collect()} == {k: v[1:3] for k, v in cells.items()}


def test_registry_entries_are_counted_in_sentences_over_orders(spark, sf):
    got = {r["kind"]: (r["n"], r["n_sentences"]) for r in e.queries()["op_scan_registry"](spark, sf).collect()}
    from normgraph.operators import policygen

    gold = policygen.render(spark, sf).selectExpr("count(gold_class)", "count(gold_pred)").first()
    assert (got["class"][1], got["property"][1]) == tuple(gold)


def test_tables_of_a_step_go_before_the_next(spark, tmp_path, monkeypatch):
    """The suffixes are gone when the windows are grouped, and each round of near duplicates leaves its labels only."""
    import os

    from normgraph.llm import common, minhash, suffix

    seen = {}
    real = common.materialise

    def spy(df, tag):  # noqa: ANN001, ANN202
        kept = {x.rsplit("-", 1)[0] for x in os.listdir(common.shared_dir(spark).removeprefix("file:").replace("//", "/"))}
        seen.setdefault(tag, []).append(kept - before)
        return real(df, tag)

    before = {x.rsplit("-", 1)[0] for x in os.listdir(common.shared_dir(spark).removeprefix("file:").replace("//", "/"))}
    for m in (common, minhash, suffix):
        monkeypatch.setattr(m, "materialise", spy)
    words = [f"w{i}" for i in range(300)]
    docs = spark.createDataFrame([(i, " ".join(words[i : i + 80])) for i in range(4)], "doc_id long, text string")
    suffix.repeated_spans(docs)
    minhash.near_duplicates(docs)
    assert "windows" in seen["groups"][0] and "suffixes" not in seen["groups"][0]
    assert all(not x & {"arcs", "component", "edges"} for x in seen["mixed"])
