"""Golden values, recomputed from printed counts."""

from __future__ import annotations

import pytest
from pyspark.sql import functions as F

from normgraph.functions import metrics as M

CONFUSION = [("O", "O", 290), ("O", "P", 1), ("O", "F", 16), ("O", "N", 1), ("P", "O", 22), ("P", "P", 49), ("P", "F", 4), ("F", "O", 14), ("F", "F", 46)]


@pytest.fixture(scope="module")
def cells(spark):
    return spark.createDataFrame(CONFUSION, "gold string, pred string, n long")


def one(df):
    return df.first().asDict()


def test_confusion_measures(cells):
    assert one(M.accuracy(cells))["accuracy"] == pytest.approx(0.8691, abs=5e-5)
    assert one(M.cohen_kappa(cells))["kappa"] == pytest.approx(0.7085, abs=5e-5)
    f1 = {r["label"]: r["f1"] for r in M.per_class(cells).collect()}
    assert [f1[k] for k in "OPF"] == pytest.approx([0.9148, 0.7840, 0.7302], abs=5e-5)
    assert one(M.macro_f1(cells))["macro_f1"] == pytest.approx(0.8097, abs=5e-5)


def test_kappa_is_one_on_identity_and_null_without_variation(spark):
    same = spark.createDataFrame([("O", "O", 3), ("P", "P", 4)], "gold string, pred string, n long")
    assert one(M.cohen_kappa(same))["kappa"] == pytest.approx(1.0)
    assert one(M.cohen_kappa(same.where("gold = 'O'")))["kappa"] is None


@pytest.mark.parametrize(("k", "n", "low", "high"), [(1, 15, 0.0119, 0.2982), (11, 15, 0.4805, 0.8910), (9, 15, 0.3575, 0.8018), (0, 15, 0.0, 0.2039), (401, 443, 0.8743, 0.9291), (330, 351, 0.9103, 0.9605), (42, 50, 0.7149, 0.9166)])
def test_wilson(spark, k, n, low, high):
    lo, hi = M.wilson(F.lit(k), F.lit(n))
    r = spark.range(1).select(lo.alias("lo"), hi.alias("hi")).first()
    assert (r["lo"], r["hi"]) == pytest.approx((low, high), abs=6e-5)


def test_exact_tests(spark):
    val = lambda c: spark.range(1).select(c.alias("x")).first()["x"]
    assert val(M.exact_upper_zero(F.lit(443))) == pytest.approx(0.0067396, abs=1e-6)
    assert M.exact_upper(0, 443) == pytest.approx(0.0067396, abs=1e-6)
    for table, p in (((11, 4, 1, 14), 0.000484), ((9, 6, 0, 15), 0.000700), ((11, 4, 9, 6), 0.699850)):
        assert val(M.fisher(*map(F.lit, table))) == pytest.approx(p, abs=1e-6)
    assert val(M.mcnemar(F.lit(5), F.lit(7))) == pytest.approx(0.774414, abs=1e-6)
    assert val(M.mcnemar(F.lit(2), F.lit(4))) == pytest.approx(0.687500, abs=1e-6)
    for a, b, h in ((11, 1, 1.53400), (9, 0, 1.77215), (11, 9, 0.28416)):
        assert val(M.cohen_h(F.lit(a / 15), F.lit(b / 15))) == pytest.approx(h, abs=1e-5)
    p, r, f1 = (val(c) for c in M.f1_counts(F.lit(42), F.lit(1), F.lit(12)))
    assert (p, r, f1) == pytest.approx((0.9767, 0.7778, 0.8660), abs=5e-5)


def test_pool_kappa(spark):
    counts = [[3, 0, 0], [0, 3, 0], [2, 1, 0], [0, 1, 2]]
    rows = [(i, f"{k}{j}", "OPF"[k]) for i, c in enumerate(counts) for k, m in enumerate(c) for j in range(m)]
    r = spark.createDataFrame(rows, "item_id int, rater string, label string")
    assert one(M.pool_kappa(r))["kappa"] == pytest.approx(0.466667, abs=1e-6)


def test_bootstrap_f1(spark):
    r = one(M.bootstrap_f1(spark, {"tp": 42, "fp": 1, "fn": 12, "tn": 14}, draws=4000))
    assert r["low"] == pytest.approx(0.787, abs=0.01)
    assert r["high"] == pytest.approx(0.932, abs=0.01)
