"""Agreement, classification and interval measures.

Everything is arithmetic on counts: one aggregate brings labelled rows down to a few cells, and the measures are
columns over those cells.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

Z95 = 1.959963984540054  # fixed value: normal quantile of a 95 % interval


def confusion(df: DataFrame, gold: str = "gold_label", pred: str = "label") -> DataFrame:
    return df.groupBy(F.col(gold).alias("gold"), F.col(pred).alias("pred")).agg(F.count(F.lit(1)).alias("n"))


def accuracy(cells: DataFrame) -> DataFrame:
    return cells.agg((F.sum(F.when(F.col("gold") == F.col("pred"), F.col("n")).otherwise(0)) / F.sum("n")).alias("accuracy"), F.sum("n").alias("n"))


def per_class(cells: DataFrame) -> DataFrame:
    """``(label, tp, n_pred, n_gold, precision, recall, f1)`` for each gold label."""
    g = cells.groupBy(F.col("gold").alias("label")).agg(F.sum("n").alias("n_gold"), F.sum(F.when(F.col("gold") == F.col("pred"), F.col("n")).otherwise(0)).alias("tp"))
    p = cells.groupBy(F.col("pred").alias("label")).agg(F.sum("n").alias("n_pred"))
    df = g.join(p, "label", "left").withColumn("n_pred", F.coalesce("n_pred", F.lit(0)))
    precision = F.when(F.col("n_pred") > 0, F.col("tp") / F.col("n_pred")).otherwise(F.lit(0.0))
    recall = F.col("tp") / F.col("n_gold")
    f1 = 2 * F.col("tp") / (F.col("n_pred") + F.col("n_gold"))
    return df.select("label", "tp", "n_pred", "n_gold", precision.alias("precision"), recall.alias("recall"), f1.alias("f1"))


def macro_f1(cells: DataFrame) -> DataFrame:
    return per_class(cells).agg(F.avg("f1").alias("macro_f1"))


def cohen_kappa(cells: DataFrame) -> DataFrame:
    """``(n, po, pe, kappa)``; null kappa where chance agreement is 1."""
    rows = cells.groupBy(F.col("gold").alias("k")).agg(F.sum("n").alias("g"))
    cols = cells.groupBy(F.col("pred").alias("k")).agg(F.sum("n").alias("p"))
    both = rows.join(cols, "k", "full").agg(F.sum(F.coalesce("g", F.lit(0)) * F.coalesce("p", F.lit(0))).alias("gp"))
    total = cells.agg(F.sum("n").alias("n"), F.sum(F.when(F.col("gold") == F.col("pred"), F.col("n")).otherwise(0)).alias("same"))
    df = total.crossJoin(F.broadcast(both))  # one row each
    po, pe = F.col("same") / F.col("n"), F.col("gp") / (F.col("n").cast("double") * F.col("n"))
    return df.select("n", po.alias("po"), pe.alias("pe"), F.when(pe < 1, (po - pe) / (1 - pe)).alias("kappa"))


def pool_kappa(ratings: DataFrame) -> DataFrame:
    """Chance-corrected agreement of any number of raters; ``ratings (item_id, rater, label)``, equally many for each item."""
    counts = ratings.groupBy("item_id", "label").agg(F.count(F.lit(1)).alias("n"))
    items = counts.groupBy("item_id").agg(F.sum("n").alias("m"), F.sum(F.col("n") * (F.col("n") - 1)).alias("agree"))
    observed = items.agg(F.avg(F.col("agree") / (F.col("m") * (F.col("m") - 1))).alias("po"), F.min("m").alias("lo"), F.max("m").alias("hi"), F.count(F.lit(1)).alias("n_items"))
    share = counts.groupBy("label").agg(F.sum("n").alias("c"))
    chance = share.agg((F.sum(F.col("c").cast("double") * F.col("c")) / F.pow(F.sum("c").cast("double"), 2)).alias("pe"))
    df = observed.crossJoin(F.broadcast(chance))  # one row each
    kappa = F.when((F.col("lo") == F.col("hi")) & (F.col("pe") < 1), (F.col("po") - F.col("pe")) / (1 - F.col("pe")))
    return df.select("n_items", "po", "pe", kappa.alias("kappa"))


def kappa_band(k: Column) -> Column:
    return F.when(k < 0, "poor").when(k <= 0.2, "slight").when(k <= 0.4, "fair").when(k <= 0.6, "moderate").when(k <= 0.8, "substantial").otherwise("almost perfect")


def wilson(k: Column, n: Column) -> tuple[Column, Column]:
    """95 % score interval of k out of n."""
    p, z2 = k / n, Z95 * Z95
    centre = (p + z2 / (2 * n)) / (1 + z2 / n)
    half = Z95 * F.sqrt(p * (1 - p) / n + z2 / (4 * n * n)) / (1 + z2 / n)
    return F.greatest(F.lit(0.0), centre - half), F.least(F.lit(1.0), centre + half)


def exact_upper_zero(n: Column, alpha: float = 0.05) -> Column:
    """One-sided exact upper bound when none of n was found."""
    return 1 - F.pow(F.lit(alpha), 1 / n)


def exact_upper(k: int, n: int, alpha: float = 0.05) -> float:
    """One-sided exact upper bound of k out of n, by bisection."""
    lo, hi = k / n, 1.0
    for _ in range(200):
        mid = (lo + hi) / 2
        tail = sum(math.exp(math.lgamma(n + 1) - math.lgamma(i + 1) - math.lgamma(n - i + 1) + i * math.log(mid) + (n - i) * math.log1p(-mid)) for i in range(k + 1)) if 0 < mid < 1 else 0.0
        lo, hi = (mid, hi) if tail > alpha else (lo, mid)
    return (lo + hi) / 2


def cohen_h(p1: Column, p2: Column) -> Column:
    return F.abs(2 * F.asin(F.sqrt(p1)) - 2 * F.asin(F.sqrt(p2)))


def _log_choose(n: Column, k: Column) -> Column:
    """ln C(n, k) by a sum of logarithms; n is a table's margin and small."""
    terms = F.when(k > 0, F.sequence(F.lit(1), k.cast("int"))).otherwise(F.array().cast("array<int>"))
    return F.aggregate(terms, F.lit(0.0), lambda s, i: s + F.log((n - k + i).cast("double")) - F.log(i.cast("double")))


def fisher(a: Column, b: Column, c: Column, d: Column) -> Column:
    """Two-sided exact p of the table [[a, b], [c, d]]: all tables with these margins that are no likelier."""
    a, b, c, d = (x.cast("int") for x in (a, b, c, d))
    r1, r2, c1 = a + b, c + d, a + c
    log_p = lambda x: _log_choose(r1, x) + _log_choose(r2, c1 - x) - _log_choose(r1 + r2, c1)
    lo, hi = F.greatest(F.lit(0), c1 - r2), F.least(r1, c1)
    here = log_p(a)
    return F.least(F.lit(1.0), F.aggregate(F.sequence(lo, hi), F.lit(0.0), lambda s, x: s + F.when(log_p(x) <= here + 1e-7, F.exp(log_p(x))).otherwise(0.0)))


def mcnemar(b: Column, c: Column) -> Column:
    """Two-sided exact p of the discordant counts."""
    b, c = b.cast("int"), c.cast("int")
    n, k = b + c, F.least(b, c)
    tail = F.aggregate(F.sequence(F.lit(0), k), F.lit(0.0), lambda s, i: s + F.exp(_log_choose(n, i) - n * math.log(2)))
    return F.when(n == 0, F.lit(1.0)).otherwise(F.least(F.lit(1.0), 2 * tail))


def f1_counts(tp: Column, fp: Column, fn: Column) -> tuple[Column, Column, Column]:
    return tp / (tp + fp), tp / (tp + fn), 2 * tp / (2 * tp + fp + fn)


def binary(df: DataFrame, gold: Column, pred: Column) -> DataFrame:
    """Precision, recall, F1, accuracy and kappa of two boolean columns, from one aggregate."""
    g, p = gold.cast("int"), pred.cast("int")
    n = df.agg(F.sum(g * p).alias("tp"), F.sum((1 - g) * p).alias("fp"), F.sum(g * (1 - p)).alias("fn"), F.sum((1 - g) * (1 - p)).alias("tn"))
    tp, fp, fn, tn = (F.col(c).cast("double") for c in ("tp", "fp", "fn", "tn"))
    total = tp + fp + fn + tn
    po = (tp + tn) / total
    pe = ((tp + fp) * (tp + fn) + (tn + fn) * (tn + fp)) / (total * total)
    return n.select("tp", "fp", "fn", "tn", (tp / (tp + fp)).alias("precision"), (tp / (tp + fn)).alias("recall"), (2 * tp / (2 * tp + fp + fn)).alias("f1"), po.alias("accuracy"), ((po - pe) / (1 - pe)).alias("kappa"))


def mix(df: DataFrame, label: str = "gold_label") -> DataFrame:
    """Share of each class, by two small aggregates instead of a window over everything."""
    n = df.groupBy(F.col(label).alias("label")).agg(F.count(F.lit(1)).alias("n"))
    total = n.agg(F.sum("n").alias("total"))
    return n.crossJoin(F.broadcast(total)).select("label", "n", (F.col("n") / F.col("total")).alias("share"))


def bootstrap_f1(spark, cells: dict[str, int], draws: int = 10_000, seed: int = 42) -> DataFrame:  # noqa: ANN001
    """Percentile interval of F1 from multinomial draws over the cells tp, fp, fn, tn.

    Drawing cell counts is the same in distribution as drawing rows, and its cost doesn't depend on their number.
    """
    names = ("tp", "fp", "fn", "tn")
    counts = [cells[c] for c in names]

    def run(batches):  # noqa: ANN001, ANN202
        import numpy as np
        import pandas as pd

        for batch in batches:
            out = []
            for i in batch["id"]:
                rng = np.random.default_rng([seed, int(i)])
                tp, fp, fn, _ = rng.multinomial(sum(counts), np.array(counts) / sum(counts))
                out.append(2 * tp / (2 * tp + fp + fn) if tp + fp + fn else 0.0)
            yield pd.DataFrame({"f1": out})

    draws_df = spark.range(draws).mapInPandas(run, "f1 double")
    return draws_df.agg(F.percentile("f1", F.lit(0.025)).alias("low"), F.percentile("f1", F.lit(0.975)).alias("high"))


def bootstrap_pool_kappa(ratings: DataFrame, draws: int = 10_000, seed: int = 42) -> DataFrame:
    """Percentile interval of the pool kappa, from multinomial draws over distinct count vectors of items."""
    labels = ["O", "P", "F", "N"]
    per_item = ratings.groupBy("item_id").agg(*[F.count_if(F.col("label") == x).cast("int").alias(x) for x in labels])
    vectors = [(tuple(r[x] for x in labels), r["n"]) for r in per_item.groupBy(*labels).agg(F.count(F.lit(1)).alias("n")).collect()]  # count vectors of a few raters
    vectors.sort()

    def run(batches):  # noqa: ANN001, ANN202
        import numpy as np
        import pandas as pd

        v = np.array([x for x, _ in vectors], dtype=float)
        n = np.array([c for _, c in vectors], dtype=float)
        m = v.sum(1)
        agree = (v * (v - 1)).sum(1) / (m * (m - 1))
        for batch in batches:
            out = []
            for i in batch["id"]:
                w = np.random.default_rng([seed, int(i)]).multinomial(int(n.sum()), n / n.sum())
                po = (w * agree).sum() / w.sum()
                share = (w[:, None] * v).sum(0)
                pe = ((share / share.sum()) ** 2).sum()
                out.append((po - pe) / (1 - pe) if pe < 1 else np.nan)
            yield pd.DataFrame({"kappa": out})

    return ratings.sparkSession.range(draws).mapInPandas(run, "kappa double").agg(F.percentile("kappa", F.lit(0.025)).alias("low"), F.percentile("kappa", F.lit(0.975)).alias("high"))


__all__ = [n for n in dir() if not n.startswith("_") and n not in ("annotations", "math", "Column", "DataFrame", "Window", "F")]
