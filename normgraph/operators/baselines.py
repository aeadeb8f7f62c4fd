"""Baselines: regular expressions, majority class, learned classifier, simulated raters and models."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from normgraph.sources.shared import stored

#: Printed accuracies of the four compared models; they are inputs of the simulation, not findings.
LINEUP = (("model_a", 0.84), ("model_b", 0.80), ("model_c", 0.88), ("model_d", 0.88))
PILOT = (("pilot_a", 0.88), ("pilot_b", 0.88), ("pilot_c", 0.84), ("pilot_d", 0.82), ("pilot_e", 0.76))


def regex_classify(text: Column) -> Column:
    """Hand-written patterns on the padded lower-case words, prohibitions first."""
    t = F.concat(F.lit(" "), F.regexp_replace(F.lower(text), "[^a-z]+", " "), F.lit(" "))
    return (
        F.when(F.regexp_like(t, F.lit(" (must|shall|may) not | prohibited | forbidden ")), F.lit("F"))
        .when(F.regexp_like(t, F.lit(" (must|shall|required) ")), F.lit("O"))
        .when(F.regexp_like(t, F.lit(" (may|permitted|allowed|entitled) ")), F.lit("P"))
        .otherwise(F.lit("N"))
    )


def marker_features(text: Column) -> dict[str, Column]:
    t = F.concat(F.lit(" "), F.regexp_replace(F.lower(text), "[^a-z]+", " "), F.lit(" "))
    flag = lambda p: F.regexp_like(t, F.lit(p)).cast("int")
    return {
        "m_must": flag(" must "), "m_shall": flag(" shall "), "m_may": flag(" may "),
        "m_negated": flag(" (must|shall) not "), "m_may_not": flag(" may not "), "m_participle": flag(" (required|permitted|prohibited) "),
    }


def draw(key: Column, salt: str, mod: int = 1000) -> Column:
    """Hash draw in [0, mod), the same on every layout."""
    return (F.conv(F.substring(F.md5(F.concat(F.lit(f"42|{salt}|"), key)), 1, 8), 16, 10).cast("long") % mod).cast("int")


def next_label(label: Column) -> Column:
    return F.when(label == "O", F.lit("P")).when(label == "P", F.lit("F")).when(label == "F", F.lit("O")).otherwise(F.lit("O"))


def noisy(gold: Column, key: Column, model: str, accuracy: float) -> Column:
    """Simulated answer: the gold label, or the next one when the draw falls beyond the accuracy."""
    return F.when(draw(key, model) < int(round(accuracy * 1000)), gold).otherwise(next_label(gold))


def lineup(df: DataFrame, models: tuple[tuple[str, float], ...] = LINEUP) -> DataFrame:
    """``(sent_id, gold_label, model, label)``: all models on the same rows, without a join."""
    each = F.array(*[F.struct(F.lit(m).alias("model"), noisy(F.col("gold_label"), F.col("sent_id"), m, a).alias("label")) for m, a in models])
    return df.select("sent_id", "gold_label", F.explode(each).alias("x")).select("sent_id", "gold_label", "x.model", "x.label")


def majority(ratings: DataFrame) -> DataFrame:
    """Most frequent label of each item, ties to the alphabetically first."""
    n = ratings.groupBy("item_id", "label").agg(F.count(F.lit(1)).alias("n"))
    return n.groupBy("item_id").agg(F.max_by("label", F.struct("n", (-F.ascii("label")).alias("first"))).alias("label"))


def folds(df: DataFrame, k: int = 5, label: str = "gold_label") -> DataFrame:
    """Stratified folds: position in the class by a hash, modulo ``k``."""
    w = Window.partitionBy(label).orderBy(F.md5(F.concat(F.lit("42|fold|"), F.col("sent_id"))), "sent_id")
    return df.withColumn("fold", ((F.row_number().over(w) - 1) % k).cast("int"))


def stratified(df: DataFrame, sizes: dict[str, int], label: str = "gold_label") -> DataFrame:
    """So many rows of each class, by a hash order; one window group limit a class."""
    w = Window.partitionBy(label).orderBy(F.md5(F.concat(F.lit("42|sample|"), F.col("sent_id"))), "sent_id")
    want = F.lit(0)
    for c, n in sizes.items():
        want = F.when(F.col(label) == c, F.lit(n)).otherwise(want)
    return df.where(F.col(label).isin(*sizes)).withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= want).drop("rank")


def logreg_cv(df: DataFrame, k: int = 5, features: int = 1 << 12, max_iter: int = 50, reg: float = 0.001, weighted: bool = True) -> DataFrame:
    """Out-of-fold predictions of a multinomial logistic regression on hashed word counts and marker flags.

    The features depend on a text's words alone. ``weighted``: rows of the same words, label and fold enter the fits
    as one row with their number as its weight, which saves work only where texts repeat. Otherwise each row enters
    the fits and is scored by itself; its features are written once for all fits.
    """
    words = F.coalesce(F.regexp_replace(F.lower("text"), "[^a-z]+", " "), F.lit(""))
    rows = folds(df.select("sent_id", "gold_label", words.alias("text")), k)
    if not weighted:
        # the folds stand in one partition a class; the fits need more
        rows = stored(_prepare(rows.repartition("sent_id"), features).select("sent_id", "gold_label", "fold", "y", "x"), "features")
        return _logreg(rows.withColumn("weight", F.lit(1.0)), k, max_iter, reg).select("sent_id", "fold", "gold_label", "label")
    rows = stored(rows, "folds")
    kinds = stored(rows.groupBy("text", "gold_label", "fold").agg(F.count(F.lit(1)).cast("double").alias("weight")), "fold-kinds")
    found = _logreg(_prepare(kinds, features), k, max_iter, reg).select(*[F.col(c).alias(f"kind_{c}") for c in ("text", "gold_label", "fold")], "label")
    same = (F.col("text") == F.col("kind_text")) & F.col("gold_label").eqNullSafe(F.col("kind_gold_label")) & (F.col("fold") == F.col("kind_fold"))
    return rows.join(found, same).select("sent_id", "fold", "gold_label", "label")


def _prepare(df: DataFrame, features: int) -> DataFrame:
    from pyspark.ml.feature import HashingTF, VectorAssembler

    words = F.filter(F.split(F.regexp_replace(F.lower("text"), "[^a-z]+", " "), " "), lambda w: w != "")
    df = df.withColumn("words", words)
    flags = marker_features(F.col("text"))
    df = df.withColumns(flags).withColumn("y", F.when(F.col("gold_label") == "O", 0.0).when(F.col("gold_label") == "P", 1.0).when(F.col("gold_label") == "F", 2.0).otherwise(3.0))
    df = HashingTF(inputCol="words", outputCol="tf", numFeatures=features).transform(df)
    return VectorAssembler(inputCols=["tf", *flags], outputCol="x").transform(df)


def _logreg(df: DataFrame, k: int, max_iter: int, reg: float) -> DataFrame:
    """Prepared and weighted rows with their ``label``, each fold scored by a fit on the others."""
    from pyspark.ml.classification import LogisticRegression

    weights = {r["fold"]: (r["w"], r["w2"]) for r in df.groupBy("fold").agg(F.sum("weight").alias("w"), F.sum(F.col("weight") * F.col("weight")).alias("w2")).collect()}  # one row a fold
    out = None
    for i in range(k):
        w, w2 = (sum(x[j] for f, x in weights.items() if f != i) for j in (0, 1))
        # Spark divides a variance by w - w2 / w, that of the single rows by w - 1; the penalty goes by the variance
        same = reg * (w - w2 / w) / (w - 1) if w > 1 and w2 < w * w else reg
        fit = LogisticRegression(featuresCol="x", labelCol="y", weightCol="weight", family="multinomial", maxIter=max_iter, regParam=same).fit(df.where(F.col("fold") != i))
        scored = fit.transform(df.where(F.col("fold") == i)).select(*df.columns, F.element_at(F.array(*map(F.lit, "OPFN")), (F.col("prediction") + 1).cast("int")).alias("label"))
        out = scored if out is None else out.unionByName(scored)
    return out


def logreg_transfer(train: DataFrame, test: DataFrame, features: int = 1 << 12, max_iter: int = 50, reg: float = 0.001) -> DataFrame:
    """Trained on one mix, tested on another."""
    from pyspark.ml.classification import LogisticRegression

    fit = LogisticRegression(featuresCol="x", labelCol="y", family="multinomial", maxIter=max_iter, regParam=reg).fit(_prepare(train, features))
    return fit.transform(_prepare(test, features)).select("sent_id", "gold_label", F.element_at(F.array(*map(F.lit, "OPFN")), (F.col("prediction") + 1).cast("int")).alias("label"))


def majority_class(df: DataFrame, label: str = "gold_label") -> DataFrame:
    return df.agg(F.mode(label, deterministic=True).alias("label"))
