"""Vocabulary grounding: raw predicate names to canonical ones, on the distinct names only.

A corpus repeats its predicates, so grounding works on a dictionary of distinct (class, predicate) pairs, whose
size is that of a vocabulary; the dictionary is then joined back.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

FUZZY = 0.8


def normal_form(name: Column) -> Column:
    """Prefix dropped, camel, snake and kebab split, lower case, final "s" of the first token dropped."""
    bare = F.regexp_replace(name, "^.*[:#/]", "")
    spaced = F.regexp_replace(F.regexp_replace(bare, "([a-z0-9])([A-Z])", "$1 $2"), "[_ -]+", " ")
    return F.regexp_replace(F.lower(F.trim(spaced)), "^([a-z]+[^s ])s( |$)", "$1$2")


def aliases(registry: DataFrame) -> DataFrame:
    """``(norm, name, domain_class)``: distinct normal forms of all property aliases."""
    return registry.where("kind = 'property'").select(normal_form(F.col("alias")).alias("norm"), "name", "domain_class").distinct()


def dictionary(formulas: DataFrame) -> DataFrame:
    """Distinct (class, predicate) pairs of well-formed formulas."""
    return formulas.where("ok").select("cls", "pred").distinct()


def exact(preds: DataFrame, registry: DataFrame) -> DataFrame:
    """Adds ``canonical`` and ``method`` (exact, alias) by equality, null where nothing is equal."""
    names = registry.where("kind = 'property'").select(F.col("name").alias("own"), F.col("name").alias("e")).distinct()
    by_norm = aliases(registry).groupBy("norm").agg(F.min("name").alias("a"))
    df = preds.withColumn("norm", normal_form(F.col("pred")))
    df = df.join(F.broadcast(names), df["pred"] == names["own"], "left").drop("own").join(F.broadcast(by_norm), "norm", "left")
    return df.select("cls", "pred", "norm", F.coalesce("e", "a").alias("canonical"), F.when(F.col("e").isNotNull(), F.lit("exact")).when(F.col("a").isNotNull(), F.lit("alias")).alias("method"))


def fuzzy(preds: DataFrame, registry: DataFrame, min_sim: float = FUZZY) -> DataFrame:
    """Best alias of at least ``min_sim`` edit similarity, among aliases of nearly the same length.

    Ties go to the shorter and then the alphabetically first name; properties of the same class come first.
    The alias side is a registry, whose size is checked when it is loaded.
    """
    rest = preds.where("canonical is null").select("cls", "pred", "norm")
    al = F.broadcast(aliases(registry).withColumnRenamed("norm", "alias_norm"))
    longest = F.greatest(F.length("norm"), F.length("alias_norm"))
    near = F.abs(F.length("norm") - F.length("alias_norm")) <= (1 - min_sim) * longest
    pairs = rest.join(al, near).withColumn("sim", 1 - F.levenshtein("norm", "alias_norm") / longest).where(F.col("sim") >= min_sim)
    order = F.struct((F.col("domain_class") != F.coalesce("cls", F.lit(""))).cast("int"), -F.round("sim", 6), F.length("name"), F.col("name"))
    best = pairs.groupBy("cls", "pred").agg(F.min_by("name", order).alias("found"))
    out = preds.join(best, ["cls", "pred"], "left")
    return out.select("cls", "pred", "norm", F.coalesce("canonical", "found").alias("canonical"), F.coalesce("method", F.when(F.col("found").isNotNull(), F.lit("fuzzy"))).alias("method"))


def fragment(registry: DataFrame, k: int = 5) -> DataFrame:
    """The vocabulary shown for a repair: up to ``k`` properties of each class."""
    w = Window.partitionBy("domain_class").orderBy("name")
    return registry.where("kind = 'property'").select("domain_class", "name").distinct().withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k)


def repair(preds: DataFrame, registry: DataFrame, k: int = 5) -> DataFrame:
    """One rerun for rejects: the proposer sees the class's fragment and takes the name that shares most words.

    A name without a common word stays unresolved.
    """
    rest = preds.where("canonical is null")
    frag = F.broadcast(fragment(registry, k))
    words = lambda c: F.split(normal_form(c), " ")
    pairs = rest.join(frag, rest["cls"] == frag["domain_class"]).withColumn("common", F.size(F.array_intersect(F.split("norm", " "), words(F.col("name"))))).where("common > 0")
    best = pairs.groupBy("cls", "pred").agg(F.min_by("name", F.struct(-F.col("common"), F.length("name"), F.col("name"))).alias("found"))
    out = preds.join(best, ["cls", "pred"], "left")
    return out.select("cls", "pred", "norm", F.coalesce("canonical", "found").alias("canonical"), F.coalesce("method", F.when(F.col("found").isNotNull(), F.lit("repaired")), F.lit("unresolved")).alias("method"))


def ground(formulas: DataFrame, registry: DataFrame, min_sim: float = FUZZY) -> DataFrame:
    """Formulas with ``path`` and ``method``; the dictionary is joined back on (class, predicate)."""
    d = repair(fuzzy(exact(dictionary(formulas), registry), registry, min_sim), registry)
    return formulas.join(d.select("cls", "pred", F.col("canonical").alias("path"), "method"), ["cls", "pred"], "left")


def select_closed_set(preds: DataFrame, registry: DataFrame) -> DataFrame:
    """Closed-set choice over the full registry: most similar alias, whatever its similarity."""
    al = F.broadcast(aliases(registry).withColumnRenamed("norm", "alias_norm"))
    df = preds.select("cls", "pred", normal_form(F.col("pred")).alias("norm")).crossJoin(al)
    sim = 1 - F.levenshtein("norm", "alias_norm") / F.greatest(F.length("norm"), F.length("alias_norm"))
    return df.withColumn("sim", F.round(sim, 6)).groupBy("cls", "pred").agg(F.min_by("name", F.struct(-F.col("sim"), F.length("name"), F.col("name"))).alias("canonical"), F.max("sim").alias("sim"))


def no_grounding(preds: DataFrame, registry: DataFrame) -> DataFrame:
    """Baseline: a raw predicate counts only when it is a canonical name."""
    names = registry.where("kind = 'property'").select(F.col("name").alias("pred")).distinct()
    hit = names.withColumn("hit", F.lit(True))
    return preds.select("cls", "pred").join(F.broadcast(hit), "pred", "left").select("cls", "pred", F.coalesce("hit", F.lit(False)).alias("hit"))


def trigrams(c: Column) -> Column:
    padded = F.concat(F.lit("  "), c, F.lit(" "))
    return F.array_distinct(F.transform(F.sequence(F.lit(1), F.length(padded) - 2), lambda i: F.substring(padded, i, 3)))


def retrieve(preds: DataFrame, registry: DataFrame, k: int = 10) -> DataFrame:
    """Baseline: top ``k`` canonical names of each predicate by cosine of character trigrams (set weights)."""
    names = F.broadcast(registry.where("kind = 'property'").select("name").distinct().withColumn("tn", trigrams(normal_form(F.col("name")))))
    df = preds.select("cls", "pred").withColumn("tp", trigrams(normal_form(F.col("pred")))).crossJoin(names)
    cos = F.size(F.array_intersect("tp", "tn")) / F.sqrt(F.size("tp") * F.size("tn"))
    w = Window.partitionBy("cls", "pred").orderBy(F.col("cos").desc(), "name")
    return df.withColumn("cos", F.round(cos, 9)).withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k).select("cls", "pred", "name", "cos", "rank")
