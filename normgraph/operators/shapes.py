"""Stage 4: formulas to constraint shapes, the direct fallback, overrides, validity and text forms."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from normgraph.operators import formalise


def emission(op: Column, quant: Column) -> dict[str, Column]:
    """Cardinality and severity, a function of operator and quantifier alone."""
    exists = (op == "O") & (quant == "exists")
    return {
        "min_count": F.when((op == "O") & ~exists, F.lit(1)),
        "max_count": F.when(op == "F", F.lit(0)),
        "q_min": F.when(exists, F.lit(1)),
        "severity": F.when(op == "P", F.lit("Info")).otherwise(F.lit("Violation")),
        "deontic": F.when(op == "O", F.lit("obligation")).when(op == "P", F.lit("permission")).otherwise(F.lit("prohibition")),
    }


def emit(grounded: DataFrame) -> DataFrame:
    """One shape for each well-formed formula; the path is the canonical name, or the raw one where unresolved."""
    df = grounded.where("ok").withColumn("path", F.coalesce("path", "pred"))
    df = df.withColumns(emission(F.col("op"), F.col("quant")))
    return df.select(F.md5(F.concat_ws("|", "sent_id", "path", "op")).alias("shape_id"), "sent_id", F.col("cls").alias("target_class"), "path", "min_count", "max_count", "q_min", "severity", "deontic", F.lit("formula").alias("route"), "exception_of")


def direct(formulas: DataFrame) -> DataFrame:
    """Sentence straight to shape for rows without a formula; may come out invalid."""
    df = formulas.where("not ok").withColumn("path", F.col("pred")).withColumn("cls", F.coalesce("cls", F.lit("Thing")))
    df = df.withColumns(emission(F.col("op"), F.lit("forall")))
    return df.select(F.md5(F.concat_ws("|", "sent_id", "path", "op")).alias("shape_id"), "sent_id", F.col("cls").alias("target_class"), "path", "min_count", "max_count", "q_min", "severity", "deontic", F.lit("direct").alias("route"), "exception_of")


def syntax_ok(target_class: Column, path: Column) -> Column:
    return F.coalesce(F.regexp_like(target_class, F.lit("^[A-Z][A-Za-z]*$")) & F.regexp_like(path, F.lit("^[a-z][A-Za-z0-9]*$")), F.lit(False))


def with_validity(shapes: DataFrame) -> DataFrame:
    return shapes.withColumn("valid", syntax_ok(F.col("target_class"), F.col("path")))


def load_valid(shapes: DataFrame) -> DataFrame:
    return with_validity(shapes).where("valid").drop("valid")


def overrides(shapes: DataFrame) -> DataFrame:
    """``(shape_id, overrides_class, overrides_path)``: an exception overrides the class's forbidden path it shares most words with.

    Base paths are few (a vocabulary), so they are aggregated before the join.
    """
    words = lambda c: F.split(F.lower(F.regexp_replace(c, "([a-z])([A-Z])", "$1 $2")), " ")
    base = shapes.where("deontic = 'prohibition' and exception_of is null").select(F.col("target_class").alias("bc"), F.col("path").alias("bp")).distinct()
    ex = shapes.where("deontic = 'permission' and exception_of is not null").select("shape_id", "target_class", "path")
    distinct_ex = ex.select("target_class", "path").distinct()
    pairs = distinct_ex.join(F.broadcast(base), distinct_ex["target_class"] == base["bc"]).withColumn("common", F.size(F.array_intersect(words(F.col("path")), words(F.col("bp"))))).where("common > 0 and path <> bp")
    best = pairs.groupBy("target_class", "path").agg(F.min_by("bp", F.struct(-F.col("common"), F.col("bp"))).alias("overrides_path"))
    return ex.join(F.broadcast(best), ["target_class", "path"]).select("shape_id", F.col("target_class").alias("overrides_class"), "overrides_path")


def defeat(violations: DataFrame, exempt: DataFrame) -> DataFrame:
    """Violations that no exception of their focus node and path defeats."""
    return violations.join(exempt, ["focus_class", "focus_id", "path"], "left_anti")


def rules_only(shapes: DataFrame) -> DataFrame:
    """Distinct constraints: what a validator has to run."""
    return shapes.select("target_class", "path", "min_count", "max_count", "q_min", "severity", "deontic").distinct()


def to_turtle(shapes: DataFrame) -> DataFrame:
    """Text of each shape in a Turtle-like syntax, one row each."""
    line = lambda cond, text: F.when(cond, text)
    body = F.concat_ws(
        " ; ",
        F.concat(F.lit("<urn:shape:"), F.col("shape_id"), F.lit("> a sh:NodeShape")),
        F.concat(F.lit("sh:targetClass ex:"), F.col("target_class")),
        F.concat(F.lit("sh:severity sh:"), F.col("severity")),
        F.concat(F.lit("deontic:type deontic:"), F.col("deontic")),
        F.concat(F.lit("sh:property [ sh:path ex:"), F.col("path"), F.coalesce(F.concat(F.lit(" ; sh:minCount "), F.col("min_count")), F.lit("")), F.coalesce(F.concat(F.lit(" ; sh:maxCount "), F.col("max_count")), F.lit("")), F.coalesce(F.concat(F.lit(" ; sh:qualifiedMinCount "), F.col("q_min")), F.lit("")), F.lit(" ]")),
    )
    return shapes.select("shape_id", F.concat(body, F.lit(" .")).alias("turtle"))


def catalog(formulas: DataFrame, shapes: DataFrame) -> DataFrame:
    """Side-by-side trace of sentence, formula and shape."""
    return formulas.select("sent_id", "text", "op", "formula").join(shapes.select("sent_id", "shape_id", "target_class", "path", "severity", "route"), "sent_id")


__all__ = ["Window", "catalog", "defeat", "direct", "emit", "formalise", "load_valid", "overrides", "rules_only", "syntax_ok", "to_turtle", "with_validity"]
