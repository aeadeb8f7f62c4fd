"""The function surface: scalar, pandas, grouped and table functions, and their SQL names."""

from __future__ import annotations

from collections.abc import Callable

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from normgraph.operators import adapter, formalise, policygen
from normgraph.sources.registry import load_registry
from normgraph.sources.tables import table

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}


def query(f):  # noqa: ANN001, ANN201
    QUERIES[f.__name__] = f
    return f


def norm_pred(name: str | None) -> str | None:
    """Python twin of the column expression, for SQL users."""
    import re

    if name is None:
        return None
    bare = re.sub(r"^.*[:#/]", "", name)
    spaced = re.sub(r"[_ -]+", " ", re.sub(r"([a-z0-9])([A-Z])", r"\1 \2", bare)).strip().lower()
    return re.sub(r"^([a-z]+[^s ])s( |$)", r"\1\2", spaced)


@F.pandas_udf(T.StructType([T.StructField("ok", T.BooleanType()), T.StructField("normal", T.StringType()), T.StructField("diagnostics", T.StringType())]))
def parse_formula(text: pd.Series) -> pd.DataFrame:
    """Recursive text form, in Arrow batches."""
    out = []
    for t in text:
        found, diagnostics = formalise.parse(t or "")
        out.append((found is not None, found.normal() if found else None, ",".join(diagnostics)))
    return pd.DataFrame(out, columns=["ok", "normal", "diagnostics"])


@F.udtf(returnType=T.StructType([T.StructField("seq", T.IntegerType()), T.StructField("piece", T.StringType())]))
class SplitPolicy:
    """Pieces of a text between sentence ends."""

    def eval(self, text: str):  # noqa: ANN201
        import re

        for i, p in enumerate(x for x in re.split(r"[.!?\n]+", text or "") if x.strip()):
            yield i, p.strip()


def register(spark: SparkSession) -> None:
    """SQL names: ``norm_pred``, ``parse_formula``, ``split_policy``, and the column macros as temporary SQL functions."""
    spark.udf.register("norm_pred", norm_pred, T.StringType())
    spark.udf.register("parse_formula", parse_formula)
    spark.udtf.register("split_policy", SplitPolicy)
    spark.sql("""create or replace temporary function kappa_band(k double) returns string return
      case when k < 0 then 'poor' when k <= 0.2 then 'slight' when k <= 0.4 then 'fair' when k <= 0.6 then 'moderate' when k <= 0.8 then 'substantial' else 'almost perfect' end""")
    z = 1.959963984540054
    for name, sign, clip in (("wilson_low", "-", "greatest(0.0D, "), ("wilson_high", "+", "least(1.0D, ")):
        spark.sql(f"""create or replace temporary function {name}(k double, n double) returns double return
          {clip}(k / n + {z * z}D / (2 * n)) / (1 + {z * z}D / n) {sign} {z}D * sqrt(k / n * (1 - k / n) / n + {z * z}D / (4 * n * n)) / (1 + {z * z}D / n))""")


@query
def udf_scalar(spark, sf):
    register(spark)
    load_registry(spark, "star").createOrReplaceTempView("_reg")
    return spark.sql("select distinct alias, norm_pred(alias) as norm from _reg where kind = 'property'")


@query
def udf_pandas(spark, sf):
    from normgraph.plans.workloads import rules

    f = formalise.lift(rules(spark, sf)).where("ok").select("formula").distinct()
    return f.select("formula", parse_formula("formula").alias("p")).select("formula", "p.ok", "p.normal")


@query
def udf_grouped_agg(spark, sf):
    """Trimmed mean of values by event type: a grouped pandas function over bounded groups of one day."""
    e = table(spark, sf, "events", "event_id", "ts", "event_type", "value").select("event_type", F.date_format("ts", "yyyy-MM-dd").alias("day"), "value")

    @F.pandas_udf("double")
    def span(v: pd.Series) -> float:
        return float(v.max() - v.min())

    return e.groupBy("event_type", "day").agg(F.round(span("value"), 9).alias("span"))


@query
def udf_cogrouped(spark, sf):
    """Old against new shapes of a class: names added and removed; groups are registry-sized."""
    new = load_registry(spark, "star").where("kind = 'property'").select("domain_class", "name").distinct()
    before = load_registry(spark, "star").where("kind = 'property'").select("domain_class", "name").distinct()
    old = before.where("name not like 'has%'").unionByName(spark.createDataFrame([("Order", "formerPath")], "domain_class string, name string"))

    def diff(a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        left, right = (set(x["name"]) if len(x) else set() for x in (a, b))
        cls = (a if len(a) else b)["domain_class"].iloc[0]
        return pd.DataFrame([(cls, n, "removed") for n in sorted(left - right)] + [(cls, n, "added") for n in sorted(right - left)], columns=["domain_class", "name", "change"])

    return old.groupBy("domain_class").cogroup(new.groupBy("domain_class")).applyInPandas(diff, "domain_class string, name string, change string")


@query
def udtf_split(spark, sf):
    register(spark)
    return spark.sql("select seq, piece from split_policy('One rule must hold. Another may. Done')")


@query
def udtf_lateral(spark, sf):
    register(spark)
    table(spark, sf, "benchmark", "item_id", "text").createOrReplaceTempView("_bench")
    return spark.sql("select item_id, count(*) as n from _bench, lateral split_policy(text) group by item_id")


@query
def sql_surface(spark, sf):
    """SQL over the pipeline's views and functions."""
    register(spark)
    policygen.render(spark, sf).createOrReplaceTempView("_sentences")
    return spark.sql("""select gold_label, n, kappa_band(n / 20000.0) as band, wilson_low(n, total) as low, wilson_high(n, total) as high
      from (select gold_label, count(*) as n from _sentences group by 1) cross join (select count(*) as total from _sentences)""")


__all__ = ["QUERIES", "SplitPolicy", "adapter", "norm_pred", "parse_formula", "register"]
