"""Order-independent digests of results, and how runs compare."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def row_digest(*cols: str):  # noqa: ANN201
    """60 bits of md5 over the columns, nulls marked."""
    text = F.concat_ws("|", *[F.coalesce(F.col(c).cast("string"), F.lit("~")) for c in cols])
    return F.conv(F.substring(F.md5(text), 1, 15), 16, 10).cast("long")


def digest(df: DataFrame, *cols: str) -> DataFrame:
    """``(n, xor, total)``: equal for equal multisets of rows, whatever their order or partitioning."""
    d = row_digest(*(cols or df.columns))
    return df.agg(F.count(F.lit(1)).alias("n"), F.coalesce(F.bit_xor(d), F.lit(0)).cast("long").alias("xor"), F.coalesce(F.sum(d.cast("decimal(38,0)")), F.lit(0)).cast("string").alias("total"))


def compare(runs: list[DataFrame]) -> DataFrame:
    """How many distinct digests so many runs gave."""
    out = runs[0]
    for r in runs[1:]:
        out = out.unionByName(r)
    return out.agg(F.count(F.lit(1)).alias("n_runs"), F.count_distinct("n", "xor", "total").alias("n_digests"))


def drift(a: DataFrame, b: DataFrame, key: str, value: str) -> DataFrame:
    """Rows of two runs that differ: changed, only in the first, only in the second, same."""
    left = a.select(key, F.col(value).alias("va"), F.lit(1).alias("ia"))
    right = b.select(key, F.col(value).alias("vb"), F.lit(1).alias("ib"))
    both = left.join(right, key, "full")
    kind = F.when(F.col("ia").isNull(), "only_second").when(F.col("ib").isNull(), "only_first").when(F.col("va").eqNullSafe(F.col("vb")), "same").otherwise("changed")
    return both.groupBy(kind.alias("kind")).agg(F.count(F.lit(1)).alias("n"))
