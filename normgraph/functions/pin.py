"""Pinned columns."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def pin(df: DataFrame, **cols: Column) -> DataFrame:
    """Add or replace computed columns behind a one-row generator.

    The optimiser pushes a filter on a computed column below its projection, writing the expression out again for
    each use; for long pattern expressions that multiplies the work.  Nothing is pushed through a generator.
    """
    kept = [f"`{c}`" for c in df.columns if c not in cols]
    return df.select(*kept, F.inline(F.array(F.struct(*[c.alias(n) for n, c in cols.items()]))))
