"""Cost measures over a sampled meter series, and price estimates."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

#: Printed token totals of one corpus and run time in minutes.
TOKENS_IN, TOKENS_OUT, MINUTES, RULES, SENTENCES = 2_200_000, 330_000, 34.9, 443, 1663
#: Our own price rates per million tokens (in, out), in four steps.
RATES = (("api_1", 2.75, 8.27), ("api_2", 0.15, 0.60), ("api_3", 3.00, 14.94), ("api_4", 0.60, 2.88))


def summary(series: DataFrame, ts: str = "ts", value: str = "value") -> DataFrame:
    """Mean, 95th percentile, peak, time covered and energy (trapezoids over hours) of a meter series.

    Energy needs the previous sample: a window by day, whose first sample starts a new trapezoid.
    """
    s = series.select(F.col(ts).cast("timestamp").alias("ts"), F.col(value).alias("v"), "event_id")
    w = Window.partitionBy(F.to_date("ts")).orderBy("ts", "event_id")
    hours = (F.unix_micros("ts") - F.unix_micros(F.lag("ts").over(w))) / 3.6e9
    s = s.withColumn("wh", F.coalesce((F.col("v") + F.lag("v").over(w)) / 2 * hours, F.lit(0.0)))
    return s.agg(F.count(F.lit(1)).alias("n"), F.avg("v").alias("mean"), F.percentile("v", F.lit(0.95)).alias("p95"), F.max("v").alias("peak"), F.sum("wh").alias("energy_wh"))


def price(spark, tokens_in: int = TOKENS_IN, tokens_out: int = TOKENS_OUT, rates=RATES) -> DataFrame:  # noqa: ANN001
    df = spark.createDataFrame(list(rates), "api string, rate_in double, rate_out double")
    return df.select("api", ((F.col("rate_in") * tokens_in + F.col("rate_out") * tokens_out) / 1e6).alias("usd"))
