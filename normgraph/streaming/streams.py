"""Structured Streaming over event files: windows, late data, joins, deadlines and incremental rules.

Each query drains the files that are there (``availableNow``) into a Parquet table in the shared folder and returns
it, so that a batch query can be held against it.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from normgraph.sources.shared import folder
from normgraph.sources.tables import table

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
FILES = 4


def query(f):  # noqa: ANN001, ANN201
    QUERIES[f.__name__] = f
    return f


def source(spark: SparkSession, sf: str, max_files: int = 1, more: tuple[str, ...] = (), close: bool = False, late: bool = False) -> DataFrame:
    """The events as a stream of files in time order; ``ts`` gets a zone, which watermarks need.

    With ``close`` a last file has a closing row for each user with a signup, at the time of the last event.
    With ``late`` a last file brings the rows of the first quarter of the time a second time.
    """
    cols = ["event_id", "ts", "user_id", "event_type", "value", *more]
    path = folder(spark, "events")
    e = table(spark, sf, "events", *cols[:5]).withColumn("ts", F.col("ts").cast("timestamp"))
    lo, hi = e.agg(F.min(F.unix_timestamp("ts")), F.max(F.unix_timestamp("ts"))).first()
    step = ((hi or 0) - (lo or 0)) // FILES + 1
    for i in range(FILES):  # one after the other: the file source takes files in the order of their times
        e.where(F.floor((F.unix_timestamp("ts") - (lo or 0)) / step) == i).coalesce(1).write.mode("append").parquet(path)
    if close:
        last = e.agg(F.max("ts").alias("ts"))
        users = e.where("event_type = 'signup'").select("user_id").distinct().crossJoin(F.broadcast(last))
        rows = {"event_id": F.lit(2**63 - 1), "event_type": F.lit("close"), "value": F.lit(None)}
        users.select(*[(rows.get(f.name, F.col(f.name))).cast(f.dataType).alias(f.name) for f in e.schema]).coalesce(1).write.mode("append").parquet(path)
    if late:
        e.where(F.floor((F.unix_timestamp("ts") - (lo or 0)) / step) == 0).coalesce(1).write.mode("append").parquet(path)
    return spark.readStream.schema(e.schema).option("maxFilesPerTrigger", max_files).option("latestFirst", "false").parquet(path)


def drain(df: DataFrame, mode: str = "append") -> DataFrame:
    """Run to the end of the input and read what was written; ``complete`` results replace the table."""
    spark = df.sparkSession
    base = folder(spark, "stream")
    writer = df.writeStream.outputMode(mode).option("checkpointLocation", f"{base}/state").trigger(availableNow=True)
    if mode == "append":
        q = writer.format("parquet").start(f"{base}/out")
    else:
        q = writer.foreachBatch(lambda b, _: b.write.mode("overwrite").parquet(f"{base}/out")).start()
    q.awaitTermination()
    return spark.read.schema(df.schema).parquet(f"{base}/out")


@query
def st_tumbling(spark, sf):
    w = source(spark, sf).groupBy(F.window("ts", "1 day").alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n"))
    return drain(w, "complete").select(F.unix_timestamp("w.start").alias("start"), "event_type", "n")


@query
def st_sliding(spark, sf):
    w = source(spark, sf).groupBy(F.window("ts", "2 days", "1 day").alias("w")).agg(F.count(F.lit(1)).alias("n"))
    return drain(w, "complete").select(F.unix_timestamp("w.start").alias("start"), "n")


@query
def st_session(spark, sf):
    w = source(spark, sf).withWatermark("ts", "1 day").groupBy(F.session_window("ts", "12 hours").alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n"))
    return drain(w, "complete").select("user_id", F.unix_timestamp("w.start").alias("start"), "n")


@query
def st_dedup(spark, sf):
    s = source(spark, sf)
    twice = s.select("event_id", "ts", F.explode(F.array(F.lit(1), F.lit(2))).alias("copy")).withWatermark("ts", "1 day")
    return drain(twice.dropDuplicatesWithinWatermark(["event_id"]).select("event_id", "ts")).select("event_id")


@query
def st_static_join(spark, sf):
    """Events against a shape table: value limits by event type; the static side has a row for each shape."""
    shapes = spark.createDataFrame([("purchase", 50.0), ("error", 10.0)], "event_type string, max_value double")
    j = source(spark, sf).join(F.broadcast(shapes), "event_type").where("value > max_value")
    return drain(j.select("event_id", "event_type"))


@query
def st_stream_join(spark, sf):
    """Clicks followed by a purchase of the same user within an hour; both sides are watermarked."""
    s = source(spark, sf, max_files=FILES)
    c = s.where("event_type = 'click'").select(F.col("event_id").alias("click"), F.col("user_id").alias("u1"), F.col("ts").alias("t1")).withWatermark("t1", "1 hour")
    p = source(spark, sf, max_files=FILES).where("event_type = 'purchase'").select(F.col("event_id").alias("purchase"), F.col("user_id").alias("u2"), F.col("ts").alias("t2")).withWatermark("t2", "1 hour")
    return drain(c.join(p, F.expr("u1 = u2 and t2 >= t1 and t2 <= t1 + interval 1 hour")).select("click", "purchase"))


@query
def st_prohibition(spark, sf):
    """More than one error of a user within a day, by windows."""
    e = source(spark, sf).where("event_type = 'error'").groupBy(F.window("ts", "1 day").alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n"))
    return drain(e, "complete").where("n > 1").select(F.unix_timestamp("w.start").alias("start"), "user_id", "n")


@query
def st_watermark_late(spark, sf):
    """Windows under a watermark: those it has closed are in the output, the open rest is not."""
    w = source(spark, sf).withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 day").alias("w")).agg(F.count(F.lit(1)).alias("n"))
    return drain(w).select(F.unix_timestamp("w.start").alias("start"), "n")


@query
def st_watermark_late_file(spark, sf):
    """The same windows when a file of old rows arrives last: these are behind the watermark and count nowhere."""
    w = source(spark, sf, late=True).withWatermark("ts", "1 hour").groupBy(F.window("ts", "1 day").alias("w")).agg(F.count(F.lit(1)).alias("n"))
    return drain(w).select(F.unix_timestamp("w.start").alias("start"), "n")


OWED_DAYS = 7


@query
def st_deadline(spark, sf):
    """A purchase is owed within seven days of a user's signup: kept or missed, as a later event of the user shows.

    Signups without such an event have no row here; ``st_deadline_all`` has one for every signup.
    """
    return _deadlines(source(spark, sf, max_files=1))


@query
def st_deadline_all(spark, sf):
    """One row for each signup: kept, missed, or open (still within its time at the last event of all)."""
    return _deadlines(source(spark, sf, max_files=1, close=True))


def _deadlines(events: DataFrame) -> DataFrame:
    """Verdicts from a stream; state holds the open signups of a user, which a closing row settles."""

    def judge(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        open_ = list(state.get[0]) if state.exists else []
        out = []
        for f in frames:
            for r in f.sort_values(["sec", "event_id"]).itertuples():
                missed = [s for s in open_ if r.sec > s + OWED_DAYS * 86400]
                out += [(key[0], s, "missed") for s in missed]
                open_ = [s for s in open_ if s not in missed]
                if r.event_type == "signup":
                    open_.append(int(r.sec))
                elif r.event_type == "purchase":
                    out += [(key[0], s, "kept") for s in open_]
                    open_ = []
                elif r.event_type == "close":
                    out += [(key[0], s, "open") for s in open_]
                    open_ = []
        state.update((open_,))
        yield pd.DataFrame(out, columns=["user_id", "signup", "verdict"])

    s = events.where("event_type in ('signup', 'purchase', 'close')").select("user_id", "event_id", "event_type", F.unix_timestamp("ts").alias("sec"))
    v = s.groupBy("user_id").applyInPandasWithState(judge, "user_id long, signup long, verdict string", "open array<long>", "append", GroupStateTimeout.NoTimeout)
    return drain(v)


@query
def st_incremental_rules(spark, sf):
    """Rules arrive in batches; a revised rule supersedes the old version, and readers take the latest."""
    base = folder(spark, "rules")
    s = source(spark, sf).select("event_id", "user_id", "value")

    def store(batch: DataFrame, batch_id: int) -> None:  # idempotent: one folder for each batch
        batch.withColumn("version", F.lit(batch_id)).write.mode("overwrite").parquet(f"{base}/batch={batch_id}")

    q = s.writeStream.foreachBatch(store).option("checkpointLocation", folder(spark, "rules-state")).trigger(availableNow=True).start()
    q.awaitTermination()
    rules = spark.read.parquet(f"{base}/batch=*")
    return rules.groupBy("user_id").agg(F.max_by("event_id", F.struct("version", "event_id")).alias("event_id"), F.count(F.lit(1)).alias("n_versions"))
