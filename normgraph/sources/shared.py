"""Where intermediate files go: the cluster's shared checkpoint folder, or the warehouse where none is set."""

from __future__ import annotations

import atexit
import contextlib
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def scratch(spark: SparkSession) -> str:
    """A folder that all executors see; one of this machine only where there is no other machine."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not found:
        local = spark.sparkContext.master.startswith("local[") or spark.sparkContext.master == "local"
        own = tempfile.mkdtemp(prefix="normgraph-") if local else f"{spark.conf.get('spark.sql.warehouse.dir').rstrip('/')}/normgraph-scratch"
        spark.sparkContext.setCheckpointDir(own)
        found = spark.sparkContext.getCheckpointDir()
    return found.rstrip("/")


def _remove(spark: SparkSession, path: str) -> None:
    with contextlib.suppress(Exception):  # the session may have ended; the folder is then the cluster's to clear
        p = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
        p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)


def folder(spark: SparkSession, tag: str) -> str:
    """A new path in the shared folder; what is written there goes when the process ends."""
    path = f"{scratch(spark)}/{tag}-{uuid.uuid4().hex}"
    atexit.register(_remove, spark, path)
    return path


def stored(df: DataFrame, tag: str) -> DataFrame:
    """``df`` written to the shared folder and read back, for a plan that is used more than once."""
    path = folder(df.sparkSession, tag)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)
