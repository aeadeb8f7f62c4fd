"""Helpers shared by the training-data operators: table access, shared storage, Arrow chunks."""

from __future__ import annotations

import atexit
import contextlib
import ctypes
import tempfile
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

CHUNK_BYTES = 2 << 20
BATCH_BYTES = 4 << 20
_CLEANUP_SETTING = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
_BATCH_SETTING = "spark.sql.execution.arrow.maxBytesPerBatch"


def table(spark: SparkSession, sf_dir: str, name: str, *cols: str) -> DataFrame:
    """One of the given tables, pruned to ``cols`` at the scan."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*cols) if cols else df


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors share: ``spark.checkpoint.dir``; where unset, the warehouse, or a folder of the only machine."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not found:
        local = spark.sparkContext.master.startswith("local[") or spark.sparkContext.master == "local"
        spark.sparkContext.setCheckpointDir(tempfile.mkdtemp(prefix="normgraph-") if local else f"{spark.conf.get('spark.sql.warehouse.dir').rstrip('/')}/normgraph-scratch")
        found = spark.sparkContext.getCheckpointDir()
    return found.rstrip("/")


def _remove(spark: SparkSession, path: str) -> None:
    try:
        jvm = spark.sparkContext._jvm
        p = jvm.org.apache.hadoop.fs.Path(path)
        p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)
    except Exception:  # noqa: BLE001  the session may have ended; the folder is then the cluster's to clear
        pass


_open: list[Workspace] = []


class Workspace:
    """Intermediate tables of one operator; they go when the operator's own result has been written."""

    def __init__(self) -> None:
        self.paths: list[tuple[SparkSession, str]] = []

    def __enter__(self) -> Workspace:
        _open.append(self)
        return self

    def __exit__(self, *_: object) -> None:
        _open.remove(self)
        for spark, path in self.paths:
            _remove(spark, path)

    def result(self, df: DataFrame, tag: str) -> DataFrame:
        """Write the result, which outlives this workspace."""
        _open.remove(self)
        try:
            return materialise(df, tag)
        finally:
            _open.append(self)


def materialise(df: DataFrame, tag: str) -> DataFrame:
    """Write ``df`` to the shared folder and read it back: cuts lineage and survives lost executors.

    The files of its shuffles go as soon as it is written, where this Spark can do so; else once the driver's
    collector finds that the plan is out of use, so that is run too.
    """
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{tag}-{uuid.uuid4().hex}"
    before = spark.conf.get(_CLEANUP_SETTING, None)
    spark.conf.set(_CLEANUP_SETTING, "true")
    try:
        df.write.option("compression", "zstd").parquet(path)
    finally:
        spark.conf.unset(_CLEANUP_SETTING) if before is None else spark.conf.set(_CLEANUP_SETTING, before)
    spark.sparkContext._jvm.System.gc()
    if _open:
        _open[-1].paths.append((spark, path))
    else:
        atexit.register(_remove, spark, path)
    return spark.read.schema(df.schema).parquet(path)


def _trim() -> None:
    """Give memory that a task no longer needs back to the system: Spark keeps its Python workers."""
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):
        ctypes.CDLL(None).malloc_trim(0)


def text_bytes(col: pa.ChunkedArray | pa.Array) -> list[bytes]:
    """UTF-8 bytes of a string column; null becomes empty."""
    return [x or b"" for x in col.cast(pa.binary()).to_pylist()]


def chunks(batches: Iterator[pa.RecordBatch], column: str = "text", limit: int = CHUNK_BYTES) -> Iterator[pa.RecordBatch]:
    """Split Arrow batches so that a chunk holds about ``limit`` bytes of text, one row at least."""
    for batch in batches:
        if not batch.num_rows:
            continue
        col = batch.column(batch.schema.get_field_index(column))
        sizes = np.array([x or 0 for x in pc.binary_length(col).to_pylist()], dtype=np.int64) + 1
        block = np.cumsum(sizes) // limit
        cuts = np.flatnonzero(np.diff(block)) + 1
        edges = [0, *cuts.tolist(), batch.num_rows]
        for a, b in zip(edges[:-1], edges[1:], strict=True):
            if b > a:
                yield batch.slice(a, b - a)
    _trim()


def runs_of(batches: Iterator[pa.RecordBatch], keys: tuple[str, ...]) -> Iterator[pa.Table]:
    """Groups of rows with equal integer ``keys`` from batches sorted by them; a group may span batches."""
    held: list[pa.RecordBatch] = []

    def edge(batch: pa.RecordBatch, row: int) -> tuple:
        return tuple(batch.column(batch.schema.get_field_index(k))[row].as_py() for k in keys)

    for batch in batches:
        if not batch.num_rows:
            continue
        new = np.zeros(batch.num_rows, dtype=bool)
        for k in keys:
            v = batch.column(batch.schema.get_field_index(k)).to_numpy(zero_copy_only=False)
            new[1:] |= v[1:] != v[:-1]
        new[0] = bool(held) and edge(held[-1], held[-1].num_rows - 1) != edge(batch, 0)
        cuts = [*np.flatnonzero(new).tolist(), batch.num_rows]
        at = 0
        for cut in cuts:
            if cut > at:
                held.append(batch.slice(at, cut - at))
            if cut < batch.num_rows and held:
                yield pa.Table.from_batches(held)
                held = []
            at = cut
    if held:
        yield pa.Table.from_batches(held)


def ragged_take(flat: np.ndarray, offs: np.ndarray, which: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Concatenate ``flat[offs[i]:offs[i+1]]`` for every i of ``which``; also the lengths."""
    begin = offs[which].astype(np.int64)
    lens = offs[which + 1] - begin
    ends = np.cumsum(lens)
    total = int(ends[-1]) if len(ends) else 0
    idx = np.arange(total, dtype=np.int64)
    idx += np.repeat(begin - (ends - lens), lens)
    return flat[idx], lens


def prune(df: DataFrame, *cols: str) -> DataFrame:
    """Only the named columns, in this order; extra and clashing columns of the caller never reach an operator.

    Python workers get their rows in batches of about ``BATCH_BYTES``, so that long texts don't add up in memory.
    """
    conf = df.sparkSession.conf
    if conf.get(_BATCH_SETTING, None) != str(BATCH_BYTES):
        conf.set(_BATCH_SETTING, str(BATCH_BYTES))
    return df.select(*[F.col(f"`{c}`") for c in cols])
