"""Exact nearest vectors by cosine: blocks of queries against blocks of all rows, multiplied inside tasks."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

QUERY_ROWS, BASE_ROWS = 512, 2048
#: Row parts are streamed by each task, so that few of them keep the lists to merge short.
BASE_PARTS = 4
_BATCH_SETTING, _BATCH_BYTES = "spark.sql.execution.arrow.maxBytesPerBatch", 4 << 20
_BLOCK = "ids binary, labels binary, known binary, vectors binary"
_SCALE = 1_000_000  # cosines are compared at six places
_NO_COSINE, _NOT_A_PAIR = -(1 << 30), -(1 << 31)


def _packed(df: DataFrame, rows: int, parts: int) -> DataFrame:
    """Rows ``(vec_id, embedding, label)`` as blocks of bytes."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, rows):
                b = batch.slice(at, rows)
                ids, vectors, labels = (b.column(b.schema.get_field_index(c)) for c in ("vec_id", "embedding", "label"))
                width = max((len(v) for v in vectors if v.is_valid), default=1)
                # a vector that is missing, or has a missing element, has no cosine with any
                m = np.array([v if v is not None and len(v) == width else [None] * width for v in vectors.to_pylist()], dtype=np.float64)
                known = ~labels.is_null().to_numpy(zero_copy_only=False)
                out = (ids.to_numpy(zero_copy_only=False).astype("<i8"), labels.fill_null(0).to_numpy(zero_copy_only=False).astype("<i8"), known, m.astype("<f4"))
                yield pa.RecordBatch.from_arrays([pa.array([x.tobytes()], pa.binary()) for x in out], names=["ids", "labels", "known", "vectors"])

    return df.select("vec_id", "embedding", "label").repartition(parts, "vec_id").mapInArrow(run, _BLOCK)


def _block(row: dict, side: str) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    ids, labels = (np.frombuffer(row[f"{side}_{c}"], "<i8") for c in ("ids", "labels"))
    m = np.frombuffer(row[f"{side}_vectors"], "<f4").reshape(len(ids), -1).astype(np.float64)
    norms = np.sqrt((m * m).sum(1))
    return ids, labels, np.frombuffer(row[f"{side}_known"], bool), m, np.where(norms > 0, norms, np.nan)


def _best(rank: np.ndarray, ids: np.ndarray, hit: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The ``k`` first of each line: highest rank, then lowest id."""
    take = np.lexsort((ids, -rank), axis=1)[:, :k]
    return tuple(np.take_along_axis(x, take, axis=1) for x in (rank, ids, hit))


def top_k(rows: DataFrame, queries: DataFrame, k: int = 10) -> DataFrame:
    """``(q, ql, vec_id, hit, rank)``: for each query its ``k`` rows of highest cosine at six places, ties to the lowest id.

    Both are ``(vec_id, embedding, label)``. No row is compared with a query of its own id; ``hit`` tells equal labels.
    Every pair is scored in double precision; a task keeps ``k`` rows of each of its queries.
    """
    spark = rows.sparkSession
    spark.conf.set(_BATCH_SETTING, str(_BATCH_BYTES))
    side = lambda df, s: df.select(*[F.col(c).alias(f"{s}_{c}") for c in df.columns])
    base = side(_packed(rows, BASE_ROWS, BASE_PARTS), "e")
    asked = side(_packed(queries, QUERY_ROWS, spark.sparkContext.defaultParallelism), "q")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[bytes, list] = {}
        for batch in batches:
            for row in batch.to_pylist():
                q, ql, qk, qm, qn = _block(row, "q")
                e, el, ek, em, en = _block(row, "e")
                if row["q_ids"] not in held:
                    held[row["q_ids"]] = [q, ql, qk, *(np.empty((len(q), 0), t) for t in (np.int64, np.int64, bool))]
                order = np.argsort(e, kind="stable")
                e, el, ek, em, en = e[order], el[order], ek[order], em[order], en[order]
                if em.shape[1] == qm.shape[1]:
                    cos = (qm @ em.T) / (en[None, :] * qn[:, None])
                else:
                    cos = np.full((len(q), len(e)), np.nan)
                rank = np.where(np.isnan(cos), _NO_COSINE, np.sign(cos) * np.floor(np.abs(np.nan_to_num(cos)) * _SCALE + 0.5)).astype(np.int64)
                rank[q[:, None] == e[None, :]] = _NOT_A_PAIR
                key = rank * BASE_ROWS - np.arange(len(e))  # unlike in a line, and in its order
                few = np.argpartition(-key, min(k, len(e)) - 1, axis=1)[:, :k]
                mine = held[row["q_ids"]]
                new = (np.take_along_axis(rank, few, axis=1), e[few], (el[few] == ql[:, None]) & ek[few] & qk[:, None])
                mine[3:] = _best(*(np.concatenate(x, axis=1) for x in zip(mine[3:], new, strict=True)), k)
        for q, ql, qk, rank, ids, hit in held.values():
            line, _ = keep = np.nonzero(rank > _NOT_A_PAIR)
            labels = pa.array(ql[line], pa.int64(), mask=~qk[line])
            cols = [pa.array(q[line]), labels, pa.array(ids[keep]), pa.array(hit[keep]), pa.array(rank[keep])]
            yield pa.RecordBatch.from_arrays(cols, names=["q", "ql", "vec_id", "hit", "score"])

    found = base.hint("shuffle_replicate_nl").join(asked).mapInArrow(run, "q long, ql long, vec_id long, hit boolean, score long")
    first = F.row_number().over(Window.partitionBy("q").orderBy(F.col("score").desc(), "vec_id"))
    return found.withColumn("rank", first).where(F.col("rank") <= k).drop("score")
