"""Grammar-compressed token files.

Documents are encoded in ascending doc_id order and their ids written in shards.  Each shard is compressed by
re-pairing: frequent pairs of neighbouring symbols are replaced, round after round, by nonterminals.  A shard
stores its alphabet, the rules with their expansion lengths, the remaining sequence, and the expansion offset of
every ``CHECK``-th symbol, so that any range of ids is decoded from the nearest offset.

The file format is one Parquet row a shard, with the bytes in ``payload`` (little-endian): the magic ``NGRP``;
unsigned 32-bit counts of ids, alphabet, rules and sequence; alphabet (u32); rules (u32 pairs); expansion
lengths of the rules (u32); sequence (u16 where all symbols fit, else u32); offsets (u64).  Spark's writer
commits the files, on any file system.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from normgraph.llm.bpe import block_encoder
from normgraph.llm.common import chunks, materialise, prune
from normgraph.llm.encoding import vocabulary_path

MAGIC, CHECK = b"NGRP", 1024


@dataclass(frozen=True)
class RePairConfig:
    """``shard_ids`` is where a shard closes (documents are never split); rules come in ``rounds``."""

    shard_ids: int = 1 << 20
    rounds: int = 4
    rules_a_round: int = 4096
    min_count: int = 24
    end_id: int = 2


def compress(ids: np.ndarray, cfg: RePairConfig = RePairConfig()) -> bytes:
    """Shard bytes for a sequence of unsigned 32-bit ids."""
    ids = np.ascontiguousarray(ids, dtype=np.uint32)
    if len(ids) and int(ids.max()) < 1 << 24:
        present = np.flatnonzero(np.bincount(ids)).astype(np.uint32)
        table = np.zeros(int(present[-1]) + 1, dtype=np.uint32)
        table[present] = np.arange(len(present), dtype=np.uint32)
        seq = table[ids]
    else:
        present, inverse = np.unique(ids, return_inverse=True)
        seq = inverse.astype(np.uint32)
    lengths = np.ones(len(present), dtype=np.uint32)
    rules = np.zeros((0, 2), dtype=np.uint32)
    for _ in range(cfg.rounds):
        symbols = len(lengths)
        room = min(cfg.rules_a_round, 65536 - symbols)
        if len(seq) < 2 or room <= 0:
            break
        code = (seq[:-1] << np.uint32(16)) | seq[1:]
        ordered = np.sort(code)
        edge = np.flatnonzero(np.concatenate([[True], ordered[1:] != ordered[:-1]]))
        count = np.diff(edge, append=len(ordered))
        some = np.flatnonzero(count >= cfg.min_count)
        if not len(some):
            break
        if len(some) > room:
            some = some[np.argsort(-count[some], kind="stable")[:room]]
        chosen = np.sort(ordered[edge[some]])
        left = np.zeros(symbols, dtype=bool)
        right = np.zeros(symbols, dtype=bool)
        left[chosen >> np.uint32(16)] = True
        right[chosen & np.uint32(0xFFFF)] = True
        at = np.flatnonzero(left[seq[:-1]] & right[seq[1:]])
        found = np.minimum(np.searchsorted(chosen, code[at]), len(chosen) - 1)
        good = chosen[found] == code[at]
        at, found = at[good], found[good]
        new_run = np.concatenate([[True], at[1:] != at[:-1] + 1])  # of overlapping pairs every other one is taken
        begin = np.maximum.accumulate(np.where(new_run, np.arange(len(at)), 0))
        take = (np.arange(len(at)) - begin) % 2 == 0
        at, found = at[take], found[take]
        seq[at] = (symbols + found).astype(np.uint32)
        keep = np.ones(len(seq), dtype=bool)
        keep[at + 1] = False
        seq = seq[keep]
        pairs = np.stack([chosen >> np.uint32(16), chosen & np.uint32(0xFFFF)], axis=1)
        rules = np.concatenate([rules, pairs])
        lengths = np.concatenate([lengths, lengths[pairs[:, 0]] + lengths[pairs[:, 1]]])
    small = len(lengths) <= 65536
    ends = np.cumsum(lengths[seq], dtype=np.uint64)
    offsets = np.concatenate([np.zeros(1, dtype=np.uint64), ends[CHECK - 1 :: CHECK]])
    counts = np.array([len(ids), len(present), len(rules), len(seq)], dtype="<u4")
    return b"".join([MAGIC, counts.tobytes(), present.astype("<u4").tobytes(), rules.astype("<u4").tobytes(), lengths[len(present) :].astype("<u4").tobytes(), seq.astype("<u2" if small else "<u4").tobytes(), offsets.astype("<u8").tobytes()])


class Shard:
    """A shard's parts, for whole and for random-access decoding."""

    def __init__(self, payload: bytes):
        if payload[:4] != MAGIC:
            raise ValueError("not a shard of this format")
        self.n, n_alpha, n_rules, n_seq = np.frombuffer(payload, "<u4", 4, 4).tolist()
        at = 20
        self.alphabet = np.frombuffer(payload, "<u4", n_alpha, at)
        at += 4 * n_alpha
        self.rules = np.frombuffer(payload, "<u4", 2 * n_rules, at).reshape(-1, 2)
        at += 8 * n_rules
        self.lengths = np.concatenate([np.ones(n_alpha, dtype=np.uint32), np.frombuffer(payload, "<u4", n_rules, at)])
        at += 4 * n_rules
        kind = "<u2" if n_alpha + n_rules <= 65536 else "<u4"
        self.seq = np.frombuffer(payload, kind, n_seq, at)
        at += n_seq * np.dtype(kind).itemsize
        self.offsets = np.frombuffer(payload, "<u8", 1 + n_seq // CHECK, at)

    def _expand(self, seq: np.ndarray) -> np.ndarray:
        seq = seq.astype(np.uint32)
        n_alpha = len(self.alphabet)
        while True:
            rule = seq >= n_alpha
            n = int(rule.sum())
            if not n:
                return self.alphabet[seq]
            at = np.arange(len(seq)) + np.cumsum(rule) - rule
            out = np.empty(len(seq) + n, dtype=np.uint32)
            out[at] = seq
            pairs = self.rules[seq[rule] - n_alpha]
            out[at[rule]] = pairs[:, 0]
            out[at[rule] + 1] = pairs[:, 1]
            seq = out

    def decode(self, start: int = 0, count: int | None = None) -> np.ndarray:
        """Ids ``start .. start + count``, expanded from the nearest stored offset."""
        stop = self.n if count is None else min(self.n, start + count)
        if stop <= start:
            return np.zeros(0, dtype=np.uint32)
        block = int(np.searchsorted(self.offsets, start, side="right")) - 1
        last = int(np.searchsorted(self.offsets, stop, side="left"))
        part = self.seq[block * CHECK : min(len(self.seq), last * CHECK)]
        ids = self._expand(part)
        base = int(self.offsets[block])
        return ids[start - base : stop - base]


def write_shards(docs: DataFrame, path: str | None = None, cfg: RePairConfig = RePairConfig(), vocabulary: str | None = None) -> DataFrame:
    """Encode whole texts in ascending doc_id order, write the shards, return the frame that reads them.

    Columns: part, seq (together the order of shards), n_ids, doc_ids, counts (ids of each document, end id
    included), payload.  Null and empty texts are the end id alone; a null doc_id comes first; rows of one
    doc_id follow the order of their texts.  ``path`` defaults to a place in the shared folder.
    """
    vocabulary = vocabulary or vocabulary_path()
    kind = dict(docs.dtypes)["doc_id"]
    arrow_id = {"bigint": pa.int64(), "int": pa.int32(), "string": pa.string()}[kind]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = block_encoder(vocabulary)
        part_no, seq = TaskContext.get().partitionId(), 0
        names: list = []
        held: list[np.ndarray] = []
        counts: list[np.ndarray] = []
        size = 0

        def shard() -> pa.RecordBatch:
            nonlocal seq, names, held, counts, size
            n = np.concatenate(counts).astype(np.int32)
            cols = [pa.array([part_no], pa.int32()), pa.array([seq], pa.int32()), pa.array([size], pa.int64()), pa.array([names], pa.list_(arrow_id)), pa.array([n.tolist()], pa.list_(pa.int32())), pa.array([compress(np.concatenate(held), cfg)], pa.binary())]
            seq, names, held, counts, size = seq + 1, [], [], [], 0
            return pa.RecordBatch.from_arrays(cols, names=["part", "seq", "n_ids", "doc_ids", "counts", "payload"])

        for part in chunks(batches, "text"):
            ids, lens = enc.encode([x or "" for x in part.column(1).to_pylist()])
            ends = np.cumsum(lens)
            held.append(np.insert(ids, ends, cfg.end_id))
            counts.append(lens + 1)
            names += part.column(0).to_pylist()
            size += len(held[-1])
            if size >= cfg.shard_ids:
                yield shard()
        if names:
            yield shard()

    ordered = prune(docs, "doc_id", "text").repartitionByRange("doc_id").sortWithinPartitions("doc_id", "text")
    shards = ordered.mapInArrow(run, f"part int, seq int, n_ids bigint, doc_ids array<{kind}>, counts array<int>, payload binary")
    if path is None:
        return materialise(shards, "tokens")
    shards.write.parquet(path)
    return read_shards(docs.sparkSession, path)


def read_shards(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.parquet(path)


def read_documents(shards: DataFrame, with_ids: bool = True) -> DataFrame:
    """``(doc_id, start, n_tokens, ids_crc32[, ids])`` from shards; ``start`` counts all ids before, in shard order."""
    kind = dict(shards.dtypes)["doc_ids"].removeprefix("array<").removesuffix(">")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i in range(batch.num_rows):
                row = batch.slice(i, 1)
                counts = row.column(3).flatten().to_numpy().astype(np.int64)
                ids = Shard(row.column(4)[0].as_py()).decode().astype("<u4")
                raw = memoryview(ids.tobytes())
                edges = np.concatenate([[0], np.cumsum(counts)])
                spans = list(zip(edges[:-1].tolist(), edges[1:].tolist(), strict=True))
                n = len(spans)
                cols = [row.column(2).flatten(), pa.repeat(row.column(0)[0], n), pa.repeat(row.column(1)[0], n), pa.array(edges[:-1]), pa.array(counts), pa.array([zlib.crc32(raw[4 * a : 4 * b]) for a, b in spans], pa.int64())]
                names = ["doc_id", "part", "seq", "at", "n_tokens", "ids_crc32"]
                if with_ids:
                    cols.append(pa.ListArray.from_arrays(pa.array(edges.astype(np.int32)), pa.array(ids.astype(np.int64))))
                    names.append("ids")
                yield pa.RecordBatch.from_arrays(cols, names=names)

    more = ", ids array<bigint>" if with_ids else ""
    docs = shards.select("part", "seq", "doc_ids", "counts", "payload").mapInArrow(run, f"doc_id {kind}, part int, seq int, at bigint, n_tokens bigint, ids_crc32 bigint{more}")
    sizes = shards.select("part", "seq", "n_ids")
    parts = sizes.groupBy("part").agg(F.sum("n_ids").alias("n"))  # one row for each writing task
    before = F.coalesce(F.sum("n").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    inside = F.coalesce(F.sum("n_ids").over(Window.partitionBy("part").orderBy("seq").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    first = sizes.select("part", "seq", inside.alias("inside")).join(parts.select("part", before.alias("before")), "part")
    first = first.select("part", "seq", (F.col("before") + F.col("inside")).alias("base"))
    out = docs.join(first, ["part", "seq"])
    return out.select("doc_id", (F.col("base") + F.col("at")).alias("start"), "n_tokens", "ids_crc32", *(["ids"] if with_ids else []))
