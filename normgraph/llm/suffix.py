"""Repeated passages by a sparse suffix array over words.

Suffixes are kept at content-selected positions only: the minimiser of every window of ``window`` k-word hashes,
so that two copies of a passage of ``words`` words keep at least one common suffix.  A suffix is a string of word
symbols (four bits of each word's hash); the suffixes are sorted over range partitions and compared with their
neighbours, which gives how far each can be extended to the right, and, sorted again within equal beginnings by what
stands before them, to the left.  Where only passages of several documents count, the neighbours are the nearest
suffixes of other documents.  Only windows of ``words`` words that these bounds admit are taken from the texts, and
compared by a 96-bit hash of their words; a document sends each of its distinct windows once, with all its places.
Overlapping repeated windows merge into spans.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from normgraph.llm.common import Workspace, chunks, materialise, prune, text_bytes
from normgraph.llm.wordhash import as_long, grams, hash_words, mix, range_hash


@dataclass(frozen=True)
class RepeatConfig:
    """A passage of ``words`` words or more is a repeat; ``key_words`` words make the sort key."""

    words: int = 50
    key_words: int = 20
    across: bool = True  # only passages that stand in more than one document

    @property
    def window(self) -> int:
        return self.words - self.key_words + 1


def minimisers(g: np.ndarray, window: int) -> np.ndarray:
    """Positions of the least value of each window (the leftmost of equals)."""
    n = len(g) - window + 1
    if n <= 0:
        return np.zeros(0, dtype=np.int64)
    best, span = g.copy(), 1
    at = np.arange(len(g))
    while span * 2 <= window:  # doubling: least of spans of 1, 2, 4, .. values
        a, b = best[:-span], best[span:]
        right = b < a
        at = np.where(right, at[span:], at[:-span])
        best = np.where(right, b, a)
        span *= 2
    rest = window - span
    a, b = best[:n], best[rest : rest + n]
    return np.unique(np.where(b < a, at[rest : rest + n], at[:n]))


def symbols(h: np.ndarray, at: np.ndarray, n: int, step: int) -> np.ndarray:
    """Packed symbols of ``n`` words from each place on, to the right (``step`` 1) or to the left (-1); none beyond the text."""
    own = (h & np.uint64(15)).astype(np.uint8)
    where = at[:, None] + step * np.arange(n + n % 2)[None, :]
    inside = (where >= 0) & (where < len(h))
    found = np.where(inside, own[np.clip(where, 0, max(0, len(h) - 1))], 0)
    return found[:, 0::2] << 4 | found[:, 1::2]


def _binary(rows: np.ndarray) -> pa.Array:
    n, width = rows.shape
    offs = pa.py_buffer((np.arange(n + 1, dtype=np.int32) * width).tobytes())
    return pa.BinaryArray.from_buffers(pa.binary(), n, [None, offs, pa.py_buffer(np.ascontiguousarray(rows).tobytes())])


def _matrix(col: pa.Array) -> np.ndarray:
    """Symbols of a column of packed symbols of one length, one row each."""
    rows = np.frombuffer(b"".join(col.to_pylist()), dtype=np.uint8).reshape(len(col), -1)
    return np.stack([rows >> 4, rows & 15], axis=2).reshape(len(rows), -1)


def anchors(docs: DataFrame, cfg: RepeatConfig) -> DataFrame:
    """``(suffix, before, doc_id, pos)``: the retained suffixes of every document, and what stands before them."""
    kind = dict(docs.dtypes)["doc_id"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in chunks(batches, "text"):
            words = hash_words(text_bytes(part.column(1)))
            g = grams(words.h, cfg.key_words)
            rows, right, left, places = [], [], [], []
            for r, (a, b) in enumerate(zip(words.first[:-1].tolist(), words.first[1:].tolist(), strict=True)):
                if b - a < cfg.words:
                    continue
                at = minimisers(g[a : b - cfg.key_words + 1], cfg.window)
                rows.append(np.full(len(at), r))
                right.append(symbols(words.h[a:b], at, cfg.words, 1))
                left.append(symbols(words.h[a:b], at - 1, cfg.words - cfg.key_words, -1))
                places.append(at)
            if rows:
                cols = [_binary(np.concatenate(right)), _binary(np.concatenate(left)), part.column(0).take(pa.array(np.concatenate(rows))), pa.array(np.concatenate(places).astype(np.int32))]
                yield pa.RecordBatch.from_arrays(cols, names=["suffix", "before", "doc_id", "pos"])

    return prune(docs, "doc_id", "text").where("doc_id is not null").mapInArrow(run, f"suffix binary, before binary, doc_id {kind}, pos int")


def _with_neighbours(ordered: DataFrame, column: str, within: int, schema: str, names: list[str], reach: str, least: int, across: bool) -> DataFrame:
    """Rows of a sorted frame with ``reach``: the symbols of ``column`` that a row shares with one of its neighbours.

    ``within`` first bytes of ``suffix`` must be equal.  Rows that share less than ``least`` go.  The first and the
    last row of a partition may have their neighbour in another one; they count as sharing everything.  With ``across``,
    a neighbour is the nearest row of another document; behind the last run of a batch it counts as sharing
    as much as that run's rows share with its end, so that no run is held.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: pa.RecordBatch | None = None  # the last row, until its right neighbour is known
        held_reach = 0

        def put(batch: pa.RecordBatch, found: np.ndarray) -> Iterator[pa.RecordBatch]:
            keep = pa.array(found >= least)
            out = pa.RecordBatch.from_arrays([*(batch.column(batch.schema.get_field_index(c)) for c in names), pa.array(found.astype(np.int32))], names=[*names, reach]).filter(keep)
            if out.num_rows:
                yield out

        for batch in batches:
            if not batch.num_rows:
                continue
            both = batch if held is None else pa.Table.from_batches([held, batch]).combine_chunks().to_batches()[0]
            own = _matrix(both.column(both.schema.get_field_index(column)))
            same = np.cumprod(own[1:] == own[:-1], axis=1, dtype=np.int64).sum(1)
            if within:
                key = _matrix(both.column(both.schema.get_field_index("suffix")))[:, : 2 * within]
                same = np.where((key[1:] == key[:-1]).all(1), same, 0)
            first = own.shape[1] if held is None else held_reach
            left = np.concatenate([[first], same])
            right = np.concatenate([same, [own.shape[1]]])
            if across:
                ids = both.column(both.schema.get_field_index("doc_id"))
                other = pc.not_equal(ids.slice(0, len(ids) - 1), ids.slice(1)).to_numpy(zero_copy_only=False)
                fall = np.concatenate([[0], np.cumsum(other)]) << 20  # beyond every reach, so that the running minimum starts anew in each run
                left = np.minimum.accumulate(left - fall) + fall
                right = (np.minimum.accumulate((right + fall)[::-1])[::-1]) - fall
            found = np.maximum(left, right)
            yield from put(both.slice(0, both.num_rows - 1), found[:-1])
            held, held_reach = both.slice(both.num_rows - 1, 1), int(left[-1])
        if held is not None:
            width = 2 * len(held.column(held.schema.get_field_index(column))[0].as_py())
            yield from put(held, np.array([width]))

    return ordered.mapInArrow(run, schema)


def extensible(docs: DataFrame, cfg: RepeatConfig) -> DataFrame:
    """``(doc_id, pos, reach_right, reach_left)``: suffixes that agree with a neighbour in the key, and their extension.

    In suffix order the longest beginning that a suffix shares with any other is shared with a neighbour; the same
    holds for what stands before it, in the order of that, and for the nearest suffixes of other documents.  Range partitions split even one very frequent suffix.
    """
    kind = dict(docs.dtypes)["doc_id"]
    order = ["suffix", "before", "doc_id", "pos"]
    ordered = anchors(docs, cfg).repartitionByRange(*order).sortWithinPartitions(*order)
    right = _with_neighbours(ordered, "suffix", 0, f"suffix binary, before binary, doc_id {kind}, pos int, reach_right int", order, "reach_right", cfg.key_words, cfg.across)
    right = materialise(right, "suffixes")
    key = F.substring("suffix", 1, cfg.key_words // 2)
    order = [key, F.col("before"), F.col("doc_id"), F.col("pos")]
    ordered = right.repartitionByRange(*order).sortWithinPartitions(*order)
    names = ["doc_id", "pos", "reach_right"]
    return _with_neighbours(ordered, "before", cfg.key_words // 2, f"doc_id {kind}, pos int, reach_right int, reach_left int", names, "reach_left", 0, cfg.across)


def windows(docs: DataFrame, places: DataFrame, cfg: RepeatConfig) -> DataFrame:
    """``(h, h2, doc_id, start, more)``: hashes of the windows of ``words`` words around suffixes that reach far enough.

    One row for each distinct window of a document, with its first place and the later ones, null where there is none.
    """
    kind = dict(docs.dtypes)["doc_id"]
    lo = F.col("pos") - F.least("reach_left", F.lit(cfg.words - cfg.key_words))
    hi = F.col("pos") - F.greatest(F.lit(0), cfg.words - F.col("reach_right"))
    ranges = places.select("doc_id", F.struct(lo.alias("lo"), (hi + 1).alias("hi")).alias("x")).where("x.lo < x.hi")
    lists = ranges.groupBy("doc_id").agg(F.collect_set("x").alias("ranges"))  # as many as one document has suffixes
    some = docs.join(lists, "doc_id").select("doc_id", "text", "ranges")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in chunks(batches, "text"):
            words = hash_words(text_bytes(part.column(1)))
            again = mix(words.h ^ np.uint64(0x5851F42D4C957F2D))
            hashes, rows, starts = [], [], []
            spans = part.column(2)
            for r in range(part.num_rows):
                h = words.h[words.first[r] : words.first[r + 1]]
                n = len(h) - cfg.words + 1
                if n <= 0:
                    continue
                own = spans[r].values
                edge = np.zeros(n + 1, dtype=np.int32)
                np.add.at(edge, np.clip(own.field("lo").to_numpy(), 0, n), 1)
                np.add.at(edge, np.clip(own.field("hi").to_numpy(), 0, n), -1)
                start = np.flatnonzero(np.cumsum(edge[:-1]) > 0)
                second = again[words.first[r] : words.first[r + 1]]
                hashes.append(np.stack([range_hash(h, start, start + cfg.words), range_hash(second, start, start + cfg.words)]))
                starts.append(start)
                rows.append(np.full(len(start), r))
            if rows:
                yield _distinct(part.column(0), np.concatenate(rows), *np.concatenate(hashes, axis=1), np.concatenate(starts))

    return some.mapInArrow(run, f"h bigint, h2 int, doc_id {kind}, start int, more array<int>")


def _distinct(ids: pa.Array, row: np.ndarray, one: np.ndarray, two: np.ndarray, start: np.ndarray) -> pa.RecordBatch:
    """The distinct windows of each row; ``start`` ascends within a row."""
    two = two >> np.uint64(32)
    order = np.lexsort((two, one, row))
    row, one, two, start = row[order], one[order], two[order], start[order].astype(np.int32)
    new = np.ones(len(row), dtype=bool)
    new[1:] = (row[1:] != row[:-1]) | (one[1:] != one[:-1]) | (two[1:] != two[:-1])
    first = np.flatnonzero(new)
    later = np.diff(first, append=len(row)) - 1
    offs = pa.array(np.concatenate([[0], np.cumsum(later)]).astype(np.int32), mask=np.append(later == 0, False))
    more = pa.ListArray.from_arrays(offs, pa.array(start[~new]))
    cols = [pa.array(as_long(one[first])), pa.array(two[first].astype(np.uint32).view(np.int32)), ids.take(pa.array(row[first])), pa.array(start[first]), more]
    return pa.RecordBatch.from_arrays(cols, names=["h", "h2", "doc_id", "start", "more"])


HEAVY = 2000  # a window with more than one row in so many of all is broadcast; there are at most as many


def repeated_windows(docs: DataFrame, cfg: RepeatConfig) -> DataFrame:
    """``(doc_id, start, more, first_doc, first_start)`` of every repeated window; the first is the least place.

    ``more`` has the later places of the same window in the document, or is null.
    """
    with Workspace() as space:  # the suffixes go before the windows are grouped
        found = space.result(windows(docs, extensible(docs, cfg), cfg), "windows")
    first = F.min(F.struct("doc_id", "start"))
    last = F.max("doc_id").alias("last_doc") if cfg.across else F.max(F.struct("doc_id", F.coalesce(F.element_at("more", -1), "start").alias("start"))).alias("last")
    groups = found.groupBy("h", "h2").agg(first.alias("first"), last, F.count(F.lit(1)).alias("n"))
    groups = groups.where("first.doc_id <> last_doc" if cfg.across else "first <> last")
    groups = materialise(groups.select("h", "h2", "n", F.col("first.doc_id").alias("first_doc"), F.col("first.start").alias("first_start")), "groups")
    heavy = F.broadcast(groups.where(F.col("n") * HEAVY > found.count()).drop("n"))
    rest = found.join(heavy.select("h", "h2"), ["h", "h2"], "left_anti").join(groups.drop("n"), ["h", "h2"])
    return found.join(heavy, ["h", "h2"]).unionByName(rest).select("doc_id", "start", "more", "first_doc", "first_start")


def _every_place(hits: DataFrame, entry: Callable[[Column, Column], Column], *cols: str) -> DataFrame:
    """``(doc_id, hits)``: the sorted entries of all places of each document; ``entry`` makes one from a window and a place.

    Places are written out behind the exchange, which moves each distinct window of a document once.
    """
    by_doc = hits.groupBy("doc_id").agg(F.collect_list(F.struct("start", "more", *cols)).alias("hits"))
    places = lambda x: F.concat(F.array(x["start"]), F.coalesce(x["more"], F.array().cast("array<int>")))
    return by_doc.select("doc_id", F.sort_array(F.flatten(F.transform("hits", lambda x: F.transform(places(x), lambda p: entry(x, p))))).alias("hits"))


def _flat(lists: pa.ListArray) -> tuple[np.ndarray, pa.StructArray]:
    """The entries of lists without nulls, and the row of each."""
    return np.repeat(np.arange(len(lists)), np.diff(lists.offsets.to_numpy())), lists.flatten()


def repeated_spans(docs: DataFrame, cfg: RepeatConfig = RepeatConfig()) -> DataFrame:
    """``(doc_id, first_word, end_word, n_words, first_doc, is_first)``: maximal repeated spans of each document.

    A span joins overlapping or adjoining repeated windows that are all first occurrences, or all later ones
    (``is_first`` tells); ``first_doc`` is the least document that holds the span's first window.  Words
    are parted by white space and compared by their bytes.  Texts that are null, empty or shorter than
    ``words`` words, and rows with a null doc_id, hold no span.  Rows that repeat a doc_id are read as one
    document.  Extra columns are dropped.  Without ``across``, passages that repeat inside one document only count too.
    """
    with Workspace() as space:
        return space.result(_spans(prune(docs, "doc_id", "text"), cfg), "spans")


def _spans(docs: DataFrame, cfg: RepeatConfig) -> DataFrame:
    hits = repeated_windows(docs, cfg)
    own = lambda x, p: (x["first_doc"] == F.col("doc_id")) & (x["first_start"] == p)
    by_doc = _every_place(hits, lambda x, p: F.struct(p.alias("start"), own(x, p).alias("own"), x["first_doc"].alias("first_doc")), "first_doc", "first_start")
    kind = dict(docs.dtypes)["doc_id"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if not batch.num_rows:
                continue
            row, hit = _flat(batch.column(1))
            start, mine = (hit.field(c).to_numpy(zero_copy_only=False) for c in ("start", "own"))
            start = start.astype(np.int64)
            new = np.append(True, (row[1:] != row[:-1]) | (mine[1:] != mine[:-1]) | (start[1:] > start[:-1] + cfg.words))
            begin = np.flatnonzero(new)
            end = start[np.append(begin[1:], len(start)) - 1] + cfg.words
            cols = [batch.column(0).take(pa.array(row[begin])), pa.array(start[begin]), pa.array(end), pa.array(end - start[begin])]
            yield pa.RecordBatch.from_arrays([*cols, hit.field("first_doc").take(pa.array(begin)), pa.array(mine[begin])], names=["doc_id", "first_word", "end_word", "n_words", "first_doc", "is_first"])

    return by_doc.mapInArrow(run, f"doc_id {kind}, first_word bigint, end_word bigint, n_words bigint, first_doc {kind}, is_first boolean")


CUT = "ranges_cut_4d1f"  # no column of a caller


def _cuts(docs: DataFrame, cfg: RepeatConfig) -> DataFrame:
    """``(doc_id, CUT)``: the word ranges to cut from each document.

    Every later window loses its words, except that one overlapping its own first copy (a text of a short
    period) loses only those behind that copy: the copy stays whole, and the window is no longer there.
    """
    later = repeated_windows(docs, cfg).where("first_doc <> doc_id or first_start <> start or more is not null")
    own = F.when(F.col("first_doc") == F.col("doc_id"), F.col("first_start"))  # of a window with its first copy in the document
    by_doc = _every_place(later.withColumn("own", own), lambda x, p: F.struct(F.greatest(p, x["own"] + cfg.words).alias("a"), (p + cfg.words).alias("b")), "own")
    by_doc = by_doc.withColumn("hits", F.filter("hits", lambda x: x["a"] < x["b"]))  # a first copy loses nothing
    kind = dict(docs.dtypes)["doc_id"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if not batch.num_rows:
                continue
            row, found = _flat(batch.column(1))
            a, b = (found.field(c).to_numpy(zero_copy_only=False).astype(np.int64) for c in ("a", "b"))
            apart = row << 40  # beyond every word position, so that the running end starts anew in each document
            end = np.maximum.accumulate(b + apart)
            begin = np.flatnonzero(np.append(True, (a + apart)[1:] > end[:-1]))
            last = np.append(begin[1:], len(row)) - 1
            cut = pa.StructArray.from_arrays([pa.array(a[begin]), pa.array(end[last] - apart[last])], names=["first_word", "end_word"])
            offs = np.searchsorted(row[begin], np.arange(batch.num_rows + 1)).astype(np.int32)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.ListArray.from_arrays(pa.array(offs), cut)], names=["doc_id", CUT])

    return by_doc.mapInArrow(run, f"doc_id {kind}, {CUT} array<struct<first_word:bigint,end_word:bigint>>")


def remove_repeats(docs: DataFrame, cfg: RepeatConfig = RepeatConfig()) -> DataFrame:
    """``docs`` without later occurrences of repeated passages; the first occurrence of each stays.

    Words of a later occurrence go, with the white space after them; a document of which nothing is left
    goes.  All columns stay; ``n_chars``, where there is one, follows the text.  Untouched rows are not altered.
    A passage that overlaps its own first copy loses only the words behind that copy.
    """
    with Workspace() as space:
        cut = space.result(_cuts(prune(docs, "doc_id", "text"), cfg), "cuts")
    joined = docs.join(cut, "doc_id", "left").select(*[F.col(f"`{c}`") for c in docs.columns], CUT)

    @F.pandas_udf("string")
    def without(text, places):
        import pandas as pd

        out = []
        for t, spans_ in zip(text, places, strict=True):
            raw = (t or "").encode()
            words = hash_words([raw])
            parts, at = [], 0
            for s in spans_:
                a, b = s["first_word"], s["end_word"]
                parts.append(raw[at : words.start[a]])
                at = int(words.start[b]) if b < len(words.start) else len(raw)
            parts.append(raw[at:])
            out.append(b"".join(parts).decode())
        return pd.Series(out)

    touched = joined.where(F.col(CUT).isNotNull()).withColumn("text", without("text", CUT)).where(F.regexp_like("text", F.lit(r"[^\x20\x09-\x0D]")))
    plain = joined.where(F.col(CUT).isNull())
    if "n_chars" in docs.columns:
        touched = touched.withColumn("n_chars", F.length("text").cast(dict(docs.dtypes)["n_chars"]))
    return plain.unionByName(touched).drop(CUT)
