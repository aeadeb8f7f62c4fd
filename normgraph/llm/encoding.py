"""Byte-pair encoding and decoding through a distinct-word table.

Words are split in Spark and counted; each distinct word is encoded once, and its ids are turned back into bytes by a
join with the id-to-piece table.  Documents then take ids and bytes from that table by position.  The commonest
words, up to ``HEAD_BYTES``, are broadcast; the rest come to the blocks of documents that need them through a
join on the word, so no task ever holds the whole table.  Bytes of a word that the join with the id-to-piece table
finds equal to the word itself, as it does for all but odd vocabularies, are not stored a second time: their
piece is null, and a document takes them from where the word stands.
"""

from __future__ import annotations

import hashlib
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import zstandard
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from normgraph.llm.bpe import joined, points_of, word_encoder, word_keys, word_starts
from normgraph.llm.common import Workspace, chunks, materialise, prune, ragged_take, runs_of, text_bytes

VOCABULARY = "byte_bpe_50k.json"
#: Bytes of the common words that each worker gets; words beyond are joined.
HEAD_BYTES = 48 << 20
_WORD = "word string, n bigint, ids array<int>, piece binary"


def vocabulary_path(name: str = VOCABULARY) -> str:
    """Where the installed vocabulary file is; executors have the package at the same place."""
    import public_tokenizers

    return public_tokenizers.path(name)


def _texts(part: pa.RecordBatch, column: int = 1) -> list[str]:
    return [x or "" for x in part.column(column).to_pylist()]


@dataclass
class Words:
    """The words of some texts, without the ends of texts: distinct ones, and where each stands."""

    keys: np.ndarray  # of the distinct words, ascending
    first: np.ndarray  # a place of each distinct word
    count: np.ndarray
    inverse: np.ndarray  # distinct word of each word
    text: np.ndarray  # text of each word
    lo: np.ndarray
    hi: np.ndarray
    whole: str

    def __getitem__(self, j: int) -> str:
        f = self.first[j]
        return self.whole[self.lo[f] : self.hi[f]]


def split_words(texts: list[str], names: list[str]) -> Words:
    """``names`` are the special tokens: workers that only split need no tokenizer, which takes much of their memory."""
    whole = joined(texts, names)
    points = points_of(whole)
    lo = word_starts(points)
    hi = np.append(lo[1:], len(points))
    ends = points[lo] == 0xD800
    text = (np.cumsum(ends) - ends)[~ends]
    lo, hi = lo[~ends], hi[~ends]
    keys, first, inverse, count = np.unique(word_keys(points, lo, hi), return_index=True, return_inverse=True, return_counts=True)
    return Words(keys, first, count, inverse.ravel(), text, lo, hi, whole)


def _shown(word: str, names: list[str]) -> str:
    """A special token's name in place of its stop point."""
    return names[ord(word[0]) - 0xD801] if 0xD801 <= ord(word[0]) < 0xDC00 else word


def distinct_words(docs: DataFrame, id_col: str, text_col: str, path: str) -> DataFrame:
    """``(word, n)``: every distinct word and how often it stands in all texts."""

    names = word_encoder(path).names

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in chunks(batches, text_col):
            words = split_words(_texts(part), names)
            yield pa.RecordBatch.from_arrays([pa.array([_shown(words[j], names) for j in range(len(words.keys))], pa.string()), pa.array(words.count.astype(np.int64))], names=["word", "n"])

    return prune(docs, id_col, text_col).mapInArrow(run, "word string, n bigint").groupBy("word").agg(F.sum("n").alias("n"))


def pieces(spark: SparkSession, path: str) -> DataFrame:
    """The id-to-piece table ``(id, piece)``, as large as the vocabulary."""
    rows = [(i, bytearray(p)) for i, p in enumerate(word_encoder(path).piece_list())]
    return spark.createDataFrame(rows, "id int, piece binary")


def word_table(words: DataFrame, path: str) -> DataFrame:
    """``(word, n, ids, piece)``: ids of each distinct word, and its bytes by a join of the ids with ``pieces``.

    ``piece`` is null where these bytes are those of the word.
    """

    def encode_each(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = word_encoder(path)
        stops = {name: chr(0xD801 + i) for i, name in enumerate(enc.names)}
        for batch in batches:
            if not batch.num_rows:
                continue
            ids = pa.array([enc.ids_of(stops.get(w, w)) for w in batch.column(0).to_pylist()], pa.list_(pa.int32()))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), ids], names=["word", "n", "ids"])

    names = word_encoder(path).special
    encoded = words.mapInArrow(encode_each, "word string, n bigint, ids array<int>")
    each = encoded.select("*", F.posexplode_outer("ids").alias("at", "id"))
    each = each.join(F.broadcast(pieces(words.sparkSession, path)), "id", "left").select("word", "n", "ids", "at", "piece")

    def put_together(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """The rows of a word follow each other in their order: the join is by broadcast, and nothing is exchanged."""
        head: list = []
        parts: list[bytes] = []
        for batch in batches:
            out: list[list] = []
            for word, n, ids, at, piece in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                if not at:
                    if head:
                        out.append(_whole(head, parts, names))
                    head, parts = [word, n, ids], []
                parts.append(piece or b"")
            if out:
                yield _rows(out)
        if head:
            yield _rows([_whole(head, parts, names)])

    return each.mapInArrow(put_together, _WORD)


def _whole(head: list, parts: list[bytes], special: dict[str, int]) -> list:
    """A row of the table; bytes that the ids give back unaltered are null, but for special tokens, which a block holds as stop points."""
    raw = b"".join(parts)
    return [*head, None if raw == head[0].encode() and head[0] not in special else raw]


def _rows(rows: list[list]) -> pa.RecordBatch:
    kinds = [pa.string(), pa.int64(), pa.list_(pa.int32()), pa.binary()]
    return pa.RecordBatch.from_arrays([pa.array(list(c), k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)], names=["word", "n", "ids", "piece"])


def _narrow(x: np.ndarray) -> np.ndarray:
    """Numbers from 0 in the narrowest type that holds them."""
    return x.astype(np.min_scalar_type(int(x.max()) if len(x) else 0))


class Lexicon:
    """Ids and bytes of some words by an ascending key, for many words at once; each worker holds one, so its numbers are narrow."""

    def __init__(self, key: np.ndarray, ids: pa.ListArray, piece: pa.BinaryArray):
        order = np.argsort(key, kind="stable")
        self.keys = key[order]
        ids, piece = ids.take(pa.array(order)), piece.take(pa.array(order))
        self.ids, self.id_offs = _narrow(ids.flatten().to_numpy(zero_copy_only=False)), _narrow(ids.offsets.to_numpy() - ids.offsets[0].as_py())
        self.same = piece.is_null().to_numpy(zero_copy_only=False)  # bytes are those of the word
        size = pc.fill_null(pc.binary_length(piece), 0).to_numpy(zero_copy_only=False).astype(np.int64)
        self.bytes = np.frombuffer(b"".join(x or b"" for x in piece.to_pylist()), dtype=np.uint8)
        self.byte_offs = _narrow(np.concatenate([[0], np.cumsum(size)]))

    def find(self, keys: np.ndarray) -> np.ndarray:
        """Row of each key, -1 for those that aren't here."""
        if not len(self.keys):
            return np.full(len(keys), -1, dtype=np.int64)
        at = np.minimum(np.searchsorted(self.keys, keys), len(self.keys) - 1)
        return np.where(self.keys[at] == keys, at, -1)

    @staticmethod
    def of(table: pa.Table, path: str) -> Lexicon:
        """From columns word, ids, piece; by the hashes of the words."""
        table = table.combine_chunks()
        one = lambda c, kind: table.column(c).chunk(0) if table.num_rows else pa.array([], kind)
        stops = {name: chr(0xD801 + i) for i, name in enumerate(word_encoder(path).names)}
        inner = [stops.get(w, w) for w in table.column("word").to_pylist()]
        end = np.cumsum(np.array([len(w) for w in inner], dtype=np.int64))
        lo = np.concatenate([[0], end])[:-1]
        return Lexicon(word_keys(points_of("".join(inner)), lo, end), one("ids", pa.list_(pa.int32())), one("piece", pa.binary()))


def common_words(table: DataFrame, path: str, max_bytes: int) -> tuple[Lexicon, DataFrame]:
    """The commonest words of ``word_table`` that fit ``max_bytes``, by classes of frequency, and the table of the others."""
    size = F.lit(24) + 4 * F.size("ids") + F.octet_length("word")
    cls = F.floor(F.log2("n") * 16).cast("int")
    classes = table.groupBy(cls.alias("c")).agg(F.sum(size).alias("bytes")).orderBy(F.desc("c")).collect()  # some thousand at most
    total, least = 0, None
    for r in classes:
        total += r["bytes"]
        if total > max_bytes:
            break
        least = r["c"]
    chosen = table.where(cls >= least) if least is not None else table.limit(0)
    return Lexicon.of(chosen.select("word", "ids", "piece").toArrow(), path), table if least is None else table.where(cls < least)


def _packed(part: pa.RecordBatch) -> tuple[int, bytes]:
    """An id that follows from the contents of a block of documents, and the block as bytes."""
    sink = pa.BufferOutputStream()
    with pa.ipc.new_stream(sink, part.schema) as writer:
        writer.write_batch(part)
    raw = sink.getvalue().to_pybytes()
    return int.from_bytes(hashlib.blake2b(raw, digest_size=8).digest(), "little", signed=True), raw


Emit = Callable[[pa.RecordBatch, np.ndarray, np.ndarray, np.ndarray, np.ndarray], pa.RecordBatch]


def _through_words(docs: DataFrame, id_col: str, text_col: str, path: str, emit: Emit, schema: str, head_bytes: int) -> DataFrame:
    """``emit(block, ids, ids of each text, bytes, bytes of each text)`` for every block of documents."""
    spark, docs, names = docs.sparkSession, prune(docs, id_col, text_col), word_encoder(path).names
    table = materialise(word_table(distinct_words(docs, id_col, text_col, path), path), "words")
    lexicon, others = common_words(table, path, head_bytes)
    shared = spark.sparkContext.broadcast(lexicon)

    def rare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        head = shared.value
        for part in chunks(batches, text_col):
            block, _ = _packed(part)
            words = split_words(_texts(part), names)
            some = np.flatnonzero(head.find(words.keys) < 0)
            if len(some):
                yield pa.RecordBatch.from_arrays([pa.array([block] * len(some), pa.int64()), pa.array(some.astype(np.int32)), pa.array([_shown(words[j], names) for j in some.tolist()], pa.string())], names=["block", "at", "word"])

    def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        squeeze = zstandard.ZstdCompressor(level=7)
        for part in chunks(batches, text_col):
            block, raw = _packed(part)
            yield pa.RecordBatch.from_arrays([pa.array([block], pa.int64()), pa.array([squeeze.compress(raw)], pa.binary())], names=["block", "raw"])

    needed = docs.mapInArrow(rare, "block bigint, at int, word string").join(others.select("word", "ids", "piece"), "word")
    needed = needed.groupBy("block").agg(F.collect_list(F.struct("at", "ids", "piece")).alias("found"))  # as many as one block has
    blocks = docs.mapInArrow(pack, "block bigint, raw binary").join(needed, "block", "left").select("raw", "found")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        head, unpack = shared.value, zstandard.ZstdDecompressor()
        for batch in batches:
            for row in range(batch.num_rows):
                found = batch.column(1).slice(row, 1).flatten()
                tail = Lexicon(found.field("at").to_numpy(), found.field("ids"), found.field("piece"))
                for part in pa.ipc.open_stream(unpack.decompress(batch.column(0)[row].as_py())):
                    yield emit(part, *_assemble(split_words(_texts(part), names), part.num_rows, head, tail, path))

    return blocks.mapInArrow(run, schema)


def _assemble(words: Words, n_texts: int, head: Lexicon, tail: Lexicon, path: str) -> tuple[np.ndarray, ...]:
    """Ids and bytes of all words in order, by position, and how many each text has; ``tail`` goes by place among the distinct words."""
    n = len(words.keys)
    points = points_of(words.whole)
    width = np.ones(len(points), dtype=np.uint8)
    for least in (0x80, 0x800, 0x10000):
        width += points >= least
    place = np.concatenate([[0], np.cumsum(width, dtype=np.int64)])
    begin, size = place[words.lo[words.first]], (place[words.hi] - place[words.lo])[words.first]  # of the words' own bytes
    raws, base = [np.frombuffer(words.whole.encode("utf-8", "surrogatepass"), dtype=np.uint8)], int(place[-1])
    slot, used, ids, id_sizes = np.full(n, -1, dtype=np.int64), 0, [], []
    for lexicon, at in ((head, head.find(words.keys)), (tail, tail.find(np.arange(n)))):
        new = np.flatnonzero((slot < 0) & (at >= 0))
        at = at[new]
        slot[new] = used + np.arange(len(new))
        used += len(new)
        found, lens = ragged_take(lexicon.ids, lexicon.id_offs, at)
        ids.append(found.astype(np.uint32))
        id_sizes.append(lens)
        stored = ~lexicon.same[at]
        begin[new[stored]], end = (base + lexicon.byte_offs[at[stored] + i].astype(np.int64) for i in (0, 1))
        size[new[stored]] = end - begin[new[stored]]
        raws.append(lexicon.bytes)
        base += len(lexicon.bytes)
    for j in np.flatnonzero(slot < 0).tolist():  # only if a recomputed task cut its blocks in another way
        enc = word_encoder(path)
        found, raw = np.array(enc.ids_of(words[j]), dtype=np.uint32), np.frombuffer(_shown(words[j], enc.names).encode(), dtype=np.uint8)
        slot[j], begin[j], size[j], used, base = used, base, len(raw), used + 1, base + len(raw)
        for out, x in zip((ids, id_sizes, raws), (found, [len(found)], raw), strict=True):
            out.append(x)
    where = slot[words.inverse]
    offs = np.concatenate([[0], np.cumsum(np.concatenate(id_sizes))]).astype(np.int64)
    values, counts = ragged_take(np.concatenate(ids), offs, where)
    lens = size[words.inverse]
    narrow = np.int32 if base + lens.sum() < 1 << 31 else np.int64
    index = np.repeat((begin[words.inverse] - (np.cumsum(lens) - lens)).astype(narrow), lens)
    index += np.arange(len(index), dtype=narrow)
    per_text = (np.bincount(words.text, weights=x, minlength=n_texts).astype(np.int64) for x in (counts, lens))
    return values, next(per_text), np.concatenate(raws)[index], next(per_text)


def encode(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", path: str | None = None, head_bytes: int = HEAD_BYTES) -> DataFrame:
    """``(id, ids array<int>)`` of every whole text, as the tokenizers library encodes it.

    One row for each input row.  Null and empty texts have an empty array.  Extra columns are dropped.  The word
    table stays in the shared folder until the session ends.
    """
    kind = dict(docs.dtypes)[id_col]

    def emit(part: pa.RecordBatch, ids: np.ndarray, counts: np.ndarray, *_: np.ndarray) -> pa.RecordBatch:
        offs = np.concatenate([[0], np.cumsum(counts)]).astype(np.int32)
        return pa.RecordBatch.from_arrays([part.column(0), pa.ListArray.from_arrays(pa.array(offs), pa.array(ids.astype(np.int32)))], names=[id_col, "ids"])

    return _through_words(docs, id_col, text_col, path or vocabulary_path(), emit, f"`{id_col}` {kind}, ids array<int>", head_bytes)


def decode(encoded: DataFrame, id_col: str = "doc_id", ids_col: str = "ids", path: str | None = None) -> DataFrame:
    """``(id, text)`` from arrays of ids by a join of the ids with the id-to-piece table.

    A null array gives an empty text; ids outside the vocabulary and null ids add nothing; broken UTF-8 becomes
    U+FFFD, as in the library's decode with ``skip_special_tokens=False``.  One row for each input row.
    """
    path = path or vocabulary_path()
    kind = dict(encoded.dtypes)[id_col]
    named = prune(encoded, id_col, ids_col).toDF("own", "ids").withColumn("row", F.monotonically_increasing_id())
    each = named.select("own", "row", F.posexplode_outer("ids").alias("at", "id"))
    each = each.join(F.broadcast(pieces(encoded.sparkSession, path)), "id", "left").select("own", "row", "piece")  # rows keep their order

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rows in runs_of(batches, ("row",)):
            raw = b"".join(x or b"" for x in rows.column("piece").to_pylist())
            yield pa.RecordBatch.from_arrays([rows.column("own").slice(0, 1).combine_chunks(), pa.array([raw.decode("utf-8", "replace")], pa.string())], names=[id_col, "text"])

    return each.mapInArrow(run, f"`{id_col}` {kind}, text string")


def round_trip(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", path: str | None = None, head_bytes: int = HEAD_BYTES) -> DataFrame:
    """``(id, n_tokens, ids_sha256, decoded_sha256)``: ids by the word table, text from the pieces of these ids.

    Hashes are lower-case hex: of the ids as little-endian unsigned 32-bit integers, and of the decoded text
    in UTF-8.  Null and empty texts have no ids and the hash of nothing.  One row for each input row.
    """
    kind = dict(docs.dtypes)[id_col]

    def emit(part: pa.RecordBatch, ids: np.ndarray, counts: np.ndarray, raw: np.ndarray, sizes: np.ndarray) -> pa.RecordBatch:
        digests = []
        for data, ends in ((ids.astype("<u4").tobytes(), 4 * np.cumsum(counts)), (raw.tobytes(), np.cumsum(sizes))):
            digests.append([data[a:b] for a, b in zip([0, *ends[:-1].tolist()], ends.tolist(), strict=True)])
        tokens = [hashlib.sha256(x).hexdigest() for x in digests[0]]
        decoded = [hashlib.sha256(x.decode("utf-8", "replace").encode()).hexdigest() for x in digests[1]]
        return pa.RecordBatch.from_arrays([part.column(0), pa.array(counts, pa.int64()), pa.array(tokens, pa.string()), pa.array(decoded, pa.string())], names=[id_col, "n_tokens", "ids_sha256", "decoded_sha256"])

    schema = f"`{id_col}` {kind}, n_tokens bigint, ids_sha256 string, decoded_sha256 string"
    with Workspace() as space:
        return space.result(_through_words(docs, id_col, text_col, path or vocabulary_path(), emit, schema, head_bytes), "round-trip")


__all__ = ["VOCABULARY", "common_words", "decode", "distinct_words", "encode", "pieces", "round_trip", "text_bytes", "vocabulary_path", "word_table"]
