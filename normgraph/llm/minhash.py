"""Near-duplicate classes by fast similarity sketching, banding and exact verification.

A sketch has ``bins`` coordinates.  In round i < bins every shingle is placed in a hashed bin; in the later
rounds all shingles go to the one bin whose turn it is.  A coordinate keeps the smallest value of the first
round that reached it, so all coordinates fill after at most twice ``bins`` rounds.  Bands of coordinates
propose pairs.  Equal sets are one class from the start; inside a bucket, members are first compared with single
centres (rounds with different centres); members of different components that are left are compared block by
block inside tasks behind exact bounds.  Every link is confirmed on the full sets.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from normgraph.llm.common import CHUNK_BYTES, Workspace, chunks, materialise, prune, runs_of, text_bytes
from normgraph.llm.wordhash import as_long, grams, hash_words, mix

ODD_BITS = 1024
BLOCK = 512  # rows of one prefix shingle that a task compares with as many others


@dataclass(frozen=True)
class NearDupConfig:
    """32 bands of 4 coordinates miss a pair of similarity 0.8 with probability 5e-8."""

    words: int = 2
    percent: int = 80
    bins: int = 128
    rows: int = 4
    seed: int = 42
    centres: tuple[int, ...] = (4,)  # centres a bucket in each later round


def shingle_sets(texts: list[bytes], k: int) -> list[np.ndarray]:
    """Sorted distinct shingle hashes of each text; fewer than k words are one shingle, none is empty."""
    words = hash_words(texts, lower=True)
    g = grams(words.h, k)
    out = []
    for a, b in zip(words.first[:-1].tolist(), words.first[1:].tolist(), strict=True):
        if b - a >= k:
            out.append(np.unique(g[a : b - k + 1]))
        elif b > a:
            out.append(grams(words.h[a:b], b - a))
        else:
            out.append(np.zeros(0, dtype=np.uint64))
    return out


def sketches(sets: list[np.ndarray], bins: int, seed: int) -> np.ndarray:
    """Sketch matrix of all sets, one row each; rows of empty sets stay at the largest value."""
    empty = np.uint64(0xFFFFFFFFFFFFFFFF)
    out = np.full((len(sets), bins), empty, dtype=np.uint64)
    sizes = np.array([len(s) for s in sets], dtype=np.int64)
    row = np.repeat(np.arange(len(sets)), sizes)
    values = np.concatenate(sets) if len(sets) else np.zeros(0, dtype=np.uint64)
    low, shift = np.uint64(0xFFFFFFFF), np.uint64(32)
    with np.errstate(over="ignore"):
        for i in range(2 * bins):
            if not len(values):
                break
            h = mix(values + np.uint64((seed * 0x9E3779B97F4A7C15 + (i + 1) * 0xC2B2AE3D27D4EB4F) & 0xFFFFFFFFFFFFFFFF))
            val = (np.uint64(i) << shift) | (h & low)
            cell = row * bins + ((h >> shift) * np.uint64(bins) >> shift).astype(np.int64) if i < bins else row * bins + (i - bins)
            flat = out.reshape(-1)
            vacant = flat[cell] > (np.uint64(i) << shift)  # empty, or reached in this very round
            if vacant.any():
                np.minimum.at(flat, cell[vacant], val[vacant])
            if i < 8 or i % 8 == 7:
                open_rows = (out == empty).any(axis=1)
                if not open_rows.any():
                    break
                stay = open_rows[row]
                if not stay.all():
                    row, values = row[stay], values[stay]
    return out


def band_keys(sketch: np.ndarray, rows: int) -> np.ndarray:
    n, bins = sketch.shape
    bands = bins // rows
    out = np.zeros((n, bands), dtype=np.uint64)
    with np.errstate(over="ignore"):
        for r in range(rows):
            out = out * np.uint64(0xD6E8FEB86659FD93) + mix(sketch[:, r::rows][:, :bands])
        return mix(out + np.arange(bands, dtype=np.uint64)[None, :] * np.uint64(0x9E3779B97F4A7C15))


def sketch_table(docs: DataFrame, cfg: NearDupConfig) -> DataFrame:
    """``(doc_id, n_shingles, set_hash, bands)`` of every document; one pass over the texts."""
    kind = dict(docs.dtypes)["doc_id"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in chunks(batches, "text", CHUNK_BYTES):
            sets = shingle_sets(text_bytes(part.column(1)), cfg.words)
            sketch = sketches(sets, cfg.bins, cfg.seed)
            bands = band_keys(sketch, cfg.rows)
            n = len(sets)
            flat = pa.array(as_long(bands.ravel()))
            yield pa.RecordBatch.from_arrays(
                [
                    part.column(0),
                    pa.array([len(s) for s in sets], pa.int64()),
                    pa.array([hashlib.blake2b(s.tobytes(), digest_size=16).digest() for s in sets], pa.binary()),
                    pa.ListArray.from_arrays(pa.array(np.arange(n + 1, dtype=np.int32) * bands.shape[1]), flat),
                ],
                names=["doc_id", "n_shingles", "set_hash", "bands"],
            )

    return prune(docs, "doc_id", "text").mapInArrow(run, f"doc_id {kind}, n_shingles bigint, set_hash binary, bands array<bigint>")


def verify(pairs: DataFrame, texts: DataFrame, cfg: NearDupConfig) -> DataFrame:
    """Those of the pairs ``(a, b)`` whose full shingle sets reach the similarity."""
    left = texts.select(F.col("rep").alias("a"), F.col("text").alias("text_a"))
    right = texts.select(F.col("rep").alias("b"), F.col("text").alias("text_b"))
    both = pairs.select("a", "b").join(left, "a").join(right, "b").select("a", "b", "text_a", "text_b")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        last: dict[bytes, np.ndarray] = {}
        for part in chunks(batches, "text_a"):
            raws_a, raws_b = text_bytes(part.column(2)), text_bytes(part.column(3))
            sets_a = shingle_sets(raws_a, cfg.words)
            need = [i for i, r in enumerate(dict.fromkeys(raws_b)) if r not in last]
            fresh = [r for r in dict.fromkeys(raws_b) if r not in last]
            if len(last) + len(need) > 512:
                last.clear()
                fresh = list(dict.fromkeys(raws_b))
            for at in range(0, len(fresh), 64):
                last.update(zip(fresh[at : at + 64], shingle_sets(fresh[at : at + 64], cfg.words), strict=True))
            good = []
            for x, raw in zip(sets_a, raws_b, strict=True):
                y = last[raw]
                least, most = min(len(x), len(y)), max(len(x), len(y))
                if 100 * least < cfg.percent * most:
                    good.append(False)
                    continue
                both = len(np.intersect1d(x, y, assume_unique=True))
                good.append(100 * both >= cfg.percent * (len(x) + len(y) - both))
            yield pa.RecordBatch.from_arrays([part.column(0), part.column(1)], names=["a", "b"]).filter(pa.array(good))

    kind = dict(pairs.dtypes)["a"]
    return both.mapInArrow(run, f"a {kind}, b {kind}")


def connect(labels: DataFrame, edges: DataFrame) -> DataFrame:
    """Smallest label reachable: ``labels (rep, label)`` joined by ``edges (a, b)``, over all labels.

    Edges are lifted to labels, whose components come from minimum propagation with pointer jumping; each
    step is written to the shared folder, and the driver only learns how many labels changed.
    """
    la = labels.select(F.col("rep").alias("a"), F.col("label").alias("la"))
    lb = labels.select(F.col("rep").alias("b"), F.col("label").alias("lb"))
    lifted = edges.join(la, "a").join(lb, "b").where("la <> lb")
    arcs = materialise(lifted.select(F.explode(F.array(F.struct(F.col("la").alias("u"), F.col("lb").alias("v")), F.struct(F.col("lb").alias("u"), F.col("la").alias("v")))).alias("e")).select("e.u", "e.v").distinct(), "arcs")
    state = arcs.groupBy("u").agg(F.least(F.col("u"), F.min("v")).alias("c"))
    state = materialise(state, "component")
    while True:
        near = arcs.join(state.select(F.col("u").alias("v"), F.col("c").alias("cv")), "v").groupBy("u").agg(F.min("cv").alias("cn"))
        step = state.join(near, "u", "left").select("u", "c", F.least("c", F.coalesce("cn", "c")).alias("n"))
        jump = state.select(F.col("u").alias("n"), F.col("c").alias("cj"))
        step = step.join(jump, "n", "left").select("u", F.least("n", F.coalesce("cj", "n")).alias("n"), "c")
        step = materialise(step, "component")
        moved = step.where("n <> c").limit(1).count()
        state = step.select("u", F.col("n").alias("c"))
        if not moved:
            break
    found = state.select(F.col("u").alias("label"), F.col("c").alias("to"))
    return labels.join(found, "label", "left").select("rep", F.coalesce("to", "label").alias("label"))


def near_duplicates(docs: DataFrame, cfg: NearDupConfig = NearDupConfig()) -> DataFrame:
    """``(doc_id, n_shingles, component_id, kept)`` for every document.

    ``component_id`` is the smallest doc_id reachable over links of at least ``percent`` similarity, ``kept``
    tells the smallest itself.  Texts without words have no shingles and are linked with nothing.  Repeated rows
    of one doc_id share its class; a null doc_id stays alone, kept, with a null class.  Extra columns are dropped.
    """
    with Workspace() as space:
        return space.result(_classes(prune(docs, "doc_id", "text"), cfg), "classes")


def _classes(docs: DataFrame, cfg: NearDupConfig) -> DataFrame:
    sk = materialise(sketch_table(docs, cfg), "sketch")
    filled = sk.where("n_shingles > 0 and doc_id is not null")
    classes = filled.groupBy("set_hash").agg(F.min("doc_id").alias("rep"))
    members = filled.select("set_hash", "doc_id").distinct()
    by_rep = filled.join(classes, (filled["set_hash"] == classes["set_hash"]) & (filled["doc_id"] == classes["rep"]), "left_semi").dropDuplicates(["doc_id", "set_hash"])
    # a doc_id with several texts stands in several classes; one key for each class
    exploded = by_rep.select(F.col("doc_id").alias("rep"), "n_shingles", F.explode("bands").alias("key"))
    shared = exploded.groupBy("key").agg(F.count(F.lit(1)).alias("n"), F.min("rep").alias("first")).where("n > 1").select("key", "first")
    buckets = materialise(exploded.join(shared, "key").select("key", "first", "rep").distinct(), "buckets")
    texts = docs.join(classes.select(F.col("rep").alias("doc_id")).join(buckets.select(F.col("rep").alias("doc_id")).distinct(), "doc_id", "left_semi").distinct(), "doc_id", "left_semi")
    texts = materialise(texts.select(F.col("doc_id").alias("rep"), "text").distinct(), "texts")
    labels = classes.select("rep", F.col("rep").alias("label")).distinct()
    several = members.groupBy("doc_id").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("doc_id")
    reps = members.join(classes, "set_hash")
    same_id = reps.join(several, "doc_id", "left_semi").select(F.col("rep").alias("a"), F.col("doc_id").alias("b"))
    labels = materialise(labels.unionByName(same_id.select(F.col("b").alias("rep"), F.col("b").alias("label"))).distinct(), "labels")

    tested = buckets.where("rep <> first").select(F.col("rep").alias("a"), F.col("first").alias("b")).distinct()
    with Workspace() as space:  # each round leaves its labels only
        edges = materialise(verify(tested, texts, cfg).unionByName(same_id.where("a <> b")), "edges")
        labels = space.result(connect(labels, edges), "labels")

    for turn, n in enumerate(cfg.centres):
        with Workspace() as space:
            again = _centre_pairs(_mixed_buckets(buckets, labels), n, turn)
            labels = space.result(connect(labels, materialise(verify(again, texts, cfg), "edges")), "labels")

    with Workspace() as space:
        third = _prefix_pairs(_mixed_buckets(buckets, labels).select("rep", "label").distinct(), texts, cfg)
        labels = space.result(connect(labels, materialise(verify(third, texts, cfg), "edges")), "labels")

    of_set = classes.join(labels, "rep").select("set_hash", "label")
    by_doc = members.join(of_set, "set_hash").groupBy("doc_id").agg(F.min("label").alias("component"))
    out = sk.select("doc_id", "n_shingles").join(by_doc, "doc_id", "left")
    component = F.coalesce("component", "doc_id")
    return out.select("doc_id", "n_shingles", component.alias("component_id"), (component.eqNullSafe(F.col("doc_id"))).alias("kept"))


def _mixed_buckets(buckets: DataFrame, labels: DataFrame) -> DataFrame:
    """Buckets whose members are still in different components, with the labels."""
    named = buckets.select("key", "rep").join(labels, "rep")
    mixed = named.groupBy("key").agg(F.min("label").alias("lo"), F.max("label").alias("hi")).where("lo <> hi").select("key")
    return materialise(named.join(mixed, "key", "left_semi").select("key", "rep", "label"), "mixed")


def _centre_pairs(mixed: DataFrame, n: int, turn: int) -> DataFrame:
    """Members outside a bucket's largest component, each with ``n`` hash-chosen members of that component.

    The smaller side of each bucket is paired with a fixed number of centres: at most ``n`` rows a member.
    """
    sizes = mixed.groupBy("key", "label").agg(F.count(F.lit(1)).alias("n"))
    largest = sizes.groupBy("key").agg(F.max_by("label", F.struct("n", "label")).alias("main"))
    named = mixed.join(largest, "key")
    picks = [F.min_by("rep", F.xxhash64("rep", "key", F.lit(100 * turn + i))).alias(f"c{i}") for i in range(n)]
    centres = named.where("label = main").groupBy("key").agg(*picks)
    pairs = named.where("label <> main").join(centres, "key").select("rep", F.explode(F.array_distinct(F.array(*[f"c{i}" for i in range(n)]))).alias("c"))
    return pairs.select(F.least("rep", "c").alias("a"), F.greatest("rep", "c").alias("b")).distinct()


def odd_sketch(values: np.ndarray) -> bytes:
    """Parity of the number of shingles in each of ``ODD_BITS`` hashed bits.

    Two sketches differ in at most as many bits as the sets differ in shingles, so the distance rules pairs out for sure.
    """
    at = (mix(values ^ np.uint64(0xA5A5A5A5A5A5A5A5)) & np.uint64(ODD_BITS - 1)).astype(np.int64)
    return np.packbits((np.bincount(at, minlength=ODD_BITS) & 1).astype(np.uint8)).tobytes()


def _prefix_rows(rest: DataFrame, texts: DataFrame, cfg: NearDupConfig) -> DataFrame:
    """``(g, rep, label, size, pos, sk)``: each set's first shingles in one global order, rarest first.

    Two sets of n and m shingles that reach the similarity share one among their first n - ceil(t n) + 1 and
    m - ceil(t m) + 1.  Shingles of one text alone come first and only use up places.
    """
    kind = dict(rest.dtypes)["rep"]

    def shingled(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in chunks(batches, "text"):
            sets = shingle_sets(text_bytes(part.column(1)), cfg.words)
            row = pa.array(np.repeat(np.arange(len(sets)), [len(x) for x in sets]))
            yield pa.RecordBatch.from_arrays([part.column(2).take(row), pa.array(as_long(np.concatenate(sets)))], names=["rid", "g"])

    def sketched(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in chunks(batches, "text"):
            sets = shingle_sets(text_bytes(part.column(1)), cfg.words)
            yield pa.RecordBatch.from_arrays([part.column(0), part.column(2), pa.array([len(x) for x in sets], pa.int64()), pa.array([odd_sketch(x) for x in sets], pa.binary())], names=["rep", "rid", "size", "sk"])

    some = texts.join(rest.select("rep").distinct(), "rep", "left_semi").select("rep", "text", F.xxhash64("rep", "text").alias("rid"))
    grams_ = materialise(some.mapInArrow(shingled, "rid bigint, g bigint"), "grams")
    sketch = some.mapInArrow(sketched, f"rep {kind}, rid bigint, size bigint, sk binary")
    common = grams_.groupBy("g").agg(F.count(F.lit(1)).alias("n")).where("n > 1")
    shared = grams_.join(common, "g").groupBy("rid").agg(F.sort_array(F.collect_list(F.struct("n", "g"))).alias("gs"))  # as many as one text has
    alone = F.col("size") - F.size("gs")
    places = F.col("size") - F.ceil(F.col("size") * cfg.percent / 100) + 1 - alone
    first = shared.join(sketch, "rid").where(places > 0).join(rest, "rep")
    first = first.select("rep", "label", "size", "sk", alone.alias("alone"), F.posexplode(F.slice(F.col("gs"), F.lit(1), places.cast("int"))).alias("at", "x"))
    return first.select(F.col("x.g").alias("g"), "rep", "label", "size", (F.col("alone") + F.col("at") + 1).alias("pos"), "sk")


def _prefix_pairs(rest: DataFrame, texts: DataFrame, cfg: NearDupConfig) -> DataFrame:
    """Pairs of different components among ``rest (rep, label)`` that may be links; no link is left out.

    Rows of one prefix shingle are cut into blocks of at most about ``BLOCK`` by a hash; a task holds one or two
    blocks and compares their rows: sizes, places (what follows the first common shingle must suffice) and the
    distance of the odd sketches.  Each of these bounds is exact, and only pairs that pass all of them leave the task.
    """
    kind = dict(rest.dtypes)["rep"]
    with Workspace() as space:
        first = space.result(_prefix_rows(rest, texts, cfg), "prefix")
    # a shingle whose texts are all in one component pairs nothing
    groups = first.groupBy("g").agg(F.count(F.lit(1)).alias("n"), F.min("label").alias("lo"), F.max("label").alias("hi")).where("lo <> hi")
    parts = F.ceil(F.col("n") / BLOCK).cast("int")
    rows = first.join(groups.select("g", parts.alias("parts")), "g").withColumn("own", F.pmod(F.xxhash64("rep"), F.col("parts")).cast("int"))
    rows = rows.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)))
    rows = rows.select("g", F.least("own", "other").alias("lo"), F.greatest("own", "other").alias("hi"), "own", "rep", "label", "size", "pos", "sk")
    rows = rows.repartition("g", "lo", "hi").sortWithinPartitions("g", "lo", "hi")

    def pairs(table: pa.Table) -> pa.RecordBatch:
        """Of one block or of one pair of blocks."""
        get = lambda c: table.column(c).to_numpy()
        own, size, pos = get("own"), get("size"), get("pos")
        _, label = np.unique(get("label"), return_inverse=True)
        sk = np.frombuffer(b"".join(table.column("sk").to_pylist()), dtype=np.uint64).reshape(len(size), -1)
        a, b = np.flatnonzero(own == own.min()), np.flatnonzero(own == own.max())
        need = cfg.percent * (size[a][:, None] + size[b][None, :])
        left = size - pos
        fits = (100 + cfg.percent) * (np.minimum(left[a][:, None], left[b][None, :]) + 1) >= need
        fits &= label[a][:, None] != label[b][None, :]
        fits &= 100 * np.minimum(size[a][:, None], size[b][None, :]) >= cfg.percent * np.maximum(size[a][:, None], size[b][None, :])
        if own.min() == own.max():
            fits = np.triu(fits, 1)
        i, j = np.nonzero(fits)
        i, j = a[i], b[j]
        near = np.zeros(len(i), dtype=bool)
        for at in range(0, len(i), 1 << 15):
            x, y = i[at : at + (1 << 15)], j[at : at + (1 << 15)]
            apart = np.bitwise_count(sk[x] ^ sk[y]).sum(1, dtype=np.int64)
            near[at : at + (1 << 15)] = (100 + cfg.percent) * apart <= (100 - cfg.percent) * (size[x] + size[y])
        rep = table.column("rep").combine_chunks()
        return pa.RecordBatch.from_arrays([rep.take(pa.array(i[near])), rep.take(pa.array(j[near]))], names=["a", "b"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for table in runs_of(batches, ("g", "lo", "hi")):
            if table.num_rows > 1:
                found = pairs(table)
                if found.num_rows:
                    yield found

    found = rows.mapInArrow(run, f"a {kind}, b {kind}").where("a <> b")
    return found.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()


def keep_one_of_each(docs: DataFrame, cfg: NearDupConfig = NearDupConfig()) -> DataFrame:
    """One document of each class; all columns of ``docs`` stay, and rows with a null doc_id stay."""
    out = near_duplicates(docs, cfg).where("not kept and doc_id is not null").select("doc_id").distinct()
    return docs.join(out, "doc_id", "left_anti").select(*[F.col(f"`{c}`") for c in docs.columns])
