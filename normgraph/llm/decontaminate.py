"""Benchmark decontamination with SimHash windows.

The weighted shingles of items and of item-sized windows of documents get 128-bit SimHash fingerprints.  The item
index has sixteen blocks of eight bits; a fingerprint within 47 bits differs in at most two bits in some block, so looking
up each block with up to two flipped bits finds all of them.  The multiset of k-word shingles, weighted by rarity
among items, verifies each candidate.  Every window start is considered at which the shingles shared with some item
weigh enough for the similarity; a document shorter than an item is one window as a whole.

A shingle counts with the square root of its weight, each further occurrence as a shingle of its own.  At similarity s
two sets then have a cosine of 2s / (1 + s) at least, a bit differs with probability 0.15 at most for s = 0.8, and the
radius is passed by 47 of 128 bits with probability 2e-8.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_type

from normgraph.llm.common import chunks, materialise, prune, text_bytes
from normgraph.llm.wordhash import Words, grams, hash_words, mix

BLOCKS, BLOCK_BITS, RADIUS = 16, 8, 47
#: Bytes of item texts that one pass broadcasts; larger sets are searched in several blocks of items, one after the other.
MAX_ITEM_BYTES = 4 << 20


@dataclass(frozen=True)
class DecontaminationConfig:
    words: int = 5
    similarity: float = 0.8


def fingerprint(shingles: Counter, weigh) -> np.ndarray:
    """16 bytes: the signs of the weighted sum of the shingles' hashed +-1 vectors."""
    each = [(s, i) for s, n in shingles.items() for i in range(n)]
    base = np.array([s for s, _ in each], dtype=np.uint64)
    turn = np.array([i for _, i in each], dtype=np.uint64)
    weight = np.sqrt(np.array([weigh(s) for s, _ in each]))
    with np.errstate(over="ignore"):
        first = mix(base + turn * np.uint64(0x9E3779B97F4A7C15))
        second = mix(first + np.uint64(0xC2B2AE3D27D4EB4F))
    bits = np.unpackbits(np.stack([first, second], axis=1).view(np.uint8), axis=1).astype(np.float64) * 2 - 1
    return np.packbits(weight @ bits > 0)


#: How many items there are, and how many hold each shingle that more than one holds.
Rarity = tuple[int, dict[int, int]]


def _flips() -> np.ndarray:
    """All bytes with at most two bits set."""
    every = np.arange(256, dtype=np.uint8)
    return every[np.bitwise_count(every) <= 2]


class ItemIndex:
    """Fingerprints, shingles and the multi-index blocks of a set of items."""

    def __init__(self, items: list[tuple[int, bytes]], cfg: DecontaminationConfig, rarity: Rarity | None = None):
        """``rarity`` is that of all items, where these are one block of several."""
        self.cfg = cfg
        words = hash_words([t for _, t in items], lower=True)
        self.ids, self.sizes, self.shingles = [], [], []
        use: Counter = Counter()
        where: dict[int, dict[int, list[int]]] = {}
        for row, (item_id, _) in enumerate(items):
            h = words.h[words.first[row] : words.first[row + 1]]
            if not len(h):
                continue
            k = min(cfg.words, len(h))
            own = Counter(grams(h, k).tolist())
            n = len(self.ids)
            self.ids.append(item_id)
            self.sizes.append(len(h))
            self.shingles.append(own)
            use.update(own.keys())
            for x in own:
                where.setdefault(k, {}).setdefault(x, []).append(n)
        total, shared = rarity or (len(self.ids), {s: n for s, n in use.items() if n > 1})
        self.weight = {s: float(np.log1p(total / n)) for s, n in shared.items()}  # a shingle of one item weighs as an unknown one
        self.unknown = float(np.log1p(total))
        self.mass = [self.weigh(s) for s in self.shingles]
        self.where = where
        self.known = {k: np.sort(np.fromiter(v, dtype=np.uint64, count=len(v))) for k, v in where.items()}
        self.prints = np.array([fingerprint(s, self._weight) for s in self.shingles], dtype=np.uint8).reshape(-1, BLOCKS)
        flips = _flips()
        self.blocks: list[tuple[np.ndarray, np.ndarray]] = []  # items in the order of their byte, and where each byte begins
        for b in range(BLOCKS):
            order = np.argsort(self.prints[:, b], kind="stable")
            self.blocks.append((order, np.searchsorted(self.prints[order, b], np.arange(257))))
        self.flips = flips

    def _weight(self, shingle: int) -> float:
        return self.weight.get(shingle, self.unknown)

    def near(self, mark: np.ndarray) -> list[int]:
        """Items within the radius of one fingerprint."""
        found = [order[edge[v] : edge[v + 1]] for (order, edge), own in zip(self.blocks, mark, strict=True) for v in (self.flips ^ own).tolist()]
        some = np.unique(np.concatenate(found))
        far = np.bitwise_count(self.prints[some] ^ mark).sum(1)
        return some[far <= RADIUS].tolist()

    def weigh(self, shingles: Counter) -> float:
        return sum(n * self._weight(s) for s, n in shingles.items())

    def similarity(self, item: int, window: Counter) -> float:
        """Weighted multiset similarity of an item's and a window's shingles."""
        own = self.shingles[item]
        both = union = 0.0
        for s in own.keys() | window.keys():
            w = self._weight(s)
            a, b = own.get(s, 0), window.get(s, 0)
            both += w * min(a, b)
            union += w * max(a, b)
        return both / union if union else 0.0

    def windows(self, h: np.ndarray, hits: dict[int, np.ndarray]) -> set[tuple[int, int, int]]:
        """``(k, start, size)`` of every window in which the shingles shared with some item weigh enough."""
        least = self.cfg.similarity - 1e-9
        out: set[tuple[int, int, int]] = set()
        for k, places in hits.items():
            g = grams(h, k)
            own: dict[int, list[int]] = {}
            for p in places.tolist():
                for n in self.where[k].get(int(g[p]), ()):
                    own.setdefault(n, []).append(p)
            weight = {p: self._weight(int(g[p])) for p in places.tolist()}
            for n, at in own.items():
                size, need = min(self.sizes[n], len(h)), least * self.mass[n]
                value = [weight[p] for p in at]
                if sum(value) < need:
                    continue
                # shingles of the window at s stand at s .. s + size - k; add each hit to the starts whose window holds it
                lo = np.maximum(0, np.array(at) - (size - k))
                hi = np.minimum(len(h) - size, np.array(at)) + 1
                base = int(lo.min())
                held = np.zeros(int(hi.max()) - base + 1)
                np.add.at(held, lo - base, value)
                np.add.at(held, hi - base, [-v for v in value])
                out.update((k, base + int(s), size) for s in np.flatnonzero(np.cumsum(held)[:-1] >= need - 1e-6))
        return out

    def search(self, words: Words, row: int, hits: dict[int, np.ndarray]) -> list[tuple[int, int, int, float]]:
        """Matches ``(item, first word, end word, similarity)`` of one text; best of overlapping windows only."""
        h = words.h[words.first[row] : words.first[row + 1]]
        best: dict[int, list[tuple[int, int, float]]] = {}
        wanted = sorted(self.windows(h, hits))
        shingled = {k: grams(h, k).tolist() for k in {k for k, _, _ in wanted}}
        for k, s, size in wanted:
            window = Counter(shingled[k][s : s + size - k + 1])
            for item in self.near(fingerprint(window, self._weight)):
                own = self.sizes[item]
                if min(own, len(h)) != size or min(self.cfg.words, own) != k:
                    continue
                sim = self.similarity(item, window)
                if sim >= self.cfg.similarity:
                    best.setdefault(item, []).append((s, s + size, sim))
        out = []
        for item, found in best.items():
            taken: list[tuple[int, int]] = []
            for s, e, sim in sorted(found, key=lambda x: (-x[2], x[0])):
                if all(e <= a or s >= b for a, b in taken):
                    taken.append((s, e))
                    out.append((self.ids[item], s, e, sim))
        return sorted(out)


def _valid(items: DataFrame) -> DataFrame:
    return prune(items, "item_id", "text").where("item_id is not null and text is not null")


def _n_blocks(items: DataFrame, max_bytes: int) -> int:
    size = _valid(items).agg(F.coalesce(F.sum(F.octet_length("text") + 16), F.lit(0)).alias("n")).first()["n"]
    return max(1, -(-int(size) // max_bytes))


def _item_block(items: DataFrame, part: int, parts: int) -> list[tuple[int, bytes]]:
    """One block of items, of a checked size; usual benchmarks are one block."""
    some = _valid(items).where(F.pmod(F.xxhash64("item_id", "text"), F.lit(parts)) == part)
    return sorted((r["item_id"], r["text"].encode()) for r in some.collect())


def _rarity(items: DataFrame, cfg: DecontaminationConfig) -> Rarity:
    """Over all items, so that a weight doesn't depend on the blocks; only shingles of several items are listed."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in chunks(batches, "text"):
            words = hash_words(text_bytes(part.column(1)), lower=True)
            for a, b in zip(words.first[:-1].tolist(), words.first[1:].tolist(), strict=True):
                if b > a:
                    k = min(cfg.words, b - a)
                    g = np.unique(grams(words.h[a:b], k)[: b - a - k + 1])
                    yield pa.RecordBatch.from_arrays([pa.array(g.view(np.int64)), pa.array(np.arange(len(g)) == 0)], names=["g", "head"])

    each = _valid(items).mapInArrow(run, "g bigint, head boolean")
    total = each.where("head").count()
    shared = each.groupBy("g").count().where("count > 1").collect()
    return total, {r["g"] & (2**64 - 1): r["count"] for r in shared}


def find_leaks(docs: DataFrame, items: DataFrame, cfg: DecontaminationConfig = DecontaminationConfig(), max_item_bytes: int = MAX_ITEM_BYTES) -> DataFrame:
    """``(doc_id, item_id, first_word, end_word, similarity)``: every place of a document that holds an item.

    Words are split at white space after A-Z are lower-cased.  Null and empty texts or items match nothing;
    repeated rows are searched one by one; a text shorter than an item is compared as a whole; an item of fewer words than a shingle matches as one whole.
    Without matches, or without items, the result is empty.  Ids may be of any type.  Extra columns are dropped.
    """
    docs = prune(docs, "doc_id", "text")
    parts = _n_blocks(items, max_item_bytes)
    rarity = _rarity(items, cfg) if parts > 1 else None
    out = None
    for part in range(parts):
        shared = docs.sparkSession.sparkContext.broadcast((_item_block(items, part, parts), rarity))
        found = _search(docs, dict(items.dtypes)["item_id"], to_arrow_type(items.schema["item_id"].dataType), shared, cfg)
        if parts > 1:  # one block at a time on the driver and in the workers
            found = materialise(found, "leaks")
            shared.unpersist()
        out = found if out is None else out.unionByName(found)
    return out


def _search(docs: DataFrame, item_kind: str, item_type: pa.DataType, shared, cfg: DecontaminationConfig) -> DataFrame:
    schema = f"doc_id {dict(docs.dtypes)['doc_id']}, item_id {item_kind}, first_word bigint, end_word bigint, similarity double"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        index = ItemIndex(shared.value[0], cfg, shared.value[1])
        filters = {}
        for k, known in index.known.items():
            bloom = np.zeros(1 << 22, dtype=bool)
            bloom[(known & np.uint64((1 << 22) - 1)).astype(np.int64)] = True
            filters[k] = bloom
        for part in chunks(batches, "text"):
            words = hash_words(text_bytes(part.column(1)), lower=True)
            hits: dict[int, dict[int, np.ndarray]] = {}
            for k, known in index.known.items():
                g = grams(words.h, k)
                at = np.flatnonzero(filters[k][(g & np.uint64((1 << 22) - 1)).astype(np.int64)])
                near = np.searchsorted(known, g[at])
                at = at[known[np.minimum(near, len(known) - 1)] == g[at]]
                row = np.searchsorted(words.first, at, side="right") - 1
                inside = at + k <= words.first[row + 1]
                at, row = at[inside], row[inside]
                for r in np.unique(row).tolist():
                    hits.setdefault(r, {})[k] = at[row == r] - words.first[r]
            rows, found = [], []
            for r in sorted(hits):
                for match in index.search(words, r, hits[r]):
                    rows.append(r)
                    found.append(match)
            if rows:
                kinds = (item_type, pa.int64(), pa.int64(), pa.float64())
                cols = [part.column(0).take(pa.array(rows)), *(pa.array([f[i] for f in found], t) for i, t in enumerate(kinds))]
                yield pa.RecordBatch.from_arrays(cols, names=["doc_id", "item_id", "first_word", "end_word", "similarity"])

    return docs.mapInArrow(run, schema)


def remove_leaks(docs: DataFrame, items: DataFrame, cfg: DecontaminationConfig = DecontaminationConfig()) -> DataFrame:
    """The documents that hold no item; all columns of ``docs`` stay.  A null ``doc_id`` is never removed."""
    leaky = find_leaks(docs, items, cfg).select("doc_id").distinct()
    return docs.join(leaky, "doc_id", "left_anti").select(*[F.col(f"`{c}`") for c in docs.columns])
