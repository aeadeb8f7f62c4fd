"""Quality classification by co-training two views of a document.

One classifier sees the text (hashed words and word pairs, kinds of characters, lines), the other the record's metadata
(language, source, stated length).  Over some rounds each labels the pool rows it is surest of for the other.
Both are then calibrated on labelled rows kept apart, and their calibrated log-odds are combined.
Only labelled rows are sampled for training (by a hash); the pool is every unlabelled document, and every document is scored.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from normgraph.llm.common import Workspace, chunks, materialise, prune, text_bytes
from normgraph.llm.wordhash import hash_words, mix

_KINDS = np.zeros(256, dtype=np.int64)  # kinds of bytes, for one bincount a text
for _name, _set in enumerate((b"#*$%&|<>", b"0123456789", bytes(range(65, 91)), b".!?", b",;:", b" \t", b"\n", bytes(range(97, 123)), b"|"), start=1):
    _KINDS[list(_set)] = _name
_SHAPES, _WORDS, _PAIRS = 16, 48, 16
_N_TEXT = _SHAPES + _WORDS + _PAIRS
_SOURCES = 64
_LENGTHS = 12


@dataclass(frozen=True)
class CoTrainingConfig:
    """``n_labelled`` bounds the labelled rows of training, ``n_pool`` the pool rows of ``training_views`` only."""

    n_labelled: int = 6000
    n_pool: int = 6000
    rounds: int = 5
    each_round: int = 100
    sure: float = 0.8
    threshold: float = 0.5
    seed: int = 42


def text_view(raws: list[bytes]) -> np.ndarray:
    """Features of whole texts: shares of kinds of characters, lengths and repeats, and hashed words and word pairs."""
    words = hash_words(raws)
    out = np.zeros((len(raws), _N_TEXT))
    for r, raw in enumerate(raws):
        n = max(1, len(raw))
        kinds = np.bincount(_KINDS[np.frombuffer(raw, dtype=np.uint8)], minlength=10)
        h = words.h[words.first[r] : words.first[r + 1]]
        size = words.end[words.first[r] : words.first[r + 1]] - words.start[words.first[r] : words.first[r + 1]]
        m = max(1, len(h))
        lines = raw.split(b"\n")
        pairs = h[:-1] * np.uint64(31) + h[1:] if len(h) > 1 else h
        out[r, :_SHAPES] = [
            np.log1p(len(h)), *(kinds[k] / n for k in (1, 2, 3, 4, 5, 6, 7, 9)), size.mean() if len(size) else 0, size.std() if len(size) else 0,
            len(np.unique(h)) / m, len(np.unique(pairs)) / max(1, len(pairs)), 1 - len(set(lines)) / len(lines), np.log1p(n / len(lines)),
            float(kinds[1] == 0 and kinds[9] == 0),
        ]
        out[r, _SHAPES:] = np.sqrt(np.r_[np.bincount((h % np.uint64(_WORDS)).astype(np.int64), minlength=_WORDS) / m, np.bincount((mix(pairs) % np.uint64(_PAIRS)).astype(np.int64), minlength=_PAIRS) / m])
    return out


def metadata_view(langs: list, sources: list, lengths: list) -> np.ndarray:
    """One-hot language (hashed to 8), source (hashed to 64) and length class; nulls have classes of their own."""
    out = np.zeros((len(langs), 8 + _SOURCES + _LENGTHS))
    for r, (lang, source, n) in enumerate(zip(langs, sources, lengths, strict=True)):
        out[r, 0 if lang is None else 1 + zlib.crc32(str(lang).encode()) % 7] = 1
        out[r, 8 + (0 if source is None else 1 + zlib.crc32(str(source).encode()) % (_SOURCES - 1))] = 1
        out[r, 8 + _SOURCES + (0 if n is None else min(_LENGTHS - 1, 1 + int(np.log2(max(1, n)) / 1.5)))] = 1
    return out


class Logistic:
    """Ridge logistic regression by Newton steps on standardised features."""

    def __init__(self, x: np.ndarray, y: np.ndarray, ridge: float = 1e-3):
        self.mean, self.scale = x.mean(0), x.std(0)
        self.scale[self.scale < 1e-9] = 1.0
        z = self._z(x)
        w = np.zeros(z.shape[1])
        penalty = np.r_[0.0, np.full(z.shape[1] - 1, ridge * len(y))]
        for _ in range(30):
            p = 1 / (1 + np.exp(-np.clip(z @ w, -30, 30)))
            step = np.linalg.solve((z * (p * (1 - p))[:, None]).T @ z + np.diag(penalty + 1e-6), z.T @ (p - y) + penalty * w)
            w = w - step
            if np.abs(step).max() < 1e-7:
                break
        self.w = w

    def _z(self, x: np.ndarray) -> np.ndarray:
        return np.c_[np.ones(len(x)), np.clip((x - self.mean) / self.scale, -8, 8)]

    def odds(self, x: np.ndarray) -> np.ndarray:
        return np.clip(self._z(x) @ self.w, -30, 30)


def _p(odds: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-odds))


@dataclass
class CoTrained:
    text: Logistic
    meta: Logistic
    text_scale: Logistic
    meta_scale: Logistic
    both: Logistic
    history: list[dict]

    def scores(self, x: np.ndarray, m: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        a = self.text_scale.odds(self.text.odds(x)[:, None])
        b = self.meta_scale.odds(self.meta.odds(m)[:, None])
        return _p(a), _p(b), _p(self.both.odds(np.c_[a, b]))


class HeldPool:
    """A pool in memory."""

    def __init__(self, x: np.ndarray, m: np.ndarray):
        self.views, self.open = {"text": x, "meta": m}, np.ones(len(x), dtype=bool)

    def surest(self, view: str, model: Logistic, label: float, n: int, least: float) -> tuple[np.ndarray, np.ndarray]:
        """Views of the ``n`` open rows that the model is surest have the label; they are open no longer."""
        rows = np.flatnonzero(self.open)
        p = _p(model.odds(self.views[view][rows]))
        sure = np.maximum(p, 1 - p)
        mine = np.flatnonzero(((p >= 0.5) == (label == 1.0)) & (sure >= least))
        pick = rows[mine[np.argsort(-sure[mine], kind="stable")[:n]]]
        self.open[pick] = False
        return self.views["text"][pick], self.views["meta"][pick]


class SpreadPool:
    """All unlabelled documents, scored in Spark; only the rows picked reach the driver."""

    def __init__(self, rows: DataFrame):
        self.rows, self.taken = rows, set()

    def surest(self, view: str, model: Logistic, label: float, n: int, least: float) -> tuple[np.ndarray, np.ndarray]:
        taken = frozenset(self.taken)

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                if not batch.num_rows:
                    continue
                x = batch.column(2).flatten().to_numpy().reshape(-1, _N_TEXT) if view == "text" else _one_hot(batch.column(3).flatten().to_numpy().reshape(-1, 3))
                p = _p(model.odds(x))
                sure = np.maximum(p, 1 - p)
                mine = np.flatnonzero(((p >= 0.5) == (label == 1.0)) & (sure >= least))
                ids = batch.column(0).take(pa.array(mine)).to_pylist()
                mine = mine[np.array([i not in taken for i in ids], dtype=bool)]
                tie = batch.column(1).to_numpy()
                mine = mine[np.lexsort((tie[mine], -sure[mine]))[:n]]  # no other row of this batch can be among the first n
                best = batch.take(pa.array(mine))
                yield pa.RecordBatch.from_arrays([*best.columns, pa.array(sure[mine])], names=[*best.schema.names, "sure"])

        kind = dict(self.rows.dtypes)["doc_id"]
        best = self.rows.mapInArrow(run, f"doc_id {kind}, tie bigint, x array<double>, at array<int>, sure double")
        found = best.orderBy(F.desc("sure"), "tie", "doc_id", "x").limit(n).collect()
        self.taken |= {r["doc_id"] for r in found}
        return np.array([r["x"] for r in found]).reshape(-1, _N_TEXT), _one_hot(np.array([r["at"] for r in found], dtype=np.int64).reshape(-1, 3))


def _one_hot(at: np.ndarray) -> np.ndarray:
    out = np.zeros((len(at), 8 + _SOURCES + _LENGTHS))
    np.put_along_axis(out, at.astype(np.int64), 1.0, axis=1)
    return out


def spread_pool(docs: DataFrame, labels: DataFrame, cfg: CoTrainingConfig) -> SpreadPool:
    """Views of every document without a label, written once; call it inside a workspace."""
    kind = dict(docs.dtypes)["doc_id"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part, x, m in _views(batches):
            at = pa.array(np.nonzero(m)[1].reshape(-1, 3).astype(np.int32).tolist(), pa.list_(pa.int32()))  # one of each of the three groups
            yield pa.RecordBatch.from_arrays([part.column(0), pa.array(list(x), pa.list_(pa.float64())), at], names=["doc_id", "x", "at"])

    views = prune(docs, "doc_id", "text", "lang", "source", "n_chars").where("doc_id is not null").mapInArrow(run, f"doc_id {kind}, x array<double>, at array<int>")
    named = prune(labels, "doc_id", "quality").where("doc_id is not null and quality in (0, 1)").select("doc_id")
    rows = views.join(named, "doc_id", "left_anti").select("doc_id", F.xxhash64(F.lit(cfg.seed), "doc_id").alias("tie"), "x", "at")
    return SpreadPool(materialise(rows, "pool"))


def co_train(x: np.ndarray, m: np.ndarray, y: np.ndarray, pool_x: np.ndarray, pool_m: np.ndarray, cfg: CoTrainingConfig = CoTrainingConfig()) -> CoTrained | None:
    """``co_train_pool`` on a pool in memory."""
    return co_train_pool(x, m, y, HeldPool(pool_x, pool_m), cfg)


def co_train_pool(x: np.ndarray, m: np.ndarray, y: np.ndarray, pool: HeldPool | SpreadPool, cfg: CoTrainingConfig = CoTrainingConfig()) -> CoTrained | None:
    """Fit both views; every fourth labelled row is kept for calibration.  None without two classes."""
    held = np.arange(len(y)) % 4 == 0
    if len(np.unique(y[held])) < 2 or len(np.unique(y[~held])) < 2:
        return None
    tx, ty_x = x[~held], y[~held]
    tm, ty_m = m[~held], y[~held]
    history = []
    for turn in range(cfg.rounds + 1):
        text, meta = Logistic(tx, ty_x), Logistic(tm, ty_m)
        history.append({"round": turn, "text_rows": len(ty_x), "meta_rows": len(ty_m), "text_accuracy": float(((text.odds(x[held]) > 0) == y[held]).mean()), "meta_accuracy": float(((meta.odds(m[held]) > 0) == y[held]).mean())})
        if turn == cfg.rounds:
            break
        for model, view in ((text, "text"), (meta, "meta")):
            for label in (0.0, 1.0):  # as many of each class as its share of the labels
                share = max(1, round(cfg.each_round * float((y == label).mean())))
                new_x, new_m = pool.surest(view, model, label, share, cfg.sure)
                if view == "text":
                    tm, ty_m = np.r_[tm, new_m], np.r_[ty_m, np.full(len(new_m), label)]
                else:
                    tx, ty_x = np.r_[tx, new_x], np.r_[ty_x, np.full(len(new_x), label)]
    a, b = text.odds(x[held])[:, None], meta.odds(m[held])[:, None]
    text_scale, meta_scale = Logistic(a, y[held]), Logistic(b, y[held])
    both = Logistic(np.c_[text_scale.odds(a), meta_scale.odds(b)], y[held])
    return CoTrained(text, meta, text_scale, meta_scale, both, history)


def _views(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[pa.RecordBatch, np.ndarray, np.ndarray]]:
    for part in chunks(batches, "text"):
        get = lambda c, part=part: part.column(part.schema.get_field_index(c))
        yield part, text_view(text_bytes(get("text"))), metadata_view(get("lang").to_pylist(), get("source").to_pylist(), get("n_chars").to_pylist())


def training_views(docs: DataFrame, labels: DataFrame, cfg: CoTrainingConfig) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Views and labels (-1: pool) of a bounded sample of rows, chosen by a hash of doc_id, from one scan."""
    rank = F.xxhash64(F.lit(cfg.seed), "doc_id")
    named = prune(labels, "doc_id", "quality").where("doc_id is not null and quality in (0, 1)")
    labelled = named.orderBy(rank, "doc_id").limit(cfg.n_labelled).select("doc_id", F.col("quality").cast("double").alias("y"))
    pool = prune(docs, "doc_id").where("doc_id is not null").join(named.select("doc_id"), "doc_id", "left_anti")
    pool = pool.orderBy(rank, "doc_id").limit(cfg.n_pool).select("doc_id", F.lit(-1.0).alias("y"))
    chosen = labelled.unionByName(pool).dropDuplicates(["doc_id"])  # at most n_labelled + n_pool ids
    some = prune(docs, "doc_id", "text", "lang", "source", "n_chars").join(F.broadcast(chosen), "doc_id")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part, x, m in _views(batches):
            yield pa.RecordBatch.from_arrays([part.column(part.schema.get_field_index("doc_id")), part.column(part.schema.get_field_index("y")), pa.array(list(x), pa.list_(pa.float64())), pa.array(list(m), pa.list_(pa.float64()))], names=["doc_id", "y", "x", "m"])

    kind = dict(docs.dtypes)["doc_id"]
    rows = some.mapInArrow(run, f"doc_id {kind}, y double, x array<double>, m array<double>").limit(2 * (cfg.n_labelled + cfg.n_pool)).collect()
    rows.sort(key=lambda r: (zlib.crc32(str(r["doc_id"]).encode()), str(r["doc_id"]), r["x"]))
    return np.array([r["x"] for r in rows]).reshape(-1, _N_TEXT), np.array([r["m"] for r in rows]).reshape(-1, 8 + _SOURCES + _LENGTHS), np.array([r["y"] for r in rows])


def score(docs: DataFrame, model: CoTrained | None, cfg: CoTrainingConfig = CoTrainingConfig()) -> DataFrame:
    """``(doc_id, text_score, meta_score, score, kept)`` of every document, repeated rows included.

    Null and empty texts and null metadata have features of their own.  Without a model all scores are 0.5 and
    every row is kept.  Extra columns are dropped.
    """
    kind = dict(docs.dtypes)["doc_id"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part, x, m in _views(batches):
            a, b, p = model.scores(x, m) if model else (np.full(len(x), 0.5),) * 3
            yield pa.RecordBatch.from_arrays([part.column(0), pa.array(a), pa.array(b), pa.array(p), pa.array(p >= cfg.threshold)], names=["doc_id", "text_score", "meta_score", "score", "kept"])

    return prune(docs, "doc_id", "text", "lang", "source", "n_chars").mapInArrow(run, f"doc_id {kind}, text_score double, meta_score double, score double, kept boolean")


def classify(docs: DataFrame, labels: DataFrame, cfg: CoTrainingConfig = CoTrainingConfig()) -> DataFrame:
    """Co-train on a bounded sample of labels and all unlabelled documents, and score all documents."""
    return score(docs, fit(docs, labels, cfg), cfg)


def fit(docs: DataFrame, labels: DataFrame, cfg: CoTrainingConfig = CoTrainingConfig()) -> CoTrained | None:
    x, m, y = training_views(docs, labels, replace(cfg, n_pool=0))
    if len(np.unique(y)) < 2:
        return None
    with Workspace():
        return co_train_pool(x, m, y, spread_pool(docs, labels, cfg), cfg)
