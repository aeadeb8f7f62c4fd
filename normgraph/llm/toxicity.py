"""Toxicity by compression distance with zstandard dictionaries trained on toxic and on ordinary text.

The ordinary dictionary is trained on windows of ordinary training texts, the toxic one on what recurs in toxic
training texts and is rare in ordinary ones.  Windows of some words, over the whole text, are compressed with
the ordinary dictionary and with both in a row; the bytes that the toxic one saves are calibrated into a score.
"""

from __future__ import annotations

import zlib
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from normgraph.llm.common import _trim, chunks, prune, text_bytes
from normgraph.llm.wordhash import LOWER

#: Bytes that words keep: a-z and everything past ASCII.
_LETTERS = bytes(b if b >= 0x80 or chr(b).isalpha() else 0x20 for b in LOWER)
_CALL = 1 << 14  # windows a call of the compressor


@dataclass(frozen=True)
class ToxicityConfig:
    """``n_toxic`` and ``n_ordinary`` bound the labelled rows used for training, ``max_bytes`` the length of each."""

    n_toxic: int = 1200
    n_ordinary: int = 2400
    max_bytes: int = 64 << 10
    window_words: int = 5
    step_words: int = 4
    ordinary_bytes: int = 8 << 10
    toxic_bytes: int = 4 << 10
    carrier_bytes: int = 48
    level: int = 13
    min_texts: int = 3
    max_share: float = 0.001
    min_ratio: float = 8.0
    calibrate_every: int = 4
    seed: int = 42


@dataclass
class ToxicityModel:
    toxic: bytes
    ordinary: bytes
    weights: np.ndarray | None
    mean: np.ndarray | None
    scale: np.ndarray | None
    prior: float
    config: ToxicityConfig


def words_of(raw: bytes) -> list[bytes]:
    return raw.translate(_LETTERS).split()


def _train_dictionary(size: int, samples: list[bytes], k: int) -> bytes:
    """The content of a dictionary of at most ``size`` bytes; samples too few to train on are the dictionary."""
    import zstandard

    size = min(size, max(512, sum(map(len, samples)) // 4))
    try:  # the trainer puts entropy tables before the content; the windows are too short to gain by them
        return zstandard.train_dictionary(size + 512, samples, k=k, d=6, level=3).as_bytes()[-size:]
    except zstandard.ZstdError:
        return b"".join(samples)[-size:]


def build_dictionaries(texts: list[tuple[bytes, int]], cfg: ToxicityConfig) -> tuple[bytes, bytes]:
    """Dictionary contents (toxic, ordinary) from labelled texts.

    Samples of the ordinary one are windows from all over the ordinary texts.  Those of the toxic one are the
    words of each toxic text that other toxic texts have too and ordinary texts hardly, in text order.
    """
    docs = [(words_of(raw), label) for raw, label in texts]
    seen, total = (Counter(), Counter()), [0, 0]
    for words, label in docs:
        seen[label].update(set(words))
        total[label] += 1
    n0, n1 = max(1, total[0]), max(1, total[1])

    def marks(w: bytes) -> bool:
        toxic, ordinary = seen[1][w], seen[0][w]
        return toxic >= cfg.min_texts and ordinary <= cfg.max_share * n0 and toxic / n1 >= cfg.min_ratio * (ordinary + 1) / n0

    toxic_samples, ordinary_samples = [], []
    rng = np.random.default_rng(cfg.seed)
    for words, label in docs:
        if label:
            own = [w for w in dict.fromkeys(words) if marks(w)]
            toxic_samples += [b" " + b" ".join(own[i : i + 2]) + b" " for i in range(0, len(own), 2)]
        elif words:
            ordinary_samples += [b" " + b" ".join(words[i : i + 8]) + b" " for i in rng.integers(0, len(words), 8)]
    return _train_dictionary(cfg.toxic_bytes, toxic_samples, 24), _train_dictionary(cfg.ordinary_bytes, ordinary_samples, 32) or b" "


class WindowMeter:
    """Bytes that the toxic dictionary saves on each window of words."""

    def __init__(self, toxic: bytes, ordinary: bytes, cfg: ToxicityConfig):
        import zstandard

        frame = {"write_content_size": False, "write_checksum": False, "write_dict_id": False}
        params = zstandard.ZstdCompressionParameters.from_level(cfg.level, min_match=3, format=zstandard.FORMAT_ZSTD1_MAGICLESS, **frame)
        self.pair = []
        for content in (ordinary, toxic + ordinary):  # ordinary words cost the same with either
            known = zstandard.ZstdCompressionDict(content, dict_type=zstandard.DICT_TYPE_RAWCONTENT)
            known.precompute_compress(compression_params=params)
            self.pair.append(zstandard.ZstdCompressor(dict_data=known, compression_params=params))
        self.cfg, self.carrier = cfg, ordinary[-cfg.carrier_bytes :]  # a start that both know, else short windows are stored as they are
        self._segments = zstandard.BufferWithSegments

    def windows(self, raw: bytes) -> list[bytes]:
        words, step = words_of(raw), self.cfg.step_words
        least = self.cfg.window_words - step  # a last window of words that the one before holds is left out
        return [self.carrier + b" " + b" ".join(words[i : i + self.cfg.window_words]) + b" " for i in range(0, max(min(len(words), 1), len(words) - least), step)]

    def saved(self, raws: list[bytes]) -> list[np.ndarray]:
        """For each text the bytes saved on each of its windows."""
        windows, counts = [], []
        for raw in raws:
            own = self.windows(raw)
            windows += own
            counts.append(len(own))
        gains = np.zeros(len(windows))
        for at in range(0, len(windows), _CALL):
            some = windows[at : at + _CALL]
            size = np.array([len(w) for w in some], dtype=np.int64)
            end = np.cumsum(size)
            buffer = self._segments(b"".join(some), np.c_[end - size, size].astype("<u8").tobytes())
            ordinary, toxic = (np.array([len(x) for x in c.multi_compress_to_buffer(buffer)], dtype=np.int64) for c in self.pair)
            gains[at : at + _CALL] = ordinary - toxic
        return np.split(gains, np.cumsum(counts)[:-1]) if raws else []

    def features(self, raws: list[bytes]) -> np.ndarray:
        return np.array([_summary(g) for g in self.saved(raws)]).reshape(len(raws), _N_FEATURES)


_N_FEATURES = 12


def _summary(gains: np.ndarray) -> list[float]:
    n = len(gains)
    if not n:
        return [0.0] * _N_FEATURES
    top = np.sort(gains)[::-1][:3]
    top = np.r_[top, np.full(3 - len(top), gains.min())]
    above = [np.log1p((gains >= k).sum()) for k in (2, 3, 4, 5)]
    return [*top, gains.mean(), gains.std(), np.log(n), np.clip(gains, 0, None).sum() / n**0.5, *above, np.log1p(100 * (gains >= 4).mean())]


def _calibrate(x: np.ndarray, y: np.ndarray, ridge: float = 1e-3) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Logistic calibration by Newton steps; a score of 0.5 is then the threshold."""
    mean, scale = x.mean(0), x.std(0) + 1e-9
    z = np.c_[np.ones(len(x)), (x - mean) / scale]
    w = np.zeros(z.shape[1])
    for _ in range(40):
        p = 1 / (1 + np.exp(-np.clip(z @ w, -30, 30)))
        grad = z.T @ (p - y) + ridge * len(y) * np.r_[0, w[1:]]
        hess = (z * (p * (1 - p))[:, None]).T @ z + np.eye(len(w)) * ridge * len(y)
        step = np.linalg.solve(hess, grad)
        w = w - step
        if np.abs(step).max() < 1e-8:
            break
    return w, mean, scale


def train(texts: list[tuple[bytes, int]], cfg: ToxicityConfig, shift: float = 0.0) -> ToxicityModel:
    """Dictionaries from most of the texts, calibrated on every ``calibrate_every``-th, which they haven't seen.

    ``shift`` (see ``sampling_shift``) turns the odds of the sample into those of all labels.
    """
    n_toxic = sum(y for _, y in texts)
    odds = n_toxic / max(1, len(texts) - n_toxic) * np.exp(shift)
    prior = float(odds / (1 + odds))
    if n_toxic < 8 or len(texts) - n_toxic < 8:
        return ToxicityModel(b"", b"", None, None, None, min(prior, 0.49), cfg)
    order = sorted(texts, key=lambda x: (-x[1], zlib.crc32(x[0], cfg.seed), x[0]))  # both classes reach both parts
    held = order[:: cfg.calibrate_every]
    dictionaries = build_dictionaries([t for i, t in enumerate(order) if i % cfg.calibrate_every], cfg)
    meter = WindowMeter(*dictionaries, cfg)
    y = np.array([t[1] for t in held], dtype=np.float64)
    w, mean, scale = _calibrate(meter.features([t[0] for t in held]), y)
    w[0] += shift
    return ToxicityModel(*dictionaries, w, mean, scale, prior, cfg)


def _eligible(labels: DataFrame) -> DataFrame:
    """Labels that may train: those whose crc32(doc_id as text) mod 5 is not 0."""
    return prune(labels, "doc_id", "toxic").where("doc_id is not null and toxic in (0, 1)").where("crc32(cast(doc_id as string)) % 5 <> 0")


def sampling_shift(labels: DataFrame, cfg: ToxicityConfig = ToxicityConfig()) -> float:
    """What the caps of ``training_rows`` add to the log-odds of toxic, with the sign turned: 0 where none binds."""
    count = {r["toxic"]: r["count"] for r in _eligible(labels).groupBy("toxic").count().collect()}
    n1, n0 = count.get(1, 0), count.get(0, 0)
    if not (n1 and n0 and cfg.n_toxic and cfg.n_ordinary):
        return 0.0
    return float(np.log((n1 / min(n1, cfg.n_toxic)) / (n0 / min(n0, cfg.n_ordinary))))


def training_rows(docs: DataFrame, labels: DataFrame, cfg: ToxicityConfig = ToxicityConfig()) -> list[tuple[bytes, int]]:
    """A bounded sample of the eligible labelled rows, by a hash of doc_id."""
    rows = _eligible(labels)
    rank = F.xxhash64(F.lit(cfg.seed), "doc_id")
    picked = None
    for label, n in ((1, cfg.n_toxic), (0, cfg.n_ordinary)):
        some = rows.where(F.col("toxic") == label).orderBy(rank, "doc_id").limit(n)
        picked = some if picked is None else picked.unionByName(some)
    picked = F.broadcast(picked.dropDuplicates(["doc_id"]))  # at most n_toxic + n_ordinary ids
    found = prune(docs, "doc_id", "text").where(F.octet_length("text") <= cfg.max_bytes).join(picked, "doc_id")
    found = found.groupBy("doc_id", "toxic").agg(F.min("text").alias("text"))  # one text of a repeated doc_id
    return [(r["text"].encode(), int(r["toxic"])) for r in sorted(found.collect(), key=lambda r: r["doc_id"])]


def fit(docs: DataFrame, labels: DataFrame, cfg: ToxicityConfig = ToxicityConfig()) -> ToxicityModel:
    """Train on the bounded sample, calibrated to the class share of all eligible labels."""
    model = train(training_rows(docs, labels, cfg), cfg, sampling_shift(labels, cfg))
    _trim()  # the sample's memory isn't needed again
    return model


def score(docs: DataFrame, model: ToxicityModel, id_col: str = "doc_id", text_col: str = "text", keep: tuple[str, ...] = ()) -> DataFrame:
    """``(id, keep.., score, predicted)`` of every whole text; ``score >= 0.5`` predicts label 1.

    One row for each input row.  Null and empty texts are scored as texts without any window; the longest text is scored whole.  Without two
    classes to train on every row gets the same score below 0.5.
    """
    kinds = dict(docs.dtypes)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        meter = WindowMeter(model.toxic, model.ordinary, model.config) if model.weights is not None else None
        for part in chunks(batches, text_col):
            raws = text_bytes(part.column(part.schema.get_field_index(text_col)))
            if meter is None:
                p = np.full(len(raws), model.prior)
            else:
                x = meter.features(raws)
                z = np.c_[np.ones(len(x)), (x - model.mean) / model.scale] @ model.weights
                p = 1 / (1 + np.exp(-np.clip(z, -30, 30)))
            cols = [part.column(part.schema.get_field_index(c)) for c in (id_col, *keep)]
            yield pa.RecordBatch.from_arrays([*cols, pa.array(p), pa.array((p >= 0.5).astype(np.int32))], names=[id_col, *keep, "score", "predicted"])

    schema = ", ".join(f"`{c}` {kinds[c]}" for c in (id_col, *keep)) + ", score double, predicted int"
    return prune(docs, *dict.fromkeys((id_col, text_col, *keep))).mapInArrow(run, schema)


def classify(docs: DataFrame, labels: DataFrame, cfg: ToxicityConfig = ToxicityConfig(), keep: tuple[str, ...] = ()) -> DataFrame:
    """Train on the bounded sample and score all documents."""
    return score(docs, fit(docs, labels, cfg), keep=keep)
