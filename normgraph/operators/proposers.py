"""Stand-ins for a generative model: one interface, deterministic implementations, a hook for real ones."""

from __future__ import annotations

import json
from collections.abc import Callable, Iterator
from concurrent.futures import ThreadPoolExecutor
from dataclasses import dataclass
from typing import Protocol

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import StringType, StructField, StructType

from normgraph.operators import baselines, classify

ANSWER = "label string, confidence double"


@dataclass(frozen=True)
class Decoding:
    """Decoding settings that travel with a run; fixed values are the printed ones."""

    temperature: float = 0.1
    seed: int = 42
    max_tokens: int = 2048
    timeout_s: float = 120.0
    demos: int = 0


class Proposer(Protocol):
    def propose(self, df: DataFrame, cfg: Decoding) -> DataFrame: ...


@dataclass(frozen=True)
class RuleProposer:
    """Cues and templates as column expressions."""

    registry: str = "english"

    def propose(self, df: DataFrame, cfg: Decoding = Decoding()) -> DataFrame:
        return classify.label(df, self.registry).select(*df.columns, "label", "confidence")


@dataclass(frozen=True)
class NoisyProposer:
    """Answers with the gold label at a given accuracy, by a hash draw."""

    model: str
    accuracy: float

    def propose(self, df: DataFrame, cfg: Decoding = Decoding()) -> DataFrame:
        return df.withColumn("label", baselines.noisy(F.col("gold_label"), F.col("sent_id"), self.model, self.accuracy)).withColumn("confidence", F.lit(self.accuracy))


@dataclass(frozen=True)
class ExternalProposer:
    """Calls ``fn(texts, cfg) -> list of JSON strings`` for each batch; bad JSON is retried once, then null.

    A call that takes longer than ``cfg.timeout_s`` counts as an attempt without answers.  Where the rows have
    ``hints``, a line with them follows the text.  Place it after the pre-filter and write its output: lineage must
    not call a model twice.
    """

    fn: Callable[[list[str], Decoding], list[str]]
    batch: int = 64
    attempts: int = 2

    def propose(self, df: DataFrame, cfg: Decoding = Decoding()) -> DataFrame:
        fn, size, attempts = self.fn, self.batch, self.attempts

        def in_time(texts: list[str]) -> list[str | None]:
            pool = ThreadPoolExecutor(1)
            try:
                return pool.submit(fn, texts, cfg).result(cfg.timeout_s)
            except TimeoutError:
                return [None] * len(texts)
            finally:
                pool.shutdown(wait=False, cancel_futures=True)

        def answer(texts: list[str]) -> list[str | None]:
            out: list[str | None] = [None] * len(texts)
            for _ in range(attempts):
                open_ = [i for i, a in enumerate(out) if a is None]
                for i, raw in zip(open_, in_time([texts[i] for i in open_]) if open_ else [], strict=True):
                    try:
                        json.loads(raw)
                    except (TypeError, ValueError):
                        continue
                    out[i] = raw
            return out

        def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            for f in frames:
                for at in range(0, len(f), size):
                    part = f.iloc[at : at + size].copy()
                    texts = part["text"].fillna("").tolist()
                    if "hints" in part:
                        texts = [f"{t}\nhints: {h}" if h else t for t, h in zip(texts, part["hints"].fillna(""), strict=True)]
                    part["raw"] = answer(texts)
                    yield part

        raw = df.mapInPandas(run, StructType([*df.schema.fields, StructField("raw", StringType())]))
        return raw.withColumn("a", F.from_json("raw", ANSWER)).select(*df.columns, "raw", "a.label", "a.confidence")


def parse_error_rate(df: DataFrame, raw: str = "raw") -> DataFrame:
    """Share of answers that are no JSON with a label."""
    bad = F.from_json(F.col(raw), ANSWER, {"mode": "PERMISSIVE"})["label"].isNull()
    return df.agg(F.count(F.lit(1)).alias("n"), F.avg(bad.cast("double")).alias("error_rate"))
