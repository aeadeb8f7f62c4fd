"""Corpus pipeline: toxicity, near duplicates, repeated passages, benchmark leaks, token ids."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from normgraph.llm import decontaminate, encoding, minhash, suffix, toxicity
from normgraph.llm.common import Workspace, materialise, table

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the compression-distance classifier doesn't call toxic."""
    docs = docs.select(*COLUMNS)
    model = toxicity.fit(docs, table(spark, sf_dir, "labels", "doc_id", "toxic"))
    return toxicity.score(docs, model, keep=COLUMNS[1:]).where("predicted = 0").select(*COLUMNS)


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each near-duplicate class, on five-word shingles."""
    return minhash.keep_one_of_each(docs.select(*COLUMNS), minhash.NearDupConfig(words=5)).select(*COLUMNS)


def drop_repeated_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without later copies of passages of 50 words or more, be they in one document or in several."""
    return suffix.remove_repeats(docs.select(*COLUMNS), suffix.RepeatConfig(across=False)).select(*COLUMNS)


def drop_leaks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold no benchmark item."""
    return decontaminate.remove_leaks(docs.select(*COLUMNS), table(spark, sf_dir, "benchmark", "item_id", "text")).select(*COLUMNS)


def encode_documents(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token counts and digests of the ids and of the decoded text of every remaining document."""
    return encoding.round_trip(docs.select("doc_id", "text"))


STAGES = [
    ("toxicity", drop_toxic),
    ("near_duplicates", drop_near_duplicates),
    ("repeated_passages", drop_repeated_passages),
    ("decontamination", drop_leaks),
    ("encoding", encode_documents),
]
#: The toxicity model and sketches can't be told in SQL; tests hold each stage against a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages in order over ``documents``; each stage's result is written, and goes once the next one is."""
    docs = table(spark, sf_dir, "documents")
    with Workspace() as space:
        for name, stage in STAGES[:-1]:
            docs = materialise(stage(spark, docs, sf_dir), f"pipeline-{name}")
        name, stage = STAGES[-1]
        return space.result(stage(spark, docs, sf_dir), f"pipeline-{name}")
