"""The orchestrator: fixed stage order, validators, bounded retries, toggles for its parts.

A loop of at most one retry is an unrolled plan: what passed, and the second attempt of what failed.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from normgraph.functions import cues
from normgraph.operators import adapter, classify, formalise, shapes
from normgraph.operators.proposers import Decoding, Proposer
from normgraph.sources.registry import load_registry
from normgraph.sources.shared import stored


@dataclass(frozen=True)
class PipelineConfig:
    cues: str = "english"
    registry: str = "star"
    prefilter: bool = True
    hints: bool = True
    reclassify: bool = True
    fol_retry: bool = True
    fallback: bool = True
    may_disambig: bool = True


@dataclass
class Result:
    candidates: DataFrame
    labelled: DataFrame
    rules: DataFrame
    formulas: DataFrame
    shapes: DataFrame


def classify_stage(sentences: DataFrame, cfg: PipelineConfig) -> tuple[DataFrame, DataFrame]:
    """Candidates and labelled candidates; hints let the proposer see mentions in quotation marks."""
    candidates = classify.prefilter(sentences, cfg.cues) if cfg.prefilter else sentences
    labelled = classify.label(candidates, cfg.cues, "relabel" if cfg.may_disambig else "off", quote_guard=cfg.hints)
    if cfg.reclassify:
        from normgraph.operators.baselines import regex_classify

        # the second proposer is surer only where the first met different operators
        other = F.when(F.col("confidence") < 0.5, regex_classify(F.col("text"))).otherwise(F.col("label"))
        sure = F.when(F.col("confidence") < 0.5, F.lit(0.8)).otherwise(F.col("confidence"))
        labelled = classify.second_opinion(labelled, other, sure)
    return candidates, labelled


def proposed(candidates: DataFrame, cfg: PipelineConfig, proposer: Proposer, decoding: Decoding) -> DataFrame:
    """Labels of a proposer, called once for each candidate and written; answers that can't be read are no rules."""
    cued = classify.label(candidates, cfg.cues, "off", quote_guard=False).drop("label", "confidence")
    if cfg.hints:
        cued = cued.withColumn("hints", F.concat_ws(",", cues.hints(cues.padded(F.col("text")), cfg.cues)))
    known = F.col("label").isin("O", "P", "F", "N")
    answers = stored(proposer.propose(cued, decoding), "answers").withColumn("label", F.when(known, F.col("label")).otherwise(F.lit("N")))
    return answers.withColumn("confidence", F.coalesce("confidence", F.lit(0.0))).drop("raw", "hints")


def shapes_of(grounded: DataFrame, cfg: PipelineConfig = PipelineConfig()) -> DataFrame:
    """Shapes of the formulas, and by the direct route of what has none."""
    out = shapes.emit(grounded)
    return out.unionByName(shapes.direct(grounded)) if cfg.fallback else out


def run(spark: SparkSession, sentences: DataFrame, cfg: PipelineConfig = PipelineConfig(), proposer: Proposer | None = None, decoding: Decoding = Decoding()) -> Result:
    """All stages over ``sentences (sent_id, text, ..)``; one plan, nothing is collected.

    A ``proposer`` takes the place of the cue rules in the classification; its answers are written before they are used.
    """
    if proposer:
        candidates = classify.prefilter(sentences, cfg.cues) if cfg.prefilter else sentences
        labelled = proposed(candidates, cfg, proposer, decoding)
    else:
        candidates, labelled = classify_stage(sentences, cfg)
    rules = labelled.where("label <> 'N'")
    formulas = formalise.lift(rules, 0)
    if cfg.fol_retry:
        formulas = formalise.retry(formulas)
    grounded = adapter.ground(formulas, load_registry(spark, cfg.registry))
    return Result(candidates, labelled, rules, grounded, shapes_of(grounded, cfg))


ABLATIONS = {
    "all_on": PipelineConfig(),
    "prefilter_off": PipelineConfig(prefilter=False),
    "hints_off": PipelineConfig(hints=False),
    "reclassify_off": PipelineConfig(reclassify=False),
    "fol_retry_off": PipelineConfig(fol_retry=False),
    "fallback_off": PipelineConfig(fallback=False),
    "may_off": PipelineConfig(may_disambig=False),
}
