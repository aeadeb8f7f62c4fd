"""Stage 2: candidates, labels, second opinions and the disambiguation of "may"."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from normgraph.functions import cues as C
from normgraph.functions.pin import pin

EPISTEMIC = ("take", "vary", "occur", "differ", "result", "cause")
CAPS = ("at most", "no more than", "only", "up to")


def prefilter(df: DataFrame, registry: str = "english", text: str = "text") -> DataFrame:
    """Sentences with any cue; narrow, and before anything that costs a call."""
    return pin(df, _t=C.padded(F.col(text))).where(C.has_cue(F.col("_t"), registry)).drop("_t")


def may_reading(text: Column, t: Column) -> Column:
    """``month``, ``prohibition``, ``cap``, ``epistemic``, ``permission``, or null without the word."""
    month = F.regexp_like(text, F.lit("(in|by|since|of) May[ .,]|May [0-9]"))
    cap = F.lit(False)
    for c in CAPS:
        cap = cap | t.contains(f" {c} ")
    epistemic = F.lit(False)
    for v in EPISTEMIC:
        epistemic = epistemic | t.contains(f" may {v} ")
    return F.when(
        t.contains(" may "),
        F.when(month, F.lit("month")).when(t.contains(" may not "), F.lit("prohibition")).when(cap, F.lit("cap")).when(epistemic, F.lit("epistemic")).otherwise(F.lit("permission")),
    )


def quoted_cue(text: Column) -> Column:
    """A cue that the sentence only mentions."""
    return F.regexp_like(text, F.lit('"(must|shall|may|must not|shall not)"'))


def label(df: DataFrame, registry: str = "english", may_mode: str = "relabel", quote_guard: bool = True) -> DataFrame:
    """Adds ``label`` (O, P, F, N), ``confidence``, ``cue_op``, ``may``.

    ``may_mode``: ``relabel`` follows the reading of "may", ``drop`` only rejects the non-rules among them,
    ``off`` admits every cue as it is.
    """
    text = F.col("text")
    df = pin(df, _t=C.padded(text))
    t = F.col("_t")
    df = pin(df, cue_op=C.operator(t, registry), confidence=C.confidence(t, registry), may=may_reading(text, t)).drop("_t")
    op = F.col("cue_op")
    if may_mode != "off":
        alone = op == "P"
        out = F.when(alone & F.col("may").isin("month", "epistemic"), F.lit("N"))
        if may_mode == "relabel":
            out = out.when(alone & (F.col("may") == "cap"), F.lit("O"))
        op = out.otherwise(op)
    if quote_guard:
        op = F.when(quoted_cue(text), F.lit("N")).otherwise(op)
    return pin(df, label=F.coalesce(op, F.lit("N")))


def second_opinion(df: DataFrame, other: Column, other_confidence: Column, gain: float = 0.2) -> DataFrame:
    """Adopt the second label where it differs and is surer by ``gain``."""
    adopt = (other != F.col("label")) & (other_confidence >= F.col("confidence") + gain)
    df = pin(df, adopted=adopt, _other=other, _sure=other_confidence)
    label = F.when(F.col("adopted"), F.col("_other")).otherwise(F.col("label"))
    return pin(df, label=label, confidence=F.when(F.col("adopted"), F.col("_sure")).otherwise(F.col("confidence"))).drop("_other", "_sure")


def confirm(labelled: DataFrame, formulas: DataFrame) -> DataFrame:
    """Liberal admits that a well-formed formula confirms."""
    return labelled.join(formulas.where("ok").select("sent_id"), "sent_id", "left_semi")
