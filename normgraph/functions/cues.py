"""Cue decision: which operator a sentence's modal words call for, longest cue first."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

from normgraph.sources.registry import cues


def padded(text: Column) -> Column:
    """Lower-case letters only, single blanks, a blank at both ends: cues are then plain substrings."""
    return F.concat(F.lit(" "), F.regexp_replace(F.lower(text), "[^a-z]+", " "), F.lit(" "))


def has_cue(t: Column, registry: str) -> Column:
    found = F.lit(False)
    for cue, _ in cues(registry):
        found = found | t.contains(f" {cue} ")
    return found


def hints(t: Column, registry: str) -> Column:
    """Array of ``cue:op`` of all cues present, longest first."""
    return F.filter(F.array(*[F.when(t.contains(f" {c} "), F.lit(f"{c}:{op}")) for c, op in cues(registry)]), lambda x: x.isNotNull())


def operator(t: Column, registry: str) -> Column:
    """Operator of the decisive cue: most words, then leftmost, then first in the list; null without any."""
    best = F.lit(None).cast("struct<rank:int,op:string>")
    options = []
    for i, (cue, op) in enumerate(cues(registry)):
        at = F.instr(t, f" {cue} ")
        rank = F.lit(-1_000_000 * len(cue.split())) + at * 100 + i
        options.append(F.when(at > 0, F.struct(rank.cast("int").alias("rank"), F.lit(op).alias("op"))))
    best = F.array_min(F.filter(F.array(*options), lambda x: x.isNotNull()))
    return best["op"]


def confidence(t: Column, registry: str) -> Column:
    """1.0 for one operator by one cue, 0.7 for one by several, 0.4 for different ones; a longer cue hides its parts."""
    left = t
    ops = []
    for cue, op in cues(registry):
        ops.append(F.when(left.contains(f" {cue} "), F.lit(op)))
        left = F.replace(left, F.lit(f" {cue} "), F.lit(" | "))
    found = F.filter(F.array(*ops), lambda x: x.isNotNull())
    return F.when(F.size(found) == 0, F.lit(0.0)).when(F.size(F.array_distinct(found)) > 1, F.lit(0.4)).when(F.size(found) > 1, F.lit(0.7)).otherwise(F.lit(1.0))
