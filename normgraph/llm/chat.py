"""Multi-party perspective rotation of dialogues.

For every participant the dialogue is rendered with that speaker as the assistant and all others as named
users; the loss mask covers what the assistant says.  A rendering is cut into blocks of ``block_turns``
turn numbers, so that one endless conversation is many rows and not one.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from normgraph.llm.common import prune


@dataclass(frozen=True)
class ChatTemplate:
    """Markers of a turn; the header holds the role, and the speaker's name for users."""

    open: str = "<|start|>"
    close: str = "<|end|>\n"
    block_turns: int = 64


def _role(speaker: Column, me: Column) -> Column:
    return F.when(speaker.eqNullSafe(me), F.lit("assistant")).otherwise(F.concat(F.lit("user name="), speaker))


def rotate(turns: DataFrame, template: ChatTemplate = ChatTemplate()) -> DataFrame:
    """``(conv_id, participant, block, n_turns, char_start, rendered, mask)`` for every participant and block.

    ``mask`` is an array of ``(start, end)`` character spans of ``rendered`` on which loss is taken: the text of
    the assistant's turns with its closing marker.  ``char_start`` is the block's offset in the whole rendering.
    Turns stand in the order of (turn, role, text); repeated rows are one turn; a null role is the speaker
    ``unknown``, a null text empty, a null turn comes first; rows with a null conv_id belong to no dialogue and
    go.  Extra columns are dropped.  A participant without turns in a block still gets the block, all masked out.
    """
    t = prune(turns, "conv_id", "turn", "role", "text").where("conv_id is not null")
    t = t.select("conv_id", F.coalesce("turn", F.lit(-1)).alias("turn"), F.coalesce("role", F.lit("unknown")).alias("role"), F.coalesce("text", F.lit("")).alias("text")).distinct()
    people = t.select("conv_id", F.col("role").alias("participant")).distinct()
    block = F.floor(F.col("turn") / template.block_turns).cast("long")
    packed = t.groupBy("conv_id", block.alias("block")).agg(F.array_sort(F.collect_list(F.struct("turn", "role", "text"))).alias("turns"))
    each = packed.join(people, "conv_id")
    me = F.col("participant")
    # a segment is its head, its text with the closing marker, and whether it is the assistant's
    head = lambda x: F.concat(F.lit(template.open), _role(x["role"], me), F.lit("\n"))
    said = lambda x: F.concat(x["text"], F.lit(template.close))
    segments = F.transform("turns", lambda x: F.struct(head(x).alias("head"), said(x).alias("said"), x["role"].eqNullSafe(me).alias("mine")))
    each = each.withColumn("segments", segments)
    rendered = F.array_join(F.transform("segments", lambda s: F.concat(s["head"], s["said"])), "")
    zero = F.struct(F.lit(0).alias("at"), F.array().cast("array<struct<start:int,end:int>>").alias("spans"))
    step = lambda a, s: F.struct(
        (a["at"] + F.length(s["head"]) + F.length(s["said"])).alias("at"),
        F.when(
            s["mine"],
            F.concat(a["spans"], F.array(F.struct((a["at"] + F.length(s["head"])).alias("start"), (a["at"] + F.length(s["head"]) + F.length(s["said"])).alias("end")))),
        ).otherwise(a["spans"]).alias("spans"),
    )
    out = each.select("conv_id", "participant", "block", F.size("turns").alias("n_turns"), rendered.alias("rendered"), F.aggregate("segments", zero, step)["spans"].alias("mask"))
    sofar = Window.partitionBy("conv_id", "participant").orderBy("block").rowsBetween(Window.unboundedPreceding, -1)
    return out.withColumn("char_start", F.coalesce(F.sum(F.length("rendered").cast("long")).over(sofar), F.lit(0)))


def digest(rendered: DataFrame) -> DataFrame:
    """Small columns of a rotation: sizes, masked characters and the md5 of text and mask."""
    spans = F.array_join(F.transform("mask", lambda m: F.concat_ws("-", m["start"].cast("string"), m["end"].cast("string"))), ",")
    masked = F.aggregate("mask", F.lit(0), lambda a, m: a + m["end"] - m["start"]).cast("long")
    return rendered.select(
        "conv_id", "participant", "block", F.col("n_turns").cast("long").alias("n_turns"), "char_start",
        F.length("rendered").cast("long").alias("n_chars"), masked.alias("mask_chars"), F.md5("rendered").alias("rendered_md5"), F.md5(spans).alias("mask_md5"),
    )
