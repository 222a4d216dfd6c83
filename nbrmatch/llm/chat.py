"""Multi-party chat formatting by perspective rotation, in DataFrame functions alone.

For every speaker of a conversation the dialogue is rendered once with that speaker as the assistant and all others as
users that carry their name; masks are the spans of the assistant's turns, which are to be learnt. Long conversations are
rendered in parts of PART turns, each of them after the conversation's first system turn, so no row holds an unbounded group.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

START, END = "<|im_start|>", "<|im_end|>\n"
#: Turn numbers of one part.
PART = 256
#: Roles that speak for nobody: rendered as they are in every perspective, never as the assistant.
NOT_SPEAKERS = ("system",)


def _harmless(text: Column) -> Column:
    """Marks of the format inside a text lose their meaning."""
    return F.replace(F.coalesce(text, F.lit("")), F.lit("<|im_"), F.lit("<| im_"))


def _name(role: Column) -> Column:
    """A role as it may stand in a turn's head: no marks, and on one line."""
    return F.translate(_harmless(role), "\n\r", "  ")


def perspectives(turns: DataFrame) -> DataFrame:
    """(conv_id, speaker, part, n_turns, rendered, mask) from turns (conv_id, turn, role, text).

    mask: (start, end) in code points of `rendered`, end exclusive, of what each turn of the speaker says, with its end
    mark. Turns go by number; turns of one number go by role, then text. Turns without a number have no order: they come
    in parts of their own with numbers below 0, dealt by a hash. Rows equal in all four columns are one turn. A part
    that doesn't hold the conversation's first system turn begins with it (it isn't counted in n_turns). Marks of the
    format in texts and roles lose their meaning, line ends in roles become spaces. A null role speaks as "unknown", a
    null text says nothing. A conversation without speakers gives no rows; a null conv_id is a conversation like any
    other. Extra columns are ignored.
    """
    turns = turns.select("conv_id", F.col("turn").cast("long").alias("turn"), F.coalesce(F.col("role").cast("string"), F.lit("unknown")).alias("role"), F.col("text").cast("string").alias("text")).distinct()
    system = F.col("role").isin(*NOT_SPEAKERS)
    speakers = turns.groupBy(F.col("conv_id").alias("conv")).agg(
        F.array_sort(F.collect_set(F.when(~system, F.col("role")))).alias("speakers"),
        F.min(F.when(system & F.col("turn").isNotNull(), F.struct("turn", "role", "text"))).alias("first"),
        F.ceil(F.count(F.when(F.col("turn").isNull(), 1)) / PART).alias("loose"),
    )
    speakers = speakers.where(F.size("speakers") > 0)
    known = turns.join(speakers.select(F.col("conv").alias("c"), "loose").where("loose > 1"), F.col("conv_id").eqNullSafe(F.col("c")), "left")
    loose = -1 - F.pmod(F.xxhash64("role", "text"), F.coalesce("loose", F.lit(1)))
    part = F.coalesce(F.floor(F.col("turn") / PART), loose).cast("long")
    parts = known.groupBy("conv_id", part.alias("part")).agg(F.sort_array(F.collect_list(F.struct("turn", "role", "text"))).alias("turns"))
    keyed = parts.join(speakers, F.col("conv_id").eqNullSafe(F.col("conv")))
    has = F.col("first").isNull() | F.array_contains("turns", F.col("first"))
    rotated = keyed.select("conv_id", F.explode("speakers").alias("speaker"), "part", F.size("turns").alias("n_turns"), F.when(has, F.col("turns")).otherwise(F.concat(F.array("first"), "turns")).alias("turns"))
    segments = F.transform("turns", lambda t: _segment(t, F.col("speaker")))
    cut = rotated.select("conv_id", "speaker", "part", "n_turns", segments.alias("segments"))
    empty = F.expr("cast(array() as array<struct<start:int,end:int>>)")
    mask = F.aggregate("segments", F.struct(F.lit(0).alias("at"), empty.alias("spans")), _masked, lambda acc: acc["spans"])
    rendered = F.array_join(F.transform("segments", lambda s: F.concat(s["head"], s["body"])), "")
    return cut.select("conv_id", "speaker", "part", "n_turns", rendered.alias("rendered"), mask.alias("mask"))


def _segment(turn: Column, speaker: Column) -> Column:
    role = F.when(turn["role"] == speaker, F.lit("assistant")).when(turn["role"].isin(*NOT_SPEAKERS), turn["role"]).otherwise(F.concat(F.lit("user name="), _name(turn["role"])))
    return F.struct(F.concat(F.lit(START), role, F.lit("\n")).alias("head"), F.concat(_harmless(turn["text"]), F.lit(END)).alias("body"), (turn["role"] == speaker).alias("own"))


def _masked(acc: Column, s: Column) -> Column:
    start = acc["at"] + F.char_length(s["head"])
    end = start + F.char_length(s["body"])
    return F.struct(end.alias("at"), F.when(s["own"], F.concat(acc["spans"], F.array(F.struct(start.alias("start"), end.alias("end"))))).otherwise(acc["spans"]).alias("spans"))


def mask_string(mask: Column) -> Column:
    return F.array_join(F.transform(mask, lambda m: F.concat_ws("-", m["start"].cast("string"), m["end"].cast("string"))), ",")
