"""Chat formatting by multi-party perspective rotation.

Every participant of a conversation becomes the assistant once; all others are users under
their own names, and only the assistant's turns bear loss. ``perspectives`` renders every dialogue
turn by turn: each segment knows where it starts in its dialogue, and the segments of a
(conversation, perspective) joined end to end are the dialogue's text. ``dialogues`` joins them.

Offsets are running sums in two levels, over chunks of consecutive turns and inside a chunk, and
turns meet participants by chunk, so that no task gets all turns of a long conversation.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window

from .common import whole

#: Turn numbers in a chunk.
CHUNK = 256
#: Characters that a name shows as a per cent sign and their number, the sign itself first.
_ESCAPED = {"%": "%25", "|": "%7C", "<": "%3C", ">": "%3E", "\n": "%0A"}


def escaped_name(name: Column) -> Column:
    """A name that cannot end or forge a head."""
    for sign, shown in _ESCAPED.items():
        name = F.replace(name, F.lit(sign), F.lit(shown))
    return name


def escaped_text(text: Column) -> Column:
    """A text that cannot forge a mark: one more bar after every ``<|``; taking it out gives the text back."""
    return F.replace(text, F.lit("<|"), F.lit("<||"))


def _head(role: str, name: Column | None = None) -> Column:
    return F.lit(f"<|{role}|>\n") if name is None else F.concat(F.lit(f"<|{role} name="), escaped_name(name), F.lit("|>\n"))


def perspectives(turns: DataFrame) -> DataFrame:
    """One row per turn and participant of its conversation, with that participant as assistant.

    (conv_id, assistant, turn, role, name, segment, mask_start, mask_end, dialogue_start):
    ``segment`` is the rendered turn, which starts at code point ``dialogue_start`` of the dialogue;
    code points of the segment from mask_start up to mask_end bear loss (both zero where none
    do). ``role`` is assistant, user or system; ``name`` is the speaker of a user turn. A dialogue is in
    order of turn, then speaker, then text. Turns of the role ``system`` are context in
    every perspective and no participant. A null role is the participant ``unknown``, a null text is
    empty, rows with null conv_id are one conversation, null turns come first; repeated rows and
    equal turn numbers are turns of their own. Marks inside texts and names are escaped. A conversation
    without participants has no rows. An empty table gives an empty result; other columns are ignored.
    """
    key = [F.coalesce(F.col("conv_id").cast("string"), F.lit("")).alias("c"), F.col("conv_id").isNull().alias("c0")]
    named = turns.select(
        "conv_id", *key, "turn", F.coalesce(F.expr(f"floor(turn / {CHUNK})"), F.lit(-(1 << 62))).alias("chunk"),
        F.coalesce(F.col("role"), F.lit("unknown")).alias("speaker"), escaped_text(whole()).alias("text"),
    )
    system = F.col("speaker") == "system"
    as_other = F.when(system, _head("system")).otherwise(_head("user", F.col("speaker")))
    end = "\n<|end|>\n"
    # characters and turns by chunk and speaker, all speakers taken as users
    by_speaker = named.groupBy("c", "c0", "chunk", "speaker").agg(
        F.sum(F.length(as_other) + F.length("text") + len(end)).alias("chars"), F.count("*").alias("n")
    )
    cast = by_speaker.where(~system).select("c", "c0", F.col("speaker").alias("assistant")).distinct()
    chunks = by_speaker.groupBy("c", "c0", "chunk").agg(F.sum("chars").alias("chars"))
    own = by_speaker.select("c", "c0", "chunk", F.col("speaker").alias("assistant"), "n")
    shorter = F.length(_head("assistant")) - F.length(_head("user", F.col("assistant")))
    earlier = Window.partitionBy("c", "c0", "assistant").orderBy("chunk").rowsBetween(Window.unboundedPreceding, -1)
    bases = (
        chunks.join(cast, ["c", "c0"])
        .join(own, ["c", "c0", "chunk", "assistant"], "left")
        .withColumn("base", F.coalesce(F.sum(F.col("chars") + F.coalesce("n", F.lit(0)) * shorter).over(earlier), F.lit(0)))
        .select("c", "c0", "chunk", "assistant", "base")
    )
    loss = F.col("speaker") == F.col("assistant")
    role = F.when(system, "system").when(loss, "assistant").otherwise("user")
    before = Window.partitionBy("c", "c0", "chunk", "assistant").orderBy("turn", "speaker", "text").rowsBetween(Window.unboundedPreceding, -1)
    rotated = (
        named.join(bases, ["c", "c0", "chunk"])
        .withColumn("head", F.when(loss, _head("assistant")).otherwise(as_other))
        .withColumn("segment", F.concat("head", "text", F.lit(end)))
        .withColumn("dialogue_start", F.col("base") + F.coalesce(F.sum(F.length("segment")).over(before), F.lit(0)))
    )
    return rotated.select(
        "conv_id",
        "assistant",
        "turn",
        role.alias("role"),
        F.when(~system & ~loss, F.col("speaker")).alias("name"),
        "segment",
        F.when(loss, F.length("head")).otherwise(0).cast("long").alias("mask_start"),
        F.when(loss, F.length("segment") - 1).otherwise(0).cast("long").alias("mask_end"),
        F.col("dialogue_start").cast("long").alias("dialogue_start"),
    )


def dialogues(turns: DataFrame) -> DataFrame:
    """(conv_id, assistant, text, masks): whole dialogues with the stretches that bear loss.

    A row holds a whole dialogue, so conversations must fit a row; ``perspectives`` has no such
    bound. masks: (start, end) in code points of ``text``, in order.
    """
    place = F.struct("dialogue_start", "segment", "mask_start", "mask_end")
    gathered = perspectives(turns).groupBy("conv_id", "assistant").agg(F.array_sort(F.collect_list(place)).alias("parts"))
    masks = F.transform(
        F.filter("parts", lambda p: p["mask_end"] > 0),
        lambda p: F.struct((p["dialogue_start"] + p["mask_start"]).alias("start"), (p["dialogue_start"] + p["mask_end"]).alias("end")),
    )
    return gathered.select("conv_id", "assistant", F.array_join("parts.segment", "").alias("text"), masks.alias("masks"))
