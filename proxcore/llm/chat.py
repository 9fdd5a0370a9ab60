"""Chat formatting by perspective rotation: each dialogue is rendered once for every participant, with that speaker as
the assistant and all others as named users; the mask covers the assistant's words and their end marks.

A dialogue is rendered whole, as consecutive chunks of `chunk_turns` turn numbers, so that no group grows with a
conversation: the chunks of a perspective joined in order of `start` are the whole rendering. `start` is the characters
that come before a chunk, and masks count from the start of the whole. `context` has the dialogue's system turns of its first
chunk, rendered, for use before a later chunk that is taken alone; it is empty in the first one.

Defined results: exact repeats of a turn count once; turns of one number are ordered by role, then text; a null role is a
speaker of its own, a null text is empty; null turn numbers come first and form a chunk; a turn with a null conversation
is a dialogue by itself; names are escaped as in XML, so that two speakers never become one, and a null role is "&null;";
system turns are context and have no perspective; a dialogue of system turns alone gives no row; marks within a text are
broken up, so that a text can't open a turn of its own.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

OPEN, CLOSE, SYSTEM = "<|im_start|>", "<|im_end|>", "system"


def _segment(turn: Column, speaker: Column) -> Column:
    """head, body: text without and with the mask, if the speaker is the assistant's."""
    own = turn["role"] == speaker
    head = F.when(own, F.lit(f"{OPEN}assistant\n")).when(turn["role"] == SYSTEM, F.lit(f"{OPEN}system\n")).otherwise(F.concat(F.lit(f"{OPEN}user name="), turn["role"], F.lit("\n")))
    return F.struct(own.alias("own"), head.alias("head"), F.concat(turn["text"], F.lit(CLOSE)).alias("body"))


def chunks(turns: DataFrame, *, conv: str = "conv_id", turn: str = "turn", role: str = "role", text: str = "text", chunk_turns: int = 64) -> DataFrame:
    """One row for each chunk of a dialogue (dialogue, conv_id, chunk), with its turns in order."""
    clean = turns.select(
        F.col(conv).alias("conv_id"), F.col(turn).cast("bigint").alias("turn"), _escaped(F.col(role)).alias("role"),
        F.replace(F.coalesce(text, F.lit("")), F.lit("<|"), F.lit("< |")).alias("text"),
    ).withColumn("chunk", F.floor(F.col("turn") / chunk_turns))
    alone = F.concat(F.lit("turn "), F.md5(F.to_json(F.struct("turn", "role", "text"))))
    clean = clean.withColumn("dialogue", F.coalesce(F.concat(F.lit("conversation "), F.col("conv_id").cast("string")), alone))
    return clean.groupBy("dialogue", "conv_id", "chunk").agg(F.sort_array(F.collect_set(F.struct(F.coalesce("turn", F.lit(-(2**62))).alias("turn"), "role", "text"))).alias("turns"))


def _escaped(role: Column) -> Column:
    out = role
    for plain, code in (("&", "&amp;"), ("<", "&lt;"), (">", "&gt;"), ("|", "&#124;"), ("\n", "&#10;")):
        out = F.replace(out, F.lit(plain), F.lit(code))
    return F.coalesce(out, F.lit("&null;"))


def rotate(turns: DataFrame, **how: object) -> DataFrame:
    """conv_id, chunk, speaker, n_turns, start, context, rendered, mask (half-open character spans of the whole rendering),
    n_mask_chars."""
    grouped = chunks(turns, **how)
    who = grouped.select(F.col("dialogue").alias("of"), F.explode(F.array_distinct(F.col("turns.role"))).alias("speaker")).where(F.col("speaker") != SYSTEM).distinct()
    both = grouped.join(who, F.col("dialogue") == F.col("of")).drop("of")
    parts = both.withColumn("parts", F.transform("turns", lambda t: _segment(t, F.col("speaker"))))
    size = F.aggregate("parts", F.lit(0).cast("bigint"), lambda n, p: n + F.length(p["head"]) + F.length(p["body"]) + 1)
    # the window holds sizes alone; chunks of one perspective are few beside the turns in them
    sizes = parts.select(F.col("dialogue").alias("d"), F.col("speaker").alias("s"), F.col("chunk").alias("c"), size.alias("size"))
    starts = sizes.withColumn("start", F.coalesce(F.sum("size").over(Window.partitionBy("d", "s").orderBy("c").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))).drop("size")
    system = F.filter("turns", lambda t: t["role"] == SYSTEM)
    first = grouped.groupBy(F.col("dialogue").alias("g")).agg(F.min_by(F.struct("chunk", system.alias("turns")), F.struct(F.col("chunk").isNotNull(), "chunk")).alias("first"))
    context = F.concat_ws("", F.transform("first.turns", lambda t: F.concat(F.lit(f"{OPEN}system\n"), t["text"], F.lit(f"{CLOSE}\n"))))
    parts = parts.join(starts, (F.col("dialogue") == F.col("d")) & (F.col("speaker") == F.col("s")) & F.col("chunk").eqNullSafe(F.col("c"))).drop("d", "s", "c")
    parts = parts.join(first, F.col("dialogue") == F.col("g")).withColumn("context", F.when(F.col("chunk").eqNullSafe(F.col("first.chunk")), F.lit("")).otherwise(context))
    empty = F.struct(F.col("start").alias("at"), F.array().cast("array<struct<start:bigint,end:bigint>>").alias("spans"))

    def extend(state: Column, p: Column) -> Column:
        start = state["at"] + F.length(p["head"])
        end = start + F.length(p["body"])
        return F.struct((end + 1).alias("at"), F.when(p["own"], F.concat(state["spans"], F.array(F.struct(start.alias("start"), end.alias("end"))))).otherwise(state["spans"]).alias("spans"))

    return parts.select(
        "conv_id", "chunk", "speaker", F.size("turns").cast("bigint").alias("n_turns"), "start", "context",
        F.concat_ws("", F.transform("parts", lambda p: F.concat(p["head"], p["body"], F.lit("\n")))).alias("rendered"),
        F.aggregate("parts", empty, extend, lambda s: s["spans"]).alias("mask"),
    ).withColumn("n_mask_chars", F.aggregate("mask", F.lit(0).cast("bigint"), lambda n, s: n + s["end"] - s["start"]))
