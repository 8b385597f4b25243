"""Preference formatting: shared turns once as prompt, then two masked completions.

A pair has a chosen and a rejected conversation.  Their longest common prefix of
turns (equal role and text at every turn number) is the prompt; what follows on
each side is a completion, in which the assistant's text and its end mark carry
loss and everything else is masked.

Rows of both sides meet in one aggregate that says which sides hold them; the first
turn with a row of one side only ends the prefix.  No task needs a conversation as a
whole: the first difference of a pair is a minimum with partial sums, it comes back
to the turns by a join (which AQE splits where one pair holds most turns), and the
text is rendered in segments of ``SEGMENT`` turn numbers, so a conversation with a
third of all turns is many rows.  One under ``SEGMENT`` turns is one row for each part.

Null role counts as '', null text as empty, a null turn as before all others.
Equal rows count once; different rows with one turn number follow by role and
text, and a turn number is common only if both sides have the same rows there.
Pairs with a null id or one side only are rendered with an empty other side.  Texts
are taken whole; a segment's text is one string in memory.  Empty tables give no
rows; other columns, whatever their names, are not looked at.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

SEGMENT = 256
OPEN, MIDDLE, CLOSE = "<|", "|>\n", "<|end|>\n"


def turns_of(conversations: DataFrame, pair, chosen, rejected) -> DataFrame:
    """pair_id, turn, role, text with nulls replaced, and which sides hold the row."""
    return conversations.select(
        pair.alias("pair_id"),
        F.coalesce(F.col("turn").cast("long"), F.lit(-1)).alias("turn"),
        F.coalesce(F.col("role").cast("string"), F.lit("")).alias("role"),
        F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"),
        chosen.alias("chosen"),
        rejected.alias("rejected"),
    )


def format_preferences(chosen: DataFrame, rejected: DataFrame) -> DataFrame:
    """pair_id, part ('prompt', 'chosen', 'rejected'), segment, n_turns, text, loss_spans.

    Both inputs have pair_id, turn, role, text.  ``loss_spans`` are start-end
    character ranges of ``text`` that carry loss, joined by commas.
    """
    yes, no = F.lit(True), F.lit(False)
    return rendered_sides(turns_of(chosen, F.col("pair_id"), yes, no).unionByName(turns_of(rejected, F.col("pair_id"), no, yes)))


def rendered_sides(rows: DataFrame) -> DataFrame:
    """The same from rows that say which sides hold them (``chosen``, ``rejected``)."""
    held = rows.groupBy("pair_id", "turn", "role", "text").agg(F.bool_or("chosen").alias("c"), F.bool_or("rejected").alias("r"))
    split = held.where("c <> r").groupBy("pair_id").agg(F.min("turn").alias("split")).withColumnRenamed("pair_id", "_pair")
    marked = held.join(split, F.col("pair_id").eqNullSafe(F.col("_pair")), "left")
    shared = F.col("split").isNull() | (F.col("turn") < F.col("split"))
    sides = F.filter(F.array(F.when(F.col("c"), F.lit("chosen")), F.when(F.col("r"), F.lit("rejected"))), lambda x: x.isNotNull())
    parts = marked.withColumn("part", F.explode(F.when(shared, F.array(F.lit("prompt"))).otherwise(sides)))
    head = F.concat(F.lit(OPEN), F.col("role"), F.lit(MIDDLE))
    rendered = F.concat(head, F.col("text"), F.lit(CLOSE))
    segments = (
        parts.select(
            "pair_id",
            "part",
            F.floor(F.col("turn") / F.lit(SEGMENT)).cast("long").alias("segment"),
            F.struct(
                "turn",
                "role",
                "text",
                rendered.alias("shown"),
                F.char_length(head).cast("long").alias("head"),
                F.char_length(rendered).cast("long").alias("size"),
                ((F.col("part") != "prompt") & (F.col("role") == "assistant")).alias("loss"),
            ).alias("t"),
        )
        .groupBy("pair_id", "part", "segment")
        .agg(F.sort_array(F.collect_list("t")).alias("ts"))
    )
    spans = F.aggregate(
        "ts",
        F.struct(F.lit(0).cast("long").alias("at"), F.array().cast("array<string>").alias("spans")),
        lambda acc, t: F.struct(
            (acc["at"] + t["size"]).alias("at"),
            F.when(t["loss"], F.array_append(acc["spans"], F.concat_ws("-", acc["at"] + t["head"], acc["at"] + t["size"]))).otherwise(acc["spans"]).alias("spans"),
        ),
        lambda acc: F.array_join(acc["spans"], ","),
    )
    return segments.select("pair_id", "part", "segment", F.size("ts").cast("long").alias("n_turns"), F.array_join(F.transform("ts", lambda t: t["shown"]), "").alias("text"), spans.alias("loss_spans"))


def stale_answer_sides(conversations: DataFrame) -> DataFrame:
    """Rows of both sides made from plain conversations, for ``rendered_sides``.

    The chosen side is the conversation up to its last assistant turn; the rejected
    side is the same with that turn's text taken from the conversation whose id
    differs in the lowest bit, where there is one (else it is empty).  Rows without
    id or turn, and conversations without an assistant turn, form no pair.
    """
    c = conversations.select(F.col("conv_id").cast("long").alias("pair_id"), F.col("turn").cast("long").alias("turn"), "role", "text").where("pair_id is not null and turn is not null")
    text = F.coalesce("text", F.lit(""))
    last = c.where("role = 'assistant'").groupBy("pair_id").agg(F.max(F.struct("turn", text.alias("answer"))).alias("last"))
    # each conversation gives its last turn to itself and its answer to its neighbour: one small aggregate, no self-join
    own = F.struct(F.col("pair_id").alias("to"), F.col("last.turn").alias("last_turn"), F.lit(None).cast("string").alias("stale"))
    other = F.struct(F.col("pair_id").bitwiseXOR(F.lit(1).cast("long")).alias("to"), F.lit(None).cast("long").alias("last_turn"), F.col("last.answer").alias("stale"))
    ends = last.select(F.inline(F.array(own, other))).groupBy("to").agg(F.max("last_turn").alias("last_turn"), F.max("stale").alias("stale")).where("last_turn is not null")
    known = c.join(ends, F.col("pair_id") == F.col("to")).where("turn <= last_turn")
    swapped = (F.col("turn") == F.col("last_turn")) & F.coalesce(F.col("role") == "assistant", F.lit(False))
    yes, no = F.lit(True), F.lit(False)
    kept = F.struct(F.col("text").alias("text"), yes.alias("chosen"), (~swapped).alias("rejected"))
    stale = F.struct(F.coalesce("stale", F.lit("")).alias("text"), no.alias("chosen"), yes.alias("rejected"))
    both = known.select("pair_id", "turn", "role", F.inline(F.when(swapped, F.array(kept, stale)).otherwise(F.array(kept))))
    return turns_of(both, F.col("pair_id"), F.col("chosen"), F.col("rejected"))
