"""Preference formatting of conversations, in DataFrame functions only.

Input: turns ``(pair_id, side, turn, role, text)`` with side 0 = chosen and 1 =
rejected.  The longest common prefix of turns becomes the prompt, rendered once;
what follows is rendered for each side with the character spans that a loss should
see (assistant turns; everything else is masked).

Defined results: null role counts as ``user``, null text as empty; turns are
ordered by (turn, role, text), nulls first, so ties and repeated rows have one
order and all stay; a pair with one side only gives an empty prompt, that side's
completion and a null for the other; null pair ids or sides take no part; two equal
conversations give empty completions and ``differs`` false; very long texts are rendered
whole, all turns of a pair in one row; an empty table gives no rows; other columns are
not read.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

# The marks of the rendered form.
OPEN, MIDDLE, CLOSE = "<|", "|>\n", "<|end|>\n"
TRAINED_ROLE = "assistant"


def _render(turns: Column) -> Column:
    parts = F.transform(
        turns, lambda t: F.concat(F.lit(OPEN), t["role"], F.lit(MIDDLE), t["text"], F.lit(CLOSE))
    )
    return F.array_join(parts, "")


def _spans(turns: Column) -> Column:
    """[start, end) of each trained text within the rendered completion, in characters."""
    head = lambda t: F.lit(len(OPEN) + len(MIDDLE)) + F.length(t["role"])
    state = F.aggregate(
        turns,
        F.struct(
            F.lit(0).cast("long").alias("at"),
            F.array().cast("array<struct<start:bigint,end:bigint>>").alias("spans"),
        ),
        lambda s, t: F.struct(
            (s["at"] + head(t) + F.length(t["text"]) + F.lit(len(CLOSE))).cast("long").alias("at"),
            F.when(
                t["role"] == F.lit(TRAINED_ROLE),
                F.array_append(
                    s["spans"],
                    F.struct(
                        (s["at"] + head(t)).cast("long").alias("start"),
                        (s["at"] + head(t) + F.length(t["text"]) + F.lit(len(CLOSE))).cast("long").alias("end"),
                    ),
                ),
            ).otherwise(s["spans"]).alias("spans"),
        ),
    )
    return state["spans"]


def preference_pairs(turns: DataFrame) -> DataFrame:
    """One row per pair: prompt, both completions, their trained spans."""
    turn = F.struct(
        F.col("turn").alias("turn"),
        F.coalesce(F.col("role"), F.lit("user")).alias("role"),
        F.coalesce(F.col("text"), F.lit("")).alias("text"),
    )
    both = (
        turns.filter(F.col("pair_id").isNotNull() & F.col("side").isin(0, 1))
        .groupBy("pair_id")
        .agg(
            F.sort_array(F.collect_list(F.when(F.col("side") == 0, turn))).alias("c"),
            F.sort_array(F.collect_list(F.when(F.col("side") == 1, turn))).alias("r"),
        )
    )
    same = F.zip_with(
        F.col("c"), F.col("r"),
        lambda a, b: F.coalesce((a["role"] == b["role"]) & (a["text"] == b["text"]), F.lit(False)),
    )
    split = both.withColumn("__same", same).withColumn(
        "n_prompt_turns",
        F.expr("CASE WHEN array_position(__same, false) = 0 THEN size(__same) "
               "ELSE cast(array_position(__same, false) as int) - 1 END"),
    )
    tail = lambda k: F.slice(F.col(k), F.col("n_prompt_turns") + 1, F.size(F.col(k)))
    # An absent side keeps null; slice() needs a positive length, so sizes of 0 never reach it.
    split = split.withColumns(
        {
            "__p": F.when(F.col("n_prompt_turns") > 0, F.slice(F.col("c"), F.lit(1), F.col("n_prompt_turns"))).otherwise(
                F.slice(F.col("c"), 1, 0)
            ),
            "__c": F.when(F.size("c") > 0, tail("c")),
            "__r": F.when(F.size("r") > 0, tail("r")),
        }
    )
    return split.select(
        "pair_id",
        F.col("n_prompt_turns").cast("long").alias("n_prompt_turns"),
        _render(F.col("__p")).alias("prompt"),
        _render(F.col("__c")).alias("chosen"),
        _render(F.col("__r")).alias("rejected"),
        _spans(F.col("__c")).alias("chosen_spans"),
        _spans(F.col("__r")).alias("rejected_spans"),
        F.coalesce(F.col("__c") != F.col("__r"), F.lit(True)).alias("differs"),
    )


def pair_neighbours(conversations: DataFrame) -> DataFrame:
    """Conversation 2p is the chosen side of pair p and 2p + 1 the rejected one."""
    return conversations.select(
        F.expr("conv_id div 2").alias("pair_id"),
        F.pmod(F.col("conv_id"), F.lit(2)).cast("int").alias("side"),
        "turn", "role", "text",
    )


def op2_preference_format(conversations: DataFrame) -> DataFrame:
    """Preference rows of the whole table; masks are the trained spans, ``start-end`` joined by commas."""
    mask = lambda k: F.array_join(F.transform(F.col(k), lambda s: F.concat_ws("-", s["start"], s["end"])), ",")
    total = lambda k: F.aggregate(F.col(k), F.lit(0).cast("long"), lambda a, s: a + s["end"] - s["start"])
    return preference_pairs(pair_neighbours(conversations)).select(
        "pair_id", "n_prompt_turns", "prompt", "chosen", "rejected",
        total("chosen_spans").alias("chosen_trained_chars"),
        total("rejected_spans").alias("rejected_trained_chars"),
        mask("chosen_spans").alias("chosen_mask"), mask("rejected_spans").alias("rejected_mask"),
    )
