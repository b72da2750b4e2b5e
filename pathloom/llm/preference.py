"""Preference formatting: the longest common turn prefix once as prompt, and two completions with loss masks.

Input: one row for each pair, with two arrays of turns (role, text). Turns are equal if role and text are. The common prefix is the
prompt; what follows in each conversation is its completion, rendered with the same template. A mask lists the character ranges
[begin, end) of the completion that count in the loss: texts and end marks of turns by the answering role.

preference_pairs() makes pairs from a table of turns: chosen is a conversation up to its last answer, rejected the same with that
answer exchanged for the last answer of the partner, the conversation whose id differs in the lowest bit.

Defined results: null role or text renders as empty. Rows without conv_id are left out of pairs. Turns of equal number stand in the order of
role and text; repeated rows are turns of their own. A conversation without an answer, or without a partner that has one, gives no pair.
Equal conversations have an empty completion and mask on both sides. Empty tables give empty results. Other columns are ignored.
One conversation is one row of the result, so its turns meet in one task; no other group is gathered.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

ANSWERS = "assistant"
BEGIN, MIDDLE, END = "<|", "|>\n", "<|end|>\n"


def gathered(turns: DataFrame) -> DataFrame:
    """conv_id, turns: array of (role, text) in order."""
    row = F.struct(F.col("turn"), F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text"))
    grouped = turns.filter(F.col("conv_id").isNotNull()).groupBy("conv_id").agg(F.array_sort(F.collect_list(row)).alias("_turns"))
    return grouped.select("conv_id", F.transform("_turns", lambda t: F.struct(t["role"].alias("role"), t["text"].alias("text"))).alias("turns"))


def preference_pairs(turns: DataFrame, answers: str = ANSWERS) -> DataFrame:
    """pair_id, chosen, rejected."""
    answered = F.transform("turns", lambda t: t["role"] == answers)
    last = F.size("turns") - F.array_position(F.reverse(answered), True).cast("int") + 1
    ready = gathered(turns).filter(F.exists("turns", lambda t: t["role"] == answers)).withColumn("_last", last)
    ready = ready.select("conv_id", F.slice("turns", 1, F.col("_last") - 1).alias("_context"), F.element_at("turns", F.col("_last")).alias("_answer"))
    partner = ready.select(F.col("conv_id").bitwiseXOR(F.lit(1)).alias("conv_id"), F.col("_answer").alias("_other"))
    return ready.join(partner, "conv_id").select(F.col("conv_id").alias("pair_id"), F.array_append("_context", F.col("_answer")).alias("chosen"), F.array_append("_context", F.col("_other")).alias("rejected"))


def common_prefix(a: Column, b: Column) -> Column:
    """Number of leading turns that both arrays share."""
    shorter = F.least(F.size(a), F.size(b))
    same = F.zip_with(F.slice(a, 1, shorter), F.slice(b, 1, shorter), lambda x, y: x == y)
    first = F.array_position(same, False).cast("int")
    return F.when(first > 0, first - 1).otherwise(shorter)


def rendered(turns: Column) -> Column:
    return F.array_join(F.transform(turns, lambda t: F.concat(F.lit(BEGIN), t["role"], F.lit(MIDDLE), t["text"], F.lit(END))), "")


def loss_mask(turns: Column, answers: str = ANSWERS) -> Column:
    """Ranges of the rendered turns that count in the loss."""
    empty = F.array().cast("array<struct<begin:int,end:int>>")
    start = F.struct(F.lit(0).alias("at"), empty.alias("spans"))

    def step(acc: Column, t: Column) -> Column:
        begin = acc["at"] + F.length(t["role"]) + len(BEGIN) + len(MIDDLE)
        end = begin + F.length(t["text"]) + len(END)
        span = F.array(F.struct(begin.alias("begin"), end.alias("end")))
        return F.struct(end.alias("at"), F.when(t["role"] == answers, F.concat(acc["spans"], span)).otherwise(acc["spans"]).alias("spans"))

    return F.aggregate(turns, start, step, lambda acc: acc["spans"])


def format_preferences(pairs: DataFrame, answers: str = ANSWERS) -> DataFrame:
    """pair_id, n_prompt_turns, prompt, chosen, chosen_mask, rejected, rejected_mask."""
    cut = pairs.withColumn("_n", common_prefix(F.col("chosen"), F.col("rejected")))
    after = lambda side: F.slice(side, F.col("_n") + 1, F.size(side))
    return cut.select(
        "pair_id", F.col("_n").alias("n_prompt_turns"), rendered(F.slice("chosen", 1, F.col("_n"))).alias("prompt"),
        rendered(after("chosen")).alias("chosen"), loss_mask(after("chosen"), answers).alias("chosen_mask"),
        rendered(after("rejected")).alias("rejected"), loss_mask(after("rejected"), answers).alias("rejected_mask"),
    )
