"""Preference pairs: one prompt, two masked completions, with DataFrame functions only.

Chosen and rejected conversations of one pair share a first part. The longest common
prefix of turns (same role, same text) is rendered once as the prompt; what follows on
either side is a completion whose turns carry a mask, 1 for turns of the assistant that a
model learns and 0 for the others.

Defined results: turns are taken in order of (turn, role, text), nulls first, and null
role or text count as empty; repeated rows are repeated turns; identical conversations
have empty completions; a side without rows is an empty conversation; extra columns are
not read. A conversation is one training example and is rendered in one row.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

OPEN, CLOSE, LEARNED = "<|im_start|>", "<|im_end|>\n", "assistant"


def conversation(turns: DataFrame, pair_col: str, name: str) -> DataFrame:
    row = F.struct(F.col("turn"), F.coalesce(F.col("role"), F.lit("")).alias("role"), F.coalesce(F.col("text"), F.lit("")).alias("text"))
    return turns.groupBy(F.col(pair_col).alias("pair_id")).agg(F.sort_array(F.collect_list(row)).alias(name))


def rendered(turn: Column) -> Column:
    return F.concat(F.lit(OPEN), turn["role"], F.lit("\n"), turn["text"], F.lit(CLOSE))


def common_turns(a: Column, b: Column) -> Column:
    """Number of turns until the first that differs."""
    most = F.least(F.size(a), F.size(b))
    differs = F.filter(F.sequence(F.lit(0), most), lambda i: (i >= most) | (F.get(a, i)["role"] != F.get(b, i)["role"]) | (F.get(a, i)["text"] != F.get(b, i)["text"]))
    return F.get(differs, 0)


def preference_pairs(chosen: DataFrame, rejected: DataFrame, pair_col: str = "pair_id") -> DataFrame:
    """pair_id, n_prompt_turns, prompt, chosen, rejected, and the masks as arrays of
    (length in characters, learned 0/1), one entry per turn of the completion."""
    both = conversation(chosen, pair_col, "c").join(conversation(rejected, pair_col, "r"), "pair_id", "full")
    none = F.array().cast("array<struct<turn:bigint,role:string,text:string>>")
    both = both.select("pair_id", *[F.coalesce(F.col(x).cast("array<struct<turn:bigint,role:string,text:string>>"), none).alias(x) for x in ("c", "r")])
    both = both.withColumn("n", common_turns(F.col("c"), F.col("r")))

    def text(x: str, first: Column, n: Column) -> Column:
        return F.array_join(F.transform(F.slice(x, first, n), rendered), "")

    def mask(x: str) -> Column:
        rest = F.slice(x, F.col("n") + 1, F.size(x))
        return F.transform(rest, lambda t: F.struct(F.length(rendered(t)).alias("chars"), (t["role"] == LEARNED).cast("int").alias("learned")))

    return both.select(
        F.col("pair_id"), F.col("n").alias("n_prompt_turns"), text("c", F.lit(1), F.col("n")).alias("prompt"),
        text("c", F.col("n") + 1, F.size("c")).alias("chosen"), text("r", F.col("n") + 1, F.size("r")).alias("rejected"),
        mask("c").alias("chosen_mask"), mask("r").alias("rejected_mask"),
    )


def swapped_replies(turns: DataFrame) -> tuple[DataFrame, DataFrame]:
    """Chosen and rejected turns from plain conversations: the chosen side ends with the
    conversation's last assistant turn; the rejected side has in its place the last
    assistant text of the neighbouring conversation (``conv_id`` with its last bit
    turned), or nothing where that has none. Conversations without an assistant turn
    stand on both sides as they are."""
    said = turns.filter(F.col("role") == LEARNED)
    last = said.groupBy("conv_id").agg(F.max(F.struct("turn", F.coalesce("text", F.lit("")).alias("text"))).alias("s"))
    ends = last.select("conv_id", F.col("s.turn").alias("end"))
    other = last.select(F.col("conv_id").bitwiseXOR(F.lit(1)).alias("conv_id"), F.col("s.text").alias("swap"))
    whole = turns.select("conv_id", "turn", "role", "text").join(ends, "conv_id", "left").join(other, "conv_id", "left")
    upto = whole.filter("end IS NULL OR turn <= end")
    chosen = upto.select(F.col("conv_id").alias("pair_id"), "turn", "role", "text")
    at_end = (F.col("turn") == F.col("end")) & (F.col("role") == LEARNED)
    kept = upto.filter(F.coalesce(~at_end | F.col("swap").isNotNull(), F.lit(True)))
    rejected = kept.select(F.col("conv_id").alias("pair_id"), "turn", "role", F.when(at_end, F.col("swap")).otherwise(F.col("text")).alias("text"))
    return chosen, rejected
