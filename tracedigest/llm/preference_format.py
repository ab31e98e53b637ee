"""Preference formatting. DataFrame functions only.

Input: one row per pair with the turns of a chosen and a rejected conversation, as arrays of (role, text). The longest
common turn prefix is found (position of the first turn that differs), rendered once as the prompt, and both
remainders are rendered as completions with masks: character spans of the assistant's words, the only ones trained on.
A long conversation costs its length; a pair is one row, so nothing is collected across pairs.

A null array counts as empty. A null role is `unknown`, a null text is empty; both nulls of the two sides compare equal. No common turn: an
empty prompt. Alike conversations: everything is prompt, both completions are empty.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: How a turn is rendered.
OPEN, MIDDLE, CLOSE = "<|", "|>\n", "\n<|end|>\n"
TURN = "struct<role:string,text:string>"


def conversations(turns: DataFrame, conv_col: str = "conv_id", turn_col: str = "turn", role_col: str = "role", text_col: str = "text") -> DataFrame:
    """conv, turns in order: one row per conversation. Rows repeated whole count once; a null conversation id is left out; a null
    turn number comes first."""
    own = turns.select(F.col(conv_col).alias("conv"), F.col(turn_col).alias("turn"), F.coalesce(F.col(role_col), F.lit("unknown")).alias("role"), F.coalesce(F.col(text_col), F.lit("")).alias("text"))
    own = own.filter(F.col("conv").isNotNull()).distinct()
    return own.groupBy("conv").agg(F.sort_array(F.collect_list(F.struct("turn", "role", "text"))).alias("t")).select("conv", F.transform("t", lambda x: F.struct(x["role"].alias("role"), x["text"].alias("text"))).alias("turns"))


def rendered(turns: Column) -> Column:
    return F.array_join(F.transform(turns, lambda x: F.concat(F.lit(OPEN), x["role"], F.lit(MIDDLE), x["text"], F.lit(CLOSE))), "")


def mask(turns: Column) -> Column:
    """array<struct<a,b>>: where the assistant's texts stand in the rendered turns, with their closing marks."""
    start = F.struct(F.lit(0).alias("at"), F.expr("cast(array() as array<struct<a:int,b:int>>)").alias("out"))

    def step(held: Column, x: Column) -> Column:
        a = held["at"] + len(OPEN) + F.length(x["role"]) + len(MIDDLE)
        b = a + F.length(x["text"]) + len(CLOSE)
        span = F.array(F.struct(a.alias("a"), b.alias("b")))
        return F.struct(b.alias("at"), F.when(x["role"] == "assistant", F.concat(held["out"], span)).otherwise(held["out"]).alias("out"))

    return F.aggregate(turns, start, step, lambda held: held["out"])


def format_pairs(pairs: DataFrame, id_col: str = "pair_id", chosen_col: str = "chosen", rejected_col: str = "rejected") -> DataFrame:
    """pair_id, n_prefix, prompt, chosen, rejected, chosen_mask, rejected_mask."""
    none = F.expr(f"cast(array() as array<{TURN}>)")
    clean = lambda c: F.transform(F.coalesce(F.col(c), none), lambda x: F.struct(F.coalesce(x["role"], F.lit("unknown")).alias("role"), F.coalesce(x["text"], F.lit("")).alias("text")))
    own = pairs.select(F.col(id_col).alias("pair_id"), clean(chosen_col).alias("c"), clean(rejected_col).alias("r"))
    n = F.least(F.size("c"), F.size("r"))
    same = F.zip_with("c", "r", lambda a, b: F.coalesce(a == b, F.lit(False)))  # the shorter side is padded with nulls, which are no match
    first = F.array_position(same, False).cast("int")
    own = own.withColumn("n_prefix", F.when(first > 0, first - 1).otherwise(n))
    rest = lambda c: F.slice(F.col(c), F.col("n_prefix") + 1, F.greatest(F.size(c) - F.col("n_prefix"), F.lit(0)))
    own = own.select("pair_id", "n_prefix", F.slice("c", F.lit(1), F.col("n_prefix")).alias("p"), rest("c").alias("c"), rest("r").alias("r"))
    return own.select("pair_id", "n_prefix", rendered(F.col("p")).alias("prompt"), rendered(F.col("c")).alias("chosen"), rendered(F.col("r")).alias("rejected"), mask(F.col("c")).alias("chosen_mask"), mask(F.col("r")).alias("rejected_mask"))


def swapped_reply_pairs(turns: DataFrame, **names) -> DataFrame:
    """pair_id, chosen, rejected for a table without preferences: a conversation is chosen against itself with its last
    assistant turn (and what follows) replaced by the last assistant turn of its neighbour (the id with the last bit changed; no
    such turn: nothing). Conversations without an assistant turn are left with equal sides."""
    own = conversations(turns, **names)
    reply = F.filter("turns", lambda x: x["role"] == "assistant")
    own = own.withColumn("reply", F.when(F.size(reply) > 0, F.element_at(reply, -1)))
    other = own.select(F.col("conv").bitwiseXOR(F.lit(1)).alias("o_conv"), F.col("reply").alias("o_reply"))
    joined = own.join(other, own["conv"] == other["o_conv"], "left")
    at = F.array_position(F.reverse(F.transform("turns", lambda x: x["role"] == "assistant")), True).cast("int")  # from the end
    kept = F.slice("turns", F.lit(1), F.size("turns") - at)
    swapped = F.when(at > 0, F.concat(kept, F.when(F.col("o_reply").isNotNull(), F.array("o_reply")).otherwise(F.expr(f"cast(array() as array<{TURN}>)")))).otherwise(F.col("turns"))
    return joined.select(F.col("conv").alias("pair_id"), F.col("turns").alias("chosen"), swapped.alias("rejected"))
