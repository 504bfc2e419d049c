"""Preference data: chosen and rejected conversations rendered with their common turns once.

The longest common prefix of turns becomes the prompt; what remains of each side becomes a
completion. A mask lists the character spans of a completion that a model is trained on: the
texts and end marks of its assistant turns.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

OPEN, CLOSE, END = "<|", "|>\n", "<|end|>\n"


def conversations(turns: DataFrame) -> DataFrame:
    """(conv_id, turns array<struct<turn, role, text>>) in turn order; ties of turn by role and text.

    Null roles and texts read as empty; rows with a null conv_id belong to no conversation and go.
    """
    item = F.struct(F.col("turn").cast("long").alias("turn"), F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text"))
    return turns.where("conv_id is not null").groupBy("conv_id").agg(F.sort_array(F.collect_list(item)).alias("turns"))


def _clean(text: Column) -> Column:
    """Text with marks broken up, so it cannot close its turn."""
    return F.replace(text, F.lit("<|"), F.lit("< |"))


def _head(t: Column) -> Column:
    return F.concat(F.lit(OPEN), _clean(t["role"]), F.lit(CLOSE))


def _body(t: Column) -> Column:
    return F.concat(_clean(t["text"]), F.lit(END))


def render(turns: Column) -> Column:
    return F.array_join(F.transform(turns, lambda t: F.concat(_head(t), _body(t))), "")


def mask(turns: Column) -> Column:
    """Spans (from, to) of the assistant turns' bodies in render(turns), in characters."""
    start = F.struct(F.lit(0).alias("at"), F.array().cast("array<struct<from:int,to:int>>").alias("spans"))

    def step(acc: Column, t: Column) -> Column:
        begin = acc["at"] + F.length(_head(t))
        end = begin + F.length(_body(t))
        span = F.array(F.struct(begin.alias("from"), end.alias("to")))
        return F.struct(end.alias("at"), F.when(t["role"] == "assistant", F.concat(acc["spans"], span)).otherwise(acc["spans"]).alias("spans"))

    return F.aggregate(turns, start, step, lambda acc: acc["spans"])


def format_pairs(pairs: DataFrame) -> DataFrame:
    """pairs with n_common, prompt, chosen_text, rejected_text, chosen_mask and rejected_mask added.

    pairs holds arrays chosen and rejected of struct<role, text> (further fields are ignored); a null
    array counts as empty. Equal conversations leave two empty completions and empty masks.
    """

    def bare(name: str) -> Column:
        return F.transform(F.coalesce(F.col(name), F.array().cast(pairs.schema[name].dataType)), lambda t: F.struct(F.coalesce(t["role"], F.lit("")).alias("role"), F.coalesce(t["text"], F.lit("")).alias("text")))

    both = pairs.withColumns({"_c": bare("chosen"), "_r": bare("rejected")})
    first = F.array_position(F.zip_with("_c", "_r", lambda a, b: a.eqNullSafe(b)), False)
    both = both.withColumn("n_common", F.when(first > 0, first - 1).otherwise(F.size("_c")).cast("long"))
    rest = {n: F.slice(n, F.col("n_common").cast("int") + 1, F.size(n)) for n in ("_c", "_r")}
    out = both.withColumns({"prompt": render(F.slice("_c", 1, F.col("n_common").cast("int"))), "_c": rest["_c"], "_r": rest["_r"]})
    out = out.withColumns({"chosen_text": render(F.col("_c")), "rejected_text": render(F.col("_r")), "chosen_mask": mask(F.col("_c")), "rejected_mask": mask(F.col("_r"))})
    return out.drop("_c", "_r")


def reply_pairs(turns: DataFrame) -> DataFrame:
    """(conv_id, other_id, chosen, rejected): each conversation up to its last assistant turn, against the
    same turns with that reply replaced by the last reply of the neighbouring conversation (conv_id with
    its lowest bit flipped). Conversations without an assistant turn, or whose neighbour has none, make no pair.
    """
    convs = conversations(turns)
    last = F.expr("array_max(transform(turns, (t, i) -> if(t.role = 'assistant', i, -1)))")
    ended = convs.withColumn("n", last).where("n >= 0").select("conv_id", F.expr("slice(turns, 1, n + 1)").alias("chosen"), F.expr("turns[n]").alias("reply"))
    other = ended.select(F.col("conv_id").alias("other_id"), F.col("conv_id").bitwiseXOR(1).alias("conv_id"), F.col("reply").alias("other"))
    swapped = F.expr("concat(slice(chosen, 1, size(chosen) - 1), array(other))")
    return ended.join(other, "conv_id").select("conv_id", "other_id", "chosen", swapped.alias("rejected"))
