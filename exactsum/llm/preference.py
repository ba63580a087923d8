"""Preference pairs from chosen and rejected conversations, in DataFrame functions only.

The turns of both sides are ordered, their longest common prefix is rendered once as the prompt,
and what follows is rendered as two completions.  Masks are character spans of the completions
that take part in the loss: bodies and end marks of the learner's turns, never headers or other
roles.  One shuffle by pair brings a pair's turns together; a pair is one training example and one
row of the result, and no other grouping is made.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

OPEN, CLOSE, END = "<|", "|>\n", "<|end|>\n"


def header(role: Column) -> Column:
    return F.concat(F.lit(OPEN), role, F.lit(CLOSE))


def body(text: Column) -> Column:
    return F.concat(text, F.lit(END))


def rendered(turns: Column) -> Column:
    return F.array_join(F.transform(turns, lambda t: F.concat(header(t["role"]), body(t["text"]))), "")


def loss_spans(turns: Column, learner: str) -> Column:
    """[start, stop) of the learner's bodies within the rendered turns."""
    start = F.struct(F.lit(0).cast("long").alias("at"), F.array().cast("array<struct<start:bigint,stop:bigint>>").alias("spans"))

    def step(s, t):
        begin = s["at"] + F.length(header(t["role"]))
        stop = begin + F.length(body(t["text"]))
        span = F.array(F.struct(begin.alias("start"), stop.alias("stop")))
        return F.struct(stop.alias("at"), F.when(t["role"] == learner, F.concat(s["spans"], span)).otherwise(s["spans"]).alias("spans"))

    return F.aggregate(turns, start, step, lambda s: s["spans"])


def preference_pairs(turns: DataFrame, learner: str = "assistant") -> DataFrame:
    """From (pair_id, chosen, turn, role, text) rows: pair_id, n_prompt_turns, prompt, chosen, rejected and their spans.

    `chosen` is true or false and tells the side.  Turns are ordered by (turn, role, text), nulls
    first, so ties have one order and repeated rows are repeated turns.  A null role or text is an
    empty one.  A pair with only one side, and rows with a null pair_id or side, give no row.
    Equal sides give the whole conversation as prompt and empty completions.  Other columns are ignored.
    """
    t = turns.where("pair_id is not null and chosen is not null")
    t = t.select("pair_id", F.col("chosen").alias("side"), F.struct("turn", F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text")).alias("t"))
    side = lambda yes: F.sort_array(F.collect_list(F.when(F.col("side") == yes, F.col("t"))))
    both = t.groupBy("pair_id").agg(side(True).alias("c"), side(False).alias("r")).where((F.size("c") > 0) & (F.size("r") > 0))
    same = F.zip_with("c", "r", lambda a, b: (a["role"] == b["role"]) & (a["text"] == b["text"]))
    first = F.array_position(F.transform(same, lambda x: F.coalesce(x, F.lit(False))), F.lit(False))
    d = both.withColumn("n", F.when(first > 0, first - 1).otherwise(F.size(same)).cast("int"))
    tail = lambda x: F.slice(x, F.col("n") + 1, F.size(x))
    d = d.select("pair_id", F.col("n").alias("n_prompt_turns"), F.slice("c", F.lit(1), F.col("n")).alias("p"), tail("c").alias("c"), tail("r").alias("r"))
    return d.select("pair_id", "n_prompt_turns", rendered(F.col("p")).alias("prompt"), rendered(F.col("c")).alias("chosen"), rendered(F.col("r")).alias("rejected"), loss_spans(F.col("c"), learner).alias("chosen_spans"), loss_spans(F.col("r"), learner).alias("rejected_spans"))
