"""Preference formatting with DataFrame functions only.

A pair of conversations (chosen, rejected: arrays of role and content) shares its longest common prefix of turns. The
prefix is rendered once as the prompt; what follows is rendered as the two completions, each with the character
spans that a loss should see (the assistant's turns with their end mark; all other turns are masked).

Defined results: null turns are dropped, a null role is `user`, null content is empty; equal conversations are all
prompt with two empty completions; an empty or null conversation has no turns; repeated rows are repeated; in a table of
turns each row without a conv_id is a conversation of its own, of one turn and without a partner.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

OPEN, BREAK, END = "<|", "|>\n", "<|end|>\n"
LEARNED = "assistant"


def cleaned(turns: Column) -> Column:
    """Turns without nulls: array<struct<role, content>>."""
    present = F.filter(turns, lambda t: t.isNotNull())
    sound = F.transform(present, lambda t: F.struct(F.coalesce(t["role"], F.lit("user")).alias("role"), F.coalesce(t["content"], F.lit("")).alias("content")))
    return F.coalesce(sound, F.array().cast("array<struct<role:string,content:string>>"))


def common_turns(a: Column, b: Column) -> Column:
    """Number of leading turns that two conversations share."""
    same = F.zip_with(a, b, lambda x, y: x.eqNullSafe(y))  # the shorter one is padded with null, which equals no turn
    at = F.array_position(same, F.lit(False))
    return F.when(at > 0, (at - 1).cast("int")).otherwise(F.size(a))


def head(turn: Column) -> Column:
    return F.concat(F.lit(OPEN), turn["role"], F.lit(BREAK))


def render(turns: Column) -> Column:
    return F.array_join(F.transform(turns, lambda t: F.concat(head(t), t["content"], F.lit(END))), "")


def learned_spans(turns: Column, learned: str = LEARNED) -> Column:
    """Spans [start, stop) of the rendered turns, in characters, that are not masked."""
    kind = "struct<at:int,spans:array<struct<start:int,stop:int>>>"
    start = F.struct(F.lit(0).alias("at"), F.array().cast("array<struct<start:int,stop:int>>").alias("spans")).cast(kind)

    def step(acc: Column, t: Column) -> Column:
        body = acc["at"] + F.char_length(head(t))
        stop = body + F.char_length(t["content"]) + F.lit(len(END))
        span = F.array(F.struct(body.cast("int").alias("start"), stop.cast("int").alias("stop")))
        return F.struct(stop.cast("int").alias("at"), F.when(t["role"] == learned, F.concat(acc["spans"], span)).otherwise(acc["spans"]).alias("spans")).cast(kind)

    return F.aggregate(turns, start, step, lambda acc: acc["spans"])


def preference(df: DataFrame, keys: list[str], chosen: str = "chosen", rejected: str = "rejected") -> DataFrame:
    """keys, n_common, prompt, chosen, rejected (completions), chosen_spans and rejected_spans of every pair."""
    given = df.select(*(F.col(k) for k in keys), cleaned(F.col(chosen)).alias("_c"), cleaned(F.col(rejected)).alias("_r"))
    given = given.withColumn("n_common", common_turns(F.col("_c"), F.col("_r")))
    tail = lambda c: F.slice(F.col(c), F.col("n_common") + 1, F.size(c))
    cut = given.select(*keys, "n_common", F.slice("_c", F.lit(1), F.col("n_common")).alias("_p"), F.when(F.size("_c") > F.col("n_common"), tail("_c")).otherwise(F.slice("_c", 1, 0)).alias("_c"), F.when(F.size("_r") > F.col("n_common"), tail("_r")).otherwise(F.slice("_r", 1, 0)).alias("_r"))
    return cut.select(*keys, "n_common", render(F.col("_p")).alias("prompt"), render(F.col("_c")).alias("chosen"), render(F.col("_r")).alias("rejected"), learned_spans(F.col("_c")).alias("chosen_spans"), learned_spans(F.col("_r")).alias("rejected_spans"))


def conversations(df: DataFrame, conv_id: str = "conv_id", turn: str = "turn", role: str = "role", text: str = "text") -> DataFrame:
    """conv_id and turns (ordered by turn, nulls first, then role and text) of every conversation.

    A conversation is one record of the output, so its turns meet in one task; conversations that share texts don't.
    """
    rows = df.select(F.col(conv_id).cast("long").alias("conv_id"), F.struct(F.col(turn).cast("long").alias("turn"), F.coalesce(F.col(role), F.lit("user")).alias("role"), F.coalesce(F.col(text), F.lit("")).alias("content")).alias("t"))
    turns = rows.where("conv_id is not null").groupBy("conv_id").agg(F.array_sort(F.collect_list("t"), _by_turn).alias("turns"))
    turns = turns.unionByName(rows.where("conv_id is null").select("conv_id", F.array("t").alias("turns")))
    return turns.select("conv_id", F.transform("turns", lambda t: F.struct(t["role"].alias("role"), t["content"].alias("content"))).alias("turns"))


def _by_turn(a: Column, b: Column) -> Column:
    order = F.lit(0)
    for field in ("content", "role", "turn"):
        x, y = a[field], b[field]
        order = F.when(x.eqNullSafe(y), order).when(x.isNull(), -1).when(y.isNull(), 1).when(x < y, -1).otherwise(1)
    return order


def reply_swaps(convs: DataFrame, learned: str = LEARNED) -> DataFrame:
    """Preference pairs of a conversation table: chosen is the conversation as it stands; rejected has its turns before
    the last reply, then the last reply of its partner (ids 2n and 2n + 1 are partners). Without a reply of its own the
    conversation is all there is of chosen; without a partner's reply rejected ends before the reply.
    """
    n = F.size("turns")
    last = n - F.array_position(F.reverse(F.transform("turns", lambda t: t["role"] == learned)), F.lit(True)).cast("int") + 1
    has = F.exists("turns", lambda t: t["role"] == learned)
    base = convs.withColumn("last", F.when(has, last).otherwise(n + 1))
    replies = base.where(F.col("last") <= n).select(F.col("conv_id").bitwiseXOR(F.lit(1).cast("long")).alias("conv_id"), F.array(F.element_at("turns", F.col("last"))).alias("reply"))
    joined = base.join(replies, "conv_id", "left")
    before = F.slice("turns", F.lit(1), F.col("last") - 1)
    return joined.select("conv_id", F.col("turns").alias("chosen"), F.concat(before, F.coalesce("reply", F.slice("turns", 1, 0))).alias("rejected"))
