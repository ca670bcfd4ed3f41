"""Chat formatting with cumulative-snapshot collapse.

Chat services log a conversation again after each turn, so most logged conversations are a prefix of a longer one.
Each turn gets a rolling hash of all turns up to it; a conversation whose last hash is also an inner hash of another
is a prefix of that one. Two anti-joins on these hashes keep the maximal conversations, of equal ones that with the
smallest id, and only these are rendered.

Defined results: turns are ordered by turn number (nulls first), then role, then text; a null role renders as
``unknown``, a null text as empty, and both differ from the strings so named when turns are compared; rows without a
conversation id are conversations of one turn each, reported with a null id; a row that repeats is a turn that
repeats; other columns play no part; an empty table gives an empty result. The rolling hash is a running aggregate
over slim rows (no conversation is collected to be compared); one that is rendered is one value of a row.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import materialize

START, END = "<|im_start|>", "<|im_end|>"


def rolling_hashes(turns: DataFrame, conv: str = "conv_id", turn: str = "turn", role: str = "role", text: str = "text") -> DataFrame:
    """(key, conv, n, h1, h2): for each conversation and each number n of leading turns the hash of those turns."""
    slim = turns.select(
        F.col(conv).alias("conv"), F.col(turn).alias("turn"), F.col(role).alias("role"),
        F.xxhash64(F.coalesce(text, F.lit("")), F.col(text).isNull()).alias("t1"),
        F.xxhash64(F.col(text).isNull(), F.reverse(F.coalesce(text, F.lit("")))).alias("t2"),
    )
    known = slim.where("conv is not null").withColumn("key", F.concat(F.lit("c"), F.col("conv").cast("string")))
    order = W.partitionBy("key").orderBy("turn", "role", "t1", "t2")
    known = known.withColumn("n", F.row_number().over(order))
    lone = slim.where("conv is null").withColumn("key", F.concat_ws(":", F.lit("r"), F.coalesce("role", F.lit("null")), "t1", "t2")).withColumn("n", F.lit(1))
    role_key = [F.coalesce("role", F.lit("")), F.col("role").isNull()]

    def hashed(df: DataFrame) -> DataFrame:
        return df.withColumns({"a": F.xxhash64("n", *role_key, "t1", "t2"), "b": F.xxhash64("t2", *role_key, "n", "t1")})

    running = order.rowsBetween(W.unboundedPreceding, 0)
    known = hashed(known).withColumns({"h1": F.expr("bit_xor(a)").over(running), "h2": F.expr("bit_xor(b)").over(running)})
    lone = hashed(lone).withColumns({"h1": F.col("a"), "h2": F.col("b")})
    return known.select("key", "conv", "n", "h1", "h2").unionByName(lone.select("key", "conv", "n", "h1", "h2"))


def maximal_conversations(turns: DataFrame, **columns) -> DataFrame:
    """(key, conv, n): conversations that are no prefix of a longer one; of equal ones the smallest id."""
    prefixes = materialize(rolling_hashes(turns, **columns), "chat-prefixes")
    last = prefixes.groupBy("key").agg(F.min("conv").alias("conv"), F.max(F.struct("n", "h1", "h2")).alias("last")).select("key", "conv", "last.*")
    whole = last.groupBy("n", "h1", "h2").agg(F.min(F.struct(F.col("conv").isNull().alias("lone"), "conv", "key")).alias("keep")).select("n", "h1", "h2", "keep.conv", "keep.key")
    inner = prefixes.join(last.select("key", F.col("n").alias("end")), "key").where("n < end").select("n", "h1", "h2").distinct()
    return whole.join(inner, ["n", "h1", "h2"], "left_anti").select("key", "conv", "n")


def clean(text: Column) -> Column:
    """Text without marks that would open or close a turn."""
    return F.replace(F.coalesce(text, F.lit("")), F.lit("<|im_"), F.lit("< |im_"))


def render_chats(turns: DataFrame, conv: str = "conv_id", turn: str = "turn", role: str = "role", text: str = "text") -> DataFrame:
    """conv, n_turns, chat: a row per maximal conversation, rendered turn by turn between start and end marks."""
    kept = materialize(maximal_conversations(turns, conv=conv, turn=turn, role=role, text=text), "chat-kept")
    one = F.concat(F.lit(START), clean(F.coalesce(role, F.lit("unknown"))), F.lit("\n"), clean(F.col(text)), F.lit(END + "\n"))
    rows = turns.select(F.col(conv).alias("conv"), F.struct(F.col(turn).alias("turn"), F.col(role).alias("role"), F.xxhash64(F.coalesce(text, F.lit("")), F.col(text).isNull()).alias("t1"), one.alias("one")).alias("x"))
    rows = rows.join(kept.where("conv is not null").select("conv"), "conv", "left_semi")
    chats = rows.groupBy("conv").agg(F.sort_array(F.collect_list("x")).alias("xs")).select("conv", F.size("xs").cast("long").alias("n_turns"), F.array_join(F.col("xs.one"), "").alias("chat"))
    lone_key = F.concat_ws(":", F.lit("r"), F.coalesce(role, F.lit("null")), F.xxhash64(F.coalesce(text, F.lit("")), F.col(text).isNull()), F.xxhash64(F.col(text).isNull(), F.reverse(F.coalesce(text, F.lit("")))))
    lone = turns.where(F.col(conv).isNull()).select(lone_key.alias("key"), F.lit(1).cast("long").alias("n_turns"), one.alias("chat"))
    lone = lone.join(kept.where("conv is null").select("key"), "key", "left_semi").groupBy("key").agg(F.first("n_turns").alias("n_turns"), F.first("chat").alias("chat"))
    chats = chats.unionByName(lone.select(F.lit(None).cast(turns.schema[conv].dataType).alias("conv"), "n_turns", "chat"))
    return chats.withColumnRenamed("conv", conv)
