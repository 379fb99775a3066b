"""Chat formatting of logged conversations after collapsing cumulative snapshots.

Loggers often store a conversation anew at each turn. The turns of a
conversation, in turn order, are hashed as a chain, so that the hash at turn i
stands for the whole prefix. A conversation whose full hash is the hash of a
proper prefix of another is a snapshot and goes; of equal conversations the
smallest conv_id stays. The rest is rendered, each turn as an opening mark with
its role, its text and a closing mark.

Rows without conv_id take no part. Null role or text counts as empty; null turns
come first; turns tied in number go by role, then text; fully repeated rows of a
conversation count once.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import stage

OPEN, CLOSE = "<|im_start|>", "<|im_end|>\n"


def _prefixes(turns: Column) -> Column:
    """Chained 128-bit hashes of all prefixes, shortest first."""
    start = F.struct(F.lit("").alias("last"), F.expr("cast(array() as array<string>)").alias("all"))

    def step(acc, t):
        h = F.md5(F.concat_ws("\x1f", acc["last"], F.length(t["role"]).cast("string"), t["role"], t["text"]).cast("binary"))
        return F.struct(h.alias("last"), F.concat(acc["all"], F.array(h)).alias("all"))

    return F.aggregate(turns, start, step, lambda acc: acc["all"])


def maximal(conversations: DataFrame) -> DataFrame:
    """(conv_id, turns, prefixes) of the conversations that no longer one extends and no equal one with a smaller id repeats."""
    clean = conversations.select(
        F.col("conv_id").cast("long").alias("conv_id"),
        F.struct(F.col("turn").cast("long").alias("turn"), F.coalesce(F.col("role").cast("string"), F.lit("")).alias("role"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text")).alias("t"),
    ).where("conv_id IS NOT NULL")
    whole = clean.groupBy("conv_id").agg(F.array_sort(F.collect_set("t")).alias("turns"))
    whole = stage(whole.select("conv_id", "turns", _prefixes(F.col("turns")).alias("prefixes")).withColumn("full", F.element_at("prefixes", -1)))
    proper = whole.select(F.explode(F.slice("prefixes", F.lit(1), F.size("prefixes") - 1)).alias("full")).distinct()
    first = whole.groupBy("full").agg(F.min("conv_id").alias("conv_id"))
    kept = first.join(proper, "full", "left_anti").select("conv_id")
    return whole.join(kept, "conv_id", "left_semi").select("conv_id", "turns", "prefixes")


def format_chats(conversations: DataFrame) -> DataFrame:
    """(conv_id, n_turns, text) of every maximal conversation."""
    rendered = F.array_join(F.transform("turns", lambda t: F.concat(F.lit(OPEN), t["role"], F.lit("\n"), t["text"], F.lit(CLOSE))), "")
    return maximal(conversations).select("conv_id", F.size("turns").cast("long").alias("n_turns"), rendered.alias("text"))
