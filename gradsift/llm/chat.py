"""Logged conversations: snapshots that a longer log contains are dropped, the rest rendered.

A chat front end often logs the whole conversation after each turn, so the log holds every
prefix. Each conversation gets a rolling hash per turn prefix; a conversation whose last
hash is a proper prefix hash of another is contained in it and goes by an anti-join. Of
equal conversations the smallest id stays. Only DataFrame functions run.

Defined results: turns are ordered by (turn, role, text); a null role or text counts as
empty; repeated rows are turns of their own; an empty table has no rows.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def _turns(log: DataFrame) -> DataFrame:
    turn = F.struct(
        F.col("turn"),
        F.coalesce(F.col("role"), F.lit("")).alias("role"),
        F.coalesce(F.col("text"), F.lit("")).alias("text"),
    )
    return log.groupBy("conv_id").agg(F.array_sort(F.collect_list(turn)).alias("turns"))


def _prefix_hashes(turns: Column) -> Column:
    """Element k: hash of the turns 1..k, each from the one before."""

    def step(acc: Column, t: Column) -> Column:
        last = F.when(F.size(acc) > 0, F.element_at(acc, -1))
        a, b = F.coalesce(last["a"], F.lit(0)), F.coalesce(last["b"], F.lit(0))
        new = F.struct(
            F.xxhash64(a, t["role"], t["text"]).alias("a"),
            F.xxhash64(F.lit("turn"), b, t["text"], t["role"]).alias("b"),
        )
        return F.concat(acc, F.array(new))

    return F.aggregate(turns, F.array().cast("array<struct<a:bigint,b:bigint>>"), step)


def collapse_snapshots(log: DataFrame) -> DataFrame:
    """Maximal conversations: conv_id, turns, and n_copies equal ones. log: conv_id, turn, role, text."""
    turns = _turns(log)
    hashed = turns.select("conv_id", _prefix_hashes(F.col("turns")).alias("_h"))
    whole = (
        hashed.select("conv_id", F.element_at("_h", -1).alias("_w")).select("conv_id", "_w.a", "_w.b")
        .groupBy("a", "b").agg(F.min("conv_id").alias("_kept"), F.count(F.lit(1)).alias("n_copies"))
    )
    inner = (
        hashed.where(F.size("_h") > 1)
        .select(F.explode(F.slice("_h", F.lit(1), F.size("_h") - 1)).alias("_w"))
        .select("_w.a", "_w.b").distinct()
    )
    # copies meet by hash and id alone; the turns of what is kept come back by id
    kept = whole.join(inner, ["a", "b"], "left_anti")
    return turns.join(kept, turns["conv_id"].eqNullSafe(kept["_kept"])).select("conv_id", "turns", "n_copies")


def render(conversations: DataFrame, opening: str = "<|{}|>\n", closing: str = "<|end|>\n") -> DataFrame:
    """One training text for each conversation; opening has {} for the role."""
    head, tail = opening.split("{}")
    text = F.array_join(
        F.transform("turns", lambda t: F.concat(F.lit(head), t["role"], F.lit(tail), t["text"], F.lit("\n"), F.lit(closing))), ""
    )
    return conversations.select("conv_id", F.size("turns").cast("long").alias("n_turns"), "n_copies", text.alias("text"))
