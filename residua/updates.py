"""Batches of capacity changes, drawn by arithmetic hashes that any engine can repeat."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .graph import FlowState
from .solvers import DYNAMIC, FlowResult

PRIME = 1_000_003
#: Ranges of the hash order that ranks are counted in; the table of their counts is broadcast.
BUCKETS = 1 << 14


def make_updates(arcs: DataFrame, pct: int, kind: str, s: int, t: int, seed: int = 1, endpoint_bias: int = 8) -> DataFrame:
    """``(src, dst, new_cap, seq)`` for pct % of the arcs; arcs at the terminals are ``endpoint_bias`` times likelier to come first.

    The order is by hash divided by weight, so a batch of pct is a prefix of any larger one. Ranks come from a row number
    within each of ``BUCKETS`` ranges of that order plus the counts of the ranges before, a table of bounded size.
    """
    h = (F.col("src") * 7919 + F.col("dst") * 104729 + seed * 31) % PRIME
    h = F.when(h < 0, h + PRIME).otherwise(h)
    near = (F.col("src") == s) | (F.col("dst") == t)
    rows = arcs.groupBy("src", "dst").agg(F.sum("cap").cast("long").alias("cap")).withColumn("h", h).withColumn("r", F.when(near, F.col("h") / endpoint_bias).otherwise(F.col("h").cast("double")))
    rows = rows.withColumn("b", F.floor(F.col("r") * BUCKETS / PRIME))
    total = Window.partitionBy(F.lit(0)).orderBy("b")
    counts = rows.groupBy("b").agg(F.count(F.lit(1)).alias("held"))
    counts = counts.select("b", (F.sum("held").over(total) - F.col("held")).alias("before"), F.sum("held").over(total.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)).alias("all"))
    rank = F.row_number().over(Window.partitionBy("b").orderBy("r", "src", "dst")) + F.col("before")
    first = rows.join(F.broadcast(counts), "b").withColumn("rank", rank).where(F.col("rank") <= F.floor(F.col("all") * pct / 100))
    up, down = F.col("cap") + 1 + F.col("h") % 100, F.floor(F.col("cap") * (F.col("h") % 10) / 10)
    new = {"increase": up, "decrease": down, "mixed": F.when(F.col("rank") % 2 == 1, up).otherwise(down)}[kind]
    return first.select("src", "dst", new.cast("long").alias("new_cap"), F.lit(0).cast("long").alias("seq"))


def replay(state: FlowState, batches: list[DataFrame], program: str = "dyn_pp") -> list[FlowResult]:
    """One batch after the other, each from the state that the one before left."""
    out = []
    for batch in batches:
        out.append(DYNAMIC[program](state, batch))
        state = out[-1].state
    return out
