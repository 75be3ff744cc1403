"""Connected components of a link table: every vertex gets the smallest id that links reach."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import Cuts


def rooted(up: DataFrame, cuts: Cuts) -> DataFrame:
    """``(id, parent)`` of a forest whose roots are their own parents -> every id with its root; paths halve in each job."""
    while True:
        far = up.select(F.col("id").alias("parent"), F.col("parent").alias("root"))
        step = cuts(up.join(far, "parent").select("id", F.col("root").alias("parent"), (F.col("root") != F.col("parent")).alias("moved")))
        cuts.drop(up)
        up = step
        if step.where("moved").isEmpty():
            return up


def components(links: DataFrame) -> DataFrame:
    """``links(a, b)`` -> ``(id, component_id)`` for the ids that occur in links (null ends are ignored).

    In each round every vertex hooks onto its neighbour of the highest degree, if that degree is above its own (equal ones
    in order of a hash); the trees shrink to their roots and links between roots go to the next round. At most half
    of the vertices stay: a root's degree is no smaller than that of its neighbours, none of which are roots, so these are
    at least as many as the roots. A chain of n vertices takes log n rounds whatever its order, a star one. Rounds are
    not limited. Counts and maxima combine before the shuffle; a hub's join partition is one that adaptive execution can
    split. Loops and repeats are harmless; empty links give an empty result.
    """
    cuts = Cuts()
    ends = links.where("a is not null and b is not null and a <> b").select("a", "b")
    edges = cuts(ends.unionByName(ends.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct())
    rounds: list[DataFrame] = []
    while not rounds or not edges.isEmpty():
        mark = lambda x, d: F.struct(F.col(d).alias("d"), F.xxhash64(x).alias("h"), F.col(x).alias("v"))
        degree = edges.groupBy(F.col("a").alias("b")).agg(F.count(F.lit(1)).alias("d"))
        top = edges.join(degree, "b").groupBy("a").agg(F.count(F.lit(1)).alias("own"), F.max(mark("b", "d")).alias("top"))
        hook = cuts(top.select(F.col("a").alias("id"), F.when(F.col("top") > mark("a", "own"), F.col("top.v")).otherwise(F.col("a")).alias("parent")))
        root = rooted(hook, cuts).select("id", "parent")
        rounds.append(root)
        a, b = (root.select(F.col("id").alias(x), F.col("parent").alias(f"r{x}")) for x in "ab")
        left = cuts(edges.join(a, "a").join(b, "b").where("ra <> rb").select(F.col("ra").alias("a"), F.col("rb").alias("b")).distinct())
        cuts.drop(edges)
        edges = left
    whole = rounds.pop()
    while rounds:
        above = whole.select(F.col("id").alias("parent"), F.col("parent").alias("root"))
        whole = rounds.pop().join(above, "parent", "left").select("id", F.coalesce("root", "parent").alias("parent"))
    whole = cuts(whole)
    least = whole.groupBy("parent").agg(F.min("id").alias("component_id"))
    return whole.join(least, "parent").select("id", "component_id")
