"""Exact distances over residual arcs by frontier expansion."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .graph import room_in, room_out
from .lineage import cut

#: Levels expanded in one Spark job.
TOGETHER = 3


def _levels(slots: DataFrame, roots: DataFrame, n: int, open_arc, pinned: tuple[int, ...]) -> tuple[DataFrame, int]:
    near = slots.where(open_arc > 0).select("src", "dst")
    if pinned:
        near = near.where(~F.col("dst").isin(*pinned))
    known = roots.select("id", F.lit(0).cast("long").alias("level")).distinct()
    depth = 0
    while depth <= n:
        for _ in range(TOGETHER):
            edge = known.where(F.col("level") == depth)
            depth += 1
            step = near.join(edge, near["src"] == edge["id"]).select(F.col("dst").alias("id")).distinct().join(known.select("id"), "id", "left_anti")
            known = known.unionByName(step.select("id", F.lit(depth).cast("long").alias("level")))
        known = cut(known)
        if known.where(F.col("level") == depth).isEmpty():
            break
    return known, depth


def sink_levels(slots: DataFrame, roots: DataFrame, n: int, pinned: tuple[int, ...] = ()) -> tuple[DataFrame, int]:
    """``(id, level)`` of the vertices with a residual path to a root, and the levels walked. Others are at ``n``."""
    return _levels(slots, roots, n, room_in(), pinned)


def source_levels(slots: DataFrame, roots: DataFrame, n: int, pinned: tuple[int, ...] = ()) -> tuple[DataFrame, int]:
    """The same along residual arcs: vertices that a root can reach."""
    return _levels(slots, roots, n, room_out(), pinned)


def full_levels(verts: DataFrame, levels: DataFrame, n: int) -> DataFrame:
    """Every vertex with its level, ``n`` where no path exists."""
    return verts.select("id").join(levels, "id", "left").select("id", F.coalesce("level", F.lit(n)).cast("long").alias("height"))
