"""Values, cuts, flows, and what certifies them."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .engine import deficits, discharge, sink_only
from .graph import FlowState, room_out, simple_arcs
from .heights import full_levels, sink_levels, source_levels
from .lineage import cut


def flow_value(state: FlowState) -> int:
    """Sum of excess at height 0, the source apart: the sink's excess plus the deficits that flow cannot fill from elsewhere."""
    rows = state.verts.where(((F.col("excess") < 0) | (F.col("id") == state.t)) & (F.col("id") != state.s))
    return int(rows.agg(F.sum("excess")).first()[0] or 0)


def cut_sides(state: FlowState, kind: str = "height", exact: bool = False) -> DataFrame:
    """``(id, side)``: 'T' for what can still reach the sink or a deficit, 'S' for the rest.

    kind 'height' takes a final exact relabel from the sink and the deficits; 'reach' also marks the vertices that the
    source or an overflow reaches as 'S' and puts vertices in neither set there. ``exact`` takes the state's own heights: a run that ended
    with a global relabel over all arcs, and moved nothing since, has them.
    """
    heights = state.verts if exact else full_levels(state.verts, sink_levels(state.slots, deficits(state), state.n, (state.s,))[0], state.n)
    sides = heights.select("id", F.when(F.col("height") < state.n, "T").otherwise("S").alias("side"))
    if kind == "reach":
        over = state.verts.where((F.col("excess") > 0) & (F.col("id") != state.t) | (F.col("id") == state.s)).select("id")
        seen, _ = source_levels(state.slots, over, state.n, (state.t,))
        sides = sides.join(seen.select("id", F.lit(True).alias("seen")), "id", "left").select("id", F.when(F.col("seen"), "S").otherwise(F.col("side")).alias("side"))
    return cut(sides)


def min_cut(arcs: DataFrame, sides: DataFrame) -> DataFrame:
    """The arcs that cross from S to T."""
    a = sides.select(F.col("id").alias("src"), F.col("side").alias("x"))
    b = sides.select(F.col("id").alias("dst"), F.col("side").alias("y"))
    return simple_arcs(arcs).join(a, "src").join(b, "dst").where("x = 'S' and y = 'T'").select("src", "dst", "cap")


def cut_capacity(arcs: DataFrame, sides: DataFrame) -> int:
    return int(min_cut(arcs, sides).agg(F.sum("cap")).first()[0] or 0)


def arc_flows(state: FlowState) -> DataFrame:
    """``(src, dst, cap, flow)``: of each pair the direction that net flow takes."""
    return state.slots.where("cap_out > 0").select("src", "dst", F.col("cap_out").alias("cap"), F.greatest(F.lit(0), F.col("net")).cast("long").alias("flow"))


def saturated_arcs(state: FlowState) -> DataFrame:
    return state.slots.where((F.col("cap_out") > 0) & (room_out() == 0)).select("src", "dst", F.col("cap_out").alias("cap"))


def settle(state: FlowState, **how) -> FlowState:
    """A flow from a pseudoflow: stranded excess goes back to the source, deficits are supplied from the sink's inflow."""

    def source_root(m: FlowState) -> DataFrame:
        return m.verts.where(F.col("id") == m.t).select("id")

    # towards the source: there it is the root, and the sink never takes part
    turned = replace(state, s=state.t, t=state.s)
    back = discharge(turned, roots=source_root, **how)
    state = replace(back, s=back.t, t=back.s)
    if not state.verts.where((F.col("excess") < 0) & ~F.col("id").isin(state.s, state.t)).isEmpty():
        turned = replace(state.mirror(), s=state.s, t=state.t)
        supplied = discharge(turned, roots=sink_only, **how)
        state = replace(supplied, s=state.t, t=state.s).mirror()
    return state


def audit_slots(slots: DataFrame) -> DataFrame:
    """Rows beyond capacity, or whose reverse row does not mirror them."""
    twin = slots.select(F.col("src").alias("dst"), F.col("dst").alias("src"), F.col("cap_out").alias("c"), F.col("cap_in").alias("d"), F.col("net").alias("f"))
    return slots.join(twin, ["src", "dst"], "left").where("net > cap_out or -net > cap_in or f is null or f <> -net or c <> cap_in or d <> cap_out")


def certificate(arcs: DataFrame, state: FlowState, sides: DataFrame) -> DataFrame:
    """``certificate_of`` the state's flow."""
    return certificate_of(arcs, arc_flows(state).select("src", "dst", "flow"), state.s, state.t, sides)


def certificate_of(arcs: DataFrame, flows: DataFrame, s: int, t: int, sides: DataFrame) -> DataFrame:
    """One row: violations of capacity and conservation of a settled flow, and the gap between a cut's capacity and its value.

    Three zeros prove that flow and cut are optimal. Everything is computed from the given arcs and the flow alone.
    """
    both = simple_arcs(arcs).join(flows.where("flow <> 0"), ["src", "dst"])  # arcs without flow violate nothing
    over = both.agg(F.count(F.when((F.col("flow") > F.col("cap")) | (F.col("flow") < 0), 1)).alias("capacity_violations"))
    ends = both.select(F.col("src").alias("id"), (-F.col("flow")).alias("d")).unionByName(both.select(F.col("dst").alias("id"), F.col("flow").alias("d")))
    nets = ends.groupBy("id").agg(F.sum("d").alias("d"))
    broken = nets.agg(F.count(F.when((F.col("d") != 0) & ~F.col("id").isin(s, t), 1)).alias("conservation_violations"), F.coalesce(F.sum(F.when(F.col("id") == t, F.col("d"))), F.lit(0)).alias("value"))
    near, far = (sides.where(F.col("side") == side).select(F.col("id").alias(end)) for side, end in (("S", "src"), ("T", "dst")))
    capacity = arcs.where("src <> dst").join(near, "src", "left_semi").join(far, "dst", "left_semi").agg(F.coalesce(F.sum("cap"), F.lit(0)).alias("capacity"))
    return over.crossJoin(broken).crossJoin(capacity).select("capacity_violations", "conservation_violations", (F.col("capacity") - F.col("value")).cast("long").alias("cut_gap"))


def cut_drift(before: DataFrame, after: DataFrame) -> DataFrame:
    """Vertices by how they changed side: ``(was, now, n)``."""
    a, b = before.withColumnRenamed("side", "was"), after.withColumnRenamed("side", "now")
    return a.join(b, "id", "full").groupBy("was", "now").agg(F.count(F.lit(1)).alias("n"))
