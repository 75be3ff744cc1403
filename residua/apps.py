"""What users ask of maximum flow: cuts, assignments, routes, segmentations, circulations."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .cuts import arc_flows, min_cut, settle
from .graph import SINK, SOURCE, FlowProblem, with_super_terminals
from .pool import kept, static
from .solvers import FlowResult, solve_dynamic, solve_pooled, solve_static, solve_static_pushpull


def cheapest_cut(problem: FlowProblem) -> DataFrame:
    return min_cut(problem.arcs, solve_static(problem).cut)


def assign(pairs: DataFrame, quota: DataFrame) -> tuple[DataFrame, FlowResult]:
    """``pairs(left, right)``, ``quota(left, cap)``: a largest assignment in which a right end serves once."""
    arcs = pairs.distinct().select(F.col("left").alias("src"), F.col("right").alias("dst"), F.lit(1).cast("long").alias("cap"))
    ends = arcs.select(F.col("dst").alias("id"), F.lit(1).cast("long").alias("cap")).distinct()
    result = solve_static(FlowProblem(with_super_terminals(arcs, quota.select(F.col("left").alias("id"), "cap"), ends), SOURCE, SINK))
    return matches(result), result


def matches(result: FlowResult) -> DataFrame:
    flows = arc_flows(settle(result.state))
    return flows.where((F.col("flow") > 0) & (F.col("src") != SOURCE) & (F.col("dst") != SINK)).select(F.col("src").alias("left"), F.col("dst").alias("right"))


def reassign(result: FlowResult, updates: DataFrame) -> tuple[DataFrame, FlowResult]:
    """Continues an assignment after pairs came (new_cap 1) or went (new_cap 0)."""
    more = solve_dynamic(result.state, updates)
    return matches(more), more


def route(problem: FlowProblem) -> DataFrame:
    """The arcs that a maximum flow uses, with their flow."""
    return arc_flows(settle(solve_static(problem).state)).where("flow > 0")


def segment(edges: DataFrame, seed_a: DataFrame, seed_b: DataFrame) -> DataFrame:
    """``(id, side)``: the cheapest cut between two sets of seeds ``(id, cap)``; edges ``(src, dst, cap)`` in both directions."""
    result = solve_pooled(kept(FlowProblem(with_super_terminals(edges, seed_a, seed_b), SOURCE, SINK)), static(True), solve_static_pushpull)
    return result.cut.where(~F.col("id").isin(SOURCE, SINK))


def feasible_circulation(nodes: DataFrame, arcs: DataFrame) -> DataFrame:
    """``nodes(id, supply)``, ``arcs(src, dst, lo, hi)`` -> one row: whether all supplies, demands and lower bounds can be met."""
    low = arcs.select(F.col("dst").alias("id"), F.col("lo").alias("d")).unionByName(arcs.select(F.col("src").alias("id"), (-F.col("lo")).alias("d"))).unionByName(nodes.select("id", F.col("supply").alias("d")))
    net = low.groupBy("id").agg(F.sum("d").cast("long").alias("d"))
    sources, sinks = net.where("d > 0").select("id", F.col("d").alias("cap")), net.where("d < 0").select("id", (-F.col("d")).alias("cap"))
    inner = arcs.select("src", "dst", (F.col("hi") - F.col("lo")).alias("cap"))
    value = solve_static(FlowProblem(with_super_terminals(inner, sources, sinks), SOURCE, SINK)).value
    need = sources.agg(F.coalesce(F.sum("cap"), F.lit(0)).cast("long").alias("supply")).crossJoin(sinks.agg(F.coalesce(F.sum("cap"), F.lit(0)).cast("long").alias("demand")))
    return need.select("supply", "demand", F.lit(value).cast("long").alias("moved"), ((F.col("supply") == value) & (F.col("demand") == value)).alias("feasible"))


def flow_paths(flows: DataFrame, s: int, t: int, most: int = 1000) -> list[tuple[list[int], int]]:
    """Peels paths off a flow ``(src, dst, flow)`` that fits the driver; for inspection of small results."""
    rows = flows.where("flow > 0").limit(100_001).collect()
    if len(rows) > 100_000:
        raise ValueError("too many arcs with flow to list as paths")
    left: dict[int, dict[int, int]] = {}
    for r in rows:
        left.setdefault(r.src, {})[r.dst] = r.flow
    out = []
    while len(out) < most and any(left.get(s, {}).values()):
        path, seen = [s], {s}
        while path[-1] != t:
            step = next((v for v, f in sorted(left.get(path[-1], {}).items()) if f and v not in seen), None)
            if step is None:
                break
            path.append(step)
            seen.add(step)
        if path[-1] != t:
            break
        d = min(left[u][v] for u, v in zip(path, path[1:], strict=False))
        for u, v in zip(path, path[1:], strict=False):
            left[u][v] -= d
        out.append((path, d))
    return out
