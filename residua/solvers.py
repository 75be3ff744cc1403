"""The programs: from scratch, after a batch of changes, and the baselines beside them."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, replace

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import pool
from .cuts import certificate, certificate_of, cut_capacity, cut_sides, flow_value, settle
from .engine import MOVES, deficits, discharge, sink_only, with_moves
from .graph import FlowProblem, FlowState, build_slots, excess_of, fresh, init_state, room_out, saturate
from .heights import sink_levels, source_levels
from .lineage import cut


@dataclass(frozen=True)
class FlowResult:
    value: int
    state: FlowState

    @property
    def cut(self) -> DataFrame:
        return self.state.cut

    def metrics(self) -> DataFrame:
        rows = sorted(self.state.counters.items()) + [("value", self.value)]
        return self.state.slots.sparkSession.createDataFrame(rows, "metric string, value long")

    def rounds(self) -> DataFrame:
        return self.state.slots.sparkSession.createDataFrame(self.state.trace, "round long, active long, pushes long, saturating long, relabels long, seconds double")


def finish(state: FlowState, kind: str = "height", exact: bool = False) -> FlowResult:
    """Publishes value and cut after a last exact relabel; ``exact`` says that the state's heights already are its result."""
    return FlowResult(flow_value(state), replace(state, cut=cut_sides(state, kind, exact)))


# ---- from scratch


def solve_static(problem: FlowProblem, drive: str = "worklist", cycles: int | None = None, step: str = "wide", global_relabel: str = "every", worklist: str = "refresh") -> FlowResult:
    """Push-relabel with global relabels; drive 'topology' or 'worklist'. Without relabels every round, steps must be fused."""
    return finish(discharge(init_state(problem), sink_only, drive, cycles, step, global_relabel, worklist=worklist), exact=global_relabel == "every")


def solve_static_pushpull(problem: FlowProblem, cycles: int | None = None, step: str = "wide") -> FlowResult:
    """Source and sink arcs saturated; deficient vertices act as sinks."""
    return finish(discharge(init_state(problem, into_sink=True), deficits, "worklist", cycles, step), "reach", exact=True)


# ---- after a batch


def apply_updates(slots: DataFrame, updates: DataFrame, allow_insert: bool = True) -> DataFrame:
    """New capacities ``(src, dst, new_cap, seq)``, the last one of an arc counting; net flow stays as it is."""
    last = updates.where("src <> dst").groupBy("src", "dst").agg(F.max_by("new_cap", "seq").alias("cap"))
    both = last.select("src", "dst", F.col("cap").alias("o"), F.lit(None).cast("long").alias("i")).unionByName(last.select(F.col("dst").alias("src"), F.col("src").alias("dst"), F.lit(None).cast("long").alias("o"), F.col("cap").alias("i")))
    both = both.groupBy("src", "dst").agg(F.max("o").alias("o"), F.max("i").alias("i"))
    zero = F.lit(0).cast("long")
    joined = slots.join(both, ["src", "dst"], "full" if allow_insert else "left")
    return joined.select("src", "dst", F.coalesce("o", "cap_out", zero).alias("cap_out"), F.coalesce("i", "cap_in", zero).alias("cap_in"), F.coalesce("net", zero).alias("net"))


def patch_arcs(arcs: DataFrame, updates: DataFrame) -> DataFrame:
    last = updates.groupBy("src", "dst").agg(F.max_by("new_cap", "seq").alias("new"))
    old = arcs.groupBy("src", "dst").agg(F.sum("cap").cast("long").alias("cap"))
    return old.join(last, ["src", "dst"], "full").select("src", "dst", F.coalesce("new", "cap").alias("cap"))


def repair_overfull(slots: DataFrame) -> DataFrame:
    """Flow that no longer fits goes back; the clamp is the same in both orientations."""
    return slots.withColumn("net", F.greatest(-F.col("cap_in"), F.least("cap_out", "net")))


def patch_totals(slots: DataFrame, s: int, t: int) -> DataFrame:
    """One row for patched slots: arcs whose flow no longer fits, then overflow and deficit of the inner vertices once it
    is repaired and the source's arcs are full again."""
    over = slots.agg(F.count(F.when(F.col("net") > F.col("cap_out"), 1)).alias("overfull"))
    e = F.col("excess")
    inner = excess_of(saturate(repair_overfull(slots), s)).where(~F.col("id").isin(s, t))
    sums = inner.agg(F.coalesce(F.sum(F.when(e > 0, e)), F.lit(0)).alias("overflow"), F.coalesce(F.sum(F.when(e < 0, -e)), F.lit(0)).alias("deficit"))
    return over.crossJoin(sums)


def patched(state: FlowState, updates: DataFrame, into_sink: bool = False) -> FlowState:
    slots = repair_overfull(apply_updates(state.slots, updates))
    slots = cut(saturate(slots, state.s, state.t if into_sink else None))
    return fresh(replace(state, slots=slots, counters={}, trace=[]))


def solve_dynamic(state: FlowState, updates: DataFrame, drive: str = "worklist", cycles: int | None = None, step: str = "wide") -> FlowResult:
    """Continues from a residual state: patch, repair, re-saturate, excess from net flow, then rounds with deficits as roots."""
    return finish(discharge(patched(state, updates), deficits, drive, cycles, step), exact=True)


def side_filter(sides: DataFrame, side: str):
    one = sides.where(F.col("side") == side).select("id")
    return lambda slots: slots.join(one.withColumnRenamed("id", "src"), "src", "left_semi").join(one.withColumnRenamed("id", "dst"), "dst", "left_semi").select("src", "dst", "cap_out", "cap_in", "net")


def saturate_cut(slots: DataFrame, sides: DataFrame) -> DataFrame:
    """Fills every residual arc from S to T, in both orientations of the rows."""
    a = sides.select(F.col("id").alias("src"), F.col("side").alias("x"))
    b = sides.select(F.col("id").alias("dst"), F.col("side").alias("y"))
    net = F.when((F.col("x") == "S") & (F.col("y") == "T"), F.col("cap_out")).when((F.col("x") == "T") & (F.col("y") == "S"), -F.col("cap_in")).otherwise(F.col("net"))
    return slots.join(a, "src", "left").join(b, "dst", "left").select("src", "dst", "cap_out", "cap_in", net.alias("net"))


def assert_disjoint(slots: DataFrame, sides: DataFrame) -> None:
    """No residual arc from S to T: the regions cannot meet."""
    a = sides.where("side = 'S'").select(F.col("id").alias("src"))
    b = sides.where("side = 'T'").select(F.col("id").alias("dst"))
    if not slots.where(room_out() > 0).join(a, "src", "left_semi").join(b, "dst", "left_semi").isEmpty():
        raise AssertionError("a residual arc crosses the saturated cut")


def solve_dynamic_pushpull(state: FlowState, updates: DataFrame, cycles: int | None = None, step: str = "wide") -> FlowResult:
    """Continues on a prior cut: saturate it, push inside T, pull inside S, then a bridge from T's overflow to S's deficits."""
    how = {"drive": "worklist", "cycles": cycles, "step": step}
    slots = repair_overfull(apply_updates(state.slots, updates))
    ends = slots.select(F.col("src").alias("id")).distinct()
    prior = state.cut if state.cut is not None else ends.select("id", F.when(F.col("id") == state.s, "S").otherwise("T").alias("side"))
    sides = cut(ends.join(prior, "id", "left").select("id", F.when(F.col("id") == state.s, "S").when(F.col("id") == state.t, "T").otherwise(F.coalesce("side", F.lit("T"))).alias("side")))
    now = fresh(replace(state, slots=cut(saturate_cut(saturate(slots, state.s, state.t), sides)), counters={}, trace=[]))
    assert_disjoint(now.slots, sides)
    inside = lambda side: lambda st: deficits(st).join(sides.where(F.col("side") == side).select("id"), "id", "left_semi")
    now = discharge(now, inside("T"), keep=side_filter(sides, "T"), **how)
    now = discharge(now.mirror(), inside("S"), keep=side_filter(sides, "S"), **how).mirror()
    return finish(run_bridge(now, **how), "reach")


def run_bridge(state: FlowState, **how) -> FlowState:
    """Push over the vertices that an overflow reaches and that reach a deficit, the source apart."""
    over = state.verts.where((F.col("excess") > 0) & ~F.col("id").isin(state.s, state.t)).select("id")
    ahead, _ = source_levels(state.slots, over, state.n, (state.s,))
    behind, _ = sink_levels(state.slots, deficits(state), state.n, (state.s,))
    region = cut(ahead.select("id").join(behind.select("id"), "id", "left_semi"))
    if region.isEmpty():
        return state
    keep = lambda slots: slots.join(region.withColumnRenamed("id", "src"), "src", "left_semi").join(region.withColumnRenamed("id", "dst"), "dst", "left_semi").select("src", "dst", "cap_out", "cap_in", "net")
    return discharge(state, deficits, keep=keep, **how)


# ---- baselines


def solve_alternating(state: FlowState, updates: DataFrame, cycles: int | None = None, max_rounds: int = 12, step: str = "wide") -> FlowResult:
    """Push and pull in turn over the whole graph; after ``max_rounds`` it pushes only, so that it ends (``fallback`` counts that)."""
    now = patched(state, updates, into_sink=True)
    for k in range(max_rounds):
        if k % 2:
            now = discharge(now.mirror(), deficits, cycles=cycles, max_rounds=1, step=step).mirror()
        else:
            now = discharge(now, deficits, cycles=cycles, max_rounds=1, step=step)
        over = now.verts.where((F.col("excess") > 0) & ~F.col("id").isin(now.s, now.t))
        levels, _ = sink_levels(now.slots, deficits(now), now.n, (now.s,))
        if over.join(levels, "id", "left_semi").isEmpty():
            return finish(now)
    now = discharge(now, deficits, cycles=cycles, step=step)
    return finish(replace(now, counters=now.counters | {"fallback": 1}))


def recompute(problem: FlowProblem, updates: DataFrame, method: str = "static_data") -> FlowResult:
    """Solves the patched network from zero."""
    return PROGRAMS[method](replace(problem, arcs=patch_arcs(problem.arcs, updates)))


def solve_augmenting(problem: FlowProblem, search: str = "shortest", max_paths: int = 500) -> FlowResult:
    """One augmenting path after another. 'shortest' takes a path of fewest arcs; 'any' takes whatever path its scaled
    network has, which holds the arcs with room for ``unit`` and more, the unit halving when no such path is left.

    For small graphs: a job for each arc of a path, whose arcs alone go through the driver.
    """
    spark = problem.arcs.sparkSession
    slots = cut(build_slots(problem.arcs))
    state = fresh(FlowState(slots, None, problem.s, problem.t, 0, 0))
    most = slots.agg(F.max(room_out())).first()[0] or 0
    unit = 1 if search == "shortest" else 1 << max(0, int(most).bit_length() - 1)
    start = state.verts.where(F.col("id") == state.s).select("id")
    paths = 0
    while True:
        wide = state.slots.where(room_out() >= unit)
        levels, _ = source_levels(wide, start, state.n)
        end = levels.where(F.col("id") == state.t).first()
        if end is None and unit == 1:
            return finish(replace(state, verts=cut(state.verts), counters={"paths": paths}))
        if end is None:
            unit //= 2
            continue
        if paths == max_paths:
            raise RuntimeError("too many augmenting paths for this baseline")
        paths += 1
        path, at = [], state.t
        for level in range(end.level - 1, -1, -1):
            before = levels.where(F.col("level") == level).select(F.col("id").alias("src"))
            back = wide.where(F.col("dst") == at).join(before, "src", "left_semi").select("src", room_out().alias("room"))
            step = back.agg(F.min(F.struct("src", "room")).alias("p")).first().p
            path.append((step.src, at, step.room))
            at = step.src
        d = min(p[2] for p in path)
        log = spark.createDataFrame([(u, v, d, None, None) for u, v, _ in path], MOVES)
        state = with_moves(state, log)
        state = replace(state, slots=cut(state.slots), verts=cut(state.verts))


PROGRAMS = {
    "static_topo": lambda p, **k: solve_static(p, "topology", **k),
    "static_data": lambda p, **k: solve_static(p, "worklist", **k),
    "static_pp": lambda p, **k: solve_static_pushpull(p, **k),
}
DYNAMIC = {
    "dyn_topo": lambda s, u, **k: solve_dynamic(s, u, "topology", **k),
    "dyn_data": lambda s, u, **k: solve_dynamic(s, u, "worklist", **k),
    "dyn_pp": lambda s, u, **k: solve_dynamic_pushpull(s, u, **k),
    "alt_pp": lambda s, u, **k: solve_alternating(s, u, **k),
}


def choose_strategy(batch_pct: float, kind: str, history: dict[str, float] | None = None) -> str:
    """'dynamic' for increases and for batches below the learnt crossover of their kind, else 'static'."""
    limit = (history or {}).get(kind, 100.0 if kind == "increase" else 20.0)
    return "dynamic" if batch_pct <= limit else "static"


def solve_auto(problem: FlowProblem, state: FlowState, updates: DataFrame, kind: str = "mixed", history: dict[str, float] | None = None) -> FlowResult:
    pct = 100 * updates.count() / max(1, state.n_arcs)
    return solve_dynamic_pushpull(state, updates) if choose_strategy(pct, kind, history) == "dynamic" else recompute(problem, updates)


def crossover(bench: DataFrame) -> DataFrame:
    """First batch share at which the dynamic program takes longer than the static one: ``(graph, kind, crossover_pct)``."""
    ratio = bench.groupBy("graph", "kind", "pct").agg((F.min(F.when(F.col("program").startswith("dyn"), F.col("seconds"))) / F.min(F.when(F.col("program").startswith("static"), F.col("seconds")))).alias("ratio"))
    w = Window.partitionBy("graph", "kind").orderBy("pct")
    return ratio.where("ratio > 1").withColumn("k", F.row_number().over(w)).where("k = 1").select("graph", "kind", F.col("pct").alias("crossover_pct"))


def certify(problem: FlowProblem, result: FlowResult) -> DataFrame:
    """Settles a result's pseudoflow and evaluates its certificate on the given arcs."""
    return certificate(problem.arcs, settle(result.state), result.cut)


def value_row(result: FlowResult, arcs: DataFrame) -> DataFrame:
    return arcs.sparkSession.createDataFrame([(result.value, cut_capacity(arcs, result.cut))], "value long, cut_capacity long")


# ---- networks that fit one task


def solve_pooled(problem: FlowProblem, run: Callable, otherwise: Callable[[FlowProblem], FlowResult]) -> FlowResult:
    """A program of ``pool`` in one task, or where the network is too large for that the same by supersteps. The arcs should be ``pool.kept``."""
    if not pool.fits(problem):
        return otherwise(problem)
    state, _ = pool.pooled(problem, run)
    return FlowResult(flow_value(state), state)


def certify_pooled(problem: FlowProblem) -> DataFrame:
    """The certificate of push and pull from scratch. Spark evaluates it on the given arcs wherever the flow was found."""
    problem = pool.kept(problem)
    if not pool.fits(problem):
        return certify(problem, solve_static_pushpull(problem))
    state, flows = pool.pooled(problem, pool.static(True), settled=True)
    return certificate_of(problem.arcs, flows, problem.s, problem.t, state.cut)
