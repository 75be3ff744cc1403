"""The experiments as tables: graph sizes, step limits, active vertices, update regimes, crossover and cut drift."""

from __future__ import annotations

import time
from collections.abc import Callable, Iterable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .cuts import cut_drift
from .engine import discharge, sink_only
from .graph import FlowProblem, init_state
from .heights import full_levels, sink_levels
from .lineage import cut
from .solvers import DYNAMIC, PROGRAMS, FlowResult, recompute
from .updates import make_updates

#: The four programs that continue and the three that start again.
SEVEN = (*DYNAMIC, *PROGRAMS)
BENCH = "graph string, kind string, pct int, program string, value long, rounds long, supersteps long, levels long, pushes long, seconds double"


def timed(run: Callable[[], FlowResult]) -> tuple[FlowResult, float]:
    began = time.perf_counter()
    return (result := run()), time.perf_counter() - began


def bench_row(result: FlowResult, *key) -> tuple:
    c = result.state.counters
    return (*key, result.value, *(c.get(k, 0) for k in ("rounds", "supersteps", "levels", "pushes")))


def graph_table(spark: SparkSession, problems: Iterable[FlowProblem], program: str = "static_pp") -> DataFrame:
    """Vertices, arcs, terminals and maximum flow of each network."""
    rows = []
    for p in problems:
        result = PROGRAMS[program](p)
        rows.append((p.name, result.state.n, result.state.n_arcs, p.s, p.t, result.value))
    return spark.createDataFrame(rows, "graph string, vertices long, arcs long, s long, t long, value long")


def sweep_cycles(problem: FlowProblem, values: Iterable[int], program: str = "static_data", step: str = "split") -> DataFrame:
    """One solve for each limit of steps between two global relabels."""
    rows = []
    for k in values:
        result, seconds = timed(lambda k=k: PROGRAMS[program](problem, cycles=k, step=step))
        rows.append((*bench_row(result, problem.name, k), result.state.counters.get("relabels", 0), seconds))
    return problem.arcs.sparkSession.createDataFrame(rows, "graph string, cycles int, value long, rounds long, supersteps long, levels long, pushes long, relabels long, seconds double")


def active_trace(problem: FlowProblem, program: str = "static_data") -> DataFrame:
    """Active vertices at the start of each round beside all vertices, and what the round moved."""
    result = PROGRAMS[program](problem)
    per = result.rounds().groupBy("round").agg(F.max("active").alias("active"), F.sum("pushes").alias("pushes"), F.sum("saturating").alias("saturating"))
    return per.withColumn("vertices", F.lit(result.state.n).cast("long"))


def regime(problem: FlowProblem, kind: str, shares: Iterable[int], programs: Iterable[str] = SEVEN, seed: int = 1) -> DataFrame:
    """Programs on batches of each share (% of the arcs); the prior state is solved once and not part of any time."""
    base = PROGRAMS["static_pp"](problem).state
    rows = []
    for pct in shares:
        batch = cut(make_updates(problem.arcs, pct, kind, problem.s, problem.t, seed))
        for name in programs:
            result, seconds = timed(lambda b=batch, p=name: DYNAMIC[p](base, b) if p in DYNAMIC else recompute(problem, b, p))
            rows.append((*bench_row(result, problem.name, kind, pct, name), seconds))
    return problem.arcs.sparkSession.createDataFrame(rows, BENCH)


def agreement(bench: DataFrame) -> DataFrame:
    """Batches on which the programs differ in value: none, if all are right."""
    return bench.groupBy("graph", "kind", "pct").agg(F.min("value").alias("low"), F.max("value").alias("high")).where("low <> high")


def ablation(bench: DataFrame) -> DataFrame:
    """Worklist against topology drive: time and supersteps of the one over those of the other."""
    sides = bench.withColumn("family", F.substring_index("program", "_", 1)).where("family in ('dyn', 'static')")
    pick = lambda drive, c: F.max(F.when(F.col("program").endswith(drive), F.col(c)))
    return sides.groupBy("graph", "kind", "pct", "family").agg((pick("data", "seconds") / pick("topo", "seconds")).alias("time_ratio"), (pick("data", "supersteps") / pick("topo", "supersteps")).alias("step_ratio"))


def ranking(bench: DataFrame) -> DataFrame:
    """Programs of each graph and regime by their total time."""
    return bench.groupBy("graph", "kind", "program").agg(F.sum("seconds").alias("seconds"), F.sum("supersteps").alias("supersteps")).orderBy("graph", "kind", "seconds")


def height_bound(problem: FlowProblem, cycles: int = 3) -> DataFrame:
    """After one round of single-arc steps: vertices above their exact residual distance to the sink, and vertices that
    fell below their distance at the round's start. Both are 0 if labels stay valid and only rise."""
    state = init_state(problem)
    before = full_levels(state.verts, sink_levels(state.slots, sink_only(state), state.n, (state.s,))[0], state.n).withColumnRenamed("height", "was")
    after = discharge(state, sink_only, cycles=cycles, step="fused", max_rounds=1)
    exact = full_levels(after.verts, sink_levels(after.slots, sink_only(after), after.n, (after.s,))[0], after.n).withColumnRenamed("height", "exact")
    rows = after.verts.where(F.col("id") != state.s).join(exact, "id").join(before, "id")
    return rows.agg(F.count(F.when(F.col("height") > F.col("exact"), 1)).alias("above"), F.count(F.when(F.col("height") < F.col("was"), 1)).alias("fell"))


def drift(problem: FlowProblem, kind: str, pct: int, seed: int = 1) -> DataFrame:
    """Vertices by side of the minimum cut before and after a batch."""
    base = PROGRAMS["static_pp"](problem)
    after = DYNAMIC["dyn_pp"](base.state, make_updates(problem.arcs, pct, kind, problem.s, problem.t, seed))
    return cut_drift(base.cut, after.cut)
