"""Bulk push-relabel supersteps over a delta log.

A superstep reads one snapshot (base tables plus the log of moves since the last compaction), lets every active vertex
push to its lowest residual neighbour or relabel, and appends one small table of moves. Slots are rewritten only when
the log is compacted, at the end of a round. Under the worklist drive base slots meet the worklist before anything else:
they are scanned, but only rows of active vertices move.
"""

from __future__ import annotations

import time
from collections.abc import Callable
from dataclasses import replace

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .graph import FlowState, default_cycles, excess_of
from .heights import full_levels, sink_levels
from .lineage import cut, drop, folder

MOVES = "src long, dst long, amount long, height long, full boolean"
#: Wide supersteps between two global relabels, at most: a round ends when none pushes.
WIDE_CYCLES = 8
Filter = Callable[[DataFrame], DataFrame]


def both_ways(log: DataFrame) -> DataFrame:
    """Every push of the log as it changes the net flow of both rows of its pair."""
    push = log.where("amount is not null")
    return push.select("src", "dst", "amount").unionByName(push.select(F.col("dst").alias("src"), F.col("src").alias("dst"), (-F.col("amount")).alias("amount")))


def slots_after(slots: DataFrame, log: DataFrame | None) -> DataFrame:
    """Slots, all or some of them, after the log's pushes."""
    if log is None:
        return slots
    by_slot = both_ways(log).groupBy("src", "dst").agg(F.sum("amount").cast("long").alias("moved"))
    return slots.join(by_slot, ["src", "dst"], "left").select("src", "dst", "cap_out", "cap_in", (F.col("net") + F.coalesce("moved", F.lit(0))).alias("net"))


def verts_after(verts: DataFrame, log: DataFrame | None) -> DataFrame:
    """Vertices after the log's pushes and relabels."""
    if log is None:
        return verts
    by_vertex = both_ways(log).select(F.col("src").alias("id"), "amount", F.lit(None).cast("long").alias("height")).unionByName(log.where("height is not null").select(F.col("src").alias("id"), F.lit(0).cast("long").alias("amount"), "height"))
    by_vertex = by_vertex.groupBy("id").agg(F.sum("amount").cast("long").alias("out"), F.max("height").alias("new"))
    return verts.join(by_vertex, "id", "left").select("id", F.coalesce("new", "height").alias("height"), (F.col("excess") - F.coalesce("out", F.lit(0))).alias("excess"))


def with_moves(state: FlowState, log: DataFrame | None) -> FlowState:
    """The state after the log's pushes and relabels."""
    return replace(state, slots=slots_after(state.slots, log), verts=verts_after(state.verts, log))


def slots_of(slots: DataFrame, work: DataFrame, log: DataFrame | None) -> DataFrame:
    """The current slots of the vertices of ``work`` alone: base slots meet the worklist first, so that the log, the
    neighbours' heights and every shuffle behind them see as many rows as these vertices have neighbours."""
    return slots_after(slots.join(work.select(F.col("id").alias("src")), "src", "left_semi"), log)


def active(state: FlowState, verts: DataFrame | None = None) -> DataFrame:
    """The worklist: overflowing vertices below height n, terminals apart."""
    rows = state.verts if verts is None else verts
    return rows.where((F.col("excess") > 0) & (F.col("height") < state.n) & ~F.col("id").isin(state.s, state.t))


def lowest_neighbours(slots: DataFrame, verts: DataFrame, work: DataFrame) -> DataFrame:
    """For each vertex of ``work`` its lowest residual neighbour (ties to the smaller id) and the room towards it."""
    mine = work.select(F.col("id").alias("src"), F.col("height").alias("own"), "excess")
    theirs = verts.select(F.col("id").alias("dst"), F.col("height").alias("far"))
    room = (F.col("cap_out") - F.col("net")).alias("room")
    near = slots.join(mine, "src").where("cap_out > net").join(theirs, "dst")
    low = near.groupBy("src", "own", "excess").agg(F.min(F.struct("far", "dst", room)).alias("low"))
    return low.select("src", "own", "excess", "low.far", "low.dst", "low.room")


def plan_pushes(low: DataFrame) -> DataFrame:
    d = F.least("excess", "room")
    return low.where("own > far").select("src", "dst", d.alias("amount"), F.lit(None).cast("long").alias("height"), (d == F.col("room")).alias("full"))


def plan_wide_pushes(slots: DataFrame, verts: DataFrame, work: DataFrame) -> DataFrame:
    """Every vertex of ``work`` pushes along all its falling residual arcs at once, lowest neighbour first, while excess lasts."""
    mine = work.select(F.col("id").alias("src"), F.col("height").alias("own"), "excess")
    theirs = verts.select(F.col("id").alias("dst"), F.col("height").alias("far"))
    near = slots.join(mine, "src").where("cap_out > net").join(theirs, "dst").where("own > far").withColumn("room", F.col("cap_out") - F.col("net"))
    order = Window.partitionBy("src").orderBy("far", "dst").rowsBetween(Window.unboundedPreceding, -1)
    d = F.least("room", F.col("excess") - F.coalesce(F.sum("room").over(order), F.lit(0)))
    moves = near.select("src", "dst", d.alias("amount"), "room", "far").where("amount > 0")
    return moves.select("src", "dst", "amount", F.lit(None).cast("long").alias("height"), (F.col("amount") == F.col("room")).alias("full"), "far")


def plan_relabels(low: DataFrame, n: int) -> DataFrame:
    none = F.lit(None).cast("long")
    return low.where("own <= far").select("src", none.alias("dst"), none.alias("amount"), F.least(F.col("far") + 1, F.lit(n)).cast("long").alias("height"), F.lit(None).cast("boolean").alias("full"))


def steep_moves(state: FlowState, slots: DataFrame, work: DataFrame | None = None) -> DataFrame:
    """Whole residual of every arc that falls by more than one level."""
    h = state.verts.select("id", "height")
    up = (h if work is None else work.select("id", "height")).where(~F.col("id").isin(state.s, state.t)).select(F.col("id").alias("src"), F.col("height").alias("own"))
    down = h.select(F.col("id").alias("dst"), F.col("height").alias("far"))
    steep = slots.where("cap_out > net").join(up, "src").join(down, "dst").where("own > far + 1")
    return steep.select("src", "dst", (F.col("cap_out") - F.col("net")).alias("amount"), F.lit(None).cast("long").alias("height"), F.lit(True).alias("full"))


def deficits(state: FlowState) -> DataFrame:
    """Roots of the dynamic relabel: the sink and every deficient vertex, the source apart."""
    return state.verts.where(((F.col("excess") < 0) & (F.col("id") != state.s)) | (F.col("id") == state.t)).select("id")


def sink_only(state: FlowState) -> DataFrame:
    return state.verts.where(F.col("id") == state.t).select("id")


def add(counters: dict, **more: int) -> None:
    for k, v in more.items():
        counters[k] = counters.get(k, 0) + int(v or 0)


def discharge(state: FlowState, roots: Callable[[FlowState], DataFrame] = deficits, drive: str = "worklist", cycles: int | None = None, step: str = "wide", relabel: str = "every", keep: Filter = lambda slots: slots, worklist: str = "refresh", max_rounds: int | None = None) -> FlowState:
    """Rounds of global relabel and at most ``cycles`` supersteps until no vertex is active.

    ``step``: 'fused' pushes and relabels on one snapshot and then fills steep arcs, 'split' pushes first and relabels
    on what is left, which makes none, 'wide' pushes along all falling arcs of a vertex at once and leaves relabelling to
    the next global relabel (far fewer supersteps; a vertex with a path always has a falling arc). A vertex that pushed so
    has no falling arc left or no excess, and pushes open rising arcs only, so the next wide superstep can move something
    only if this one pushed to a height above 0. ``drive``: 'worklist' joins only active vertices to slots, 'topology' scans all.
    ``worklist``: 'frozen' keeps the round's first list. ``relabel``: 'every' round, 'once', or 'never'. ``keep``
    restricts the arcs that may be used.
    """
    spark = state.slots.sparkSession
    k = cycles or (WIDE_CYCLES if step == "wide" else default_cycles(state.n_arcs, state.n, None))
    counters, trace = dict(state.counters), list(state.trace)
    rounds = 0
    while max_rounds is None or rounds < max_rounds:
        if relabel == "every" or (relabel == "once" and not rounds):
            levels, depth = sink_levels(keep(state.slots), roots(state), state.n, (state.s,))
            verts = full_levels(state.verts, levels, state.n).join(state.verts.select("id", "excess"), "id").withColumn("height", F.when(F.col("id") == state.s, F.lit(state.n)).otherwise(F.col("height")))
            state = replace(state, verts=cut(verts))
            add(counters, relabels_global=1, levels=depth)
        elif not rounds and relabel == "never":
            state = replace(state, verts=cut(state.verts.withColumn("height", F.when(F.col("id") == state.s, F.lit(state.n)).otherwise(F.lit(0)).cast("long"))))
        n_active = active(state).count()
        if not n_active:
            break
        rounds += 1
        paths: list[str] = []
        first = active(state).select("id")
        for _ in range(k):
            began = time.perf_counter()
            log = spark.read.schema(MOVES).parquet(*paths) if paths else None
            now = replace(state, verts=verts_after(state.verts, log))
            work = active(now)
            if worklist == "frozen":
                work = work.join(first, "id", "left_semi")
            usable = slots_after(keep(state.slots), log) if drive == "topology" else slots_of(keep(state.slots), work, log)
            if step == "wide":
                if drive == "topology":  # every vertex looks at its neighbours; those that are not active have nothing to push
                    live = (F.col("excess") > 0) & (F.col("height") < state.n) & ~F.col("id").isin(state.s, state.t)
                    work = now.verts.withColumn("excess", F.when(live, F.col("excess")).otherwise(F.lit(0)))
                moves = plan_wide_pushes(usable, now.verts, work)
            elif drive == "topology":
                # every vertex looks at its neighbours; those that are not active drop out afterwards
                low = lowest_neighbours(usable, now.verts, now.verts)
                low = low.where((F.col("excess") > 0) & (F.col("own") < state.n) & ~F.col("src").isin(state.s, state.t))
            else:
                low = lowest_neighbours(usable, now.verts, work)
            if step != "wide":
                moves = plan_pushes(low) if step == "split" else plan_pushes(low).unionByName(plan_relabels(low, state.n))
            path = folder(spark)
            moves.write.parquet(path)
            paths.append(path)
            done = spark.read.schema(f"{MOVES}, far long").parquet(path)
            if step == "split":
                log = spark.read.schema(MOVES).parquet(*paths)
                after = replace(state, verts=verts_after(state.verts, log))
                low = lowest_neighbours(slots_of(keep(state.slots), active(after), log), after.verts, active(after))
                path = folder(spark)
                plan_relabels(low, state.n).write.parquet(path)
                paths.append(path)
                done = spark.read.schema(f"{MOVES}, far long").parquet(paths[-2], path)
            c = done.agg(F.count("amount"), F.count(F.when(F.col("full"), 1)), F.count("height"), F.count(F.when(F.col("far") > 0, 1))).first()
            add(counters, pushes=c[0], saturating=c[1], relabels=c[2], supersteps=1, message_rows=2 * c[0])
            trace.append((rounds, n_active, c[0], c[1], c[2], time.perf_counter() - began))
            if not c[3] if step == "wide" else not c[0] and not c[2]:
                break
        log = spark.read.schema(MOVES).parquet(*paths)
        state = with_moves(state, log)
        if step == "fused":
            worked = state.verts.join(log.where("height is not null").select(F.col("src").alias("id")), "id", "left_semi") if drive == "worklist" else None
            steep = cut(steep_moves(state, keep(state.slots), worked))
            add(counters, steep=steep.count())
            state = with_moves(state, steep)
        slots = cut(state.slots)
        state = replace(state, slots=slots, verts=cut(state.verts))
        drop(spark, paths)  # the round's log is in the state now
        add(counters, rounds=1)
    return replace(state, counters=counters, trace=trace)


def check_excess(state: FlowState) -> DataFrame:
    """Vertices whose kept excess differs from the one that net flow gives."""
    true = excess_of(state.slots).withColumnRenamed("excess", "true")
    return state.verts.join(true, "id", "left").where(F.coalesce("true", F.lit(0)) != F.col("excess"))
