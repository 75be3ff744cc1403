"""Hand graphs with known values, seeded random graphs against oracles, and certificates."""

import random
from datetime import datetime

import pytest
from pyspark.sql import functions as F

from residua.cuts import arc_flows, audit_slots, settle
from residua.engine import MOVES, lowest_neighbours, slots_of
from residua.experiments import height_bound
from residua.graph import ARCS, FlowProblem, FlowState, build_slots, init_state, rejected_arcs, validate_arcs
from residua.plans.explain import has_product, physical
from residua.reference import sequential_push_relabel, smallest_cut
from residua.solvers import DYNAMIC, PROGRAMS, apply_updates, certify, patch_totals, solve_augmenting, solve_dynamic, solve_static
from residua.streaming.maintain import Maintainer, run_to_table

HAND = {
    "g1": ([(0, 1, 5), (1, 9, 3)], 3, [(1, 9, 10)], 5),
    "g2": ([(0, 1, 5), (1, 9, 5)], 5, [(0, 1, 2)], 2),
    "g3": ([(0, 1, 4), (0, 2, 2), (1, 2, 3), (2, 1, 1), (1, 9, 1), (2, 9, 6)], 6, [(1, 2, 1)], 4),
    "g6": ([(0, 9, 7), (0, 1, 1), (1, 9, 1)], 8, [(0, 9, 2)], 3),
}
ZERO = (0, 0, 0)


def problem(spark, arcs, t=9):
    return FlowProblem(spark.createDataFrame(arcs, ARCS), 0, t)


def batch(spark, rows):
    return spark.createDataFrame([(u, v, c, i) for i, (u, v, c) in enumerate(rows)], "src long, dst long, new_cap long, seq long")


@pytest.mark.parametrize("name", HAND)
def test_hand_graphs(spark, name):
    arcs, value, change, after = HAND[name]
    first = solve_static(problem(spark, arcs))
    assert first.value == value
    more = solve_dynamic(first.state, batch(spark, change))
    assert more.value == after


def test_programs_agree(spark):
    rng = random.Random(4)
    arcs = [(u, v, rng.randint(0, 9)) for u in range(7) for v in range(7) if u != v and rng.random() < 0.45]
    change = [(u, v, rng.randint(0, 12)) for u, v, _ in arcs if rng.random() < 0.3]
    p = problem(spark, arcs, 6)
    value = smallest_cut(arcs, 0, 6)
    assert sequential_push_relabel(arcs, 0, 6) == value
    base = PROGRAMS["static_pp"](p)
    assert base.value == value and tuple(certify(p, base).first()) == ZERO
    assert PROGRAMS["static_topo"](p).value == value
    new = [(u, v, c) for (u, v), c in ({(u, v): c for u, v, c in arcs} | {(u, v): c for u, v, c in change}).items()]
    q = problem(spark, new, 6)
    for program in ("dyn_data", "dyn_pp", "alt_pp"):
        result = DYNAMIC[program](base.state, batch(spark, change))
        assert result.value == smallest_cut(new, 0, 6), program
        assert tuple(certify(q, result).first()) == ZERO


def test_fused_step_with_steep_arcs(spark):
    arcs = [(0, 1, 5), (0, 2, 4), (2, 3, 4), (3, 1, 4), (1, 9, 2), (1, 4, 5), (4, 5, 5), (5, 6, 5), (6, 9, 5)]
    result = solve_static(problem(spark, arcs), step="fused", cycles=2)
    assert result.value == 7 and audit_slots(result.state.slots).isEmpty()


def test_augmenting_paths(spark):
    arcs = HAND["g3"][0]
    for search in ("shortest", "any"):
        result = solve_augmenting(problem(spark, arcs), search)
        assert result.value == 6 and tuple(certify(problem(spark, arcs), result).first()) == ZERO


def test_inserted_and_deleted_arcs(spark):
    """An arc that was not there, a deleted one, then both batches undone: a sequence continues from state to state."""
    arcs = [(0, 1, 4), (1, 9, 2)]
    state = solve_static(problem(spark, arcs)).state
    for change, value in (([(1, 2, 3), (2, 9, 3)], 4), ([(1, 9, 0)], 3), ([(1, 2, 0), (1, 9, 2), (0, 1, 1)], 1)):
        result = solve_dynamic(state, batch(spark, change), step="fused")
        assert result.value == value
        state = result.state


def test_superstep_moves_only_the_worklists_rows(spark, tmp_path):
    n = 20_000
    path = str(tmp_path / "slots")
    ring = spark.range(n).select("id", ((F.col("id") + 1) % n).alias("to"))
    build_slots(ring.select(F.col("id").alias("src"), F.col("to").alias("dst"), F.lit(3).cast("long").alias("cap"))).write.parquet(path)
    log = spark.createDataFrame([(5, 6, 1, None, None)], MOVES)
    work = spark.createDataFrame([(5, 1, 2), (6, 1, 1)], "id long, height long, excess long")
    verts = spark.range(n).select("id", F.lit(1).cast("long").alias("height"), F.lit(0).cast("long").alias("excess"))
    low = lowest_neighbours(slots_of(spark.read.parquet(path), work, log), verts, work)
    assert {(r.src, r.dst, r.room) for r in low.collect()} == {(5, 6, 2), (6, 5, 1)}
    assert not has_product(low)
    lines = physical(low).splitlines()
    scan = next(k for k, x in enumerate(lines) if "FileScan parquet" in x and "cap_out" in x)
    joins = [x for x in lines[:scan] if "Join" in x]
    assert "LeftSemi" in joins[-1], lines  # the join right above the base slots is the one with the worklist


def test_stream_of_changes_keeps_a_state_current(spark, tmp_path):
    base = solve_static(problem(spark, [(0, 1, 5), (1, 9, 3)]))
    keeper = Maintainer(str(tmp_path))
    base.state.save(f"{tmp_path}/state-base")
    rows = lambda *r: spark.createDataFrame(r, "src long, dst long, new_cap long, seq long, ts timestamp")
    day = datetime(2024, 1, 1)
    keeper(rows((1, 9, 1, 0, day), (1, 9, 10, 1, day)), 0)
    keeper(rows((1, 9, 1, 0, day)), 0)  # a replayed batch does nothing
    keeper(rows((0, 1, 2, 0, day)), 1)
    assert [(r.batch_id, r.value) for r in spark.read.parquet(f"{tmp_path}/done").orderBy("batch_id").collect()] == [(0, 5), (1, 2)]


def test_state_and_flow(spark, tmp_path):
    arcs = [(0, 1, 10), (1, 2, 10), (1, 9, 1)]
    result = solve_static(problem(spark, arcs))
    assert result.value == 1
    result.state.save(str(tmp_path))
    again = FlowState.load(spark, str(tmp_path))
    assert arc_flows(settle(again)).where("flow > 0").count() == 2
    assert build_slots(spark.createDataFrame([(0, 1, 2), (0, 1, 3), (1, 1, 9)], ARCS)).where("src = 0").first().cap_out == 5


def test_rejects(spark):
    bad = spark.createDataFrame([(0, 1, -1)], ARCS)
    assert rejected_arcs(bad).count() == 1
    with pytest.raises(ValueError):
        validate_arcs(bad)
    with pytest.raises(ValueError):
        init_state(FlowProblem(bad, 1, 1))


def test_patch_totals_and_height_bounds(spark):
    arcs = HAND["g2"][0]
    slots = apply_updates(solve_static(problem(spark, arcs)).state.slots, batch(spark, HAND["g2"][2]))
    assert tuple(patch_totals(slots, 0, 9).first()) == (1, 0, 3)
    assert tuple(height_bound(problem(spark, HAND["g3"][0])).first()) == (0, 0)


def test_update_mode_keeps_the_last_row_of_a_key(spark, tmp_path):
    path = str(tmp_path / "in")
    for rows in ([(1, 2), (2, 5)], [(1, 7)]):
        spark.createDataFrame(rows, "k long, v long").coalesce(1).write.mode("append").parquet(path)
    stream = spark.readStream.schema("k long, v long").option("maxFilesPerTrigger", 1).parquet(path)
    totals = run_to_table(stream.groupBy("k").agg(F.sum("v").alias("v")), "update", keys=("k",))
    assert {tuple(r) for r in totals.collect()} == {(1, 9), (2, 5)}
