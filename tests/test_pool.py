"""Networks solved in one task against brute force, and the jobs that queries over them start."""

import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from residua import pool
from residua import workloads as W
from residua.apps import segment
from residua.cuts import audit_slots, certificate_of, flow_value
from residua.graph import ARCS, FlowProblem
from residua.operators import registry
from residua.plans.explain import physical
from residua.reference import smallest_cut
from residua.solvers import certify_pooled, solve_pooled, solve_static_pushpull

PROGRAMS = {
    "static_pp": pool.static(True),
    "static": pool.static(False),
    "fused": pool.static(False, step="fused"),
    "split": pool.static(False, step="split", cycles=3),
    "frozen": pool.static(False, step="fused", worklist="frozen"),
    "topology": pool.static(False, drive="topology", step="fused"),
    "once": pool.static(False, relabel="once", step="fused"),
    "wide of two": pool.static(True, cycles=2),
    "shortest": pool.augmenting("shortest", 500),
    "any": pool.augmenting("any", 500),
}


def arrays(arcs, s, t):
    ids = np.unique([s, t] + [x for a in arcs for x in a[:2]])
    src, dst, cap = (np.array([a[k] for a in arcs], np.int64) for k in range(3))
    return pool.Arrays(ids, np.searchsorted(ids, src), np.searchsorted(ids, dst), cap, s, t)


def proven(graph, arcs, near_s):
    """The value of the settled flow and the capacity of the cut, after the flow's own checks."""
    graph.settle()
    src, dst, flow = graph.flows()
    room, net = {}, {}
    for u, v, c in arcs:
        room[u, v] = room.get((u, v), 0) + c
    for u, v, f in zip(src.tolist(), dst.tolist(), flow.tolist(), strict=True):
        assert 0 < f <= room[u, v]
        net[u], net[v] = net.get(u, 0) - f, net.get(v, 0) + f
    s, t = graph.ids[graph.s], graph.ids[graph.t]
    assert all(not x for v, x in net.items() if v not in (s, t))
    inside = set(graph.ids[near_s].tolist())
    assert s in inside and t not in inside
    return net.get(t, 0), sum(c for u, v, c in arcs if u in inside and v not in inside)


@pytest.mark.parametrize("name", PROGRAMS)
def test_programs_in_one_task(name):
    rng = random.Random(11)
    for _ in range(60):
        n = rng.randint(2, 8)
        arcs = [(u * 5 - 3, v * 5 - 3, rng.randint(0, 9)) for u in range(n) for v in range(n) if u != v for _ in range(rng.choice((0, 0, 1, 1, 2)))]
        graph = arrays(arcs, -3, (n - 1) * 5 - 3)
        assert proven(graph, arcs, PROGRAMS[name](graph)) == (smallest_cut(arcs, -3, (n - 1) * 5 - 3),) * 2


def test_state_and_certificate_of_a_long_chain(spark):
    """400 vertices in a row, both ways: more levels than supersteps could walk, a job each."""
    arcs = [(k, k + 1, 5 + k % 7) for k in range(400)] + [(k + 1, k, 3) for k in range(400)] + [(7, 7, 9), (0, 1, 0)]
    q = FlowProblem(spark.createDataFrame(arcs, ARCS), 0, 400)
    state, flows = pool.pooled(pool.kept(q), pool.static(True), settled=True)
    assert flow_value(state) == 5 and state.n == 401
    assert audit_slots(state.slots).isEmpty()
    assert tuple(certificate_of(q.arcs, flows, 0, 400, state.cut).first()) == (0, 0, 0)
    assert tuple(certify_pooled(q).first()) == (0, 0, 0)


def test_larger_networks_take_supersteps(spark, monkeypatch):
    arcs = [(0, 1, 4), (0, 2, 2), (1, 2, 3), (2, 1, 1), (1, 9, 1), (2, 9, 6)]
    q = pool.kept(FlowProblem(spark.createDataFrame(arcs, ARCS), 0, 9))
    here = solve_pooled(q, pool.static(True), solve_static_pushpull)
    monkeypatch.setattr(pool, "POOL", 5)
    monkeypatch.setattr(pool, "pooled", None)
    there = solve_pooled(q, pool.static(True), solve_static_pushpull)
    assert here.value == there.value == 6 and {tuple(r) for r in here.cut.collect()} == {tuple(r) for r in there.cut.collect()}
    assert tuple(certify_pooled(q).first()) == (0, 0, 0)


def test_faulty_arcs_and_ends(spark):
    for bad in ((0, None, 1), (0, 1, -1)):
        with pytest.raises(ValueError):
            pool.kept(FlowProblem(spark.createDataFrame([bad], "src long, dst long, cap long"), 0, 1))
    none = pool.kept(FlowProblem(spark.createDataFrame([], ARCS), 4, 2))
    state, flows = pool.pooled(none, pool.static(True), settled=True)
    assert flow_value(state) == 0 and flows.isEmpty() and {tuple(r) for r in state.cut.collect()} == {(4, "S"), (2, "T")}
    with pytest.raises(ValueError):
        pool.pooled(FlowProblem(none.arcs, 4, 4), pool.static(True))


def jobs(spark, work):
    """What ``work`` returns, and the Spark jobs it started."""
    group = f"jobs-{random.random()}"
    spark.sparkContext.setJobGroup(group, group)
    found = work()
    n = len(spark.sparkContext.statusTracker().getJobIdsForGroup(group))
    spark.sparkContext.setJobGroup("rest", "rest")
    return found, n


def chain(spark):
    """30 vertices in a row, both ways, seeds at its ends."""
    one = spark.range(29).select(F.col("id").alias("src"), (F.col("id") + 1).alias("dst"), (2 + F.col("id") % 5).alias("cap"))
    return one.unionByName(one.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "cap"))


def test_jobs_of_segment(spark):
    seeds = [spark.createDataFrame([(k, 9)], "id long, cap long") for k in (0, 29)]
    sides, n = jobs(spark, lambda: {r.id: r.side for r in segment(chain(spark), *seeds).collect()})
    assert sides == {k: "S" if k <= 25 else "T" for k in range(30)} and n < 40


def vectors(spark, d, n=120):
    rng = np.random.default_rng(5)
    rows = [(i, rng.standard_normal(6).astype(np.float32).tolist(), i % 4) for i in range(n)]
    spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int").repartition(3).write.parquet(f"{d}/embeddings.parquet")
    return str(d)


def test_vectors_are_compared_once(spark, tmp_path, monkeypatch):
    """The network's arcs lie in files; before, each reader of them compared all vectors again."""
    d = vectors(spark, tmp_path)
    want = {tuple(r) for r in W.segment(spark, d).arcs.collect()}
    assert "MapInArrow" not in physical(W.segment(spark, d).arcs)
    monkeypatch.setattr(W, "TILE", 7)
    assert {tuple(r) for r in W.segment(spark, d).arcs.collect()} == want
    rows = spark.read.parquet(f"{d}/embeddings.parquet").selectExpr("vec_id as u", "embedding as x")
    double = rows.withColumn("x", F.col("x").cast("array<double>"))
    assert {tuple(r) for r in W.nearest(double, 5).collect()} == {tuple(r) for r in W.nearest(rows, 5, 9).collect()}


def test_jobs_of_segment_sizes(spark, tmp_path):
    d = vectors(spark, tmp_path)
    sizes, n = jobs(spark, lambda: sum(r.n for r in registry.queries()["segment_sizes"](spark, d).collect()))
    assert sizes == 120 and n < 60


def test_jobs_of_certificate_copurchase(spark, tmp_path):
    rng = random.Random(6)
    save = lambda name, data, schema: spark.createDataFrame(data, schema).coalesce(1).write.parquet(f"{tmp_path}/{name}.parquet")
    save("customer", [(k, 13 * (k % 2)) for k in range(12)], "c_custkey long, c_nationkey int")
    save("orders", [(k, k % 12) for k in range(40)], "o_orderkey long, o_custkey long")
    save("lineitem", [(rng.randrange(40), rng.randrange(9), rng.randrange(4), float(rng.randint(1, 50))) for _ in range(150)], "l_orderkey long, l_partkey long, l_suppkey long, l_quantity double")
    zeros, n = jobs(spark, lambda: tuple(registry.queries()["certificate_copurchase"](spark, str(tmp_path)).first()))
    assert zeros == (0, 0, 0) and n < 60


def test_jobs_of_certificate_quality(spark, tmp_path):
    """One row of 60 documents with seeds at its ends: before, each level of it cost jobs."""
    spark.createDataFrame([(k, "de", "web", 10 * k) for k in range(60)], "doc_id long, lang string, source string, n_chars long").coalesce(1).write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([(0, 1), (59, 0)], "doc_id long, quality int").coalesce(1).write.parquet(f"{tmp_path}/labels.parquet")
    zeros, n = jobs(spark, lambda: tuple(registry.queries()["certificate_quality"](spark, str(tmp_path)).first()))
    assert zeros == (0, 0, 0) and n < 60


def test_jobs_of_certificate_segment(spark, tmp_path):
    d = vectors(spark, tmp_path)
    zeros, n = jobs(spark, lambda: tuple(registry.queries()["certificate_segment"](spark, d).first()))
    assert zeros == (0, 0, 0) and n < 60


@pytest.mark.parametrize("name", ["value_trade_augment_shortest", "value_trade_no_relabel"])
def test_jobs_of_trade_baselines(spark, tmp_path, name):
    rng, nations = random.Random(12), (3, 5, 8, 12, 14, 20, 24)
    rows = [(k, rng.choice(nations), rng.choice(nations), float(rng.randint(1, 50))) for k in range(200)]
    save = lambda name, data, schema: spark.createDataFrame(data, schema).coalesce(1).write.parquet(f"{tmp_path}/{name}.parquet")
    save("supplier", [(n, n) for n in nations], "s_suppkey long, s_nationkey int")
    save("customer", [(n, n) for n in nations], "c_custkey long, c_nationkey int")
    save("orders", [(k, v) for k, _, v, _ in rows], "o_orderkey long, o_custkey long")
    save("lineitem", [(k, u, q) for k, u, _, q in rows], "l_orderkey long, l_suppkey long, l_quantity double")
    arcs = [tuple(r) for r in W.trade(spark, str(tmp_path)).arcs.collect()]
    value, n = jobs(spark, lambda: tuple(registry.queries()[name](spark, str(tmp_path)).first()))
    assert value == (smallest_cut(arcs, 3, 12),) * 2 and n < 40


def test_copies_among_vectors_stay_few(spark, tmp_path):
    """200 copies tie with each other: a block hands on the nearest few of each, not all pairs."""
    x = np.random.default_rng(9).standard_normal((230, 4)).astype(np.float32)
    x[30:] = x[3]
    rows = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "u long, x array<float>").coalesce(1)
    found = W.nearest(rows, 5)
    dots = (x[:, None].astype(float) * x[None].astype(float)).sum(axis=2)
    want = {(i, int(j)) for i in range(230) for j in [k for k in np.lexsort((np.arange(230), -dots[i])) if k != i][:5]}
    assert {(r.u, r.v) for r in found.collect()} == want and found.count() == 230 * 5
    i, v = (k.ravel() for k in np.indices((3, 200)))
    kept = W.first_of(i, v[::-1].copy(), np.zeros(600), 5)
    assert sorted(zip(i[kept].tolist(), v[::-1][kept].tolist(), strict=True)) == [(a, b) for a in range(3) for b in range(5)]
