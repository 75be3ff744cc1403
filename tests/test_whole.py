"""Queries over whole tables against brute force on small ones."""

import random
from collections import Counter

import numpy as np
import pytest

from residua import workloads as W
from residua.operators import registry
from residua.reference import smallest_cut

NATIONS = (3, 12, 14, 17, 20, 24)


@pytest.fixture(scope="module")
def traded(spark, tmp_path_factory):
    """Tables in which half of the nations have keys of 14 or more, and the lines as (supplier's nation, customer's nation, quantity)."""
    d, rng = str(tmp_path_factory.mktemp("traded")), random.Random(8)
    rows = [(k, rng.choice(NATIONS), rng.choice(NATIONS), float(rng.randint(1, 50))) for k in range(150)]
    save = lambda name, data, schema: spark.createDataFrame(data, schema).coalesce(1).write.parquet(f"{d}/{name}.parquet")
    save("supplier", [(n, n) for n in NATIONS], "s_suppkey long, s_nationkey int")
    save("customer", [(n, n) for n in NATIONS], "c_custkey long, c_nationkey int")
    save("orders", [(k, v) for k, _, v, _ in rows], "o_orderkey long, o_custkey long")
    save("lineitem", [(k, u, q) for k, u, _, q in rows], "l_orderkey long, l_suppkey long, l_quantity double")
    return d, [(u, v, int(q)) for _, u, v, q in rows]


def test_trade_over_all_nations(spark, traded):
    d, rows = traded
    q = Counter()
    for u, v, n in rows:
        if u != v:
            q[u, v] += n
    arcs = [(u, v, 40 + n % 60 if u % 5 == v % 5 else 1 + n % 4) for (u, v), n in q.items()]
    found = registry.queries()
    assert sorted(tuple(r) for r in found["network_trade"](spark, d).collect()) == sorted(arcs)
    assert tuple(found["value_trade_static_pp"](spark, d).first()) == (smallest_cut(arcs, 3, 12),) * 2
    assert tuple(found["certificate_trade"](spark, d).first()) == (0, 0, 0)
    assert {r.src for r in W.trade14(spark, d).arcs.collect()} <= {3, 12}


def test_join_full_over_all_nations(spark, traded):
    d, rows = traded
    n = Counter((u, v) for u, v, _ in rows)
    want = {(u, v, n[u, v], n[v, u]) for u, v in n} | {(v, u, n[v, u], n[u, v]) for u, v in n}
    assert {tuple(r) for r in registry.queries()["op_join_full_nations"](spark, d).collect()} == want


def test_match_over_all_events(spark, tmp_path):
    events = [(k + 1, u, "ab"[(u + k) % 2]) for k, u in enumerate((5, 6, 7, 8, 9, 5, 6))]
    spark.createDataFrame(events, "event_id long, user_id long, event_type string").write.parquet(f"{tmp_path}/events.parquet")
    pairs = {("ab".index(t), u) for _, u, t in events}
    held = Counter(i for i, _ in pairs)
    arcs = [(-1, 100 + i, n * (1 + 2 * i) // 8) for i, n in held.items()] + [(100 + i, u, 1) for i, u in pairs] + [(u, -2, 1) for u in {u for _, u in pairs}]
    assert tuple(registry.queries()["value_match_events_static_data"](spark, str(tmp_path)).first()) == (smallest_cut(arcs, -1, -2),) * 2


def test_segment_over_all_vectors(spark, tmp_path):
    rng = np.random.default_rng(2)
    x = rng.standard_normal((130, 8)).astype(np.float32)
    x[100:] = x[7]
    spark.createDataFrame([(i, v.tolist(), i % 3) for i, v in enumerate(x)], "vec_id long, embedding array<float>, label int").write.parquet(f"{tmp_path}/embeddings.parquet")
    dots = (x[:, None].astype(float) * x[None].astype(float)).sum(axis=2)
    want = {(i, int(j)) for i in range(130) for j in [k for k in np.lexsort((np.arange(130), -dots[i])) if k != i][:5]}
    rows = spark.read.parquet(f"{tmp_path}/embeddings.parquet").selectExpr("vec_id as u", "embedding as x")
    for block in (1024, 16):
        assert {(r.u, r.v) for r in W.nearest(rows, 5, block).collect()} == want
    got = {(r.src, r.dst) for r in W.segment(spark, str(tmp_path)).arcs.where("src >= 0 and dst >= 0").collect()}
    assert got == want | {(j, i) for i, j in want}


def test_applications(spark, traded, tmp_path):
    d, _ = traded
    found = registry.queries()
    arcs = [tuple(r) for r in W.trade(spark, d).arcs.collect()]
    net = Counter()
    for u, v, c in arcs:
        net[v] += c // 4
        net[u] -= c // 4
    ends = [(-1, n, x) for n, x in net.items() if x > 0] + [(n, -2, -x) for n, x in net.items() if x < 0]
    moved, need = smallest_cut([(u, v, c - c // 4) for u, v, c in arcs] + ends, -1, -2), sum(x for x in net.values() if x > 0)
    assert tuple(found["circulation_feasible"](spark, d).first()) == (need, need, moved, moved == need)
    events = [(k + 1, u, "ab"[(u + k) % 2]) for k, u in enumerate((5, 6, 7, 8, 9, 5, 6))]
    spark.createDataFrame(events, "event_id long, user_id long, event_type string").write.parquet(f"{tmp_path}/events.parquet")
    pairs = {("ab".index(t), u) for _, u, t in events}
    held = Counter(i for i, _ in pairs)
    quota = [(-1, 100 + i, n * (1 + 2 * i) // 8) for i, n in held.items()]
    for name, gone in (("matching_pairs_count", False), ("matching_pairs_count_after_removal", True)):
        left = [(i, u) for i, u in pairs if not gone or ((2 << 40) + u) % 3]
        want = smallest_cut(quota + [(100 + i, u, 1) for i, u in left] + [(u, -2, 1) for u in {u for _, u in left}], -1, -2)
        assert found[name](spark, str(tmp_path)).first().n == want


def test_certificate_and_sides_of_segment(spark, tmp_path):
    rng = np.random.default_rng(3)
    rows = [(i, rng.standard_normal(4).astype(np.float32).tolist(), i % 3) for i in range(9)]
    spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int").write.parquet(f"{tmp_path}/embeddings.parquet")
    found = registry.queries()
    assert tuple(found["certificate_segment"](spark, str(tmp_path)).first()) == (0, 0, 0)
    assert sum(r.n for r in found["segment_sizes"](spark, str(tmp_path)).collect()) == 9
