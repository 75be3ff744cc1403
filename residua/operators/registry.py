"""Registered queries of the flow methods, with closed-form or one-step SQL twins."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .. import apps
from .. import experiments as X
from .. import pool
from .. import workloads as W
from ..cuts import cut_capacity
from ..engine import lowest_neighbours, plan_pushes, plan_relabels, steep_moves
from ..graph import SINK, SOURCE, FlowProblem, FlowState, build_slots, default_cycles, excess_of, init_state, saturate, simple_arcs
from ..heights import sink_levels, source_levels
from ..solvers import DYNAMIC, PROGRAMS, apply_updates, certify, certify_pooled, patch_totals, recompute, repair_overfull, saturate_cut, solve_augmenting, solve_pooled, solve_static, value_row
from ..streaming import maintain
from ..updates import make_updates
from . import relational

# ---- SQL of the networks

TRADE_Q = "SELECT CAST(s_nationkey AS BIGINT) AS u, CAST(c_nationkey AS BIGINT) AS v, CAST(sum(l_quantity) AS BIGINT) AS q FROM lineitem JOIN supplier ON l_suppkey = s_suppkey JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey WHERE s_nationkey < 14 AND c_nationkey < 14 AND s_nationkey <> c_nationkey GROUP BY 1, 2"
TRADE_ALL_Q = "SELECT CAST(s_nationkey AS BIGINT) AS u, CAST(c_nationkey AS BIGINT) AS v, CAST(sum(l_quantity) AS BIGINT) AS q FROM lineitem JOIN supplier ON l_suppkey = s_suppkey JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey WHERE s_nationkey <> c_nationkey GROUP BY 1, 2"
TRADE = f"SELECT u, v, CASE WHEN u % 5 = v % 5 THEN 40 + q % 60 ELSE 1 + q % 4 END AS cap FROM ({TRADE_Q})"
TRADE_ALL = f"SELECT u, v, CASE WHEN u % 5 = v % 5 THEN 40 + q % 60 ELSE 1 + q % 4 END AS cap FROM ({TRADE_ALL_Q})"
RANK = "(SELECT {c}, dense_rank() OVER (ORDER BY {c}) - 1 AS {r} FROM (SELECT DISTINCT {c} FROM {t}))"
TIER = f"SELECT u, CAST(c_nationkey AS BIGINT) AS v, count(*) AS cap FROM customer JOIN {RANK.format(c='c_mktsegment', r='u', t='customer')} USING (c_mktsegment) GROUP BY 1, 2"
DOCS = f"SELECT u, v, count(*) AS cap FROM documents JOIN {RANK.format(c='lang', r='u', t='documents')} USING (lang) JOIN {RANK.format(c='source', r='v', t='documents')} USING (source) GROUP BY 1, 2"
MATCH = f"SELECT DISTINCT u, user_id AS v, CAST(1 AS BIGINT) AS cap FROM events JOIN {RANK.format(c='event_type', r='u', t='events')} USING (event_type) WHERE event_id % 61 = 0"
MATCH_ALL = f"SELECT DISTINCT u, user_id AS v, CAST(1 AS BIGINT) AS cap FROM events JOIN {RANK.format(c='event_type', r='u', t='events')} USING (event_type)"
RULE = {
    None: "cap",
    "increase": "CASE WHEN (7*u+11*v) % 4 = 0 THEN cap + 1 + (31*u+17*v) % 100 ELSE cap END",
    "decrease": "CASE WHEN (7*u+11*v) % 4 = 0 THEN (cap * ((31*u+17*v) % 10)) // 10 ELSE cap END",
    "mixed": "CASE WHEN (7*u+11*v) % 8 = 0 THEN cap + 1 + (31*u+17*v) % 100 WHEN (7*u+11*v) % 8 = 4 THEN (cap * ((31*u+17*v) % 10)) // 10 ELSE cap END",
}


def cut_trade(kind: str | None = None) -> str:
    return f"WITH a AS (SELECT u, v, {RULE[kind]} AS cap FROM ({TRADE})), m AS (SELECT range AS m FROM range(16384) WHERE (range >> 3) & 1 = 1 AND (range >> 12) & 1 = 0), c AS (SELECT m, coalesce(sum(cap) FILTER ((m >> u) & 1 = 1 AND (m >> v) & 1 = 0), 0) AS cost FROM m, a GROUP BY m) SELECT CAST(min(cost) AS BIGINT) AS value, CAST(min(cost) AS BIGINT) AS cut_capacity FROM c"


def cut_bipartite(middle: str, out_cap: str, in_cap: str, kind: str | None = None) -> str:
    """Every subset of the small side stays with the source; each vertex of the other side takes its cheaper side."""
    return f"WITH b AS ({middle}), l AS (SELECT u, ({out_cap}) AS cap FROM (SELECT u, sum(cap) AS m FROM b GROUP BY u)), r AS (SELECT v, ({in_cap}) AS cap FROM (SELECT v, sum(cap) AS m FROM b GROUP BY v)), a AS (SELECT u, v, {RULE[kind]} AS cap FROM b), m AS (SELECT range AS k FROM range((SELECT 1 << CAST(max(u) + 1 AS INTEGER) FROM b))), x AS (SELECT k, coalesce(sum(cap) FILTER ((k >> u) & 1 = 0), 0) AS cost FROM m, l GROUP BY k), y AS (SELECT k, v, coalesce(sum(cap) FILTER ((k >> u) & 1 = 1), 0) AS inflow FROM m, a GROUP BY k, v), z AS (SELECT k, sum(least(inflow, r.cap)) AS cost FROM y JOIN r USING (v) GROUP BY k) SELECT CAST(min(x.cost + z.cost) AS BIGINT) AS value, CAST(min(x.cost + z.cost) AS BIGINT) AS cut_capacity FROM x JOIN z USING (k)"


NEW_CAP = {"increase": "cap + 1 + h % 100", "decrease": "(cap * (h % 10)) // 10", "mixed": "CASE WHEN k % 2 = 1 THEN cap + 1 + h % 100 ELSE (cap * (h % 10)) // 10 END"}

CLOSED = {
    "trade14": cut_trade,
    "tier": lambda kind=None: cut_bipartite(TIER, "(m * (1 + 2 * u)) // 4", "(m * (1 + v % 4)) // 3", kind),
    "docs": lambda kind=None: cut_bipartite(DOCS, "(m * (1 + u)) // 2", "(m * (1 + v % 3)) // 2", kind),
    "match": lambda kind=None: cut_bipartite(MATCH, "(m * (1 + 2 * u)) // 8", "1", kind),
    "match_events": lambda kind=None: cut_bipartite(MATCH_ALL, "(m * (1 + 2 * u)) // 8", "1", kind),
    "tree": lambda kind=None: f"SELECT CAST(sum(value) AS BIGINT) AS value, CAST(sum(value) AS BIGINT) AS cut_capacity FROM ({relational.ORACLES['op_udaf']})",
}
ZERO = "SELECT CAST(0 AS BIGINT) AS capacity_violations, CAST(0 AS BIGINT) AS conservation_violations, CAST(0 AS BIGINT) AS cut_gap"

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def put(name: str, query: Callable, sql: str | None = None) -> None:
    QUERIES[name] = query
    if sql:
        ORACLES[name] = sql


# ---- values from scratch, after batches, of baselines

for _net, _programs in {"tier": ("static_topo", "static_data", "static_pp"), "trade14": ("static_topo", "static_data", "static_pp"), "tree": ("static_data",), "docs": ("static_pp",), "match": ("static_data",), "match_events": ("static_data",)}.items():
    for _p in _programs:
        put(f"value_{_net}_{_p}", lambda s, d, net=_net, p=_p: (lambda q: value_row(PROGRAMS[p](q), q.arcs))(W.NETWORKS[net](s, d)), CLOSED[_net]())


# the single-arc steps, K = average degree: 'fused' with steep arcs filled, 'split', and the worklist frozen for a round
for _p in PROGRAMS:
    put(f"value_tier_{_p}_fused", lambda s, d, p=_p: (lambda q: value_row(PROGRAMS[p](q, step="fused"), q.arcs))(W.tier(s, d)), CLOSED["tier"]())
put("value_tier_static_data_split", lambda s, d: (lambda q: value_row(PROGRAMS["static_data"](q, step="split"), q.arcs))(W.tier(s, d)), CLOSED["tier"]())
put("value_tier_static_data_frozen", lambda s, d: (lambda q: value_row(PROGRAMS["static_data"](q, step="fused", worklist="frozen"), q.arcs))(W.tier(s, d)), CLOSED["tier"]())


def after_batch(net: str, kind: str, program: str, **how: str) -> Callable:
    """Solves the network, then the fixtures' batch from the residual state (or from zero for 'recompute')."""

    def run(s: SparkSession, d: str) -> DataFrame:
        old, new = W.NETWORKS[net](s, d), W.NETWORKS[net](s, d, kind)
        before = simple_arcs(old.arcs)
        changed = simple_arcs(new.arcs).join(before.withColumnRenamed("cap", "old"), ["src", "dst"], "left").where("old is null or old <> cap")
        batch = changed.select("src", "dst", F.col("cap").alias("new_cap"), F.lit(0).cast("long").alias("seq"))
        if program == "recompute":
            return value_row(recompute(old, batch), new.arcs)
        base = PROGRAMS["static_pp"](old).state
        return value_row(DYNAMIC[program](base, batch, **how), new.arcs)

    return run


for _net, _kind, _p in (("trade14", "increase", "dyn_pp"), ("trade14", "decrease", "dyn_data"), ("trade14", "mixed", "alt_pp"), ("trade14", "mixed", "recompute"), ("tier", "increase", "dyn_data"), ("tier", "decrease", "dyn_topo"), ("tier", "mixed", "dyn_pp"), ("docs", "decrease", "dyn_pp"), ("docs", "increase", "alt_pp")):
    put(f"value_{_net}_{_kind}_{_p}", after_batch(_net, _kind, _p), CLOSED[_net](_kind))
for _kind, _p in (("increase", "dyn_topo"), ("mixed", "dyn_data"), ("decrease", "dyn_pp"), ("increase", "alt_pp")):
    put(f"value_tier_{_kind}_{_p}_fused", after_batch("tier", _kind, _p, step="fused"), CLOSED["tier"](_kind))
put("value_trade14_augment_shortest", lambda s, d: (lambda q: value_row(solve_augmenting(q), q.arcs))(W.trade14(s, d)), cut_trade())
put("value_trade14_augment_any", lambda s, d: (lambda q: value_row(solve_augmenting(q, "any"), q.arcs))(W.trade14(s, d)), cut_trade())
put("value_trade14_no_relabel", lambda s, d: (lambda q: value_row(solve_static(q, global_relabel="once", step="fused"), q.arcs))(W.trade14(s, d)), cut_trade())
# all nations: 2^25 cuts are too many to enumerate, so these have no twin; the certificate proves the value
for _p in PROGRAMS:
    put(f"value_trade_{_p}", lambda s, d, p=_p: (lambda q: value_row(PROGRAMS[p](q), q.arcs))(W.trade(s, d)))
for _kind, _p in (("increase", "dyn_pp"), ("decrease", "dyn_data"), ("mixed", "alt_pp"), ("mixed", "recompute")):
    put(f"value_trade_{_kind}_{_p}", after_batch("trade", _kind, _p))
put("value_trade_augment_shortest", lambda s, d: (lambda q: value_row(solve_pooled(q, pool.augmenting("shortest", 500), solve_augmenting), q.arcs))(pool.kept(W.trade(s, d))))
put("value_trade_augment_any", lambda s, d: (lambda q: value_row(solve_augmenting(q, "any"), q.arcs))(W.trade(s, d)))
put("value_trade_no_relabel", lambda s, d: (lambda q: value_row(solve_pooled(q, pool.static(False, relabel="once", step="fused"), lambda p: solve_static(p, global_relabel="once", step="fused")), q.arcs))(pool.kept(W.trade(s, d))))
for _net in ("relay", "dialog", "trade14", "trade"):
    put(f"certificate_{_net}", lambda s, d, net=_net: (lambda q: certify(q, PROGRAMS["static_pp"](q)))(W.NETWORKS[net](s, d)), ZERO)

# larger networks: no twin, three zeros are the proof
for _net in ("relay_comm", "links", "supply"):
    put(f"certificate_{_net}", lambda s, d, net=_net: (lambda q: certify(q, PROGRAMS["static_pp"](q)))(W.NETWORKS[net](s, d)))
# in one task where the network fits it
for _net in ("copurchase", "segment", "quality"):
    put(f"certificate_{_net}", lambda s, d, net=_net: certify_pooled(W.NETWORKS[net](s, d)))

# ---- applications


def inner(q: FlowProblem) -> DataFrame:
    return q.arcs.where((F.col("src") != SOURCE) & (F.col("dst") != SINK))


def outer(q: FlowProblem, side: str) -> DataFrame:
    """``(id, cap)`` of the arcs from the super source or to the super sink."""
    return q.arcs.where(F.col("src") == SOURCE).select(F.col("dst").alias("id"), "cap") if side == "source" else q.arcs.where(F.col("dst") == SINK).select(F.col("src").alias("id"), "cap")


def assigned(s: SparkSession, d: str):
    q = W.match_events(s, d)
    return apps.assign(inner(q).select(F.col("src").alias("left"), F.col("dst").alias("right")), outer(q, "source").withColumnRenamed("id", "left"))


def reassigned(s: SparkSession, d: str) -> DataFrame:
    """The assignment after every pair of a user with an id divisible by 3 went."""
    gone = inner(W.match_events(s, d)).where("dst % 3 = 0").select("src", "dst", F.lit(0).cast("long").alias("new_cap"), F.lit(0).cast("long").alias("seq"))
    return apps.reassign(assigned(s, d)[1], gone)[0]


def balanced(s: SparkSession, d: str) -> DataFrame:
    """Whether trade between all nations can circulate with a quarter of each capacity as its lower bound."""
    a = W.trade(s, d).arcs.select("src", "dst", F.floor(F.col("cap") / 4).cast("long").alias("lo"), F.col("cap").alias("hi"))
    return apps.feasible_circulation(a.select(F.col("src").alias("id"), F.lit(0).cast("long").alias("supply")).distinct(), a)


count = lambda df: df.agg(F.count(F.lit(1)).alias("n"))
put("matching_pairs_count", lambda s, d: count(assigned(s, d)[0]), f"SELECT value AS n FROM ({CLOSED['match_events']()})")
put("matching_pairs_count_after_removal", lambda s, d: count(reassigned(s, d)))
put("segment_sizes", lambda s, d: (lambda q: apps.segment(inner(q), outer(q, "source"), outer(q, "sink")))(W.segment(s, d)).groupBy("side").agg(F.count(F.lit(1)).alias("n")))
put("circulation_feasible", balanced)
put("route_flow_tier", lambda s, d: apps.route(W.tier(s, d)).where(F.col("src") == SOURCE).agg(F.sum("flow").cast("long").alias("flow")), f"SELECT value AS flow FROM ({CLOSED['tier']()})")
put("cheapest_cut_tier", lambda s, d: apps.cheapest_cut(W.tier(s, d)).agg(F.sum("cap").cast("long").alias("cap")), f"SELECT value AS cap FROM ({CLOSED['tier']()})")

# ---- networks and single steps

put("network_relay", lambda s, d: W.relay(s, d).arcs, "SELECT DISTINCT u AS src, v AS dst, CAST(1 + (7 * u + 13 * v) % 100 AS BIGINT) AS cap FROM (SELECT user_id AS u, lead(user_id) OVER (PARTITION BY event_type ORDER BY ts, event_id) AS v FROM events) WHERE v IS NOT NULL AND u <> v")
put("network_segment", lambda s, d: W.segment(s, d).arcs)
put("network_sizes", lambda s, d: sizes(s, d))


def sizes(s: SparkSession, d: str) -> DataFrame:
    out = None
    for name, build in W.NETWORKS.items():
        one = build(s, d).arcs.agg(F.lit(name).alias("network"), F.count(F.lit(1)).alias("arcs"), F.sum("cap").cast("long").alias("capacity"))
        out = one if out is None else out.unionByName(one)
    return out


SLOTS = f"SELECT src, dst, CAST(sum(o) AS BIGINT) AS cap_out, CAST(sum(i) AS BIGINT) AS cap_in FROM (SELECT u AS src, v AS dst, cap AS o, 0 AS i FROM t UNION ALL SELECT v, u, 0, cap FROM t) GROUP BY 1, 2"
put("degree_stats_relay", lambda s, d: (lambda a: a.groupBy("src").agg(F.count(F.lit(1)).alias("n")).agg(F.count(F.lit(1)).alias("vertices"), F.sum("n").alias("arcs"), F.max("n").alias("top")))(W.relay(s, d).arcs), f"WITH a AS ({ORACLES['network_relay']}), g AS (SELECT src, count(*) AS n FROM a GROUP BY 1) SELECT count(*) AS vertices, CAST(sum(n) AS BIGINT) AS arcs, max(n) AS top FROM g")
put("default_cycles_relay", lambda s, d: cycles(s, d), f"WITH a AS ({ORACLES['network_relay']}) SELECT CAST(greatest(1, round(count(*) / (SELECT count(DISTINCT x) FROM (SELECT src AS x FROM a UNION SELECT dst FROM a)))) AS BIGINT) AS cycles FROM a")


def cycles(s: SparkSession, d: str) -> DataFrame:
    a = W.relay(s, d).arcs
    v = a.select("src").union(a.select("dst")).distinct().count()
    return s.createDataFrame([(default_cycles(a.count(), v, None),)], "cycles long")


def steps(net: str, build: Callable[..., FlowProblem], trade: str, n: int) -> None:
    """Network, slots, single steps, levels and batches of a network of ``n`` nations with its SQL ``trade``."""

    put(f"network_{net}", lambda s, d: build(s, d).arcs, f"SELECT u AS src, v AS dst, CAST(cap AS BIGINT) AS cap FROM ({trade})")
    head = f"WITH t AS ({trade}), sl AS ({SLOTS}), st AS (SELECT *, CASE WHEN src = 3 THEN cap_out WHEN dst = 3 THEN -cap_in ELSE 0 END AS net FROM sl)"
    put(f"slots_{net}", lambda s, d: build_slots(build(s, d).arcs), f"{head} SELECT src, dst, cap_out, cap_in, CAST(0 AS BIGINT) AS net FROM st")
    put(f"init_excess_{net}", lambda s, d: excess_of(saturate(build_slots(build(s, d).arcs), 3)), f"{head} SELECT src AS id, CAST(-sum(net) AS BIGINT) AS excess FROM st GROUP BY 1")
    ex = f"{head}, v AS (SELECT src AS id, -sum(net) AS excess, CASE WHEN src = 3 THEN {n} WHEN src = 12 THEN 0 ELSE 1 END AS height FROM st GROUP BY 1), near AS (SELECT st.src, x.excess, x.height AS own, y.height AS far, st.dst, cap_out - net AS room FROM st JOIN v x ON x.id = st.src AND x.excess > 0 AND x.id NOT IN (3, 12) JOIN v y ON y.id = st.dst WHERE cap_out > net), low AS (SELECT * FROM near QUALIFY row_number() OVER (PARTITION BY src ORDER BY far, dst) = 1)"

    def snapshot(s: SparkSession, d: str):
        """The network after saturation, with heights 0 at the sink, ``n`` at the source and 1 elsewhere."""
        slots = saturate(build_slots(build(s, d).arcs), 3)
        verts = excess_of(slots).select("id", F.when(F.col("id") == 3, n).when(F.col("id") == 12, 0).otherwise(1).cast("long").alias("height"), "excess")
        return slots, verts, lowest_neighbours(slots, verts, verts.where("excess > 0 and id not in (3, 12)"))

    put(f"lowest_neighbour_{net}", lambda s, d: snapshot(s, d)[2].select("src", "dst", "far", "room"), f"{ex} SELECT src, dst, CAST(far AS BIGINT) AS far, CAST(room AS BIGINT) AS room FROM low")
    put(f"push_step_{net}", lambda s, d: plan_pushes(snapshot(s, d)[2]).select("src", "dst", "amount", "full"), f"{ex} SELECT src, dst, CAST(least(excess, room) AS BIGINT) AS amount, least(excess, room) = room AS \"full\" FROM low WHERE own > far")
    def grounded(s: SparkSession, d: str) -> DataFrame:
        """Lowest neighbours in the very first state: every height 0 but the source's, so that active vertices relabel."""
        slots, verts, _ = snapshot(s, d)
        verts = verts.withColumn("height", F.when(F.col("id") == 3, F.lit(n)).otherwise(F.lit(0)).cast("long"))
        return lowest_neighbours(slots, verts, verts.where("excess > 0 and id not in (3, 12)"))

    put(f"relabel_step_{net}", lambda s, d: plan_relabels(grounded(s, d), n).select("src", "height"), f"{ex.replace('WHEN src = 12 THEN 0 ELSE 1 END AS height', 'ELSE 0 END AS height')} SELECT src, CAST(least(far + 1, {n}) AS BIGINT) AS height FROM low WHERE own <= far")

    def steep(s: SparkSession, d: str) -> DataFrame:
        slots = saturate(build_slots(build(s, d).arcs), 3)
        verts = excess_of(slots).select("id", (F.col("id") * 5 % 7).alias("height"), "excess")
        return steep_moves(FlowState(slots, verts, 3, 12, n, 0), slots).select("src", "dst", F.col("amount").alias("room"))

    put(f"steep_arcs_{net}", steep, f"{head} SELECT src, dst, CAST(cap_out - net AS BIGINT) AS room FROM st WHERE cap_out > net AND src NOT IN (3, 12) AND src * 5 % 7 > dst * 5 % 7 + 1")

    def levels(s: SparkSession, d: str) -> DataFrame:
        p = build(s, d)
        slots = build_slots(p.arcs.where("cap <= 3"))
        return sink_levels(slots, s.range(1).select(F.lit(12).cast("long").alias("id")), n)[0]

    put(f"levels_single_{net}", levels, f"WITH RECURSIVE t AS ({trade}), r(id, level) AS (SELECT CAST(12 AS BIGINT), CAST(0 AS BIGINT) UNION SELECT t.u, r.level + 1 FROM r JOIN t ON t.v = r.id WHERE t.cap <= 3 AND t.cap > 0 AND r.level < {n}) SELECT id, min(level) AS level FROM r GROUP BY id")

    def multi(s: SparkSession, d: str) -> DataFrame:
        slots = build_slots(build(s, d).arcs.where("cap <= 3"))
        return sink_levels(slots, s.createDataFrame([(12,), (5,)], "id long"), n, (3,))[0]

    put(f"levels_multi_{net}", multi, f"WITH RECURSIVE t AS ({trade}), r(id, level) AS (SELECT CAST(x AS BIGINT), CAST(0 AS BIGINT) FROM (VALUES (12), (5)) q(x) UNION SELECT t.u, r.level + 1 FROM r JOIN t ON t.v = r.id WHERE t.cap <= 3 AND t.cap > 0 AND t.u <> 3 AND r.level < {n}) SELECT id, min(level) AS level FROM r GROUP BY id")

    def patch(s: SparkSession, d: str) -> DataFrame:
        old, new = build(s, d).arcs, build(s, d, "mixed").arcs
        return new.join(old.withColumnRenamed("cap", "old"), ["src", "dst"]).where("cap <> old").select("src", "dst", F.col("cap").alias("new_cap"), F.lit(0).cast("long").alias("seq"))

    renewed = f"WITH t AS (SELECT u, v, {RULE['mixed']} AS cap FROM ({trade})), sl AS ({SLOTS}), o AS (WITH t AS ({trade}) {SLOTS}), p AS (SELECT sl.src, sl.dst, sl.cap_out, sl.cap_in, CASE WHEN sl.src = 3 THEN o.cap_out WHEN sl.dst = 3 THEN -o.cap_in ELSE 0 END AS net FROM sl JOIN o USING (src, dst))"
    put(f"patched_slots_{net}", lambda s, d: apply_updates(saturate(build_slots(build(s, d).arcs), 3), patch(s, d)), f"{renewed} SELECT src, dst, cap_out, cap_in, CAST(net AS BIGINT) AS net FROM p")
    put(f"repaired_slots_{net}", lambda s, d: repair_overfull(apply_updates(saturate(build_slots(build(s, d).arcs), 3), patch(s, d))), f"{renewed} SELECT src, dst, cap_out, cap_in, CAST(greatest(-cap_in, least(cap_out, net)) AS BIGINT) AS net FROM p")
    put(f"excess_after_patch_{net}", lambda s, d: excess_of(saturate(repair_overfull(apply_updates(saturate(build_slots(build(s, d).arcs), 3), patch(s, d))), 3)), f"{renewed} SELECT src AS id, CAST(-sum(CASE WHEN src = 3 THEN cap_out WHEN dst = 3 THEN -cap_in ELSE greatest(-cap_in, least(cap_out, net)) END) AS BIGINT) AS excess FROM p GROUP BY 1")
    put(f"cut_saturation_{net}", lambda s, d: saturate_cut(build_slots(build(s, d).arcs), s.range(n).select("id", F.when(F.col("id") % 3 == 0, "S").otherwise("T").alias("side"))), f"{head} SELECT src, dst, cap_out, cap_in, CAST(CASE WHEN src % 3 = 0 AND dst % 3 <> 0 THEN cap_out WHEN src % 3 <> 0 AND dst % 3 = 0 THEN -cap_in ELSE 0 END AS BIGINT) AS net FROM st")
    put(f"patch_totals_{net}", lambda s, d: patch_totals(apply_updates(saturate(build_slots(build(s, d).arcs), 3), patch(s, d)), 3, 12), f"{renewed}, e AS (SELECT src AS id, -sum(CASE WHEN src = 3 THEN cap_out WHEN dst = 3 THEN -cap_in ELSE greatest(-cap_in, least(cap_out, net)) END) AS e FROM p GROUP BY 1) SELECT (SELECT count(*) FROM p WHERE net > cap_out) AS overfull, CAST(coalesce(sum(e) FILTER (e > 0), 0) AS BIGINT) AS overflow, CAST(coalesce(sum(-e) FILTER (e < 0), 0) AS BIGINT) AS deficit FROM e WHERE id NOT IN (3, 12)")
    put(f"levels_forward_{net}", lambda s, d: source_levels(build_slots(build(s, d).arcs.where("cap <= 3")), s.createDataFrame([(3,)], "id long"), n)[0], f"WITH RECURSIVE t AS ({trade}), r(id, level) AS (SELECT CAST(3 AS BIGINT), CAST(0 AS BIGINT) UNION SELECT t.v, r.level + 1 FROM r JOIN t ON t.u = r.id WHERE t.cap <= 3 AND t.cap > 0 AND r.level < {n}) SELECT id, min(level) AS level FROM r GROUP BY id")
    sides = lambda s: s.range(n).select("id", F.when(F.col("id") % 3 == 0, "S").otherwise("T").alias("side"))
    put(f"cutcap_{net}", lambda s, d: s.createDataFrame([(cut_capacity(build(s, d).arcs, sides(s)),)], "capacity long"), f"SELECT CAST(sum(cap) AS BIGINT) AS capacity FROM ({trade}) WHERE u % 3 = 0 AND v % 3 <> 0")
    put(f"state_size_{net}", lambda s, d: init_state(build(s, d)).size(), f"{head}, k AS (SELECT count(*) AS slots, count(DISTINCT src) AS vertices FROM sl) SELECT slots, vertices, 40 * slots + 24 * vertices AS bytes FROM k")

    def in_sql(s: SparkSession, d: str) -> DataFrame:
        init_state(build(s, d)).register_views(f"residua_{net}")
        return s.sql(f"SELECT id, excess, (SELECT count(*) FROM residua_{net}_slots WHERE src = id AND cap_out > net) AS open FROM residua_{net}_verts")

    put(f"views_{net}", in_sql, f"{head} SELECT src AS id, CAST(-sum(net) AS BIGINT) AS excess, count(*) FILTER (cap_out > net) AS open FROM st GROUP BY 1")
    for _kind in ("increase", "decrease", "mixed"):
        put(f"updates_{_kind}_{net}", lambda s, d, kind=_kind: make_updates(build(s, d).arcs, 10, kind, 3, 12), f"WITH a AS ({trade}), b AS (SELECT *, (u * 7919 + v * 104729 + 31) % 1000003 AS h FROM a), c AS (SELECT *, row_number() OVER (ORDER BY CASE WHEN u = 3 OR v = 12 THEN h / 8.0::DOUBLE ELSE CAST(h AS DOUBLE) END, u, v) AS k FROM b) SELECT u AS src, v AS dst, CAST({NEW_CAP[_kind]} AS BIGINT) AS new_cap, CAST(0 AS BIGINT) AS seq FROM c WHERE k <= (SELECT count(*) FROM a) * 10 // 100")


steps("trade14", W.trade14, TRADE, 14)
steps("trade", W.trade, TRADE_ALL, 25)

# ---- the experiments, on the smallest network; seconds are left out where values have a twin

TREE_ARCS = "WITH d AS (SELECT CAST(n_regionkey AS BIGINT) AS r, CAST(n_nationkey AS BIGINT) AS n, count(c_custkey) AS d FROM nation LEFT JOIN customer ON c_nationkey = n_nationkey GROUP BY 1, 2), a AS (SELECT CAST(-1 AS BIGINT) AS src, 1099511627776 + r AS dst, CAST((sum(d) * (2 + r)) // 4 AS BIGINT) AS cap FROM d GROUP BY r UNION ALL SELECT 1099511627776 + r, 2199023255552 + n, d FROM d UNION ALL SELECT 2199023255552 + n, -2, 1 + (d * (1 + n % 3)) // 2 FROM d)"
SHARE = 20


def tree_regime(kind: str) -> str:
    """Nested minima over the patched tree, one row for each program."""
    named = ", ".join(f"('{p}')" for p in X.SEVEN)
    return f"{TREE_ARCS}, b AS (SELECT *, ((src * 7919 + dst * 104729 + 31) % 1000003 + 1000003) % 1000003 AS h FROM a), c AS (SELECT *, row_number() OVER (ORDER BY CASE WHEN src = -1 OR dst = -2 THEN h / 8.0::DOUBLE ELSE CAST(h AS DOUBLE) END, src, dst) AS k FROM b), p AS (SELECT src, dst, CASE WHEN k <= (SELECT count(*) FROM a) * {SHARE} // 100 THEN {NEW_CAP[kind]} ELSE cap END AS cap FROM c), low AS (SELECT m.src AS r, sum(least(m.cap, l.cap)) AS cap FROM p m JOIN p l ON m.dst = l.src WHERE m.src <> -1 GROUP BY 1), f AS (SELECT CAST(sum(least(x.cap, low.cap)) AS BIGINT) AS value FROM p x JOIN low ON x.dst = low.r WHERE x.src = -1) SELECT 'tree' AS graph, '{kind}' AS kind, CAST({SHARE} AS INTEGER) AS pct, program, value FROM f, (VALUES {named}) q(program)"


for _kind in NEW_CAP:
    put(f"experiment_regime_{_kind}", lambda s, d, kind=_kind: X.regime(W.tree(s, d), kind, [SHARE]).select("graph", "kind", "pct", "program", "value"), tree_regime(_kind))
put("experiment_sweep_cycles", lambda s, d: X.sweep_cycles(W.tree(s, d), (1, 2, 4)).select("graph", "cycles", "value"), f"SELECT 'tree' AS graph, CAST(k AS INTEGER) AS cycles, value FROM ({CLOSED['tree']()}), (VALUES (1), (2), (4)) q(k)")
put("experiment_graphs", lambda s, d: X.graph_table(s, [W.tree(s, d)]), f"{TREE_ARCS} SELECT 'tree' AS graph, CAST((SELECT count(*) FROM (SELECT src FROM a UNION SELECT dst FROM a)) AS BIGINT) AS vertices, (SELECT count(*) FROM a WHERE cap > 0) AS arcs, CAST(-1 AS BIGINT) AS s, CAST(-2 AS BIGINT) AS t, (SELECT value FROM ({CLOSED['tree']()})) AS value")
put("experiment_height_bound", lambda s, d: X.height_bound(W.trade14(s, d)), "SELECT CAST(0 AS BIGINT) AS above, CAST(0 AS BIGINT) AS fell")
put("experiment_active_trace", lambda s, d: X.active_trace(W.tree(s, d)))
put("experiment_cut_drift", lambda s, d: X.drift(W.tree(s, d), "mixed", SHARE))

# ---- streams

DAY = "CAST(ts AS DATE)"


def stream(s: SparkSession, d: str, make: Callable[[DataFrame], DataFrame], mode: str = "append") -> DataFrame:
    return maintain.run_to_table(make(maintain.event_stream(s, d)), mode)


def windowed(w) -> Callable[[DataFrame], DataFrame]:
    return lambda e: maintain.changes(e).groupBy(w("ts").alias("w")).agg(F.sum("new_cap").alias("cap"), F.count(F.lit(1)).alias("n")).select(F.unix_seconds("w.start").alias("start"), "cap", "n")


CHG = "SELECT user_id % 14 AS src, event_id % 14 AS dst, CAST(1 + CAST(floor(value) AS BIGINT) % 100 AS BIGINT) AS new_cap, event_id AS seq, ts FROM events WHERE user_id % 14 <> event_id % 14"
put("stream_tumbling", lambda s, d: stream(s, d, windowed(lambda c: F.window(c, "1 day")), "complete"), f"SELECT CAST(epoch(date_trunc('day', ts)) AS BIGINT) AS start, CAST(sum(new_cap) AS BIGINT) AS cap, count(*) AS n FROM ({CHG}) GROUP BY 1")
put("stream_sliding", lambda s, d: stream(s, d, windowed(lambda c: F.window(c, "1 day", "6 hours")), "complete"), f"SELECT CAST((CAST(floor(epoch(ts)) AS BIGINT) // 21600) * 21600 AS BIGINT) - k.range * 21600 AS start, CAST(sum(new_cap) AS BIGINT) AS cap, count(*) AS n FROM ({CHG}), range(4) k GROUP BY 1")
put("stream_session", lambda s, d: stream(s, d, lambda e: e.withWatermark("ts", "1 hour").groupBy("user_id", F.session_window("ts", "1 hour").alias("w")).agg(F.count(F.lit(1)).alias("n")).select("user_id", "n"), "append"))
put("stream_dedup", lambda s, d: stream(s, d, lambda e: maintain.changes(e).withWatermark("ts", "3650 days").dropDuplicatesWithinWatermark(["src", "dst", "new_cap"]).select("src", "dst", "new_cap")), f"SELECT DISTINCT src, dst, new_cap FROM ({CHG})")
put("stream_late", lambda s, d: stream(s, d, lambda e: maintain.changes(e).withWatermark("ts", "1 day").groupBy(F.window("ts", "1 day").alias("w")).agg(F.count(F.lit(1)).alias("n")).select(F.unix_seconds("w.start").alias("start"), "n")))
put("stream_last_cap", lambda s, d: stream(s, d, lambda e: maintain.changes(e).groupBy("src", "dst").agg(F.max_by("new_cap", F.struct("ts", "seq")).alias("new_cap")), "complete"), f"SELECT src, dst, max_by(new_cap, struct_pack(a := ts, b := seq)) AS new_cap FROM ({CHG}) GROUP BY 1, 2")

put("stream_update_mode", lambda s, d: maintain.run_to_table(maintain.changes(maintain.event_stream(s, d)).groupBy("src").agg(F.max("new_cap").alias("top"), F.count(F.lit(1)).alias("n")), "update", keys=("src",)), f"SELECT src, max(new_cap) AS top, count(*) AS n FROM ({CHG}) GROUP BY 1")
put("stream_static_join", lambda s, d: stream(s, d, lambda e: maintain.changes(e).join(W.trade14(s, d).arcs, ["src", "dst"]).select("seq", "src", "dst", "cap", "new_cap")), f"SELECT seq, c.src, c.dst, CAST(t.cap AS BIGINT) AS cap, new_cap FROM ({CHG}) c JOIN ({TRADE}) t ON t.u = c.src AND t.v = c.dst")


def confirmations(s: SparkSession, d: str) -> DataFrame:
    """Changes with an even number announce, those with an odd one confirm; both are streams of their own."""
    half = lambda odd: maintain.event_stream(s, d).where(F.col("event_id") % 2 == odd).select(F.col("user_id").alias("key"), F.col("event_id").alias("seq"), "ts")
    return maintain.run_to_table(maintain.confirmed(half(0), half(1)))


put("stream_interval_join", confirmations, "SELECT a.user_id AS key, a.event_id AS announced, b.event_id AS confirmed FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_id % 2 = 0 AND b.event_id % 2 = 1 AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 DAY")
put("stream_foreach_batch", lambda s, d: maintain.keep_current(maintain.changes(maintain.event_stream(s, d)), PROGRAMS["static_pp"](W.trade14(s, d)).state).agg(F.max_by("value", "batch_id").alias("value")), f"WITH l AS (SELECT src AS u, dst AS v, max_by(new_cap, struct_pack(a := ts, b := seq)) AS cap FROM ({CHG}) GROUP BY 1, 2), a AS (SELECT u, v, coalesce(l.cap, t.cap) AS cap FROM ({TRADE}) t FULL JOIN l USING (u, v)), m AS (SELECT range AS m FROM range(16384) WHERE (range >> 3) & 1 = 1 AND (range >> 12) & 1 = 0), c AS (SELECT m, coalesce(sum(cap) FILTER ((m >> u) & 1 = 1 AND (m >> v) & 1 = 0), 0) AS cost FROM m, a GROUP BY m) SELECT CAST(min(cost) AS BIGINT) AS value FROM c")


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return QUERIES | relational.QUERIES


def oracle_sql() -> dict[str, str]:
    return ORACLES | relational.ORACLES


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Maximum flow of the routing network by the worklist program, with the capacity of its cut."""
    problem: FlowProblem = W.tier(spark, sf_dir)
    result = solve_static(problem)
    assert problem.t == SINK and cut_capacity(problem.arcs, result.cut) == result.value
    return value_row(result, problem.arcs)

