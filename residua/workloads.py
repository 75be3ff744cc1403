"""Flow networks built from the given tables. Vertex ids of layered networks are ``layer * 2^40 + key``."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .graph import SINK, SOURCE, FlowProblem, with_super_terminals
from .lineage import cut
from .sources.tables import read

#: Rows of a block of vectors that are multiplied with another block at once.
TILE = 512


def node(layer: int, key):
    return F.lit(layer << 40) + F.col(key).cast("long") if isinstance(key, str) else F.lit(layer << 40) + key.cast("long")


def arc(df: DataFrame, src, dst, cap) -> DataFrame:
    return df.select(src.cast("long").alias("src"), dst.cast("long").alias("dst"), cap.cast("long").alias("cap"))


def ranked(df: DataFrame, column: str, name: str) -> DataFrame:
    """Distinct values of a column of small domain with 0-based rank by code point."""
    return df.select(column).distinct().withColumn(name, F.dense_rank().over(Window.partitionBy(F.lit(0)).orderBy(column)) - 1)


def updated(middle: DataFrame, kind: str | None) -> DataFrame:
    """The fixtures' update rule on arcs ``(u, v, cap)``."""
    if kind is None:
        return middle
    g, h, cap = F.lit(7) * F.col("u") + F.lit(11) * F.col("v"), F.lit(31) * F.col("u") + F.lit(17) * F.col("v"), F.col("cap")
    up, down = cap + 1 + h % 100, F.floor(cap * (h % 10) / 10).cast("long")
    rule = {"increase": F.when(g % 4 == 0, up), "decrease": F.when(g % 4 == 0, down), "mixed": F.when(g % 8 == 0, up).when(g % 8 == 4, down)}[kind]
    return middle.withColumn("cap", rule.otherwise(cap))


def trade(spark: SparkSession, sf_dir: str, kind: str | None = None, below: int | None = None) -> FlowProblem:
    """Quantities between nations; ``below`` keeps nations of smaller keys only, few enough to enumerate cuts."""
    line, orders = read(spark, sf_dir, "lineitem", "l_orderkey", "l_suppkey", "l_quantity"), read(spark, sf_dir, "orders", "o_orderkey", "o_custkey")
    supplier, customer = read(spark, sf_dir, "supplier", "s_suppkey", "s_nationkey"), read(spark, sf_dir, "customer", "c_custkey", "c_nationkey")
    if below is not None:
        supplier, customer = supplier.where(F.col("s_nationkey") < below), customer.where(F.col("c_nationkey") < below)
    pairs = line.join(orders, F.col("l_orderkey") == F.col("o_orderkey")).join(supplier, F.col("l_suppkey") == F.col("s_suppkey")).join(customer, F.col("o_custkey") == F.col("c_custkey"))
    q = pairs.where("s_nationkey <> c_nationkey").groupBy(F.col("s_nationkey").cast("long").alias("u"), F.col("c_nationkey").cast("long").alias("v")).agg(F.sum("l_quantity").cast("long").alias("q"))
    cap = F.when(F.col("u") % 5 == F.col("v") % 5, 40 + F.col("q") % 60).otherwise(1 + F.col("q") % 4)
    middle = updated(q.select("u", "v", cap.alias("cap")), kind)
    return FlowProblem(arc(middle, F.col("u"), F.col("v"), F.col("cap")), 3, 12, "trade" if below is None else f"trade{below}")


def trade14(spark: SparkSession, sf_dir: str, kind: str | None = None) -> FlowProblem:
    return trade(spark, sf_dir, kind, 14)


def bipartite(middle: DataFrame, out_cap, in_cap, name: str, kind: str | None = None) -> FlowProblem:
    """``middle(u, v, cap)``; terminals' capacities from the unchanged sums."""
    left = middle.groupBy("u").agg(F.sum("cap").alias("m")).select(node(1, "u").alias("id"), out_cap(F.col("m"), F.col("u")).cast("long").alias("cap"))
    right = middle.groupBy("v").agg(F.sum("cap").alias("m")).select(node(2, "v").alias("id"), in_cap(F.col("m"), F.col("v")).cast("long").alias("cap"))
    return FlowProblem(with_super_terminals(arc(updated(middle, kind), node(1, "u"), node(2, "v"), F.col("cap")), left, right), SOURCE, SINK, name)


def tier(spark: SparkSession, sf_dir: str, kind: str | None = None) -> FlowProblem:
    rows = read(spark, sf_dir, "customer", "c_mktsegment", "c_nationkey")
    rows = rows.groupBy("c_mktsegment", "c_nationkey").agg(F.count(F.lit(1)).alias("cap")).join(F.broadcast(ranked(rows, "c_mktsegment", "u")), "c_mktsegment")
    return bipartite(rows.select(F.col("u").cast("long"), F.col("c_nationkey").cast("long").alias("v"), "cap"), lambda m, i: F.floor(m * (1 + 2 * i) / 4), lambda m, n: F.floor(m * (1 + n % 4) / 3), "tier", kind)


def docs(spark: SparkSession, sf_dir: str, kind: str | None = None) -> FlowProblem:
    rows = read(spark, sf_dir, "documents", "lang", "source")
    cells = rows.groupBy("lang", "source").agg(F.count(F.lit(1)).alias("cap")).join(ranked(rows, "lang", "u"), "lang").join(ranked(rows, "source", "v"), "source")
    return bipartite(cells.select(F.col("u").cast("long"), F.col("v").cast("long"), "cap"), lambda m, i: F.floor(m * (1 + i) / 2), lambda m, n: F.floor(m * (1 + n % 3) / 2), "docs", kind)


def tree(spark: SparkSession, sf_dir: str) -> FlowProblem:
    d = read(spark, sf_dir, "customer", "c_nationkey").groupBy("c_nationkey").agg(F.count(F.lit(1)).alias("d"))
    d = read(spark, sf_dir, "nation", "n_nationkey", "n_regionkey").join(d, F.col("n_nationkey") == F.col("c_nationkey"), "left").select("n_nationkey", "n_regionkey", F.coalesce("d", F.lit(0)).alias("d"))
    first = d.groupBy("n_regionkey").agg(F.sum("d").alias("d")).select(node(1, "n_regionkey").alias("id"), F.floor(F.col("d") * (2 + F.col("n_regionkey")) / 4).cast("long").alias("cap"))
    last = d.select(node(2, "n_nationkey").alias("id"), (1 + F.floor(F.col("d") * (1 + F.col("n_nationkey") % 3) / 2)).cast("long").alias("cap"))
    return FlowProblem(with_super_terminals(arc(d, node(1, "n_regionkey"), node(2, "n_nationkey"), F.col("d")), first, last), SOURCE, SINK, "tree")


def match_events(spark: SparkSession, sf_dir: str, every: int = 1) -> FlowProblem:
    """Event types matched to users; with ``every`` only events whose id it divides."""
    events = read(spark, sf_dir, "events", "event_id", "user_id", "event_type")
    taken = events.where(F.col("event_id") % every == 0) if every > 1 else events
    pairs = taken.select("event_type", "user_id").distinct().join(ranked(events, "event_type", "u"), "event_type").select(F.col("u").cast("long"), F.col("user_id").alias("v"), F.lit(1).cast("long").alias("cap"))
    return bipartite(pairs, lambda p, i: F.floor(p * (1 + 2 * i) / 8), lambda p, v: F.lit(1), "match_events" if every == 1 else "match")


def match(spark: SparkSession, sf_dir: str) -> FlowProblem:
    return match_events(spark, sf_dir, 61)


def relay(spark: SparkSession, sf_dir: str, communities: bool = False) -> FlowProblem:
    events = read(spark, sf_dir, "events", "event_id", "ts", "user_id", "event_type")
    nxt = events.select(F.col("user_id").alias("u"), F.lead("user_id").over(Window.partitionBy("event_type").orderBy("ts", "event_id")).alias("v")).where("v is not null and u <> v").distinct()
    wide = 1 + (7 * F.col("u") + 13 * F.col("v")) % 100
    if communities:
        thin = 1 + (7 * F.col("u") + 13 * F.col("v")) % 4
        arcs = arc(nxt, F.col("u"), F.col("v"), F.when(F.col("u") % 5 == F.col("v") % 5, wide).otherwise(thin))
        users = events.select(F.col("user_id").alias("id")).distinct().withColumn("cap", F.lit(1000).cast("long"))
        return FlowProblem(with_super_terminals(arcs, users.where("id % 5 = 0"), users.where("id % 5 = 3")), SOURCE, SINK, "relay_comm")
    arcs = arc(nxt, F.col("u"), F.col("v"), wide)
    top = arcs.groupBy("src").agg(F.sum("cap").alias("c")).orderBy(F.desc("c"), "src").limit(2).collect()
    return FlowProblem(arcs, top[0].src, top[1].src, "relay")


def copurchase(spark: SparkSession, sf_dir: str, limit: int = 1000) -> FlowProblem:
    line = read(spark, sf_dir, "lineitem", "l_orderkey", "l_partkey", "l_suppkey", "l_quantity").join(read(spark, sf_dir, "orders", "o_orderkey", "o_custkey"), F.col("l_orderkey") == F.col("o_orderkey"))
    n = F.count(F.lit(1))
    a = arc(line.groupBy("o_custkey", "l_suppkey").agg((F.sum("l_quantity").cast("long") % 100 + 1).alias("c")), node(1, "o_custkey"), node(2, "l_suppkey"), F.col("c"))
    b = arc(line.groupBy("l_suppkey", "l_partkey").agg(n.alias("c")), node(2, "l_suppkey"), node(3, "l_partkey"), F.col("c"))
    c = arc(line.groupBy("l_partkey", "o_custkey").agg(n.alias("c")), node(3, "l_partkey"), node(1, "o_custkey"), F.col("c"))
    customers = read(spark, sf_dir, "customer", "c_custkey", "c_nationkey").select(node(1, "c_custkey").alias("id"), F.lit(limit).cast("long").alias("cap"), "c_nationkey")
    return FlowProblem(with_super_terminals(a.unionByName(b).unionByName(c), customers.where("c_nationkey = 0"), customers.where("c_nationkey = 13")), SOURCE, SINK, "copurchase")


def links(spark: SparkSession, sf_dir: str) -> FlowProblem:
    pages = read(spark, sf_dir, "pages", "url", "html").select(F.regexp_extract("url", r"://([^/]+)", 1).alias("host"), F.explode(F.regexp_extract_all("html", F.lit(r'href="([^"]+)"'), F.lit(1))).alias("target"))
    hosts, targets = ranked(pages, "host", "h"), ranked(pages, "target", "g")
    n = hosts.count()
    out = pages.join(hosts, "host").join(targets, "target").groupBy("h", "g").agg(F.count(F.lit(1)).alias("c"))
    back = targets.select("g", (F.lit(7919) * F.col("g") % n).alias("h"), (1 + F.col("g") % 10).alias("c"))
    arcs = arc(out, node(1, "h"), node(2, "g"), F.col("c")).unionByName(arc(back, node(2, "g"), node(1, "h"), F.col("c")))
    return FlowProblem(arcs, 1 << 40, (1 << 40) + n - 1, "links")


def first_of(i: np.ndarray, v: np.ndarray, dot: np.ndarray, near: int) -> np.ndarray:
    """Places of the ``near`` largest ``dot`` of each ``i``, ties to the smaller ``v``: of copies that tie in crowds no others can stay."""
    order = np.lexsort((v, -dot, i))
    return order[np.arange(len(order)) - np.searchsorted(i[order], i[order]) < near]


def nearest(rows: DataFrame, near: int, block: int = 10_000) -> DataFrame:
    """``(u, v, dot)``: for each vector of ``rows(u, x)`` the ``near`` others of its length with the largest inner product, over all rows.

    Blocks of vectors meet as matrices, so no pair of rows is formed; each block keeps its best before the best of all are taken.
    What is shuffled falls with the size of a block; a task multiplies ``TILE`` rows of one at a time.
    """
    packed = T.StructType([T.StructField("dims", T.IntegerType()), T.StructField("ids", T.BinaryType()), T.StructField("data", T.BinaryType())])
    found = T.StructType([T.StructField("u", T.LongType()), T.StructField("v", T.LongType()), T.StructField("dot", T.DoubleType())])
    kind = np.float32 if isinstance(rows.schema["x"].dataType.elementType, T.FloatType) else np.float64

    def pack(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in it:
            by: dict[int, list] = {}
            for i, x in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                by.setdefault(len(x), []).append((i, x))
            for dims, own in by.items():
                for k in range(0, len(own), block):
                    ids, data = zip(*own[k : k + block], strict=True)
                    yield pa.RecordBatch.from_arrays([pa.array([dims], pa.int32()), pa.array([np.array(ids, np.int64).tobytes()], pa.binary()), pa.array([np.array(data, kind).tobytes()], pa.binary())], names=packed.names)

    def meet(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in it:
            for row in range(batch.num_rows):
                dims, ids, data, other, more = (batch.column(k)[row].as_py() for k in range(5))
                ids, v = np.frombuffer(ids, np.int64), np.frombuffer(other, np.int64)
                rest, y = np.frombuffer(data, kind).reshape(-1, dims), np.frombuffer(more, kind).reshape(-1, dims).astype(np.float64)
                for k in range(0, len(ids), TILE):
                    u, x = ids[k : k + TILE], rest[k : k + TILE].astype(np.float64)
                    dots = x @ y.T
                    _, own, self = np.intersect1d(u, v, return_indices=True)
                    dots[own, self] = -np.inf
                    floor = np.partition(dots, max(0, len(v) - near), axis=1)[:, max(0, len(v) - near), None]
                    i, j = np.nonzero(dots >= floor - 1e-9 * (1 + np.abs(np.where(np.isinf(floor), 0, floor))))  # with all that tie, up to rounding
                    finite = ~np.isinf(dots[i, j])
                    i, j = i[finite], j[finite]
                    exact = (x[i] * y[j]).sum(axis=1)
                    best = first_of(i, v[j], exact, near)
                    yield pa.RecordBatch.from_arrays([pa.array(u[i[best]]), pa.array(v[j[best]]), pa.array(exact[best])], names=found.names)

    one = cut(rows.mapInArrow(pack, packed))
    two = one.select("dims", F.col("ids").alias("other"), F.col("data").alias("more"))
    pairs = one.join(two, "dims").select("dims", "ids", "data", "other", "more")
    tasks = max(1, min(10_000, one.count() ** 2 // 4))  # a few pairs of blocks each
    met = pairs.repartition(tasks, F.xxhash64("ids"), F.xxhash64("other")).mapInArrow(meet, found)
    return met.withColumn("r", F.row_number().over(Window.partitionBy("u").orderBy(F.desc("dot"), "v"))).where(F.col("r") <= near).drop("r")


def segment(spark: SparkSession, sf_dir: str, near: int = 5, seed_cap: int = 1000) -> FlowProblem:
    """Neighbours by inner product over all vectors, similarity as weight; labels 0 and 1 seed the two sides. Of a repeated id the least row counts."""
    rows = read(spark, sf_dir, "embeddings", "vec_id", "embedding", "label").where("vec_id is not null and embedding is not null")
    rows = rows.groupBy("vec_id").agg(F.min(F.struct("embedding", "label")).alias("r")).select("vec_id", "r.*")
    top = cut(nearest(rows.select(F.col("vec_id").alias("u"), F.col("embedding").alias("x")), near))  # else each reader of the arcs compares all vectors again
    one = arc(top, F.col("u"), F.col("v"), F.greatest(F.lit(0), F.floor(100 * F.col("dot"))))
    both = one.unionByName(one.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "cap"))
    seeds = rows.select(F.col("vec_id").alias("id"), F.lit(seed_cap).cast("long").alias("cap"), "label")
    return FlowProblem(with_super_terminals(both, seeds.where("label = 0"), seeds.where("label = 1")), SOURCE, SINK, "segment")


def dialog(spark: SparkSession, sf_dir: str) -> FlowProblem:
    rows = read(spark, sf_dir, "conversations", "conv_id", "turn", "role")
    w = Window.partitionBy("conv_id").orderBy("turn")
    place = lambda t, r: F.least(t, F.lit(6)) * 2 + F.when(r == "user", 0).otherwise(1)
    steps = rows.select(place(F.col("turn"), F.col("role")).alias("u"), place(F.lead("turn").over(w), F.lead("role").over(w)).alias("v")).where("v is not null and u <> v").groupBy("u", "v").agg(F.count(F.lit(1)).alias("c"))
    ends = spark.range(14).select("id", F.lit(1_000_000).cast("long").alias("cap"))
    return FlowProblem(with_super_terminals(arc(steps, F.col("u"), F.col("v"), F.col("c")), ends.where("id < 2"), ends.where("id >= 12")), SOURCE, SINK, "dialog")


def supply(spark: SparkSession, sf_dir: str) -> FlowProblem:
    line = read(spark, sf_dir, "lineitem", "l_orderkey", "l_partkey", "l_suppkey", "l_quantity").join(read(spark, sf_dir, "orders", "o_orderkey", "o_custkey"), F.col("l_orderkey") == F.col("o_orderkey"))
    q = F.sum("l_quantity").cast("long").alias("c")
    a = arc(line.groupBy("l_suppkey", "l_partkey").agg(q), node(1, "l_suppkey"), node(2, "l_partkey"), F.col("c"))
    b = arc(line.groupBy("l_partkey", "o_custkey").agg(q), node(2, "l_partkey"), node(3, "o_custkey"), F.col("c"))
    first = line.groupBy("l_suppkey").agg(q).select(node(1, "l_suppkey").alias("id"), F.col("c").alias("cap"))
    last = line.groupBy("o_custkey").agg(q).select(node(3, "o_custkey").alias("id"), F.floor(F.col("c") / 2).cast("long").alias("cap"))
    return FlowProblem(with_super_terminals(a.unionByName(b), first, last), SOURCE, SINK, "supply")


def quality(spark: SparkSession, sf_dir: str) -> FlowProblem:
    rows = read(spark, sf_dir, "documents", "doc_id", "lang", "source", "n_chars")
    w = Window.partitionBy("lang", "source").orderBy("n_chars", "doc_id")
    near = rows.select(F.col("doc_id").alias("u"), F.lead("doc_id").over(w).alias("v"), (F.lead("n_chars").over(w) - F.col("n_chars")).alias("d")).where("v is not null")
    one = arc(near, F.col("u"), F.col("v"), F.when(F.col("d") <= 200, 10).otherwise(1))
    seeds = read(spark, sf_dir, "labels", "doc_id", "quality").select(F.col("doc_id").alias("id"), F.lit(20).cast("long").alias("cap"), "quality")
    return FlowProblem(with_super_terminals(one.unionByName(one.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "cap")), seeds.where("quality = 1"), seeds.where("quality = 0")), SOURCE, SINK, "quality")


NETWORKS = {f.__name__: f for f in (trade, trade14, tier, docs, tree, match_events, match, relay, copurchase, links, segment, dialog, supply, quality)}
NETWORKS["relay_comm"] = lambda spark, sf_dir: relay(spark, sf_dir, communities=True)
