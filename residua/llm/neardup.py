"""Near-duplicate vectors by a subspace pigeonhole join.

Unit vectors whose cosine is at least t lie at a squared distance of at most 2 - 2t. After a random rotation they are
split into blocks of few dimensions; the squared distance is the sum over blocks, so in some block it is within that
block's share of the budget (in proportion to its dimensions). Each block is range-joined by itself: a tree of median
cuts, fitted on a bounded sample, deals the vectors out; a vector is at home in one leaf and visits the leaves that
its budget's radius touches. What one block finds is verified by the exact cosine of the original vectors, and a pair
counts in the first block that admits it, so the union over blocks counts each pair once.

No pair leaves a task: a leaf hands on each vector's number of links and a spanning forest of its links.

Crowds do not go through the blocks. Where the sample is dense, a ball of half the threshold's angle is drawn around
the mean of its vectors; by the triangle inequality all members of a ball link with each other. Against any other
vector a ball is all linked, not linked, or, near the threshold only, compared member by member.

Equal vectors are one vertex with a multiplicity, however many rows share them.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import Cuts
from .components import components
from .vectors import matrix, sample, usable


def fields(**kinds: T.DataType) -> T.StructType:
    return T.StructType([T.StructField(n, t) for n, t in kinds.items()])


def rotation(dims: int, seed: int = 11) -> np.ndarray:
    return np.linalg.qr(np.random.default_rng(seed).standard_normal((dims, dims)))[0]


def leaves(x: np.ndarray, levels: int) -> tuple[np.ndarray, np.ndarray]:
    """Lower and upper corners of the boxes of a tree of median cuts, each along the widest dimension."""
    boxes = [(np.full(x.shape[1], -np.inf), np.full(x.shape[1], np.inf), x)]
    for _ in range(levels):
        more = []
        for lo, hi, own in boxes:
            if len(own) < 2:
                more.append((lo, hi, own))
                continue
            d = int(own.std(axis=0).argmax())
            m = float(np.median(own[:, d]))
            up, low = lo.copy(), hi.copy()
            low[d] = up[d] = m
            more += [(lo, low, own[own[:, d] < m]), (up, hi, own[own[:, d] >= m])]
        boxes = more
    return np.stack([b[0] for b in boxes]), np.stack([b[1] for b in boxes])


U = fields(u=T.LongType(), n=T.LongType())
#: A task's finds: ``links`` of a vector (rows that it links with), and a vector ``to`` that it hangs together with.
FIND = fields(u=T.LongType(), links=T.LongType(), to=T.LongType())
#: Balls at most, vectors of the sample that make one, members of a ball compared in one task.
BALLS, CROWD, MEMBERS = 512, 16, 4096
#: Safety of angles in radians and of squared distances in single precision.
SLACK, SLACK32 = 1e-7, 2e-5


def unit(x: np.ndarray) -> np.ndarray:
    return x / np.linalg.norm(x, axis=1, keepdims=True)


def angles(x: np.ndarray, centres: np.ndarray) -> np.ndarray:
    return np.arccos(np.clip(x @ centres.T, -1, 1))


def crowds(fit: np.ndarray, half: float) -> np.ndarray:
    """Centres of balls of angle ``half`` that hold at least ``CROWD`` vectors of the sample, densest first."""
    near = np.concatenate([(fit[i : i + 512] @ fit.T >= np.cos(half)).sum(axis=1) for i in range(0, len(fit), 512)]) if len(fit) else np.zeros(0)
    free, centres = np.ones(len(fit), bool), []
    for i in np.argsort(-near, kind="stable").tolist():
        if near[i] < CROWD or len(centres) == BALLS:
            break
        if free[i] and (own := free & (fit @ fit[i] >= np.cos(half))).sum() >= CROWD:
            centre = fit[own].mean(axis=0)
            centre /= np.linalg.norm(centre)
            inside = free & (fit @ centre >= np.cos(half))
            if inside.sum() >= CROWD:
                centres.append(centre)
                free &= ~inside
            free[i] = False
    return np.array(centres).reshape(-1, fit.shape[1] if fit.ndim == 2 else 0)


class Forest:
    """Links of visitors to the rows at home in one place: numbers of links, and roots that hang together."""

    def __init__(self, ids: np.ndarray, times: np.ndarray):
        self.ids, self.times = ids, times
        self.links, self.root = np.zeros(len(ids), np.int64), np.arange(len(ids))

    def join(self, i: np.ndarray, j: np.ndarray, ids: np.ndarray, times: np.ndarray, back: np.ndarray) -> pa.RecordBatch:
        """Visitor i links with home j; ``back`` says which of these links count for the home too. Finds of the visitors."""
        many = np.bincount(i, self.times[j], minlength=len(ids)).astype(np.int64)
        self.links += np.bincount(j[back], times[i[back]], minlength=len(self.ids)).astype(np.int64)
        first = np.full(len(ids), len(self.ids))
        np.minimum.at(first, i, j)
        a, b = j, first[i]
        while len(a):  # roots of linked homes hook onto smaller ones, then paths shorten
            x, y = self.root[a], self.root[b]
            apart = x != y
            a, b, x, y = a[apart], b[apart], x[apart], y[apart]
            np.minimum.at(self.root, np.maximum(x, y), np.minimum(x, y))
            while (self.root[self.root] != self.root).any():
                self.root = self.root[self.root]
        k = np.flatnonzero(many)
        return pa.RecordBatch.from_arrays([pa.array(ids[k]), pa.array(many[k]), pa.array(self.ids[first[k]])], names=FIND.names)

    def finds(self) -> pa.RecordBatch:
        k = np.flatnonzero((self.links > 0) | (self.root != np.arange(len(self.root))))
        return pa.RecordBatch.from_arrays([pa.array(self.ids[k]), pa.array(self.links[k]), pa.array(self.ids[self.root[k]])], names=FIND.names)


def cosines(p: np.ndarray, q: np.ndarray) -> np.ndarray:
    return (p * q).sum(axis=1) / np.sqrt((p * p).sum(axis=1) * (q * q).sum(axis=1))


def link(rows: DataFrame, least: float = 0.95, key: str = "vec_id", vec: str = "embedding", block_dims: int = 16, leaf_rows: int = 8192, most_fit: int = 8192) -> DataFrame:
    """``(vec_id, n_links, component_id, kept)`` for each row.

    Vectors of one length are compared, each length by itself. Vectors that are null, empty, zero, or hold null or
    non-finite components link with nothing: they are their own component. So are rows with a null id (their component is null). Rows that repeat an
    id and vector link like any equal vectors; an id's different vectors are vectors of their own, each with its own links. An empty table gives an
    empty one; other columns are ignored.
    """
    cuts = Cuts()
    given = rows.select(F.col(key).cast("long").alias("vec_id"), F.col(vec).alias("v"))
    mine = F.when(F.col("vec_id").isNotNull() & usable(F.col("v")), F.struct(F.xxhash64("v").alias("x"), F.xxhash64(F.lit(1), "v").alias("y")))
    given = given.withColumn("same", mine)
    classes = cuts(given.where("same is not null").groupBy("same").agg(F.min("vec_id").alias("id"), F.count(F.lit(1)).alias("n"), F.first("v").alias("v")).withColumn("u", F.monotonically_increasing_id()))
    lengths = [r.d for r in classes.groupBy(F.size("v").alias("d")).agg(F.count(F.lit(1)).alias("n")).where("n > 1").orderBy("d").collect()]
    found = classes.select("u", F.lit(0).cast("long").alias("links"), F.col("u").alias("to")).limit(0)
    for dims in lengths:
        found = found.unionByName(cuts(finds(classes.where(F.size("v") == dims).select("u", "n", "v"), least, dims, block_dims, leaf_rows, most_fit, cuts)))
    classes = classes.select("same", "u", "id", "n")
    others = found.groupBy("u").agg(F.sum("links").alias("others"))
    root = components(found.select(F.col("u").alias("a"), F.col("to").alias("b"))).select(F.col("id").alias("u"), F.col("component_id").alias("root"))
    named = cuts(classes.join(others, "u", "left").join(root, "u", "left").select("same", "id", (F.col("n") - 1 + F.coalesce("others", F.lit(0))).alias("n_links"), F.coalesce("root", "u").alias("root")))
    named = named.join(named.groupBy("root").agg(F.min("id").alias("component_id")), "root").drop("root", "id")
    out = given.join(named, "same", "left").select("vec_id", F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"), F.coalesce("component_id", "vec_id").alias("component_id"))
    return out.withColumn("kept", F.coalesce(F.col("vec_id") == F.col("component_id"), F.lit(True)))


def finds(classes: DataFrame, least: float, dims: int, block_dims: int, leaf_rows: int, most_fit: int, cuts: Cuts) -> DataFrame:
    """Finds of ``(u, n, v)`` rows of one length: links at a cosine of ``least`` or more; several rows a vector add up."""
    fit = unit(sample(classes, "v", most_fit))
    theta = float(np.arccos(least))
    centres = crowds(fit, theta / 2 - SLACK)
    if not len(centres):
        return join(classes, fit, least, dims, block_dims, leaf_rows)
    vector = classes.schema["v"].dataType
    placed = T.StructType([*U.fields, T.StructField("v", vector), T.StructField("ball", T.IntegerType()), T.StructField("angle", T.DoubleType())])

    def place(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in it:
            for lo in range(0, batch.num_rows, 2048):
                part = batch.slice(lo, 2048)
                far = angles(unit(matrix(part.column(2))), centres)
                ball, angle = far.argmin(axis=1), far.min(axis=1)
                ball = np.where(angle <= theta / 2 - SLACK, ball, -1).astype(np.int32)
                yield pa.RecordBatch.from_arrays([*part.columns, pa.array(ball), pa.array(angle)], names=placed.names)

    rows = cuts(classes.mapInArrow(place, placed))
    spark = classes.sparkSession
    of_ball = rows.where("ball >= 0").groupBy("ball").agg(F.max("angle").alias("r"), F.sum("n").alias("mass"), F.min("u").alias("head"), F.ceil(F.count(F.lit(1)) / MEMBERS).cast("int").alias("chunks")).collect()  # BALLS rows at most
    radius = np.full(len(centres), np.nan)
    for r in of_ball:
        radius[r.ball] = r.r
    balls = F.broadcast(spark.createDataFrame([(r.ball, r.mass, r.head, r.chunks) for r in of_ball], "c int, mass long, head long, chunks int"))
    ints = T.ArrayType(T.IntegerType())
    seen = T.StructType([*U.fields, T.StructField("v", vector), T.StructField("ball", T.IntegerType()), T.StructField("sure", ints), T.StructField("open", ints)])

    def view(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """The balls besides its own all of whose members a vector links with, and those near the threshold."""
        for batch in it:
            for lo in range(0, batch.num_rows, 2048):
                part = batch.slice(lo, 2048)
                far, own = angles(unit(matrix(part.column(2))), centres), part.column(3).to_numpy()
                sure = far + radius <= theta - SLACK
                near = (far - radius <= theta + SLACK) & ~sure
                lists = []
                for which in (sure, near):
                    which[np.flatnonzero(own >= 0), own[own >= 0]] = False
                    ends = np.concatenate([[0], np.cumsum(which.sum(axis=1))])
                    lists.append(pa.ListArray.from_arrays(pa.array(ends.astype(np.int32)), pa.array(np.nonzero(which)[1].astype(np.int32))))
                yield pa.RecordBatch.from_arrays([*(part.column(k) for k in range(4)), *lists], names=seen.names)

    views = cuts(rows.mapInArrow(view, seen))
    inside = views.where("ball >= 0").join(balls, F.col("ball") == F.col("c"))
    sure = views.select("u", "n", "ball", F.explode("sure").alias("c")).join(balls, "c")
    settled = inside.select("u", (F.col("mass") - F.col("n")).alias("links"), F.col("head").alias("to")).unionByName(sure.select("u", F.col("mass").alias("links"), F.col("head").alias("to")))
    for_all = F.broadcast(sure.where("ball < 0").groupBy(F.col("c").alias("ball")).agg(F.sum("n").alias("links")))  # BALLS rows at most
    settled = settled.unionByName(rows.where("ball >= 0").join(for_all, "ball").select("u", "links", F.col("u").alias("to")))
    at_home = inside.select("ball", F.pmod("u", "chunks").cast("int").alias("chunk"), F.lit(False).alias("visits"), F.lit(False).alias("back"), "u", "n", "v")
    asks = views.select("u", "n", "v", "ball", F.explode("open").alias("c")).join(balls, "c")
    asks = asks.select(F.col("c").alias("ball"), F.explode(F.sequence(F.lit(0), F.col("chunks") - 1)).alias("chunk"), F.lit(True).alias("visits"), (F.col("ball") < 0).alias("back"), "u", "n", "v")

    def compare(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for forest, homes, new, x, back in met(it, 2, 3):
            if forest is None:
                yield homes
                continue
            h = homes.astype(np.float32)
            for lo in range(0, len(x), 512):
                y = unit(x[lo : lo + 512])
                i, j = np.nonzero(y.astype(np.float32) @ h.T >= least - SLACK32)
                good = cosines(x[lo + i], forest.vectors[j]) >= least
                i, j = i[good], j[good]
                if len(i):
                    yield forest.join(i, j, new[0][lo : lo + 512], new[1][lo : lo + 512], back[lo + i])

    dealt = at_home.unionByName(asks).repartition("ball", "chunk").sortWithinPartitions("ball", "chunk", "visits")
    out = cuts(settled).unionByName(cuts(dealt.mapInArrow(compare, FIND)))
    cuts.drop(views)
    outside = fit[angles(fit, centres).min(axis=1) > theta / 2]
    return out.unionByName(join(rows.where("ball < 0").select("u", "n", "v"), outside, least, dims, block_dims, leaf_rows))


def met(it: Iterator[pa.RecordBatch], visits: int, back: int) -> Iterator[tuple]:
    """Rows ``(place, part, ..., u, n, v)`` in order of (place, part, visits) -> ``(forest, unit vectors at home, (u, n), vectors, back)``
    for each run of visitors, and ``(None, finds, ...)`` at the end of a place."""
    spot, forest, held, homes = None, None, [], None
    for batch in it:
        spots = np.stack([batch.column(0).to_numpy(), batch.column(1).to_numpy()], axis=1)
        edges = [0, *(np.flatnonzero((spots[1:] != spots[:-1]).any(axis=1)) + 1).tolist(), len(spots)]
        for a, b in zip(edges[:-1], edges[1:], strict=True):
            if a == b:
                continue
            own = batch.slice(a, b - a)
            if tuple(spots[a]) != spot:
                if forest is not None:
                    yield None, forest.finds(), None, None, None
                spot, forest, held = (int(spots[a][0]), int(spots[a][1])), None, []
            u, n, x = own.column(own.num_columns - 3).to_numpy(), own.column(own.num_columns - 2).to_numpy(), matrix(own.column(own.num_columns - 1))
            away = own.column(visits).to_numpy(zero_copy_only=False)
            if not away.all():
                held.append((u[~away], n[~away], x[~away]))
            if away.any() and held:
                if forest is None:
                    forest, homes = settle(held)
                yield forest, homes, (u[away], n[away]), x[away], own.column(back).to_numpy(zero_copy_only=False)[away]
    if forest is not None:
        yield None, forest.finds(), None, None, None


def settle(held: list[tuple]) -> tuple[Forest, np.ndarray]:
    u, n, x = (np.concatenate(c) for c in zip(*held, strict=True))
    forest = Forest(u, n)
    forest.vectors = x
    return forest, unit(x)


def join(classes: DataFrame, fit: np.ndarray, least: float, dims: int, block_dims: int, leaf_rows: int) -> DataFrame:
    """Finds among ``(u, n, v)`` rows by range joins over blocks of dimensions."""
    n = classes.count()
    turn = rotation(dims)
    span = [slice(c, min(dims, c + block_dims)) for c in range(0, dims, block_dims)]
    budget = [(2 - 2 * least) * (s.stop - s.start) / dims + 1e-9 for s in span]
    levels = max(0, int(np.ceil(np.log2(max(1, n / leaf_rows)))))
    trees = [leaves((fit @ turn)[:, s], levels) for s in span]
    meet = T.StructType([T.StructField("block", T.IntegerType()), T.StructField("leaf", T.IntegerType()), T.StructField("visits", T.BooleanType()), *U.fields, classes.schema["v"]])

    def deal(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in it:
            for first in range(0, batch.num_rows, 2048):
                part = batch.slice(first, 2048)
                x = unit(matrix(part.column(2))) @ turn
                for k, (s, (lo, hi)) in enumerate(zip(span, trees, strict=True)):
                    apart, home = np.zeros((len(x), len(lo))), np.ones((len(x), len(lo)), bool)
                    for d in range(s.stop - s.start):
                        y = x[:, s.start + d, None]
                        apart += np.maximum(0, np.maximum(lo[:, d] - y, y - hi[:, d])) ** 2
                        home &= (y >= lo[:, d]) & (y < hi[:, d])
                    row, leaf = np.nonzero(apart <= budget[k])
                    visits = home.argmax(axis=1)[row] != leaf
                    at = pa.array(row)
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(row), k, np.int32)), pa.array(leaf.astype(np.int32)), pa.array(visits), *(part.column(c).take(at) for c in range(3))], names=meet.names)

    def range_join(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Home vectors of a leaf, compared with each other, then with its visitors."""
        spot, held, forest, turned = None, [], None, None
        for batch in it:
            spots = np.stack([batch.column(0).to_numpy(), batch.column(1).to_numpy()], axis=1)
            edges = [0, *(np.flatnonzero((spots[1:] != spots[:-1]).any(axis=1)) + 1).tolist(), len(spots)]
            for a, b in zip(edges[:-1], edges[1:], strict=True):
                if a == b:
                    continue
                own = batch.slice(a, b - a)
                if tuple(spots[a]) != spot:
                    yield from ended(spot, held, forest, turned)
                    spot, held, forest, turned = (int(spots[a][0]), int(spots[a][1])), [], None, None
                u, n, x = own.column(3).to_numpy(), own.column(4).to_numpy(), matrix(own.column(5))
                away = own.column(2).to_numpy(zero_copy_only=False)
                if not away.all():
                    held.append((u[~away], n[~away], x[~away]))
                if away.any() and held:
                    if forest is None:
                        forest, homes = settle(held)
                        turned = homes @ turn
                        yield from compared(spot[0], forest, turned, forest.ids, forest.times, forest.vectors, True)
                    yield from compared(spot[0], forest, turned, u[away], n[away], x[away], False)
        yield from ended(spot, held, forest, turned)

    def ended(spot, held: list, forest: Forest | None, turned: np.ndarray | None) -> Iterator[pa.RecordBatch]:
        if forest is None and held:
            forest, homes = settle(held)
            yield from compared(spot[0], forest, homes @ turn, forest.ids, forest.times, forest.vectors, True)
        if forest is not None:
            yield forest.finds()

    def compared(k: int, forest: Forest, turned: np.ndarray, ids: np.ndarray, times: np.ndarray, x: np.ndarray, at_home: bool) -> Iterator[pa.RecordBatch]:
        """A pair at home counts at its later row; a visitor counts where the smaller number is at home."""
        h = turned[:, span[k]].astype(np.float32)
        right = np.concatenate([-2 * h, np.ones((len(h), 1), np.float32), (h * h).sum(axis=1, keepdims=True)], axis=1).T
        for lo in range(0, len(ids), 512):
            w = unit(x[lo : lo + 512]) @ turn
            g = w[:, span[k]].astype(np.float32)
            left = np.concatenate([g, (g * g).sum(axis=1, keepdims=True), np.ones((len(g), 1), np.float32)], axis=1)
            i, j = np.nonzero(left @ right <= np.float32(budget[k] + SLACK32))
            keep = lo + i > j if at_home else forest.ids[j] < ids[lo + i]
            i, j = i[keep], j[keep]
            good = cosines(x[lo + i], forest.vectors[j]) >= least
            i, j = i[good], j[good]
            for other, (s, most) in enumerate(zip(span[: k + 1], budget, strict=False)):
                inside = ((w[i][:, s] - turned[j][:, s]) ** 2).sum(axis=1) <= most
                keep = inside if other == k else ~inside
                i, j = i[keep], j[keep]
            if len(i):
                yield forest.join(i, j, ids[lo : lo + 512], times[lo : lo + 512], np.ones(len(i), bool))

    dealt = classes.mapInArrow(deal, meet).repartition("block", "leaf").sortWithinPartitions("block", "leaf", "visits")
    return dealt.mapInArrow(range_join, FIND)
