"""Approximate nearest neighbours by an inverted multi-index.

Each half of a vector is quantised by its own codebook, so two codebooks of ``codes`` centroids make ``codes``^2 cells.
A query ranks both codebooks by how far a centroid's inner product falls short of the best one, and walks the pairs in
order of the summed shortfall with a heap (of blocks of neighbouring pairs) until the cells walked hold ``share`` of all
rows. Rows of those cells, and no others, are multiplied, in single precision, and those near the k-th best are reranked
by the exact inner product in double precision.

Codebooks are fitted on a bounded sample (``most_fit`` rows); every row is indexed. Cells are dealt into ``parts``, and
parts into chunks of about ``chunk`` rows, so a crowded cell is searched by many tasks. Since a fixed share of all rows is
walked, a query goes to most chunks: the work for a query grows with the rows, at ``share`` of a full scan.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import cut
from .vectors import matrix, sample, usable, width


#: Ranked centroids a side of a block that the heap holds.
STEP = 32


def centroids(x: np.ndarray, k: int, rounds: int = 15, seed: int = 7) -> np.ndarray:
    """Lloyd's algorithm from a seeded choice; fewer centroids if there are fewer distinct rows."""
    x = np.unique(x, axis=0)
    c = x[np.sort(np.random.default_rng(seed).permutation(len(x))[:k])]
    for _ in range(rounds):
        near = nearest(x, c)
        n = np.bincount(near, minlength=len(c))
        c = np.stack([np.bincount(near, x[:, j], len(c)) for j in range(x.shape[1])], axis=1) / np.maximum(n, 1)[:, None] + np.where(n[:, None] > 0, 0, c)
    return c


def nearest(x: np.ndarray, c: np.ndarray) -> np.ndarray:
    return ((c * c).sum(axis=1) - 2 * x @ c.T).argmin(axis=1)


def walk(first: np.ndarray, second: np.ndarray, held: np.ndarray, goal: float, owned: np.ndarray, least: float) -> np.ndarray:
    """Cells in order of the summed shortfall of their two centroids until they hold ``goal`` rows and ``least`` in ``owned``.

    The heap holds blocks of ``STEP`` x ``STEP`` pairs of ranked centroids by their least sum. A popped block opens its two
    neighbours; all cells whose sum is no greater than the least block left are final.
    """
    a, b = np.argsort(first, kind="stable"), np.argsort(second, kind="stable")
    at = np.ix_(a, b)
    rows, ids = held.reshape(len(a), len(b))[at], owned.reshape(len(a), len(b))[at]
    sums = first[a][:, None] + second[b][None]
    opened, heap, seen, got = np.zeros(sums.shape, bool), [(sums[0, 0], 0, 0)], {(0, 0)}, 0
    while heap:
        _, i, j = heapq.heappop(heap)
        block = slice(i, i + STEP), slice(j, j + STEP)
        opened[block] = True
        got += int(rows[block].sum())
        for p, q in ((i + STEP, j), (i, j + STEP)):
            if p < len(a) and q < len(b) and (p, q) not in seen:
                seen.add((p, q))
                heapq.heappush(heap, (sums[p, q], p, q))
        if heap and got < goal:
            continue
        final = opened & (sums <= heap[0][0]) if heap else opened
        if not heap or rows[final].sum() >= goal and ids[final].sum() >= least - 1e-6:
            u, v = np.nonzero(final & (rows > 0))
            order = np.argsort(sums[u, v], kind="stable")
            u, v = u[order], v[order]
            enough = np.flatnonzero((np.cumsum(rows[u, v]) >= goal) & (np.cumsum(ids[u, v]) >= least - 1e-6))
            return (a[u] * len(b) + b[v])[: enough[0] + 1 if len(enough) else None]
    return np.zeros(0, np.int64)


def fields(**kinds: T.DataType) -> T.StructType:
    return T.StructType([T.StructField(n, t) for n, t in kinds.items()])


def search(rows: DataFrame, is_query: Column, k: int = 20, key: str = "vec_id", vec: str = "embedding", share: float = 0.35, codes: int = 256, most_fit: int = 8192, parts: int = 8, chunk: int = 8192) -> DataFrame:
    """``(query_id, rank, vec_id, score)``: the ``k`` rows of largest inner product found for each query row.

    A query's own id is no candidate (for repeated ids, all rows of it). Null ids and vectors that are null, empty,
    zero, of another length than most, or hold null or non-finite components, take no part. Ties go to the smaller id;
    repeated rows of one id answer once; an empty table gives an empty one. ``share`` 1 gives exact answers.
    """
    rows = rows.select(F.col(key).cast("long").alias("id"), F.col(vec).alias("v"), F.coalesce(is_query, F.lit(False)).alias("q")).where(F.col("id").isNotNull() & usable(F.col("v")))
    out = fields(query_id=T.LongType(), vec_id=T.LongType(), score=T.DoubleType())
    dims = width(rows, "v")
    if not dims:
        return rows.sparkSession.createDataFrame([], fields(query_id=T.LongType(), rank=T.IntegerType(), vec_id=T.LongType(), score=T.DoubleType()))
    # repeated rows are one; an id may keep several vectors
    rows = cut(rows.where(F.size("v") == dims).groupBy("id", "v").agg(F.bool_or("q").alias("q")))
    half = max(1, dims // 2)
    fit = sample(rows, "v", most_fit)
    one = centroids(fit[:, :half], codes)
    two = centroids(fit[:, half:], codes) if dims > half else np.zeros((1, 0))
    wide = len(two)

    def cells(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in it:
            x = matrix(batch.column(1))
            cell = nearest(x[:, :half], one) * wide + (nearest(x[:, half:], two) if dims > half else 0)
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(cell.astype(np.int32))], names=["id", "v", "q", "cell"])

    placed = cut(rows.mapInArrow(cells, T.StructType([*rows.schema.fields, T.StructField("cell", T.IntegerType())])))
    counts = {r.cell: r.n for r in placed.groupBy("cell").agg(F.count(F.lit(1)).alias("n")).collect()}  # at most codes^2 rows
    held = np.zeros(len(one) * wide, np.int64)
    held[list(counts)] = list(counts.values())
    # ids by cell, an id of several vectors in shares that sum to 1: cells walked hold at least as many distinct ids
    several = placed.groupBy("id").agg(F.count(F.lit(1)).alias("all")).where(F.col("all") > 1)
    spread = placed.groupBy("id", "cell").agg(F.count(F.lit(1)).alias("n")).join(several, "id")
    owned = held.astype(np.float64)
    for r in spread.groupBy("cell").agg(F.sum("n").alias("n"), F.sum(F.col("n") / F.col("all")).alias("ids")).collect():
        owned[r.cell] += r.ids - r.n
    # crowded cells first, each to the part that has least
    part_of, local, load, width_of = np.zeros(len(held), np.int64), np.zeros(len(held), np.int64), [0] * parts, [0] * parts
    for cell in np.argsort(-held, kind="stable")[: np.count_nonzero(held)].tolist():
        part_of[cell] = p = load.index(min(load))
        local[cell] = width_of[p]
        load[p] += int(held[cell])
        width_of[p] += 1
    chunks = [max(1, -(-n // chunk)) for n in load]
    goal, least = share * held.sum(), min(k + 1, owned.sum())

    def ask(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in it:
            x = matrix(batch.column(1))
            s1, s2 = x[:, :half] @ one.T, (x[:, half:] @ two.T if dims > half else np.zeros((len(x), 1)))
            at, part, piece, mine = [], [], [], []
            for k_, (a, b) in enumerate(zip(s1.max(axis=1, keepdims=True) - s1, s2.max(axis=1, keepdims=True) - s2, strict=True)):
                found = walk(a, b, held, goal, owned, least)
                for p in np.unique(part_of[found]).tolist():
                    bits = np.zeros(width_of[p], bool)
                    bits[local[found[part_of[found] == p]]] = True
                    for c in range(chunks[p]):
                        at.append(k_), part.append(p), piece.append(c), mine.append(np.packbits(bits).tobytes())
            yield pa.RecordBatch.from_arrays([pa.array(part, pa.int32()), pa.array(piece, pa.int32()), pa.array([True] * len(at), pa.bool_()), batch.column(0).take(pa.array(at, pa.int64())), batch.column(1).take(pa.array(at, pa.int64())), pa.array([-1] * len(at), pa.int32()), pa.array(mine, pa.binary())], names=MEET.names)

    vector = rows.schema["v"].dataType
    MEET = fields(part=T.IntegerType(), piece=T.IntegerType(), q=T.BooleanType(), id=T.LongType(), v=vector, cell=T.IntegerType(), cells=T.BinaryType())
    queries = rows.where("q").select("id", "v").mapInArrow(ask, MEET)
    n_chunks = F.element_at(F.array(*[F.lit(c) for c in chunks]), F.col("part") + 1)

    def deal(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in it:
            cell = batch.column(3).to_numpy()
            yield pa.RecordBatch.from_arrays([pa.array(part_of[cell].astype(np.int32)), batch.column(0), batch.column(1), pa.array(local[cell].astype(np.int32))], names=["part", "id", "v", "cell"])

    index = placed.mapInArrow(deal, fields(part=T.IntegerType(), id=T.LongType(), v=vector, cell=T.IntegerType()))
    index = index.withColumn("q", F.lit(False)).withColumn("piece", F.pmod(F.xxhash64("id"), n_chunks).cast("int")).withColumn("cells", F.lit(None).cast("binary"))

    def rerank(it: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Rows of a chunk, then the queries that ask it."""
        spot, ids, xs, cs, low, size = None, [], [], [], None, 0.0
        for batch in it:
            spots = np.stack([batch.column(0).to_numpy(), batch.column(1).to_numpy()], axis=1)
            edges = [0, *(np.flatnonzero((spots[1:] != spots[:-1]).any(axis=1)) + 1), len(spots)]
            for a, b in zip(edges[:-1], edges[1:], strict=True):
                own = batch.slice(a, b - a)
                if tuple(spots[a]) != spot:
                    spot, ids, xs, cs, low = tuple(spots[a]), [], [], [], None
                asks = own.column(2).to_numpy(zero_copy_only=False)
                if (~asks).any():
                    sub = own.filter(pa.array(~asks))
                    ids.append(sub.column(3).to_numpy()), xs.append(matrix(sub.column(4))), cs.append(sub.column(5).to_numpy())
                if not asks.any() or not ids:
                    continue
                if len(ids) > 1 or low is None:  # rows in order of their cells, a cell's rows side by side
                    ids, xs, cs = np.concatenate(ids), np.concatenate(xs), np.concatenate(cs)
                    order = np.argsort(cs, kind="stable")
                    ids, xs, cs = [ids[order]], [xs[order]], [cs[order]]
                    low = xs[0].astype(np.float32)
                    size = np.linalg.norm(xs[0], axis=1).max()
                sub = own.filter(pa.array(asks))
                res: list[list] = [[], [], []]
                for qid, q, mask in zip(sub.column(3).to_pylist(), matrix(sub.column(4)), sub.column(6).to_pylist(), strict=True):
                    asked = np.unpackbits(np.frombuffer(mask, np.uint8)).astype(bool)
                    may = np.flatnonzero(asked[cs[0]])  # the rows of the cells asked for; the others are not looked at
                    may = may[ids[0][may] != qid]
                    if not len(may):
                        continue
                    s = low[may] @ q.astype(np.float32)
                    slack = 1e-5 * size * float(np.linalg.norm(q))
                    order = np.lexsort((-s, ids[0][may]))
                    own_ids = ids[0][may][order]
                    first = np.concatenate([[True], own_ids[1:] != own_ids[:-1]])
                    tops = s if first.all() else s[order][first]  # the best vector of each id, up to rounding
                    if len(tops) > k:  # all that may be among the k best
                        floor = np.partition(tops, len(tops) - k)[len(tops) - k]
                        may = may[s >= floor - slack]
                    s = (xs[0][may] * q).sum(axis=1)
                    best = np.lexsort((ids[0][may], -s))
                    best = best[np.sort(np.unique(ids[0][may][best], return_index=True)[1])[:k]]
                    res[0] += [qid] * len(best)
                    res[1] += ids[0][may][best].tolist()
                    res[2] += s[best].tolist()
                yield pa.RecordBatch.from_arrays([pa.array(r, t) for r, t in zip(res, (pa.int64(), pa.int64(), pa.float64()), strict=True)], names=out.names)

    meet = index.select(*MEET.names).unionByName(queries).repartition("part", "piece").sortWithinPartitions("part", "piece", "q")
    found = meet.mapInArrow(rerank, out).groupBy("query_id", "vec_id").agg(F.max("score").alias("score"))
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return found.withColumn("rank", F.row_number().over(order)).where(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")
