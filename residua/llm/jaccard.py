"""N-gram Jaccard join over count vectors in R-trees.

A text's set holds its distinct word shingles, as 64-bit hashes. Hashing the shingles into groups gives a point of
group counts; the summed coordinate minima of two points, or of a point and the upper corner of a box of points, bound
the overlap from above. Sets are met and joined like this:

1. Equal sets (by size and 128 bits of hash) are one vertex, however many texts share them.
2. Every set posts its ``n - ceil(t n) + 1`` least hashes; two sets above the threshold share such a posting. Hashes that
   many sets would post stand after all others in this order, so that only sets with little else post them; any order
   finds the same pairs. Postings that only one set has are dropped by a combining count, and of postings with the same
   sets one stays, with a weight.
3. Every vertex is first compared with one pivot, the least vertex of the postings it shares with it most often.
   Components of the links found leave little open.
4. Postings that still hold several components go, in bands of set size, to R-trees over count points; each finds the
   pairs of different components whose bound reaches the overlap needed. These are verified exactly, and the components
   of all links are the result. Pairs inside a component need no look: they change nothing. So that a crowd of near copies
   is one component before its pairs are asked for, crowded bands first give each vertex's best candidate alone.
   Pairs of the label that most members of a posting have are not looked at.
   Count points of long sets are all alike, so a pair also needs enough postings in common: beyond the lower of the two
   last posted hashes, the set that has it holds ``ceil(t n) - 1`` hashes, and no more than these can be shared there.

Only narrow rows move until a pair has passed the bounds of size and counts; then the texts themselves come to the
pair, once, and the task that verifies makes their sets. Tables that nothing reads any more are deleted.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import Cuts, PrefixHash, mix, text_blocks
from .components import components

GROUPS = 256
LEAF = 16
#: Rows at home that are one leaf of a posting's tree.
FEW = 64
FOLD = np.arange(256, dtype=np.uint8)
FOLD[65:91] += 32


def shingle_sets(data: np.ndarray, offsets: np.ndarray, words: int = 4) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct shingle hashes of the texts of a block, one text after the other, and the offsets of each text's."""
    data, n = FOLD[data], len(offsets) - 1
    solid = ~((data == 32) | ((data >= 9) & (data <= 13)))
    edge = np.zeros(len(data) + 1, bool)
    edge[offsets] = True
    before = np.concatenate([[False], solid[:-1]]) & ~edge[:-1] if len(data) else solid
    after = np.concatenate([solid[1:], [False]]) & ~edge[1:] if len(data) else solid
    starts, ends = np.flatnonzero(solid & ~before), np.flatnonzero(solid & ~after) + 1
    word = mix(PrefixHash(data).of(starts, ends) + (ends - starts).astype(np.uint64))
    row = np.searchsorted(offsets, starts, side="right") - 1
    per = np.bincount(row, minlength=n)
    first = np.cumsum(per) - per
    sets = np.maximum(per - words + 1, (per > 0).astype(np.int64))
    at = np.concatenate([[0], np.cumsum(sets)])
    head = np.repeat(first - at[:-1], sets) + np.arange(at[-1])
    owner = np.repeat(np.arange(n), sets)
    last = (first + per)[owner] - 1
    h = np.full(len(head), words, np.uint64)
    for k in range(words):
        h = mix(h * np.uint64(0x9E3779B97F4A7C15) + np.where(head + k <= last, word[np.minimum(head + k, max(0, len(word) - 1))] if len(word) else 0, np.uint64(k + 1)))
    for a, b in zip(at[:-1].tolist(), at[1:].tolist(), strict=True):
        h[a:b].sort()
    fresh = np.ones(len(h), bool)
    fresh[1:] = (h[1:] != h[:-1]) | (owner[1:] != owner[:-1])
    return h[fresh], np.concatenate([[0], np.cumsum(np.bincount(owner[fresh], minlength=n))])


def needed(a, b, percent: int):
    """Least overlap of two sets of such sizes with 100 * overlap >= percent * union."""
    return -(-percent * (a + b) // (100 + percent))


def fields(**kinds: T.DataType) -> T.StructType:
    return T.StructType([T.StructField(n, t) for n, t in kinds.items()])


LONG = T.LongType()
PAIR = fields(a=LONG, b=LONG)
FOUND = fields(a=LONG, b=LONG, shared=LONG)
OFTEN = fields(h=LONG, times=LONG)
POINT = fields(doc_id=LONG, h=LONG, n=LONG, v=LONG, twin=LONG, top=LONG, counts=T.BinaryType(), posted=T.ArrayType(LONG))
#: Hashes below this are counted over all sets beforehand: sets post their least ones, from the least 15 to 20 % of a long set's range.
POSTED_FROM = np.uint64(1 << 62)
#: Sets that hold a hash which goes to the end of the order; sets of a task that hold it for the task to name it; how many hashes go there at most.
HEAVY, SEEN, MOST_HEAVY = 64, 3, 1 << 16
#: Hashes that a task counts together, and those it holds on to with a count of 1.
TALLY = 1 << 21
#: Vertices verified against one copy of a pivot's text.
CHUNK = 1024
#: Rows of ids (some 40 bytes each) that are broadcast to the texts at most; beyond it the texts are shuffled to them.
BROADCAST_ROWS = 1 << 18
#: Members of a band of a posting above which they first follow their best candidates only.
CROWDED = 16
#: Finds of pairs that a task holds before it hands on each pair once.
FLUSH = 1 << 15


def packed_counts(held: np.ndarray) -> bytes:
    """Counts of a point in one byte each if they fit, else in four."""
    return (held.astype(np.uint8) if held.max(initial=0) < 256 else held.astype("<u4")).tobytes()


def unpacked_counts(column: pa.Array) -> np.ndarray:
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    _, offsets, data = column.cast(pa.binary()).buffers()
    at = np.frombuffer(offsets, np.int32, len(column) + 1, column.offset * 4) if len(column) else np.zeros(1, np.int32)
    if len(column) and (np.diff(at) == GROUPS).all():  # one byte each
        return np.frombuffer(data, np.uint8)[at[0] : at[-1]].reshape(-1, GROUPS).astype(np.int32)
    out = np.empty((len(column), GROUPS), np.int32)
    for k, x in enumerate(column.to_pylist()):
        out[k] = np.frombuffer(x, np.uint8 if len(x) == GROUPS else "<u4")
    return out


def often(rows: Iterator[pa.RecordBatch], words: int) -> Iterator[pa.RecordBatch]:
    """(text) -> hashes in the part of their range that sets post from, with the number of the task's sets that hold them, from ``SEEN`` on."""
    held, met = np.zeros((2, 0), np.uint64), set()
    fresh: list[np.ndarray] = []

    def counted() -> np.ndarray:
        h, place = np.unique(np.concatenate([held[0], *fresh]), return_inverse=True)
        times = np.ones(len(place), np.uint64)
        times[: held.shape[1]] = held[1]
        fresh.clear()
        return np.stack([h, np.bincount(place, times, len(h)).astype(np.uint64)])

    for batch in rows:
        for _, _, data, offsets in text_blocks(batch, "text"):
            h, at = shingle_sets(data, offsets, words)
            low = h < POSTED_FROM
            owner = np.repeat(np.arange(len(at) - 1), np.diff(at))
            total = np.concatenate([np.zeros(1, np.uint64), np.cumsum(mix(h))])
            new = np.zeros(len(at) - 1, bool)
            for k, x in enumerate((total[at[1:]] - total[at[:-1]]).tolist()):  # equal sets count once
                new[k] = x not in met
                met.add(x)
            fresh.append(h[low & new[owner]])
            if sum(map(len, fresh)) > TALLY:
                held = counted()
                if held.shape[1] > TALLY:
                    held = held[:, held[1] > 1]
                if len(met) > TALLY:
                    met.clear()
        pa.default_memory_pool().release_unused()
    held = counted()
    held = held[:, held[1] >= SEEN]
    yield pa.RecordBatch.from_arrays([pa.array(held[0].view(np.int64)), pa.array(held[1].astype(np.int64))], names=OFTEN.names)


def common_hashes(texts: DataFrame, words: int) -> np.ndarray:
    """Sorted hashes that most sets hold. They only order the postings: results are the same whichever they are."""
    found = texts.select("text").mapInArrow(lambda it: often(it, words), OFTEN).groupBy("h").agg(F.sum("times").alias("times"))
    rows = found.where(F.col("times") > HEAVY).orderBy(F.desc("times"), "h").limit(MOST_HEAVY).select("h").toArrow()
    return np.sort(rows.column(0).to_numpy().astype(np.int64).view(np.uint64))


def first_posted(h: np.ndarray, at: np.ndarray, size: np.ndarray, common: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Places of the first ``size`` hashes of each set, those of ``common`` after all others, and half the last one's place in that order."""
    late = np.zeros(len(h), bool)
    if len(common):
        some = np.flatnonzero(h <= common[-1])
        late[some] = common[np.searchsorted(common, h[some])] == h[some]
    order, take = [], []
    for places, most in ((np.flatnonzero(~late), size), (np.flatnonzero(late), None)):
        start = np.searchsorted(places, at)
        own = np.minimum(np.diff(start), most if most is not None else size - take[0])
        order.append((places, start[:-1]))
        take.append(own)
    ends = np.concatenate([[0], np.cumsum(size)])
    nth = np.arange(ends[-1]) - np.repeat(ends[:-1], size)
    (light, a), (heavy, b) = order
    of_light = nth < np.repeat(take[0], size)
    posted = np.empty(ends[-1], np.int64)
    posted[of_light] = light[(np.repeat(a, size) + nth)[of_light]]
    posted[~of_light] = heavy[(np.repeat(b - take[0], size) + nth)[~of_light]]
    top = np.zeros(len(size), np.int64)
    some = size > 0
    last = posted[ends[1:][some] - 1]
    top[some] = (h[last] >> np.uint64(2)).astype(np.int64) + (late[last].astype(np.int64) << 62)
    return posted, top


def points(rows: Iterator[pa.RecordBatch], words: int, percent: int, common: np.ndarray) -> Iterator[pa.RecordBatch]:
    """(doc_id, h, text) -> size of the set, a hash of the set, a second one, where its last posted hash stands, count point, posted hashes."""
    for batch in rows:
        for first, end, data, offsets in text_blocks(batch, "text"):
            h, at = shingle_sets(data, offsets, words)
            n, rows_ = np.diff(at), end - first
            owner = np.repeat(np.arange(rows_), n)
            total = lambda x: np.diff(np.concatenate([np.zeros(1, np.uint64), np.cumsum(x)])[at])  # noqa: E731, B023
            v = mix(total(mix(h)) + n.astype(np.uint64)).view(np.int64)
            twin = mix(total(mix(h ^ np.uint64(0xA5A5A5A5A5A5A5A5)))).view(np.int64)
            held = np.bincount(owner * GROUPS + (mix(h) >> np.uint64(56)).astype(np.int64), minlength=rows_ * GROUPS).reshape(rows_, GROUPS)
            size = np.where(n > 0, n - -(-percent * n // 100) + 1, 0)
            ends = np.concatenate([[0], np.cumsum(size)])
            places, top = first_posted(h, at, size, common)
            posted = h[places].view(np.int64)
            yield pa.RecordBatch.from_arrays([batch.column(0).slice(first, rows_), batch.column(1).slice(first, rows_), pa.array(n), pa.array(v), pa.array(twin), pa.array(top), pa.array([packed_counts(x) for x in held], pa.binary()), pa.ListArray.from_arrays(pa.array(ends.astype(np.int32)), pa.array(posted))], names=POINT.names)
        pa.default_memory_pool().release_unused()


class CountTree:
    """R-tree over count vectors, packed by sorting: boxes keep their upper corner and the least set size inside."""

    def __init__(self, counts: np.ndarray, n: np.ndarray):
        # packing order: by size, then by the heaviest half of the groups, so that boxes stay tight
        self.order = np.lexsort((counts[:, : GROUPS // 2].sum(axis=1), n // 8))
        self.counts, self.n = counts[self.order], n[self.order]
        self.levels = []
        corner, least = self.counts, self.n
        while len(corner) > 1:
            cuts = np.arange(0, len(corner), LEAF)
            corner, least = np.maximum.reduceat(corner, cuts, axis=0), np.minimum.reduceat(least, cuts)
            self.levels.append((corner, least))

    def reach(self, q: np.ndarray, n: int, percent: int) -> np.ndarray:
        """Rows whose overlap bound with a query point reaches the overlap their sizes need."""
        at = np.arange(1)
        for corner, least in reversed(self.levels):
            at = at[at < len(corner)]
            at = at[np.minimum(corner[at], q).sum(axis=1) >= needed(least[at], n, percent)]
            at = (at[:, None] * LEAF + np.arange(LEAF)).ravel()
        at = at[at < len(self.n)]
        return self.order[at[np.minimum(self.counts[at], q).sum(axis=1) >= needed(self.n[at], n, percent)]]




def tree_pairs(rows: Iterator[pa.RecordBatch], percent: int, best: bool) -> Iterator[pa.RecordBatch]:
    """Rows (posting, band, home, vertex, n, label, weight, counts) in order of (posting, band) -> candidate pairs of
    different labels, with the number of postings in which this task found them (each pair once in a posting).

    ``best``: of a vertex's candidates in a posting only the one whose bound is furthest above the overlap needed.
    """
    key, held, pairs = None, [], []

    def found() -> None:
        home, v, n, label, weight, counts = (np.concatenate([h[k] for h in held]) for k in range(6))
        own = np.flatnonzero(home)
        names, place, members = np.unique(label, return_inverse=True, return_counts=True)
        if not len(own) or len(names) == 1:
            return
        # of two vertices of different labels one at least is outside the label that most have
        out = place != members.argmax()
        meet(home, v, n, label, weight, counts, np.flatnonzero(out), own)
        meet(home, v, n, label, weight, counts, np.flatnonzero(~out), own[out[own]])

    def meet(home, v, n, label, weight, counts, some: np.ndarray, own: np.ndarray) -> None:
        """Candidates of the rows ``some`` among the rows ``own`` at home."""
        if not len(own):
            return
        if len(own) <= FEW:  # one leaf: all bounds at once
            mine = counts[own]
            for lo in range(0, len(some), FEW):
                at = some[lo : lo + FEW]
                above = np.minimum(counts[at, None], mine[None]).sum(axis=2) - needed(n[own][None], n[at, None], percent)
                good = (above >= 0) & (label[own][None] != label[at, None])
                if best:
                    good &= np.arange(len(own)) == np.where(good, above, -1).argmax(axis=1)[:, None]
                else:
                    good &= ~home[at, None] | (v[own][None] < v[at, None])
                x, y = np.nonzero(good)
                if len(x):
                    x, y = v[at[x]], v[own[y]]
                    pairs.append(np.stack([np.minimum(x, y), np.maximum(x, y), np.full(len(x), weight[0])]))
            return
        tree = CountTree(counts[own], n[own])
        for x in some.tolist():
            near = own[tree.reach(counts[x], int(n[x]), percent)]
            near = near[(label[near] != label[x]) & (best | ~home[x] | (v[near] < v[x]))]
            if best and len(near) > 1:
                above = np.minimum(counts[near], counts[x]).sum(axis=1) - needed(n[near], n[x], percent)
                near = near[[above.argmax()]]
            if len(near):
                pairs.append(np.stack([np.minimum(v[near], v[x]), np.maximum(v[near], v[x]), np.full(len(near), weight[0])]))

    def handed() -> pa.RecordBatch:
        """The pairs so far, each once: postings that two vertices share find them again and again."""
        a, b, times = np.concatenate([np.zeros((3, 0), np.int64), *pairs], axis=1)
        pairs.clear()
        order = np.lexsort((b, a))
        a, b, times = a[order], b[order], times[order]
        first = np.flatnonzero(np.concatenate([[True], (a[1:] != a[:-1]) | (b[1:] != b[:-1])])[: len(a)])
        shared = np.add.reduceat(times, first) if len(first) else times
        return pa.RecordBatch.from_arrays([pa.array(a[first]), pa.array(b[first]), pa.array(shared)], names=FOUND.names)

    for batch in rows:
        t, band, home, v, n, label, weight = (batch.column(k).to_numpy(zero_copy_only=False) for k in range(7))
        counts = unpacked_counts(batch.column(7))
        edges = [0, *(np.flatnonzero((t[1:] != t[:-1]) | (band[1:] != band[:-1])) + 1).tolist(), len(t)]
        for a, b in zip(edges[:-1], edges[1:], strict=True):
            if a < b and (t[a], band[a]) != key:
                if held:
                    found()
                if len(pairs) > FLUSH:
                    yield handed()
                key, held = (t[a], band[a]), []
            held.append((home[a:b], v[a:b], n[a:b], label[a:b], weight[a:b], counts[a:b]))
    if held:
        found()
    yield handed()


def verified(rows: Iterator[pa.RecordBatch], words: int, percent: int) -> Iterator[pa.RecordBatch]:
    """Rows (pivot, chunk, side, vertex, text) in this order, a pivot's own text first -> the pairs at or above the threshold."""
    key, pivot = None, np.zeros(0, np.uint64)
    for batch in rows:
        a, chunk, side, u = (batch.column(k).to_numpy() for k in range(4))
        keep = np.zeros(len(a), bool)
        for first, end, data, offsets in text_blocks(batch, "text", 1 << 19):
            h, at = shingle_sets(data, offsets, words)
            for k in range(first, end):
                own = h[at[k - first] : at[k - first + 1]]
                if not side[k]:
                    key, pivot = (a[k], chunk[k]), own.copy()
                elif len(pivot) and (a[k], chunk[k]) == key:
                    place = np.minimum(np.searchsorted(pivot, own), len(pivot) - 1)
                    keep[k] = int((pivot[place] == own).sum()) >= needed(len(pivot), len(own), percent)
        yield pa.RecordBatch.from_arrays([pa.array(a[keep]), pa.array(u[keep])], names=PAIR.names)


def bounded(rows: Iterator[pa.RecordBatch], percent: int) -> Iterator[pa.RecordBatch]:
    """(a, b, n and counts of a, of b) -> the pairs whose summed minima reach the overlap needed."""
    for batch in rows:
        n, m = batch.column(2).to_numpy(), batch.column(4).to_numpy()
        x, y = (unpacked_counts(batch.column(k)) for k in (3, 5))
        yield batch.select([0, 1]).filter(pa.array(np.minimum(x, y).sum(axis=1) >= needed(n, m, percent)))


def one_of_each(post: DataFrame) -> DataFrame:
    """Postings ``(u, t)`` of vertices -> ``(t, pivot, weight)``: one of the postings that the same vertices share, and their number."""
    who = post.groupBy("t").agg(F.min("u").alias("pivot"), F.max("u").alias("top"), F.count(F.lit(1)).alias("n"), F.expr("bit_xor(xxhash64(u))").alias("x"), F.expr("bit_xor(xxhash64(u, 1))").alias("y"))
    return who.where("pivot <> top").groupBy("pivot", "n", "x", "y").agg(F.min("t").alias("t"), F.count(F.lit(1)).alias("weight")).select("t", "pivot", "weight")


def gathered(rows: DataFrame, *keys: str, within: tuple[str, ...] = ()) -> DataFrame:
    """Rows of equal keys one after the other in one task.

    They are dealt by a hash of the keys, not by the keys: after joins or counts on the same keys Spark would leave out the
    exchange, as rows lie right already, and adaptive execution may then replace those joins and read rows where they were
    written, since nothing it knows of still asks for them together.
    """
    return rows.repartition(F.xxhash64(*keys)).sortWithinPartitions(*keys, *within)


def near_sets(docs: DataFrame, key: str = "doc_id", text: str = "text", words: int = 4, percent: int = 85) -> DataFrame:
    """``(doc_id, n_shingles, component_id)`` for each row.

    Null, empty and wordless texts have no shingles and stay alone. Rows of one id are one vertex of the links; rows
    with a null id get a null component and link nothing. Empty tables give empty ones; other columns are ignored.
    """
    cuts = Cuts()
    texts = docs.select(F.col(key).cast("long").alias("doc_id"), F.xxhash64(text).alias("h"), F.col(text).alias("text"))
    common = common_hashes(texts, words)
    wide = cuts(texts.mapInArrow(lambda it: points(it, words, percent, common), POINT).withColumn("row", F.monotonically_increasing_id()))
    made = cuts(wide.select("doc_id", "h", "n", "v", "twin", "row"))
    some = made.where("n > 0 and doc_id is not null")
    # a vertex takes the number of one row that holds its set
    vertex = cuts(some.groupBy("n", "v", "twin").agg(F.min(F.struct("doc_id", "row", "h")).alias("least")).select("n", "v", "twin", F.col("least.row").alias("u"), F.col("least.doc_id").alias("id"), F.col("least.h").alias("h")))
    own = cuts(wide.select("row", "n", "top", "counts", "posted").join(vertex.select(F.col("u").alias("row")), "row", "left_semi").withColumnRenamed("row", "u"))
    cuts.drop(wide)
    post = own.select("u", F.explode("posted").alias("t"))
    shared = cuts(post.groupBy("t").agg(F.min("u").alias("pivot"), F.count(F.lit(1)).alias("n")).where("n > 1").select("t"))
    held = cuts(post.join(shared, "t"))
    kept = cuts(one_of_each(held))
    post = cuts(held.join(kept, "t").select("t", "u", "pivot", "weight"))
    point = cuts(own.select("u", "n", "top", "counts").join(post.select("u").distinct(), "u", "left_semi"))
    cuts.drop(own, shared, held, kept)
    size = vertex.select("u", "n")
    least = lambda x, y: 100 * F.least(x, y) >= percent * F.greatest(x, y)

    def check(pairs: DataFrame) -> DataFrame:
        """Exact verification: texts come to a pivot's group, in chunks that each get a copy of the pivot's text."""
        pairs = cuts(pairs)
        times = pairs.groupBy("a").agg(F.ceil(F.count(F.lit(1)) / CHUNK).cast("int").alias("chunks"))
        heads = times.select("a", F.explode(F.sequence(F.lit(0), F.col("chunks") - 1)).alias("chunk"), F.lit(0).alias("side"), F.col("a").alias("u"))
        tails = pairs.join(times, "a").select("a", F.pmod(F.xxhash64("b"), "chunks").cast("int").alias("chunk"), F.lit(1).alias("side"), F.col("b").alias("u"))
        roles = cuts(heads.unionByName(tails).join(vertex.select("u", "id", F.col("h").alias("hash")), "u"))
        few = roles.count() <= BROADCAST_ROWS
        rows = texts.join(F.broadcast(roles) if few else roles, (F.col("doc_id") == F.col("id")) & (F.col("h") == F.col("hash")))
        rows = gathered(rows.select("a", "chunk", "side", "u", "text"), "a", "chunk", within=("side",))
        out = cuts(rows.mapInArrow(lambda it: verified(it, words, percent), PAIR).distinct())
        cuts.drop(pairs, roles)
        return out

    times = post.where("u <> pivot").groupBy("u", "pivot").agg(F.sum("weight").alias("times"))
    star = times.groupBy("u").agg(F.max_by("pivot", F.struct("times", "pivot")).alias("a")).select("a", F.col("u").alias("b"))
    na, nb = (size.select(F.col("u").alias(x), F.col("n").alias(f"n{x}")) for x in "ab")
    star = cuts(star.join(na, "a").join(nb, "b").where(least("na", "nb")).select("a", "b", "na", "nb"))
    ca, cb = (point.select(F.col("u").alias(x), F.col("counts").alias(f"c{x}")) for x in "ab")
    near = star.join(ca, "a").join(cb, "b").select("a", "b", "na", "ca", "nb", "cb").mapInArrow(lambda it: bounded(it, percent), PAIR)
    links = check(near)
    label = cuts(components(links))
    band = F.floor(F.log("n") / math.log(100 / percent) + 1e-9)
    left = post.select("t", "u", "weight").join(size, "u").select("t", "weight", F.explode(F.array(F.struct(band.alias("band"), F.lit(True).alias("home")), F.struct((band + 1).alias("band"), F.lit(False).alias("home")))).alias("in"), "u", "n")
    left = cuts(left.select("t", "in.band", "in.home", "u", "n", "weight"))

    def trees(label: DataFrame, best: bool) -> DataFrame:
        """Candidates from the bands of postings that hold several components, one of them at home (``best``: from the crowded ones)."""
        open_ = left.join(label, F.col("u") == F.col("id"), "left").withColumn("label", F.coalesce("component_id", "u"))
        split = open_.groupBy("t", "band").agg(F.min("label").alias("x"), F.max("label").alias("y"), F.bool_or("home").alias("any"), F.count(F.lit(1)).alias("members"))
        split = split.where(f"x <> y and any and members > {CROWDED if best else 1}").select("t", "band")
        rows = open_.join(split, ["t", "band"]).join(point.select("u", "counts"), "u")
        rows = gathered(rows.select("t", "band", "home", "u", "n", "label", "weight", "counts"), "t", "band")
        found = rows.mapInArrow(lambda it: tree_pairs(it, percent, best), FOUND).groupBy("a", "b").agg(F.sum("shared").alias("shared"))
        return found if best else enough(found)

    def enough(found: DataFrame) -> DataFrame:
        """Pairs, with all the postings they share counted, whose postings and sizes leave the overlap needed possible."""
        pa_, pb = (point.select(F.col("u").alias(x), F.col("n").alias(f"n{x}"), F.col("top").alias(f"t{x}")) for x in "ab")
        rest = {x: F.expr(f"(n{x} * {percent} + 99) div 100 - 1") for x in "ab"}
        beyond = F.when(F.col("ta") < F.col("tb"), rest["a"]).when(F.col("ta") > F.col("tb"), rest["b"]).otherwise(F.greatest(rest["a"], rest["b"]))
        return found.join(pa_, "a").join(pb, "b").where((F.col("shared") + beyond) * (100 + percent) >= percent * (F.col("na") + F.col("nb"))).select("a", "b")

    # crowds first grow together along each vertex's best candidate; then every pair still open is looked at
    links = links.unionByName(check(trees(label, True).select("a", "b")))
    whole = cuts(components(links))
    links = links.unionByName(check(trees(whole, False)))
    cuts.drop(left, label, whole, star, post, point)
    # the sets of one id are one vertex
    rows = cuts(made.join(vertex.select("n", "v", "twin", "u"), ["n", "v", "twin"], "left").select("doc_id", "n", F.when(F.col("doc_id").isNotNull(), F.col("u")).alias("u")))
    many = rows.where("u is not null").groupBy("doc_id").agg(F.min("u").alias("a"), F.max("u").alias("b")).where("a <> b").select("doc_id", "a")
    links = links.unionByName(rows.join(many, "doc_id").where("u <> a").select("a", F.col("u").alias("b")))
    root = components(links).select(F.col("id").alias("u"), F.col("component_id").alias("root"))
    named = cuts(vertex.select("u", "id").join(root, "u", "left").select("u", "id", F.coalesce("root", "u").alias("root")))
    cuts.drop(made, vertex)
    named = named.join(named.groupBy("root").agg(F.min("id").alias("least")), "root").select("u", F.col("least").alias("component_id"))
    return rows.join(named, "u", "left").select("doc_id", F.col("n").alias("n_shingles"), F.coalesce("component_id", "doc_id").alias("component_id"))
