"""Removal of repeated byte strings by hash-compared suffix sorting.

A byte goes if some ``length``-byte string that covers it also starts elsewhere (in any text; strings lie inside one
text and may overlap). Suffixes are sorted only where they can matter:

1. Anchors. Every window of ``length`` bytes names the position in it where a ``gram``-byte hash is least. Equal
   windows name the same place, so windows are grouped by anchor and about one position in 75 is an anchor. An anchor
   owns a run of window starts; its context is the bytes that those windows cover.
2. Anchors whose gram occurs once are done: none of their windows repeats. Anchors that share gram and context with
   another are done too: all their windows repeat. Only groups with different contexts of one gram go on, each
   context once.
3. In such a group the suffixes that start at the anchors are sorted by mergesort, as are the reversed prefixes that
   end there. A comparison finds the common extension by binary search over prefix polynomial hashes (a logarithmic
   number of probes), verifies it on the bytes, and looks at the next byte. Contexts are then joined in order of
   falling common extension (small sets into large ones), with neighbours in the order of prefixes giving the longest
   extension to the left; a pair with left + right >= length marks the windows it shares.
4. Groups of more than ``most`` contexts are split before that, by ranges of the distance between window start and
   anchor: windows of a range share a core of bytes, whose hash is the new group. A group whose members agree in the
   whole range is settled by a combining count; what is still large goes on to narrower ranges, down to single windows,
   which always settle. So no group has to fit one task, and a context costs a few rows, not one a window.
5. Repeated windows turn into byte intervals, merged for each text and cut out.
"""

from __future__ import annotations

import hashlib
from bisect import bisect_left
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import PrefixHash, cut, mix, text_blocks

LENGTH, GRAM = 200, 48


def anchors(data: np.ndarray, offsets: np.ndarray, length: int = LENGTH, gram: int = GRAM) -> tuple[np.ndarray, ...]:
    """Runs of window starts with one anchor: (text, first start, last start, anchor, gram hash, context hash); places in the block."""
    n, wide = len(data), length - gram + 1
    none = tuple(np.zeros(0, t) for t in (np.int64, np.int64, np.int64, np.int64, np.uint64, np.uint64))
    if n < length:
        return none
    hashed = PrefixHash(data)
    at = np.arange(n - gram + 1)
    h = hashed.of(at, at + gram)
    # order of grams: 32 scrambled bits, then the place, so that the leftmost of equal grams wins
    key = (mix(h) & np.uint64(0xFFFFFFFF00000000)) | at.astype(np.uint64)
    pad = -len(key) % wide
    key = np.concatenate([key, np.full(pad, np.iinfo(np.uint64).max, np.uint64)]).reshape(-1, wide)
    left = np.minimum.accumulate(key, axis=1).ravel()
    right = np.minimum.accumulate(key[:, ::-1], axis=1)[:, ::-1].ravel()
    starts = np.arange(n - length + 1)
    anchor = (np.minimum(right[: len(starts)], left[wide - 1 : wide - 1 + len(starts)]) & np.uint64(0xFFFFFFFF)).astype(np.int64)
    text = np.searchsorted(offsets, starts, side="right") - 1
    valid = starts + length <= offsets[text + 1]
    starts, anchor, text = starts[valid], anchor[valid], text[valid]
    if not len(starts):
        return none
    new = np.ones(len(starts), bool)
    new[1:] = (anchor[1:] != anchor[:-1]) | (text[1:] != text[:-1])
    first = np.flatnonzero(new)
    last = np.append(first[1:], len(starts)) - 1
    lo, hi, a = starts[first], starts[last], anchor[first]
    context = mix(hashed.of(lo, hi + length) + mix(((a - lo) << 20 | (hi - lo)).astype(np.uint64)))
    return text[first], lo, hi, a, h[a], context


class Sorter:
    """Mergesort of strings in one buffer by hashed common extensions."""

    mask = (1 << 64) - 1

    def __init__(self, strings: list[bytes]):
        self.data = b"".join(strings)
        hashed = PrefixHash(np.frombuffer(self.data, np.uint8))
        self.sums, self.down = hashed.sums.tolist(), hashed.down[: len(self.data) + 1].tolist()

    def common(self, i: int, j: int, most: int) -> int:
        """Length of the common extension of two places: binary search over prefix hashes, verified on the bytes."""
        sums, down, mask, data = self.sums, self.down, self.mask, self.data
        low, high = 0, most
        while low < high:
            mid = (low + high + 1) >> 1
            if ((sums[i + mid] - sums[i]) * down[i] - (sums[j + mid] - sums[j]) * down[j]) & mask:
                high = mid - 1
            else:
                low = mid
        while data[i : i + low] != data[j : j + low]:  # a collision: the equal part is shorter
            low = next(k for k in range(low) if data[i + k] != data[j + k])
        return low

    def sort(self, starts: list[int], ends: list[int]) -> tuple[list[int], list[int]]:
        """Order of the strings [start, end), and the common extension of each with the one before it in that order."""

        def less(x: int, y: int) -> bool:
            i, j = starts[x], starts[y]
            most = min(ends[x] - i, ends[y] - j)
            k = self.common(i, j, most)
            return ends[x] - i < ends[y] - j if k == most else self.data[i + k] < self.data[j + k]

        def merged(a: list[int], b: list[int]) -> list[int]:
            out, p, q = [], 0, 0
            while p < len(a) and q < len(b):
                if less(b[q], a[p]):
                    out.append(b[q])
                    q += 1
                else:
                    out.append(a[p])
                    p += 1
            return out + a[p:] + b[q:]

        runs = [[k] for k in range(len(starts))]
        while len(runs) > 1:
            runs = [merged(runs[k], runs[k + 1]) if k + 1 < len(runs) else runs[k] for k in range(0, len(runs), 2)]
        order = runs[0] if runs else []
        pairs = zip(order, order[1:], strict=False)
        return order, [0, *(self.common(starts[x], starts[y], min(ends[x] - starts[x], ends[y] - starts[y])) for x, y in pairs)]


def repeats(contexts: list[tuple[bytes, int, int, int]], length: int = LENGTH) -> list[list[tuple[int, int]]]:
    """For contexts (bytes, anchor's place, first and last window start to judge): runs of window starts that another context shares.

    All contexts hold the same gram at their anchors. A pair shares the windows that start up to ``l`` bytes before the
    anchor and end up to ``r`` behind it, for its common extensions l and r.
    """
    n = len(contexts)
    right = Sorter([c[a:] for c, a, _, _ in contexts])
    ends = np.cumsum([len(c) - a for c, a, _, _ in contexts]).tolist()
    order, reach = right.sort([e - (len(c) - a) for e, (c, a, _, _) in zip(ends, contexts, strict=True)], ends)
    left = Sorter([c[:a][::-1] for c, a, _, _ in contexts])
    ends = np.cumsum([a for _, a, _, _ in contexts]).tolist()
    starts = [e - a for e, (_, a, _, _) in zip(ends, contexts, strict=True)]
    back, _ = left.sort(starts, ends)
    rank = [0] * n
    for r, x in enumerate(back):
        rank[x] = r
    marks: list[list[tuple[int, int]]] = [[] for _ in range(n)]
    sets = [[rank[x]] for x in order]  # by place in the order of suffixes
    of = list(range(n))

    def root(k: int) -> int:
        while of[k] != k:
            of[k] = of[of[k]]
            k = of[k]
        return k

    for k in sorted(range(1, n), key=lambda k: -reach[k]):
        r = reach[k]
        if r < GRAM:
            break
        big, small = root(k - 1), root(k)
        if len(sets[big]) < len(sets[small]):
            big, small = small, big
        kept = sets[big]
        for s in sets[small]:
            p = bisect_left(kept, s)
            for q in (p - 1, p):
                if 0 <= q < len(kept):
                    x, y = back[s], back[kept[q]]
                    i, j = starts[x], starts[y]
                    l = left.common(i, j, min(ends[x] - i, ends[y] - j))
                    if l + r >= length:
                        for z in (x, y):
                            _, a, lo, hi = contexts[z]
                            if (first := max(lo, a - l)) <= (last := min(hi, a + r - length)):
                                marks[z].append((first, last))
        merged = sorted(kept + sets[small])
        sets[big], sets[small], of[small] = merged, [], big
    return marks


def fields(**kinds: T.DataType) -> T.StructType:
    return T.StructType([T.StructField(n, t) for n, t in kinds.items()])


LONG, INT = T.LongType(), T.IntegerType()
ANCHORS = fields(key=LONG, tag=LONG, h=LONG, ctx=LONG, pos=LONG)
PIECE = fields(g=LONG, h=LONG, ctx=LONG, a=INT, lo=INT, hi=INT, bytes=T.BinaryType())
PART = fields(**{f.name: f.dataType for f in PIECE}, c=LONG)
#: Widths of the ranges that large groups are split into, one after the other.
WIDTHS = (32, 8, 2, 1)
RUN = fields(h=LONG, ctx=LONG, first=INT, last=INT)


def signed(x: np.ndarray) -> pa.Array:
    return pa.array(np.ascontiguousarray(x).view(np.int64))


def find_anchors(texts: DataFrame, length: int) -> DataFrame:
    """``(key, tag, h, ctx, pos)``: pos packs the first window start with the distances to the anchor and the last window start."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keys, tags = (batch.column(k).to_numpy(zero_copy_only=False).astype(np.int64) for k in (0, 1))
            for first, _, data, offsets in text_blocks(batch, "text"):
                row, lo, hi, a, h, ctx = anchors(data, offsets, length)
                pos = (lo - offsets[row]) << 20 | (a - lo) << 10 | (hi - lo)
                yield pa.RecordBatch.from_arrays([pa.array(keys[first + row]), pa.array(tags[first + row]), signed(h), signed(ctx), pa.array(pos)], names=ANCHORS.names)

    return texts.select("key", "tag", "text").mapInArrow(run, ANCHORS)


def asked(batch: pa.RecordBatch) -> Iterator[tuple[np.ndarray, int, dict, int, int, int]]:
    """The anchors asked for of each text: its block, where it begins, the request, and first start, anchor, last start."""
    wants = batch.column(batch.schema.get_field_index("want")).to_pylist()
    for first, end, data, offsets in text_blocks(batch, "text"):
        for row in range(first, end):
            for want in wants[row]:
                pos = want["pos"]
                yield data, int(offsets[row - first]), want, pos >> 20, (pos >> 20) + (pos >> 10 & 1023), (pos >> 20) + (pos & 1023)


def batch_of(rows: list[tuple], schema: T.StructType) -> pa.RecordBatch:
    kinds = {LONG: pa.int64(), INT: pa.int32(), T.BinaryType(): pa.binary()}
    cols = list(zip(*rows, strict=True)) if rows else [[]] * len(schema)
    return pa.RecordBatch.from_arrays([pa.array(c, kinds[f.dataType]) for c, f in zip(cols, schema, strict=True)], names=schema.names)


def cut_contexts(rows: Iterator[pa.RecordBatch], length: int) -> Iterator[pa.RecordBatch]:
    """Bytes of contexts: the anchor's place and the last window start count from the first window start, ``lo`` is 0."""
    for batch in rows:
        yield batch_of([(w["h"], w["h"], w["ctx"], a - lo, 0, hi - lo, data[at + lo : at + hi + length].tobytes()) for data, at, w, lo, a, hi in asked(batch)], PIECE)


def split_ranges(rows: Iterator[pa.RecordBatch], width: int, length: int) -> Iterator[pa.RecordBatch]:
    """Pieces cut into ranges of ``width`` distances from the anchor. Group: hash of the core that all windows of the
    range share, whether the piece owns all of them or not; ``c``: hash of the piece's own windows of the range."""
    for batch in rows:
        out = []
        for _, h, ctx, a, lo, hi, data in zip(*(batch.column(k).to_pylist() for k in range(7)), strict=True):
            hashed = PrefixHash(np.frombuffer(data, np.uint8))
            # distances a - p of the window starts p in [lo, hi]; bytes begin at lo
            for d in range((a - hi) // width * width, a - lo + 1, width):
                x, y = max(lo, a - (d + width - 1)), min(hi, a - d)
                core, own = hashed.of(np.array([a - d, x]) - lo, np.array([a - (d + width - 1) + length, y + length]) - lo)
                g = mix(np.array([core + np.uint64(d * 1024 + width)]))
                c = mix(np.array([own + np.uint64((a - x) * 1024 + (a - y))]))
                out.append((int(g.view(np.int64)[0]), h, ctx, a, x, y, data[x - lo : y + length - lo], int(c.view(np.int64)[0])))
        yield batch_of(out, PART)


def sort_groups(rows: Iterator[pa.RecordBatch], length: int) -> Iterator[pa.RecordBatch]:
    """From contexts in order of their gram: runs of window starts (counted from a context's first) that repeat."""
    group: int | None = None
    held: list[tuple] = []

    def judged() -> list[tuple]:
        if len(held) < 2:
            return []
        found = repeats([(b, a - lo, 0, hi - lo) for _, _, a, lo, hi, b in held], length)
        return [(h, c, lo + f, lo + l) for (h, c, _, lo, *_), runs in zip(held, found, strict=True) for f, l in set(runs)]

    out: list[tuple] = []
    for batch in rows:
        for g, *piece in zip(*(batch.column(k).to_pylist() for k in range(7)), strict=True):
            if g != group:
                out += judged()
                group, held = g, []
            held.append(piece)
        if len(out) > 5000:
            yield batch_of(out, RUN)
            out = []
    yield batch_of(out + judged(), RUN)


def split_large(state: DataFrame, most: int, length: int) -> tuple[DataFrame, DataFrame]:
    """Large groups of pieces -> settled runs, and pieces in groups of at most ``most`` distinct contents."""
    n = F.count(F.lit(1))
    settled = state.select("h", "ctx", F.col("lo").alias("first"), F.col("hi").alias("last")).limit(0)
    small = state.limit(0)
    for width in WIDTHS:
        if state.isEmpty():
            break
        parts = cut(state.mapInArrow(lambda it, width=width: split_ranges(it, width, length), PART))
        same = parts.groupBy("g", "c").agg(n.alias("n"))
        groups = same.groupBy("g").agg(n.alias("m"))
        parts = parts.join(same, ["g", "c"])
        settled = settled.unionByName(parts.where("n > 1").select("h", "ctx", F.col("lo").alias("first"), F.col("hi").alias("last")))
        # one piece of each content goes on, if its group has others
        one = parts.groupBy("g", "c").agg(F.min(F.struct("h", "ctx", "a", "lo", "hi", "bytes")).alias("p")).join(groups.where("m > 1"), "g")
        rest = cut(one.select("g", "p.*", "m"))
        small = small.unionByName(rest.where(F.col("m") <= most).select(*PIECE.names))
        state = rest.where(F.col("m") > most).select(*PIECE.names)
    return settled, small


def strip(rows: Iterator[pa.RecordBatch], length: int, keep_bytes: bool) -> Iterator[pa.RecordBatch]:
    for batch in rows:
        keys, texts, runs = (batch.column(batch.schema.get_field_index(k)).to_pylist() for k in ("doc_id", "text", "runs"))
        out: list[list] = [[] for _ in range(6)]
        for key, text, found in zip(keys, texts, runs, strict=True):
            data = (text or "").encode()
            kept, at, removed, spans = [], 0, 0, 0
            end = -1
            for run in sorted(found or [], key=lambda r: r["lo"]):
                a, b = run["lo"], run["hi"] + length
                if a > end:
                    kept.append(data[at:a])
                    spans += 1
                    removed += b - a
                    at = end = b
                elif b > end:
                    removed += b - end
                    at = end = b
            kept.append(data[at:])
            left = b"".join(kept)
            for v, c in zip((key, len(data), removed, spans, hashlib.sha256(left).hexdigest(), left if keep_bytes else None), out, strict=True):
                c.append(v)
        arrays = [pa.array(c, t) for c, t in zip(out, (pa.int64(), pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.binary()), strict=True)]
        yield pa.RecordBatch.from_arrays(arrays[: 5 + keep_bytes], names=["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256", "kept"][: 5 + keep_bytes])


def remove_repeats(docs: DataFrame, key: str = "doc_id", text: str = "text", length: int = LENGTH, most: int = 512, keep_bytes: bool = False) -> DataFrame:
    """``(doc_id, n_bytes, n_removed, n_spans, kept_sha256)`` and, on demand, the ``kept`` bytes, for each row.

    Null texts read as empty. Rows that repeat an id (null included) are texts of their own, told apart by a hash of
    the text; wholly equal rows are copies of each other. An empty table gives an empty one; other columns are ignored.
    Nothing is capped: see the module's text for groups of any size. ``length`` may be 64 to 1000.
    """
    texts = docs.select(F.col(key).cast("long").alias("doc_id"), F.coalesce(F.col(key).cast("long"), F.lit(-1)).alias("key"), F.xxhash64(F.col(text)).alias("tag"), F.col(text).alias("text"))
    found = find_anchors(texts, length)
    n = F.count(F.lit(1))
    shared = found.groupBy("h").agg(n.alias("n")).where("n > 1").select("h")
    twins = cut(found.join(shared, "h"))
    classes = twins.groupBy("h", "ctx").agg(n.alias("copies"), F.min(F.struct("key", "tag", "pos")).alias("one"))
    classes = cut(classes)
    mixed = classes.groupBy("h").agg(n.alias("n")).where("n > 1")
    want = cut(classes.join(mixed, "h").select("one.key", "one.tag", "n", F.struct("h", "ctx", "one.pos").alias("want")))
    whole = classes.where("copies > 1").select("h", "ctx", F.lit(0).alias("first"), F.lit(1023).alias("last"))

    def with_text(wanted: DataFrame) -> DataFrame:
        return texts.join(wanted.groupBy("key", "tag").agg(F.collect_list("want").alias("want")), ["key", "tag"]).select("doc_id", "want", "text")

    contexts = lambda wanted: with_text(wanted).mapInArrow(lambda it: cut_contexts(it, length), PIECE)
    pieces = contexts(want.where(F.col("n") <= most))
    runs = whole
    if not want.where(F.col("n") > most).isEmpty():
        settled, small = split_large(cut(contexts(want.where(F.col("n") > most))), most, length)
        pieces, runs = pieces.unionByName(small), runs.unionByName(settled)
    runs = runs.unionByName(pieces.repartition("g").sortWithinPartitions("g").mapInArrow(lambda it: sort_groups(it, length), RUN))
    lo, wide = F.shiftright("pos", 20), F.col("pos").bitwiseAND(1023)
    placed = twins.join(runs, ["h", "ctx"]).select("key", "tag", F.struct((lo + F.col("first")).alias("lo"), (lo + F.least(F.col("last"), wide)).alias("hi")).alias("run"))
    gone = placed.groupBy("key", "tag").agg(F.collect_list("run").alias("runs"))
    both = texts.join(gone, ["key", "tag"], "left").select("doc_id", "text", "runs")
    kinds = {"doc_id": LONG, "n_bytes": LONG, "n_removed": LONG, "n_spans": LONG, "kept_sha256": T.StringType()} | ({"kept": T.BinaryType()} if keep_bytes else {})
    return both.mapInArrow(lambda it: strip(it, length, keep_bytes), fields(**kinds))
