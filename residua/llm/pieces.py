"""SentencePiece encoding and decoding for merge-type vocabularies.

A text is cut where no vocabulary entry can span: before a space mark that follows another character. Inside such a
chunk the encoder keeps an agenda of adjacent symbol pairs ordered by score (leftmost first among equals) and merges
the best pair until none is left. The distinct chunks of a block of texts are merged together, one array column each;
long chunks, and those with characters outside ASCII and the vocabulary, take a heap. A bounded memo remembers chunks, found by a
64-bit hash and then compared by their bytes. A share of the chunks that a block meets for the first time is compared with the sentencepiece library
on the spot; a difference raises.
"""

from __future__ import annotations

import hashlib
import heapq
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import sentencepiece
from pyspark.sql import DataFrame
from pyspark.sql import types as T

from .common import PrefixHash, mix, text_blocks

MARK = "\u2581"
#: Chunks of more symbols use the heap; places in an agenda entry take so many bits.
ARRAY_SYMBOLS, PLACES = 60, 6
#: Columns merged together, and chunks remembered by a worker.
COLUMNS, MEMO = 2048, 400_000
#: Every so-manieth new chunk is compared with the library.
COMPARE = 32
NONE = np.int32(1 << 30)


#: Masks of the first bytes of an 8-byte word.
FIRST = np.array([(1 << 8 * k) - 1 for k in range(9)], np.uint64)
#: Fills up rows of bytes; no UTF-8 text has it.
FILL = b"\xff"


def ragged(starts: np.ndarray, lens: np.ndarray) -> np.ndarray:
    """Indices of all places of runs, one run after the other."""
    ends = np.cumsum(lens)
    out = np.repeat(starts - (ends - lens), lens)
    out += np.arange(len(out))
    return out


def short_words(data: np.ndarray, starts: np.ndarray, lens: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The first and the last 8 bytes of runs (the last as 0 if the first hold all): equal runs of up to 16 bytes have equal lengths and words."""
    padded = np.zeros(len(data) + 8, np.uint8)
    padded[: len(data)] = data
    word = np.ascontiguousarray(np.ndarray(len(data) + 1, "<u8", padded.data, strides=(1,)))
    return word[starts] & FIRST[np.minimum(lens, 8)], np.where(lens > 8, word[starts + np.maximum(lens - 8, 0)], np.uint64(0))


def same_runs(a: np.ndarray, at: np.ndarray, b: np.ndarray, to: np.ndarray, lens: np.ndarray) -> np.ndarray:
    """Whether the bytes of ``a`` from each place of ``at`` equal those of ``b`` from the place of ``to``, over ``lens`` of 1 or more."""
    if not len(lens):
        return np.zeros(0, bool)
    apart = a[ragged(at, lens)] != b[ragged(to, lens)]
    return ~np.logical_or.reduceat(apart, np.cumsum(lens) - lens)


class PieceCoder:
    def __init__(self, path: str):
        self.library = sp = sentencepiece.SentencePieceProcessor(model_file=path)
        n = sp.get_piece_size()
        self.pieces = [sp.id_to_piece(i) for i in range(n)]
        self.n, self.eos, self.unknown = n, sp.eos_id(), sp.unk_id()
        plain = {p: i for i, p in enumerate(self.pieces) if not (sp.is_control(i) or sp.is_unknown(i) or sp.is_byte(i) or sp.is_unused(i))}
        if any(MARK in p.lstrip(MARK) for p in plain):
            raise ValueError("a piece spans a space mark; chunks of this vocabulary are not independent")
        self.plain = plain
        self.byte = {int(self.pieces[i][3:5], 16): i for i in range(n) if sp.is_byte(i)}
        # rank 0 is the best score; equal scores share a rank, so that the leftmost pair wins
        self.rank = np.unique([-sp.get_score(i) for i in range(n)], return_inverse=True)[1].astype(np.int64)
        pairs = sorted((plain[p[:k]] * n + plain[p[k:]], i) for p, i in plain.items() for k in range(1, len(p)) if p[:k] in plain and p[k:] in plain)
        self.keys = np.array([k for k, _ in pairs], np.int64)
        self.made = np.array([i for _, i in pairs], np.int32)
        self.rank_of_pair = self.rank[self.made].astype(np.int32)
        self.slot = np.full(1 << 20, -1, np.int32)  # one pair for each hash value; pairs that lose their slot are searched for
        self.slot[self._hash(self.keys)] = np.arange(len(self.keys))
        self.of_char = np.full(0x110000, -1, np.int32)
        for p, i in plain.items():
            if len(p) == 1:
                self.of_char[ord(p)] = i
        self.of_char[32] = self.of_char[ord(MARK)]
        if self.byte:  # an ASCII character without a piece joins nothing and ends as its byte's id
            self.of_char[:128] = np.where(self.of_char[:128] < 0, -10 - np.arange(128), self.of_char[:128])
        self.of_odd = np.array([self.byte.get(b, 0) for b in range(128)], np.int32)
        self.joined = dict(pairs)
        self.digits, self.n_digits = self._rows([f"{i} ".encode() for i in range(n)])
        as_byte = {i: bytes([b]) for b, i in self.byte.items()}
        read = [as_byte[i] if i in as_byte else b"" if sp.is_control(i) else self.pieces[i].replace(MARK, " ").encode() for i in range(n)]
        self.read, self.n_read = self._rows(read)
        self.forget()

    @staticmethod
    def _rows(said: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
        """One filled-up item of bytes each, and their lengths."""
        width = max(map(len, said))
        return np.array([np.void(x.ljust(width, FILL)) for x in said]), np.array([len(x) for x in said])

    def forget(self) -> None:
        self.hash, self.at = np.zeros(0, np.uint64), np.zeros(0, np.int64)
        self.size, self.pool = np.zeros(0, np.int64), np.zeros(0, np.int32)
        self.bytes, self.start, self.lens = np.zeros(0, np.uint8), np.zeros(0, np.int64), np.zeros(0, np.int64)

    def _keep(self, order: np.ndarray) -> None:
        """Of the remembered chunks only those at ascending places ``order`` stay."""
        self.pool, self.bytes = self.pool[ragged(self.at[order], self.size[order])], self.bytes[ragged(self.start[order], self.lens[order])]
        self.hash, self.size, self.lens = self.hash[order], self.size[order], self.lens[order]
        self.at, self.start = np.cumsum(self.size) - self.size, np.cumsum(self.lens) - self.lens

    def _pair(self, left: np.ndarray, right: np.ndarray, at: np.ndarray) -> np.ndarray:
        """Agenda entries (rank, then place ``at``) of symbol pairs; NONE where no piece joins them. Symbols below 0 are no pieces."""
        hit, found = self._find(left, right)
        return np.where(found, (self.rank_of_pair[hit] << PLACES) | at, NONE)

    @staticmethod
    def _hash(keys: np.ndarray) -> np.ndarray:
        return (keys * 0x9E3779B97F4A7 >> 23) & 0xFFFFF

    def _find(self, left: np.ndarray, right: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Places of pairs in ``keys``, and whether they are there."""
        key = left.astype(np.int64) * self.n + right
        hit = self.slot[self._hash(key)]
        own = self.keys[hit] == key
        other = np.nonzero((hit >= 0) & ~own)
        if len(other[0]):
            at = np.minimum(np.searchsorted(self.keys, key[other]), len(self.keys) - 1)
            hit[other] = at
            own[other] = self.keys[at] == key[other]
        return hit, own & (left >= 0) & (right >= 0) & (hit >= 0)

    def _merge_arrays(self, flat: np.ndarray, lens: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Chunks of single-character symbols, a column each: every round pops the least agenda entry of each column."""
        cols, width = len(lens), int(lens.max()) + 2
        ids = np.full((cols, width), -2, np.int32)
        ids[np.arange(width) < lens[:, None]] = flat
        done = np.full((width, cols), -2, np.int32)
        ids = np.ascontiguousarray(ids.T)
        place = np.broadcast_to(np.arange(width, dtype=np.int32)[:, None], (width, cols))
        agenda = np.full((width, cols), NONE, np.int32)
        agenda[:-1] = self._pair(ids[:-1], ids[1:], place[:-1])
        after, before = np.minimum(place + 1, width - 1), np.maximum(place - 1, 0)
        every = np.arange(cols)
        while True:
            best = agenda.min(axis=0)
            go = np.flatnonzero(best < NONE)
            if len(go) < 0.7 * agenda.shape[1]:  # columns that have ended leave
                done[:, every] = ids
                if not len(go):
                    break
                every, best = every[go], best[go]
                ids, agenda, after, before = (np.ascontiguousarray(x[:, go]) for x in (ids, agenda, after, before))
                go = np.arange(len(go))
            else:
                best = best[go]
            m = agenda.shape[1]
            at = best & ((1 << PLACES) - 1)
            here = at * m + go
            i, ag, af, be = ids.reshape(-1), agenda.reshape(-1), after.reshape(-1), before.reshape(-1)
            gone = af[here] * m + go
            nxt = af[gone]
            far, prev = nxt * m + go, be[here]
            back = prev * m + go
            made = self.made[self._find(i[here], i[gone])[0]]
            i[here], i[gone], ag[gone] = made, -3, NONE
            af[here], be[far] = nxt, at
            ag[here] = self._pair(made, i[far], at)
            ag[back] = np.where(prev < at, self._pair(i[back], made, prev), ag[back])
        done = np.ascontiguousarray(done.T)
        held = (done != -2) & (done != -3)
        ids = done[held]
        low = ids < 0
        ids[low] = self.of_odd[-10 - ids[low]]
        return ids, held.sum(axis=1)

    def _merge_heap(self, chunk: str) -> list[int]:
        n, joined, size, rank = len(chunk), self.joined, self.n, self.rank
        ids = [self.plain.get(x, -1) for x in chunk]
        after, before = list(range(1, n + 1)), list(range(-1, n - 1))
        agenda: list[tuple] = []

        def offer(i: int, j: int) -> None:
            if i >= 0 and j < n and ids[i] >= 0 and ids[j] >= 0 and (m := joined.get(ids[i] * size + ids[j])) is not None:
                heapq.heappush(agenda, (int(rank[m]), i, j, ids[i], ids[j], m))

        for i in range(n - 1):
            offer(i, i + 1)
        while agenda:
            _, i, j, left, right, m = heapq.heappop(agenda)
            if ids[i] != left or ids[j] != right or after[i] != j:
                continue
            ids[i], ids[j] = m, -3
            after[i] = after[j]
            if after[i] < n:
                before[after[i]] = i
            offer(before[i], i)
            offer(i, after[i])
        return self._ids([x for x in ids if x != -3], chunk)

    def _ids(self, symbols: list[int], chunk: str) -> list[int]:
        """Characters without a piece become the ids of their UTF-8 bytes, in order of appearance."""
        if -1 not in symbols:
            return symbols
        odd = iter([c for c in chunk if c not in self.plain])
        out: list[int] = []
        for x in symbols:
            if x >= 0:
                out.append(x)
            else:
                c = next(odd)
                out += [self.byte[b] for b in c.encode()] if self.byte else [self.unknown]
        return out

    def learn(self, raw: bytes, lens: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Ids of chunks that stand one after the other in ``raw`` (``lens`` bytes each), and how many each has."""
        text = raw.decode()
        codes = np.frombuffer(text.encode("utf-32-le"), np.uint32)
        lead = (np.frombuffer(raw, np.uint8) & 0xC0) != 0x80
        ends = np.concatenate([[0], np.cumsum(lead)])[np.cumsum(lens)]
        starts = np.concatenate([[0], ends[:-1]])
        chars, symbols = ends - starts, self.of_char[codes]
        odd = np.add.reduceat(symbols == -1, starts) > 0
        size, parts = np.zeros(len(lens), np.int64), [None] * len(lens)
        slow = np.flatnonzero(odd | (chars > ARRAY_SYMBOLS))
        for k in slow.tolist():
            parts[k] = np.array(self._merge_heap(text[starts[k] : ends[k]].replace(" ", MARK)), np.int32)
            size[k] = len(parts[k])
        fast = np.flatnonzero(~odd & (chars <= ARRAY_SYMBOLS))
        fast = fast[np.argsort(chars[fast], kind="stable")]
        pool, at, used = [], np.zeros(len(lens), np.int64), 0
        for k in range(0, len(fast), COLUMNS):
            own = fast[k : k + COLUMNS]
            ids, n = self._merge_arrays(symbols[ragged(starts[own], chars[own])], chars[own])
            size[own], at[own] = n, used + np.cumsum(n) - n
            used += len(ids)
            pool.append(ids)
        for k in slow.tolist():
            at[k] = used
            used += len(parts[k])
            pool.append(parts[k])
        pool = np.concatenate(pool)
        probe = [k for k in range(0, len(lens), COMPARE) if codes[starts[k]] in (32, 0x2581) and chars[k] > 1]
        theirs = self.library.encode([text[starts[k] + 1 : ends[k]] for k in probe], num_threads=1) if probe else []
        for k, ids in zip(probe, theirs, strict=True):
            if pool[at[k] : at[k] + size[k]].tolist() != ids:
                raise ValueError(f"the library encodes {text[starts[k] : ends[k]]!r} as {ids}, the agenda as {pool[at[k] : at[k] + size[k]].tolist()}")
        return pool[ragged(at, size)], size

    def encode_block(self, raw: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Ids (without end ids) of the texts of a block, one after the other, and the offsets of each text's ids."""
        lens = np.diff(offsets)
        some = lens > 0
        if not some.any():
            return np.zeros(0, np.int32), np.zeros(len(lens) + 1, np.int64)
        view = raw.tobytes()
        one = [view[a:b] for a, b in zip(offsets[:-1].tolist(), offsets[1:].tolist(), strict=True) if b > a]
        if b"\xe2\x96\x81" in view:  # the mark itself reads as a space
            one = [x.replace(b"\xe2\x96\x81", b" ") for x in one]
        data = np.frombuffer(b" " + b" ".join(one), np.uint8)  # a space before each text that is not empty
        first = np.cumsum([0, *(len(x) + 1 for x in one)])[:-1]
        space = data == 32
        head = space.copy()
        head[1:] &= ~space[:-1]
        head[first] = True
        starts = np.flatnonzero(head)
        ends = np.append(starts[1:], len(data))
        lens_of = ends - starts
        head8, tail8 = short_words(data, starts, lens_of)
        long = np.flatnonzero(lens_of > 16)
        hashes = mix(mix(head8 + lens_of.astype(np.uint64)) + tail8)
        if len(long):
            at = np.cumsum(lens_of[long])
            hashes[long] = PrefixHash(data[ragged(starts[long], lens_of[long])]).of(at - lens_of[long], at)
        while True:  # chunks of one hash that differ take another one
            whole, pick, back = np.unique(hashes, return_index=True, return_inverse=True)
            like = pick[back]
            odd = (lens_of != lens_of[like]) | (head8 != head8[like]) | (tail8 != tail8[like])
            rest = long[~odd[long]]
            odd[rest] = ~same_runs(data, starts[rest], data, starts[like[rest]], lens_of[rest])
            if not odd.any():
                break
            hashes[odd] = mix(hashes[odd] + np.uint64(1))
        size = lens_of[pick]
        at = np.minimum(np.searchsorted(self.hash, whole), max(0, len(self.hash) - 1))
        new = np.ones(len(whole), bool)
        if len(self.hash):
            hit = np.flatnonzero((self.hash[at] == whole) & (self.lens[at] == size))
            new[hit] = ~same_runs(data, starts[pick[hit]], self.bytes, self.start[at[hit]], size[hit])
        if new.any():
            lack = pick[new]
            raws = data[ragged(starts[lack], size[new])]
            ids, n = self.learn(raws.tobytes(), size[new])
            if len(self.hash) + len(lack) > MEMO:  # only what this block uses stays
                self._keep(at[~new])
            elif len(self.hash) and (self.hash[at[new]] == whole[new]).any():  # a remembered chunk gives way to another one of its hash
                self._keep(np.flatnonzero(~np.isin(self.hash, whole[new])))
            to = np.searchsorted(self.hash, whole[new])
            self.hash, self.size, self.lens = np.insert(self.hash, to, whole[new]), np.insert(self.size, to, n), np.insert(self.lens, to, size[new])
            self.at = np.insert(self.at, to, len(self.pool) + np.cumsum(n) - n)
            self.start = np.insert(self.start, to, len(self.bytes) + np.cumsum(size[new]) - size[new])
            self.pool, self.bytes = np.concatenate([self.pool, ids]), np.concatenate([self.bytes, raws])
            at = np.searchsorted(self.hash, whole)
        slot = at[back]
        n = self.size[slot]
        ids = self.pool[ragged(self.at[slot], n)]
        total = np.concatenate([[0], np.cumsum(n)])
        bounds = np.zeros(len(lens) + 1, np.int64)
        bounds[:-1][some] = total[np.searchsorted(starts, first)]
        bounds[-1] = total[-1]
        for k in np.flatnonzero(~some)[::-1]:
            bounds[k] = bounds[k + 1]
        return ids, bounds

    def decode_block(self, flat: np.ndarray, at: np.ndarray) -> list[bytes]:
        """UTF-8 bytes of the texts that runs of ids (of encoded texts) stand for; every so-manieth is compared with the library."""
        if not self.byte:  # unknown characters are lost, and the library says how they read
            return [self.library.decode(flat[a:b].tolist()).encode() for a, b in zip(at[:-1].tolist(), at[1:].tolist(), strict=True)]
        said = self.read[flat].tobytes().translate(None, FILL)
        ends = np.concatenate([[0], np.cumsum(self.n_read[flat])])[at].tolist()
        out = [said[a + (said[a : a + 1] == b" " and b > a) : b] for a, b in zip(ends[:-1], ends[1:], strict=True)]
        for k in range(0, len(out), COMPARE):
            if out[k] != self.library.decode(flat[at[k] : at[k + 1]].tolist()).encode():
                raise ValueError(f"the library decodes {flat[at[k] : at[k + 1]][:50].tolist()} in another way")
        return out

    def encode(self, texts: list[str]) -> list[list[int]]:
        raw = [t.encode() for t in texts]
        ids, at = self.encode_block(np.frombuffer(b"".join(raw), np.uint8), np.cumsum([0, *map(len, raw)]))
        return [ids[a:b].tolist() for a, b in zip(at[:-1], at[1:], strict=True)]

    def decode(self, ids: list[int]) -> str:
        """Pieces joined, byte ids as UTF-8, space marks as spaces, the mark put before the text taken off."""
        raw = bytearray()
        back = {i: b for b, i in self.byte.items()}
        for i in ids:
            if i in back:
                raw.append(back[i])
            elif not self.library.is_control(i):
                raw += self.pieces[i].encode()
        return raw.decode("utf-8", "replace").replace(MARK, " ").removeprefix(" ")


CODERS: dict[str, PieceCoder] = {}


def coder(path: str) -> PieceCoder:
    """One coder for each vocabulary and worker process."""
    if path not in CODERS:
        CODERS[path] = PieceCoder(path)
    return CODERS[path]


SCHEMA = [("n_tokens", pa.int64()), ("ids_sha256", pa.string()), ("decoded_sha256", pa.string())]


def encode_column(docs: DataFrame, path: str, text: str = "text", keep: list[str] | None = None, ids: bool = False, end: bool = True) -> DataFrame:
    """``keep`` columns of ``docs`` plus n_tokens, ids_sha256, decoded_sha256 (and ``token_ids`` on demand).

    Null texts count as empty ones (only the end id); repeated rows stay repeated; an empty table gives an empty one.
    A kept column called like an output raises; other columns of ``docs`` are ignored.
    """
    keep = ["doc_id"] if keep is None else keep
    if clash := {x.lower() for x in keep} & {*(n for n, _ in SCHEMA), "token_ids"}:
        raise ValueError(f"kept columns and outputs share names: {sorted(clash)}")
    fields = [docs.schema[k] for k in keep] + [T.StructField("n_tokens", T.LongType()), T.StructField("ids_sha256", T.StringType()), T.StructField("decoded_sha256", T.StringType())]
    if ids:
        fields.append(T.StructField("token_ids", T.ArrayType(T.IntegerType())))
    kept = len(keep)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = coder(path)
        tail, last_id, sha = ([own.eos] if end else []), str(own.eos).encode(), hashlib.sha256
        for batch in batches:
            for first, last, raw, offsets in text_blocks(batch, "__text"):
                flat, at = own.encode_block(raw, offsets)
                line = own.digits[flat].tobytes().translate(None, FILL)
                cuts = np.concatenate([[0], np.cumsum(own.n_digits[flat])])[at].tolist()
                out: list[list] = [(np.diff(at) + len(tail)).tolist(), [], [], []]
                for a, b, text in zip(cuts[:-1], cuts[1:], own.decode_block(flat, at), strict=True):
                    out[1].append(sha(line[a:b] + last_id if end else line[a : max(a, b - 1)]).hexdigest())
                    out[2].append(sha(text).hexdigest())
                if ids:
                    out[3] = [flat[a:b].tolist() + tail for a, b in zip(at[:-1].tolist(), at[1:].tolist(), strict=True)]
                arrays = [pa.array(v, t) for v, (_, t) in zip(out, [*SCHEMA, ("token_ids", pa.list_(pa.int32()))] if ids else SCHEMA, strict=False)]
                rows = batch.slice(first, last - first)
                yield pa.RecordBatch.from_arrays([rows.column(k) for k in range(kept)] + arrays, names=[f.name for f in fields])
            pa.default_memory_pool().release_unused()

    return docs.select(*keep, docs[text].alias("__text")).mapInArrow(run, T.StructType(fields))
