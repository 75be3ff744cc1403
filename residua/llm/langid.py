"""Language identification by rank-order profiles of letter n-grams.

A profile lists a language's most frequent n-grams (one to three letters of words with a space at either end) by rank,
counted over all training texts. A document's own most frequent n-grams are compared with each profile by out-of-place
distance: the difference of ranks, or the profile's length for an n-gram it lacks. The smallest distance wins.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import free_name, text_blocks

#: N-grams of a profile.
PROFILE = 400
#: Bits of a symbol: any code point. An n-gram of fewer than three symbols has ``PAD`` in the places before.
BITS, PAD = 21, 1
#: Bytes of text looked at together, and distinct n-grams that a task holds before it hands on their counts.
WINDOW, HELD = 1 << 17, 1 << 19
TABLE: list[np.ndarray] = []


def symbols() -> np.ndarray:
    """Code point -> code point of the lower-case letter, 0 for what is no letter."""
    if not TABLE:
        table = np.zeros(0x110000, np.uint32)
        for c in range(0x110000):
            ch = chr(c)
            if ch.isalpha():
                low = ch.lower()
                table[c] = ord(low) if len(low) == 1 else c
        TABLE.append(table)
    return TABLE[0]


def decoded(data: np.ndarray) -> np.ndarray:
    return symbols()[np.frombuffer(data.tobytes().decode().encode("utf-32-le"), np.uint32)]


def grams(s: np.ndarray, before: np.ndarray, last: bool) -> tuple[np.ndarray, np.ndarray]:
    """N-grams that end in a stretch of symbols, and the stretch's last two symbols, which the next one takes as ``before``.

    Runs of separators count as one; a text begins after a separator (``before`` = [0]) and its last stretch ends with one.
    """
    parts = [before, s, np.zeros(1, np.uint32)] if last else [before, s]
    t = np.concatenate(parts).astype(np.int64)
    solid = t != 0
    keep = solid.copy()
    keep[1:] |= solid[:-1]
    keep[: len(before)] = True
    t = t[keep]
    n = len(before)
    one, end = t[n:], np.int64(PAD)
    pair = t[n - 1 : -1] << BITS | one
    out = [(end << 2 * BITS | end << BITS | one)[one > 0], end << 2 * BITS | pair]
    a, b, c = t[max(0, n - 2) : -2], t[max(1, n - 1) : -1], t[max(2, n) :]
    out.append((a << 2 * BITS | b << BITS | c)[b > 0])
    return np.concatenate(out), t[-2:]


def tallied(data: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Distinct n-grams and their counts in each stretch of a text, in ascending order of n-grams."""
    before, at = np.zeros(1, np.int64), 0
    while at < len(data):
        end = min(len(data), at + WINDOW)
        while end < len(data) and data[end] & 0xC0 == 0x80:
            end += 1
        g, before = grams(decoded(data[at:end]), before, end == len(data))
        yield np.unique(g, return_counts=True)
        at = end


def merged(parts: list[tuple[np.ndarray, np.ndarray]]) -> tuple[np.ndarray, np.ndarray]:
    """Counts of the same n-grams in several lists added up."""
    if len(parts) == 1:
        return parts[0]
    whole, back = np.unique(np.concatenate([g for g, _ in parts]), return_inverse=True)
    return whole, np.bincount(back, np.concatenate([n for _, n in parts])).astype(np.int64)


def profile_of(data: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Distinct n-grams of a whole text and their counts; a text without a letter has none."""
    held: list[tuple[np.ndarray, np.ndarray]] = []
    for part in tallied(data):
        held = [merged([*held, part])]
    g, n = held[0] if held else (np.zeros(0, np.int64), np.zeros(0, np.int64))
    letters = (g >> 2 * BITS == PAD) & (g >> BITS & (1 << BITS) - 1 == PAD)
    return (g, n) if letters.any() else (g[:0], n[:0])


COUNTS = T.StructType([T.StructField("lang", T.StringType()), T.StructField("gram", T.LongType()), T.StructField("n", T.LongType())])


def count_grams(rows: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """(text, lang) -> counts of n-grams by language; one that a task meets in many batches may come several times."""
    held: dict[str, list[tuple[np.ndarray, np.ndarray]]] = {}
    size = 0

    def handed() -> Iterator[pa.RecordBatch]:
        for lang, parts in held.items():
            g, n = merged(parts)
            yield pa.RecordBatch.from_arrays([pa.array([lang] * len(g), pa.string()), pa.array(g), pa.array(n)], names=COUNTS.names)

    for batch in rows:
        langs = batch.column(1).to_pylist()
        for first, _, data, offsets in text_blocks(batch, "text", WINDOW):
            by_lang: dict[str, list[np.ndarray]] = {}
            for k, (a, b) in enumerate(zip(offsets[:-1].tolist(), offsets[1:].tolist(), strict=True)):
                by_lang.setdefault(langs[first + k], []).append(data[a:b])
            for lang, texts in by_lang.items():
                # a line feed parts two texts: n-grams meet no more than the separator there
                whole = texts[0] if len(texts) == 1 else np.concatenate([x for t in texts for x in (t, np.full(1, 10, np.uint8))])
                for part in tallied(whole):
                    own = held.setdefault(lang, [])
                    own.append(part)
                    if len(own) > 16:
                        held[lang] = [merged(own)]
            size = sum(len(g) for parts in held.values() for g, _ in parts)
            if size > HELD:
                held = {lang: [merged(parts)] for lang, parts in held.items()}
                if sum(len(parts[0][0]) for parts in held.values()) > HELD // 2:
                    yield from handed()
                    held = {}
    yield from handed()


def learn(labelled: DataFrame, size: int = PROFILE) -> list[tuple[str, list[int]]]:
    """Profiles ``(lang, n-grams by rank)`` from columns text and lang; equal counts rank by n-gram.

    Counts cover all rows with text and lang. What reaches the driver is ``size`` n-grams a language.
    """
    counts = labelled.where("text is not null and lang is not null").select("text", "lang").mapInArrow(count_grams, COUNTS)
    counts = counts.groupBy("lang", "gram").agg(F.sum("n").alias("n")).withColumn("salt", F.pmod(F.hash("gram"), F.lit(16)))
    by = lambda *keys: Window.partitionBy(*keys).orderBy(F.desc("n"), "gram")
    top = counts.withColumn("r", F.row_number().over(by("lang", "salt"))).where(F.col("r") <= size)
    top = top.withColumn("r", F.row_number().over(by("lang"))).where(F.col("r") <= size)
    profiles: dict[str, list[int]] = {}
    for row in top.select("lang", "gram", "r").collect():
        profiles.setdefault(row.lang, [0] * size)[row.r - 1] = row.gram
    return sorted((lang, [g for g in p if g]) for lang, p in profiles.items())


PREDICTED = ("lang_pred", "score")


def predict(docs: DataFrame, profiles: list[tuple[str, list[int]]], keep: tuple[str, ...] = ("doc_id",), text: str = "text", size: int = PROFILE, names: tuple[str, str] = PREDICTED) -> DataFrame:
    """``keep`` columns plus the language and its score (1 - distance / largest distance), called ``names``.

    Null texts, texts without a letter, and all texts if nothing was learnt, are ``und`` with score 0; ties go to the
    first language by code point; repeated rows stay; an empty table gives an empty one. Whole texts are read, in stretches
    whose counts add up. A kept column called like an output raises; ``names`` says how to call the outputs instead.
    """
    if clash := {x.lower() for x in keep} & {x.lower() for x in names}:
        raise ValueError(f"kept columns and outputs share names: {sorted(clash)}")
    langs = [lang for lang, _ in profiles]
    vocabulary = np.unique(np.array([g for _, p in profiles for g in p], np.int64))
    ranks = np.full((len(vocabulary) + 1, max(1, len(langs))), size, np.int64)
    for k, (_, p) in enumerate(profiles):
        ranks[np.searchsorted(vocabulary, np.array(p, np.int64)), k] = np.arange(len(p))
    kept = len(keep)
    schema = T.StructType([docs.schema[k] for k in keep] + [T.StructField(names[0], T.StringType()), T.StructField(names[1], T.DoubleType())])
    own_text = text if text in keep else free_name("text", keep)  # a kept text goes to Python once

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        place = np.arange(size)
        for batch in batches:
            found, scores = [], []
            for _, _, data, offsets in text_blocks(batch, own_text, WINDOW):
                for a, b in zip(offsets[:-1].tolist(), offsets[1:].tolist(), strict=True):
                    whole, n = profile_of(data[a:b])
                    if not len(whole) or not langs:
                        found.append("und")
                        scores.append(0.0)
                        continue
                    # most frequent first, equal counts by n-gram
                    best = np.argsort(-n, kind="stable")[:size]
                    mine = whole[best]
                    v = np.minimum(np.searchsorted(vocabulary, mine), len(vocabulary) - 1)
                    v = np.where(vocabulary[v] == mine, v, len(vocabulary))
                    rank = ranks[v]
                    apart = np.where(rank < size, np.abs(rank - place[: len(best), None]), size).sum(axis=0)
                    k = int(apart.argmin())
                    found.append(langs[k])
                    scores.append(1 - float(apart[k]) / (size * len(best)))
            yield pa.RecordBatch.from_arrays([batch.column(k) for k in range(kept)] + [pa.array(found, pa.string()), pa.array(scores, pa.float64())], names=schema.names)
            pa.default_memory_pool().release_unused()

    given = docs.select(*keep) if text in keep else docs.select(*keep, docs[text].alias(own_text))
    return given.mapInArrow(run, schema)


def held_out(key: str = "doc_id") -> Column:
    return F.coalesce(F.crc32(F.col(key).cast("string").cast("binary")) % 3 == 1, F.lit(False))
