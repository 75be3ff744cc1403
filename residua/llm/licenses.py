"""License scans: normalised text against license templates by the Dice coefficient over word bigrams.

A text is compared as a whole, line by line, and in runs of consecutive words of any place and length, across lines. Dice
2c / (a + b) with at most min(a, b) common bigrams reaches the threshold t only if the smaller side has at least t / (2 - t)
of the larger side's bigrams: templates of which the text holds fewer bigrams are never looked at, and runs end where they
hold more. A best run begins and ends with a bigram of its template, so only those places are tried.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass
from pathlib import Path

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import types as T

#: Fixed wording of licenses and of the notices that name them.
TEMPLATES = (
    ("MIT", "Released under the MIT License."),
    ("MIT", "Licensed under the MIT License."),
    ("MIT", "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions:"),
    ("MIT", "The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software."),
    ("Apache-2.0", "Licensed under the Apache License, Version 2.0."),
    ("Apache-2.0", "Licensed under the Apache License, Version 2.0 (the \"License\"); you may not use this file except in compliance with the License."),
    ("Apache-2.0", "Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an \"AS IS\" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied."),
    ("GPL-3.0", "This work is licensed under the GNU General Public License, version 3."),
    ("GPL-3.0", "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version."),
    ("BSD-3-Clause", "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met:"),
    ("ISC", "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies."),
    ("CC-BY-4.0", "Licensed under CC BY 4.0."),
    ("CC-BY-SA-4.0", "Licensed under CC BY-SA 4.0."),
    ("CC-BY-NC-4.0", "Licensed under CC BY-NC 4.0."),
    ("MPL-2.0", "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0."),
    ("Unlicense", "This is free and unencumbered software released into the public domain."),
)

#: Whole license texts, one file each.
FULL_TEXTS = tuple((f.stem, f.read_text(encoding="utf-8")) for f in sorted((Path(__file__).parent / "license_texts").glob("*.txt")))

breaks = re.compile(r"[^\w\n]+|_+").sub


def normal(text: str) -> str:
    """Lower case, words apart by one space; line feeds stay."""
    return breaks(" ", text.lower())


def bigrams(words: list[str]) -> set[tuple[str, str]]:
    """Distinct word bigrams; a single word pairs with nothing."""
    return set(zip(words, words[1:], strict=False)) if len(words) > 1 else {(w, "") for w in words}


@dataclass(frozen=True)
class Template:
    name: str
    grams: frozenset


class Matcher:
    def __init__(self, templates: tuple[tuple[str, str], ...] = TEMPLATES + FULL_TEXTS, least: float = 0.8):
        self.least, self.ratio = least, least / (2 - least)
        self.templates = sorted((Template(n, frozenset(bigrams(normal(t).split()))) for n, t in templates), key=lambda t: (len(t.grams), t.name))
        self.known = frozenset().union(*(t.grams for t in self.templates))

    def held(self, grams: set[tuple[str, str]]) -> list[Template]:
        """Templates of which a text with these bigrams of templates holds enough for any of its units or runs."""
        return [t for t in self.templates if len(grams) >= self.ratio * len(t.grams) and len(grams & t.grams) >= self.ratio * len(t.grams)]

    def best(self, words: list[str], templates: list[Template] | None = None) -> tuple[str, float] | None:
        """Best template of a unit at or above the threshold; ties go to the smaller template, then by name."""
        grams = bigrams(words)
        n, top = len(grams), None
        for t in self.templates if templates is None else templates:
            m = len(t.grams)
            if min(n, m) < self.ratio * max(n, m):
                continue
            dice = 2 * len(grams & t.grams) / (n + m)
            if dice >= self.least and (top is None or dice > top[1]):
                top = (t.name, dice)
        return top

    def runs(self, pairs: list[tuple[str, str]], templates: list[Template]) -> list[tuple[float, int, int, str]]:
        """(Dice, first word, word after the last, license) of the best runs; of runs of one license that overlap, and of
        runs that share most of their words, the best one stays."""
        place: dict[tuple[str, str], int] = {}
        gram = np.array([place.setdefault(g, len(place)) for g in pairs], np.int64)
        order = np.argsort(gram, kind="stable")
        again = gram[order[1:]] == gram[order[:-1]]
        before = np.full(len(gram), -1)
        before[order[1:][again]] = order[:-1][again]
        found = []
        for t in templates:
            m, mark = len(t.grams), np.zeros(len(place), bool)
            mark[[place[g] for g in t.grams if g in place]] = True
            own, most = mark[gram], m / self.ratio + 1e-9
            for s in np.flatnonzero(own).tolist():
                width = 2 * m + 64
                while True:  # a run ends with the first place of a bigram of the template
                    fresh = before[s : s + width] < s
                    new = fresh & own[s : s + width]
                    n, c = np.cumsum(fresh), np.cumsum(new)
                    if s + width >= len(gram) or n[-1] > most or c[-1] == mark.sum():
                        break
                    width *= 2
                dice = np.where(new, 2 * c / (n + m), 0)
                e = int(dice.argmax())
                if dice[e] >= self.least:
                    found.append((float(dice[e]), s, s + e + 2, t.name))
        kept: list[tuple[float, int, int, str]] = []
        for run in sorted(found, key=lambda r: (-r[0], r[1] - r[2], r[1], r[3])):
            if not any((shared := min(run[2], k[2]) - max(run[1], k[1])) > 0 and (k[3] == run[3] or 2 * shared > max(run[2] - run[1], k[2] - k[1])) for k in kept):
                kept.append(run)
        return kept

    def scan(self, text: str) -> list[tuple[int, str, float]]:
        """(line from 1, or 0 for the whole text; license; Dice), in that order; runs inside a unit of their license are left to it."""
        whole = normal(text)
        words = whole.split()
        pairs = list(zip(words, words[1:], strict=False))
        templates = self.held(self.known.intersection(pairs) | (self.known & {(w, "") for w in words} if any("" in g for g in self.known) else set()))
        if not templates:
            return []
        lines = [line.split() for line in whole.split("\n")]
        ends = np.cumsum([0] + [len(line) for line in lines]).tolist()
        units = [(0, words, 0, len(words))] if len(lines) > 1 else []
        units += [(k, line, ends[k - 1], ends[k]) for k, line in enumerate(lines, 1)]
        hits, spans = [], []
        for k, w, a, b in units:
            if hit := self.best(w, templates):
                hits.append((k, *hit))
                spans.append((a, b, hit[0]))
        for dice, a, b, name in self.runs(pairs, templates):
            if not any(p <= a and b <= q and n == name for p, q, n in spans):
                hits.append((int(np.searchsorted(ends, a, side="right")), name, dice))
        return sorted(hits, key=lambda h: h[0])


SCHEMA = T.StructType([T.StructField("licenses", T.StringType()), T.StructField("best", T.StringType()), T.StructField("score", T.DoubleType()), T.StructField("n_hits", T.LongType()), T.StructField("hits", T.StringType())])


def scan_licenses(docs: DataFrame, keep: tuple[str, ...] = ("doc_id",), text: str = "text", templates: tuple[tuple[str, str], ...] = TEMPLATES + FULL_TEXTS, least: float = 0.8) -> DataFrame:
    """``keep`` columns plus licenses (distinct names, sorted, comma-joined), best and its score (null and 0 without a hit), n_hits, hits (``line:license:dice`` with six decimals, comma-joined).

    Null and empty texts have no hit; repeated rows stay; an empty table gives an empty one. Whole texts are read.
    """
    kept = len(keep)
    schema = T.StructType([docs.schema[k] for k in keep] + SCHEMA.fields)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = Matcher(templates, least)
        for batch in batches:
            cols: list[list] = [[] for _ in range(5)]
            for value in batch.column(kept):
                hits = own.scan(value.as_py() or "")
                top = max(hits, key=lambda h: (h[2], -h[0])) if hits else (0, None, 0.0)
                for c, v in zip(cols, (",".join(sorted({h[1] for h in hits})), top[1], top[2], len(hits), ",".join(f"{k}:{n}:{d:.6f}" for k, n, d in hits)), strict=True):
                    c.append(v)
            kinds = (pa.string(), pa.string(), pa.float64(), pa.int64(), pa.string())
            yield pa.RecordBatch.from_arrays([batch.column(k) for k in range(kept)] + [pa.array(c, t) for c, t in zip(cols, kinds, strict=True)], names=schema.names)

    return docs.select(*keep, docs[text].alias("__text")).mapInArrow(run, schema)
