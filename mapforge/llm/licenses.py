"""Operator 1: license scans by winnowed fingerprints and banded alignment.

Templates are turned into winnowed fingerprints (least hash of every window of word runs) held in an
inverted index fingerprint -> (template, position); every run of a template counts where the coverage does
not ensure a common run that fills a window. The index grows with the templates, which are a
parameter of bounded size, never with the corpus; it travels to the tasks as a broadcast variable.
A document's word runs are looked up in the index; a hit proposes a template and a diagonal. For each
diagonal with a hit outside the template's matches so far, a banded alignment (longest common word sequence within ``BAND`` words of the
diagonal) gives the matched words and the span in the text, in code points with exclusive end. Coverage is the
share of matched words among the template's and the words that the text puts between them, so words left out
and words put in both cost. Versions and the words that tell license variants apart must agree: where
one is missing or one too many, there is no match. Overlapping matches keep the one with most matched words.

Null and empty texts give no rows; every match in whole texts is reported, repeated ones and repeated rows included. An
empty table gives no rows.
"""

from __future__ import annotations

import math
import pickle
import re
import zlib
from bisect import bisect_left, bisect_right
from collections import defaultdict
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from mapforge.llm.common import table

RUN = 3
WINDOW = 2
BAND = 8
MIN_COVERAGE = 0.8
SLICE_ROWS = 512
_WORD = re.compile(r"[^\W_]+")
_MORE = re.compile(r"\.([0-9]+)")

#: Notices by which licenses are declared, and the wording of short licenses.
TEMPLATES = {
    "Apache-2.0": ["Licensed under the Apache License, Version 2.0", "you may not use this file except in compliance with the License. You may obtain a copy of the License at", "distributed under the License is distributed on an AS IS BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied"],
    "MIT": ["Released under the MIT License", "Licensed under the MIT License", "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files, to deal in the Software without restriction", "The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software"],
    "ISC": ["Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies"],
    "GPL-3.0": ["This work is licensed under the GNU General Public License, version 3", "GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version", "either version 3 of the License, or (at your option) any later version"],
    "GPL-2.0": ["This work is licensed under the GNU General Public License, version 2", "GNU General Public License as published by the Free Software Foundation, either version 2 of the License, or (at your option) any later version", "either version 2 of the License, or (at your option) any later version"],
    "LGPL-2.1": ["This work is licensed under the GNU Lesser General Public License, version 2.1", "GNU Lesser General Public License as published by the Free Software Foundation, either version 2.1 of the License, or (at your option) any later version"],
    "LGPL-3.0": ["This work is licensed under the GNU Lesser General Public License, version 3", "GNU Lesser General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version"],
    "AGPL-3.0": ["This work is licensed under the GNU Affero General Public License, version 3", "GNU Affero General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version"],
    "CC-BY-4.0": ["Licensed under CC BY 4.0", "This work is licensed under a Creative Commons Attribution 4.0 International License"],
    "CC-BY-SA-4.0": ["Licensed under CC BY-SA 4.0", "This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License"],
    "CC-BY-ND-4.0": ["Licensed under CC BY-ND 4.0", "This work is licensed under a Creative Commons Attribution-NoDerivatives 4.0 International License"],
    "CC-BY-NC-4.0": ["Licensed under CC BY-NC 4.0", "This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International License"],
    "CC-BY-NC-SA-4.0": ["Licensed under CC BY-NC-SA 4.0", "This work is licensed under a Creative Commons Attribution-NonCommercial-ShareAlike 4.0 International License"],
    "CC-BY-NC-ND-4.0": ["Licensed under CC BY-NC-ND 4.0", "This work is licensed under a Creative Commons Attribution-NonCommercial-NoDerivatives 4.0 International License"],
    "BSD": ["Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met"],
    "MPL-2.0": ["This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0"],
    "Unlicense": ["This is free and unencumbered software released into the public domain"],
}
#: Words that tell variants of a license apart.
VARIANTS = frozenset("nc nd sa noncommercial noderivatives noderivs sharealike lesser library affero lgpl agpl".split())


def _hash(words: tuple[str, ...]) -> int:
    return zlib.crc32(" ".join(words).encode())


def winnow(hashes: list[int], window: int) -> list[tuple[int, int]]:
    """(hash, position) of the least hash of every window, the rightmost of equals; all of a short list's minima."""
    picked = set()
    for a in range(max(1, len(hashes) - window + 1)):
        part = hashes[a : a + window]
        if part:
            low = min(part)
            picked.add((low, a + max(i for i, h in enumerate(part) if h == low)))
    return sorted(picked, key=lambda x: x[1])


def banded_match(a: list[str], b: list[str], band: int) -> list[tuple[int, int]]:
    """Pairs of a longest common sequence of ``a`` and ``b`` whose positions differ by at most ``band``.

    Only the band is kept: column ``c`` of row ``i`` stands for the first ``i + c - band`` words of ``b``.
    """
    n, m, width = len(a), len(b), 2 * band + 1
    best = np.zeros((n + 1, width + 1), np.int32)  # one column more, always 0, for what lies outside
    inside = lambda i, j: 0 <= j - i + band < width
    at = lambda i, j: int(best[i, j - i + band]) if inside(i, j) else 0
    for i in range(1, n + 1):
        for j in range(max(1, i - band), min(m, i + band) + 1):
            best[i, j - i + band] = at(i - 1, j - 1) + 1 if a[i - 1] == b[j - 1] else max(at(i - 1, j), at(i, j - 1))
    i, pairs = n, []
    j = max(range(max(0, n - band), min(m, n + band) + 1), key=lambda k: at(n, k), default=0)
    while i and j and at(i, j):
        if a[i - 1] == b[j - 1] and at(i, j) == at(i - 1, j - 1) + 1:
            pairs.append((i - 1, j - 1))
            i, j = i - 1, j - 1
        elif inside(i - 1, j) and at(i - 1, j) == at(i, j):
            i -= 1
        else:
            j -= 1
    return pairs[::-1]


def _tells(word: str) -> bool:
    return word in VARIANTS or word.isdigit()


def agrees(template: list[str], found: list[str], pairs: list[tuple[int, int]]) -> bool:
    """Whether versions and variant words of the template and of the matched stretch of the text are the same ones."""
    ours, theirs = {i for i, _ in pairs}, {j for _, j in pairs}
    missing = any(_tells(w) for i, w in enumerate(template) if i not in ours)
    return not missing and not any(_tells(found[j]) for j in range(pairs[0][1], pairs[-1][1] + 1) if j not in theirs)


@dataclass
class Index:
    """Templates as words, their fingerprints, and all words that occur in a fingerprinted run."""

    templates: list[tuple[str, list[str]]]
    postings: dict[int, list[tuple[int, int]]]
    words: dict[str, int]


def build_index(templates: dict[str, list[str]] | None = None, run: int = RUN, window: int = WINDOW) -> Index:
    listed = [(name, _WORD.findall(t.lower())) for name, texts in (templates or TEMPLATES).items() for t in texts]
    postings: dict[int, list[tuple[int, int]]] = defaultdict(list)
    words: dict[str, int] = {}
    for k, (_, ws) in enumerate(listed):
        matched = math.ceil(MIN_COVERAGE * len(ws))
        sure = math.ceil(matched / (len(ws) - matched + 1))  # longest run that is left at least when words are taken out
        for h, at in winnow([_hash(tuple(ws[i : i + run])) for i in range(len(ws) - run + 1)], window if sure >= run + window - 1 else 1):
            postings[h].append((k, at))
            for w in ws[at : at + run]:
                words.setdefault(w, len(words) + 1)
    return Index(listed, dict(postings), words)


class _Covered:
    """Stretches of words, with the furthest end among those that begin no later than a place."""

    def __init__(self) -> None:
        self.begins: list[int] = []
        self.furthest: list[int] = []

    def add(self, a: int, b: int) -> None:
        at = bisect_right(self.begins, a)
        self.begins.insert(at, a)
        self.furthest.insert(at, max(b, self.furthest[at - 1] if at else b))
        for k in range(at + 1, len(self.furthest)):  # hardly ever more than a few: matches come in order of place
            self.furthest[k] = max(self.furthest[k], b)

    def holds(self, a: int, b: int) -> bool:
        at = bisect_right(self.begins, a)
        return at > 0 and b <= self.furthest[at - 1]


def _goes_on(text: str, last: str, end: int) -> bool:
    """Whether a version at the end of a match has another number behind it, as 2 in 2.1; 2.0 is 2."""
    more = _MORE.match(text, end) if last.isdigit() else None
    return more is not None and int(more[1]) != 0


def find(text: str, index: Index, min_coverage: float = MIN_COVERAGE, run: int = RUN, band: int = BAND) -> list[tuple[str, int, int, float, int]]:
    """(license, start, end, coverage, matched words) of each match, in order of place."""
    low = text.lower()
    if len(low) != len(text):  # a letter whose lower case is longer: spans must stay those of the text
        low = "".join(c if len(c.lower()) != 1 else c.lower() for c in text)
    spans, found = [m.span() for m in _WORD.finditer(low)], []
    words = [low[a:b] for a, b in spans]
    known = np.fromiter((w in index.words for w in words), bool, len(words))
    if len(words) < run:
        return []
    whole = known[: len(words) - run + 1].copy()
    for s in range(1, run):
        whole &= known[s : len(words) - run + 1 + s]
    proposed: dict[int, dict[int, list[int]]] = defaultdict(lambda: defaultdict(list))
    for i in np.flatnonzero(whole).tolist():
        for k, at in index.postings.get(_hash(tuple(words[i : i + run])), ()):
            proposed[k][i - at].append(i)
    for k, diagonals in proposed.items():
        name, template = index.templates[k]
        done = _Covered()
        for d in sorted(diagonals):
            if all(done.holds(i, i + run - 1) for i in diagonals[d]):
                continue
            base = max(0, d - band // 2)
            near = words[base : d + len(template) + band]
            pairs = banded_match(template, near, band + abs(d - base))
            if not pairs or not agrees(template, near, pairs):
                continue
            a, b = base + pairs[0][1], base + pairs[-1][1]
            coverage = len(pairs) / (len(template) + (b - a + 1 - len(pairs)))
            if coverage >= min_coverage and not _goes_on(low, words[b], spans[b][1]):
                done.add(a, b)
                found.append((name, spans[a][0], spans[b][1], coverage, len(pairs)))
    kept: list[tuple[int, int, tuple[str, int, int, float, int]]] = []  # disjoint, by place
    for f in sorted(found, key=lambda f: (-f[4], -f[3], f[1], f[0])):
        at = bisect_left(kept, (f[1],))
        if (at == len(kept) or f[2] <= kept[at][0]) and (at == 0 or kept[at - 1][1] <= f[1]):
            kept.insert(at, (f[1], f[2], f))
    return [f for _, _, f in kept]


def scan(docs: DataFrame, templates: dict[str, list[str]] | None = None, min_coverage: float = MIN_COVERAGE) -> DataFrame:
    """One row per match: doc_id, license, start, end, coverage, matched_words."""
    index = build_index(templates)
    state = docs.sparkSession.sparkContext.broadcast(pickle.dumps(index))
    names = ["doc_id", "license", "start", "end", "coverage", "matched_words"]
    kinds = [pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.float64(), pa.int64()]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = pickle.loads(state.value)
        for whole in batches:
            for i in range(0, whole.num_rows, SLICE_ROWS):
                part = whole.slice(i, SLICE_ROWS)
                rows = [(k, *f) for k, t in zip(part.column(0).to_pylist(), part.column(1).to_pylist()) if t for f in find(t, own, min_coverage)]
                if rows:
                    yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), kinds)], names=names)

    return docs.selectExpr("cast(doc_id as long) doc_id", "text").mapInArrow(run, "doc_id long, license string, start long, `end` long, coverage double, matched_words long")


def op1_licenses(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan(table(spark, sf_dir, "documents", "doc_id", "text"))
