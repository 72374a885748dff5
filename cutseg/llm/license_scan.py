"""License scan by patience alignment of texts with license templates.

Words that occur once in both sides are anchors; the longest run of anchors that
keeps their order is kept, and the gaps between them are aligned in the same
way.  Where a gap has no anchor, equal words at its two ends are matched.

A notice that stands more than once has no anchors, so each place of the
template's rarest words is a window of its own, aligned exactly.
"""

from __future__ import annotations

import re
from bisect import bisect_left
from collections import Counter
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame

from cutseg.llm.words import small_batches, tidy

_WORD = re.compile(r"\w+")

#: Notices and grants by SPDX identifier; the first of equal coverage wins.
TEMPLATES = [
    ("MIT", "Released under the MIT License"),
    ("Apache-2.0", "Licensed under the Apache License, Version 2.0"),
    ("GPL-3.0", "This work is licensed under the GNU General Public License, version 3"),
    ("CC-BY-NC-4.0", "Licensed under CC BY-NC 4.0"),
    ("CC-BY-4.0", "This work is licensed under a Creative Commons Attribution 4.0 International License"),
    ("MIT", "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files"),
    ("BSD-3-Clause", "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met"),
    ("MPL-2.0", "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0"),
]
#: Share of a template's words that must align.
COVERAGE = 0.8
_FOUND = "doc_id long, license string, template int, coverage double, matched int, template_words int, first_word int, last_word int, occurrences array<struct<license: string, template: int, coverage: double, first_word: int, last_word: int>>"
_PLACE = pa.struct([("license", pa.string()), ("template", pa.int32()), ("coverage", pa.float64()), ("first_word", pa.int32()), ("last_word", pa.int32())])


def longest_rising(values: list[int]) -> list[int]:
    """Indices of one longest strictly rising subsequence."""
    tops, at, before = [], [], [-1] * len(values)
    for i, v in enumerate(values):
        k = bisect_left(tops, v)
        before[i] = at[k - 1] if k else -1
        tops[k:k + 1], at[k:k + 1] = [v], [i]
    chain, i = [], at[-1] if at else -1
    while i >= 0:
        chain.append(i)
        i = before[i]
    return chain[::-1]


def _once(words: list, low: int, high: int) -> dict:
    """Words that occur once in words[low:high], with their place."""
    seen: dict = {}
    for i in range(low, high):
        seen[words[i]] = -1 if words[i] in seen else i
    return {w: i for w, i in seen.items() if i >= 0}


def align(a: list, b: list) -> list[tuple[int, int]]:
    """Matched places of two word lists, rising in both."""
    found, todo = [], [(0, len(a), 0, len(b))]
    while todo:
        a0, a1, b0, b1 = todo.pop()
        if a0 >= a1 or b0 >= b1:
            continue
        mine, theirs = _once(a, a0, a1), _once(b, b0, b1)
        shared = sorted((i, theirs[w]) for w, i in mine.items() if w in theirs)
        anchors = [shared[k] for k in longest_rising([j for _, j in shared])]
        if anchors:
            found += anchors
            edges = [(a0 - 1, b0 - 1), *anchors, (a1, b1)]
            todo += [(i + 1, k, j + 1, m) for (i, j), (k, m) in zip(edges, edges[1:])]
            continue
        while a0 < a1 and b0 < b1 and a[a0] == b[b0]:
            found.append((a0, b0))
            a0, b0 = a0 + 1, b0 + 1
        while a0 < a1 and b0 < b1 and a[a1 - 1] == b[b1 - 1]:
            a1, b1 = a1 - 1, b1 - 1
            found.append((a1, b1))
    return sorted(found)


def tightest(words: list[tuple[int, str]], template: list) -> tuple[int, int, int]:
    """Length of the longest common subsequence of placed words and a template,
    with the first and last place of its shortest run."""
    state, best = [(0, 0)] * (len(template) + 1), (0, 0, 0, 0)
    for at, w in words:
        row = [(0, 0)]
        for j, t in enumerate(template):
            new = max(row[j], state[j + 1])
            if w == t:
                n, start = state[j]
                new = max(new, (n + 1, start if n else at))
            row.append(new)
        state = row
        n, start = state[-1]
        best = max(best, (n, start - at, start, at))
    return best[0], best[2], best[3]


def densest(places: list[int], width: int) -> tuple[int, int]:
    """The first of the ranges of rising places, at most ``width`` wide, that
    hold most of them."""
    best, low = (0, 0), 0
    for high in range(len(places)):
        while places[high] - places[low] >= width:
            low += 1
        if high + 1 - low > best[1] - best[0]:
            best = low, high + 1
    return best


class Scanner:
    """Aligns texts with templates.

    Words that a template lacks are left out first.  A word can be unique then
    that was not, so more may align than in the whole text; what counts is the
    part of an alignment that stands within twice the template's length.
    """

    def __init__(self, templates=TEMPLATES, coverage: float = COVERAGE):
        self.names = [n for n, _ in templates]
        self.words = [_WORD.findall(t.lower()) for _, t in templates]
        self.known = {w for t in self.words for w in t}
        self.coverage = coverage

    def occurrences(self, placed: list[tuple[int, str]], template: list) -> list[tuple[int, int, int]]:
        """Matched words, first and last place of all disjoint runs that reach
        the coverage with at most half a template of other words in them.

        So few words may miss that one of the rarest stands in every such run."""
        m = len(template)
        need = next(n for n in range(m + 1) if n / m >= self.coverage)
        count, own = Counter(w for _, w in placed), Counter(template)
        if sum(min(n, count[w]) for w, n in own.items()) < max(1, need):
            return []
        rare, covered = set(), 0
        for w in sorted(own, key=lambda w: (count[w], w)):
            if covered > m - need:
                break
            rare.add(w)
            covered += own[w]
        slack, places, runs = max(4, m // 2), [at for at, _ in placed], set()
        windows = {(at - t - slack, at + m - t + slack) for at, w in placed if w in rare for t in range(m) if template[t] == w}
        for low, high in windows:
            part = placed[bisect_left(places, low):bisect_left(places, high)]
            if len(part) >= need:
                runs.add(tightest(part, template))
        out: list = []
        taken: list = []  # ends of taken runs in order: start, end, start, end
        for n, first, last in sorted(runs, key=lambda r: (-r[0], r[2] - r[1], r[1])):
            i = bisect_left(taken, first)
            if n >= need and i % 2 == 0 and (i == len(taken) or taken[i] > last):
                taken[i:i] = [first, last + 0.5]
                out.append((n, first, last))
        return sorted(out, key=lambda r: r[1])

    def scan(self, text: str | None) -> tuple:
        """license or None, template, coverage, matched, template words, the
        places among the text's words where the match begins and ends, and all
        occurrences of all templates that reach the coverage."""
        at, kept = [], []
        for i, w in enumerate(_WORD.findall(text.lower()) if text else ()):
            if w in self.known:
                at.append(i)
                kept.append(w)
        best, every = (None, None, 0.0, 0, 0, None, None), []
        for k, template in enumerate(self.words):
            own = set(template)
            places = [i for i, w in enumerate(kept) if w in own]
            runs = self.occurrences([(at[i], kept[i]) for i in places], template)
            every += [(self.names[k], k, n / len(template), first, last) for n, first, last in runs]
            if len(places) <= best[2] * len(template):
                continue  # it can't cover more than the best
            hits = [at[places[i]] for i, _ in align([kept[i] for i in places], template)]
            low, high = densest(hits, 2 * len(template))
            share = (high - low) / len(template)
            if share > best[2]:
                best = (self.names[k] if share >= self.coverage else None, k, share, high - low, len(template), hits[low], hits[high - 1])
            for n, first, last in runs:
                if n / len(template) > best[2]:
                    best = (self.names[k], k, n / len(template), n, len(template), first, last)
        return *best, every


def _scan(scanner: Scanner):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = [scanner.scan(t) for t in batch.column(1).to_pylist()]
            columns = list(zip(*rows)) or [()] * 8
            kinds = (pa.string(), pa.int32(), pa.float64(), *[pa.int32()] * 4, pa.list_(_PLACE))
            columns[-1] = [[dict(zip(("license", "template", "coverage", "first_word", "last_word"), o)) for o in r] for r in columns[-1]]
            yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(c, k) for c, k in zip(columns, kinds))],
                                             ["doc_id", "license", "template", "coverage", "matched", "template_words", "first_word", "last_word", "occurrences"])
    return run


def scan_licenses(docs: DataFrame, scanner: Scanner | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The template that covers most of itself in each text, and all
    occurrences that reach the least coverage; one row per row.

    ``license`` is null below the least coverage.  Null, empty and wordless
    texts, and those without any template word, have coverage 0 and null
    places.  Nothing is shuffled.
    """
    small_batches(docs.sparkSession)
    rows = docs.select(docs[id_col].cast("long").alias("doc_id"), docs[text_col].cast("string").alias("text"))
    return rows.mapInArrow(tidy(_scan(scanner or Scanner())), _FOUND)


def op8_license_patience(spark, sf_dir: str) -> DataFrame:
    return scan_licenses(spark.read.parquet(f"{sf_dir}/documents.parquet"))
