"""License scans by patience alignment.

A text's words (lower-cased, without marks at their ends) are compared with license templates. Where words of a template
that are rare among templates gather, a stretch of the text is aligned with it: words that occur once in the stretch and
once in the template are anchors; the longest increasing run of anchors is kept; the gaps between them are aligned in the
same way, after equal words at their ends are taken. The coverage is the share of the template's words that are aligned; a
stretch with enough of it is a match. Of matches that overlap, the one with more aligned words stays.

Templates are data: a dictionary, or a table of (license, template) rows, a rule list of bounded size. A text is read by words
only for templates that it can match: so many of a template's words must be in it as a match needs.

Edge cases: null and empty texts and texts without a template's words match nothing. Long texts are scanned whole: stretches
begin where a template's rarest words stand. Repeated statements are matches each. Repeated rows are scanned each; null ids
pass through. No documents give no rows, no templates no matches; templates that are null or hold no word are left out.
Columns may have any name; one called ``matches`` is replaced.
"""

from __future__ import annotations

import re
from bisect import bisect_left
from collections import Counter
from collections.abc import Callable, Iterator
from math import ceil

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from propalign.llm.bytes_np import slices
from propalign.llm.tables import kept_columns, schema_with

COVERAGE = 0.8
#: Rows of a template table that are taken to the driver, and on to every task; more are an error.
MOST_TEMPLATES = 20_000

#: Common license statements, in their published wording.
TEMPLATES = {
    "gpl-3.0": "This work is licensed under the GNU General Public License, version 3.",
    "gpl-3.0-notice": "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version.",
    "lgpl-3.0-notice": "This library is free software; you can redistribute it and/or modify it under the terms of the GNU Lesser General Public License as published by the Free Software Foundation; either version 3 of the License, or (at your option) any later version.",
    "apache-2.0": "Licensed under the Apache License, Version 2.0.",
    "apache-2.0-notice": "Licensed under the Apache License, Version 2.0 (the \"License\"); you may not use this file except in compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0 Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an \"AS IS\" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied.",
    "mit": "Released under the MIT License.",
    "mit-text": "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions:",
    "bsd-text": "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met:",
    "isc-text": "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies.",
    "mpl-2.0-notice": "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can obtain one at http://mozilla.org/MPL/2.0/.",
    "cc-by-nc-4.0": "Licensed under CC BY-NC 4.0.",
    "cc-by-4.0": "Licensed under CC BY 4.0.",
    "cc-by-sa-4.0": "Licensed under CC BY-SA 4.0.",
}

_word = re.compile(r"[^\W_](?:[\w./'-]*[^\W_])?")


def words_of(text: str) -> list[tuple[str, int, int]]:
    return [(m[0].lower(), m.start(), m.end()) for m in _word.finditer(text)]


def _rising(pairs: list[tuple[int, int]]) -> list[tuple[int, int]]:
    """The longest run of pairs (sorted by the first) whose seconds increase: piles, each topped by its smallest second."""
    tops: list[int] = []
    at: list[int] = []
    back = [-1] * len(pairs)
    for i, (_, b) in enumerate(pairs):
        k = bisect_left(tops, b)
        back[i] = at[k - 1] if k else -1
        tops[k : k + 1] = [b]
        at[k : k + 1] = [i]
    out, i = [], at[-1] if at else -1
    while i >= 0:
        out.append(pairs[i])
        i = back[i]
    return out[::-1]


def patience(a: list[str], b: list[str]) -> list[tuple[int, int]]:
    """Aligned places (i, j) with a[i] == b[j], both rising."""
    out: list[tuple[int, int]] = []
    todo = [(0, len(a), 0, len(b))]
    while todo:
        a0, a1, b0, b1 = todo.pop()
        while a0 < a1 and b0 < b1 and a[a0] == b[b0]:
            out.append((a0, b0))
            a0, b0 = a0 + 1, b0 + 1
        while a0 < a1 and b0 < b1 and a[a1 - 1] == b[b1 - 1]:
            a1, b1 = a1 - 1, b1 - 1
            out.append((a1, b1))
        if a0 >= a1 or b0 >= b1:
            continue
        in_a, in_b = Counter(a[a0:a1]), Counter(b[b0:b1])
        once = {w: j for j, w in enumerate(b[b0:b1], b0) if in_b[w] == 1 and in_a.get(w) == 1}
        anchors = _rising([(i, once[w]) for i, w in enumerate(a[a0:a1], a0) if w in once])
        out += anchors
        for (i, j), (k, m) in zip([(a0 - 1, b0 - 1), *anchors], [*anchors, (a1, b1)], strict=True):
            if anchors and k > i + 1 and m > j + 1:
                todo.append((i + 1, k, j + 1, m))
    return sorted(out)


class Scanner:
    def __init__(self, templates: dict[str, str] = TEMPLATES, coverage: float = COVERAGE):
        self.words = {n: ws for n, t in templates.items() if t and (ws := [w for w, _, _ in words_of(t)])}
        self.coverage = coverage
        #: Of each template, the words that a match needs at least, and how often each word stands in it.
        self.need = {n: ceil(coverage * len(ws)) for n, ws in self.words.items()}
        self.bag = {n: Counter(ws) for n, ws in self.words.items()}
        known = Counter(w for ws in self.words.values() for w in set(ws))
        self.lead: dict[str, list[str]] = {}
        self.cues: dict[str, set[str]] = {}
        for n, ws in self.words.items():
            # A match misses at most a share of the template's words; so of this many rarest ones, one is there.
            spare = len(ws) - self.need[n] + 1
            rare = sorted(set(ws), key=lambda w: (known[w], -len(w), w))
            need, took = [], 0
            for w in rare:
                need.append(w)
                took += ws.count(w)
                if took >= spare:
                    break
            self.cues[n] = set(need)
            for w in need:
                self.lead.setdefault(w, []).append(n)

    def possible(self, has: Callable[[str], bool]) -> set[str]:
        """Templates of whose words enough are there, with one of the cues. has: whether a word is in the text."""
        out, known = set(), {}
        there = lambda w: known[w] if w in known else known.setdefault(w, has(w))
        for n, bag in self.bag.items():
            if any(map(there, self.cues[n])) and sum(k for w, k in bag.items() if there(w)) >= self.need[n]:
                out.add(n)
        return out

    def scan(self, text: str) -> list[tuple[str, int, int, int, float]]:
        """(license, start, end, aligned words, coverage), by start; code points, ends exclusive."""
        low = text.lower()
        if not self.possible(low.__contains__):
            return []
        found = words_of(text)
        text_words = [w for w, _, _ in found]
        open_ = self.possible(set(text_words).__contains__)
        places: dict[str, list[int]] = {}
        for i, w in enumerate(text_words):
            for n in self.lead.get(w, ()):
                if n in open_:
                    places.setdefault(n, []).append(i)
        hits = []
        for n, at in places.items():
            template = self.words[n]
            size = len(template)
            done = -1
            for i in at:
                if i <= done:
                    continue
                lo, hi = max(done + 1, i - size), min(len(text_words), i + size + size // 4 + 1)
                here = Counter(text_words[lo:hi])
                if sum(min(k, here[w]) for w, k in self.bag[n].items()) < self.need[n]:
                    continue
                pairs = patience(text_words[lo:hi], template)
                # Only what lies near the cue counts, in a span not much longer than the template.
                pairs = [(lo + x, y) for x, y in pairs]
                pairs = self._dense(pairs, size)
                if len(pairs) >= self.need[n]:
                    hits.append((n, pairs[0][0], pairs[-1][0], len(pairs), len(pairs) / size))
                    done = pairs[-1][0]
        hits.sort(key=lambda h: (-h[3], -h[4], h[1], h[0]))
        kept: list[tuple] = []
        for h in hits:
            if all(h[2] < k[1] or h[1] > k[2] for k in kept):
                kept.append(h)
        return sorted((n, found[a][1], found[b][2], k, c) for n, a, b, k, c in kept)

    @staticmethod
    def _dense(pairs: list[tuple[int, int]], size: int) -> list[tuple[int, int]]:
        """The most pairs within a stretch of one and a quarter times the template."""
        best, left = (0, 0), 0
        for right in range(len(pairs)):
            while pairs[right][0] - pairs[left][0] >= size + size // 4 + 1:
                left += 1
            best = max(best, (right - left + 1, -left))
        return pairs[-best[1] : -best[1] + best[0]] if best[0] else []


def license_scan(docs: DataFrame, text: str = "text", keep: tuple[str, ...] = ("doc_id",), templates: dict[str, str] | DataFrame = TEMPLATES, coverage: float = COVERAGE) -> DataFrame:
    """keep and matches: array of (license, start, stop, words, coverage), by start."""
    if isinstance(templates, DataFrame):
        rows = templates.where("license is not null and template is not null").select("license", "template").limit(MOST_TEMPLATES + 1).collect()
        if len(rows) > MOST_TEMPLATES:
            raise ValueError(f"more than {MOST_TEMPLATES} templates")
        templates = {r["license"]: r["template"] for r in rows}
    rows = docs.select(F.struct(*kept_columns(docs, keep, ["matches"])).alias("row"), F.col(f"`{text}`").alias("text"))
    hit = pa.struct([("license", pa.string()), ("start", pa.int64()), ("stop", pa.int64()), ("words", pa.int64()), ("coverage", pa.float64())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scanner = Scanner(templates, coverage)
        for b in (s for whole in batches for s in slices(whole, 1)):
            out = [[dict(zip(("license", "start", "stop", "words", "coverage"), h, strict=True)) for h in (scanner.scan(x) if x else [])] for x in b.column(1).to_pylist()]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(out, pa.list_(hit))], names=["row", "matches"])

    found = rows.mapInArrow(run, schema_with([rows.schema["row"]], "matches array<struct<license: string, start: bigint, stop: bigint, words: bigint, coverage: double>>"))
    return found.select("row.*", "matches")
