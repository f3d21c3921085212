"""License scans by patience alignment.

A text and a license template are compared as word sequences. Words that occur exactly once in both
are anchors; the longest run of anchors that keeps the order in both (a longest increasing
subsequence) is fixed, and the gaps between its members are aligned in the same way, down to common
words at the ends of a gap. Coverage is the share of the template's words that found a partner.

Templates are short against documents, so a text is aligned around words of the template that any
match of the wanted coverage must hold one of: with n words and at most m misses allowed, each set
of m + 1 of its words is such a set; the rarer-looking words are chosen. Texts without any of them
cannot reach the coverage and are not aligned. Anchors are unique in such a window, as words of a
license are rarely unique in a long text; where no window reaches the coverage, the whole stretch
that holds starting words is aligned at once.
"""

from __future__ import annotations

import re
from bisect import bisect_left
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from proxigraph.runtime import map_arrow

LEAST_COVERAGE = 0.8

# Short notices and standard header texts of well-known public licenses.
TEMPLATES = {
    "MIT": (
        "Released under the MIT License",
        "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated "
        "documentation files (the \"Software\"), to deal in the Software without restriction, including without limitation "
        "the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to "
        "permit persons to whom the Software is furnished to do so, subject to the following conditions: The above copyright "
        "notice and this permission notice shall be included in all copies or substantial portions of the Software.",
    ),
    "Apache-2.0": (
        "Licensed under the Apache License, Version 2.0",
        "Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on "
        "an \"AS IS\" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. See the License for the "
        "specific language governing permissions and limitations under the License.",
    ),
    "GPL-3.0": (
        "This work is licensed under the GNU General Public License, version 3",
        "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public "
        "License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version.",
    ),
    "CC-BY-4.0": ("Licensed under CC BY 4.0", "This work is licensed under a Creative Commons Attribution 4.0 International License"),
    "CC-BY-SA-4.0": ("Licensed under CC BY-SA 4.0", "This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License"),
    "CC-BY-NC-4.0": ("Licensed under CC BY-NC 4.0", "This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International License"),
    "BSD-3-Clause": (
        "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the "
        "following conditions are met: Redistributions of source code must retain the above copyright notice, this list of "
        "conditions and the following disclaimer. Redistributions in binary form must reproduce the above copyright notice, "
        "this list of conditions and the following disclaimer in the documentation and/or other materials provided with the "
        "distribution. Neither the name of the copyright holder nor the names of its contributors may be used to endorse or "
        "promote products derived from this software without specific prior written permission.",
    ),
    "ISC": (
        "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby "
        "granted, provided that the above copyright notice and this permission notice appear in all copies.",
    ),
    "MPL-2.0": ("This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0",),
}
# Words too common in English to start an alignment from, if others will do.
_COMMON = frozenset("a above all an and any are as be by can do either for free from in is it its list may must name no of on or other see shall so such that the their this to under use used v which with without work you".split())

_WORD = re.compile(r"[a-z0-9]+(?:[.\-][a-z0-9]+)*")


def words(text: str) -> list[str]:
    return _WORD.findall(text.lower())


def _increasing(seq: list[int]) -> list[int]:
    """Indices of a longest increasing subsequence of distinct numbers."""
    tops: list[int] = []
    where: list[int] = []
    back = [-1] * len(seq)
    for i, x in enumerate(seq):
        pile = bisect_left(tops, x)
        back[i] = where[pile - 1] if pile else -1
        if pile == len(tops):
            tops.append(x)
            where.append(i)
        else:
            tops[pile], where[pile] = x, i
    out = []
    i = where[-1] if where else -1
    while i >= 0:
        out.append(i)
        i = back[i]
    return out[::-1]


def align(a: list[str], b: list[str]) -> list[tuple[int, int]]:
    """Index pairs (i, j) with a[i] == b[j], increasing in both, by patience alignment."""
    pairs: list[tuple[int, int]] = []
    todo = [(0, len(a), 0, len(b))]
    while todo:
        i, m, j, n = todo.pop()
        while i < m and j < n and a[i] == b[j]:
            pairs.append((i, j))
            i, j = i + 1, j + 1
        while i < m and j < n and a[m - 1] == b[n - 1]:
            m, n = m - 1, n - 1
            pairs.append((m, n))
        if i == m or j == n:
            continue
        in_a, in_b = Counter(a[i:m]), Counter(b[j:n])
        at = {w: k for k, w in enumerate(b[j:n], j)}
        anchors = [(k, at[a[k]]) for k in range(i, m) if in_a[a[k]] == 1 and in_b[a[k]] == 1]
        if not anchors:
            continue
        chain = [anchors[k] for k in _increasing([y for _, y in anchors])]
        pairs += chain
        for (i0, j0), (i1, j1) in zip([(i - 1, j - 1), *chain], [*chain, (m, n)], strict=True):
            if i1 - i0 > 1 and j1 - j0 > 1:
                todo.append((i0 + 1, i1, j0 + 1, j1))
    return sorted(pairs)


@dataclass(frozen=True)
class Template:
    license: str
    words: tuple[str, ...]
    starts: dict[str, tuple[int, ...]]  # places of the words to start from

    @classmethod
    def of(cls, name: str, text: str, coverage: float) -> Template:
        w = words(text)
        needed = len(w) - int(np.ceil(coverage * len(w) - 1e-9)) + 1
        order = sorted(range(len(w)), key=lambda k: (w[k] in _COMMON, -len(w[k]), w[k], k))
        starts: dict[str, tuple[int, ...]] = {}
        for k in order[:needed]:
            starts[w[k]] = (*starts.get(w[k], ()), k)
        return cls(name, tuple(w), starts)


def compiled(coverage: float = LEAST_COVERAGE, templates: dict[str, tuple[str, ...]] | None = None) -> list[Template]:
    return [Template.of(k, t, coverage) for k, texts in (templates or TEMPLATES).items() for t in texts]


def _places(text: list[str], places: dict[str, list[int]], t: Template, coverage: float) -> list[tuple[int, int, int]]:
    """(matched words, first word, end word) of the alignments of t that reach the coverage: one around
    each starting word, in a window that leaves room for insertions of a quarter of t on both sides, and,
    if none of these does, one over the whole stretch from the first to the last of them, which any
    insertion between the parts of t leaves in reach."""
    n, least = len(t.words), coverage * len(t.words) - 1e-9
    slack = max(2, n // 4)
    begins = sorted({p - k for w, ks in t.starts.items() for p in places.get(w, ()) for k in ks})
    found: set[tuple[int, int, int]] = set()
    upto = 0  # before this word t is found completely
    for begin in begins:
        if begin < upto:
            continue
        lo = max(0, begin - slack)
        pairs = align(text[lo: begin + n + slack], list(t.words))
        if len(pairs) >= least:
            found.add((len(pairs), lo + pairs[0][0], lo + pairs[-1][0] + 1))
            if len(pairs) == n:
                upto = lo + pairs[-1][0] + 1
    if not found and begins:
        lo = max(0, begins[0] - slack)
        stretch = text[lo: begins[-1] + n + slack]
        have, need = Counter(stretch), Counter(t.words)
        if sum(min(have[w], m) for w, m in need.items()) >= least:
            pairs = align(stretch, list(t.words))
            if len(pairs) >= least:
                found.add((len(pairs), lo + pairs[0][0], lo + pairs[-1][0] + 1))
    return sorted(found)


def scan_text(text: str | None, found_by: re.Pattern, templates: list[Template], coverage: float) -> list[tuple[str, float, int, int, int]]:
    """(license, coverage, matched words, first word, end word) of each place of a license in the whole
    text; of overlapping places the one with the higher coverage (then more words) stays."""
    low = (text or "").lower()
    if not found_by.search(low):
        return []
    text_words = _WORD.findall(low)
    places: dict[str, list[int]] = {}
    wanted = {w for t in templates for w in t.starts}
    for p, w in enumerate(text_words):
        if w in wanted:
            places.setdefault(w, []).append(p)
    every = [(t.license, m / len(t.words), m, first, end) for t in templates for m, first, end in _places(text_words, places, t, coverage)]
    kept: list[tuple[str, float, int, int, int]] = []
    begun: list[int] = []  # first words of the kept places, in order, and their end words
    ended: list[int] = []
    for x in sorted(every, key=lambda x: (-x[1], -x[2], x[4] - x[3], x[3], x[0])):
        at = bisect_left(begun, x[3])
        if (at == 0 or ended[at - 1] <= x[3]) and (at == len(begun) or begun[at] >= x[4]):
            kept.append(x)
            begun.insert(at, x[3])
            ended.insert(at, x[4])
    return sorted(kept, key=lambda x: (x[3], x[0]))


def scan(docs: DataFrame, coverage: float = LEAST_COVERAGE, templates: dict[str, tuple[str, ...]] | None = None) -> DataFrame:
    """doc_id, license, coverage, matched_words, first_word, end_word of every place of a license that
    docs' whole texts hold with that coverage; places do not overlap. A document without any gets one
    row with a null license and coverage 0. Null and empty texts hold none; repeated rows give repeated
    results. Of a license that is torn apart by insertions of more than a quarter of its words, only
    one place in a text is found, and none if the words between repeat its anchors too often."""
    known = compiled(coverage, templates)
    pattern = "|".join(re.escape(w) for w in sorted({w for t in known for w in t.starts}))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        found_by = re.compile(pattern)
        for batch in batches:
            rows = []
            for key, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                rows += [(key, *x) for x in scan_text(text, found_by, known, coverage)] or [(key, None, 0.0, 0, None, None)]
            types = (pa.int64(), pa.string(), pa.float64(), pa.int64(), pa.int64(), pa.int64())
            names = ["doc_id", "license", "coverage", "matched_words", "first_word", "end_word"]
            columns = list(zip(*rows, strict=True)) or [[]] * 6
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, types, strict=True)], names)

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    return map_arrow(rows, run, "doc_id long, license string, coverage double, matched_words long, first_word long, end_word long")
