"""License scans: patience alignment of license templates within whole texts.

Words are runs of digits, letters and non-ASCII characters, A-Z lower-cased.
*Regions.* For each template the words of a text that it holds are located.
A region is a maximal group of windows, three template lengths long and one
apart, that hold distinct template words worth ``least`` of the template; no occurrence
of up to two template lengths escapes that test.
*Alignment.* In a region, words that occur once in the region and once in the
template are anchors; the longest increasing run of anchors is kept, and the
gaps between them are aligned the same way. A gap without such words is
closed from both its ends: equal words at its start and at its end are matched.
*Coverage* is the share of template words matched. After an occurrence is
found, the region left of it and right of it are searched too, so repeats count.

The result has one row for each occurrence that covers at least ``least`` of
the template: (doc_id, license, start, end, matched, words, coverage); start
and end are byte offsets in the text's UTF-8 form.

Edge cases: null, empty and wordless texts have no rows; of occurrences of
several templates that overlap, all are reported; repeated rows are scanned
each; templates without words match nothing; an empty table gives no rows;
other columns are ignored.
"""

from __future__ import annotations

from bisect import bisect_left
from collections import Counter
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from winjoin.llm import bytetext as B
from winjoin.llm.frames import text_of

#: Public license notices, by SPDX-like name.
TEMPLATES = {
    "Apache-2.0": "Licensed under the Apache License, Version 2.0.",
    "Apache-2.0-header": (
        'Licensed under the Apache License, Version 2.0 (the "License"); you may not use this file except in compliance with the License. '
        "You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0 Unless required by applicable law or agreed to in writing, "
        'software distributed under the License is distributed on an "AS IS" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. '
        "See the License for the specific language governing permissions and limitations under the License."
    ),
    "MIT": "Released under the MIT License.",
    "MIT-text": (
        "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the Software), "
        "to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, "
        "and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions: "
        "The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software."
    ),
    "GPL-3.0": "This work is licensed under the GNU General Public License, version 3.",
    "GPL-3.0-header": (
        "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by "
        "the Free Software Foundation, either version 3 of the License, or (at your option) any later version."
    ),
    "CC-BY-NC-4.0": "Licensed under CC BY-NC 4.0.",
    "CC-BY-4.0": "This work is licensed under a Creative Commons Attribution 4.0 International License.",
    "BSD-text": (
        "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: "
        "Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer."
    ),
    "MPL-2.0": "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0.",
}


def _increasing(values: list[int]) -> list[int]:
    """Places of a longest strictly increasing subsequence."""
    tails: list[int] = []
    ends: list[int] = []
    before = [-1] * len(values)
    for k, v in enumerate(values):
        at = bisect_left(tails, v)
        before[k] = ends[at - 1] if at else -1
        tails[at : at + 1] = [v]
        ends[at : at + 1] = [k]
    out, k = [], ends[-1] if ends else -1
    while k >= 0:
        out.append(k)
        k = before[k]
    return out[::-1]


def align(text: list[int], template: list[int]) -> list[tuple[int, int]]:
    """Matched (text place, template place), increasing in both; negative numbers in ``text`` match nothing."""
    out: list[tuple[int, int]] = []
    work = [(0, len(text), 0, len(template))]
    while work:
        a, b, c, d = work.pop()
        if a >= b or c >= d:
            continue
        once_text = {w: a + k for k, w in _once(text[a:b])}
        once_template = {w: c + k for k, w in _once(template[c:d])}
        anchors = sorted((once_text[w], once_template[w]) for w in once_text.keys() & once_template.keys())
        anchors = [anchors[k] for k in _increasing([q for _, q in anchors])]
        if not anchors:
            while a < b and c < d and text[a] == template[c]:
                out.append((a, c))
                a, c = a + 1, c + 1
            while a < b and c < d and text[b - 1] == template[d - 1]:
                b, d = b - 1, d - 1
                out.append((b, d))
            continue
        out += anchors
        edges = [(a - 1, c - 1), *anchors, (b, d)]
        work += [(p + 1, r, q + 1, s) for (p, q), (r, s) in zip(edges, edges[1:])]
    return sorted(out)


def _once(words: list[int]) -> list[tuple[int, int]]:
    n = Counter(words)
    return [(k, w) for k, w in enumerate(words) if w >= 0 and n[w] == 1]


class Scanner:
    def __init__(self, templates: dict[str, str], least: float):
        self.least = least
        names = [n for n in templates]
        raw, offs = B.flat(pa.array([templates[n] for n in names]))
        raw = B.LOWER[raw]
        starts, ends, first = B.spans(raw, offs, B.ALNUM)
        hashes = B.run_hashes(raw, starts, ends)
        self.vocabulary = np.unique(hashes)
        ids = np.searchsorted(self.vocabulary, hashes)
        self.templates = [(n, ids[first[k] : first[k + 1]].tolist()) for k, n in enumerate(names) if first[k + 1] > first[k]]
        #: Per template: worth of a distinct word, its number of places in the template.
        self.worth = []
        for _, t in self.templates:
            w = np.zeros(len(self.vocabulary) + 1, np.int64)
            np.add.at(w, t, 1)
            self.worth.append(w)

    def words(self, column: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """Word numbers (-1: in no template) of all rows, their byte spans, each row's first word and byte."""
        raw, offs = B.flat(column)
        raw = B.LOWER[raw]
        starts, ends, first = B.spans(raw, offs, B.ALNUM)
        hashes = B.run_hashes(raw, starts, ends)
        at = np.minimum(np.searchsorted(self.vocabulary, hashes), len(self.vocabulary) - 1)
        return np.where(self.vocabulary[at] == hashes, at, -1), starts, ends, first, offs

    def regions(self, words: np.ndarray, k: int) -> list[tuple[int, int]]:
        """Word ranges that may hold an occurrence of template k."""
        size, worth = len(self.templates[k][1]), self.worth[k]
        need = self.least * size - 1e-9
        places = np.flatnonzero(worth[words] > 0)
        if not len(places) or worth[np.unique(words[places])].sum() < need:
            return []
        # a window starts at each multiple of the template's size; a place lies in three of them
        home = places // size
        window = np.concatenate([home, home - 1, home - 2])
        pair = np.unique(np.stack([window, np.tile(words[places], 3)]), axis=1)
        total = np.bincount(pair[0] + 2, weights=worth[pair[1]])
        good = np.flatnonzero(total >= need) - 2
        out: list[tuple[int, int]] = []
        for w in good.tolist():
            a, b = max(0, w * size), min(len(words), (w + 3) * size)
            if out and a <= out[-1][1]:
                out[-1] = (out[-1][0], b)
            else:
                out.append((a, b))
        return out

    def occurrences(self, words: np.ndarray) -> Iterator[tuple[int, int, int, int]]:
        """(template, first word, last word, matched words) of one text."""
        for k, (_, template) in enumerate(self.templates):
            worth = self.worth[k]
            own = np.where(worth[words] > 0, words, -1)
            work = self.regions(own, k)
            while work:
                a, b = work.pop()
                size = len(template)
                found = self._densest(align(own[a:b].tolist(), template), size)
                if len(found) < self.least * size - 1e-9 and b - a > 3 * size:
                    # words that repeat in a long region hide its anchors: search it by halves that overlap
                    half = (a + b) // 2
                    work += [r for r in ((a, min(b, half + size)), (max(a, half - size), b)) if r[1] - r[0] < b - a]
                    continue
                if len(found) >= self.least * size - 1e-9:
                    lo, hi = a + found[0][0], a + found[-1][0]
                    yield k, lo, hi, len(found)
                    work += [(p, q) for p, q in ((a, lo), (hi + 1, b)) if q - p >= self.least * size and self.regions(own[p:q], k)]

    def _densest(self, pairs: list[tuple[int, int]], size: int) -> list[tuple[int, int]]:
        """The most matched words within two template lengths of text."""
        best, lo = (0, 0), 0
        for hi in range(len(pairs)):
            while pairs[hi][0] - pairs[lo][0] >= 2 * size:
                lo += 1
            if hi + 1 - lo > best[1] - best[0]:
                best = (lo, hi + 1)
        return pairs[best[0] : best[1]]


def license_scan(docs: DataFrame, templates: dict[str, str] | None = None, id_col: str = "doc_id", text_col: str = "text", least: float = 0.8) -> DataFrame:
    """Rows (doc_id, license, start, end, matched, words, coverage), one for each occurrence."""
    if not 0 < least <= 1:
        raise ValueError("least is a share above 0")
    src = text_of(docs, id_col, text_col)
    shipped = docs.sparkSession.sparkContext.broadcast((templates if templates is not None else TEMPLATES, least))
    names = ["doc_id", "license", "start", "end", "matched", "words", "coverage"]
    types = [pa.string(), pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.float64()]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scanner = Scanner(*shipped.value)
        for batch in batches:
            for p in B.pieces(batch, "text") if scanner.templates else ():
                words, starts, ends, first, offs = scanner.words(p.column(1))
                rows, out = [], []
                for r in range(p.num_rows):
                    own = words[first[r] : first[r + 1]]
                    if len(own) and (own >= 0).any():
                        seen = {(k, lo, hi): n for k, lo, hi, n in scanner.occurrences(own)}
                        for (k, lo, hi), n in sorted(seen.items()):
                            name, template = scanner.templates[k]
                            rows.append(r)
                            out.append((name, int(starts[first[r] + lo] - offs[r]), int(ends[first[r] + hi] - offs[r]), n, len(template), n / len(template)))
                columns = [pa.array([o[j] for o in out], types[j]) for j in range(6)]
                yield pa.RecordBatch.from_arrays([p.column(0).take(pa.array(rows, pa.int64())), *columns], names)

    kind = src.schema["doc_id"].dataType.simpleString()
    return src.mapInArrow(run, f"doc_id {kind}, license string, start long, end long, matched int, words int, coverage double")
