"""License scans: winnowed fingerprints, an inverted index and banded alignment.

Words are runs of ASCII letters and digits and of non-ASCII bytes, A-Z lower-cased.  Texts
and templates are fingerprinted by winnowing their word pairs (windows of three), which
keeps one fingerprint of every common run of four words.  Templates with enough common
fingerprints are aligned with the text around the hits; the alignment runs in a band about
the hits' diagonal and maximises the number of matched template words.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from nearcohort.llm.textblocks import blocks, mix, release, words
from nearcohort.plans.runtime import ship

WINDOW = 3
MIN_COVERAGE = 0.8

#: Bytes of all templates together: they travel with every task.
MAX_TEMPLATE_BYTES = 8 << 20

#: Public texts of well-known licenses and the notices by which they are applied.
TEMPLATES: tuple[tuple[str, str], ...] = (
    ("mit-notice", "Released under the MIT License."),
    ("mit-grant", "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and "
     "associated documentation files, to deal in the Software without restriction, including without limitation the "
     "rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software"),
    ("mit-conditions", "The above copyright notice and this permission notice shall be included in all copies or substantial "
     "portions of the Software."),
    ("mit-disclaimer", "THE SOFTWARE IS PROVIDED \"AS IS\", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT "
     "LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL "
     "THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, "
     "TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE."),
    ("isc", "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby "
     "granted, provided that the above copyright notice and this permission notice appear in all copies."),
    ("isc-disclaimer", "THE SOFTWARE IS PROVIDED \"AS IS\" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE "
     "INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, "
     "DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER "
     "IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE "
     "OF THIS SOFTWARE."),
    ("apache-2.0-notice", "Licensed under the Apache License, Version 2.0."),
    ("apache-2.0-header", "Licensed under the Apache License, Version 2.0 (the \"License\"); you may not use this file except in "
     "compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0 Unless "
     "required by applicable law or agreed to in writing, software distributed under the License is distributed on an \"AS IS\" "
     "BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. See the License for the specific language "
     "governing permissions and limitations under the License."),
    ("gpl-3.0-notice", "This work is licensed under the GNU General Public License, version 3."),
    ("gpl-grant", "This program is free software: you can redistribute it and/or modify it under the terms of the GNU "
     "General Public License as published by the Free Software Foundation"),
    ("lgpl-grant", "This library is free software; you can redistribute it and/or modify it under the terms of the GNU Lesser "
     "General Public License as published by the Free Software Foundation"),
    ("agpl-grant", "This program is free software: you can redistribute it and/or modify it under the terms of the GNU Affero "
     "General Public License as published by the Free Software Foundation"),
    ("gpl-disclaimer", "This program is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the "
     "implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE."),
    ("cc-by-nc-4.0-notice", "Licensed under CC BY-NC 4.0."),
    ("cc-by-4.0-notice", "This work is licensed under a Creative Commons Attribution 4.0 International License."),
    ("cc-by-sa-4.0-notice", "This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License."),
    ("cc-by-nd-4.0-notice", "This work is licensed under a Creative Commons Attribution-NoDerivatives 4.0 International License."),
    ("cc0-notice", "To the extent possible under law, the author has waived all copyright and related or neighboring rights to "
     "this work."),
    ("unlicense", "This is free and unencumbered software released into the public domain. Anyone is free to copy, modify, "
     "publish, use, compile, sell, or distribute this software, either in source code form or as a compiled binary, for any "
     "purpose, commercial or non-commercial, and by any means."),
    ("bsd-grant", "Redistribution and use in source and binary forms, with or without modification, are permitted "
     "provided that the following conditions are met"),
    ("bsd-endorsement", "Neither the name of the copyright holder nor the names of its contributors may be used to endorse or "
     "promote products derived from this software without specific prior written permission."),
    ("bsd-disclaimer", "THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS \"AS IS\" AND ANY EXPRESS OR IMPLIED "
     "WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE "
     "ARE DISCLAIMED."),
    ("mpl-2.0-notice", "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0."),
    ("epl-2.0-notice", "This program and the accompanying materials are made available under the terms of the Eclipse Public "
     "License 2.0"),
    ("boost-grant", "Permission is hereby granted, free of charge, to any person or organization obtaining a copy of the software "
     "and accompanying documentation covered by this license to use, reproduce, display, distribute, execute, and transmit the "
     "Software, and to prepare derivative works of the Software"),
    ("zlib", "This software is provided 'as-is', without any express or implied warranty. In no event will the authors be held "
     "liable for any damages arising from the use of this software."),
)

RESULT = ("doc_id long, license string, n_template long, n_matched long, coverage double, "
          "start_byte long, end_byte long")

_PLAIN = np.arange(256, dtype=np.uint8)
_PLAIN[[b for b in range(128) if not chr(b).isalnum()]] = 0x20


def pair_hashes(h: np.ndarray, first: np.ndarray) -> np.ndarray:
    """Hash of each word with its successor; the greatest value where a text ends between."""
    if len(h) < 2:
        return np.zeros(0, np.uint64)
    with np.errstate(over="ignore"):
        p = mix(h[:-1] * np.uint64(3) + h[1:])
    ends = first[1:-1] - 1
    p[ends[(ends >= 0) & (ends < len(p))]] = np.iinfo(np.uint64).max
    return p


def winnow(p: np.ndarray, window: int = WINDOW) -> np.ndarray:
    """Mask of the values that are least in some window of neighbours."""
    top = np.iinfo(np.uint64).max
    wide = np.concatenate([np.full(window - 1, top), p, np.full(window - 1, top)])
    least = np.min([wide[i:len(wide) - window + 1 + i] for i in range(window)], axis=0)
    keep = np.zeros(len(p), bool)
    for i in range(window):
        keep |= p == least[i:i + len(p)]
    return keep & (p != top)


def align(template: np.ndarray, text: np.ndarray, diagonal: int, band: int) -> tuple[int, int, int]:
    """Banded alignment: (matched words, first, last matched place in ``text``).

    Place j of ``text`` may meet word i of ``template`` if |j - i - diagonal| <= band.
    Matches are maximised; among equals the shortest stretch of text is taken.
    """
    n, m = len(template), len(text)
    best: dict[int, tuple[int, int, int]] = {}
    for i in range(n):
        now: dict[int, tuple[int, int, int]] = {}
        lo, hi = max(0, i + diagonal - band), min(m, i + diagonal + band + 1)
        for j in range(lo, hi):
            options = [x for x in (best.get(j), now.get(j - 1)) if x]
            if template[i] == text[j]:
                b = best.get(j - 1)
                options.append((b[0] + 1, b[1], -j) if b else (1, j, -j))
            if options:
                now[j] = max(options)
        # what the band leaves behind stays reachable from its lower edge
        tail = [best[j] for j in best if j < lo]
        if tail and lo < hi:
            now[lo] = max([*tail, now[lo]] if lo in now else tail)
        best = now or best
    if not best:
        return 0, 0, 0
    count, start, last = max(best.values())
    return count, start, -last


class TemplateIndex:
    """Inverted index from fingerprints to (template, place)."""

    def __init__(self, templates, min_coverage: float):
        self.names = [n for n, _ in templates]
        self.min_coverage = min_coverage
        self.words, self.marks, v, who, at = [], [], [], [], []
        for t, (_, text) in enumerate(templates):
            raw = np.frombuffer(text.encode(), np.uint8)
            _, _, h, first = words(np.array([0, len(raw)]), _PLAIN[raw])
            p = pair_hashes(h, first)
            keep = np.flatnonzero(winnow(p))
            self.words.append(h)
            self.marks.append(max(1, len(keep)))
            v.append(p[keep])
            who.append(np.full(len(keep), t))
            at.append(keep)
        v, who, at = map(np.concatenate, (v, who, at))
        order = np.argsort(v, kind="stable")
        self.v, self.who, self.at = v[order], who[order], at[order]

    def scan(self, off: np.ndarray, data: np.ndarray):
        """(row, template, matched, first byte, end byte) of the matches in a block."""
        starts, ends, h, first = words(off, _PLAIN[data])
        p = pair_hashes(h, first)
        lo, hi = np.searchsorted(self.v, p, "left"), np.searchsorted(self.v, p, "right")
        places = np.flatnonzero((hi > lo) & winnow(p))
        rows = np.searchsorted(first, places, "right") - 1
        hits: dict[tuple[int, int], list[tuple[int, int]]] = {}
        for r, j in zip(rows.tolist(), places.tolist(), strict=True):
            for x in range(lo[j], hi[j]):
                hits.setdefault((r, int(self.who[x])), []).append((j, int(self.at[x])))
        for (r, t), found in sorted(hits.items()):
            n = len(self.words[t])
            band = 4 + n // 10
            group: list[tuple[int, int]] = []
            for j, i in [*sorted(found), (1 << 60, 0)]:
                if group and j - i > group[0][0] - group[0][1] + band:
                    yield from self._one(r, t, group, band, off, starts, ends, h, first)
                    group = []
                group.append((j, i))

    def _one(self, r, t, group, band, off, starts, ends, h, first):
        n = len(self.words[t])
        if len({i for _, i in group}) * 3 < self.marks[t]:
            return
        a = max(int(first[r]), group[0][0] - group[0][1] - band)
        b = min(int(first[r + 1]), group[-1][0] + n + band)
        count, s, e = align(self.words[t], h[a:b], group[0][0] - group[0][1] - a, band)
        if count and count >= self.min_coverage * n:
            yield r, t, count, int(starts[a + s] - off[r]), int(ends[a + e] - off[r])


def _scan(batches, templates, min_coverage):
    release()
    index = TemplateIndex(templates, min_coverage)
    for b in batches:
        ids, out = b.column("doc_id"), []
        for row, off, data in blocks(b.column("text")):
            for r, t, count, start, end in index.scan(off, data):
                n = len(index.words[t])
                out.append((ids[row + r].as_py(), index.names[t], n, count, count / n, start, end))
        cols = list(zip(*out, strict=True)) if out else [[]] * 7
        kinds = [pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.float64(), pa.int64(), pa.int64()]
        yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)],
                                         [x.split()[0] for x in RESULT.split(", ")])


def license_spans(docs: DataFrame, templates=TEMPLATES, min_coverage: float = MIN_COVERAGE) -> DataFrame:
    """Every place of a whole text that covers a template: coverage and span in bytes.

    ``templates`` are pairs (name, text) or a DataFrame of ``name, text``, for instance of whole
    license files; more than ``MAX_TEMPLATE_BYTES`` of them are refused.  Null and empty texts
    match nothing; a template that occurs several times is reported for each place.  Repeated
    rows, repeated ids and null ids give rows of their own; other columns, whatever their names,
    are ignored; empty tables give an empty result.
    """
    ship(docs.sparkSession)
    if isinstance(templates, DataFrame):
        templates = templates.select("name", "text").where("text is not null")
        if (templates.agg(F.sum(F.octet_length("text"))).first()[0] or 0) > MAX_TEMPLATE_BYTES:
            raise ValueError("too many templates for one pass: split the table")
        templates = [tuple(r) for r in templates.orderBy("name", "text").collect()]
    templates = [(n, t) for n, t in templates if t and t.strip()]
    if sum(len(t.encode()) for _, t in templates) > MAX_TEMPLATE_BYTES:
        raise ValueError("too many templates for one pass: split them")
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    if not templates:
        return docs.sparkSession.createDataFrame([], RESULT)
    return docs.mapInArrow(lambda it: _scan(it, templates, min_coverage), RESULT)
