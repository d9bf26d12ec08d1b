"""License scans: winnowed fingerprints pick candidates, banded alignment confirms them.

Templates are cut into lower-case words of letters and digits. Of the hashes of GRAM neighbouring words, the least of each
WINDOW goes into an inverted index: gram -> (template, place). A document's grams are looked up; hits of one
template on one diagonal make a candidate, and an alignment within BAND words of the diagonal gives the matched
share of the template and the span in the text. Of overlapping spans the one with more matched words stays,
then that with larger coverage, then by template name, then the earlier one; each diagonal is aligned again on the words that the
spans found so far leave, so neighbouring notices of one template are all found.

A diagonal is aligned only if the words of the template that stand within its reach could be enough. A notice is found if it shares
GRAM + WINDOW - 1 neighbouring words with its template somewhere and the words of it that match, in order, reach
LEAST_COVERAGE of the template. Templates with fewer than GRAM words are indexed whole; a template without words is refused;
without templates there are no spans.

A null or empty text has no spans. Texts are taken whole; memory grows with the longest one. Repeated rows give their spans each time; null ids
are carried through; other columns are ignored. An empty table gives an empty result.
"""

from __future__ import annotations

import bisect
import heapq
import re
import zlib
from collections import defaultdict
from collections.abc import Iterator, Sequence
from dataclasses import dataclass
from pathlib import Path

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from pathlore.llm.common import map_batches

GRAM, WINDOW, BAND, LEAST_COVERAGE = 3, 2, 8, 0.8
WORD = re.compile(r"[a-z0-9]+")
#: Notices, opening clauses and whole texts of public licenses.
TEMPLATES = {
    "apache-2.0-notice": "Licensed under the Apache License, Version 2.0.",
    "apache-2.0-header": 'Licensed under the Apache License, Version 2.0 (the "License"); you may not use this file except in compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0',
    "mit-notice": "Released under the MIT License.",
    "mit-grant": 'Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the "Software"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software',
    "gpl-3.0-notice": "This work is licensed under the GNU General Public License, version 3.",
    "gpl-3.0-header": "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version.",
    "bsd-clause": "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met",
    "cc-by-nc-4.0-notice": "Licensed under CC BY-NC 4.0.",
    "cc-by-4.0-notice": "Licensed under CC BY 4.0.",
    "cc-by-sa-4.0-notice": "Licensed under CC BY-SA 4.0.",
    "mpl-2.0-notice": "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0.",
    "mit": 'Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the "Software"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions: The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software. THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE.',
    "isc": 'Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies. THE SOFTWARE IS PROVIDED "AS IS" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE.',
    "bsd-2-clause": 'Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: 1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer. 2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution. THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS "AS IS" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE.',
    "bsd-3-clause": 'Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: 1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer. 2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution. 3. Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission. THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS "AS IS" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE.',
    "zlib": "This software is provided 'as-is', without any express or implied warranty. In no event will the authors be held liable for any damages arising from the use of this software. Permission is granted to anyone to use this software for any purpose, including commercial applications, and to alter it and redistribute it freely, subject to the following restrictions: 1. The origin of this software must not be misrepresented; you must not claim that you wrote the original software. If you use this software in a product, an acknowledgment in the product documentation would be appreciated but is not required. 2. Altered source versions must be plainly marked as such, and must not be misrepresented as being the original software. 3. This notice may not be removed or altered from any source distribution.",
    "unlicense": 'This is free and unencumbered software released into the public domain. Anyone is free to copy, modify, publish, use, compile, sell, or distribute this software, either in source code form or as a compiled binary, for any purpose, commercial or non-commercial, and by any means. In jurisdictions that recognize copyright laws, the author or authors of this software dedicate any and all copyright interest in the software to the public domain. We make this dedication for the benefit of the public at large and to the detriment of our heirs and successors. We intend this dedication to be an overt act of relinquishment in perpetuity of all present and future rights to this software under copyright law. THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE.',
    "gpl-2.0-header": "This program is free software; you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation; either version 2 of the License, or (at your option) any later version. This program is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE. See the GNU General Public License for more details.",
    "mpl-2.0-header": "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can obtain one at https://mozilla.org/MPL/2.0/.",
}


def lower_in_place(text: str) -> str:
    """Lower-case, with every character at its place: the few whose lower case is longer are left as they are."""
    low = text.lower()
    return low if len(low) == len(text) else "".join(x if len(x := c.lower()) == 1 else c for c in text)


def words_of(text: str) -> list[str]:
    return WORD.findall(lower_in_place(text))


def align(template: Sequence[int], words: Sequence[int], shift: int, band: int = BAND) -> tuple[int, int, int]:
    """Matched words of the best common subsequence within ``band`` of the diagonal ``shift``, and the first and last place in ``words``.

    Ties prefer the shorter span, then the earlier one. One pass over the template, each word against its 2 * band + 1 places at once; a cell
    holds matched * (words + 1) + first place, so the larger cell has more matches, then the later beginning.
    """
    t, w = np.asarray(template, "int64"), np.asarray(words, "int64")
    rows, n, width = len(t), len(w), 2 * band + 1
    if not rows or not n:
        return 0, 0, 0
    low, high = shift - band, rows + shift + band  # places that any row looks at
    padded = np.full(high - low, -1, "int64")
    inside = slice(max(0, low), min(n, high))
    if inside.start < inside.stop:
        padded[inside.start - low : inside.stop - low] = w[inside]
    unit = n + 1
    hits = np.lib.stride_tricks.sliding_window_view(padded, width)[:rows] == t[:, None]
    fresh = unit + np.arange(low, low + len(padded))  # a match that begins at the place
    ends = np.zeros((rows, width), "int64")
    best = np.zeros(width + 1, "int64")
    for i in range(rows):
        before = best[:width]  # of the row above: the places one to the left, as each row's window moves on by one
        if hits[i].any():
            ends[i] = np.where(hits[i], np.where(before > 0, before + unit, fresh[i : i + width]), 0)
        best[:width] = np.maximum.accumulate(np.maximum(np.maximum(best[1:], before), ends[i]))
    matched = ends // unit
    top = int(matched.max())
    if not top:
        return 0, 0, 0
    i, k = np.nonzero(matched == top)
    first, last = ends[i, k] % unit, i + k + low
    pick = np.lexsort((first, last - first))[0]
    return top, int(first[pick]), int(last[pick])


def free_parts(lo: int, hi: int, taken: list[tuple[int, int]]) -> Iterator[tuple[int, int]]:
    """What of the words from ``lo`` to before ``hi`` the sorted spans (first, last) leave."""
    for first, last in taken[max(0, bisect.bisect_left(taken, (lo, 0)) - 1) :]:
        if first >= hi:
            break
        if lo < first:
            yield lo, first
        lo = max(lo, last + 1)
    if lo < hi:
        yield lo, hi


@dataclass
class LicenseIndex:
    """Vocabulary, words of each template, and the postings of the winnowed grams, by the gram's number of words."""

    numbers: dict[str, int]
    words: dict[str, list[int]]
    keys: dict[int, np.ndarray]
    postings: dict[int, list[list[tuple[str, int]]]]

    @classmethod
    def build(cls, templates: dict[str, str]) -> LicenseIndex:
        numbers: dict[str, int] = {}
        words = {name: [numbers.setdefault(w, len(numbers) + 1) for w in words_of(t)] for name, t in templates.items()}
        if empty := sorted(name for name, ws in words.items() if not ws):
            raise ValueError(f"template {empty[0]} has no words")
        base = len(numbers) + 1
        index: dict[int, dict[int, list[tuple[str, int]]]] = defaultdict(lambda: defaultdict(list))
        for name, ws in words.items():
            size = min(GRAM, len(ws))
            grams = [sum(w * base**k for k, w in enumerate(ws[i : i + size])) for i in range(len(ws) - size + 1)]
            ranks = [zlib.crc32(str(g).encode()) for g in grams]
            picked = {min(range(i, min(i + WINDOW, len(grams))), key=lambda p: (ranks[p], -p)) for i in range(max(1, len(grams) - WINDOW + 1))}
            for p in sorted(picked):
                index[size][grams[p]].append((name, p))
        keys = {size: sorted(found) for size, found in index.items()}
        return cls(numbers, words, {size: np.array(k, "int64") for size, k in keys.items()}, {size: [index[size][g] for g in k] for size, k in keys.items()})

    def hits(self, ids: np.ndarray) -> dict[str, set[int]]:
        """The diagonals of each template that a gram of the text lies on."""
        near: dict[str, set[int]] = defaultdict(set)
        base = len(self.numbers) + 1
        for size, keys in self.keys.items():
            n = len(ids) - size + 1
            if n < 1:
                continue
            key, whole = np.zeros(n, "int64"), np.ones(n, bool)
            for k in range(size):
                key += ids[k : n + k] * base**k
                whole &= ids[k : n + k] > 0
            at = np.minimum(np.searchsorted(keys, key), len(keys) - 1)
            for p in np.flatnonzero(whole & (keys[at] == key)).tolist():
                for name, place in self.postings[size][at[p]]:
                    near[name].add(p - place)
        return near

    def scan(self, text: str | None) -> list[tuple[str, float, int, int, int]]:
        """(template, coverage, matched words, first character, character after the last)."""
        low = lower_in_place(text or "")
        ids = np.fromiter(map(self.numbers.get, words := WORD.findall(low), [0] * len(words)), "int64", len(words))
        near = self.hits(ids)
        if not near:
            return []
        own: dict[str, np.ndarray] = {}  # of a template: how many of its words stand before each place
        for name in near:
            known = np.zeros(len(self.numbers) + 1, "int64")
            known[self.words[name]] = 1
            own[name] = np.concatenate([[0], np.cumsum(known[ids])])
        found: list[tuple] = []
        taken: list[tuple[int, int]] = []

        def look(name: str, shift: int, lo: int, hi: int) -> None:
            template = self.words[name]
            if own[name][hi] - own[name][lo] >= LEAST_COVERAGE * len(template):  # no alignment can match more
                matched, first, end = align(template, ids[lo:hi], shift - lo)
                if matched >= LEAST_COVERAGE * len(template):
                    heapq.heappush(found, (-matched, -matched / len(template), name, lo + first, lo + end, shift, lo, hi))

        for name, shifts in near.items():
            for shift in shifts:
                look(name, shift, max(0, shift - BAND), min(len(ids), shift + len(self.words[name]) + BAND))
        kept: list[tuple] = []
        while found:
            matched, cov, name, first, end, shift, lo, hi = heapq.heappop(found)
            parts = [*free_parts(lo, hi, taken)]
            if any(a <= first and end < b for a, b in parts):
                kept.append((-matched, -cov, name, first, end))
                bisect.insort(taken, (first, end))
                parts = [*free_parts(lo, hi, taken)]
            #: The diagonal goes on with the words that are left: another notice may lie within its band.
            for part in parts:
                look(name, shift, *part)
        if not kept:
            return []
        places = [m.span() for m in WORD.finditer(low)]
        return sorted(((name, cov, m, places[a][0], places[b][1]) for m, cov, name, a, b in kept), key=lambda x: x[3])


def read_templates(paths: dict[str, str]) -> dict[str, str]:
    """More templates: the whole text of each file, by name."""
    return {name: Path(path).read_text(encoding="utf-8") for name, path in paths.items()}


def scan_licenses(docs: DataFrame, templates: dict[str, str] | None = None) -> DataFrame:
    """doc_id, license, coverage, matched_words, span_start, span_end: a row for each span."""
    index = LicenseIndex.build(TEMPLATES if templates is None else templates)

    def work(batch: pa.RecordBatch) -> Iterator[pa.RecordBatch]:
        rows = [(d, *x) for d, t in zip(batch.column("doc_id").to_pylist(), batch.column("text"), strict=True) for x in index.scan(t.as_py())]
        kinds = [pa.int64(), pa.string(), pa.float64(), pa.int64(), pa.int64(), pa.int64()]
        cols = [*zip(*rows, strict=True)] if rows else [[]] * 6
        yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], ["doc_id", "license", "coverage", "matched_words", "span_start", "span_end"])

    return map_batches(docs.select("doc_id", "text"), work, "doc_id long, license string, coverage double, matched_words long, span_start long, span_end long")
