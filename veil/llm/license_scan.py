"""License scans: winnowed fingerprints pick candidates, banded alignment decides.

Templates are reduced to winnowed fingerprints of three consecutive words, held
in an inverted index (fingerprint -> template and place). Every run of three
words of a document is looked up in the index; hits of one template on nearby
diagonals are a candidate region, on which the template is aligned with the
document inside a band around the diagonals. A match reports how many template
words were found in order, their share, and the span in the document. Of
overlapping matches the one with more matched words stays.

The index grows with the templates only, and its size is checked; it travels
with the tasks. Documents are never shuffled. Regions are bounded by template
length plus band, so a text of any length is a row of small alignments.

Defined results: null and empty texts have no match; repeated rows report the
same matches each; a template of fewer than three words is refused; matches of
equal weight go to the earlier, then the template of smaller name; extra
columns are ignored; spans are in code points, end exclusive; an empty table has
no matches. A body without its license's other parts is reported with the share
of words it has, if that reaches the least coverage.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from veil.llm.word_hash import BLOCK, SIGNS, mix, segments, word_hashes
from veil.sources.shared import in_arrow

GRAM, WINDOW, BAND = 3, 3, 8
LEAST_COVERAGE = 0.8
MOST_FINGERPRINTS = 2_000_000

_BSD_DISCLAIMER = (
    "THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS \"AS IS\" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT "
    "LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT "
    "HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT "
    "LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY "
    "THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF "
    "THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE."
)

#: Fixed texts: short notices, file headers, and whole licenses in one line each, without their copyright lines.
TEMPLATES = {
    "apache-2.0-notice": "Licensed under the Apache License, Version 2.0.",
    "cc-by-nc-4.0-notice": "Licensed under CC BY-NC 4.0.",
    "gpl-3.0-notice": "This work is licensed under the GNU General Public License, version 3.",
    "mit-notice": "Released under the MIT License.",
    "apache-2.0-header": (
        "Licensed under the Apache License, Version 2.0 (the \"License\"); you may not use this file except in compliance with the License. "
        "You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0 Unless required by applicable law or agreed to in "
        "writing, software distributed under the License is distributed on an \"AS IS\" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, "
        "either express or implied. See the License for the specific language governing permissions and limitations under the License."
    ),
    "gpl-3.0-header": (
        "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published "
        "by the Free Software Foundation, either version 3 of the License, or (at your option) any later version. This program is distributed in "
        "the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A "
        "PARTICULAR PURPOSE. See the GNU General Public License for more details."
    ),
    "gpl-2.0-header": (
        "This program is free software; you can redistribute it and/or modify it under the terms of the GNU General Public License as published "
        "by the Free Software Foundation; either version 2 of the License, or (at your option) any later version. This program is distributed in "
        "the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A "
        "PARTICULAR PURPOSE. See the GNU General Public License for more details."
    ),
    "mpl-2.0-header": (
        "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this "
        "file, You can obtain one at https://mozilla.org/MPL/2.0/."
    ),
    "mit": (
        "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the "
        "\"Software\"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, "
        "distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to "
        "the following conditions: The above copyright notice and this permission notice shall be included in all copies or substantial portions "
        "of the Software. THE SOFTWARE IS PROVIDED \"AS IS\", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE "
        "WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS "
        "BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN "
        "CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE."
    ),
    "isc": (
        "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that "
        "the above copyright notice and this permission notice appear in all copies. THE SOFTWARE IS PROVIDED \"AS IS\" AND THE AUTHOR DISCLAIMS "
        "ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR "
        "BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR "
        "PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR "
        "PERFORMANCE OF THIS SOFTWARE."
    ),
    "bsd-2-clause": (
        "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are "
        "met: 1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer. "
        "2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the "
        "documentation and/or other materials provided with the distribution. " + _BSD_DISCLAIMER
    ),
    "bsd-3-clause": (
        "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are "
        "met: 1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer. "
        "2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the "
        "documentation and/or other materials provided with the distribution. 3. Neither the name of the copyright holder nor the names of its "
        "contributors may be used to endorse or promote products derived from this software without specific prior written permission. "
        + _BSD_DISCLAIMER
    ),
    "zlib": (
        "This software is provided 'as-is', without any express or implied warranty. In no event will the authors be held liable for any damages "
        "arising from the use of this software. Permission is granted to anyone to use this software for any purpose, including commercial "
        "applications, and to alter it and redistribute it freely, subject to the following restrictions: 1. The origin of this software must not "
        "be misrepresented; you must not claim that you wrote the original software. If you use this software in a product, an acknowledgment in "
        "the product documentation would be appreciated but is not required. 2. Altered source versions must be plainly marked as such, and must "
        "not be misrepresented as being the original software. 3. This notice may not be removed or altered from any source distribution."
    ),
    "unlicense": (
        "This is free and unencumbered software released into the public domain. Anyone is free to copy, modify, publish, use, compile, sell, or "
        "distribute this software, either in source code form or as a compiled binary, for any purpose, commercial or non-commercial, and by any "
        "means. In jurisdictions that recognize copyright laws, the author or authors of this software dedicate any and all copyright interest in "
        "the software to the public domain. We make this dedication for the benefit of the public at large and to the detriment of our heirs and "
        "successors. We intend this dedication to be an overt act of relinquishment in perpetuity of all present and future rights to this "
        "software under copyright law. THE SOFTWARE IS PROVIDED \"AS IS\", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT "
        "LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS BE "
        "LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN "
        "CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE. For more information, please refer to <https://unlicense.org>"
    ),
}

OUT = "doc_id long, license string, matched_words long, template_words long, coverage double, start long, end long"


def grams(h: np.ndarray) -> np.ndarray:
    """Hashes of GRAM consecutive words."""
    n = len(h) - GRAM + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    return mix(h[:n] + mix(h[1 : n + 1] + mix(h[2 : n + 2])))


def winnow(g: np.ndarray) -> np.ndarray:
    """Places of the smallest hash of every window, the rightmost of equals."""
    if len(g) <= WINDOW:
        return np.array([len(g) - 1 - int(np.argmin(g[::-1]))]) if len(g) else np.zeros(0, np.int64)
    w = np.lib.stride_tricks.sliding_window_view(g, WINDOW)[:, ::-1]
    return np.unique(np.arange(len(w)) + WINDOW - 1 - np.argmin(w, axis=1))


class Index:
    """Fingerprints of all templates, sorted, with template and place of each."""

    def __init__(self, templates: dict[str, str]):
        self.names = sorted(templates)
        self.words: list[np.ndarray] = []
        keys, owner, place = [], [], []
        for t, name in enumerate(self.names):
            h, _, _ = word_hashes(templates[name].encode(), SIGNS)
            if len(h) < GRAM:
                raise ValueError(f"template {name} has fewer than {GRAM} words")
            g = grams(h)
            # of a short template every gram is held, as a region of enough coverage may keep any one only
            at = winnow(g) if len(h) > (GRAM + WINDOW) / (1 - LEAST_COVERAGE) else np.arange(len(g))
            self.words.append(h)
            keys.append(g[at])
            owner.append(np.full(len(at), t))
            place.append(at)
        key = np.concatenate(keys) if keys else np.zeros(0, np.uint64)
        if len(key) > MOST_FINGERPRINTS:
            raise ValueError("too many fingerprints to travel with the tasks")
        order = np.argsort(key, kind="stable")
        self.key, self.owner, self.place = key[order], np.concatenate(owner or [[]])[order], np.concatenate(place or [[]])[order]

    def hits(self, g: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Places in the document, templates and places in them, of all grams found in the index."""
        lo, hi = np.searchsorted(self.key, g, "left"), np.searchsorted(self.key, g, "right")
        at = np.flatnonzero(hi > lo)
        count = (hi - lo)[at]
        doc = np.repeat(at, count)
        j = np.repeat(lo[at], count) + np.arange(count.sum()) - np.repeat(np.cumsum(count) - count, count)
        return doc, self.owner[j], self.place[j]


def band_of(template: np.ndarray) -> int:
    """Half width of the band: narrower for short templates, whose copies may follow each other closely."""
    return min(BAND, max(2, len(template) // 4))


def align(doc: np.ndarray, template: np.ndarray, diagonal: int, band: int = BAND) -> tuple[int, int, int]:
    """Longest common subsequence inside a band around ``diagonal``: matched words, first and last place in doc."""
    width = 2 * band + 1
    none = (0, 0, 0)
    above: list[tuple[int, int, int]] = [none] * (width + 1)
    for i, w in enumerate(template):
        row: list[tuple[int, int, int]] = []
        base = diagonal + i - band
        for c in range(width):
            j = base + c
            best = above[c + 1] if above[c + 1][0] > (row[-1][0] if row else 0) else (row[-1] if row else above[c + 1])
            if 0 <= j < len(doc) and doc[j] == w:
                n, first, _ = above[c]
                if n + 1 > best[0]:
                    best = (n + 1, first if n else j, j)
            row.append(best)
        above = row + [row[-1]]
    return max(above, key=lambda x: x[0])


def matches(index: Index, h: np.ndarray, least: float) -> list[tuple[int, int, int, int]]:
    """(template, matched words, first word, last word) of the regions that reach the coverage, without overlaps."""
    doc, owner, place = index.hits(grams(h))
    if not len(doc):
        return []
    diagonal = doc - place
    order = np.lexsort((diagonal, owner))
    doc, owner, diagonal = doc[order], owner[order], diagonal[order]
    bands = np.array([band_of(w) for w in index.words])
    new = np.concatenate([[True], (owner[1:] != owner[:-1]) | (np.diff(diagonal) > bands[owner[1:]])])
    found: set[tuple[int, int, int, int]] = set()
    starts = np.flatnonzero(new)
    for lo, hi in zip(starts, np.append(starts[1:], len(doc))):
        t = int(owner[lo])
        template, band = index.words[t], int(bands[t])
        at = int(diagonal[lo])
        while True:  # long runs of diagonals are taken band by band
            j0 = max(0, at - band)
            piece = h[j0 : max(0, at + len(template) + 2 * band)]
            n, first, last = align(piece, template, at - j0 + band // 2, band)
            if n >= least * len(template):
                found.add((t, n, j0 + first, j0 + last))
            rest = diagonal[lo:hi][diagonal[lo:hi] > at + band]
            if not len(rest):
                break
            at = int(rest[0])
    kept: list[tuple[int, int, int, int]] = []
    for m in sorted(found, key=lambda m: (-m[1], m[2], index.names[m[0]])):
        if all(m[3] < k[2] or m[2] > k[3] for k in kept):
            kept.append(m)
    return sorted(kept, key=lambda m: m[2])


def _rows(batches: Iterator[pa.RecordBatch], schema: pa.Schema, index: Index, least: float) -> Iterator[pa.RecordBatch]:
    for b in batches:
        ids, texts = b.column("doc_id").to_pylist(), b.column("text").cast(pa.binary())
        out: list[tuple] = []
        at = 0
        while at < len(ids):
            block, held = [], 0
            while at < len(ids) and (not block or held < BLOCK):
                block.append((ids[at], texts[at].as_py() or b""))
                held += len(block[-1][1]) + 1
                at += 1
            for doc_id, data, h, starts, ends in _words(block):
                for t, n, first, last in matches(index, h, least):
                    lo, hi = int(starts[first]), int(ends[last])
                    begin = len(data[:lo].decode("utf-8", "replace"))
                    end = begin + len(data[lo:hi].decode("utf-8", "replace"))
                    total = len(index.words[t])
                    out.append((doc_id, index.names[t], n, total, n / total, begin, end))
        cols = list(zip(*out)) if out else [[] for _ in schema]
        yield pa.RecordBatch.from_arrays([pa.array(list(c), f.type) for c, f in zip(cols, schema)], schema=schema)


def _words(block: list[tuple[int, bytes]]) -> Iterator[tuple]:
    """Word hashes and offsets of each text of a block, hashed together."""
    if len(block) == 1:
        (doc_id, data), = block
        parts = list(segments(data, SIGNS)) or [(np.zeros(0, np.uint64), np.zeros(0, int), np.zeros(0, int))]
        yield doc_id, data, *map(np.concatenate, zip(*parts))
        return
    h, starts, ends = word_hashes(b" ".join(d for _, d in block), SIGNS)
    offsets = np.cumsum([0] + [len(d) + 1 for _, d in block])
    cut = np.searchsorted(starts, offsets)
    for j, (doc_id, data) in enumerate(block):
        s = slice(cut[j], cut[j + 1])
        yield doc_id, data, h[s], starts[s] - offsets[j], ends[s] - offsets[j]


def scan(docs: DataFrame, templates: dict[str, str] | None = None, least: float = LEAST_COVERAGE, text: str = "text", key: str = "doc_id") -> DataFrame:
    """One row per match: ``doc_id, license, matched_words, template_words, coverage, start, end``."""
    index = Index(TEMPLATES if templates is None else templates)
    narrow = docs.select(F.col(key).alias("doc_id"), F.col(text).alias("text"))
    return in_arrow(narrow, _rows, OUT, index, least)
