"""Licence scan: normalised text against licence templates by the Dice coefficient of their word bigrams.

A unit of text is a whole document without its copyright lines, one line, or a passage: any run of successive
words, over line breaks or inside a line. A passage counts if the whole text matches nothing and no matching
line or passage that it overlaps is as good. Words are lower-cased runs of
letters and digits, so case, punctuation and line breaks don't count. A unit of a distinct bigrams and a
template of b can reach 2 min(a,b) / (a+b) at most; templates out of reach of the threshold are pruned by
that bound before any bigram is compared. The templates are a fixed, small list, and are broadcast.

Defined results: null or empty text and units of one word match nothing; on equal coefficients the whole
text comes before a line, a line before a passage, an earlier one before a later one, and then the template that
is listed first. The line of a passage is that of its first word.
Repeated rows and further columns change nothing; an empty table gives an empty result.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from rotahash.llm.bytesops import BASE, U, distinct_sorted, lean, mix, slices, word_hashes

THRESHOLD = 0.9
MIT = """Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the "Software"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions: The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software. THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE."""
ISC = """Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies. THE SOFTWARE IS PROVIDED "AS IS" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE."""
BSD_CONDITIONS = """Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: 1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer. 2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution."""
BSD_NAMES = """3. Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission."""
BSD_DISCLAIMER = """THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS "AS IS" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE."""
#: Names and texts of licences and of the notices that refer to them.
TEMPLATES = (
    ("MIT", MIT),
    ("ISC", ISC),
    ("BSD-2-Clause", f"{BSD_CONDITIONS} {BSD_DISCLAIMER}"),
    ("BSD-3-Clause", f"{BSD_CONDITIONS} {BSD_NAMES} {BSD_DISCLAIMER}"),
    ("Apache-2.0", 'Licensed under the Apache License, Version 2.0 (the "License"); you may not use this file except in compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0 Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an "AS IS" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. See the License for the specific language governing permissions and limitations under the License.'),
    ("GPL-3.0-or-later", "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version. This program is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE. See the GNU General Public License for more details. You should have received a copy of the GNU General Public License along with this program. If not, see <https://www.gnu.org/licenses/>."),
    ("Apache-2.0", "Licensed under the Apache License, Version 2.0."),
    ("MIT", "Released under the MIT License."),
    ("MIT", "Licensed under the MIT License."),
    ("GPL-3.0", "This work is licensed under the GNU General Public License, version 3."),
    ("CC-BY-NC-4.0", "Licensed under CC BY-NC 4.0."),
    ("CC-BY-4.0", "Licensed under CC BY 4.0."),
    ("CC-BY-SA-4.0", "Licensed under CC BY-SA 4.0."),
    ("all-rights-reserved", "All rights reserved."),
)
FILTER_BITS = 16


def bigrams(words: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of the distinct pairs of successive words of each unit, and the units' offsets."""
    count = np.maximum(np.diff(at) - 1, 0)
    to = np.concatenate([[0], np.cumsum(count)])
    pos = np.arange(to[-1]) - np.repeat(to[:-1] - at[:-1], count)
    return distinct_sorted(mix(words[pos] * BASE + words[pos + 1]), to)


class Templates:
    def __init__(self, templates, threshold: float):
        self.threshold, self.names = threshold, [n for n, _ in templates]
        grams = []
        for _, _, data, at in slices(pa.array([t for _, t in templates]), 1 << 40, lower=True):
            values, to = bigrams(*word_hashes(data, at))
            grams = [values[to[i] : to[i + 1]] for i in range(len(to) - 1)]
        self.sizes = np.array([len(g) for g in grams], np.int64)
        self.grams = grams
        keys = np.concatenate([*grams, np.zeros(0, U)])
        order = np.argsort(keys, kind="stable")
        self.keys, self.owner = keys[order], np.repeat(np.arange(len(grams)), self.sizes)[order]
        self.filter = np.zeros(1 << FILTER_BITS, bool)
        self.filter[(self.keys >> U(64 - FILTER_BITS)).astype(np.int64)] = True

    def match(self, words: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(unit, template, coefficient) of all that reach the threshold."""
        grams, to = bigrams(words, at)
        size, m = np.diff(to), len(self.sizes)
        low = self.sizes * self.threshold / (2 - self.threshold) - 1e-9
        high = self.sizes * (2 - self.threshold) / self.threshold + 1e-9
        fits = (size[:, None] >= low) & (size[:, None] <= high) & (size[:, None] > 0)  # the size bound
        maybe = np.flatnonzero(self.filter[(grams >> U(64 - FILTER_BITS)).astype(np.int64)] & np.repeat(fits.any(1), size))
        lo, hi = np.searchsorted(self.keys, grams[maybe]), np.searchsorted(self.keys, grams[maybe], "right")
        unit = np.repeat(np.searchsorted(to, maybe, "right") - 1, hi - lo)
        n = np.cumsum(hi - lo)
        owner = self.owner[np.arange(n[-1] if len(n) else 0) - np.repeat(n - (hi - lo), hi - lo) + np.repeat(lo, hi - lo)]
        pair, common = np.unique(unit * m + owner, return_counts=True)
        unit, owner = pair // m, pair % m
        dice = 2 * common / (size[unit] + self.sizes[owner])
        keep = fits[unit, owner] & (dice >= self.threshold - 1e-12)
        return unit[keep], owner[keep], dice[keep]

    def candidates(self, values: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(document, template) that share enough bigrams for a passage to match; values: the pair of each word and the next, at: the documents' first words."""
        maybe = np.flatnonzero(self.filter[(values >> U(64 - FILTER_BITS)).astype(np.int64)])
        doc = np.searchsorted(at, maybe, "right") - 1
        inside = maybe + 1 < at[doc + 1]
        maybe, doc = maybe[inside], doc[inside]
        lo, hi = np.searchsorted(self.keys, values[maybe]), np.searchsorted(self.keys, values[maybe], "right")
        n = np.cumsum(hi - lo)
        key = np.arange(n[-1] if len(n) else 0) - np.repeat(n - (hi - lo), hi - lo) + np.repeat(lo, hi - lo)
        seen = np.unique(np.repeat(doc, hi - lo) * len(self.keys) + key)
        pair, common = np.unique(seen // max(len(self.keys), 1) * len(self.sizes) + self.owner[seen % max(len(self.keys), 1)], return_counts=True)
        doc, owner = pair // len(self.sizes), pair % len(self.sizes)
        enough = common >= self.sizes[owner] * self.threshold / (2 - self.threshold) - 1e-9
        return doc[enough], owner[enough]

    def passages(self, values: np.ndarray, owners: list[int], lines: list[tuple[float, int, int]]) -> list[tuple[float, int, int]]:
        """(coefficient, first word, template) of a document's passages; lines: coefficient, first word and end of the lines that match."""
        n = len(values)
        before = np.full(n, -1)
        order = np.argsort(values, kind="stable")
        same = values[order][1:] == values[order][:-1]
        before[order[1:][same]] = order[:-1][same]
        found = [(-dice, 0, begin, -1, end) for dice, begin, end in lines]
        for t in owners:
            own, size = self.grams[t], self.sizes[t]
            inside = own[np.minimum(np.searchsorted(own, values), size - 1)] == values
            reach = int((inside & (before < 0)).sum())
            high = size * (2 - self.threshold) / self.threshold + 1e-9
            for i in np.flatnonzero(inside).tolist():  # a best passage begins with a bigram of the template
                width = 4 * int(size) + 16
                while True:
                    new = before[i : i + width] < i
                    distinct, common = np.cumsum(new), np.cumsum(new & inside[i : i + width])
                    if i + width >= n or distinct[-1] > high or common[-1] == reach:
                        break
                    width *= 2
                dice = 2 * common / (distinct + size)
                k = int(dice.argmax())
                if dice[k] >= self.threshold - 1e-12:
                    found.append((-float(dice[k]), 1, i, t, i + k + 2))
        taken, out = np.zeros(n + 1, bool), []
        for dice, passage, begin, t, end in sorted(found):
            if passage and not taken[begin:end].any():
                out.append((-dice, begin, t))
            if not passage or out and out[-1][1:] == (begin, t):
                taken[begin:end] = True
        return out


def scan(docs: DataFrame, threshold: float = THRESHOLD, templates=TEMPLATES) -> DataFrame:
    """One row per document: doc_id, license (null: none), dice, line (number of the line from 0; -1: the whole text; null: none), n_matches (units that match some template; passages as defined above)."""
    shared = docs.sparkSession.sparkContext.broadcast((tuple(templates), threshold))

    def find(batches):
        index = Templates(*shared.value)
        (mark,), _ = word_hashes(np.frombuffer(b"copyright", np.uint8), np.array([0, 9]))
        for b in batches:
            n = b.num_rows
            name, best, place, many = np.full(n, -1), np.zeros(n), np.zeros(n, np.int64), np.zeros(n, np.int64)
            for lo, hi, data, at in slices(b.column("text"), lower=True):
                feeds = np.flatnonzero(data == 10)
                lines = np.unique(np.concatenate([at, feeds]))  # a line may begin with its line feed
                words, to = word_hashes(data, lines)
                doc_of = np.searchsorted(at, lines[:-1], "right") - 1
                number = np.arange(len(doc_of)) - np.searchsorted(doc_of, np.arange(hi - lo))[doc_of] if len(doc_of) else doc_of
                filled = np.flatnonzero(np.diff(to))
                notice = np.zeros(len(doc_of), bool)
                notice[filled] = words[to[filled]] == mark
                keep = ~np.repeat(notice, np.diff(to))
                count = np.bincount(doc_of, weights=np.where(notice, 0, np.diff(to)), minlength=hi - lo).astype(np.int64)
                whole, alike = np.zeros(hi - lo, bool), {}
                for texts in (True, False):
                    unit, owner, dice = index.match(words[keep], np.concatenate([[0], np.cumsum(count)])) if texts else index.match(words, to)
                    row = unit if texts else doc_of[unit]
                    line = np.full(len(unit), -1) if texts else number[unit]
                    if texts:
                        whole[unit] = True
                    else:
                        for d, x, y, z in zip(row.tolist(), dice.tolist(), to[unit].tolist(), to[unit + 1].tolist(), strict=True):
                            alike.setdefault(d, []).append((x, y, z))
                    first = np.concatenate([[True], unit[1:] != unit[:-1]]) if len(unit) else np.zeros(0, bool)
                    np.add.at(many, lo + row[first], 1)
                    for k in np.lexsort((owner, line, -dice)).tolist():
                        r = lo + row[k]
                        if dice[k] > best[r]:
                            best[r], name[r], place[r] = dice[k], owner[k], line[k]
                values, begin = mix(words[:-1] * BASE + words[1:]), to[np.searchsorted(lines, at)]
                near: dict = {}
                for d, t in zip(*(x.tolist() for x in index.candidates(values, begin)), strict=True):
                    if not whole[d]:
                        near.setdefault(d, []).append(t)
                for d, owners in near.items():
                    b0, r = begin[d], lo + d
                    for x, y, t in index.passages(values[b0 : begin[d + 1] - 1], owners, [(x, y - b0, z - b0) for x, y, z in alike.get(d, [])]):
                        many[r] += 1
                        if x > best[r]:
                            best[r], name[r], place[r] = x, t, number[np.searchsorted(to, b0 + y, "right") - 1]
            none = name < 0
            names = pa.array([None if i < 0 else index.names[i] for i in name.tolist()], pa.string())
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), names, pa.array(best), pa.array(place, mask=none), pa.array(many)], ["doc_id", "license", "dice", "line", "n_matches"])

    return docs.select("doc_id", "text").mapInArrow(lean(find), "doc_id long, license string, dice double, line long, n_matches long")
