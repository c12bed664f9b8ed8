"""Licence scans: MinHash bands over overlapping windows find templates, exact containment confirms them.

A template is the set of its word shingles (five words; words are runs of letters and digits, A-Z folded). Templates of
more than L/2 and at most L shingles belong to class L (powers of two from 2), and are sought in windows of 2L shingles
that begin at every multiple of L, so every stretch of L shingles lies whole in a window. A window that holds the share
`containment` of a template has a Jaccard similarity above a floor; the number of bands (of one row each) is the least
that finds such a window with the wanted probability. A found window counts only if it really holds that share.

Minima over windows of a class are minima of two windows of the class below: each text is hashed once for each band.

Cases: null or short texts match nothing; a template of fewer than five words is one shingle of all its words and matches
only a text that is just these words; repeated rows are matched alike; whole texts of any length; an empty table gives an
empty table; a null key is a key like any other; extra columns aren't read.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .base import NOT_ALNUM, mix64, ship, shingles, utf8, words

#: Public licence notices, and whole texts of short licences. Another library is a parameter of `scan`.
TEMPLATES = {
    "Apache-2.0": "Licensed under the Apache License, Version 2.0",
    "Apache-2.0-notice": "you may not use this file except in compliance with the License. You may obtain a copy of the License at",
    "MIT": "Released under the MIT License",
    "MIT-notice": "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the Software), to deal in the Software without restriction",
    "GPL-3.0": "This work is licensed under the GNU General Public License, version 3",
    "GPL-notice": "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation",
    "CC-BY-NC-4.0": "Licensed under CC BY-NC 4.0",
    "BSD-notice": "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met",
    "MIT-text": """Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the "Software"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions: The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software. THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE.""",
    "BSD-3-Clause-text": """Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: 1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer. 2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution. 3. Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission. THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS "AS IS" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE.""",
    "ISC-text": """Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies. THE SOFTWARE IS PROVIDED "AS IS" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE.""",
    "Zlib-text": """This software is provided 'as-is', without any express or implied warranty. In no event will the authors be held liable for any damages arising from the use of this software. Permission is granted to anyone to use this software for any purpose, including commercial applications, and to alter it and redistribute it freely, subject to the following restrictions: 1. The origin of this software must not be misrepresented; you must not claim that you wrote the original software. If you use this software in a product, an acknowledgment in the product documentation would be appreciated but is not required. 2. Altered source versions must be plainly marked as such, and must not be misrepresented as being the original software. 3. This notice may not be removed or altered from any source distribution.""",
    "Unlicense-text": """This is free and unencumbered software released into the public domain. Anyone is free to copy, modify, publish, use, compile, sell, or distribute this software, either in source code form or as a compiled binary, for any purpose, commercial or non-commercial, and by any means. In jurisdictions that recognize copyright laws, the author or authors of this software dedicate any and all copyright interest in the software to the public domain. We make this dedication for the benefit of the public at large and to the detriment of our heirs and successors. We intend this dedication to be an overt act of relinquishment in perpetuity of all present and future rights to this software under copyright law.""",
    "Apache-2.0-text": """Licensed under the Apache License, Version 2.0 (the "License"); you may not use this file except in compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0 Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an "AS IS" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. See the License for the specific language governing permissions and limitations under the License.""",
    "GPL-3.0-text": """This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version. This program is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE. See the GNU General Public License for more details. You should have received a copy of the GNU General Public License along with this program. If not, see https://www.gnu.org/licenses/.""",
    "LGPL-notice": "This library is free software; you can redistribute it and/or modify it under the terms of the GNU Lesser General Public License as published by the Free Software Foundation",
    "MPL-2.0-text": "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can obtain one at https://mozilla.org/MPL/2.0/",
    "CC-BY-4.0": "This work is licensed under the Creative Commons Attribution 4.0 International License",
    "CC-BY-SA-4.0": "This work is licensed under the Creative Commons Attribution-ShareAlike 4.0 International License",
}
TABLE = 1 << 16


def jaccard_floor(containment: float) -> float:
    """Least similarity of a window of 2L shingles and a template of more than L/2 of which it holds the share."""
    return containment * 0.5 / (2 + 0.5 * (1 - containment))


def bands_for(similarity: float, probability: float) -> int:
    return math.ceil(math.log(1 - probability) / math.log(1 - similarity))


@dataclass
class Library:
    """Templates by class, and for each band which minima lead to a template."""

    names: list[str]
    sets: list[np.ndarray]
    levels: list[int]
    seeds: np.ndarray
    floor: float

    @classmethod
    def of(cls, templates: dict[str, str], containment: float, probability: float) -> Library:
        names, sets = list(templates), []
        for name in names:
            raw = np.frombuffer(templates[name].encode(), np.uint8)
            h, doc, _ = words(raw, np.array([0, len(raw)]), between=NOT_ALNUM)
            sets.append(np.unique(shingles(h, doc, 1)[0]))
        levels = [max(2, 1 << math.ceil(math.log2(max(1, len(s))))) for s in sets]
        bands = bands_for(jaccard_floor(containment), probability)
        seeds = mix64(np.arange(1, bands + 1, dtype=np.uint64) * np.uint64(0x2545F4914F6CDD1D)) | np.uint64(1)
        return cls(names, sets, levels, seeds, containment)

    def values(self, s: np.ndarray, band: int) -> np.ndarray:
        x = s * self.seeds[band]
        return ((x ^ (x >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9) >> np.uint64(32)).astype(np.uint32)

    def scan(self, s: np.ndarray, owner: np.ndarray) -> Iterator[tuple[int, int, int, float]]:
        """document, template, place of the first shingle in the document, share: of confirmed windows, s in the order of the texts."""
        found: set[tuple[int, int, int]] = set()  # class, window, template
        classes = sorted(set(self.levels))
        begin = np.searchsorted(owner, owner)  # place of the document's first shingle
        rank = np.arange(len(s)) - begin
        # pieces of two shingles that never cross documents: cut at even ranks
        cut = np.flatnonzero(rank % 2 == 0)
        for band in range(len(self.seeds)):
            low, level, at = np.minimum.reduceat(self.values(s, band), cut), 2, cut
            while True:
                doc, piece = owner[at], rank[at] // level
                if level in classes:
                    two = low.copy()
                    same = doc[1:] == doc[:-1]
                    two[:-1][same] = np.minimum(low[:-1], low[1:])[same]
                    table = np.zeros(TABLE, bool)
                    keys = {}
                    for t, lv in enumerate(self.levels):
                        if lv == level and len(self.sets[t]):
                            keys.setdefault(int(self.values(self.sets[t], band).min()), []).append(t)
                    table[[k & (TABLE - 1) for k in keys]] = True
                    for w in np.flatnonzero(table[two & np.uint32(TABLE - 1)]):
                        found.update((level, int(at[w]), t) for t in keys.get(int(two[w]), ()))
                if level >= classes[-1]:
                    break
                keep = np.flatnonzero(piece % 2 == 0)
                low, at, level = np.minimum.reduceat(low, keep), at[keep], level * 2
        for level, start, t in sorted(found):
            stop = min(start + 2 * level, int(np.searchsorted(owner, owner[start], side="right")))
            share = np.isin(self.sets[t], s[start:stop]).mean()
            if share >= self.floor:
                first = int(np.flatnonzero(np.isin(s[start:stop], self.sets[t]))[0])
                yield int(owner[start]), t, int(rank[start]) + first, float(share)


def scan(docs: DataFrame, templates: dict[str, str] = TEMPLATES, containment: float = 0.75, probability: float = 0.999, key: str = "doc_id", text: str = "text", at_once: int = 2 << 20) -> DataFrame:
    """key, license, n_matches (distinct places), first_word and containment (the best): a row for each document and template found in it."""
    ship(docs.sparkSession)
    library = docs.sparkSession.sparkContext.broadcast(Library.of(templates, containment, probability))
    kind = docs.schema[key].dataType.simpleString()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        lib = library.value
        for batch in batches:
            raw, offsets = utf8(batch.column(1))
            lo, rows, best = 0, batch.num_rows, {}
            while lo < rows:
                hi = max(lo + 1, int(np.searchsorted(offsets, offsets[lo] + at_once, side="right")) - 1)
                own = offsets[lo : hi + 1] - offsets[lo]
                h, doc, _ = words(raw[offsets[lo] : offsets[hi]], own, between=NOT_ALNUM)
                s, owner = shingles(h, doc, hi - lo)
                if len(s):
                    for d, t, place, share in lib.scan(s, owner):
                        places, top = best.setdefault((lo + d, t), ({}, 0.0))
                        places[place] = True
                        best[lo + d, t] = (places, max(top, share))
                lo = hi
            order = sorted(best)
            yield pa.RecordBatch.from_arrays(
                [batch.column(0).take(pa.array([d for d, _ in order], pa.int64())), pa.array([lib.names[t] for _, t in order], pa.string()), pa.array([len(best[k][0]) for k in order], pa.int64()), pa.array([min(best[k][0]) for k in order], pa.int64()), pa.array([best[k][1] for k in order], pa.float64())],
                ["key", "license", "n_matches", "first_word", "containment"],
            )

    return docs.select(F.col(key).alias("key"), F.col(text).cast("string")).mapInArrow(run, f"key {kind}, license string, n_matches long, first_word long, containment double").withColumnRenamed("key", key)
