"""License scans: normalised text against license templates by the Dice coefficient over word bigrams.

Compared are the whole text, each paragraph and each line of a document; then, for each template with enough of its
bigrams in the document, runs of consecutive sentences and lines, and windows of the template's own number of words.
Of runs and windows that overlap, the one of highest Dice stays (of equal ones the longest), unless it overlaps a
matching unit of the first kind that bears its name or scores as much. A unit's and a template's bigrams are
sets; Dice is twice the shared ones over the sum of both sizes. It can only reach ``least`` if the sizes lie
within a factor of (2 - least) / least of each other, so a unit meets only templates in that range, found by
bisection in the list of templates by size. Each template also has anchor words, without all of which too few of
its bigrams are left; a document or unit that has no anchor of any template is passed over at once.

Defined results: null and empty texts match nothing; of equal scores the template that comes first by name wins;
texts of one word have no bigrams and match nothing; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import math
import re
from bisect import bisect_left, bisect_right
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import table, whole_text

LEAST = 0.9
WORD = re.compile(r"[^\W_]+")
# fixed values: short notices and license texts as published
NOTICES = {
    "MIT": ["Released under the MIT License.", "Licensed under the MIT License.", "This work is licensed under the MIT License.", "This project is licensed under the terms of the MIT license."],
    "Apache-2.0": ["Licensed under the Apache License, Version 2.0.", "Released under the Apache License, Version 2.0.", "This work is licensed under the Apache License, Version 2.0."],
    "GPL-3.0": ["This work is licensed under the GNU General Public License, version 3.", "Licensed under the GNU General Public License, version 3.", "Released under the GNU General Public License, version 3."],
    "GPL-2.0": ["This work is licensed under the GNU General Public License, version 2.", "Licensed under the GNU General Public License, version 2."],
    "LGPL-3.0": ["This work is licensed under the GNU Lesser General Public License, version 3."],
    "CC-BY-4.0": ["Licensed under CC BY 4.0.", "This work is licensed under a Creative Commons Attribution 4.0 International License."],
    "CC-BY-SA-4.0": ["Licensed under CC BY-SA 4.0.", "This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License."],
    "CC-BY-NC-4.0": ["Licensed under CC BY-NC 4.0.", "This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International License."],
    "CC-BY-ND-4.0": ["Licensed under CC BY-ND 4.0."],
    "CC0-1.0": ["Released under CC0 1.0.", "To the extent possible under law, the author has waived all copyright and related or neighboring rights to this work."],
    "MPL-2.0": ["This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can obtain one at http://mozilla.org/MPL/2.0/."],
    "BSD-3-Clause": ["Released under the BSD 3-Clause License.", "Licensed under the BSD 3-Clause License."],
}
TEXTS = {
    "BSD-2-Clause": "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met:\n\n1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer.\n\n2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution.\n\nTHIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS \"AS IS\" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE.",
    "BSD-3-Clause": "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met:\n\n1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer.\n\n2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution.\n\n3. Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission.\n\nTHIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS \"AS IS\" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE.",
    "Zlib": "This software is provided 'as-is', without any express or implied warranty. In no event will the authors be held liable for any damages arising from the use of this software.\n\nPermission is granted to anyone to use this software for any purpose, including commercial applications, and to alter it and redistribute it freely, subject to the following restrictions:\n\n1. The origin of this software must not be misrepresented; you must not claim that you wrote the original software. If you use this software in a product, an acknowledgment in the product documentation would be appreciated but is not required.\n\n2. Altered source versions must be plainly marked as such, and must not be misrepresented as being the original software.\n\n3. This notice may not be removed or altered from any source distribution.",
    "Unlicense": "This is free and unencumbered software released into the public domain.\n\nAnyone is free to copy, modify, publish, use, compile, sell, or distribute this software, either in source code form or as a compiled binary, for any purpose, commercial or non-commercial, and by any means.\n\nIn jurisdictions that recognize copyright laws, the author or authors of this software dedicate any and all copyright interest in the software to the public domain. We make this dedication for the benefit of the public at large and to the detriment of our heirs and successors. We intend this dedication to be an overt act of relinquishment in perpetuity of all present and future rights to this software under copyright law.\n\nTHE SOFTWARE IS PROVIDED \"AS IS\", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE.\n\nFor more information, please refer to <https://unlicense.org>",
    "BSL-1.0": "Permission is hereby granted, free of charge, to any person or organization obtaining a copy of the software and accompanying documentation covered by this license (the \"Software\") to use, reproduce, display, distribute, execute, and transmit the Software, and to prepare derivative works of the Software, and to permit third-parties to whom the Software is furnished to do so, all subject to the following:\n\nThe copyright notices in the Software and this entire statement, including the above license grant, this restriction and the following disclaimer, must be included in all copies of the Software, in whole or in part, and all derivative works of the Software, unless such copies or derivative works are solely in the form of machine-executable object code generated by a source language processor.\n\nTHE SOFTWARE IS PROVIDED \"AS IS\", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE, TITLE AND NON-INFRINGEMENT. IN NO EVENT SHALL THE COPYRIGHT HOLDERS OR ANYONE DISTRIBUTING THE SOFTWARE BE LIABLE FOR ANY DAMAGES OR OTHER LIABILITY, WHETHER IN CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE.",
    "MIT": "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions:\n\nThe above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software.\n\nTHE SOFTWARE IS PROVIDED \"AS IS\", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE.",
    "ISC": "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies.\n\nTHE SOFTWARE IS PROVIDED \"AS IS\" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE.",
    "Apache-2.0": "Licensed under the Apache License, Version 2.0 (the \"License\"); you may not use this file except in compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0 Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an \"AS IS\" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. See the License for the specific language governing permissions and limitations under the License.",
    "GPL-3.0": "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version. This program is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE. See the GNU General Public License for more details. You should have received a copy of the GNU General Public License along with this program. If not, see https://www.gnu.org/licenses/.",
}


def bigrams(text: str) -> set[tuple[str, str]]:
    """Word bigrams of the normalised text: lower case, words of letters and digits."""
    words = WORD.findall(text.lower())
    return set(zip(words, words[1:]))


class Templates:
    """Templates by size, with an index from bigram to templates."""

    def __init__(self, least: float = LEAST, templates: list[tuple[str, str]] | None = None):
        self.least = least
        given = templates if templates is not None else [(n, t) for n, ts in NOTICES.items() for t in ts] + list(TEXTS.items())
        kept = sorted(((len(g), n, g, len(WORD.findall(t.lower()))) for n, t in given if (g := bigrams(t))), key=lambda x: (x[0], x[1]))
        self.items, self.lengths = [x[:3] for x in kept], [x[3] for x in kept]
        self.sizes = [x[0] for x in self.items]
        self.anchors = frozenset().union(*(self._anchors(g) for _, _, g in self.items))
        self.index: dict[tuple[str, str], list[int]] = {}
        for i, (_, _, g) in enumerate(self.items):
            for b in g:
                self.index.setdefault(b, []).append(i)
        #: fewest shared bigrams that can reach ``least``
        self.needs = [math.ceil(least * n / (2 - least) - 1e-9) for n in self.sizes]

    def _anchors(self, grams: set[tuple[str, str]]) -> set[str]:
        """Words of a template, the longest first, until a unit with none of them cannot reach ``least``."""
        found, left = set(), set(grams)
        for w in sorted({w for g in grams for w in g}, key=lambda w: (-len(w), w)):
            if len(left) < self.least * len(grams) / (2 - self.least) - 1e-9:
                break
            found.add(w)
            left = {g for g in left if w not in g}
        return found

    def range_of(self, size: int) -> tuple[int, int]:
        """The templates that a unit of this many bigrams can reach ``least`` with."""
        factor = (2 - self.least) / self.least
        return bisect_left(self.sizes, size / factor - 1e-9), bisect_right(self.sizes, size * factor + 1e-9)

    def best(self, unit: set[tuple[str, str]]) -> tuple[float, str] | None:
        """The best (Dice, name) of at least ``least``."""
        low, high = self.range_of(len(unit))
        if low >= high:
            return None
        shared: dict[int, int] = {}
        for b in unit & self.index.keys() if len(unit) < len(self.index) else [x for x in self.index if x in unit]:
            for i in self.index[b]:
                if low <= i < high:
                    shared[i] = shared.get(i, 0) + 1
        found = [(-2 * n / (len(unit) + self.sizes[i]), self.items[i][1]) for i, n in shared.items()]
        hit = min(found, default=None)
        return (-hit[0], hit[1]) if hit and -hit[0] >= self.least - 1e-12 else None

    def scan(self, text: str) -> list[tuple[float, str, int, int]]:
        """(Dice, name, begin, end) of every unit of the text that matches, in order of place; the whole text first."""
        if self.anchors.isdisjoint(WORD.findall(text.lower())):
            return []
        spans = {(0, len(text))}
        for cut in (r"\n[ \t]*\n\s*", r"\n"):
            at = 0
            for m in [*re.finditer(cut, text), None]:
                end = m.start() if m else len(text)
                spans.add((at, end))
                at = m.end() if m else end
        out = []
        for begin, end in sorted(spans, key=lambda s: (s[0], -s[1])):
            words = WORD.findall(text[begin:end].lower())
            if not self.anchors.isdisjoint(words) and (hit := self.best(set(zip(words, words[1:])))):
                out.append((*hit, begin, end))
        return out + self._within(text, out)

    def _within(self, text: str, found: list[tuple[float, str, int, int]]) -> list[tuple[float, str, int, int]]:
        """Matches inside the text whose bounds are no bounds of paragraphs or lines."""
        at = [(m.start(), m.end()) for m in WORD.finditer(text)]
        words = [w.lower() for w in WORD.findall(text)]
        grams = list(zip(words, words[1:]))
        places: dict[int, list[int]] = {}
        for p, g in enumerate(grams):
            for i in self.index.get(g, ()):
                places.setdefault(i, []).append(p)
        # the first words of sentences and lines, and the end
        begins = sorted({bisect_left(at, (m.end(), -1)) for m in re.finditer(r"[.!?:;]+[\s\"')\]]+|\n", text)} | {0, len(words)})
        hits = set()
        for i, ps in places.items():
            size, name, wanted = self.items[i]
            need, most = self.needs[i], size * (2 - self.least) / self.least + 1e-9
            if len({grams[p] for p in ps}) < need:
                continue
            dice = lambda unit: 2 * len(unit & wanted) / (len(unit) + size)  # noqa: E731, B023
            length = self.lengths[i]
            for k, p in enumerate(ps):  # windows of as many words as the template
                if k + need <= len(ps) and ps[k + need - 1] < p + length - 1:
                    stop = min(p + length, len(words))
                    if (d := dice(set(grams[p : stop - 1]))) >= self.least - 1e-12:
                        hits.add((d, name, p, stop))
            for k, b in enumerate(begins[:-1]):  # runs of sentences and lines
                j = bisect_left(ps, b)
                if j + need > len(ps) or k + 1 < len(begins) and ps[j] >= begins[k + 1]:
                    continue
                unit: set[tuple[str, str]] = set()
                for last, e in zip(begins[k:], begins[k + 1 :]):
                    unit.update(grams[max(b, last - 1) : e - 1])
                    if len(unit) > most:
                        break
                    if len(unit) >= need and (d := dice(unit)) >= self.least - 1e-12:
                        hits.add((d, name, b, e))
        out, taken = [], []
        for d, name, p, stop in sorted(hits, key=lambda h: (-h[0], h[2] - h[3], h[2], h[1])):
            begin, end = at[p][0], at[stop - 1][1]
            if any(begin < e and b < end for b, e in taken) or any(begin < e and b < end and (n == name or x >= d) for x, n, b, e in found):
                continue
            taken.append((begin, end))
            out.append((d, name, begin, end))
        return sorted(out, key=lambda h: h[2:])


def scanned(docs: DataFrame, least: float = LEAST) -> DataFrame:
    """doc_id, license (the best match or null), dice, n_notices, licenses (all names found, sorted)."""
    schema = "doc_id long, license string, dice double, n_notices long, licenses array<string>"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        templates = Templates(least)
        for b in batches:
            out = [[], [], [], []]
            for text in b.column("text").to_pylist():
                hits = templates.scan(text)
                top = min(((-h[0], h[1]) for h in hits), default=None)
                for column, x in zip(out, (top and top[1], -top[0] if top else 0.0, len({h[2:] for h in hits}), sorted({h[1] for h in hits}))):
                    column.append(x)
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array(out[0], pa.string()), pa.array(out[1], pa.float64()), pa.array(out[2], pa.int64()), pa.array(out[3], pa.list_(pa.string()))], ["doc_id", "license", "dice", "n_notices", "licenses"])

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), whole_text().alias("text")).mapInArrow(run, schema)


def op8_licenses(spark, sf_dir: str) -> DataFrame:
    return scanned(table(spark, sf_dir, "documents"))
