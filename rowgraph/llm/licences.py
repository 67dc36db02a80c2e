"""Licence scans: windows of a normalised text against licence templates, by Dice coefficient over word bigrams.

Windows are all runs of words, so lines, paragraphs and whole texts are among them.  Of a template with s bigrams only
windows of t / (2 - t) * s to (2 - t) / t * s bigrams can reach the threshold t, and the best begin and end with one of
its bigrams; so only a text that has enough of a template's bigrams near each other is looked at.
A window that has other version or clause words than a template is of another licence, however alike the rest is.
The plainer scan by units (lines, paragraphs, whole text) goes by the coefficient alone, so it names near relatives too.
"""

from __future__ import annotations

import bisect
import re
from collections import Counter
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame

from .shared import clean_columns

#: Least Dice coefficient of a match, in percent.
MIN_PERCENT = 80

# Public licence texts and the notices in common use.
_GNU = (
    "This program is free software: you can redistribute it and/or modify it under the terms of the GNU {0}General Public License as published by the Free Software Foundation, either version {1} of the License, or (at your option) any later version. "
    "This program is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE. See the GNU {0}General Public License for more details. "
    "You should have received a copy of the GNU {0}General Public License along with this {2}. If not, see <https://www.gnu.org/licenses/>."
)


def _gnu(kind: str, version: str) -> list[str]:
    notice = _GNU.format(kind, version, "program")
    return [f"This work is licensed under the GNU {kind}General Public License, version {version}.", notice] + ([notice.replace("program", "library")] if kind == "Lesser " else [])


def _commons(short: str, long: str) -> list[str]:
    return [f"Licensed under CC {short} 4.0.", f"This work is licensed under a Creative Commons {long} 4.0 International License."]


TEMPLATES: dict[str, list[str]] = {
    "AGPL-3.0": _gnu("Affero ", "3"),
    "Apache-2.0": [
        "Licensed under the Apache License, Version 2.0.",
        'Licensed under the Apache License, Version 2.0 (the "License"); you may not use this file except in compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0 '
        'Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an "AS IS" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. '
        "See the License for the specific language governing permissions and limitations under the License.",
    ],
    "BSD-2-Clause": [
        "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: "
        "1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer. "
        "2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution. "
        'THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS "AS IS" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. '
        "IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) "
        "HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE.",
    ],
    "CC-BY-4.0": ["Licensed under CC BY 4.0.", "This work is licensed under a Creative Commons Attribution 4.0 International License."],
    "CC-BY-NC-4.0": ["Licensed under CC BY-NC 4.0.", "This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International License."],
    "CC-BY-NC-ND-4.0": _commons("BY-NC-ND", "Attribution-NonCommercial-NoDerivatives"),
    "CC-BY-NC-SA-4.0": _commons("BY-NC-SA", "Attribution-NonCommercial-ShareAlike"),
    "CC-BY-ND-4.0": _commons("BY-ND", "Attribution-NoDerivatives"),
    "CC-BY-SA-4.0": _commons("BY-SA", "Attribution-ShareAlike"),
    "GPL-2.0": _gnu("", "2"),
    "GPL-3.0": [
        "This work is licensed under the GNU General Public License, version 3.",
        "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version. "
        "This program is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE. See the GNU General Public License for more details. "
        "You should have received a copy of the GNU General Public License along with this program. If not, see <https://www.gnu.org/licenses/>.",
    ],
    "ISC": [
        "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies. "
        'THE SOFTWARE IS PROVIDED "AS IS" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. '
        "IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE.",
    ],
    "LGPL-2.1": _gnu("Lesser ", "2.1"),
    "LGPL-3.0": _gnu("Lesser ", "3"),
    "MIT": [
        "Released under the MIT License.",
        'Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the "Software"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, '
        "and to permit persons to whom the Software is furnished to do so, subject to the following conditions: The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software. "
        'THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. '
        "IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE.",
    ],
    "MPL-2.0": [
        "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can obtain one at https://mozilla.org/MPL/2.0/."
    ],
    "Zlib": [
        "This software is provided 'as-is', without any express or implied warranty. In no event will the authors be held liable for any damages arising from the use of this software. "
        "Permission is granted to anyone to use this software for any purpose, including commercial applications, and to alter it and redistribute it freely, subject to the following restrictions: "
        "1. The origin of this software must not be misrepresented; you must not claim that you wrote the original software. If you use this software in a product, an acknowledgment in the product documentation would be appreciated but is not required. "
        "2. Altered source versions must be plainly marked as such, and must not be misrepresented as being the original software. 3. This notice may not be removed or altered from any source distribution.",
    ],
}

_CLAUSE = "Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission. "
TEMPLATES["BSD-3-Clause"] = [t.replace("THIS SOFTWARE IS", f"3. {_CLAUSE}THIS SOFTWARE IS", 1) for t in TEMPLATES["BSD-2-Clause"]]

#: Words that tell near relatives apart, whatever the template.
CLAUSES = frozenset(b"lesser library affero sharealike sa noncommercial nc noderivatives noderivs nd endorse advertising".split())
#: Digits are versions in these; elsewhere they may number the clauses.
VERSIONED = ("AGPL", "Apache", "CC-", "GPL", "LGPL", "MPL")
_DIGITS = frozenset(b"%d" % k for k in range(10))

_TOKEN = re.compile(rb"[a-z0-9]+")
_BLANK = re.compile(rb"\n[ \t\r]*\n")


def normal_words(text: bytes) -> list[bytes]:
    """Runs of ASCII letters and digits, lower case; everything else parts them."""
    return _TOKEN.findall(text.lower())


class Matcher:
    def __init__(self, templates: dict[str, list[str]] | None = None, min_percent: int = MIN_PERCENT):
        known = TEMPLATES if templates is None else templates
        made = [(name, Counter(zip(w, w[1:], strict=False))) for name, texts in known.items() for t in texts if len(w := normal_words(t.encode())) > 1]
        self.made = sorted(((sum(c.values()), name, c) for name, c in made), key=lambda x: (x[0], x[1]))
        self.sizes = [m[0] for m in self.made]
        self.pairs = {b for _, _, c in self.made for b in c}
        self.percent = min_percent
        p, self.where, self.need, self.most, self.guards = min_percent, {}, [], [], []
        for k, (size, name, c) in enumerate(self.made):
            for x in c:
                self.where.setdefault(x, []).append(k)
            # shared bigrams that the smallest window must have, and bigrams of the largest window
            self.need.append(-(-p * (-(-p * size // (200 - p)) + size) // 200))
            self.most.append((200 - p) * size // p)
            guard = CLAUSES | _DIGITS if name.startswith(VERSIONED) else CLAUSES
            self.guards.append((guard, {w for x in c for w in x if w in guard}))

    def candidates(self, b: int) -> list[tuple]:
        """Templates whose size can reach the threshold against b bigrams."""
        p = self.percent
        return self.made[bisect.bisect_left(self.sizes, -(-p * b // (200 - p))) : bisect.bisect_right(self.sizes, (200 - p) * b // p)]

    def match(self, words: list[bytes]) -> list[tuple[str, float]]:
        """(licence, coefficient) of templates at or above the threshold."""
        b = len(words) - 1
        if b < 1 or not (near := self.candidates(b)):
            return []
        shared = [x for x in zip(words, words[1:], strict=False) if x in self.pairs]
        if 200 * len(shared) < self.percent * (b + near[0][0]):
            return []
        mine, out = Counter(shared), []
        for size, name, theirs in near:
            both = sum(min(n, theirs[x]) for x, n in mine.items() if x in theirs)
            if 200 * both >= self.percent * (b + size):
                out.append((name, 2.0 * both / (b + size)))
        return out

    def units(self, text: bytes) -> list[tuple[str, float]]:
        """(licence, coefficient) of every match of a line, of a paragraph of several lines (cut at blank lines) or of the whole text."""
        lines = [normal_words(x) for x in text.split(b"\n")]
        found = [m for w in lines for m in self.match(w)]
        if len(lines) > 1:
            for part in _BLANK.split(text):
                found += self.match(normal_words(part)) if b"\n" in part else []
            # only a whole text that a template's size can reach
            if self.made and sum(map(len, lines)) - 1 <= (200 - self.percent) * self.sizes[-1] // self.percent:
                found += self.match([w for line in lines for w in line])
        return found

    def scan(self, text: bytes) -> list[tuple[str, float]]:
        """(licence, coefficient) of the best window of each template that has one at or above the threshold."""
        words = normal_words(text)
        hits: dict[int, list[int]] = {}
        for at, x in enumerate(zip(words, words[1:], strict=False)):
            if x in self.where:
                for k in self.where[x]:
                    hits.setdefault(k, []).append(at)
        marked = None
        out = []
        for k, places in hits.items():
            need, most = self.need[k], self.most[k]
            if len(places) < need:
                continue
            starts = [i for i in range(len(places) - need + 1) if places[i + need - 1] - places[i] < most]
            if not starts:
                continue
            if marked is None:
                marked = [at for at, w in enumerate(words) if w in CLAUSES or w in _DIGITS]
            best = self._best(k, words, places, starts, marked)
            if best:
                out.append((self.made[k][1], best))
        return out

    def _best(self, k: int, words: list[bytes], places: list[int], starts: list[int], marked: list[int]) -> float:
        size, _, theirs = self.made[k]
        guard, wanted = self.guards[k]
        best, p = 0.0, self.percent
        for i in starts:
            lo, both, seen = places[i], 0, {}
            for j in range(i, len(places)):
                b = places[j] - lo + 1
                if b > self.most[k]:
                    break
                x = (words[places[j]], words[places[j] + 1])
                n = seen.get(x, 0)
                if n >= theirs[x]:
                    continue
                seen[x] = n + 1
                both += 1
                if 200 * both >= p * (b + size) and 2.0 * both / (b + size) > best:
                    inside = marked[bisect.bisect_left(marked, lo) : bisect.bisect_right(marked, lo + b)]
                    if {words[at] for at in inside if words[at] in guard} == wanted:
                        best = 2.0 * both / (b + size)
            if best == 1.0:
                break
        return best


def scan_licences(docs: DataFrame, min_percent: int = MIN_PERCENT, units: bool = False) -> DataFrame:
    """doc_id, licence, dice, licences of every row.

    ``licence`` is that of the best match (ties: first by name) and ``dice`` its coefficient, null and 0 without one;
    ``licences`` lists all that match, by name, joined by commas.  Null and empty texts match nothing.  Each row stands
    for itself, so repeated rows give equal rows.  Other columns are ignored.  All windows are compared; with ``units``
    lines, paragraphs and whole texts, by the coefficient alone.
    """
    rows = clean_columns(docs, "doc_id", "text")
    rows = rows.select(rows["doc_id"].cast("long").alias("doc_id"), "text")
    schema = pa.schema([("doc_id", pa.int64()), ("licence", pa.string()), ("dice", pa.float64()), ("licences", pa.string())])

    def run(batches: Iterator[pa.RecordBatch]):
        matcher = Matcher(min_percent=min_percent)
        look = matcher.units if units else matcher.scan
        for batch in batches:
            best, score, names = [], [], []
            for text in batch.column(1):
                found = look((text.as_py() or "").encode())
                top = min(found, key=lambda m: (-m[1], m[0]), default=(None, 0.0))
                best.append(top[0])
                score.append(top[1])
                names.append(",".join(sorted({m[0] for m in found})))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(best, pa.string()), pa.array(score, pa.float64()), pa.array(names, pa.string())], schema=schema)

    return rows.mapInArrow(run, "doc_id long, licence string, dice double, licences string")
