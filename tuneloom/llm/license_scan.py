"""License scan: normalised text against license templates by Dice coefficient over word bigrams.

Units of comparison are each line, runs of lines, and the whole text. The score is 2 * shared / (bigrams of unit + bigrams of
template), as multisets. It can reach t only if the unit's size lies between t / (2 - t) and (2 - t) / t of the template's, and
only if it shares t / (2 - t) of the template's bigrams; so templates are kept by size, those that share too little with the
whole text fall out, and windows of lines of a possible size are scored for the rest. Of one template the window of highest
score is taken (the earliest and shortest of equals), and the search goes on before and behind it: licenses that follow each
other, or have foreign lines inside, are all found.

Edges: null and empty texts and an empty table give no rows; equal scores of several templates are all reported; a repeated
line or license is reported once for each place; repeated rows give repeated results; a null id stays null; long texts are
read whole.
"""

from __future__ import annotations

import re
from bisect import bisect_left, bisect_right
from collections import Counter
from importlib import resources
from pathlib import Path

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import batch_of, column, pieces

# Public license notices and texts, by identifier.
_WARRANTY_MIT = (
    'THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. '
    "IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE."
)
_WARRANTY_BSD = (
    'THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS "AS IS" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. '
    "IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) "
    "HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE."
)
_BSD_TWO = (
    "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: "
    "1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer. "
    "2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution. "
)
TEMPLATES = {
    "MIT/notice": ["Released under the MIT License.", "Licensed under the MIT License.", "This project is licensed under the terms of the MIT license."],
    "MIT/text": [
        "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, "
        "and to permit persons to whom the Software is furnished to do so, subject to the following conditions: The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software. " + _WARRANTY_MIT
    ],
    "ISC/text": [
        "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies. "
        'THE SOFTWARE IS PROVIDED "AS IS" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, '
        "WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE."
    ],
    "BSD-2-Clause/text": [_BSD_TWO + _WARRANTY_BSD],
    "BSD-3-Clause/text": [_BSD_TWO + "3. Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission. " + _WARRANTY_BSD],
    "BSD/notice": ["Licensed under the BSD License.", "Use of this source code is governed by a BSD-style license that can be found in the LICENSE file."],
    "Apache-2.0/notice": ["Licensed under the Apache License, Version 2.0.", "Released under the Apache License 2.0."],
    "Apache-2.0/header": [
        'Licensed under the Apache License, Version 2.0 (the "License"); you may not use this file except in compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0 '
        'Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an "AS IS" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. See the License for the specific language governing permissions and limitations under the License.'
    ],
    "GPL-3.0/notice": ["This work is licensed under the GNU General Public License, version 3.", "Licensed under the GNU General Public License v3.0."],
    "GPL-2.0/notice": ["This work is licensed under the GNU General Public License, version 2.", "Licensed under the GNU General Public License v2.0."],
    "LGPL-3.0/notice": ["This work is licensed under the GNU Lesser General Public License, version 3."],
    "AGPL-3.0/notice": ["This work is licensed under the GNU Affero General Public License, version 3."],
    "GPL-3.0/header": [
        "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version. "
        "This program is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE. See the GNU General Public License for more details. "
        "You should have received a copy of the GNU General Public License along with this program. If not, see https://www.gnu.org/licenses/."
    ],
    "MPL-2.0/header": ["This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can obtain one at https://mozilla.org/MPL/2.0/."],
    "CC-BY-4.0/short": ["Licensed under CC BY 4.0."],
    "CC-BY-SA-4.0/short": ["Licensed under CC BY-SA 4.0."],
    "CC-BY-NC-4.0/short": ["Licensed under CC BY-NC 4.0."],
    "CC-BY-ND-4.0/short": ["Licensed under CC BY-ND 4.0."],
    "CC-BY-NC-SA-4.0/short": ["Licensed under CC BY-NC-SA 4.0."],
    "CC0-1.0/short": ["Released under CC0 1.0."],
    "CC-BY-4.0/notice": ["This work is licensed under a Creative Commons Attribution 4.0 International License."],
    "CC-BY-SA-4.0/notice": ["This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License."],
    "Unlicense/text": [
        "This is free and unencumbered software released into the public domain. Anyone is free to copy, modify, publish, use, compile, sell, or distribute this software, either in source code form or as a compiled binary, for any purpose, commercial or non-commercial, and by any means."
    ],
}



def full_texts(folder: str | None = None) -> dict[str, list[str]]:
    """Templates from the text files of a folder, named after them; read where the query is made."""
    files = Path(folder).glob("*.txt") if folder else (f for f in resources.files(__package__).joinpath("license_texts").iterdir() if f.name.endswith(".txt"))
    return {f.name.removesuffix(".txt") + "/full": [f.read_text(encoding="utf-8")] for f in files}


_WORD = re.compile(r"[^\W_]+")


def words(text: str) -> list[str]:
    """Lower-case runs of letters and digits."""
    return _WORD.findall(text.lower())


def bigrams(w: list[str]) -> Counter:
    return Counter(zip(w, w[1:]))


class Templates:
    def __init__(self, texts: dict[str, list[str]], threshold: float):
        entries = sorted(((bigrams(words(t)), name) for name, all_ in texts.items() for t in all_), key=lambda x: x[0].total())
        self.entries, self.t = entries, threshold
        self.sizes = [c.total() for c, _ in entries]
        self.known = {g for c, _ in entries for g in c}
        #: bigram -> templates that have it, and how often
        self.uses: dict[tuple, list] = {}
        for i, (c, _) in enumerate(entries):
            for g, n in c.items():
                self.uses.setdefault(g, []).append((i, n))
        #: a bigram's first words: lines without any of them need no look
        self.heads = {a for a, _ in self.known}

    def bounds(self, size: int) -> range:
        low, high = size * self.t / (2 - self.t), size * (2 - self.t) / self.t
        return range(bisect_left(self.sizes, low - 1e-9), bisect_right(self.sizes, high + 1e-9))

    def score(self, w: list[str]):
        """(license, dice, whether none scores more) of the templates at or over the threshold."""
        size = len(w) - 1
        span = self.bounds(size) if size > 0 else ()
        if not span:
            return []
        shared = sum(g in self.known for g in zip(w, w[1:]))
        own = None
        out = {}
        for i in span:
            if 2 * shared < self.t * (size + self.sizes[i]):
                continue
            own = own or bigrams(w)
            c, name = self.entries[i]
            dice = 2 * sum(min(n, own[g]) for g, n in c.items() if g in own) / (size + self.sizes[i])
            if dice >= self.t:
                out[name] = max(dice, out.get(name, 0))
        top = max(out.values(), default=0)
        return [(name, dice, dice == top) for name, dice in sorted(out.items())]

    def windows(self, lines: list[list[str]], i: int):
        """(dice, first, last) of the windows of whole lines that meet template i, each the best of what the ones before leave."""
        own, size = self.entries[i][0], self.sizes[i]
        low, high = size * self.t / (2 - self.t), size * (2 - self.t) / self.t
        flat = [x for w in lines for x in w]
        starts = [0]
        for w in lines:
            starts.append(starts[-1] + len(w))
        hit = [0]  # bigrams of the template up to each word
        for g in zip(flat, flat[1:]):
            hit.append(hit[-1] + (g in own))
        least = self.t * (low + size) / 2
        found, todo = [], [(0, len(lines))]
        while todo:
            lo, hi = todo.pop()
            best = None
            for a in range(lo, hi):
                at = starts[a]
                stop = min(starts[hi], at + int(high) + 1)  # words of the longest window
                if stop - at < 2 or hit[stop - 1] - hit[at] < least - 1e-9:
                    continue
                counts, shared, done = Counter(), 0, at
                for b in range(a, hi):
                    end = starts[b + 1]
                    if end - at - 1 > high + 1e-9:
                        break
                    for j in range(done, end - 1):
                        g = flat[j], flat[j + 1]
                        if (n := own.get(g)) and counts[g] < n:
                            shared += 1
                        counts[g] += 1
                    done = max(done, end - 1)
                    n = end - at - 1
                    if n >= low - 1e-9 and n > 0:
                        dice = 2 * shared / (n + size)
                        if dice >= self.t and (best is None or dice > best[0]):
                            best = dice, a, b
            if best:
                found.append(best)
                todo += [(lo, best[1]), (best[2] + 1, hi)]
        return found

    def scan(self, text: str):
        """(unit, first line, last line, license, dice, best) rows of a text."""
        rows, lines, places = [], text.split("\n"), []
        heads, known = self.heads, self.known
        kept, looked = [], False
        for no, line in enumerate(lines):
            if not (w := words(line)):
                continue
            kept.append(w)
            places.append(no)
            if not heads.isdisjoint(w):
                looked = True
                rows.extend(("line", no, no, *hit) for hit in self.score(w))
        if not looked:
            return rows
        every = [x for w in kept for x in w]
        if len(lines) > 1:  # a text too large for every template has no template inside its size bounds
            rows.extend(("text", 0, len(lines) - 1, *hit) for hit in self.score(every))
        if len(kept) > 1:
            counts = Counter(g for g in zip(every, every[1:]) if g in known)
            shared: Counter = Counter()
            for g, n in counts.items():
                for i, m in self.uses[g]:
                    shared[i] += min(n, m)
            blocks = []
            for i, n in shared.items():
                if n >= self.t / (2 - self.t) * self.sizes[i] - 1e-9:
                    blocks += [(places[a], places[b], dice, self.entries[i][1]) for dice, a, b in self.windows(kept, i) if b > a]
            top: dict[tuple, float] = {}
            for a, b, dice, name in blocks:
                top[a, b, name] = max(dice, top.get((a, b, name), 0))
            for (a, b, name), dice in sorted(top.items()):
                # no other license scores more on lines that this one covers
                first = all(d <= dice for (x, y, _), d in top.items() if x <= b and y >= a)
                rows.append(("block", a, b, name, dice, first))
        return rows


def scan(docs: DataFrame, threshold: float = 0.8, templates: dict[str, list[str]] | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, unit, first_line, last_line, license, dice, best): every unit of every text that meets a template; best marks
    the highest score of a unit. templates: name -> texts; without any, the notices above and the full texts beside this file."""
    out = pa.schema([("doc_id", pa.int64()), ("unit", pa.string()), ("first_line", pa.int64()), ("last_line", pa.int64()), ("license", pa.string()), ("dice", pa.float64()), ("best", pa.bool_())])
    texts = templates or TEMPLATES | full_texts()

    def run(batches):
        known = Templates(texts, threshold)
        for batch in pieces(batches, "body"):
            rows = [(doc, *r) for doc, t in zip(column(batch, "doc_id"), column(batch, "body")) if t for r in known.scan(t)]
            if rows:
                yield batch_of(out, list(zip(*rows)))

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("body")).mapInArrow(run, "doc_id long, unit string, first_line long, last_line long, license string, dice double, best boolean")
