"""License scans: an inverted index of winnowed template fingerprints, then banded alignment.

Templates and texts are read as words (runs of ASCII letters and digits, lower-cased).  Of a template's hashes of GRAM
words, winnowing keeps the smallest of each WINDOW neighbouring ones; they form the index, hash -> (template, place).
A text's hashes are looked up at every place, so a passage that shares GRAM + WINDOW - 1 words with a template is found.
Look-ups of one template on neighbouring diagonals are one candidate; the words around it are aligned with the template
within BAND words of its diagonal (match 1, mismatch and gap -1 each, free ends in the text).  Matched words over the
template's words is the coverage; the span runs from the first matched word to the last, in code points.  What lies
before and after a match in its candidate is aligned again, without the matched words, until no match is left, so that
notices that repeat close together are all found.

Matches that cover LEAST of a template or more are reported with their coverage, the best first where they overlap; those
of COVERAGE or more are marked as matched.  Null and empty texts have none; each row of a table is scanned by itself, so
rows that repeat have the same matches, and an empty table has none.  Every place of a text is looked up and every
candidate aligned; the templates are a fixed, small set or the caller's own.  Of equal matches that overlap, the first
in the text, then the first template stays.
"""

from __future__ import annotations

import re
from bisect import bisect_left
from collections import defaultdict

import numpy as np
import xxhash
from pyspark.sql import DataFrame

from .base import arrow_map

GRAM, WINDOW, BAND = 3, 2, 12
#: Coverage from which a match counts as the license, and the least that is reported.
COVERAGE, LEAST = 0.8, 0.3
WORD = re.compile(r"[A-Za-z0-9]+")

#: Parts that two licenses share.
_REDISTRIBUTION = "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution."
_AS_IS = "THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS \"AS IS\" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE."
#: Short notices, and the bodies of short licenses.
TEMPLATES: dict[str, tuple[str, ...]] = {
    "MIT": (
        "Released under the MIT License",
        "Licensed under the MIT License",
        "This project is licensed under the terms of the MIT license",
        "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions: The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software. THE SOFTWARE IS PROVIDED \"AS IS\", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE.",
    ),
    "Apache-2.0": (
        "Licensed under the Apache License, Version 2.0",
        "you may not use this file except in compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0 Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an \"AS IS\" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. See the License for the specific language governing permissions and limitations under the License.",
    ),
    "GPL-3.0": (
        "licensed under the GNU General Public License, version 3",
        "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version.",
    ),
    "GPL-2.0": (
        "licensed under the GNU General Public License, version 2",
        "This program is free software; you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation; either version 2 of the License, or (at your option) any later version.",
    ),
    "LGPL-3.0": ("licensed under the GNU Lesser General Public License, version 3",),
    "AGPL-3.0": ("licensed under the GNU Affero General Public License, version 3",),
    "MPL-2.0": ("This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can obtain one at http://mozilla.org/MPL/2.0/.",),
    "BSD-2-Clause": (
        "Licensed under the BSD 2-Clause License",
        f"{_REDISTRIBUTION} {_AS_IS}",
    ),
    "BSD-3-Clause": (
        "Licensed under the BSD 3-Clause License",
        f"{_REDISTRIBUTION} Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission. {_AS_IS}",
    ),
    "ISC": ("Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies. THE SOFTWARE IS PROVIDED \"AS IS\" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE.",),
    "Zlib": ("This software is provided 'as-is', without any express or implied warranty. In no event will the authors be held liable for any damages arising from the use of this software. Permission is granted to anyone to use this software for any purpose, including commercial applications, and to alter it and redistribute it freely, subject to the following restrictions: 1. The origin of this software must not be misrepresented; you must not claim that you wrote the original software. If you use this software in a product, an acknowledgment in the product documentation would be appreciated but is not required. 2. Altered source versions must be plainly marked as such, and must not be misrepresented as being the original software. 3. This notice may not be removed or altered from any source distribution.",),
    "BSL-1.0": ("Boost Software License - Version 1.0 - August 17th, 2003", "Distributed under the Boost Software License, Version 1.0."),
    "Unlicense": ("This is free and unencumbered software released into the public domain. Anyone is free to copy, modify, publish, use, compile, sell, or distribute this software, either in source code form or as a compiled binary, for any purpose, commercial or non-commercial, and by any means.",),
    "CC-BY-4.0": ("Licensed under CC BY 4.0", "This work is licensed under a Creative Commons Attribution 4.0 International License"),
    "CC-BY-SA-4.0": ("Licensed under CC BY-SA 4.0", "This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License"),
    "CC-BY-NC-4.0": ("Licensed under CC BY-NC 4.0", "This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International License"),
    "CC0-1.0": ("released under CC0 1.0 Universal", "To the extent possible under law, the author has waived all copyright and related or neighboring rights to this work"),
}


def words_of(text: str) -> list[str]:
    return WORD.findall(text.lower() if text.isascii() else text.encode("utf-8", "surrogatepass").lower().decode("utf-8", "surrogatepass"))


def winnow(words: list[str], gram: int = GRAM, window: int = WINDOW) -> dict[int, int]:
    """place -> hash of the kept fingerprints; of equal smallest ones the rightmost, as the method has it."""
    n = len(words) - gram + 1
    h = [xxhash.xxh32_intdigest(" ".join(words[i : i + gram])) for i in range(n)]
    kept = {}
    for i in range(max(1, n - window + 1)):
        part = h[i : i + window]
        if part:
            j = max(k for k, x in enumerate(part) if x == min(part))
            kept[i + j] = part[j]
    return kept


def align(text: list[str], template: list[str], offset: int, band: int = BAND) -> tuple[int, int, int]:
    """(matched words, first matched place, place after the last) of the best alignment near a diagonal.

    Row i is template word i, column k text word i + offset - band + k.
    """
    width, m = 2 * band + 1, len(template)
    low = -(1 << 20)
    score = np.full((m + 1, width + 2), low)
    score[0] = 0
    move = np.zeros((m + 1, width + 2), np.int8)  # 1 diagonal match, 2 diagonal mismatch, 3 word missing, 4 word added
    n = len(text)
    for i in range(1, m + 1):
        w, prev, row, mv = template[i - 1], score[i - 1], score[i], move[i]
        base = i - 1 + offset - band
        for k in range(width):
            j = base + k
            best, how = prev[k + 1] - 1, 3
            if 0 <= j < n:
                d = prev[k] + (1 if text[j] == w else -1)
                if d >= best:
                    best, how = d, 1 if text[j] == w else 2
                if k and row[k - 1] - 1 > best:
                    best, how = row[k - 1] - 1, 4
            row[k], mv[k] = best, how
    k, i, matched, first, last = int(np.argmax(score[m][:width])), m, 0, -1, -1
    while i > 0:
        how, j = move[i][k], i - 1 + offset - band + k
        if how == 1:
            matched, first, last = matched + 1, j, last if last >= 0 else j
            i -= 1
        elif how == 2:
            i -= 1
        elif how == 3:
            i, k = i - 1, k + 1
        else:
            k -= 1
    return matched, first, last + 1


class Scanner:
    def __init__(self, templates: dict[str, tuple[str, ...]], gram: int = GRAM, window: int = WINDOW, band: int = BAND, least: float = LEAST):
        self.names, self.bodies = [], []
        self.index: dict[int, list[tuple[int, int]]] = defaultdict(list)
        #: The first two words of every fingerprint: most places of a text are passed over by these.
        self.pairs: set[tuple[str, str]] = set()
        self.gram, self.band, self.least = gram, band, least
        for name, bodies in templates.items():
            for body in bodies:
                words = words_of(body)
                if len(words) < gram:
                    continue
                for at, h in winnow(words, gram, window).items():
                    self.index[h].append((len(self.bodies), at))
                    self.pairs.add((words[at], words[at + 1]))
                self.names.append(name)
                self.bodies.append(words)
        self.index = dict(self.index)

    def matches(self, words: list[str], t: int, group: list[tuple[int, int]]) -> list[tuple[float, int, int, int]]:
        """(coverage, matched words, first place, place after the last) of every match of a candidate's seeds (diagonal, place)."""
        out, body, todo, rest = [], self.bodies[t], [group], words
        while todo:
            now = todo.pop()
            middle = sorted(d for d, _ in now)[len(now) // 2]
            matched, first, last = align(rest, body, middle, self.band)
            if matched and (cover := matched / len(body)) >= self.least:
                out.append((cover, matched, first, last))
                rest = list(words) if rest is words else rest
                rest[first:last] = [None] * (last - first)
                parts = [s for s in now if s[1] < first], [s for s in now if s[1] >= last]
            else:
                parts = ([s for s in now if abs(s[0] - middle) > self.band],)
            todo += [part for part in parts if part]
        return out

    def scan(self, text: str | None) -> list[tuple[str, float, int, int]]:
        """(license, coverage, start, end) in code points, by start."""
        if not text:
            return []
        words, index, pairs, gram = words_of(text), self.index, self.pairs, self.gram
        seeds: dict[int, list[tuple[int, int]]] = defaultdict(list)
        for i, pair in enumerate(zip(words, words[1:], strict=False)):
            if pair in pairs and i + gram <= len(words) and (hit := index.get(xxhash.xxh32_intdigest(" ".join(words[i : i + gram])))):
                for t, at in hit:
                    seeds[t].append((i - at, i))
        if not seeds:
            return []
        found = []
        for t, at in seeds.items():
            body, group = self.bodies[t], []
            for diagonal, i in sorted(at, key=lambda s: s[1]):
                # A new candidate where the diagonal leaves the band or the text is past the template.
                if group and (abs(diagonal - group[0][0]) > self.band or i - group[0][0] > len(body) + self.band):
                    found.append((t, group))
                    group = []
                group.append((diagonal, i))
            found.append((t, group))
        best = [(cover, matched, first, last, t) for t, group in found for cover, matched, first, last in self.matches(words, t, group)]
        taken, out, places = [], [], [m.span() for m in WORD.finditer(text)] if best else []
        for cover, matched, first, last, t in sorted(best, key=lambda b: (-b[0] * b[1], b[2], b[4])):
            at = bisect_left(taken, (first, last))
            if (at == len(taken) or last <= taken[at][0]) and (at == 0 or first >= taken[at - 1][1]):
                taken.insert(at, (first, last))
                out.append((self.names[t], round(cover, 6), places[first][0], places[last - 1][1]))
        return sorted(out, key=lambda m: (m[2], m[0]))


def scan_licenses(docs: DataFrame, templates: dict[str, tuple[str, ...]] | None = None, coverage: float = COVERAGE, least: float = LEAST) -> DataFrame:
    """One row per match: doc_id, license, coverage, matched (``coverage`` or more), start, end."""
    held = TEMPLATES if templates is None else templates

    def make():
        scanner = Scanner(held, least=least)

        def kernel(cols):
            out: list[list] = [[], [], [], [], [], []]
            for i, t in zip(*cols, strict=True):
                for name, cover, start, end in scanner.scan(t):
                    for c, v in zip(out, (i, name, cover, cover >= coverage, start, end), strict=True):
                        c.append(v)
            return out

        return kernel

    return arrow_map(docs.select("doc_id", "text"), make, "doc_id long, license string, coverage double, matched boolean, start long, end long")
