"""License scans by patience alignment of texts with license templates."""

from __future__ import annotations

import bisect
import re
from collections import Counter

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import annotate, ship, texts

WORD = re.compile(r"[a-z0-9]+")
TABLE = bytes(b + 32 if 65 <= b <= 90 else b if 48 <= b <= 57 or 97 <= b <= 122 else 32 for b in range(256))

#: Public license notices and texts; fixed values.
TEMPLATES = {
    "Apache-2.0": "Licensed under the Apache License, Version 2.0",
    "Apache-2.0-notice": (
        'Licensed under the Apache License, Version 2.0 (the "License"); you may not use this file except in compliance with the License. '
        "You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0 Unless required by applicable law or agreed to in writing, "
        'software distributed under the License is distributed on an "AS IS" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. '
        "See the License for the specific language governing permissions and limitations under the License."
    ),
    "Apache-1.1": "Licensed under the Apache License, Version 1.1",
    "MIT": "Released under the MIT License",
    "BSD-short": "Released under the BSD License",
    "MIT-text": (
        "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the "
        '"Software"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, '
        "distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the "
        "following conditions: The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software. "
        'THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF '
        "MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY "
        "CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE "
        "SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE."
    ),
    "GPL-2.0": "This work is licensed under the GNU General Public License, version 2",
    "GPL-3.0": "This work is licensed under the GNU General Public License, version 3",
    "LGPL-2.1": "This work is licensed under the GNU Lesser General Public License, version 2.1",
    "LGPL-3.0": "This work is licensed under the GNU Lesser General Public License, version 3",
    "AGPL-3.0": "This work is licensed under the GNU Affero General Public License, version 3",
    "GPL-notice": (
        "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the "
        "Free Software Foundation, either version 3 of the License, or (at your option) any later version. This program is distributed in the hope that "
        "it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE. See the "
        "GNU General Public License for more details. You should have received a copy of the GNU General Public License along with this program."
    ),
    "MPL-2.0": (
        "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, "
        "You can obtain one at https://mozilla.org/MPL/2.0/."
    ),
    "EPL-2.0": (
        "This program and the accompanying materials are made available under the terms of the Eclipse Public License 2.0 which is available at "
        "https://www.eclipse.org/legal/epl-2.0/"
    ),
    "CC0-1.0": "Licensed under CC0 1.0",
    "CC-BY-4.0": "Licensed under CC BY 4.0",
    "CC-BY-SA-4.0": "Licensed under CC BY-SA 4.0",
    "CC-BY-ND-4.0": "Licensed under CC BY-ND 4.0",
    "CC-BY-NC-4.0": "Licensed under CC BY-NC 4.0",
    "CC-BY-NC-SA-4.0": "Licensed under CC BY-NC-SA 4.0",
    "CC-BY-NC-ND-4.0": "Licensed under CC BY-NC-ND 4.0",
    "CC-BY-3.0": "Licensed under CC BY 3.0",
    "CC-BY-SA-3.0": "Licensed under CC BY-SA 3.0",
    "BSD": (
        "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: "
        "Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer. "
        "Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the "
        "documentation and/or other materials provided with the distribution. "
        'THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS "AS IS" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, '
        "THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR "
        "CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, "
        "PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF "
        "LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS "
        "SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE."
    ),
    "ISC": (
        "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above "
        'copyright notice and this permission notice appear in all copies. THE SOFTWARE IS PROVIDED "AS IS" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH '
        "REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS."
    ),
    "Unlicense": (
        "This is free and unencumbered software released into the public domain. Anyone is free to copy, modify, publish, use, compile, sell, or "
        "distribute this software, either in source code form or as a compiled binary, for any purpose, commercial or non-commercial, and by any means."
    ),
    "Zlib": (
        "This software is provided 'as-is', without any express or implied warranty. In no event will the authors be held liable for any damages arising "
        "from the use of this software. Permission is granted to anyone to use this software for any purpose, including commercial applications, and to "
        "alter it and redistribute it freely."
    ),
}
#: Templates of so many words may be torn apart by insertions of any length; shorter ones must stand in one stretch.
LONG = 30


def words_of(text: str) -> list[bytes]:
    return text.encode("utf-8", "surrogatepass").translate(TABLE).split()


def longest_rising(pairs: list[tuple[int, int]]) -> list[tuple[int, int]]:
    """The longest sequence that rises in both places; pairs come by rising first place."""
    tails: list[int] = []
    ends: list[int] = []
    before = [-1] * len(pairs)
    for n, (_, j) in enumerate(pairs):
        k = bisect.bisect_left(tails, j)
        before[n] = ends[k - 1] if k else -1
        if k == len(tails):
            tails.append(j)
            ends.append(n)
        else:
            tails[k], ends[k] = j, n
    out, n = [], ends[-1] if ends else -1
    while n >= 0:
        out.append(pairs[n])
        n = before[n]
    return out[::-1]


def align(a: list[bytes], b: list[bytes], reach: int | None = 12) -> list[tuple[int, int]]:
    """Matched places (in a, in b), rising in both: equal ends first, then words unique to both sides as anchors, of
    these the longest rising sequence, and so on in every gap. Before the first and after the last anchor only as many
    words of ``a`` count as ``b`` has there, and ``reach`` more (None: all of them). Work is kept in a list, so depth is not bound."""
    out: list[tuple[int, int]] = []
    todo = [(0, len(a), 0, len(b), True, True)]
    while todo:
        a0, a1, b0, b1, open_left, open_right = todo.pop()
        while not open_left and a0 < a1 and b0 < b1 and a[a0] == b[b0]:
            out.append((a0, b0))
            a0, b0 = a0 + 1, b0 + 1
        while not open_right and a0 < a1 and b0 < b1 and a[a1 - 1] == b[b1 - 1]:
            out.append((a1 - 1, b1 - 1))
            a1, b1 = a1 - 1, b1 - 1
        if a0 >= a1 or b0 >= b1:
            continue
        if open_left != open_right and reach is not None:  # beyond the outermost anchor
            room = (b1 - b0) + reach
            a0, a1 = (max(a0, a1 - room), a1) if open_left else (a0, min(a1, a0 + room))
        there = Counter(a[a0:a1])
        own = Counter(b[b0:b1])
        place = {w: i for i, w in enumerate(b[b0:b1], b0) if own[w] == 1 and there.get(w) == 1}
        pairs = [(i, place[w]) for i, w in enumerate(a[a0:a1], a0) if w in place]
        if not pairs:
            continue
        chain = longest_rising(pairs)
        out += chain
        left_a, left_b, edge = a0, b0, open_left
        for i, j in chain:
            todo.append((left_a, i, left_b, j, edge, False))
            left_a, left_b, edge = i + 1, j + 1, False
        todo.append((left_a, a1, left_b, b1, False, open_right))
    return sorted(out)


class Scanner:
    def __init__(self, templates: dict[str, str], least: float):
        self.least = least
        self.own = [(name, w, Counter(w)) for name, t in sorted(templates.items()) if (w := words_of(t))]

    def scan(self, words: list[bytes]) -> list[tuple[str, float, int, int]]:
        """(template, coverage, from word, to word) for every template covered to ``least`` at some place.

        Only texts that hold enough of a template's words can cover it, so all others are passed over. A template may
        stand in a text more than once, and its words elsewhere too; so stretches around each place of its rarest
        words are aligned, and the best counts. If none of them covers enough of a long template, the whole text is
        aligned with it, so that no insertion is too long.
        """
        there, out = set(words), []
        for name, own, counts in self.own:
            if sum(n for w, n in counts.items() if w in there) < self.least * len(own):
                continue
            where: dict[bytes, list[int]] = {w: [] for w in counts}
            for i, w in enumerate(words):
                if w in where:
                    where[w].append(i)
            # at least one of these words stands in any alignment that covers enough
            order = sorted(counts, key=lambda w: (len(where[w]), w))
            missable, seeds = (1 - self.least) * len(own), []
            for w in order:
                seeds += where[w]
                missable -= counts[w]
                if missable < 0:
                    break
            best, reach, done = (0.0, 0, 0), 2 * len(own) + 12, set()
            slack = 2 + int(len(own) * (1 - self.least))
            tries = []
            for at in sorted(seeds):
                # the template's own stretch first, in which its words are unique even if it is repeated; then wider
                tries += [(at - j - slack, at - j + len(own) + slack, 12) for j, w in enumerate(own) if w == words[at]]
                tries.append((at - reach, at + reach, 12))
            if len(own) >= LONG:
                tries.append((0, len(words), None))
            for lo, hi, far in tries:
                span = (max(0, lo), min(len(words), hi))
                if (span, far) in done or (far is None and best[0] >= self.least):
                    continue
                done.add((span, far))
                if sum(1 for w in words[span[0] : span[1]] if w in counts) <= best[0] * len(own):
                    continue  # too few of its words to be better
                got = align(words[span[0] : span[1]], own, far)
                cover = len(got) / len(own)
                if got and cover > best[0]:
                    best = (cover, span[0] + got[0][0], span[0] + got[-1][0] + 1)
                if best[0] == 1.0:
                    break
            if best[0] >= self.least:
                out.append((name, *best))
        return out


FOUND = [
    T.StructField("license", T.StringType()),
    T.StructField("coverage", T.DoubleType()),
    T.StructField("from_word", T.LongType()),
    T.StructField("to_word", T.LongType()),
    T.StructField("licenses", T.ArrayType(T.StringType())),
]


def scan_licenses(docs: DataFrame, templates: dict[str, str] | None = None, least: float = 0.8, text_col: str = "text", keep: list[str] | None = None) -> DataFrame:
    """``docs`` with the license of best coverage (ties: the longer template, then by name), its coverage, the words it
    spans, and all licenses covered to ``least``. Texts without one, and null or empty texts, get null, 0 and no list
    entries. Rows, repeated ones too, are kept; columns named as new ones give way."""
    spark = docs.sparkSession
    ship(spark)
    held = dict(TEMPLATES if templates is None else templates)
    sizes = {k: len(words_of(v)) for k, v in held.items()}

    def start():
        scanner = Scanner(held, least)

        def work(batch: pa.RecordBatch) -> dict[str, list]:
            made: dict[str, list] = {f.name: [] for f in FOUND}
            for t in texts(batch, text_col):
                got = scanner.scan(words_of(t))
                top = max(got, key=lambda g: (round(g[1], 9), sizes[g[0]], g[0]), default=(None, 0.0, None, None))
                for n, v in zip(made, (*top, sorted(g[0] for g in got)), strict=True):
                    made[n].append(v)
            return made

        return work

    return annotate(docs, start, FOUND, [text_col], keep)


def op3(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = scan_licenses(spark.read.parquet(f"{sf_dir}/documents.parquet"), keep=["doc_id"])
    return found.select("doc_id", "license", "coverage", "from_word", "to_word", F.concat_ws(",", "licenses").alias("licenses"))
