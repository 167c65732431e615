"""License scans by conditional compression.

Wherever a text has a cue (the word license, a copyright sign, ...) the lines around it form a
candidate block. A block is compressed in overlapping windows of bounded size, once plainly and
once with each license template as a raw zstandard dictionary; the more of a template's wording
a window repeats, the more bytes the dictionary saves. Every place of a block where a template's
words stand with no more than ``TOLERANCE`` of them missing or interrupted by others is a
candidate, whatever it saves. Words belong to one match only: fewer wording differences come
first, then more bytes saved, then more words; what remains open is searched again until no template holds. The
character span of a match is that of the aligned words, its saving the best among the windows
that it touches (it may be zero or less).

A block reaches from a cue over the paragraph around it, at most ``BEFORE`` characters back and
``AFTER`` on; every template has a cue, and blocks that touch are one, so a wording of any length
is in a block as long as its cues are not further apart than that.

Edge cases: null and empty texts have no block; a text of any length is scanned whole, block by
block; templates that save equally rank by name; repeated rows are scanned alike; other columns
of the input are kept, those with this operator's names are overwritten.
"""

from __future__ import annotations

import re
from bisect import bisect_left

import zstandard
from pyspark.sql import DataFrame, functions as F, types as T

from repsum.llm.arrow import add_columns

LEVEL = 3
#: Share of a template's words that may differ.
TOLERANCE = 0.1
#: Characters before and after a cue that belong to its block, cut at the paragraph.
BEFORE, AFTER = 600, 1200
#: Characters that are compressed at once, and how many of them the next window repeats.
WINDOW, OVERLAP = 1500, 400

#: Wordings of public licenses, by SPDX identifier (BSD: shared by its variants). A long
#: license is a template for each of its sentences, so its text counts however much of it is quoted.
TEMPLATES: tuple[tuple[str, str], ...] = (
    ("MIT", "Released under the MIT License."),
    ("MIT", "Licensed under the MIT License."),
    ("MIT", "SPDX-License-Identifier: MIT"),
    ("MIT", "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software"),
    ("Apache-2.0", "Licensed under the Apache License, Version 2.0."),
    ("Apache-2.0", "Released under the Apache License, Version 2.0."),
    ("Apache-2.0", "SPDX-License-Identifier: Apache-2.0"),
    ("Apache-2.0", "you may not use this file except in compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0"),
    ("GPL-3.0", "This work is licensed under the GNU General Public License, version 3."),
    ("GPL-3.0", "SPDX-License-Identifier: GPL-3.0-only"),
    ("GPL-3.0", "it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version"),
    ("GPL-2.0", "This work is licensed under the GNU General Public License, version 2."),
    ("GPL-2.0", "SPDX-License-Identifier: GPL-2.0-only"),
    ("LGPL-3.0", "This work is licensed under the GNU Lesser General Public License, version 3."),
    ("AGPL-3.0", "This work is licensed under the GNU Affero General Public License, version 3."),
    ("BSD-3-Clause", "Licensed under the BSD 3-Clause License."),
    ("BSD-3-Clause", "Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission"),
    ("BSD-2-Clause", "Licensed under the BSD 2-Clause License."),
    ("MPL-2.0", "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0."),
    ("ISC", "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies."),
    ("Unlicense", "This is free and unencumbered software released into the public domain."),
    ("CC0-1.0", "Licensed under CC0 1.0."),
    ("CC-BY-4.0", "Licensed under CC BY 4.0."),
    ("CC-BY-SA-4.0", "Licensed under CC BY-SA 4.0."),
    ("CC-BY-NC-4.0", "Licensed under CC BY-NC 4.0."),
    ("CC-BY-ND-4.0", "Licensed under CC BY-ND 4.0."),
    ("CC-BY-NC-SA-4.0", "Licensed under CC BY-NC-SA 4.0."),
    ("CC-BY-4.0", "This work is licensed under a Creative Commons Attribution 4.0 International License."),
    ("CC-BY-SA-4.0", "This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License."),
    ("CC-BY-NC-4.0", "This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International License."),
    ("MIT", "The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software."),
    ("MIT", "THE SOFTWARE IS PROVIDED \"AS IS\", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE."),
    ("MIT", "The MIT License (MIT)"),
    ("MIT", "under the MIT License"),
    ("MIT", "This project is licensed under the terms of the MIT license."),
    ("Apache-2.0", "Apache License Version 2.0, January 2004"),
    ("Apache-2.0", "under the Apache License, Version 2.0"),
    ("Apache-2.0", "TERMS AND CONDITIONS FOR USE, REPRODUCTION, AND DISTRIBUTION"),
    ("Apache-2.0", "Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an \"AS IS\" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. See the License for the specific language governing permissions and limitations under the License."),
    ("GPL-3.0", "GNU GENERAL PUBLIC LICENSE Version 3, 29 June 2007"),
    ("GPL-2.0", "GNU GENERAL PUBLIC LICENSE Version 2, June 1991"),
    ("GPL-2.0", "it under the terms of the GNU General Public License as published by the Free Software Foundation; either version 2 of the License, or (at your option) any later version"),
    ("LGPL-3.0", "GNU LESSER GENERAL PUBLIC LICENSE Version 3, 29 June 2007"),
    ("AGPL-3.0", "GNU AFFERO GENERAL PUBLIC LICENSE Version 3, 19 November 2007"),
    ("BSD", "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met"),
    ("BSD", "Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer."),
    ("BSD", "Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution."),
    ("BSD", "THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS \"AS IS\" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED."),
    ("BSD-3-Clause", "SPDX-License-Identifier: BSD-3-Clause"),
    ("BSD-2-Clause", "SPDX-License-Identifier: BSD-2-Clause"),
    ("MPL-2.0", "If a copy of the MPL was not distributed with this file, You can obtain one at https://mozilla.org/MPL/2.0/."),
    ("MPL-2.0", "SPDX-License-Identifier: MPL-2.0"),
    ("Zlib", "This software is provided 'as-is', without any express or implied warranty. In no event will the authors be held liable for any damages arising from the use of this software."),
    ("BSL-1.0", "Distributed under the Boost Software License, Version 1.0."),
    ("EPL-2.0", "This program and the accompanying materials are made available under the terms of the Eclipse Public License 2.0"),
    ("proprietary", "All rights reserved."),
)

_CUE = re.compile(r"licen[cs]|copyright|©|spdx|creative\s+commons|\bcc[ -](?:by|0)|public\s+domain|rights\s+reserved|permission\s+(?:is|to|notice)|mozilla\s+public|\bmpl\b|gnu\s+|redistribut|as[ -]is\b|terms\s+and\s+conditions", re.IGNORECASE)
_WORD = re.compile(r"[^\W_]+")

MATCH = T.ArrayType(
    T.StructType(
        [
            T.StructField("license", T.StringType()),
            T.StructField("begin", T.IntegerType()),
            T.StructField("end", T.IntegerType()),
            T.StructField("saved", T.IntegerType()),
            T.StructField("missing", T.IntegerType()),
            T.StructField("extra", T.IntegerType()),
        ]
    )
)
FIELDS = [T.StructField("n_blocks", T.IntegerType()), T.StructField("matches", MATCH), T.StructField("best_saving", T.DoubleType())]


def blocks_of(text: str) -> list[tuple[int, int]]:
    """Spans of candidate blocks: around each cue, within its paragraph, overlapping ones joined."""
    spans: list[tuple[int, int]] = []
    for cue in _CUE.finditer(text):
        a, b = max(0, cue.start() - BEFORE), min(len(text), cue.end() + AFTER)
        a = max(a, text.rfind("\n\n", a, cue.start()) + 2 if "\n\n" in text[a : cue.start()] else a)
        stop = text.find("\n\n", cue.end(), b)
        b = stop if stop >= 0 else b
        if spans and a <= spans[-1][1]:
            spans[-1] = spans[-1][0], max(b, spans[-1][1])
        else:
            spans.append((a, b))
    return spans


def windows_of(a: int, b: int) -> list[tuple[int, int]]:
    """Overlapping spans of at most ``WINDOW`` characters that cover a block."""
    return [(x, min(b, x + WINDOW)) for x in range(a, max(a + 1, b - OVERLAP), WINDOW - OVERLAP)]


class Templates:
    def __init__(self, templates=TEMPLATES) -> None:
        self.names = [n for n, _ in templates]
        self.words = [[w.lower() for w in _WORD.findall(t)] for _, t in templates]
        raw = zstandard.DICT_TYPE_RAWCONTENT
        self.conditional = [zstandard.ZstdCompressor(level=LEVEL, dict_data=zstandard.ZstdCompressionDict(t.encode(), dict_type=raw)) for _, t in templates]
        self.plain = zstandard.ZstdCompressor(level=LEVEL)
        # differences within the tolerance leave one of so many pieces of a template whole
        self.allowed = [int(TOLERANCE * len(w)) for w in self.words]
        self.pieces = [[(k * len(w) // (n + 1), " ".join(["", *w[k * len(w) // (n + 1) : (k + 1) * len(w) // (n + 1)], ""])) for k in range(n + 1)] for w, n in zip(self.words, self.allowed)]

    def savings(self, window: bytes) -> list[int]:
        """Bytes that each template saves."""
        alone = len(self.plain.compress(window))
        return [alone - len(c.compress(window)) for c in self.conditional]

    def align(self, i: int, words: list[str]) -> tuple[int, int, int, int] | None:
        """(missing, extra, first word, word after the last) of the template's closest place, None beyond the tolerance.

        Words are matched in order; what lies before the first and after the last matched word is free.
        """
        want, allowed = self.words[i], self.allowed[i]
        # best[j]: (differences, -first word, extra, last) with the first j words of the template dealt with
        best: list[tuple[int, int, int, int] | None] = [None] * (len(want) + 1)
        found = None
        for at, word in enumerate(words):
            before = best
            best = [None] * (len(want) + 1)
            for j, wanted in enumerate(want):
                options = []
                if word == wanted:
                    if j <= allowed:
                        options.append((j, -at, 0))
                    if before[j] is not None:
                        options.append(before[j])
                if options:
                    match = min(options)
                    rest = len(want) - j - 1
                    if match[0] + rest <= allowed:
                        end = (match[0] + rest, match[1], match[2], at + 1)
                        found = end if found is None or end < found else found
                else:
                    match = None
                moves = [m for m in (match, best[j] and (best[j][0] + 1, *best[j][1:]), before[j + 1] and (before[j + 1][0] + 1, before[j + 1][1], before[j + 1][2] + 1)) if m and m[0] <= allowed]
                best[j + 1] = min(moves) if moves else None
        if found is None:
            return None
        return found[0] - found[2], found[2], -found[1], found[3]

    def places(self, i: int, words: list[str], joined: str, starts: list[int]) -> list[tuple[int, int, int, int]]:
        """(missing, extra, first word, word after the last) wherever the template stands within the tolerance."""
        want, allowed, begins, found = self.words[i], self.allowed[i], set(), set()
        for offset, piece in self.pieces[i]:
            p = joined.find(piece)
            while p >= 0:
                begins.add(bisect_left(starts, p + 1) - offset)
                p = joined.find(piece, p + 1)
        for p in sorted(begins):
            if p >= 0 and words[p : p + len(want)] == want:
                found.add((0, 0, p, p + len(want)))
            elif allowed:
                x = max(0, p - allowed)
                got = self.align(i, words[x : p + len(want) + allowed])
                if got:
                    found.add((got[0], got[1], x + got[2], x + got[3]))
        return sorted(found)

    def scan(self, text: str | None) -> dict:
        text = text or ""
        found, spans, best = [], blocks_of(text), 0.0
        for a, b in spans:
            saved = []
            for x, y in windows_of(a, b):
                raw = text[x:y].encode("utf-8", "surrogatepass")
                saved.append((x, y, self.savings(raw)))
                best = max(best, max(saved[-1][2]) / max(1, len(raw)))
            at = [(a + m.start(), a + m.end()) for m in _WORD.finditer(text[a:b])]
            open_words = [text[x:y].lower() for x, y in at]
            # a word that a match has used is taken out, the others are searched again
            hoped = range(len(self.words))
            while hoped:
                joined = " ".join(["", *open_words, ""])
                starts, p = [], 1
                for w in open_words:
                    starts.append(p)
                    p += len(w) + 1
                held = {i: got for i in hoped if (got := self.places(i, open_words, joined, starts))}
                ranked = []
                for i, got in held.items():
                    for missing, extra, x, y in got:
                        begin, end = at[x][0], at[y - 1][1]
                        worth = max(s[i] for p, q, s in self.touched(saved, begin, end, a))
                        ranked.append((missing + extra, -worth, x - y, self.names[i], i, x, y, missing, extra))
                taken = bytearray(len(open_words))
                for _, worth, _, name, _, x, y, missing, extra in sorted(ranked):
                    if not any(taken[x:y]):
                        taken[x:y] = b"\1" * (y - x)
                        found.append({"license": name, "begin": at[x][0], "end": at[y - 1][1], "saved": -worth, "missing": missing, "extra": extra})
                        open_words[x:y] = [""] * (y - x)
                hoped = list(held)
        found.sort(key=lambda m: (m["begin"], m["license"]))
        return {"n_blocks": len(spans), "matches": found, "best_saving": float(best)}

    @staticmethod
    def touched(saved: list, begin: int, end: int, a: int) -> list:
        """The windows that overlap a span of the block that begins at ``a``."""
        step = WINDOW - OVERLAP
        first = max(0, (begin - a - WINDOW) // step)
        return [s for s in saved[first : (end - a) // step + 1] if s[0] < end and s[1] > begin] or saved[-1:]


def scan_licenses(docs: DataFrame, templates=TEMPLATES, text_col: str = "text") -> DataFrame:
    """Append n_blocks, matches (license, span, bytes saved, wording differences) and best_saving to every row."""

    def work():
        own = Templates(templates)

        def step(texts: list) -> dict:
            rows = [own.scan(t) for t in texts]
            return {f.name: [r[f.name] for r in rows] for f in FIELDS}

        return step

    return add_columns(docs, text_col, FIELDS, work)


def digest(scanned: DataFrame, id_col: str = "doc_id") -> DataFrame:
    """doc_id, n_blocks, n_matches, licenses (distinct, sorted, comma-joined), best_saving."""
    names = F.array_sort(F.array_distinct(F.transform("matches", lambda m: m["license"])))
    return scanned.select(F.col(id_col), F.col("n_blocks").cast("long").alias("n_blocks"), F.size("matches").cast("long").alias("n_matches"), F.array_join(names, ",").alias("licenses"), "best_saving")
