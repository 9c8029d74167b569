"""Licence scan: Dice coefficient over word bigrams against licence notices and texts.

Texts and templates are normalised to lower-case words. A template of n bigrams is
compared with windows of the text that begin and end with one of its bigrams, up to the
size n * (2 - t) / t beyond which no window reaches the coefficient t, and with windows
of n bigrams. Size bounds prune templates before any comparison: neither a text with fewer
bigrams than t * m / (2 - t), where the template has m different ones, can reach the
coefficient t, nor a window that holds fewer of the template's.

Of overlapping windows the one with the larger coefficient stays, then that of the longer
template, then the first. They are looked for in that order: a start has the bound 2u / (u + m)
where its largest window holds u different bigrams of the template, its best window is worked out when the
bound's turn comes, and never where its start lies in a window that stays already. So a licence
costs about one comparison of its size, however many of its bigrams could begin a window.

Templates are the public notices below, or those of a folder of text files (read_templates).

Defined results: a null or wordless text has no licence; equal coefficients of
two templates of one length go by place, then by name; a letter whose lower case is longer
moves no position; very long texts are scanned whole, in time in proportion to their hits;
repeated rows give equal results; an empty table an empty result; other columns are ignored.
"""

from __future__ import annotations

import re
from bisect import bisect_left, insort
from collections.abc import Iterator
from heapq import heapify, heappop, heappush

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from splitguard.llm.rows import lean

LEAST_DICE = 0.8

# Public licence notices and short licences, whole, by SPDX-like name.
NOTICES = {
    "Apache-2.0": [
        "Licensed under the Apache License, Version 2.0.",
        "Licensed under the Apache License, Version 2.0 (the \"License\"); you may not use this file "
        "except in compliance with the License. You may obtain a copy of the License at "
        "http://www.apache.org/licenses/LICENSE-2.0 Unless required by applicable law or agreed to in "
        "writing, software distributed under the License is distributed on an \"AS IS\" BASIS, WITHOUT "
        "WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. See the License for the "
        "specific language governing permissions and limitations under the License.",
    ],
    "MIT": [
        "Released under the MIT License.",
        "Licensed under the MIT License.",
        "Permission is hereby granted, free of charge, to any person obtaining a copy of this software "
        "and associated documentation files (the \"Software\"), to deal in the Software without "
        "restriction, including without limitation the rights to use, copy, modify, merge, publish, "
        "distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the "
        "Software is furnished to do so, subject to the following conditions: The above copyright "
        "notice and this permission notice shall be included in all copies or substantial portions of "
        "the Software.",
        "Permission is hereby granted, free of charge, to any person obtaining a copy of this software "
        "and associated documentation files (the \"Software\"), to deal in the Software without "
        "restriction, including without limitation the rights to use, copy, modify, merge, publish, "
        "distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the "
        "Software is furnished to do so, subject to the following conditions: The above copyright "
        "notice and this permission notice shall be included in all copies or substantial portions of "
        "the Software. THE SOFTWARE IS PROVIDED \"AS IS\", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR "
        "IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A "
        "PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE "
        "LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR "
        "OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS "
        "IN THE SOFTWARE.",
    ],
    "ISC": [
        "Permission to use, copy, modify, and/or distribute this software for any purpose with or without "
        "fee is hereby granted, provided that the above copyright notice and this permission notice "
        "appear in all copies.",
        "Permission to use, copy, modify, and/or distribute this software for any purpose with or without "
        "fee is hereby granted, provided that the above copyright notice and this permission notice "
        "appear in all copies. THE SOFTWARE IS PROVIDED \"AS IS\" AND THE AUTHOR DISCLAIMS ALL WARRANTIES "
        "WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. IN "
        "NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES "
        "OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF "
        "CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR "
        "PERFORMANCE OF THIS SOFTWARE.",
    ],
    "Zlib": [
        "This software is provided 'as-is', without any express or implied warranty. In no event will the "
        "authors be held liable for any damages arising from the use of this software. Permission is "
        "granted to anyone to use this software for any purpose, including commercial applications, and "
        "to alter it and redistribute it freely, subject to the following restrictions: 1. The origin of "
        "this software must not be misrepresented; you must not claim that you wrote the original "
        "software. If you use this software in a product, an acknowledgment in the product documentation "
        "would be appreciated but is not required. 2. Altered source versions must be plainly marked as "
        "such, and must not be misrepresented as being the original software. 3. This notice may not be "
        "removed or altered from any source distribution.",
    ],
    "Unlicense": [
        "This is free and unencumbered software released into the public domain. Anyone is free to copy, "
        "modify, publish, use, compile, sell, or distribute this software, either in source code form or "
        "as a compiled binary, for any purpose, commercial or non-commercial, and by any means.",
    ],
    "BSL-1.0": [
        "Distributed under the Boost Software License, Version 1.0.",
        "Permission is hereby granted, free of charge, to any person or organization obtaining a copy of "
        "the software and accompanying documentation covered by this license (the \"Software\") to use, "
        "reproduce, display, distribute, execute, and transmit the Software, and to prepare derivative "
        "works of the Software, and to permit third-parties to whom the Software is furnished to do so",
    ],
    "BSD": [
        "Redistribution and use in source and binary forms, with or without modification, are permitted "
        "provided that the following conditions are met: Redistributions of source code must retain the "
        "above copyright notice, this list of conditions and the following disclaimer. Redistributions "
        "in binary form must reproduce the above copyright notice, this list of conditions and the "
        "following disclaimer in the documentation and/or other materials provided with the "
        "distribution.",
        "THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS \"AS IS\" AND ANY EXPRESS OR "
        "IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND "
        "FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR "
        "CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL "
        "DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, "
        "DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, "
        "WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY "
        "WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE.",
    ],
    "LGPL-2.1": [
        "This library is free software; you can redistribute it and/or modify it under the terms of the "
        "GNU Lesser General Public License as published by the Free Software Foundation; either version "
        "2.1 of the License, or (at your option) any later version.",
    ],
    "AGPL-3.0": [
        "This program is free software: you can redistribute it and/or modify it under the terms of the "
        "GNU Affero General Public License as published by the Free Software Foundation, either version 3 "
        "of the License, or (at your option) any later version.",
    ],
    "GPL-2.0": [
        "This work is licensed under the GNU General Public License, version 2.",
        "This program is free software; you can redistribute it and/or modify it under the terms of the "
        "GNU General Public License as published by the Free Software Foundation; either version 2 of "
        "the License, or (at your option) any later version.",
    ],
    "GPL-3.0": [
        "This work is licensed under the GNU General Public License, version 3.",
        "This program is free software: you can redistribute it and/or modify it under the terms of the "
        "GNU General Public License as published by the Free Software Foundation, either version 3 of "
        "the License, or (at your option) any later version.",
    ],
    "MPL-2.0": [
        "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy "
        "of the MPL was not distributed with this file, You can obtain one at "
        "http://mozilla.org/MPL/2.0/.",
    ],
    "CC-BY-4.0": [
        "Licensed under CC BY 4.0.",
        "This work is licensed under a Creative Commons Attribution 4.0 International License.",
    ],
    "CC-BY-SA-4.0": [
        "Licensed under CC BY-SA 4.0.",
        "This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License.",
    ],
    "CC-BY-NC-4.0": [
        "Licensed under CC BY-NC 4.0.",
        "This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International "
        "License.",
    ],
    "All-Rights-Reserved": ["All rights reserved."],
}

_WORD = re.compile(r"\w+")


def normal_words(text: str) -> list[str]:
    """Lower-case words; a word is found before its letters change, so positions hold."""
    return [w.lower() for w in _WORD.findall(text)]


def read_templates(spark: SparkSession, path: str) -> dict[str, list[str]]:
    """Templates of a folder of text files, one a licence, named by file; its size is that of a licence list."""
    files = spark.read.text(path, wholetext=True).select(F.input_file_name().alias("path"), "value")
    out: dict[str, list[str]] = {}
    for row in files.collect():
        name = row["path"].rsplit("/", 1)[-1].removesuffix(".txt")
        out.setdefault(name, []).append(row["value"])
    return out


class Scanner:
    def __init__(self, notices: dict[str, list[str]] | None = None, least: float = LEAST_DICE):
        self.least = least
        self.names: list[str] = []
        self.bigrams: list[frozenset[tuple[str, str]]] = []
        self.sizes: list[int] = []
        self.holders: dict[tuple[str, str], list[int]] = {}
        for name, texts in sorted((notices or NOTICES).items()):
            for text in texts:
                words = normal_words(text)
                pairs = list(zip(words, words[1:]))
                if not pairs:
                    raise ValueError(f"a notice of {name} has fewer than two words")
                for pair in set(pairs):
                    self.holders.setdefault(pair, []).append(len(self.names))
                self.names.append(name)
                self.bigrams.append(frozenset(pairs))
                self.sizes.append(len(pairs))

    def scan(self, text: str | None) -> list[tuple[str, float, int, int]]:
        """(name, dice, start, end) of each notice found; positions in code points."""
        if not text:
            return []
        words = normal_words(text)
        pairs = list(zip(words, words[1:]))
        hits: dict[int, list[int]] = {}
        holders = self.holders
        for at, pair in enumerate(pairs):
            if pair in holders:
                for k in holders[pair]:
                    hits.setdefault(k, []).append(at)
        # Entries of two kinds: bounds (-bound, 0, template, hit), and windows, which come after
        # bounds that may yet give an equal one: (-dice, 1, -n, start, end, name).
        queue = [x for k, at in hits.items() for x in self._bounds(k, at, pairs)]
        heapify(queue)
        kept: list[tuple[int, int, float, str]] = []
        while queue:
            entry = heappop(queue)
            if entry[1] == 0:
                k, i = entry[2:]
                start, n = hits[k][i], self.sizes[k]
                if not self._free(kept, start, start + 1):
                    continue
                last = bisect_left(hits[k], start + self._most(n), i)
                dice, end = self._best_window(pairs, self.bigrams[k], hits[k][i:last], min(start + n, len(pairs)))
                if dice >= self.least:
                    heappush(queue, (-dice, 1, -n, start, end, self.names[k]))
            else:
                dice, _, _, start, end, name = entry
                if self._free(kept, start, end):
                    insort(kept, (start, end, -dice, name))
        if not kept:
            return []
        spots = [m.span() for m in _WORD.finditer(text)]
        return [(name, dice, spots[s][0], spots[e][1]) for s, e, dice, name in kept]

    @staticmethod
    def _free(kept: list[tuple[int, int, float, str]], start: int, end: int) -> bool:
        """Whether start..end overlaps none of the kept windows, which are sorted and apart."""
        at = bisect_left(kept, (start + 1,))
        return (not at or kept[at - 1][1] <= start) and (at == len(kept) or end <= kept[at][0])

    def _most(self, n: int) -> int:
        return int(n * (2 - self.least) / self.least + 1e-9)  # no larger window reaches the coefficient

    def _bounds(self, k: int, at: list[int], pairs: list[tuple[str, str]]) -> list[tuple]:
        """(-bound, 0, k, i) of each hit from which a window can reach the coefficient."""
        own, most, out = self.bigrams[k], self._most(self.sizes[k]), []
        # A window must hold this many different ones of the template, and so must the text.
        need = self.least * len(own) / (2 - self.least) - 1e-9
        if len(pairs) < need or len(at) < need:
            return out
        counts: dict[tuple[str, str], int] = {}
        last = 0
        for i, start in enumerate(at):
            while last < len(at) and at[last] < start + most:
                counts[pairs[at[last]]] = counts.get(pairs[at[last]], 0) + 1
                last += 1
            if len(counts) >= need:
                out.append((-2 * len(counts) / (len(counts) + len(own)), 0, k, i))
            counts[pairs[start]] -= 1
            if not counts[pairs[start]]:
                del counts[pairs[start]]
        return out

    @staticmethod
    def _best_window(
        pairs: list[tuple[str, str]], own: frozenset[tuple[str, str]], at: list[int], full: int
    ) -> tuple[float, int]:
        """(dice, end) of the best window from at[0] that ends behind one of at, or at full."""
        seen: set[tuple[str, str]] = set()
        best, end, shared = (-1.0, 0), at[0], 0
        for stop in sorted({*(x + 1 for x in at), full}):
            fresh = set(pairs[end:stop]) - seen
            seen |= fresh
            shared += len(fresh & own)
            end = stop
            dice = 2 * shared / (len(seen) + len(own))
            if dice >= best[0]:  # of equal windows the longest
                best = (dice, stop)
        return best


def scan_licences(
    docs: DataFrame,
    id_col: str = "doc_id",
    text_col: str = "text",
    notices: dict[str, list[str]] | None = None,
    least: float = LEAST_DICE,
) -> DataFrame:
    """(doc_id, n_licences, licences, best_licence, best_dice, spans) for every row.

    licences: the different names, sorted, comma-joined; spans: name:start:end, by start.
    """
    slim = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"))

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scanner = Scanner(notices, least)
        for batch in batches:
            found = [scanner.scan(t.as_py()) for t in batch.column("text")]
            best = [min(f, key=lambda x: (-x[1], x[0]), default=(None, None)) for f in found]
            yield pa.RecordBatch.from_arrays(
                [
                    batch.column("doc_id"),
                    pa.array([len(f) for f in found], pa.int64()),
                    pa.array([",".join(sorted({x[0] for x in f})) for f in found], pa.string()),
                    pa.array([b[0] for b in best], pa.string()),
                    pa.array([b[1] for b in best], pa.float64()),
                    pa.array([",".join(f"{n}:{s}:{e}" for n, _, s, e in f) for f in found], pa.string()),
                ],
                names=["doc_id", "n_licences", "licences", "best_licence", "best_dice", "spans"],
            )

    return slim.mapInArrow(
        lean(kernel),
        "doc_id long, n_licences long, licences string, best_licence string, best_dice double, "
        "spans string",
    )
