"""Licence scan with a generalised suffix automaton of template tokens.

The automaton of all templates is small (bounded by their length) and goes to every task. A file's tokens run through
it once: the matching statistic at a token is the length of the longest template substring that ends there. Maximal
matches of ``min_match`` tokens or more are chained, in file and template order, into covered template spans; a
template is found if its chain covers enough of it.
"""

from __future__ import annotations

from collections.abc import Iterator, Mapping
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ordjoin.llm import kernels as K
from ordjoin.llm.common import map_arrow, slices, table

#: fixed values: phrases that count as base labels
PHRASES = {"mit": "mit license", "apache": "apache license", "gpl": "general public license"}
#: fixed values: wording of common licence notices
TEMPLATES = {
    "apache": "Licensed under the Apache License, Version 2.0 (the \"License\"); you may not use this file except in compliance with the License. You may obtain a copy of the License at",
    "apache-short": "Licensed under the Apache License, Version 2.0.",
    "bsd": "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met",
    "cc-by": "This work is licensed under a Creative Commons Attribution 4.0 International License",
    "cc-by-nc": "Licensed under CC BY-NC 4.0.",
    "gpl": "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation",
    "gpl-short": "This work is licensed under the GNU General Public License, version 3.",
    "mit": "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files",
    "mit-short": "Released under the MIT License.",
    "mpl": "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0",
    "apache-text": "Licensed under the Apache License, Version 2.0 (the \"License\"); you may not use this file except in compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0 Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an \"AS IS\" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. See the License for the specific language governing permissions and limitations under the License.",
    "bsd-text": "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: 1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer. 2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution. 3. Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission. THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS \"AS IS\" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE.",
    "gpl-text": "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version. This program is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE. See the GNU General Public License for more details. You should have received a copy of the GNU General Public License along with this program. If not, see <https://www.gnu.org/licenses/>.",
    "isc-text": "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies. THE SOFTWARE IS PROVIDED \"AS IS\" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE.",
    "mit-text": "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions: The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software. THE SOFTWARE IS PROVIDED \"AS IS\", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE.",
    "mpl-text": "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can obtain one at http://mozilla.org/MPL/2.0/.",
    "unlicense-text": "This is free and unencumbered software released into the public domain. Anyone is free to copy, modify, publish, use, compile, sell, or distribute this software, either in source code form or as a compiled binary, for any purpose, commercial or non-commercial, and by any means.",
    "zlib-text": "This software is provided 'as-is', without any express or implied warranty. In no event will the authors be held liable for any damages arising from the use of this software. Permission is granted to anyone to use this software for any purpose, including commercial applications, and to alter it and redistribute it freely, subject to the following restrictions: 1. The origin of this software must not be misrepresented; you must not claim that you wrote the original software. If you use this software in a product, an acknowledgment in the product documentation would be appreciated but is not required. 2. Altered source versions must be plainly marked as such, and must not be misrepresented as being the original software. 3. This notice may not be removed or altered from any source distribution.",
}
MIN_MATCH, MIN_COVER, MAX_GAP = 4, 0.7, 10
GAP = np.ones(256, bool)
GAP[[*range(0x30, 0x3A), *range(0x61, 0x7B), *range(0x80, 0x100)]] = False


def tokens_of(raw: np.ndarray, ends: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Hash of each token of lower-cased bytes, and each document's first token."""
    low = K.LOWER[raw]
    starts, stops, first = K.word_spans(low, ends, GAP)
    return K.word_hashes(low, starts, stops), first


def hashes_of(text: str) -> list[int]:
    raw = np.frombuffer(text.encode(), np.uint8)
    return tokens_of(raw, np.array([0, len(raw)]))[0].tolist()


@dataclass
class SuffixAutomaton:
    """Of several token sequences; ``ends[s]``: (template, last token) of every occurrence of state s's strings."""

    step: list[dict[int, int]] = field(default_factory=lambda: [{}])
    link: list[int] = field(default_factory=lambda: [-1])
    length: list[int] = field(default_factory=lambda: [0])
    ends: list[set[tuple[int, int]]] = field(default_factory=lambda: [set()])
    marks: list[tuple[int, int, int]] = field(default_factory=list)

    def _state(self, length: int, step: dict[int, int], link: int) -> int:
        self.step.append(step), self.length.append(length), self.link.append(link), self.ends.append(set())
        return len(self.step) - 1

    def _grow(self, last: int, token: int) -> int:
        found = self.step[last].get(token)
        if found is not None and self.length[found] == self.length[last] + 1:
            return found
        new = self._state(self.length[last] + 1, {}, 0) if found is None else -1
        at = last
        while at != -1 and token not in self.step[at]:
            self.step[at][token] = new
            at = self.link[at]
        if at == -1:
            return new
        to = self.step[at][token]
        if self.length[to] == self.length[at] + 1:
            self.link[new] = to
            return new
        twin = self._state(self.length[at] + 1, dict(self.step[to]), self.link[to])
        while at != -1 and self.step[at].get(token) == to:
            self.step[at][token] = twin
            at = self.link[at]
        self.link[to] = twin
        if new == -1:
            return twin
        self.link[new] = twin
        return new

    def add(self, number: int, tokens: list[int]) -> None:
        last = 0
        for i, t in enumerate(tokens):
            last = self._grow(last, t)
            self.marks.append((last, number, i))

    def finish(self) -> SuffixAutomaton:
        """Hand each end down to the shorter strings of its suffix links."""
        for s, number, i in self.marks:
            self.ends[s].add((number, i))
        for s in sorted(range(1, len(self.step)), key=lambda x: -self.length[x]):
            if self.link[s] > 0:
                self.ends[self.link[s]] |= self.ends[s]
        return self

    def statistics(self, tokens: list[int]) -> Iterator[tuple[int, int]]:
        """(length, state) of the longest match that ends at each token."""
        s = n = 0
        for t in tokens:
            while s and t not in self.step[s]:
                s = self.link[s]
                n = self.length[s]
            if t in self.step[s]:
                s, n = self.step[s][t], n + 1
            yield n, s


@dataclass
class Scanner:
    names: list[str]
    lengths: list[int]
    automaton: SuffixAutomaton
    vocabulary: np.ndarray

    @staticmethod
    def of(templates: Mapping[str, str]) -> Scanner:
        names, sequences = sorted(templates), [hashes_of(templates[k]) for k in sorted(templates)]
        automaton = SuffixAutomaton()
        for i, s in enumerate(sequences):
            automaton.add(i, s)
        return Scanner(names, [len(s) for s in sequences], automaton.finish(), np.unique(np.array([t for s in sequences for t in s], np.uint64)))

    def matches(self, tokens: list[int], first: int, least: int) -> list[tuple[int, int, int]]:
        """(file end, length, state) of maximal matches: those that the next token doesn't lengthen."""
        out, before = [], (0, 0)
        for i, (n, s) in enumerate(self.automaton.statistics(tokens)):
            if before[0] >= least and n <= before[0]:
                out.append((first + i, *before))
            before = (n, s)
        if before[0] >= least:
            out.append((first + len(tokens), *before))
        return out

    def covered(self, found: list[tuple[int, int, int]]) -> dict[str, tuple[float, list[tuple[int, int]]]]:
        """Template -> (share of it that its best chain covers, file spans of that chain).

        Every place that a matched string has in a template may stand in the chain; a hit may follow any one that ends
        within the template's reach before it.
        """
        by: dict[int, list[tuple[int, int, int, int]]] = {}
        for end, n, s in found:
            for number, i in sorted(self.automaton.ends[s]):
                by.setdefault(number, []).append((end - n, end, i + 1 - n, i + 1))
        out = {}
        for number, places in by.items():
            reach = self.lengths[number] + MAX_GAP
            hits = np.array(places, np.int64)
            a, b, x, y = hits.T
            best, back = y - x, np.full(len(hits), -1)
            least = np.searchsorted(b, a - reach)  # hits come in the order of their ends
            for j in range(1, len(hits)):
                lo = int(least[j])
                fits = (y[lo:j] < y[j]) & (x[lo:j] < x[j]) & (a[lo:j] < a[j])
                more = np.where(fits, best[lo:j] + y[j] - np.maximum(x[j], y[lo:j]), 0)
                if len(more) and more.max() > best[j]:
                    best[j], back[j] = more.max(), lo + int(more.argmax())
            j = int(best.argmax())
            spans, share = [], float(best[j]) / self.lengths[number]
            while j != -1:
                spans.append((int(a[j]), int(b[j])))
                j = int(back[j])
            out[self.names[number]] = (min(1.0, share), spans[::-1])
        return out


def scan(docs: DataFrame, templates: Mapping[str, str] = TEMPLATES, min_match: int = MIN_MATCH, min_cover: float = MIN_COVER) -> DataFrame:
    """Per document: doc_id, n_words, base_places (array of (label, word)), covers (array of (template, share, spans)).

    Null and empty texts have no words and no labels; rows are judged one by one, so ids may repeat or be null. A
    template shorter than ``min_match`` tokens can't be found.
    """
    scanner = Scanner.of(templates)
    phrases = {k: hashes_of(v) for k, v in PHRASES.items()}
    schema = "doc_id long, n_words long, base_places array<struct<label:string,word:long>>, covers array<struct<template:string,share:double,spans:array<struct<a:long,b:long>>>>"
    kind = pa.list_(pa.struct([("label", pa.string()), ("word", pa.int64())]))
    cover_kind = pa.list_(pa.struct([("template", pa.string()), ("share", pa.float64()), ("spans", pa.list_(pa.struct([("a", pa.int64()), ("b", pa.int64())])))]))

    def each(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        vocabulary = scanner.vocabulary
        for batch in batches:
            counts: list[int] = []
            bases: list[list] = [[] for _ in range(batch.num_rows)]
            covers: list[list] = [[] for _ in range(batch.num_rows)]
            for a, b, raw, ends in slices(batch.column(1), 1 << 20):
                tokens, first = tokens_of(raw, ends)
                counts += np.diff(first).tolist()
                if not len(tokens):
                    continue
                for label, words in phrases.items():
                    m = len(words)
                    hit = np.ones(max(0, len(tokens) - m + 1), bool)
                    for j, w in enumerate(words):
                        hit &= tokens[j : j + len(hit)] == np.uint64(w)
                    for at in np.flatnonzero(hit).tolist():
                        d = int(np.searchsorted(first, at, side="right")) - 1
                        if at + m <= first[d + 1]:
                            bases[a + d].append((label, at - int(first[d])))
                spot = np.minimum(np.searchsorted(vocabulary, tokens), len(vocabulary) - 1)
                known = np.zeros(len(tokens) + 1, bool)
                known[:-1] = vocabulary[spot] == tokens
                edge = np.zeros(len(tokens) + 1, bool)
                edge[first] = True
                begin = np.flatnonzero(known & (edge | ~np.concatenate([[False], known[:-1]])))
                after = np.concatenate([known[1:], [False]])
                stop = np.flatnonzero(known & (~after | np.concatenate([edge[1:], [True]]))) + 1
                found: dict[int, list] = {}
                for x, y in zip(begin.tolist(), stop.tolist(), strict=True):
                    if y - x >= min_match:
                        d = int(np.searchsorted(first, x, side="right")) - 1
                        found.setdefault(d, []).extend(scanner.matches(tokens[x:y].tolist(), x - int(first[d]), min_match))
                for d, hits in found.items():
                    covers[a + d] = [{"template": t, "share": share, "spans": [{"a": p, "b": q} for p, q in spans]} for t, (share, spans) in sorted(scanner.covered(hits).items())]
            base = [[{"label": x, "word": w} for x, w in sorted(rows, key=lambda r: r[1])] for rows in bases]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(counts, pa.int64()), pa.array(base, kind), pa.array(covers, cover_kind)], names=["doc_id", "n_words", "base_places", "covers"])

    body = F.coalesce(F.col("text"), F.lit("")).cast("binary")
    return map_arrow(docs.select(F.col("doc_id").cast("long"), body), each, schema)



def op8_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = scan(table(spark, sf_dir, "documents").select("doc_id", "text"))
    base = F.transform("base_places", lambda x: x["label"])
    own = F.transform(F.filter("covers", lambda x: x["share"] >= MIN_COVER), lambda x: F.regexp_replace(x["template"], "-(short|text)$", ""))
    joined = lambda x: F.array_join(F.array_sort(F.array_distinct(x)), ",")
    return out.select(
        "doc_id",
        "n_words",
        F.size("base_places").cast("long").alias("n_base"),
        F.array_min(F.transform("base_places", lambda x: x["word"])).alias("first_word"),
        F.array_max(F.transform("base_places", lambda x: x["word"])).alias("last_word"),
        joined(base).alias("base_labels"),
        joined(F.concat(base, own)).alias("labels"),
        F.coalesce(F.array_max(F.transform("covers", lambda x: x["share"])), F.lit(0.0)).alias("score"),
    )
