"""Licence scans with a generalised suffix automaton over the words of licence notices.

The automaton holds every run of words of every template, with all places where a run stands. A text streams through it once
and gives, at each word, the length of the longest template run that ends there (matching statistics). Runs of at least `min_run`
words that cannot be extended are chained, per template, in the order of both text and template, so that most words are covered; a chain
that covers enough of its template is a find. Short fixed phrases are counted besides, exactly.
"""

from __future__ import annotations

from bisect import bisect
from collections.abc import Iterator
from dataclasses import dataclass, field

import pyarrow as pa
from pyspark.sql import DataFrame

from .common import as_bytes, id_text

#: Public licence notices, their openings and some whole texts.
TEMPLATES = [
    ("mit", "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the Software), to deal in the Software without restriction"),
    ("mit", "released under the MIT license"),
    ("mit", "licensed under the MIT license"),
    ("apache", "licensed under the Apache license version 2 0"),
    ("apache", "you may not use this file except in compliance with the License. You may obtain a copy of the License at"),
    ("gpl", "this work is licensed under the GNU General Public License version 3"),
    ("gpl", "This program is free software; you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation"),
    ("bsd", "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met"),
    ("isc", "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted"),
    ("mpl", "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0"),
    ("cc-by-nc", "licensed under cc by nc 4 0"),
    ("cc-by", "this work is licensed under a Creative Commons Attribution 4 0 International license"),
    (
        "mit",
        "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the Software), to deal in the Software without restriction, "
        "including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, "
        "subject to the following conditions: The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software. "
        "THE SOFTWARE IS PROVIDED AS IS, WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. "
        "IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH "
        "THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE.",
    ),
    (
        "apache",
        "Licensed under the Apache License, Version 2.0 (the License); you may not use this file except in compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0 "
        "Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an AS IS BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. "
        "See the License for the specific language governing permissions and limitations under the License.",
    ),
    (
        "gpl",
        "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, "
        "or (at your option) any later version. This program is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE. "
        "See the GNU General Public License for more details. You should have received a copy of the GNU General Public License along with this program. If not, see http://www.gnu.org/licenses/",
    ),
    (
        "bsd",
        "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: "
        "1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer. "
        "2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution. "
        "3. Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission. "
        "THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS AS IS AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. "
        "IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES",
    ),
    (
        "isc",
        "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies. "
        "THE SOFTWARE IS PROVIDED AS IS AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. "
        "IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, "
        "NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE.",
    ),
    (
        "mpl",
        "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can obtain one at http://mozilla.org/MPL/2.0/.",
    ),
    (
        "zlib",
        "This software is provided as-is, without any express or implied warranty. In no event will the authors be held liable for any damages arising from the use of this software. "
        "Permission is granted to anyone to use this software for any purpose, including commercial applications, and to alter it and redistribute it freely, subject to the following restrictions",
    ),
    (
        "unlicense",
        "This is free and unencumbered software released into the public domain. Anyone is free to copy, modify, publish, use, compile, sell, or distribute this software, either in source code form or as a compiled binary, "
        "for any purpose, commercial or non-commercial, and by any means.",
    ),
]
BASE = [("mit", ("mit", "license")), ("apache", ("apache", "license")), ("gpl", ("general", "public", "license"))]

_LOW = bytes(c + 32 if 65 <= c <= 90 else c for c in range(256))
_TO_WORDS = bytes(w if (w := _LOW[c]) >= 0x80 or 48 <= w <= 57 or 97 <= w <= 122 else 32 for c in range(256))


def words_of(text: bytes) -> list[bytes]:
    """Runs of 0-9, a-z and bytes from 0x80 on, after lower-casing A-Z."""
    return text.translate(_TO_WORDS).split()


@dataclass
class SuffixAutomaton:
    """Of many word sequences. ends: for each state, every (template, place of a word in it) where its runs end; there after `close`."""

    nexts: list[dict[bytes, int]] = field(default_factory=lambda: [{}])
    link: list[int] = field(default_factory=lambda: [-1])
    length: list[int] = field(default_factory=lambda: [0])
    prefixes: dict[int, list[tuple[int, int]]] = field(default_factory=dict)
    ends: list[tuple[tuple[int, int], ...]] = field(default_factory=list)

    def _state(self, length: int, nexts: dict, link: int) -> int:
        self.nexts.append(dict(nexts))
        self.link.append(link)
        self.length.append(length)
        return len(self.length) - 1

    def _split(self, p: int, word: bytes) -> int:
        """The state that stands for exactly the run of p and the word."""
        q = self.nexts[p][word]
        if self.length[p] + 1 == self.length[q]:
            return q
        copy = self._state(self.length[p] + 1, self.nexts[q], self.link[q])
        while p >= 0 and self.nexts[p].get(word) == q:
            self.nexts[p][word] = copy
            p = self.link[p]
        self.link[q] = copy
        return copy

    def add(self, words: list[bytes], template: int) -> None:
        last = 0
        for place, word in enumerate(words):
            if word in self.nexts[last]:
                last = self._split(last, word)
            else:
                new, p = self._state(self.length[last] + 1, {}, 0), last
                while p >= 0 and word not in self.nexts[p]:
                    self.nexts[p][word] = new
                    p = self.link[p]
                if p >= 0:
                    self.link[new] = self._split(p, word)
                last = new
            self.prefixes.setdefault(last, []).append((template, place))

    def close(self, least: int = 1) -> None:
        """Hand every end mark down the suffix links, once all templates are in: states split off later get theirs too. States whose runs are all shorter
        than `least` words are left without."""
        ends: list[set] = [set(self.prefixes.get(s, ())) for s in range(len(self.length))]
        for s in sorted(range(1, len(self.length)), key=lambda s: -self.length[s]):
            if self.length[self.link[s]] >= least:
                ends[self.link[s]] |= ends[s]
        self.ends = [tuple(sorted(e)) if n >= least else () for e, n in zip(ends, self.length, strict=True)]

    def matches(self, words: list[bytes], least: int) -> dict[int, list[tuple[int, int, int]]]:
        """For each template, (start, length, place of the last word in it) of every common run of at least `least` words that can be
        extended on neither side, by end. A shorter run that another template shares stands further up the suffix links."""
        out: dict[int, list[tuple[int, int, int]]] = {}
        state, n = 0, 0
        before: dict[tuple[int, int], int] = {}  # runs that end at the word before: (template, place), length
        for i in range(len(words) + 1):
            now: dict[tuple[int, int], int] = {}
            if i < len(words):
                word = words[i]
                while state and word not in self.nexts[state]:
                    state = self.link[state]
                    n = self.length[state]
                if word in self.nexts[state]:
                    state, n = self.nexts[state][word], n + 1
                if n >= least:
                    s, size = state, n
                    while size >= least:
                        for at in self.ends[s]:
                            now.setdefault(at, size)
                        s = self.link[s]
                        size = self.length[s]
            for (t, place), size in before.items():
                if (t, place + 1) not in now:
                    out.setdefault(t, []).append((i - size, size, place))
            before = now
        return out


def chains(matches: list[tuple[int, int, int]], gap: int) -> list[tuple[int, int, int]]:
    """(words covered, first, last word) of the chain that covers most of those that end with each match.

    matches: (start, length, place of the last word in the template), by end. A later match follows an earlier one if it ends further on in text
    and template, at most `gap` words lie between them in the text, and what it adds beyond the earlier one's end in the text lies beyond its end
    in the template too.
    """
    best: list[tuple[int, int]] = []
    for i, (start, n, place) in enumerate(matches):
        top = (n, start)
        for j in range(i - 1, -1, -1):
            s, m, p = matches[j]
            if s + m < start - gap:
                break
            fresh = min(n, start + n - s - m)
            if fresh > 0 and p <= place - fresh and best[j][0] + fresh > top[0]:
                top = (best[j][0] + fresh, best[j][1])
        best.append(top)
    return [(covered, first, s + m - 1) for (covered, first), (s, m, _) in zip(best, matches, strict=True)]


class LicenceScanner:
    def __init__(self, templates=tuple(TEMPLATES), min_run: int = 3, gap: int = 12):
        texts = [words_of(text.encode()) for _, text in templates]
        self.names = [label for label, _ in templates]
        self.sizes = [len(t) for t in texts]
        self.min_run, self.gap = min_run, gap
        self.auto = SuffixAutomaton()
        for i, t in enumerate(texts):
            self.auto.add(t, i)
        self.auto.close(min_run)

    def least(self, template: int) -> float:
        """Words of a template that a find covers at least."""
        n = self.sizes[template]
        return min(n, max(4, 0.6 * n, min(12, 0.8 * n)))

    def spans(self, words: list[bytes]) -> list[tuple[str, float, int, int]]:
        """(label, covered share of the template, first word, last word) of every chain that covers enough of its template.

        Chains of one template do not overlap: those that cover most are taken first, on a tie the one that ends first.
        """
        found = []
        for t, every in self.auto.matches(words, self.min_run).items():
            least, taken = self.least(t), []
            if sum(n for _, n, _ in every) < least:
                continue
            for covered, first, last in sorted(chains(every, self.gap), key=lambda c: (-c[0], c[2])):
                if covered < least:
                    break
                at = bisect(taken, (first, last))
                if (at == 0 or taken[at - 1][1] < first) and (at == len(taken) or taken[at][0] > last):
                    taken.insert(at, (first, last))
                    found.append((self.names[t], min(1.0, covered / self.sizes[t]), first, last))
        return sorted(found, key=lambda x: (x[2], x[0], x[3]))


def base_places(words: list[bytes]) -> list[tuple[int, str]]:
    """(start, label) of every place where the words of a fixed phrase stand one after the other."""
    out = []
    at = -1
    for _ in range(words.count(b"license")):
        at = words.index(b"license", at + 1)
        for label, phrase in BASE:
            n = len(phrase)
            if at - n + 1 >= 0 and words[at - n + 1 : at + 1] == [w.encode() for w in phrase]:
                out.append((at - n + 1, label))
    return sorted(out)


def scan_licences(docs: DataFrame) -> DataFrame:
    """One row per document: doc_id, n_words, n_base, first_word, last_word, base_labels, labels, score, spans.

    Null text is empty and has zero words, no places and score 0. spans lists label, covered share, first and last
    word of each chain. score: 1 where a fixed phrase stands, else the largest covered share of a template found, else 0. Repeated rows give
    repeated results; texts of any length are read whole; an empty table gives an empty result.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scanner = LicenceScanner()
        names = ["doc_id", "n_words", "n_base", "first_word", "last_word", "base_labels", "labels", "score", "spans"]
        for batch in batches:
            rows = []
            for doc_id, text in zip(batch.column("doc_id").to_pylist(), as_bytes(batch.column("text")), strict=True):
                words = words_of(text or b"")
                base, spans = base_places(words), scanner.spans(words)
                own = sorted({label for _, label in base})
                labels = sorted({*own, *(s[0] for s in spans)})
                score = 1.0 if base else max((s[1] for s in spans), default=0.0)
                rows.append((doc_id, len(words), len(base), base[0][0] if base else None, base[-1][0] if base else None, ",".join(own), ",".join(labels), score, ";".join(f"{a}:{c:.3f}:{f}:{z}" for a, c, f, z in spans)))
            kinds = [pa.int64()] * 5 + [pa.string(), pa.string(), pa.float64(), pa.string()]
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), kinds, strict=True)] if rows else [pa.array([], k) for k in kinds], names=names)

    return id_text(docs).mapInArrow(run, "doc_id long, n_words long, n_base long, first_word long, last_word long, base_labels string, labels string, score double, spans string")
