"""License scans by patience alignment.

A text and a license template are aligned like two versions of a file: words that occur once
in each are anchors; the longest increasing subsequence of their positions is kept, and the
gaps between anchors are aligned in the same way, with the words that are unique within the
gap. Gaps without unique words are closed by matching their equal ends. Coverage is the share
of the template's words that are aligned, within a stretch of the text that is at most twice
the template's length. Where a notice is repeated nearby no word is unique, so besides the
stretch around needed words, windows of one to two template lengths are aligned, placed where
a needed word says that the template begins.

All covered notices of a text are listed in `notices`, by place; those of one template do not
overlap, those of different templates may (a one-line MIT notice covers 4 of 5 words of the
BSD line). The other columns tell of the best one.

A text is aligned only with templates of which it has a needed word: a covering alignment
matches COVERAGE of the template's words, so of any set of words that makes up more than the
rest at least one must occur. The rarest such set is searched for first, over whole texts.

Defined results: null and empty texts have no license and coverage 0; of equal coverage the
longer template wins, then the first by name; repeated rows are scanned alike.
"""

from __future__ import annotations

import re
from bisect import bisect_left, insort
from collections import Counter

import ahocorasick
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import types as T

from .common import map_arrow

COVERAGE = 0.8

# Public license notices.
TEMPLATES = {
    "mit-line": "Released under the MIT License.",
    "apache-2.0-line": "Licensed under the Apache License, Version 2.0.",
    "bsd-line": "Released under the BSD License.",
    "gpl-3.0-line": "Licensed under the GNU General Public License, version 3.",
    "mpl-2.0-line": "Licensed under the Mozilla Public License, version 2.0.",
    "cc-by-4.0-line": "This work is licensed under a Creative Commons Attribution 4.0 International License.",
    "apache-2.0": 'Licensed under the Apache License, Version 2.0 (the "License"); you may not use this file except in '
    "compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0 "
    "Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on "
    'an "AS IS" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. See the License for the '
    "specific language governing permissions and limitations under the License.",
    "mit": "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated "
    'documentation files (the "Software"), to deal in the Software without restriction, including without limitation the '
    "rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to "
    "permit persons to whom the Software is furnished to do so, subject to the following conditions: The above copyright "
    "notice and this permission notice shall be included in all copies or substantial portions of the Software. THE SOFTWARE "
    'IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF '
    "MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS "
    "BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, "
    "OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE.",
    "isc": "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby "
    "granted, provided that the above copyright notice and this permission notice appear in all copies.",
    "bsd-2-clause": "Redistribution and use in source and binary forms, with or without modification, are permitted provided "
    "that the following conditions are met: 1. Redistributions of source code must retain the above copyright notice, this "
    "list of conditions and the following disclaimer. 2. Redistributions in binary form must reproduce the above copyright "
    "notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with "
    'the distribution. THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS "AS IS" AND ANY EXPRESS OR IMPLIED '
    "WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE "
    "ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, "
    "SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; "
    "LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN "
    "CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, "
    "EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE.",
    "gpl-3.0": "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General "
    "Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any "
    "later version.",
}
WORD = re.compile(r"[^\W_]+(?:[.-][^\W_]+)*")


def words_of(text: str) -> list[str]:
    return WORD.findall(text.lower())


def longest_increasing(values: list[int]) -> list[int]:
    """Indices of one longest strictly increasing subsequence."""
    tops: list[int] = []
    at: list[int] = []
    back: list[int] = []
    for i, v in enumerate(values):
        k = bisect_left(tops, v)
        if k == len(tops):
            tops.append(v)
            at.append(i)
        else:
            tops[k], at[k] = v, i
        back.append(at[k - 1] if k else -1)
    out, i = [], at[-1] if at else -1
    while i >= 0:
        out.append(i)
        i = back[i]
    return out[::-1]


def align(text: list[str], template: list[str]) -> list[tuple[int, int]]:
    """Aligned (text position, template position) pairs, increasing in both."""
    out: list[tuple[int, int]] = []
    stack = [(0, len(text), 0, len(template))]
    while stack:
        a, b, c, d = stack.pop()
        while a < b and c < d and text[a] == template[c]:
            out.append((a, c))
            a, c = a + 1, c + 1
        while a < b and c < d and text[b - 1] == template[d - 1]:
            b, d = b - 1, d - 1
            out.append((b, d))
        if a >= b or c >= d:
            continue
        in_template = Counter(template[c:d])
        in_text = Counter(w for w in text[a:b] if w in in_template)
        where = {w: i for i, w in enumerate(template[c:d], c) if in_template[w] == 1 and in_text[w] == 1}
        if not where:
            continue
        pairs = [(i, where[w]) for i, w in enumerate(text[a:b], a) if w in where]
        anchors = [pairs[i] for i in longest_increasing([p for _, p in pairs])]
        out += anchors
        edges = [(a - 1, c - 1), *anchors, (b, d)]
        stack += [(x + 1, y, p + 1, q) for (x, p), (y, q) in zip(edges, edges[1:], strict=False) if y - x > 1 and q - p > 1]
    return sorted(out)


def densest(pairs: list[tuple[int, int]], n_template: int) -> list[tuple[int, int]]:
    """The most pairs within a stretch of twice the template's length."""
    best, begin = [], 0
    for end in range(len(pairs)):
        while pairs[end][0] - pairs[begin][0] >= 2 * n_template:
            begin += 1
        if end + 1 - begin > len(best):
            best = pairs[begin : end + 1]
    return best


def needed_words(template: list[str], coverage: float) -> list[str]:
    """Words that make up more than 1 - coverage of the template: an alignment that covers
    it has one of them. Long and singular words are taken first."""
    counts = Counter(template)
    need, have, out = (1 - coverage) * len(template), 0, []
    for w in sorted(counts, key=lambda w: (w not in RARE, counts[w], -len(w), w)):
        if have > need:
            break
        out.append(w)
        have += counts[w]
    return out


# Words that ordinary prose seldom has.
RARE = set("license licensed mit apache bsd gnu mozilla sublicense redistributions redistribution copyright commons".split())


class Scanner:
    def __init__(self, templates: dict[str, str], coverage: float = COVERAGE) -> None:
        self.coverage = coverage
        self.templates = {k: words_of(v) for k, v in templates.items()}
        self.needed: dict[str, set[str]] = {}
        for name, words in self.templates.items():
            for w in needed_words(words, coverage):
                self.needed.setdefault(w, set()).add(name)
        self.search = ahocorasick.Automaton()
        for w in self.needed:
            self.search.add_word(w, w)
        if len(self.search):
            self.search.make_automaton()

    def places(self, low: str) -> dict[str, list[int]]:
        """Character positions of needed words, by template."""
        out: dict[str, list[int]] = {}
        n = len(low)
        for end, w in self.search.iter(low) if len(self.search) else ():
            start = end - len(w) + 1
            if (start and low[start - 1].isalnum()) or (end + 1 < n and low[end + 1].isalnum()):
                continue
            for name in self.needed[w]:
                out.setdefault(name, []).append(start)
        return out

    def scan(self, text: str | None) -> tuple[str | None, float, int, int, int, list[tuple]]:
        """(license, coverage, matched words, first and end word of the stretch) of the best
        notice, and the list of all."""
        low = (text or "").lower()
        wanted = self.places(low)
        if not wanted:
            return None, 0.0, 0, 0, 0, []
        words = words_of(low)
        best = (None, 0.0, 0, 0, 0)
        key = (0.0, 0)
        found = []
        for name in sorted(wanted):
            template = self.templates[name]
            for n_pairs, first, end in self.notices(words, template):
                share = n_pairs / len(template)
                found.append((name, share, n_pairs, first, end))
                if (share, len(template)) > key:
                    key = (share, len(template))
                    best = found[-1]
        return *best, sorted(found, key=lambda x: (x[3], x[4], x[0]))

    def notices(self, words: list[str], template: list[str]) -> list[tuple[int, int, int]]:
        """Covered (matched words, first, end) of one template that do not overlap: the fullest
        first, then the shortest, then the first in the text. What is left of a stretch between
        them is searched again."""
        taken: list[tuple[int, int, int]] = []  # first, end, matched words; in order
        open_ = self.stretches(words, template)[::-1]
        while open_:
            a, b = open_.pop()
            at = bisect_left(taken, (b,)) - 1  # the last to begin before b
            if at >= 0 and taken[at][1] > a:  # stretches overlap
                open_ += [(x, y) for x, y in ((a, taken[at][0]), (taken[at][1], b)) if x < y]
                continue
            chosen: list[tuple[int, int, int]] = []
            for n_pairs, first, end in sorted(self.candidates(words, template, a, b), key=lambda x: (-x[0], x[2] - x[1], x[1])):
                if all(end <= y[0] or y[1] <= first for y in chosen):
                    chosen.append((first, end, n_pairs))
            for x in chosen:
                insort(taken, x)
            if chosen:
                open_.append((a, b))
        return [(n_pairs, first, end) for first, end, n_pairs in sorted(taken, key=lambda x: (-x[2], x[0]))]

    def candidates(self, words: list[str], template: list[str], a: int, b: int) -> set[tuple[int, int, int]]:
        """Covered alignments of the stretch and of the windows around its needed words."""
        n = len(template)
        at: dict[str, list[int]] = {}
        for i, w in enumerate(template):
            if w in self.needed:
                at.setdefault(w, []).append(i)
        windows = {(a, b)}
        for i in range(a, b):
            for p in at.get(words[i], ()):
                windows |= {(max(a, i - p - more), min(b, i - p + n + more)) for more in (0, n // 4, n // 2)}
        have = Counter(template)
        out: set[tuple[int, int, int]] = set()
        whole_to = a  # windows within whole notices need no look
        for x, y in sorted(windows):
            if y <= whole_to:
                continue
            near = Counter(w for w in words[x:y] if w in have)
            if sum(min(k, have[w]) for w, k in near.items()) < self.coverage * n:
                continue  # too few of the template's words in any order
            pairs = densest(align(words[x:y], template), n)
            if len(pairs) / n >= self.coverage:
                out.add((len(pairs), x + pairs[0][0], x + pairs[-1][0] + 1))
                if len(pairs) == n and pairs[-1][0] - pairs[0][0] == n - 1:
                    whole_to = x + pairs[-1][0] + 1
        return out

    def stretches(self, words: list[str], template: list[str]) -> list[tuple[int, int]]:
        """Stretches of the text around runs of the template's needed words: uniqueness of
        anchors is judged near the license, not over a long text."""
        n = len(template)
        need = {w for w in set(template) if w in self.needed}
        at = [i for i, w in enumerate(words) if w in need]
        out: list[tuple[int, int]] = []
        for i in at:
            a, b = max(0, i - 2 * n), min(len(words), i + 2 * n + 1)
            if out and i < out[-1][1] - n and b - out[-1][0] <= 6 * n:
                out[-1] = (out[-1][0], b)
            elif not out or out[-1][1] < b:
                out.append((a, b))
        return out


def scan(df: DataFrame, templates: dict[str, str] | None = None, text: str = "text", coverage: float = COVERAGE) -> DataFrame:
    """Add license, coverage, matched_words, first_word, end_word and notices to every row;
    whole texts."""
    added = [("license", T.StringType()), ("coverage", T.DoubleType()), ("matched_words", T.LongType()), ("first_word", T.LongType()), ("end_word", T.LongType())]
    added.append(("notices", T.ArrayType(T.StructType([T.StructField(n, t) for n, t in added]))))
    df = df.drop(*[n for n, _ in added])
    names, at = df.columns, df.columns.index(text)
    schema = T.StructType([*df.schema.fields, *(T.StructField(n, t) for n, t in added)])
    chosen = templates or TEMPLATES
    fields = [n for n, _ in added[:-1]]
    made: list[Scanner] = []

    def run(batch: pa.RecordBatch) -> pa.RecordBatch:
        if not made:
            made.append(Scanner(chosen, coverage))
        rows = [made[0].scan(t) for t in batch.column(at).to_pylist()]
        kinds = [pa.string(), pa.float64(), pa.int64(), pa.int64(), pa.int64()]
        one = pa.struct(list(zip(fields, kinds, strict=True)))
        new = [pa.array([r[i] for r in rows], k) for i, k in enumerate(kinds)]
        new.append(pa.array([[dict(zip(fields, x, strict=True)) for x in r[5]] for r in rows], pa.list_(one)))
        return pa.record_batch([*[batch.column(i) for i in range(len(names))], *new], names=schema.names)

    return map_arrow(df, run, schema)
