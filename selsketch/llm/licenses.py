"""Licence scan with a generalised suffix automaton of licence tokens.

The automaton of all templates gives, word by word, the longest run that ends there and occurs in some template (matching
statistics).  Long maximal runs are chained per template in order, and every stretch of text whose chain covers enough of the
template is reported.  Words outside the templates' vocabulary reset the automaton, so only stretches of known words are streamed.
"""

from __future__ import annotations

import bisect
import math
import re
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import docs_of, kept_in_worker, map_batches, small_batches
from .text import NON_ALNUM, split_words, words_of

#: Phrases of the base rule and their labels.
PHRASES = {"mit license": "mit", "apache license": "apache", "general public license": "gpl"}
#: Standard public licence texts and notices.
TEMPLATES = {
    "mit-text": """Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated
documentation files (the "Software"), to deal in the Software without restriction, including without limitation the rights to use, copy,
modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished
to do so, subject to the following conditions: The above copyright notice and this permission notice shall be included in all copies or
substantial portions of the Software. THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT
LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT.""",
    "apache-notice": """Licensed under the Apache License, Version 2.0 (the "License"); you may not use this file except in compliance with
the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0 Unless required by applicable law or agreed
to in writing, software distributed under the License is distributed on an "AS IS" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND,
either express or implied. See the License for the specific language governing permissions and limitations under the License.""",
    "gpl-notice": """This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public
License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version. This program is
distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR
A PARTICULAR PURPOSE. See the GNU General Public License for more details.""",
    "bsd-text": """Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following
conditions are met: Redistributions of source code must retain the above copyright notice, this list of conditions and the following
disclaimer. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in
the documentation and/or other materials provided with the distribution.""",
    "isc-text": """Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted,
provided that the above copyright notice and this permission notice appear in all copies.""",
    "bsd-disclaimer": """THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS "AS IS" AND ANY EXPRESS OR IMPLIED WARRANTIES,
INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL
THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING,
BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON
ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE
OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE.""",
    "mpl-notice": """This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed
with this file, You can obtain one at http://mozilla.org/MPL/2.0/.""",
    "lgpl-notice": """This library is free software; you can redistribute it and/or modify it under the terms of the GNU Lesser General Public
License as published by the Free Software Foundation; either version 2.1 of the License, or (at your option) any later version. This library is
distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A
PARTICULAR PURPOSE. See the GNU Lesser General Public License for more details.""",
    "zlib-text": """This software is provided 'as-is', without any express or implied warranty. In no event will the authors be held liable for any
damages arising from the use of this software. Permission is granted to anyone to use this software for any purpose, including commercial
applications, and to alter it and redistribute it freely, subject to the following restrictions""",
    "unlicense-text": """This is free and unencumbered software released into the public domain. Anyone is free to copy, modify, publish, use,
compile, sell, or distribute this software, either in source code form or as a compiled binary, for any purpose, commercial or non-commercial,
and by any means.""",
    "boost-text": """Permission is hereby granted, free of charge, to any person or organization obtaining a copy of the software and accompanying
documentation covered by this license (the "Software") to use, reproduce, display, distribute, execute, and transmit the Software, and to
prepare derivative works of the Software, and to permit third-parties to whom the Software is furnished to do so""",
    "mit-line": "Released under the MIT License.",
    "apache-line": "Licensed under the Apache License, Version 2.0.",
    "gpl-line": "This work is licensed under the GNU General Public License, version 3.",
}
LEAST_RUN, COVERAGE, GAP = 4, 0.6, 30
_WORD = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")


def words_in(text: str) -> list[str]:
    return _WORD.findall(re.sub("[A-Z]", lambda m: m[0].lower(), text))


class SuffixAutomaton:
    """All substrings of several token sequences.  The end positions of a state's substrings are one slice of ``marks``: the
    prefixes below the state in the tree of suffix links, in depth-first order."""

    def __init__(self, sequences: list[list[int]]):
        self.length, self.link, self.next = [0], [-1], [{}]
        own: dict[int, list[tuple[int, int]]] = {}
        for which, tokens in enumerate(sequences):
            last = 0
            for at, c in enumerate(tokens):
                last = self._extend(last, c)
                own.setdefault(last, []).append((which, at + 1))
        below: list[list[int]] = [[] for _ in self.link]
        for s, up in enumerate(self.link[1:], 1):
            below[up].append(s)
        self.marks: list[tuple[int, int]] = []
        self.first, self.last = [0] * len(self.link), [0] * len(self.link)
        todo = [(0, False)]
        while todo:
            s, done = todo.pop()
            if done:
                self.last[s] = len(self.marks)
                continue
            self.first[s] = len(self.marks)
            self.marks += own.get(s, [])
            todo.append((s, True))
            todo += [(x, False) for x in below[s]]

    def ends(self, state: int) -> list[tuple[int, int]]:
        """Every (sequence, end position) of the state's substrings."""
        return self.marks[self.first[state] : self.last[state]]

    def _new(self, length: int, link: int, moves: dict[int, int]) -> int:
        self.length.append(length)
        self.link.append(link)
        self.next.append(moves)
        return len(self.length) - 1

    def _extend(self, last: int, c: int) -> int:
        if c in self.next[last]:
            q = self.next[last][c]
            return q if self.length[q] == self.length[last] + 1 else self._clone(last, c, q)
        new, p = self._new(self.length[last] + 1, 0, {}), last
        while p != -1 and c not in self.next[p]:
            self.next[p][c] = new
            p = self.link[p]
        if p != -1:
            q = self.next[p][c]
            self.link[new] = q if self.length[q] == self.length[p] + 1 else self._clone(p, c, q)
        return new

    def _clone(self, p: int, c: int, q: int) -> int:
        copy = self._new(self.length[p] + 1, self.link[q], dict(self.next[q]))
        self.link[q] = copy
        while p != -1 and self.next[p].get(c) == q:
            self.next[p][c] = copy
            p = self.link[p]
        return copy

    def runs(self, tokens: list[int], least: int) -> list[tuple[int, int, int]]:
        """Matching statistics as right-maximal runs of at least ``least`` tokens: (start, end, state)."""
        out, at, length = [], 0, 0
        for i, c in enumerate(tokens):
            if c not in self.next[at] and length >= least:
                out.append((i - length, i, at))
            while at and c not in self.next[at]:
                at = self.link[at]
                length = self.length[at]
            if c in self.next[at]:
                at, length = self.next[at][c], length + 1
        if length >= least:
            out.append((len(tokens) - length, len(tokens), at))
        return out


class Matcher:
    """Runs of a text in each template.  A run in one template lies inside a run of the automaton of all templates, so the
    common automaton streams the text, and each distinct run it finds is looked up in the other templates once."""

    def __init__(self, sequences: list[list[int]]):
        self.all, self.each = SuffixAutomaton(sequences), [SuffixAutomaton([s]) for s in sequences]
        self.seen: dict[tuple[int, int], list[tuple[int, int, int, int]]] = {}

    def _inside(self, tokens: list[int], state: int, least: int) -> list[tuple[int, int, int, int]]:
        """(template, start, end, end in the template) of the runs in a stretch that the state stands for."""
        if (key := (state, len(tokens))) not in self.seen:
            found = [(which, 0, len(tokens), to) for which, to in self.all.ends(state)]
            whole = {x[0] for x in found}
            for which, own in enumerate(self.each):
                if which not in whole:
                    found += [(which, s, e, to) for s, e, at in own.runs(tokens, least) for _, to in own.ends(at)]
            if len(self.seen) >= 1 << 16:  # a bound of memory, not of results
                self.seen.clear()
            self.seen[key] = found
        return self.seen[key]

    def anchors(self, tokens: list[int], least: int) -> dict[int, list[tuple[int, int, int]]]:
        """template -> (start, end, end in the template) of every run that no longer one of this template contains."""
        found: dict[int, set[tuple[int, int, int]]] = {}
        for start, end, state in self.all.runs(tokens, least):
            for which, s, e, to in self._inside(tokens[start:end], state, least):
                found.setdefault(which, set()).add((start + s, start + e, to))
        out = {}
        for which, own in found.items():
            kept, reach, begun = [], -1, -1
            for s, e, to in sorted(own, key=lambda a: (a[0], -a[1], a[2])):
                if e > reach or (e == reach and s == begun):
                    kept.append((s, e, to))
                    reach, begun = e, s
            out[which] = kept
        return out


@dataclass
class Templates:
    names: list[str]
    size: list[int]
    matcher: Matcher
    hashes: np.ndarray
    token: np.ndarray
    phrases: list[tuple[str, np.ndarray]]


def _hash(words: list[str]) -> np.ndarray:
    data = np.frombuffer("".join(words).encode(), np.uint8)
    ptr = np.append(0, np.cumsum([len(w.encode()) for w in words])).astype(np.int64)
    return split_words(data, ptr, NON_ALNUM).hash


def prepare(templates: dict[str, str] = TEMPLATES, phrases: dict[str, str] = PHRASES) -> Templates:
    texts = {k: words_in(v) for k, v in templates.items()}
    vocabulary = sorted({w for ws in texts.values() for w in ws})
    number = {w: i for i, w in enumerate(vocabulary)}
    hashes = _hash(vocabulary)
    order = np.argsort(hashes)
    return Templates(list(texts), [len(w) for w in texts.values()], Matcher([[number[w] for w in ws] for ws in texts.values()]), hashes[order], order, [(label, _hash(words_in(p))) for p, label in phrases.items()])


def chains(anchors: list[tuple[int, int, int]], size: int, least: int, gap: int = GAP) -> tuple[int, list[tuple[int, int, int]]]:
    """Covered spans of one template: (most words covered by a chain, [(covered, first word, end word)]).

    A chain's runs are in order in the text and in the template, at most ``gap`` words apart in the text; what overlaps counts
    once.  Each run ends one candidate, its best chain (of equal ones the shortest); of the candidates that cover at least
    ``least`` words, the set without overlaps that covers most is returned.
    """
    best: list[tuple[int, int, int, int]] = []  # covered, end in the template, end, first word
    ended: list[int] = []
    for start, end, to in sorted(anchors, key=lambda a: (a[1], a[0], a[2])):
        top = (end - start, to, end, start)
        for covered, t_end, x_end, x_start in best[bisect.bisect_left(ended, start - gap) :]:
            new = min(end - start, to - t_end, end - x_end)
            if new > 0 and (covered + new, x_start) > (top[0], top[3]):
                top = (covered + new, to, end, x_start)
        best.append(top)
        ended.append(end)
    passing = sorted({(e, s, c) for c, _, e, s in best if c >= least})
    ends = [p[0] for p in passing]
    total: list[tuple[int, int | None]] = [(0, None)]  # covered by the best set among the first candidates, its last one
    for i, (_, s, c) in enumerate(passing):
        with_it = total[bisect.bisect_right(ends, s, 0, i)][0] + c
        total.append((with_it, i) if with_it > total[-1][0] else (total[-1][0], total[-1][1]))
    spans, at = [], len(passing)
    while at and (i := total[at][1]) is not None:
        e, s, c = passing[i]
        spans.append((min(c, size), s, e))
        at = bisect.bisect_right(ends, s, 0, i)
    return min(max((b[0] for b in best), default=0), size), spans[::-1]


def licenses(docs: DataFrame, templates: dict[str, str] = TEMPLATES, phrases: dict[str, str] = PHRASES, least: int = LEAST_RUN, coverage: float = COVERAGE) -> DataFrame:
    """docs(doc_id, text) -> (doc_id, n_words, n_base, first_word, last_word, base_labels, labels, score, spans).

    Words are runs of lower-cased letters and digits.  ``spans``: label:first word:end word of every covered template span.
    score is the largest coverage, at least 0.5 where a base phrase stands.  Null and empty texts have no words: counts 0,
    empty labels, score 0.  Repeated ids give repeated rows; other columns are ignored.
    """
    small_batches(docs.sparkSession)

    def step(batch: pa.RecordBatch):
        known = kept_in_worker(("licences", repr(templates), repr(phrases)), lambda: prepare(templates, phrases))
        ids = batch.column("doc_id")
        for lo, hi, words in words_of(batch.column("text"), NON_ALNUM, lower=True):
            n, h = words.rows, words.hash
            count, first, last = np.zeros(n, np.int64), [None] * n, [None] * n
            base: list[set] = [set() for _ in range(n)]
            found: list[set] = [set() for _ in range(n)]
            spans: list[list] = [[] for _ in range(n)]
            score = np.zeros(n)
            for label, phrase in known.phrases:
                at = words.windows(len(phrase))
                for j, x in enumerate(phrase):
                    at = at[h[at + j] == x]
                for i, r in zip(at, words.row_of(at), strict=True):
                    place = int(i - words.ptr[r])
                    count[r] += 1
                    first[r] = place if first[r] is None else min(first[r], place)
                    last[r] = place if last[r] is None else max(last[r], place)
                    base[r].add(label)
                    score[r] = max(score[r], 0.5)
            if len(h):
                at = np.minimum(np.searchsorted(known.hashes, h), len(known.hashes) - 1)
                token = np.where(known.hashes[at] == h, known.token[at], -1)
                inside = np.append(token >= 0, False)
                edge = np.zeros(len(h) + 1, bool)
                edge[words.ptr] = True
                begins = np.flatnonzero(inside[:-1] & (edge[:-1] | ~np.append(False, inside[:-2])))
                stops = np.flatnonzero(inside[:-1] & (edge[1:] | ~inside[1:])) + 1
                long = stops - begins >= least
                stretches: dict[int, dict[int, list]] = {}
                for a, b in zip(begins[long], stops[long], strict=True):
                    r = int(words.row_of(a))
                    shift = int(a - words.ptr[r])
                    for which, own in known.matcher.anchors(token[a:b].tolist(), least).items():
                        stretches.setdefault(r, {}).setdefault(which, []).extend((s + shift, e + shift, to) for s, e, to in own)
                for r, by_template in stretches.items():
                    for which, own in by_template.items():
                        size = known.size[which]
                        most, covered = chains(own, size, math.ceil(coverage * size - 1e-9))
                        score[r] = max(score[r], most / size)
                        if covered:
                            found[r].add(known.names[which])
                            spans[r] += [(x_start, x_end, known.names[which]) for _, x_start, x_end in covered]
            yield {
                "doc_id": ids.slice(lo, hi - lo), "n_words": words.counts().astype(np.int64), "n_base": count, "first_word": first, "last_word": last,
                "base_labels": [",".join(sorted(b)) for b in base], "labels": [",".join(sorted(b | f)) for b, f in zip(base, found, strict=True)],
                "score": np.minimum(score, 1.0), "spans": [",".join(f"{k}:{a}:{b}" for a, b, k in sorted(s)) for s in spans],
            }

    kinds = {"doc_id": "long", "n_words": "long", "n_base": "long", "first_word": "long", "last_word": "long", "base_labels": "string", "labels": "string", "score": "double", "spans": "string"}
    return map_batches(docs.select(F.col("doc_id").cast("long"), F.col("text").cast("string")), step, **kinds)


def op8_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    """doc_id, n_words, n_base, first_word, last_word, base_labels, labels, score and spans for every document."""
    return licenses(docs_of(spark, sf_dir))
