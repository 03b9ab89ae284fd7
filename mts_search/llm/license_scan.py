"""Licence scan: matching statistics against a generalised suffix automaton of licence templates.

The templates' words go into one suffix automaton. A text is streamed through it word by word: the
automaton keeps the longest stretch of any template that ends at the current word. Maximal stretches
of ``least`` words or more are anchors; anchors of one template that follow each other in text and
template, a few words apart at most, are chained into a span. A span labels the text if it covers
enough of its template. Words outside the templates' vocabulary reset the automaton, so only runs of
vocabulary words are streamed.

Phrases are counted where their words stand consecutively, whatever lies around them.

Edge cases: null or empty texts have no words, no labels, null places and score 0; repeated rows stay
repeated; texts of any length are read whole.
"""

from __future__ import annotations

from collections import defaultdict
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import text_or_empty

# Phrases and their labels.
PHRASES = (("cc by", "cc-by"), ("general public license", "gpl"), ("all rights reserved", "reserved"))
# Wording of public licences and of the notices that name them.
TEMPLATES = {
    "mit": (
        "released under the mit license",
        "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files the software to deal in the software without restriction including without limitation the rights to use copy modify merge publish distribute sublicense and or sell copies of the software and to permit persons to whom the software is furnished to do so subject to the following conditions the above copyright notice and this permission notice shall be included in all copies or substantial portions of the software",
    ),
    "apache-2.0": (
        "licensed under the apache license version 2 0",
        "licensed under the apache license version 2 0 the license you may not use this file except in compliance with the license you may obtain a copy of the license at http www apache org licenses license 2 0 unless required by applicable law or agreed to in writing software distributed under the license is distributed on an as is basis without warranties or conditions of any kind either express or implied see the license for the specific language governing permissions and limitations under the license",
    ),
    "gpl-3.0": ("this work is licensed under the gnu general public license version 3",),
    "gpl-header": (
        "this program is free software you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation either version 3 of the license or at your option any later version this program is distributed in the hope that it will be useful but without any warranty without even the implied warranty of merchantability or fitness for a particular purpose see the gnu general public license for more details",
    ),
    "bsd": (
        "redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met redistributions of source code must retain the above copyright notice this list of conditions and the following disclaimer redistributions in binary form must reproduce the above copyright notice this list of conditions and the following disclaimer in the documentation and or other materials provided with the distribution",
    ),
    "isc": ("permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted provided that the above copyright notice and this permission notice appear in all copies",),
    "mpl-2.0": ("this source code form is subject to the terms of the mozilla public license v 2 0 if a copy of the mpl was not distributed with this file you can obtain one at http mozilla org mpl 2 0",),
    "cc-by-nc": ("licensed under cc by nc 4 0", "this work is licensed under a creative commons attribution noncommercial 4 0 international license"),
    "cc-by-sa": ("licensed under cc by sa 4 0", "this work is licensed under a creative commons attribution sharealike 4 0 international license"),
    "cc-by": ("licensed under cc by 4 0", "this work is licensed under a creative commons attribution 4 0 international license"),
    "unlicense": ("this is free and unencumbered software released into the public domain",),
    "reserved": ("all rights reserved",),
}
#: A-Z become a-z; all of ASCII that is neither letter nor digit parts words.
TABLE = bytes(c + 32 if 65 <= c <= 90 else c if c >= 128 or 48 <= c <= 57 or 97 <= c <= 122 else 32 for c in range(256))
LEAST, GAP, SHARE = 3, 6, 0.5


def words(text: str) -> list[bytes]:
    return text.encode("utf-8", "replace").translate(TABLE).split()


@dataclass
class Automaton:
    """Suffix automaton of several sequences of word numbers; ``ends`` lists (template, position) of each state."""

    go: list[dict[int, int]]
    link: list[int]
    length: list[int]
    ends: list[list[tuple[int, int]]]

    @classmethod
    def build(cls, sequences: list[list[int]]) -> Automaton:
        self = cls([{}], [-1], [0], [[]])
        for t, seq in enumerate(sequences):
            last = 0
            for p, c in enumerate(seq):
                last = self._extend(last, c)
                self.ends[last].append((t, p))
        for s in sorted(range(1, len(self.go)), key=lambda s: -self.length[s]):  # a state's places are also its suffix's
            if self.link[s] > 0:
                self.ends[self.link[s]] += self.ends[s]
        self.ends = [sorted(set(e)) for e in self.ends]
        return self

    def _state(self, length: int, go: dict[int, int], link: int) -> int:
        self.go.append(go)
        self.link.append(link)
        self.length.append(length)
        self.ends.append([])
        return len(self.go) - 1

    def _split(self, p: int, c: int) -> int:
        """The state reached from ``p`` by ``c``, alone for the words that are as short as p's plus one."""
        q = self.go[p][c]
        if self.length[q] == self.length[p] + 1:
            return q
        twin = self._state(self.length[p] + 1, dict(self.go[q]), self.link[q])
        while p >= 0 and self.go[p].get(c) == q:
            self.go[p][c] = twin
            p = self.link[p]
        self.link[q] = twin
        return twin

    def _extend(self, last: int, c: int) -> int:
        if c in self.go[last]:
            return self._split(last, c)
        new = self._state(self.length[last] + 1, {}, 0)
        p = last
        while p >= 0 and c not in self.go[p]:
            self.go[p][c] = new
            p = self.link[p]
        if p >= 0:
            self.link[new] = self._split(p, c)
        return new

    def statistics(self, seq: list[int]) -> list[tuple[int, int]]:
        """(state, length) of the longest template stretch that ends at each word."""
        state = n = 0
        out = []
        for c in seq:
            while state and c not in self.go[state]:
                state = self.link[state]
                n = self.length[state]
            if c in self.go[state]:
                state = self.go[state][c]
                n += 1
            else:
                state = n = 0
            out.append((state, n))
        return out


class Scanner:
    """Labels and spans of texts; ``templates`` maps labels to wordings."""

    def __init__(self, templates: dict[str, tuple[str, ...]] = TEMPLATES, phrases=PHRASES, least: int = LEAST, gap: int = GAP, share: float = SHARE) -> None:
        self.vocabulary: dict[bytes, int] = {}
        self.labels, sequences = [], []
        for label, wordings in templates.items():
            for wording in wordings:
                self.labels.append(label)
                sequences.append([self.vocabulary.setdefault(w, len(self.vocabulary) + 1) for w in words(wording)])
        self.sizes = [len(s) for s in sequences]
        self.phrases = [([self.vocabulary.setdefault(w, len(self.vocabulary) + 1) for w in words(p)], label) for p, label in phrases]
        self.automaton = Automaton.build(sequences)
        self.least, self.gap, self.share = least, gap, share

    def base(self, ids: np.ndarray) -> dict[str, list[int]]:
        """Starts of each phrase."""
        found: dict[str, list[int]] = {}
        for seq, label in self.phrases:
            n = len(ids) - len(seq) + 1
            if n > 0:
                hit = ids[:n] == seq[0]
                for o, c in enumerate(seq[1:], 1):
                    hit &= ids[o : n + o] == c
                if hit.any():
                    found[label] = sorted([*found.get(label, []), *np.flatnonzero(hit).tolist()])
        return found

    def spans(self, ids: np.ndarray) -> list[tuple[int, int, int, int]]:
        """(template, start word, end word, template words matched) of every chain."""
        known = np.concatenate([[0], (ids > 0).astype(np.int8), [0]])
        edge = np.diff(known)
        anchors: dict[int, list[tuple[int, int, int]]] = defaultdict(list)  # template: (text start, template start, words)
        for a, b in zip(np.flatnonzero(edge == 1).tolist(), np.flatnonzero(edge == -1).tolist(), strict=True):
            if b - a < self.least:
                continue
            stats = self.automaton.statistics(ids[a:b].tolist())
            for i, (state, n) in enumerate(stats):
                if n >= self.least and (i + 1 == len(stats) or stats[i + 1][1] <= n):  # can't grow to the right
                    for t, p in self.automaton.ends[state]:
                        anchors[t].append((a + i + 1 - n, p + 1 - n, n))
        out = []
        for t, found in anchors.items():
            chains: list[list[int]] = []  # [start, end, template end, matched]
            near: list[list[int]] = []  # those that end within the gap; anchors come in order of text, so the others are done
            for s, p, n in sorted(found):
                best = None
                near = [c for c in near if s - c[1] <= self.gap]
                for c in near:
                    skip = max(c[1] - s, c[2] - p, 0)  # words that both anchors hold
                    if n > skip and p - c[2] <= 4 * self.gap and s + n > c[1] and p + n > c[2] and (best is None or c[3] > best[0][3]):
                        best = c, skip
                if best:
                    c, skip = best
                    c[1], c[2], c[3] = s + n, p + n, c[3] + n - skip
                else:
                    near.append([s, s + n, p + n, n])
                    chains.append(near[-1])
            out += [(t, c[0], c[1], c[3]) for c in chains if c[3] >= min(self.sizes[t], max(self.least, self.share * self.sizes[t], 5 if self.sizes[t] >= 5 else 0))]
        return sorted(out, key=lambda x: (x[1], x[2], x[0]))

    def scan(self, text: str) -> dict:
        w = words(text)
        get = self.vocabulary.get
        ids = np.fromiter((get(x, 0) for x in w), np.int32, len(w))
        base = self.base(ids) if ids.any() else {}
        spans = self.spans(ids) if ids.any() else []
        starts = [s for found in base.values() for s in found]
        labels = sorted(set(base) | {self.labels[t] for t, *_ in spans})
        score = max([min(1.0, m / self.sizes[t]) for t, _, _, m in spans], default=0.5 if base else 0.0)
        covered = np.zeros(len(w) + 1, np.int32)
        for _, a, b, _ in spans:
            covered[a] += 1
            covered[b] -= 1
        return {
            "n_words": len(w), "n_base": len(starts), "first_word": min(starts, default=None), "last_word": max(starts, default=None), "base_labels": ",".join(sorted(base)), "labels": ",".join(labels), "score": float(score),
            "n_spans": len(spans), "covered_words": int((np.cumsum(covered) > 0).sum()),
        }


FIELDS = {"n_words": "bigint", "n_base": "bigint", "first_word": "bigint", "last_word": "bigint", "base_labels": "string", "labels": "string", "score": "double", "n_spans": "bigint", "covered_words": "bigint"}


def scan(docs: DataFrame, key: str = "doc_id", scanner: Scanner | None = None) -> DataFrame:
    """``key`` and the scan of each whole text; map-only."""
    scanner = scanner or Scanner()
    kept = docs.select(F.col(key).cast("bigint").alias(key), text_or_empty().alias("text"))
    types = {"bigint": pa.int64(), "string": pa.string(), "double": pa.float64()}

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for big in batches:
            for at in range(0, big.num_rows, 512):
                rows = big.slice(at, 512)
                found = [scanner.scan(t) for t in rows.column(1).to_pylist()]
                yield pa.RecordBatch.from_arrays([rows.column(0), *(pa.array([f[c] for f in found], types[t]) for c, t in FIELDS.items())], names=[key, *FIELDS])

    return kept.mapInArrow(run, ", ".join([f"{key} bigint", *(f"{c} {t}" for c, t in FIELDS.items())]))
