"""Licence scans with a generalised suffix automaton of licence tokens.

A file's words are streamed through the automaton; its matching statistics (the longest template
substring that ends at each word, and through the suffix links the longest of each template) give
base phrases and the maximal matches of every template, and long matches are chained into covered
template spans."""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rowloom.llm.shared import utf8

WORD = re.compile(rb"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")

# Base phrases and their labels.
BASE = {"under the mit license": "mit", "apache license version 2": "apache-2", "cc by nc": "cc-by-nc"}

# Public licence wordings that the method adds.
TEMPLATES = {
    "mit-text": """Permission is hereby granted, free of charge, to any person obtaining a copy of this software
    and associated documentation files (the "Software"), to deal in the Software without restriction, including
    without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies
    of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following
    conditions: The above copyright notice and this permission notice shall be included in all copies or
    substantial portions of the Software.""",
    "isc-text": """Permission to use, copy, modify, and/or distribute this software for any purpose with or without
    fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies.""",
    "bsd-text": """Redistribution and use in source and binary forms, with or without modification, are permitted
    provided that the following conditions are met: Redistributions of source code must retain the above copyright
    notice, this list of conditions and the following disclaimer. Redistributions in binary form must reproduce the
    above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other
    materials provided with the distribution.""",
    "apache-2-notice": """you may not use this file except in compliance with the License. You may obtain a copy of
    the License at http://www.apache.org/licenses/LICENSE-2.0 Unless required by applicable law or agreed to in
    writing, software distributed under the License is distributed on an "AS IS" BASIS, WITHOUT WARRANTIES OR
    CONDITIONS OF ANY KIND, either express or implied.""",
    "gpl-notice": """This program is free software: you can redistribute it and/or modify it under the terms of the
    GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at
    your option) any later version.""",
    "gpl": "licensed under the GNU General Public License",
    "cc-by-sa": "licensed under a Creative Commons Attribution-ShareAlike 4.0 International License",
    "cc0": "has waived all copyright and related or neighboring rights to this work",
    "all-rights-reserved": "all rights reserved",
}
#: Words of the shortest match that is chained (or the whole template, if that is shorter).
MIN_MATCH = 4
#: Words that may stand between two matches of one chain, and the covered part that gives a label.
MAX_GAP, COVERED = 40, 0.6


def words_of(text: bytes) -> list[bytes]:
    return WORD.findall(text.lower())


class SuffixAutomaton:
    """All substrings of several token sequences, built online; states know where they end."""

    def __init__(self, sequences: list[list[int]]):
        self.moves: list[dict[int, int]] = [{}]
        self.link, self.length = [-1], [0]
        self.ends: list[list[tuple[int, int]]] = [[]]
        for k, sequence in enumerate(sequences):
            last = 0
            for i, token in enumerate(sequence):
                last = self._extend(last, token)
                self.ends[last].append((k, i))
        for s in sorted(range(1, len(self.link)), key=self.length.__getitem__, reverse=True):
            if self.link[s] > 0:
                self.ends[self.link[s]].extend(self.ends[s])
        self.ends = [sorted(set(e)) for e in self.ends]

    def _state(self, length: int, link: int, moves: dict[int, int]) -> int:
        self.length.append(length)
        self.link.append(link)
        self.moves.append(moves)
        self.ends.append([])
        return len(self.length) - 1

    def _split(self, p: int, token: int, q: int) -> int:
        clone = self._state(self.length[p] + 1, self.link[q], dict(self.moves[q]))
        while p >= 0 and self.moves[p].get(token) == q:
            self.moves[p][token] = clone
            p = self.link[p]
        self.link[q] = clone
        return clone

    def _extend(self, last: int, token: int) -> int:
        q = self.moves[last].get(token)
        if q is not None:
            return q if self.length[q] == self.length[last] + 1 else self._split(last, token, q)
        state, p = self._state(self.length[last] + 1, 0, {}), last
        while p >= 0 and token not in self.moves[p]:
            self.moves[p][token] = state
            p = self.link[p]
        if p >= 0:
            q = self.moves[p][token]
            self.link[state] = q if self.length[q] == self.length[p] + 1 else self._split(p, token, q)
        return state

    def step(self, state: int, length: int, token: int) -> tuple[int, int]:
        """The longest matched suffix after one more token, as a state and its length."""
        while token not in self.moves[state]:
            if state == 0:
                return 0, 0
            state = self.link[state]
            length = self.length[state]
        return self.moves[state][token], length + 1


@dataclass
class Span:
    """A chain of matches: template label, first and last word of the file, covered part of the template."""

    label: str
    first: int
    last: int
    covered: float


class LicenseScanner:
    def __init__(self, base: dict[str, str] | None = None, templates: dict[str, str] | None = None):
        base = BASE if base is None else base
        templates = TEMPLATES if templates is None else templates
        texts = [*base.items(), *((t, label) for label, t in templates.items())]
        split = [words_of(t.encode()) for t, _ in texts]
        self.labels = [label for _, label in texts]
        self.n_base = len(base)
        self.vocabulary = {w: i for i, w in enumerate(dict.fromkeys(w for s in split for w in s))}
        self.sizes = [len(s) for s in split]
        self.automaton = SuffixAutomaton([[self.vocabulary[w] for w in s] for s in split])
        # a state ends with a base phrase if the phrase's last token is among its ends
        self.phrases = [
            [k for k, i in ends if k < self.n_base and i == self.sizes[k] - 1] for ends in self.automaton.ends
        ]
        self.need = [min(MIN_MATCH, n) for n in self.sizes]
        self.shortest = min([MIN_MATCH, *self.sizes])
        #: The word that follows each word of a template; -2 after its last.
        self.following = [[*(self.vocabulary[w] for w in s[1:]), -2] for s in split]
        #: For each state, places of its suffixes in templates where the state itself does not end.
        self.inner: list[list[tuple[int, int, int]]] = [[] for _ in self.automaton.link]
        for state in sorted(range(1, len(self.automaton.link)), key=self.automaton.length.__getitem__):
            up = self.automaton.link[state]
            length, own = self.automaton.length[up], set(self.automaton.ends[state])
            fresh = [(k, e, length) for k, e in self.automaton.ends[up] if (k, e) not in own and length >= self.need[k]]
            known = {(k, e) for k, e, _ in fresh} | own
            self.inner[state] = fresh + [x for x in self.inner[up] if x[:2] not in known]

    def scan(self, words: list[bytes]) -> tuple[list[tuple[int, int]], list[Span]]:
        """(phrase, first word) of every base phrase's places, and the chained spans of the templates."""
        n, places = len(words), []
        matches: dict[int, list[tuple[int, int, int]]] = {}
        known = np.fromiter((self.vocabulary.get(w, -1) for w in words), "int64", n)
        inside = np.concatenate([[False], known >= 0, [False]])
        edges = np.flatnonzero(inside[1:] != inside[:-1]).reshape(-1, 2)
        step, sizes, need, following = self.automaton.step, self.sizes, self.need, self.following
        for a, b in edges[edges[:, 1] - edges[:, 0] >= self.shortest].tolist():
            state = length = 0
            run = [*known[a:b].tolist(), -1]
            for i in range(b - a):
                state, length = step(state, length, run[i])
                if length < self.shortest:
                    continue
                for k in self.phrases[state]:
                    if length >= sizes[k]:
                        places.append((k, a + i - sizes[k] + 1))
                # a match ends for a template where its next word is not the file's
                after = run[i + 1]
                for k, e in self.automaton.ends[state]:
                    if following[k][e] != after and length >= need[k]:
                        matches.setdefault(k, []).append((a + i - length + 1, e - length + 1, length))
                for k, e, m in self.inner[state]:
                    if following[k][e] != after:
                        matches.setdefault(k, []).append((a + i - m + 1, e - m + 1, m))
        return places, self._chains(matches)

    def _chains(self, matches: dict[int, list[tuple[int, int, int]]]) -> list[Span]:
        """Per template: matches in file order, those near each other chained along the template."""
        spans = []
        for k, found in matches.items():
            found.sort()
            group: list[tuple[int, int, int]] = []
            reach = -1
            for m in [*found, None]:
                if group and (m is None or m[0] > reach + MAX_GAP):
                    spans += self._best(k, group)
                    group = []
                if m is not None:
                    group.append(m)
                    reach = max(reach, m[0] + m[2])
        return sorted((s for s in spans if s.covered >= COVERED), key=lambda s: (s.first, s.last, s.label))

    def _best(self, k: int, group: list[tuple[int, int, int]]) -> list[Span]:
        """The chain with most covered words: words of the matches that rise in the file and in the
        template, so that matches which overlap are cut. A prefix-maximum tree over template positions
        has the best chain up to each."""
        size = self.sizes[k]
        tree: list[tuple[int, int, int]] = [(0, 0, 0)] * (size + 1)
        words = sorted({(first + j, -at - j) for first, at, length in group for j in range(length)})
        top = (0, 0, 0)
        for i, minus in words:
            at = -minus
            best, j = (0, 0, 0), at
            while j > 0:
                best = max(best, tree[j])
                j -= j & -j
            # of equally long chains, that which starts first
            chain = (best[0] + 1, best[1] if best[0] else -i, -i)
            if chain > top:
                top = chain
            j = at + 1
            while j <= size and tree[j] < chain:
                tree[j] = chain
                j += j & -j
        return [Span(self.labels[k], -top[1], -top[2], top[0] / size)] if top[0] else []


def scan_licenses(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", spans: bool = True) -> DataFrame:
    """doc_id, n_words, n_base, first_word, last_word, base_labels, labels, score and, with `spans`,
    spans array<struct<label, first, last, covered>>.

    Base phrases count at every place, overlapping or not; first_word and last_word are the
    smallest and largest start (null without one). labels has the base labels and those of
    templates covered by COVERED or more; score is the largest covered part of any template, 1
    with a base phrase. Null and empty texts have no words, no labels and score 0; ids may be null
    or repeat; extra columns are ignored."""
    kind = ", spans array<struct<label:string,first:int,last:int,covered:double>>" if spans else ""
    schema = (
        "doc_id long, n_words long, n_base long, first_word long, last_word long, base_labels string, labels string, "
        f"score double{kind}"
    )

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scanner = LicenseScanner()
        fields = [("label", pa.string()), ("first", pa.int32()), ("last", pa.int32()), ("covered", pa.float64())]
        types = [pa.int64()] * 4 + [pa.string()] * 2 + [pa.float64(), pa.list_(pa.struct(fields))]
        names = ["doc_id", "n_words", "n_base", "first_word", "last_word", "base_labels", "labels", "score", "spans"]
        for batch in batches:
            for part in (batch.slice(i, 256) for i in range(0, batch.num_rows, 256)):
                rows = []
                for cell in part.column(1):
                    words = words_of(cell.as_py())
                    places, found = scanner.scan(words)
                    starts = [p for _, p in places]
                    base = {scanner.labels[k] for k, _ in places}
                    labels = base | {s.label for s in found}
                    score = 1.0 if base else max([0.0, *(s.covered for s in found)])
                    rows.append(
                        (
                            len(words), len(places), min(starts, default=None), max(starts, default=None),
                            ",".join(sorted(base)), ",".join(sorted(labels)), min(1.0, score),
                            [vars(s) for s in found],
                        )
                    )
                columns = [pa.array(x, t) for x, t in zip(zip(*rows, strict=True), types, strict=True)]
                yield pa.RecordBatch.from_arrays([part.column(0), *columns][: 8 + spans], names=names[: 8 + spans])

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), utf8(text_col).alias("text")).mapInArrow(run, schema)
