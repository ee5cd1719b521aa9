"""License notices and texts in documents, by winnowed fingerprints and banded alignment.

Templates are the whole texts in ``licenses/`` and the notices below, by which
licenses are applied. They are cut into word triples; winnowing keeps the smallest
hash of every window of triples, so any stretch of ``WINDOW + GRAM - 1`` words that a
document shares with a template holds a kept fingerprint; notices of up to ``SHORT``
words keep all theirs. The fingerprints are an inverted index to (template, place). A document's triples that are in the index are
chained per template: places that go on in both, with a drift of at most ``BAND``
words from one to the next. Along each chain a local alignment over words, in a
band, finds what is matched, changed, added or left out.

A match has the template's name, its coverage, and the span of the document from
its first to its last matched word, in characters of the text as it is. Coverage is
matched words over the template's words and the span's unmatched words together,
so an inserted word costs as much as a missing one. A notice of up to ``SHORT`` words
is reported from a coverage of ``COVERAGE`` on; of longer templates every passage of
at least ``PASSAGE`` matched words that make up ``COVERAGE`` of its span is, with the
coverage it has. Of matches that overlap, the one with the best alignment stays.

The index is as large as the templates, a parameter; documents are read whole, one
at a time, with no shuffle.

Defined results: null and empty texts have no match; repeated notices are separate
matches with their own spans; rows that repeat are scanned again; ties go to the
template that comes first by name; an empty table gives an empty result; extra
columns are ignored.
"""

from __future__ import annotations

import hashlib
import re
from collections import defaultdict
from collections.abc import Iterator
from importlib import resources

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from subgraph_engine.storage import text_batches

GRAM = 3
WINDOW = 4
BAND = 6
#: Words from one fingerprint of a chain to the next, and words that are looked at before and after it.
REACH = 40
SHORT = 16
PASSAGE = 12
COVERAGE = 0.75
MATCH, CHANGE, GAP = 2, -1, -1

# Notices by which public licenses are applied.
NOTICES: dict[str, list[str]] = {
    "AGPL-3.0": [
        "This work is licensed under the GNU Affero General Public License, version 3.",
        "This program is free software: you can redistribute it and/or modify it under the terms of the GNU Affero General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version.",
    ],
    "Apache-2.0": [
        "Licensed under the Apache License, Version 2.0.",
        'Licensed under the Apache License, Version 2.0 (the "License"); you may not use this file except in compliance with the License. You may obtain a copy of the License at',
        'Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an "AS IS" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied.',
    ],
    "CC-BY-4.0": [
        "Licensed under CC BY 4.0.",
        "This work is licensed under a Creative Commons Attribution 4.0 International License.",
    ],
    "CC-BY-NC-4.0": [
        "Licensed under CC BY-NC 4.0.",
        "This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International License.",
    ],
    "CC-BY-SA-4.0": [
        "Licensed under CC BY-SA 4.0.",
        "This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License.",
    ],
    "EPL-2.0": [
        "This program and the accompanying materials are made available under the terms of the Eclipse Public License 2.0 which is available at",
    ],
    "GPL-2.0": [
        "This work is licensed under the GNU General Public License, version 2.",
        "This program is free software; you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation; either version 2 of the License, or (at your option) any later version.",
    ],
    "GPL-3.0": [
        "This work is licensed under the GNU General Public License, version 3.",
        "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version.",
    ],
    "LGPL-2.1": [
        "This library is free software; you can redistribute it and/or modify it under the terms of the GNU Lesser General Public License as published by the Free Software Foundation; either version 2.1 of the License, or (at your option) any later version.",
    ],
    "LGPL-3.0": [
        "This work is licensed under the GNU Lesser General Public License, version 3.",
    ],
    "MIT": [
        "Released under the MIT License.",
        "Licensed under the MIT License.",
    ],
    "MPL-2.0": [
        "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0.",
    ],
}

_WORD = re.compile(r"[^\W_]+(?:\.[0-9]+)*")


def templates_of_files() -> dict[str, list[str]]:
    """The notices, and the whole texts beside them."""
    found = {name: list(texts) for name, texts in NOTICES.items()}
    for file in resources.files("subgraph_engine.llm").joinpath("licenses").iterdir():
        if file.name.endswith(".txt"):
            found.setdefault(file.name.removesuffix(".txt"), []).append(file.read_text(encoding="utf-8"))
    return found


def words_of(text: str) -> list[str]:
    return _WORD.findall(text.lower())


def winnow(hashes: list[int], window: int = WINDOW) -> set[int]:
    """Places of the smallest hash of each window, the last of equals."""
    if len(hashes) <= window:
        return {min(range(len(hashes)), key=lambda k: (hashes[k], -k))} if hashes else set()
    return {min(range(a, a + window), key=lambda k: (hashes[k], -k)) for a in range(len(hashes) - window + 1)}


class TemplateIndex:
    """Fingerprints of templates; words are numbered by the templates' vocabulary, 0 is any other."""

    def __init__(self, templates: dict[str, list[str]] | None = None):
        templates = templates_of_files() if templates is None else templates
        self.names = [name for name in sorted(templates) for _ in templates[name]]
        words = [words_of(text) for name in sorted(templates) for text in templates[name]]
        vocabulary = sorted({w for own in words for w in own})
        self.number = {w: k + 1 for k, w in enumerate(vocabulary)}
        self.base = len(vocabulary) + 1
        self.words = [[self.number[w] for w in own] for own in words]
        self.vocabulary = [set(own) for own in self.words]
        self.places: dict[int, list[tuple[int, int]]] = defaultdict(list)
        for t, own in enumerate(self.words):
            grams = self.grams(np.array(own, np.int64)).tolist()
            # mixed, so that "smallest" is no matter of the alphabet
            for k in winnow([(g * 0x9E3779B97F4A7C15) & (2**64 - 1) for g in grams], 1 if len(own) <= SHORT else WINDOW):
                self.places[grams[k]].append((t, k))
        self.keys = np.array(sorted(self.places), np.int64)

    def grams(self, ids: np.ndarray) -> np.ndarray:
        """Numbers of all word triples; -1 where a word is no template's."""
        if len(ids) < GRAM:
            return np.empty(0, np.int64)
        parts = [ids[k : len(ids) - GRAM + 1 + k] for k in range(GRAM)]
        whole = (parts[0] * self.base + parts[1]) * self.base + parts[2]
        return np.where(np.minimum.reduce(parts) > 0, whole, -1)

    def hits(self, grams: np.ndarray) -> list[int]:
        """Places of a document's triples that are in the index."""
        usable = np.flatnonzero(grams >= 0)
        if not len(usable) or not len(self.keys):
            return []
        at = np.minimum(np.searchsorted(self.keys, grams[usable]), len(self.keys) - 1)
        return usable[self.keys[at] == grams[usable]].tolist()

    def scan(self, text: str | None) -> list[tuple[str, float, int, int, int]]:
        """(license, coverage, matched words, start, end), in order of start."""
        if not text:
            return []
        number = self.number
        lower = text.lower()
        if len(lower) == len(text):  # letter by letter, so places are those of the text
            source, found = lower, _WORD.findall(lower)
        else:
            source, found = text, [w.lower() for w in _WORD.findall(text)]
        ids = np.fromiter((number.get(w, 0) for w in found), np.int64, len(found))
        grams = self.grams(ids)
        at = self.hits(grams)
        if not at:
            return []
        anchors: dict[int, list[tuple[int, int]]] = defaultdict(list)
        for p in at:
            for t, k in self.places[int(grams[p])]:
                anchors[t].append((p, k))
        document = ids.tolist()
        best: set[tuple[int, str, int, int, float, int]] = set()
        found_chains = [(t, chain) for t, places in anchors.items() for chain in chains(places)]
        for t, chain in sorted(found_chains, key=lambda c: -len(c[1])):
            # what lies inside a match that scores more than this chain can would give way to it
            first, last = chain[0][0], chain[-1][0]
            most = MATCH * min(len(self.words[t]), last - first + GRAM + 2 * REACH)
            if any(a <= first and last <= b and -score > most for score, _, a, b, _, _ in best):
                continue
            if match := self._match(t, chain, document):
                best.add(match)
        spans = [m.span() for m in _WORD.finditer(source)] if best else []
        kept: list[tuple[int, str, int, int, float, int]] = []
        for match in sorted(best):
            if all(match[3] < a or match[2] > b for _, _, a, b, _, _ in kept):
                kept.append(match)
        rows = [(name, coverage, matched, spans[a][0], spans[b][1]) for _, name, a, b, coverage, matched in kept]
        return sorted(rows, key=lambda r: (r[3], r[0]))

    def _match(self, t: int, chain: list[tuple[int, int]], document: list[int]) -> tuple[int, str, int, int, float, int] | None:
        """(-score, name, first, last, coverage, matched) of a chain's alignment, where it is worth a report."""
        own = self.words[t]
        short = len(own) <= SHORT
        if short:
            p, k = chain[0]
            near = document[max(0, p - k - BAND) : p - k + len(own) + BAND]
            if len(self.vocabulary[t].intersection(near)) < COVERAGE * len(self.vocabulary[t]):
                return None
        elif chain[-1][0] - chain[0][0] + GRAM + 2 * (WINDOW + GRAM) < PASSAGE:
            return None
        score, matched, a, b = align(own, document, chain)
        span = b - a + 1
        coverage = matched / (len(own) + span - matched)
        good = coverage >= COVERAGE if short else matched >= PASSAGE and matched >= COVERAGE * span
        return (-score, self.names[t], a, b, coverage, matched) if good else None


def chains(places: list[tuple[int, int]]) -> list[list[tuple[int, int]]]:
    """Anchors (place in the document, place in the template) that go on from each other.

    Anchors of one diagonal that are near make a run; runs are linked to the heaviest
    chains, so that a phrase which the template repeats does not lead astray.
    """
    runs: list[list[tuple[int, int]]] = []
    last: dict[int, list[tuple[int, int]]] = {}
    for p, k in sorted(places):
        run = last.get(p - k)
        if run is not None and p - run[-1][0] <= REACH:
            run.append((p, k))
        else:
            last[p - k] = run = [(p, k)]
            runs.append(run)
    weight, before = [len(r) for r in runs], [-1] * len(runs)
    near: list[int] = []  # earlier runs that may go on
    order = sorted(range(len(runs)), key=lambda i: runs[i][-1][0])
    ended = 0
    for i, run in enumerate(runs):
        p, k = run[0]
        while ended < len(order) and runs[order[ended]][-1][0] < p:
            near.append(order[ended])
            ended += 1
        near = [j for j in near if p - runs[j][-1][0] <= REACH]
        for j in near:
            q, m = runs[j][-1]
            if m < k <= m + REACH and abs(p - k - q + m) <= BAND and weight[j] + len(run) > weight[i]:
                weight[i], before[i] = weight[j] + len(run), j
    out, used = [], set()
    for i in sorted(range(len(runs)), key=lambda i: (-weight[i], i)):
        chain, at = [], i
        while at >= 0 and at not in used:
            used.add(at)
            chain.append(at)
            at = before[at]
        if chain:
            out.append([anchor for j in reversed(chain) for anchor in runs[j]])
    return out


#: A cell holds its score above and its matched words below, so comparing cells compares both.
UNIT = 1 << 24


def align(template: list[int], words: list[int], chain: list[tuple[int, int]], band: int = BAND) -> tuple[int, int, int, int]:
    """Score, matched words, first and last matched place in ``words`` of the best local alignment that goes through a chain.

    The band lies around the diagonal of the last anchor, and reaches to that of the next. As it may also hold a
    notice beside the chain's own, only alignments with an anchor in them count.
    """
    hit, miss = MATCH * UNIT + 1, CHANGE * UNIT
    best = (0, -1, -1)
    cells, firsts, lasts, marks, begin = [], [], [], [], 0
    anchors = {k: p for p, k in chain}
    at, size = 0, len(words)
    for i in range(max(0, chain[0][1] - REACH), min(len(template), chain[-1][1] + GRAM + REACH)):
        while at + 1 < len(chain) and chain[at + 1][1] <= i:
            at += 1
        here = chain[at][0] - chain[at][1]
        ahead = chain[min(at + 1, len(chain) - 1)]
        there = ahead[0] - ahead[1] if i >= chain[0][1] else here
        w = template[i]
        low, high = max(0, i + min(here, there) - band), min(size, i + max(here, there) + band + 1)
        row, row_first, row_last, row_mark = [], [], [], []
        left = left_first = left_last = 0
        left_mark = False
        anchor = anchors.get(i, -1)
        held = len(cells)
        for j in range(low, high):
            x = j - 1 - begin
            if 0 <= x < held:
                cell, first, last, mark = cells[x], firsts[x], lasts[x], marks[x]
            else:
                cell, first, last, mark = 0, -1, -1, False
            if words[j] == w:
                if not cell:
                    first, mark = j, False
                cell, last = cell + hit, j
                mark = mark or j == anchor
            else:
                cell += miss
            x += 1
            if 0 <= x < held and cells[x] + GAP * UNIT > cell:
                cell, first, last, mark = cells[x] + GAP * UNIT, firsts[x], lasts[x], marks[x]
            if left + GAP * UNIT > cell:
                cell, first, last, mark = left + GAP * UNIT, left_first, left_last, left_mark
            if cell < UNIT:
                cell, mark = 0, False
            elif mark and cell > best[0]:
                best = (cell, first, last)
            row.append(cell)
            row_first.append(first)
            row_last.append(last)
            row_mark.append(mark)
            left, left_first, left_last, left_mark = cell, first, last, mark
        cells, firsts, lasts, marks, begin = row, row_first, row_last, row_mark, low
    return best[0] // UNIT, best[0] % UNIT, best[1], best[2]


FOUND = "doc_id long, license string, coverage double, matched_words int, span_start int, span_end int"
_indexes: dict[bytes, TemplateIndex] = {}


def _index(templates: dict[str, list[str]]) -> TemplateIndex:
    """Built once in a process."""
    name = hashlib.sha256(repr(sorted(templates.items())).encode()).digest()
    if name not in _indexes:
        _indexes.clear()
        _indexes[name] = TemplateIndex(templates)
    return _indexes[name]


def scan_licenses(docs: DataFrame, templates: dict[str, list[str]] | None = None) -> DataFrame:
    """doc_id, license, coverage, matched_words, span_start, span_end: a row per match."""
    text_batches(docs.sparkSession)
    templates = templates_of_files() if templates is None else templates

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        index = _index(templates)
        kinds = [pa.int64(), pa.string(), pa.float64(), pa.int32(), pa.int32(), pa.int32()]
        names = [c.split()[0] for c in FOUND.split(", ")]
        for batch in batches:
            rows = [
                (doc_id, *match)
                for doc_id, text in zip(batch.column("doc_id").to_pylist(), batch.column("text").to_pylist())
                for match in index.scan(text)
            ]
            columns = zip(*rows) if rows else [()] * len(kinds)
            yield pa.RecordBatch.from_arrays([pa.array(list(c), k) for c, k in zip(columns, kinds)], names)

    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(run, FOUND)


def licenses_of_documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan_licenses(spark.read.parquet(f"{sf_dir}/documents.parquet"))
