"""License scans by conditional compression.

Candidate blocks are the lines of a text around words that license wordings
can't do without. A block of any length is cut into overlapping windows, twice as
long as the templates that they are held against, so that every notice lies whole
in one of them. Every distinct window is compressed alone and once with each
template as a zstandard raw dictionary; the bytes that the dictionary saves are
taken as a share of the template's own compressed size. All templates that reach
a least share are confirmed by exact wording differences: the words of window and
template are aligned, and what the window lacks, adds or changes inside the
aligned span decides between ``exact``, ``modified`` and ``none``.

Templates are the public short notices and opening grants of common licenses;
the list is a parameter. Templates without a usual license word are sought around
the words that they begin with.

Defined results: null and empty texts have no candidates; repeated blocks count
each time; ties between templates go to the earlier template; an empty table
gives no rows; extra columns are ignored.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass, field, replace
from difflib import SequenceMatcher

import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fedlake.llm.runtime import WordCache, slices, strings

# fixed values: license wordings by SPDX identifier
TEMPLATES: tuple[tuple[str, str], ...] = (
    ("MIT", "Released under the MIT License."),
    ("MIT", "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions: The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software."),
    ("Apache-2.0", "Licensed under the Apache License, Version 2.0."),
    ("Apache-2.0", "Licensed under the Apache License, Version 2.0 (the \"License\"); you may not use this file except in compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0"),
    ("GPL-3.0-only", "This work is licensed under the GNU General Public License, version 3."),
    ("GPL-3.0-or-later", "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version."),
    ("LGPL-2.1-or-later", "This library is free software; you can redistribute it and/or modify it under the terms of the GNU Lesser General Public License as published by the Free Software Foundation; either version 2.1 of the License, or (at your option) any later version."),
    ("BSD-3-Clause", "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution. Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission."),
    ("BSD-2-Clause", "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution."),
    ("ISC", "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies."),
    ("MPL-2.0", "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can obtain one at http://mozilla.org/MPL/2.0/."),
    ("CC-BY-NC-4.0", "Licensed under CC BY-NC 4.0."),
    ("CC-BY-4.0", "Licensed under CC BY 4.0."),
    ("CC-BY-SA-4.0", "Licensed under CC BY-SA 4.0."),
    ("CC-BY-4.0", "This work is licensed under a Creative Commons Attribution 4.0 International License."),
    ("CC-BY-SA-4.0", "This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License."),
    ("CC-BY-NC-4.0", "This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International License."),
    ("Unlicense", "This is free and unencumbered software released into the public domain. Anyone is free to copy, modify, publish, use, compile, sell, or distribute this software, either in source code form or as a compiled binary, for any purpose, commercial or non-commercial, and by any means."),
    ("LicenseRef-all-rights-reserved", "All rights reserved."),
)
ANCHOR = re.compile(r"licen[cs]e|copyright|permission|redistribut|public domain|free software|rights reserved|creative commons", re.I)
_WORD = re.compile(r"\w+(?:[.\-/+]\w+)*")
_SPACE = re.compile(r"\s")
#: A line joins a block if an anchor line is at most so many lines away.
REACH = 2
#: Characters of the shortest windows' step, and how much longer than its template a notice may be; steps double.
STEP = 256
LONGER = 1.3
#: Saved share from which a template is confirmed by wording.
MIN_SAVED = 0.1
#: Wording verdicts: share of the template's words found, and differing words per template word.
MIN_FOUND = 0.8
MAX_CHANGED = 0.25
LEVEL = 3


@dataclass(frozen=True)
class Wording:
    """How a block words a template, and the place of its words from the first to the last match."""

    missing: int
    added: int
    words: int
    start: int = field(default=0, compare=False)
    stop: int = field(default=0, compare=False)

    @property
    def verdict(self) -> str:
        if self.missing == self.added == 0:
            return "exact"
        return "modified" if self.missing <= (1 - MIN_FOUND) * self.words + 1e-9 and self.missing + self.added <= MAX_CHANGED * self.words + 1e-9 else "none"


def anchors(templates: tuple[tuple[str, str], ...]) -> re.Pattern:
    """Words around which the templates are sought."""
    others = [r"\W+".join(map(re.escape, _WORD.findall(t)[:3])) for _, t in templates if not ANCHOR.search(t) and _WORD.search(t)]
    return re.compile("|".join([ANCHOR.pattern, *others]), re.I)


def blocks(text: str, anchor: re.Pattern = ANCHOR) -> list[tuple[int, str]]:
    """(first line, text) of the candidate blocks: anchor lines with the lines near them, merged where they meet."""
    if not anchor.search(text):
        return []
    lines = text.split("\n")
    near: set[int] = set()
    for k, line in enumerate(lines):
        if anchor.search(line):
            near.update(range(max(0, k - REACH), min(len(lines), k + REACH + 1)))
    out, run = [], []
    for k in sorted(near):
        if run and k != run[-1] + 1:
            out.append((run[0], "\n".join(lines[i] for i in run)))
            run = []
        run.append(k)
    if run:
        out.append((run[0], "\n".join(lines[i] for i in run)))
    return out


def windows(block: str, size: int) -> list[tuple[int, str]]:
    """(start, text) of overlapping stretches: what is no longer than ``size`` lies whole in one. They begin at white space where there is some."""
    edges = [0]
    while len(block) - edges[-1] > 2 * size:
        at = edges[-1] + size
        space = _SPACE.search(block, at, at + size // 2)
        edges.append(space.start() if space else at)
    return [(a, block[a : edges[k + 2] if k + 2 < len(edges) else len(block)]) for k, a in enumerate(edges[: max(1, len(edges) - 1)])]


def wording(block: str, template: str) -> Wording:
    """Words of the template that the block lacks, and words that it adds between the first and last match."""
    ours, theirs = [_WORD.findall(x.lower()) for x in (block, template)]
    if not theirs:
        return Wording(0, 0, 0)
    # the stretch of the block with the template's first words in it, so that text around the notice doesn't count
    matches = [m for m in SequenceMatcher(None, ours, theirs, autojunk=False).get_matching_blocks() if m.size]
    if not matches:
        return Wording(len(theirs), 0, len(theirs))
    main = max(range(len(matches)), key=lambda i: matches[i].size)
    low = high = main
    while low and matches[low].a - (matches[low - 1].a + matches[low - 1].size) <= 2 + len(theirs) // 8:
        low -= 1
    while high + 1 < len(matches) and matches[high + 1].a - (matches[high].a + matches[high].size) <= 2 + len(theirs) // 8:
        high += 1
    chosen = matches[low : high + 1]
    found = sum(m.size for m in chosen)
    span = chosen[-1].a + chosen[-1].size - chosen[0].a
    return Wording(len(theirs) - found, span - found, len(theirs), chosen[0].a, chosen[0].a + span)


class Scanner:
    """Compressors with every template as raw dictionary; one per Python worker."""

    def __init__(self, templates: tuple[tuple[str, str], ...] = TEMPLATES):
        self.templates = templates
        self.anchor = anchors(templates)
        self.alone = zstandard.ZstdCompressor(level=LEVEL, write_content_size=False)
        raw = [zstandard.ZstdCompressionDict(t.encode(), dict_type=zstandard.DICT_TYPE_RAWCONTENT) for _, t in templates]
        self.given = [zstandard.ZstdCompressor(level=LEVEL, dict_data=d, write_content_size=False) for d in raw]
        self.sizes = [len(self.alone.compress(t.encode())) for _, t in templates]
        self.steps: dict[int, list[int]] = {}
        for k, (_, t) in enumerate(templates):
            step = STEP
            while step < LONGER * len(t):
                step *= 2
            self.steps.setdefault(step, []).append(k)
        self.cache = WordCache(20_000)

    def reductions(self, block: str, which: list[int] | None = None) -> list[tuple[int, float, int]]:
        """(bytes saved, their share of the template's own size, template number)."""
        data = block.encode("utf-8", "replace")
        alone = len(self.alone.compress(data))
        which = list(range(len(self.given))) if which is None else which
        saved = [(alone - len(self.given[k].compress(data)), k) for k in which]
        return [(s, s / self.sizes[k], k) for s, k in saved]

    def _confirmed(self, window: str, step: int) -> list[tuple[int, float, Wording]]:
        """Templates of one step whose wording a window confirms."""
        key = (step, window)
        if key not in self.cache:
            if len(self.cache) > self.cache.limit:
                self.cache.clear()
            found = self.reductions(window, self.steps[step]) if self.anchor.search(window) else []
            likely = [(k, share, wording(window, self.templates[k][1])) for _, share, k in found if share >= MIN_SAVED]
            self.cache[key] = [x for x in likely if x[2].verdict != "none"]
        return self.cache[key]

    def match(self, block: str) -> list[tuple[str, float, Wording]]:
        """(license, saved share, wording) of the templates whose wording confirms them.

        All of them, exact and modified, without those whose place in the block
        lies inside that of a better one: exact before modified, then by words
        found, then by fewer changes.
        """
        sure: list[tuple[int, float, Wording]] = []
        for step in self.steps:
            before, last = 0, 0
            for start, window in windows(block, step):
                if found := self._confirmed(window, step):
                    before, last = before + len(_WORD.findall(block, last, start)), start
                    sure += [(k, share, replace(w, start=w.start + before, stop=w.stop + before)) for k, share, w in found]
        ranked = sorted(sure, key=lambda x: (x[2].verdict != "exact", x[2].missing - x[2].words, x[2].missing + x[2].added, x[0]))
        kept: list[tuple[int, float, Wording]] = []
        for x in ranked:
            if not any(y[2].start <= x[2].start and x[2].stop <= y[2].stop for y in kept):
                kept.append(x)
        kept.sort(key=lambda x: (x[0], x[2].start))
        return [(self.templates[k][0], share, w) for k, share, w in kept]


def scan_blocks(docs: DataFrame, templates: tuple[tuple[str, str], ...] = TEMPLATES) -> DataFrame:
    """One row per candidate block and confirmed license (a null one where none is): doc_id, first_line, license, saved, missing, added, verdict."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scanner = Scanner(templates)
        for part in slices(batches, "text"):
            rows = []
            for doc_id, text in zip(part.column("doc_id").to_pylist(), strings(part, "text"), strict=True):
                for line, block in blocks(text, scanner.anchor):
                    for name, saved, words in scanner.match(block) or [(None, 0.0, Wording(0, 0, 0))]:
                        rows.append((doc_id, line, name, saved, words.missing, words.added, words.verdict if name else "none"))
            if rows:
                columns = list(zip(*rows, strict=True))
                types = [pa.int64(), pa.int64(), pa.string(), pa.float64(), pa.int64(), pa.int64(), pa.string()]
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, types, strict=True)], ["doc_id", "first_line", "license", "saved", "missing", "added", "verdict"])

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return rows.mapInArrow(run, "doc_id long, first_line long, license string, saved double, missing long, added long, verdict string")


def scan_documents(docs: DataFrame, templates: tuple[tuple[str, str], ...] = TEMPLATES) -> DataFrame:
    """One row per document: its candidate blocks, confirmed licenses (comma-separated, in order of name) and best wording."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scanner = Scanner(templates)
        for part in slices(batches, "text"):
            out = []
            for text in strings(part, "text"):
                found = [scanner.match(b) for _, b in blocks(text, scanner.anchor)]
                sure = [h for hits in found for h in hits]
                best = max(sure, key=lambda h: (h[2].verdict == "exact", h[1]), default=(None, 0.0, Wording(0, 0, 0)))
                out.append((len(found), sum(map(bool, found)), ",".join(sorted({h[0] for h in sure})), best[2].verdict if sure else "none", best[1], best[2].missing, best[2].added))
            columns = list(zip(*out, strict=True))
            types = [pa.int64(), pa.int64(), pa.string(), pa.string(), pa.float64(), pa.int64(), pa.int64()]
            yield pa.RecordBatch.from_arrays([part.column("doc_id"), *[pa.array(c, t) for c, t in zip(columns, types, strict=True)]], ["doc_id", "n_candidates", "n_confirmed", "licenses", "verdict", "saved", "missing", "added"])

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return rows.mapInArrow(run, "doc_id long, n_candidates long, n_confirmed long, licenses string, verdict string, saved double, missing long, added long")
