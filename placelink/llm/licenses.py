"""License scans by conditional compression.

A candidate block is what lies around words that licenses use: as many words on either side as the longest template could
reach, whatever the lines; blocks that overlap are one. Every template is aligned with the parts of the block it fits;
such a part, without the prose around it, is compressed alone and again with each template as a zstandard raw
dictionary. That ranks the templates: of parts that overlap, the one wins whose template spares the most bytes beyond
those it leaves (then the template that ranks first in its part). The size reduction and the exact differences in wording
confirm it, or not; then the next one is tried. Every confirmed part that overlaps no better one is a row, so a block
may name several licenses.

Defined cases: null and empty texts have no blocks; what confirmed parts leave of a block is reported with a null license
if it has a cue of its own (from the line of its first cue to that of its last one); templates that tie in bytes and rank
go by the words they explain, then by position, then by their text; repeated rows and null ids pass through as they are; very long texts and lines are scanned whole,
tile by tile, so the work grows with the words around cues; an empty table gives an empty result; only doc_id and text
are read, so other columns may have any name.
"""

from __future__ import annotations

import difflib
import re
from bisect import bisect_right
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field

import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame, SparkSession

from placelink.llm.common import table

#: How licenses announce themselves (lower case).
CUES = ("licens", "licenc", "copyright", "spdx", "permission is hereby granted", "all rights reserved", "without warrant", "creative commons", "cc by", "cc-by", "cc0", "public domain", "redistribution and use")
#: Further words on either side of where a template should lie (its own number of words, if larger) that an alignment looks at.
SLACK = 10
#: The smallest size reduction of the part a template aligns with that makes it a winner, the least share of its words to be found.
LEAST_GAIN, LEAST_SHARE = 0.25, 0.8

#: Public license notices and one-line statements by SPDX identifier.
TEMPLATES = {
    "MIT": (
        "Released under the MIT License.",
        "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions: The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software.",
    ),
    "Apache-2.0": (
        "Licensed under the Apache License, Version 2.0.",
        "Licensed under the Apache License, Version 2.0 (the \"License\"); you may not use this file except in compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0 Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an \"AS IS\" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied.",
    ),
    "GPL-3.0": (
        "This work is licensed under the GNU General Public License, version 3.",
        "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version.",
    ),
    "GPL-2.0": (
        "This work is licensed under the GNU General Public License, version 2.",
        "This program is free software; you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation; either version 2 of the License, or (at your option) any later version.",
    ),
    "LGPL-3.0": ("This work is licensed under the GNU Lesser General Public License, version 3.",),
    "AGPL-3.0": ("This work is licensed under the GNU Affero General Public License, version 3.",),
    "MPL-2.0": ("This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can obtain one at http://mozilla.org/MPL/2.0/.",),
    "BSD-3-Clause": (
        "Licensed under the BSD 3-Clause License.",
        "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution. Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission.",
    ),
    "ISC": ("Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies.",),
    "CC-BY-4.0": ("Licensed under CC BY 4.0.", "This work is licensed under a Creative Commons Attribution 4.0 International License."),
    "CC-BY-SA-4.0": ("Licensed under CC BY-SA 4.0.", "This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License."),
    "CC-BY-NC-4.0": ("Licensed under CC BY-NC 4.0.", "This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International License."),
    "CC0-1.0": ("To the extent possible under law, the author has waived all copyright and related or neighboring rights to this work.",),
    "LicenseRef-All-rights-reserved": ("All rights reserved.",),
    "Unlicense": ("This is free and unencumbered software released into the public domain.",),
}
SCHEMA = "doc_id long, block_start long, block_length long, license string, size_reduction double, found_share double, missing array<string>, added array<string>, verdict string"

#: What is cut off both ends of an unconfirmed rest.
_EDGE = " \t\r\n.,;:"
_WORD = re.compile(r"[^\W_]+(?:[.][0-9]+)*")
_TELLING = re.compile(r"\d|^(?:mit|apache|gnu|general|lesser|affero|mozilla|bsd|nc|sa|nd|by|cc|zero|noncommercial|sharealike|clause|not)$")


def words(text: str) -> list[str]:
    return _WORD.findall(text.lower())


def _lower(text: str) -> str:
    low = text.lower()
    if len(low) != len(text):  # a few letters change their length
        low = "".join(x if len(x) == 1 else "?" for x in map(str.lower, text))
    return low


def _located(text: str) -> tuple[list[str], list[tuple[int, int]]]:
    """The words of a text and where each starts and ends."""
    found = list(_WORD.finditer(_lower(text)))
    return [m.group() for m in found], [m.span() for m in found]


@dataclass
class Template:
    license: str
    text: str
    words: list[str] = field(init=False)
    counts: Counter = field(init=False)
    telling: set[str] = field(init=False)
    compressor: zstandard.ZstdCompressor = field(init=False)

    def __post_init__(self) -> None:
        self.words = words(self.text)
        self.counts = Counter(self.words)
        self.telling = {w for w in self.counts if _TELLING.search(w)}
        dictionary = zstandard.ZstdCompressionDict(self.text.encode(), dict_type=zstandard.DICT_TYPE_RAWCONTENT)
        self.compressor = zstandard.ZstdCompressor(level=9, dict_data=dictionary, write_content_size=False, write_dict_id=False)

    def may_lie_in(self, own: list[str]) -> bool:
        """False only if no alignment can reach LEAST_SHARE or one must miss a telling word."""
        there = Counter(w for w in own if w in self.counts)
        return bool(self.words) and self.telling <= there.keys() and (self.counts & there).total() / len(self.words) >= LEAST_SHARE


class Scanner:
    """Templates with their dictionaries, and the automaton of the cues; one per Python worker."""

    def __init__(self, templates: dict[str, tuple[str, ...]] = TEMPLATES, cues: tuple[str, ...] = CUES):
        import ahocorasick

        self.templates = [Template(name, text) for name, texts in templates.items() for text in texts]
        self.plain = zstandard.ZstdCompressor(level=9, write_content_size=False)
        self.cues = ahocorasick.Automaton()
        for cue in cues:
            self.cues.add_word(cue, len(cue))
        self.cues.make_automaton()
        silent = [t.text for t in self.templates if not any(True for _ in self.cues.iter(t.text.lower()))]
        if silent:
            raise ValueError(f"templates without any cue are never looked for: {silent}")
        #: Words on either side of a cue that an alignment with the longest template can reach.
        self.reach = max(len(t.words) + 2 * max(SLACK, len(t.words)) for t in self.templates)

    def blocks(self, text: str) -> list[tuple[int, int]]:
        """Start and end of every candidate block."""
        return [(at[i][0], at[j - 1][1]) for _, at, i, j in self._blocks(text)]

    def _blocks(self, text: str) -> Iterator[tuple[list[str], list[tuple[int, int]], int, int]]:
        """The words of a text, where they lie, and the first word of every block and the one after its last."""
        cues = list(self.cues.iter(_lower(text)))
        if not cues:
            return
        own, at = _located(text)
        starts, found = [a for a, _ in at], []
        for end, size in cues:
            i, j = max(0, bisect_right(starts, end + 1 - size) - 1 - self.reach), min(len(at), bisect_right(starts, end) + self.reach)
            if found and i <= found[-1][1]:
                found[-1][1] = max(found[-1][1], j)
            else:
                found.append([i, j])
        yield from ((own, at, i, j) for i, j in found if i < j)

    def _sizes(self, block: str) -> tuple[int, list[tuple[int, Template]]]:
        """Bytes of the block compressed alone, and with every template, fewest first."""
        data = block.encode()
        return len(self.plain.compress(data)), sorted(((len(t.compressor.compress(data)), t) for t in self.templates), key=lambda x: (x[0], x[1].text))

    def reductions(self, block: str) -> list[tuple[float, Template]]:
        """Every template with the share by which it makes the compressed block smaller, best first."""
        alone, given = self._sizes(block)
        return [(1 - size / alone, t) for size, t in given]

    def judge(self, block: str) -> tuple:
        """license, size_reduction, found_share, missing, added, verdict of the part that a template explains best."""
        own, at = _located(block)
        won = self._winners(block, own, at, 0, len(own))
        return min(won)[3] if won else self._unconfirmed(block)

    def verdicts(self, text: str) -> list[tuple]:
        """Start, length and judgement of every confirmed part of a text, and of what lies between them and holds a cue."""
        out = []
        for own, at, first, last in self._blocks(text):
            won = sorted(((at[i][0], at[j - 1][1], verdict) for _, i, j, verdict in self._winners(text, own, at, first, last)), key=lambda x: x[:2])
            done, end = at[first][0], at[last - 1][1]
            for i, j, verdict in [*won, (end, end, None)]:
                out += self._rest(text, done, i)
                if verdict:
                    out.append((i, j - i, *verdict))
                done = j
        return out

    def _rest(self, text: str, a: int, b: int) -> list[tuple]:
        """The lines of text[a:b] from its first cue to its last one, unconfirmed; nothing without a cue."""
        cues = [(a + end + 1 - size, a + end + 1) for end, size in self.cues.iter(_lower(text[a:b]))]
        if not cues:
            return []
        end = text.find("\n", max(e for _, e in cues), b)
        a, b = max(a, text.rfind("\n", a, min(s for s, _ in cues)) + 1), b if end < 0 else end
        part = text[a:b]
        return [(a + len(part) - len(part.lstrip(_EDGE)), len(part.strip(_EDGE)), *self._unconfirmed(part.strip(_EDGE)))]

    def _unconfirmed(self, block: str) -> tuple:
        return None, round(max(0.0, self.reductions(block)[0][0]), 4), 0.0, [], [], "unconfirmed"

    def _winners(self, text: str, own: list[str], at: list[tuple[int, int]], first: int, last: int) -> list[tuple]:
        """Confirmed parts of the words first to last that do not overlap, those whose compression gains most first.

        What a winner leaves is searched again.
        """
        won, todo = [], [(first, last)]
        while todo:
            lo, hi = todo.pop()
            found = sorted((x for t in self.templates for x in self._spans(t, text, own, at, lo, hi)), key=lambda x: x[0])
            taken, lost, here = bytearray(hi - lo), bytearray(hi - lo), []
            for x in found:
                i, j = x[1] - lo, x[2] - lo
                if any(taken[i:j]):
                    lost[i:j] = b"\1" * (j - i)
                else:
                    taken[i:j] = b"\1" * (j - i)
                    here.append(x)
            won += here
            ends = [lo, *(k for x in sorted(here, key=lambda x: x[1]) for k in x[1:3]), hi]
            todo += [(i, j) for i, j in zip(ends[::2], ends[1::2], strict=True) if any(lost[i - lo : j - lo])]
        return won

    def _spans(self, t: Template, block: str, own: list[str], at: list[tuple[int, int]], lo: int, hi: int) -> Iterator[tuple]:
        """Parts of the words lo to hi that confirm a template: key (best first), start, end, verdict.

        Tiles overlap by as much as a part may span, so that the work grows with the words and not with their square.
        """
        n = len(t.words)
        slack = max(SLACK, n)
        step, seen = n + 2 * slack, set()
        match = difflib.SequenceMatcher(None, "", t.words, autojunk=False)  # the second sequence is the indexed one
        for tile in range(lo, max(lo + 1, hi - step), step):
            todo = [(tile, min(hi, tile + 2 * step))]
            while todo:
                i, j = todo.pop()
                if not t.may_lie_in(own[i:j]):
                    continue
                match.set_seq1(own[i:j])
                anchor = match.find_longest_match()
                first = i + anchor.a
                got = self._confirmed(t, block, own, at, max(i, first - anchor.b - slack), min(j, first - anchor.b + n + slack))
                if got:
                    todo += [(i, got[1]), (got[2], j)]
                    if got[1:3] not in seen:
                        seen.add(got[1:3])
                        yield got
                else:
                    todo += [(i, first), (first + anchor.size, j)]

    def _confirmed(self, t: Template, block: str, own: list[str], at: list[tuple[int, int]], lo: int, hi: int) -> tuple | None:
        """The part of the words lo to hi that aligns with a template, if its wording and its size reduction confirm it."""
        match = difflib.SequenceMatcher(None, t.words, own[lo:hi], autojunk=False)
        same = [m for m in match.get_matching_blocks() if m.size]
        share = sum(m.size for m in same) / max(1, len(t.words))
        if share < LEAST_SHARE:
            return None
        i, j = lo + same[0].b, lo + same[-1].b + same[-1].size
        kept_t = {k for m in same for k in range(m.a, m.a + m.size)}
        kept_o = {lo + k for m in same for k in range(m.b, m.b + m.size)}
        missing = [w for k, w in enumerate(t.words) if k not in kept_t]
        added = [w for k, w in enumerate(own[i:j], i) if k not in kept_o]
        if any(_TELLING.search(w) for w in missing):
            return None  # another license or version
        alone, given = self._sizes(block[at[i][0] : at[j - 1][1]])
        size = next(size for size, other in given if other is t)
        gain = 1 - size / alone
        if gain < LEAST_GAIN:
            return None
        rank = sum(other < size for other, _ in given)
        key = (2 * size - alone, rank, len(missing) + len(added) - len(kept_t), i, t.text)
        return key, i, j, (t.license, round(gain, 4), round(share, 4), missing, added, "variant" if missing or added else "exact")


_scanner: list[Scanner] = []


def scan(docs: DataFrame) -> DataFrame:
    """One row per confirmed part of a candidate block, and one per part with a cue that nothing confirms (see SCHEMA).

    Positions are code points; those of a confirmed part reach from its first to its last aligned word.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        if not _scanner:
            _scanner.append(Scanner())
        for batch in batches:
            rows = []
            for doc, text in zip(batch.column("doc_id"), batch.column("text"), strict=True):
                rows += [(doc.as_py(), *row) for row in _scanner[0].verdicts(text.as_py() or "")]
            if rows:
                types = [pa.int64()] * 3 + [pa.string(), pa.float64(), pa.float64(), pa.list_(pa.string()), pa.list_(pa.string()), pa.string()]
                columns = [pa.array(list(x), t) for x, t in zip(zip(*rows, strict=True), types, strict=True)]
                yield pa.RecordBatch.from_arrays(columns, names=[x.split()[0] for x in SCHEMA.split(", ")])

    return docs.select("doc_id", "text").mapInArrow(run, SCHEMA)


def op4_licenses(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan(table(spark, sf_dir, "documents"))
