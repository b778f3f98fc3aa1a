"""License scan by conditional compression.

Candidate blocks are stretches of a text that share three-word runs with any template, joined where at most NEAR_WORDS words lie between two of them;
line breaks and cue words play no part. A block is compressed once alone and once with each license template as zstandard
raw-content dictionary: templates are ranked by how much they shrink it. Those that shrink it, and the best `ranked` anyway, are then aligned with
it word by word (longest common subsequence) at each place where their runs gather. A place is confirmed if `confirm` of the template's words and all of its signs
stand there in order and close together. Of confirmed places that overlap the one with most equal words, less its differences, stays, so a block has a row
for each license; the words that a place lacks before, inside and after its match, and those foreign to the template, are reported exactly.

Defined results: null text or text without a template's words in a row gives no rows; a block without a confirmed place keeps the closest place of its best-ranked templates with
confirmed = false; ties in the reduction go to the first template by name; repeated rows are scanned each; further columns are not read.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator
from functools import lru_cache
from typing import NamedTuple

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from contactscope.llm.wordhash import Hasher, shingles

# Widely published license notices, and the words of each that no text under this license goes without.
_MIT = (
    "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction, "
    "including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, "
    "subject to the following conditions: The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software. "
    "THE SOFTWARE IS PROVIDED \"AS IS\", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. "
    "IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE."
)
_BSD_HEAD = (
    "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: "
    "Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer. "
    "Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution. "
)
_BSD_TAIL = "THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS \"AS IS\" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED."
TEMPLATES = {
    "AGPL-3.0": "This program is free software: you can redistribute it and/or modify it under the terms of the GNU Affero General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version.",
    "AGPL-3.0 notice": "This work is licensed under the GNU Affero General Public License, version 3.",
    "Apache-2.0": "Licensed under the Apache License, Version 2.0 (the \"License\"); you may not use this file except in compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0 Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an \"AS IS\" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. See the License for the specific language governing permissions and limitations under the License.",
    "Apache-2.0 notice": "Licensed under the Apache License, Version 2.0.",
    "BSD-2-Clause": _BSD_HEAD + _BSD_TAIL,
    "BSD-3-Clause": _BSD_HEAD + "Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission. " + _BSD_TAIL,
    "BSD notice": "Released under the BSD License.",
    "CC-BY-4.0": "This work is licensed under a Creative Commons Attribution 4.0 International License.",
    "CC-BY-4.0 notice": "Licensed under CC BY 4.0.",
    "CC-BY-NC-4.0": "This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International License.",
    "CC-BY-NC-4.0 notice": "Licensed under CC BY-NC 4.0.",
    "CC-BY-SA-4.0": "This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License.",
    "CC-BY-SA-4.0 notice": "Licensed under CC BY-SA 4.0.",
    "CC0-1.0": "To the extent possible under law, the author has waived all copyright and related or neighboring rights to this work.",
    "CC0-1.0 notice": "Dedicated to the public domain under CC0 1.0.",
    "GPL-2.0": "This program is free software; you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation; either version 2 of the License, or (at your option) any later version.",
    "GPL-2.0 notice": "This work is licensed under the GNU General Public License, version 2.",
    "GPL-3.0": "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version.",
    "GPL-3.0 notice": "This work is licensed under the GNU General Public License, version 3.",
    "ISC": "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies.",
    "LGPL-3.0 notice": "This library is licensed under the GNU Lesser General Public License, version 3.",
    "MIT": _MIT,
    "MIT notice": "Released under the MIT License.",
    "MPL-2.0": "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can obtain one at http://mozilla.org/MPL/2.0/.",
    "Proprietary": "All rights reserved. This material may not be reproduced, distributed or transmitted in any form without prior written permission.",
    "Proprietary notice": "All rights reserved.",
    "Unlicense": "This is free and unencumbered software released into the public domain. Anyone is free to copy, modify, publish, use, compile, sell, or distribute this software, either in source code form or as a compiled binary, for any purpose, commercial or non-commercial, and by any means.",
}
SIGNS = {
    "AGPL-3.0": ["affero", "3"],
    "AGPL-3.0 notice": ["affero", "3"],
    "Apache-2.0": ["apache", "2.0"],
    "Apache-2.0 notice": ["apache", "2.0"],
    "BSD notice": ["bsd"],
    "CC-BY-4.0": ["attribution", "4.0"],
    "CC-BY-4.0 notice": ["by", "4.0"],
    "CC-BY-NC-4.0": ["attribution-noncommercial", "4.0"],
    "CC-BY-NC-4.0 notice": ["by-nc", "4.0"],
    "CC-BY-SA-4.0": ["attribution-sharealike", "4.0"],
    "CC-BY-SA-4.0 notice": ["by-sa", "4.0"],
    "CC0-1.0 notice": ["cc0", "1.0"],
    "GPL-2.0": ["gnu", "2"],
    "GPL-2.0 notice": ["gnu", "2"],
    "GPL-3.0": ["gnu", "3"],
    "GPL-3.0 notice": ["gnu", "3"],
    "LGPL-3.0 notice": ["lesser", "3"],
    "MIT notice": ["mit"],
    "MPL-2.0": ["mozilla"],
}
#: Words as the hasher cuts them, and words of the comparison: versions and compounds are one.
PLAIN_WORD = re.compile(rb"[0-9A-Za-z\x80-\xff]+")
WORD = re.compile(rb"[0-9A-Za-z\x80-\xff]+(?:[.-][0-9A-Za-z\x80-\xff]+)*")
RUN, NEAR_WORDS, LEAST_WORDS = 3, 25, 4
#: Verdicts that are remembered, on blocks of at most so many bytes.
REMEMBERED, SHORT_BLOCK = 4_000, 4_000
FOUND = (
    "doc_id long, block_no long, start_byte long, end_byte long, license string, reduction double, confirmed boolean, covered double, match_start long, match_end long, "
    "missing array<string>, missing_before array<string>, missing_after array<string>, foreign array<string>, ranking array<string>"
)


class Place(NamedTuple):
    """Where a template stands in a block: bytes [start, end), its words there and not there, the foreign words between."""

    license: str
    equal: int
    covered: float
    signed: bool
    start: int
    end: int
    missing: list[str]
    before: list[str]
    after: list[str]
    foreign: list[str]

    def differences(self) -> int:
        return len(self.missing) + len(self.before) + len(self.after) + len(self.foreign)


def common(a: np.ndarray, b: np.ndarray) -> list[tuple[int, int]]:
    """Places of a longest common subsequence."""
    table = np.zeros((len(a) + 1, len(b) + 1), np.int32)
    for i, w in enumerate(a):
        row = table[i + 1]
        row[1:] = np.maximum(table[i, 1:], table[i, :-1] + (b == w))
        np.maximum.accumulate(row, out=row)
    found, i, j = [], len(a), len(b)
    while i and j:
        if a[i - 1] == b[j - 1] and table[i, j] == table[i - 1, j - 1] + 1:
            i, j = i - 1, j - 1
            found.append((i, j))
        elif table[i - 1, j] == table[i, j]:
            i -= 1
        else:
            j -= 1
    return found[::-1]


def densest(pairs: list[tuple[int, int]]) -> list[tuple[int, int]]:
    """The stretch of aligned words with most of them, less half a word for each other one between."""
    best, held, start, part = 0.0, 0.0, 0, (0, 0)
    for n, (i, j) in enumerate(pairs):
        if n:
            held -= max(i - pairs[n - 1][0], j - pairs[n - 1][1]) / 2 - 0.5
        if held <= 0:
            held, start = 0.0, n
        held += 1
        if held > best:
            best, part = held, (start, n + 1)
    return pairs[part[0] : part[1]]


class Scanner:
    """Templates as dictionaries; the verdicts on short blocks are remembered for equal ones."""

    def __init__(self, templates: dict[str, str], level: int, ranked: int, confirm: float, signs: dict[str, list[str]] | None = None):
        self.names = sorted(templates)
        self.words = {k: WORD.findall(templates[k].lower().encode()) for k in self.names}
        self.signs = {k: [w.encode() for w in (signs or {}).get(k, [])] for k in self.names}
        made = lambda d=None: zstandard.ZstdCompressor(level=level, dict_data=d, write_content_size=False, write_dict_id=False)
        self.plain = made()
        self.with_dict = {k: made(zstandard.ZstdCompressionDict(b" ".join(self.words[k]), dict_type=zstandard.DICT_TYPE_RAWCONTENT)) for k in self.names}
        self.ranked, self.confirm = ranked, confirm
        self.hasher = Hasher()
        self.runs = np.unique(np.concatenate([shingles(h, RUN) for h in self.hasher.texts([templates[k].encode() for k in self.names]) if len(h) >= RUN]))
        self.remembered = lru_cache(REMEMBERED)(self._verdict)

    def blocks(self, texts: list[bytes]) -> Iterator[list[tuple[int, int]]]:
        """Byte ranges of each text's candidate blocks."""
        for text, hashes in zip(texts, self.hasher.texts(texts), strict=True):
            hits = np.zeros(0, np.int64)
            if len(hashes) >= RUN:
                h = shingles(hashes, RUN)
                at = np.minimum(np.searchsorted(self.runs, h), len(self.runs) - 1)
                hits = np.flatnonzero(self.runs[at] == h)
            if not len(hits):
                yield []
                continue
            cut = np.flatnonzero(np.diff(hits) > NEAR_WORDS + RUN)
            firsts, lasts = hits[np.concatenate(([0], cut + 1))], hits[np.append(cut, len(hits) - 1)] + RUN - 1
            wanted = dict.fromkeys([*firsts.tolist(), *lasts.tolist()])
            for n, m in enumerate(PLAIN_WORD.finditer(text)):
                if n in wanted:
                    wanted[n] = m.span()
            yield [(wanted[s][0], wanted[e][1]) for s, e in zip(firsts.tolist(), lasts.tolist(), strict=True)]

    def reductions(self, words: list[bytes]) -> list[tuple[float, str]]:
        """How much of its size a block loses with each template, best first; both as lower-case words, so that case, wrapping and comment marks count for nothing."""
        data = b" ".join(words)
        alone = len(self.plain.compress(data))
        return sorted(((1 - len(self.with_dict[k].compress(data)) / alone, k) for k in self.names), key=lambda x: (-x[0], x[1]))

    def places(self, name: str, own: list[bytes], spans: list[tuple[int, int]]) -> list[Place]:
        """A template's places in a block, at the diagonals where most of its runs stand."""
        known = self.words[name]
        m, size = len(known), min(RUN, len(known))
        runs: dict[tuple, list[int]] = {}
        for q in range(m - size + 1):
            runs.setdefault(tuple(known[q : q + size]), []).append(q)
        slack = m // 4 + 4
        hits = [(p, q) for p in range(len(own) - size + 1) for q in runs.get(tuple(own[p : p + size]), ())]
        buckets = Counter((p - q) // slack for p, q in hits)
        held: dict[int, set[int]] = {}
        for p, q in hits:
            held.setdefault((p - q) // slack, set()).add(p)
        number: dict[bytes, int] = {}
        a = np.array([number.setdefault(w, len(number)) for w in known])
        b = np.array([number.get(w, -1) for w in own])
        found: list[Place] = []
        taken = np.zeros(len(own), bool)
        for k, _ in sorted(buckets.items(), key=lambda x: (-x[1], x[0])):
            low, high = max(0, (k - 1) * slack), min(len(own), (k + 2) * slack + m)
            # a bucket may hold several places; each takes its words away
            while not all(taken[p] for p in held[k]):
                pairs = [(i, j + low) for i, j in densest(common(a, np.where(taken[low:high], -2, b[low:high])))]
                if not pairs:
                    break
                taken[pairs[0][1] : pairs[-1][1] + 1] = True
                found.append(self._place(name, pairs, own, spans))
        return found

    def _place(self, name: str, pairs: list[tuple[int, int]], own: list[bytes], spans: list[tuple[int, int]]) -> Place:
        known, (i, j), (ie, je) = self.words[name], pairs[0], pairs[-1]
        at, there = {x for x, _ in pairs}, {y for _, y in pairs}
        matched = {known[x] for x in at}
        missing, foreign = [known[x] for x in range(i, ie) if x not in at], [own[y] for y in range(j, je) if y not in there]
        text = lambda words: [w.decode("utf-8", "replace") for w in words]
        return Place(name, len(pairs), len(pairs) / len(known), matched.issuperset(self.signs[name]), spans[j][0], spans[je][1], text(missing), text(known[:i]), text(known[ie + 1 :]), text(foreign))

    def _sure(self, p: Place) -> bool:
        return p.covered >= self.confirm and p.equal >= min(LEAST_WORDS, len(self.words[p.license])) and p.signed

    def verdict(self, block: bytes) -> list[tuple]:
        return self.remembered(block) if len(block) <= SHORT_BLOCK else self._verdict(block)

    def _verdict(self, block: bytes) -> list[tuple]:
        """License, reduction, confirmed, covered, match, differences and ranking: a row for each confirmed place, by place, or one for the closest."""
        spans = [x.span() for x in WORD.finditer(block)]
        own = [block[s:e].lower() for s, e in spans]
        order = self.reductions(own)
        gains = {k: g for g, k in order}
        rank = {k: i for i, (_, k) in enumerate(order)}
        tried = [k for i, (g, k) in enumerate(order) if g > 0 or i < self.ranked]
        every = sorted((p for k in tried for p in self.places(k, own, spans)), key=lambda p: (p.differences() - 2 * p.equal, rank[p.license], p.start))
        kept: list[Place] = []
        for p in every:
            if gains[p.license] > 0 and self._sure(p) and all(p.end <= o.start or o.end <= p.start for o in kept):
                kept.append(p)
        sure = bool(kept)
        closest = [p for p in every if rank[p.license] < self.ranked] or every
        ranking = [k for _, k in order[: self.ranked]]
        rows = sorted(kept, key=lambda p: p.start) if sure else closest[:1]
        return [(p.license, round(gains[p.license], 6), sure, round(p.covered, 6), p.start, p.end, p.missing, p.before, p.after, p.foreign, ranking) for p in rows]


def scan(docs: DataFrame, templates: dict[str, str] | None = None, level: int = 3, ranked: int = 3, confirm: float = 0.8, signs: dict[str, list[str]] | None = None) -> DataFrame:
    """Rows of FOUND: one per confirmed license of a candidate block, or one for a block without any. start_byte and end_byte are the block's, match_start and
    match_end those of the license in the text. signs: words that a template's confirmed place must hold."""
    signs = SIGNS if templates is None else signs
    templates = templates or TEMPLATES

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scanner = Scanner(templates, level, ranked, confirm, signs)
        strings = pa.list_(pa.string())
        kinds = [pa.int64()] * 4 + [pa.string(), pa.float64(), pa.bool_(), pa.float64(), pa.int64(), pa.int64()] + [strings] * 5
        names = [c.split()[0] for c in FOUND.split(", ")]
        for b in batches:
            out = []
            texts = [t or b"" for t in b.column("text").cast(pa.binary()).to_pylist()]
            for doc, text, found in zip(b.column("doc_id").to_pylist(), texts, scanner.blocks(texts), strict=True):
                for n, (s, e) in enumerate(found):
                    out += [(doc, n, s, e, *v[:4], s + v[4], s + v[5], *v[6:]) for v in scanner.verdict(text[s:e])]
            yield pa.RecordBatch.from_arrays([pa.array([r[i] for r in out], t) for i, t in enumerate(kinds)], names)

    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(run, FOUND)
