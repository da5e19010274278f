"""Licence scans: normalised text against licence templates by the Dice coefficient over word bigrams.

Units are every line, every run of lines between blank lines, every run of neighbouring ones of these, the whole text, and, where
none of these matches, every window of as many words as a template has, so that a notice within a longer line is found. A
unit is compared with a template only when their sizes allow the threshold (the smaller at least t / (2 - t) of the larger)
and when the text shares as large a part of the template's bigrams; both conditions are necessary for a match, so nothing is
lost. One pass without a shuffle.

Of overlapping spans of one template the best stays. A span inside that of another template goes only where its template is a
part of the other's (the conditions within a whole licence); a window goes where a span of such a template fits better.

Defined cases: null or empty text has no units; very long texts are read whole; a unit of one word has the single pseudo-bigram
(word,); a tie between templates goes to the first name; equal spans found as line and as paragraph count once, and of equal scores
the shortest and then the first span stays; repeated rows are judged alike; an empty table gives an empty result; extra columns,
whatever their names, are ignored.
"""

from __future__ import annotations

import re
from bisect import bisect_left, bisect_right
from collections import Counter, defaultdict
from collections.abc import Collection

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from gridmul.llm.common import map_rows, text_of
from gridmul.llm.licence_texts import TEXTS

THRESHOLD = 0.85
WORD = re.compile(r"[^\W_]+(?:[.'-][^\W_]+)*")
BLANK_LINE = re.compile(r"\n[^\S\n]*(?:\n[^\S\n]*)+")

#: Public licence notices and whole texts (SPDX name: text).
TEMPLATES = {
    "Apache-2.0 (notice)": "Licensed under the Apache License, Version 2.0.",
    "Apache-2.0": "Licensed under the Apache License, Version 2.0 (the \"License\"); you may not use this file except in compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0 Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an \"AS IS\" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. See the License for the specific language governing permissions and limitations under the License.",
    "BSD-2-Clause": "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: 1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer. 2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution.",
    "BSD-3-Clause": "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: 1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer. 2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution. 3. Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission.",
    "BSL-1.0 (notice)": "Distributed under the Boost Software License, Version 1.0.",
    "CC-BY-4.0 (notice)": "Licensed under CC BY 4.0.",
    "CC-BY-NC-4.0 (notice)": "Licensed under CC BY-NC 4.0.",
    "CC-BY-NC-ND-4.0 (notice)": "Licensed under CC BY-NC-ND 4.0.",
    "CC-BY-NC-SA-4.0 (notice)": "Licensed under CC BY-NC-SA 4.0.",
    "CC-BY-ND-4.0 (notice)": "Licensed under CC BY-ND 4.0.",
    "CC-BY-SA-4.0 (notice)": "Licensed under CC BY-SA 4.0.",
    "CC-BY-4.0": "This work is licensed under a Creative Commons Attribution 4.0 International License.",
    "CC-BY-SA-4.0": "This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License.",
    "CC-BY-NC-4.0": "This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International License.",
    "CC0-1.0": "To the extent possible under law, the author has waived all copyright and related or neighboring rights to this work.",
    "AGPL-3.0 (notice)": "This work is licensed under the GNU Affero General Public License, version 3.",
    "GPL-2.0 (notice)": "This work is licensed under the GNU General Public License, version 2.",
    "GPL-3.0 (notice)": "This work is licensed under the GNU General Public License, version 3.",
    "GPL-3.0-or-later": "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version. This program is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE. See the GNU General Public License for more details. You should have received a copy of the GNU General Public License along with this program.",
    "ISC": "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies.",
    "LGPL-3.0 (notice)": "This work is licensed under the GNU Lesser General Public License, version 3.",
    "MIT (notice)": "Licensed under the MIT License.",
    "MIT (release notice)": "Released under the MIT License.",
    "MIT": "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions: The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software.",
    "MPL-2.0": "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can obtain one at https://mozilla.org/MPL/2.0/.",
    "Proprietary": "All rights reserved.",
    "Unlicense": "This is free and unencumbered software released into the public domain.",
    "Zlib": "This software is provided 'as-is', without any express or implied warranty. In no event will the authors be held liable for any damages arising from the use of this software.",
    **TEXTS,
}


def bigrams(text: str) -> Counter:
    words = WORD.findall(text.lower())
    return Counter(zip(words, words[1:])) if len(words) != 1 else Counter([(words[0],)])


def dice(a: Counter, b: Counter) -> float:
    total = a.total() + b.total()
    return 2 * (a & b).total() / total if total else 0.0


class Scanner:
    """Templates with an index from bigram to template, for candidates by size and shared bigrams."""

    def __init__(self, templates: dict[str, str] = TEMPLATES, threshold: float = THRESHOLD):
        self.threshold = threshold
        self.shapes = {name: bigrams(t) for name, t in sorted(templates.items())}
        self.sizes = {name: s.total() for name, s in self.shapes.items()}
        self.by_bigram: dict[tuple, list[str]] = defaultdict(list)
        for name, shape in self.shapes.items():
            for g in shape:
                self.by_bigram[g].append(name)
        self.least = threshold / (2 - threshold)
        self.bounds = {name: (n * self.least - 1e-9, n / self.least + 1e-9) for name, n in self.sizes.items()}
        # a template is a part of a larger one that has the threshold's share of its bigrams
        self.part_of = {n: {o for o, t in self.shapes.items() if self.sizes[o] > self.sizes[n] and (s & t).total() >= threshold * self.sizes[n]} for n, s in self.shapes.items()}

    def shared(self, grams: list[tuple]) -> dict[str, int]:
        """How many bigrams each template has in common with the given ones."""
        out: dict[str, int] = defaultdict(int)
        for g, k in Counter(filter(self.by_bigram.__contains__, grams)).items():
            for n in self.by_bigram[g]:
                out[n] += min(k, self.shapes[n][g])
        return out

    def best(self, unit: str, names: Collection[str] | None = None) -> tuple[str, float] | None:
        names = self.shapes if names is None else names
        low = min((self.bounds[n][0] for n in names), default=0)
        # a word takes two characters with its separator at least, so few characters are few bigrams
        if not names or len(unit) + 1 < 2 * low:
            return None
        words = WORD.findall(unit.lower())
        size = max(len(words) - 1, min(len(words), 1))
        fit = [n for n in names if self.bounds[n][0] <= size <= self.bounds[n][1]]
        if not fit:
            return None
        common = self.shared(list(zip(words, words[1:])) if len(words) != 1 else [(words[0],)])
        scored = [(-2 * common[n] / (size + self.sizes[n]), n) for n in fit if n in common]
        if scored and -min(scored)[0] >= self.threshold:
            d, n = min(scored)
            return n, -d
        return None

    def runs(self, parts: list[list[str]], names: Collection[str]) -> dict[tuple[int, int], tuple[str, float]]:
        """{(first, last): (template, score)} of the runs of two or more paragraphs, given as their words, that match."""
        found: dict[tuple[int, int], tuple[str, float]] = {}
        for name in sorted(names):
            shape, total, high = self.shapes[name], self.sizes[name], self.bounds[name][1]
            for first in range(len(parts) - 1):
                have: dict[tuple, int] = defaultdict(int)
                common, n_words, before = 0, 0, None
                for last in range(first, len(parts)):
                    for w in parts[last]:
                        if before is not None and (g := (before, w)) in shape:
                            have[g] += 1
                            common += have[g] <= shape[g]
                        before = w
                    n_words += len(parts[last])
                    if n_words - 1 > high:
                        break
                    if last == first and common == 0 and parts[first] and (parts[first][-1], next((p[0] for p in parts[first + 1 :] if p), None)) not in shape:
                        break  # without its first paragraph the run matches better
                    score = 2 * common / (n_words - 1 + total) if n_words > 1 else 0.0
                    if last > first and score >= self.threshold and ((first, last) not in found or score > found[first, last][1]):
                        found[first, last] = (name, score)
        return found

    def windows(self, text: str, names: Collection[str]) -> dict[tuple[int, int, str], float]:
        """{(start, end, template): score} of the windows with as many words as the template has, that match."""
        places = [(m.start(), m.end(), m[0].lower()) for m in WORD.finditer(text)]
        grams = [(a[2], b[2]) for a, b in zip(places, places[1:])]
        found: dict[tuple[int, int, str], float] = {}
        for name in sorted(names):
            shape, total = self.shapes[name], self.sizes[name]
            have: dict[tuple, int] = defaultdict(int)
            common = 0
            for i, g in enumerate(grams):
                if g in shape:
                    have[g] += 1
                    common += have[g] <= shape[g]
                if i >= total and (gone := grams[i - total]) in shape:
                    common -= have[gone] <= shape[gone]
                    have[gone] -= 1
                if i >= total - 1 and common >= self.threshold * total:
                    found[places[i - total + 1][0], places[i + 1][1], name] = common / total
        return found

    def scan(self, text: str) -> list[tuple[int, int, str, float]]:
        """(start, end, template, score) in code points, by start and end."""
        words = WORD.findall(text.lower())
        common = self.shared([*zip(words, words[1:]), *((w,) for w in words)])
        # a unit has no bigram that the text lacks, and a match has so many of the template's at least
        names = [n for n, k in common.items() if k >= self.least * self.sizes[n] - 1e-9]
        if not names:
            return []
        found: dict[tuple[int, int], tuple[str, float]] = {}
        units = [(0, len(text))]
        at = 0
        for line in text.split("\n"):
            units.append((at, at + len(line)))
            at += len(line) + 1
        at = 0
        paragraphs = []
        for gap in BLANK_LINE.finditer(text):
            paragraphs.append((at, gap.start()))
            at = gap.end()
        paragraphs.append((at, len(text)))
        for a, b in units + paragraphs:
            if a < b and (a, b) not in found and (hit := self.best(text[a:b], names)):
                found[a, b] = hit
        for (first, last), hit in self.runs([WORD.findall(text[a:b].lower()) for a, b in paragraphs], names).items():
            found.setdefault((paragraphs[first][0], paragraphs[last][1]), hit)
        kept: dict[str, list[tuple[int, int]]] = defaultdict(list)
        scores: dict[tuple[int, int, str], float] = {}

        def keep(a: int, b: int, name: str, score: float) -> None:
            same = kept[name]
            # the kept ones do not overlap, so only the neighbours of the place can
            k = bisect_left(same, (a, b))
            if (k == 0 or same[k - 1][1] <= a) and (k == len(same) or b <= same[k][0]):
                same.insert(k, (a, b))
                scores[a, b, name] = score

        for a, b in sorted(found, key=lambda s: (-found[s][1], s[1] - s[0], s)):
            keep(a, b, *found[a, b])

        def better(a: int, b: int, name: str, score: float) -> bool:
            """Whether a span of a part of the template, or of one that it is a part of, overlaps and fits better."""
            for other in (o for o in kept if o in self.part_of[name] or name in self.part_of[o]):
                k = bisect_left(kept[other], (a, a))
                if any(x < b and a < y and scores[x, y, other] > score for x, y in kept[other][max(k - 1, 0) : bisect_left(kept[other], (b, b))]):
                    return True
            return False

        inside = self.windows(text, names)
        for a, b, name in sorted(inside, key=lambda s: (-inside[s], s[1] - s[0], s)):
            if not better(a, b, name, inside[a, b, name]):
                keep(a, b, name, inside[a, b, name])

        def within(a: int, b: int, larger: str) -> bool:
            k = bisect_right(kept[larger], (a, len(text)))
            return k > 0 and kept[larger][k - 1][0] <= a and b <= kept[larger][k - 1][1]

        spans = sorted((a, b, n) for n, some in kept.items() for a, b in some)
        return [(a, b, n, scores[a, b, n]) for a, b, n in spans if not any(within(a, b, o) for o in self.part_of[n] if o in kept)]


def scan_licences(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", templates: dict[str, str] = TEMPLATES, threshold: float = THRESHOLD) -> DataFrame:
    """(doc_id, n_spans, licence, score, spans): the best template, its coefficient, and all spans found."""

    def rows(source):
        scanner = Scanner(templates, threshold)
        for key, text in source:
            spans = scanner.scan(text)
            best = min(((-s, n) for _, _, n, s in spans), default=(None, None))
            yield key, len(spans), best[1], round(-best[0], 6) if spans else None, [{"start": a, "end": b, "licence": n, "score": round(s, 6)} for a, b, n, s in spans]

    return map_rows(docs, [F.col(id_col).cast("long").alias("doc_id"), text_of(text_col)], 'doc_id long, n_spans long, licence string, score double, spans array<struct<start:long,`end`:long,licence:string,score:double>>', rows)
