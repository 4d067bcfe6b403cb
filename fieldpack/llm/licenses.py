"""License scans: normalised text against license templates by the Dice coefficient over word bigrams.

A candidate is a window of words, inside a line or across lines. Both sides are lower-cased and cut
into words; word bigrams are counted with repeats. For a template of b bigrams only windows of a
bigrams with 2*min(a, b)/(a + b) at least the threshold can match, which bounds the windows to be
tried and prunes templates by size and by the number of shared bigrams before any counting. A window
starts and ends at bigrams that the template shares, since any other word outside only lowers the
score. Where such a bigram is not the template's first (or last), the words of the same line that
stand in the place of the template's missing ones belong to the window: otherwise the words that
name another license would be cut off ("This project is licensed under the" is no MIT notice).
Runs of whole lines are tried first; of overlapping matches the best stays: higher score, then
earlier, then shorter, then by name. Windows of words then fill what is left, and of those the one
stays that explains most: shared bigrams less those that only one side has, since a template may
stand whole inside another.

Cases: null and empty texts match nothing; a window may lie in one very long line, and a line may
hold several matches; repeated rows give repeated results; texts of any length are scanned whole.
"""

from __future__ import annotations

import heapq
import math
import re
from bisect import bisect_left, bisect_right, insort
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, DoubleType, IntegerType, LongType, StringType, StructField, StructType

from .common import bound_batches, read_table

THRESHOLD = 0.8
WORD = re.compile(r"[^\W_]+(?:[.'-][^\W_]+)*")

#: Well-known public license notices and texts.
TEMPLATES: list[tuple[str, str]] = [
    ("MIT", "Released under the MIT License."),
    ("MIT", "Licensed under the MIT License."),
    ("MIT", "This project is licensed under the MIT License."),
    ("MIT", "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions: The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software."),
    ("Apache-2.0", "Licensed under the Apache License, Version 2.0."),
    ("Apache-2.0", "Licensed under the Apache License 2.0."),
    ("Apache-2.0", "Licensed under the Apache License, Version 2.0 (the \"License\"); you may not use this file except in compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0 Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an \"AS IS\" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. See the License for the specific language governing permissions and limitations under the License."),
    ("GPL-3.0", "Licensed under the GNU General Public License, version 3."),
    ("GPL-2.0", "Licensed under the GNU General Public License, version 2."),
    ("GPL-3.0", "This work is licensed under the GNU General Public License, version 3."),
    ("GPL-3.0", "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version."),
    ("GPL-2.0", "This program is free software; you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation; either version 2 of the License, or (at your option) any later version."),
    ("BSD-3-Clause", "Licensed under the BSD 3-Clause License."),
    ("BSD-2-Clause", "Licensed under the BSD 2-Clause License."),
    ("BSD-3-Clause", "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution. Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission."),
    ("BSD-2-Clause", "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution."),
    ("MPL-2.0", "Licensed under the Mozilla Public License 2.0."),
    ("MPL-2.0", "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can obtain one at http://mozilla.org/MPL/2.0/."),
    ("CC-BY-4.0", "Licensed under CC BY 4.0."),
    ("CC-BY-4.0", "This work is licensed under a Creative Commons Attribution 4.0 International License."),
    ("CC-BY-SA-4.0", "Licensed under CC BY-SA 4.0."),
    ("CC-BY-SA-4.0", "This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License."),
    ("CC-BY-NC-4.0", "Licensed under CC BY-NC 4.0."),
    ("CC-BY-NC-4.0", "This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International License."),
    ("CC0-1.0", "To the extent possible under law, the author has waived all copyright and related or neighboring rights to this work."),
    ("ISC", "Licensed under the ISC License."),
    ("ISC", "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies."),
    ("Unlicense", "This is free and unencumbered software released into the public domain."),
]


def words_of(text: str) -> list[str]:
    return WORD.findall(text.lower())


def bigrams_of(words: list[str]) -> Counter:
    return Counter(zip(words, words[1:]))


def dice(a: Counter, b: Counter) -> float:
    total = a.total() + b.total()
    return 2 * sum(min(n, b[g]) for g, n in a.items() if g in b) / total if total else 0.0


@dataclass(frozen=True)
class Match:
    """Words `first` to `last` of the text; `gain` is shared bigrams less those that one side has alone."""

    score: float
    first: int
    last: int
    name: str
    gain: int = 0

    @property
    def rank(self) -> tuple:
        return (-self.score, self.first, self.last - self.first, self.name)


class Scanner:
    def __init__(self, templates: list[tuple[str, str]] = TEMPLATES, threshold: float = THRESHOLD):
        self.threshold = threshold
        words = [(name, words_of(text)) for name, text in templates]
        self.templates = [(name, bigrams_of(w)) for name, w in words]
        self.sizes = [b.total() for _, b in self.templates]
        ratio = threshold / (2 - threshold)
        self.bounds = [(b * ratio - 1e-9, b / ratio + 1e-9) for b in self.sizes]
        self.holders: dict[tuple[str, str], set[int]] = {}
        #: Of each template: how many of its bigrams stand before the first, and after the last, place of a bigram.
        self.before: list[dict[tuple[str, str], int]] = []
        self.after: list[dict[tuple[str, str], int]] = []
        for i, (_, w) in enumerate(words):
            pairs = list(zip(w, w[1:]))
            for g in pairs:
                self.holders.setdefault(g, set()).add(i)
            self.before.append({g: at for at, g in reversed(list(enumerate(pairs)))})
            self.after.append({g: len(pairs) - 1 - at for at, g in enumerate(pairs)})
        self.vocabulary = {w for g in self.holders for w in g}

    def matches(self, text: str | None) -> list[Match]:
        """All matches that don't overlap, best first."""
        return [m for m, _, _ in self.placed(text)]

    def placed(self, text: str | None) -> list[tuple[Match, int, int]]:
        """The matches, each with its first and last line."""
        if not text:
            return []
        words: list[str] = []
        starts: list[int] = []  # the first word of each line
        shared: dict[int, list[int]] = {}  # template -> places of bigrams that it shares
        known, holders = self.vocabulary, self.holders
        before = None
        for line in text.split("\n"):
            starts.append(len(words))
            for at, w in enumerate(found := words_of(line), len(words)):
                if w not in known:
                    before = None
                    continue
                if before is not None and (held := holders.get((before, w))):
                    for i in held:
                        shared.setdefault(i, []).append(at - 1)
                before = w
            words += found
        line_of = lambda word: bisect_right(starts, word) - 1
        ends = [*starts[1:], len(words)]
        line = lambda word: (starts[n := line_of(word)], ends[n])
        out: list[Match] = []
        taken: list[tuple[int, int]] = []
        for whole in (True, False):
            rank = (lambda m: m.rank) if whole else (lambda m: (-m.gain, *m.rank[1:]))
            tried = {i: t for i, at in shared.items() if (t := self._edges(i, at, words, line, whole))}
            best = lambda i, first, stop: self._best(i, first, tried[i][1], shared[i], words, stop, rank)  # noqa: B023, E731
            # each start stands for its best window; where that overlaps a better match, for the best that ends before it
            heap = [(rank(m), i, m) for i, (firsts, _) in tried.items() for first in firsts if (m := best(i, first, len(words)))]
            heapq.heapify(heap)
            while heap:
                _, i, m = heapq.heappop(heap)
                at = bisect_right(taken, (m.first, len(words)))
                if at and taken[at - 1][1] >= m.first:
                    continue
                if at == len(taken) or taken[at][0] > m.last:
                    out.append(m)
                    insort(taken, (m.first, m.last))
                elif m := best(i, m.first, taken[at][0]):
                    heapq.heappush(heap, (rank(m), i, m))
        return [(m, line_of(m.first), line_of(m.last)) for m in sorted(out, key=lambda m: m.rank)]

    def _edges(self, i: int, at: list[int], words: list[str], line, whole: bool) -> tuple[list[int], list[int]] | None:
        """Places of the bigrams at which windows (or, if `whole`, runs of lines) start and end."""
        low, high = self.bounds[i]
        least = max(1, math.ceil(low))  # a match shares so many bigrams
        near = [k for k in range(len(at) - least + 1) if at[k + least - 1] - at[k] < high]
        if not near:
            return None
        firsts, lasts = set(), set()
        reach = -1
        for k in near:
            p = at[k]
            firsts.add(line(p)[0] if whole else max(line(p)[0], p - self.before[i][words[p], words[p + 1]]))
            for k in range(max(reach + 1, k), bisect_left(at, p + high)):
                p = at[k]
                lasts.add(line(p + 1)[1] - 2 if whole else min(line(p + 1)[1] - 2, p + self.after[i][words[p], words[p + 1]]))
                reach = k
        return sorted(firsts), sorted(lasts)

    def _best(self, i: int, first: int, lasts: list[int], at: list[int], words: list[str], stop: int, rank) -> Match | None:
        """The best window that starts at this bigram and whose words stand before `stop`."""
        name, template = self.templates[i]
        low, high = self.bounds[i]
        total = self.sizes[i]
        seen: Counter = Counter()
        common, k = 0, bisect_left(at, first)
        best = None
        for last in lasts[bisect_left(lasts, first) :]:
            size = last - first + 1
            if size > high or last + 1 >= stop:
                break
            while k < len(at) and at[k] <= last:
                g = words[at[k]], words[at[k] + 1]
                seen[g] += 1
                common += seen[g] <= template[g]
                k += 1
            score = 2 * common / (size + total)
            if size >= low and score >= self.threshold:
                m = Match(score, first, last + 1, name, 3 * common - size - total)
                best = m if best is None or rank(m) < rank(best) else best
        return best


SCAN = StructType([
    StructField("n_matches", LongType()), StructField("license", StringType()), StructField("score", DoubleType()), StructField("licenses", StringType()),
    StructField("spans", ArrayType(StructType([StructField("license", StringType()), StructField("first_line", IntegerType()), StructField("last_line", IntegerType()), StructField("score", DoubleType())]))),
])


def license_matches(text: Column, templates: list[tuple[str, str]] = TEMPLATES, threshold: float = THRESHOLD) -> Column:
    """A struct with the best license, all licenses (sorted, comma-joined) and the lines of every match."""

    @F.pandas_udf(SCAN)
    def run(batches: Iterator[pd.Series]) -> Iterator[pd.DataFrame]:
        scanner = Scanner(templates, threshold)
        for col in batches:
            rows = []
            for t in col:
                placed = scanner.placed(t)
                found = [m for m, _, _ in placed]
                spans = [{"license": m.name, "first_line": first, "last_line": last, "score": m.score} for m, first, last in placed]
                rows.append((len(found), found[0].name if found else None, found[0].score if found else None, ",".join(sorted({m.name for m in found})), spans))
            yield pd.DataFrame(rows, columns=SCAN.names)

    return run(text)


def op10_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    bound_batches(spark)
    docs = read_table(spark, sf_dir, "documents", "doc_id", "text")
    return docs.select("doc_id", license_matches(F.col("text")).alias("m")).select("doc_id", "m.n_matches", "m.license", "m.score", "m.licenses")
