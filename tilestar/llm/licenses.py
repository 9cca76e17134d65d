"""Licence scan: normalised text against licence templates, by the Dice coefficient over word bigrams.

A text is normalised to its lower-cased runs of ASCII letters and digits. Its units are its lines, if it has several the whole text, and every run of words (a passage), so a notice
that is wrapped over lines or stands inside a longer one is found. A passage counts as a matching unit where it touches neither a matching line or text nor a better passage. A unit and a template
are compared by 2 |A and B| / (|A| + |B|) over their sets of word bigrams; a match is a coefficient of at least `least`. Such a match needs
least / (2 - least) <= |A| / |B| <= (2 - least) / least, so templates of other sizes are never compared. A match also needs least / (2 - least) of
the template's bigrams, so passages are sought only for templates of which a text holds so many. The best passage starts and ends with bigrams of the template, and holds at most
(2 - least) / least as many distinct ones as it; for each start, the bigrams that follow are kept in order of their next occurrence, so every such passage is tried.

Defined results: null and empty texts, and texts of one word, match nothing (licence null, dice 0); of several matches the highest coefficient wins, then the template's name,
ties counted once; repeated rows are scanned alike; extra columns are ignored; an empty table gives an empty result. One pass, no shuffle; templates
are a parameter of bounded size and travel with the code.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from pathlib import Path

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

LEAST = 0.8
_WORD = re.compile("[a-z0-9]+")
_AS_IS = (
    'THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE'
    " AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE,"
    " ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE."
)
#: Fixed values: (name, text) of notices and of short licences in common public use.
TEMPLATES: tuple[tuple[str, str], ...] = (
    ("Apache-2.0", "Licensed under the Apache License, Version 2.0."),
    ("Apache-2.0", 'Licensed under the Apache License, Version 2.0 (the "License"); you may not use this file except in compliance with the License.'),
    (
        "Apache-2.0",
        'Licensed under the Apache License, Version 2.0 (the "License"); you may not use this file except in compliance with the License. You may obtain a copy of the License at'
        " http://www.apache.org/licenses/LICENSE-2.0 Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an"
        ' "AS IS" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. See the License for the specific language governing permissions and limitations under the License.',
    ),
    ("MIT", "Released under the MIT License."),
    ("MIT", "Licensed under the MIT License."),
    ("MIT", "This project is licensed under the MIT License."),
    (
        "MIT",
        "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without"
        " restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom"
        " the Software is furnished to do so, subject to the following conditions: The above copyright notice and this permission notice shall be included in all copies or substantial"
        " portions of the Software. " + _AS_IS,
    ),
    ("ISC", "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies."),
    ("BSD-2-Clause", "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met:"),
    ("BSD-3-Clause", "Licensed under the BSD 3-Clause License."),
    ("GPL-3.0", "This work is licensed under the GNU General Public License, version 3."),
    ("GPL-3.0", "Licensed under the GNU General Public License v3.0."),
    (
        "GPL-3.0-or-later",
        "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3"
        " of the License, or (at your option) any later version.",
    ),
    ("MPL-2.0", "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0."),
    ("CC-BY-4.0", "Licensed under CC BY 4.0."),
    ("CC-BY-4.0", "This work is licensed under a Creative Commons Attribution 4.0 International License."),
    ("CC-BY-NC-4.0", "Licensed under CC BY-NC 4.0."),
    ("CC-BY-NC-4.0", "This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International License."),
    ("CC-BY-SA-4.0", "Licensed under CC BY-SA 4.0."),
    ("Unlicense", "This is free and unencumbered software released into the public domain."),
    ("All-rights-reserved", "All rights reserved."),
    *((path.stem, path.read_text()) for path in sorted((Path(__file__).parent / "licence_texts").glob("*.txt"))),
)


def bigrams(text: str) -> set[tuple[str, str]]:
    words = _WORD.findall(text)
    return set(zip(words, words[1:], strict=False))


class Scanner:
    def __init__(self, templates: tuple[tuple[str, str], ...] = TEMPLATES, least: float = LEAST) -> None:
        self.least = least
        self.templates = sorted(((name, bigrams(text.lower())) for name, text in templates), key=lambda x: len(x[1]))
        sizes = [len(b) for _, b in self.templates]
        self.low, self.high = min(sizes) * least / (2 - least), max(sizes) * (2 - least) / least

    def unit(self, own: set[tuple[str, str]]) -> tuple[float, str] | None:
        """Best match of a unit: (coefficient, name)."""
        n, best = len(own), None
        if not self.low <= n <= self.high:
            return None
        for name, theirs in self.templates:
            m = len(theirs)
            if n * (2 - self.least) < self.least * m - 1e-9:
                break  # templates are sorted by size: all further ones are too large
            if n * self.least > (2 - self.least) * m + 1e-9:
                continue
            dice = 2.0 * len(own & theirs) / (n + m)
            if dice >= self.least and (best is None or (-dice, name) < (-best[0], best[1])):
                best = (dice, name)
        return best

    def passages(self, pairs: list[tuple[str, str]]) -> list[tuple[float, str, int, int]]:
        """Best match of each start among the runs of a text's bigrams: (coefficient, name, first bigram, last bigram)."""
        own, found = set(pairs), []
        for name, theirs in self.templates:
            m = len(theirs)
            if not m or len(own & theirs) * (2 - self.least) < self.least * m - 1e-9:
                continue
            most = int((2 - self.least) * m / self.least + 1e-9)
            count = np.arange(1, most + 1)
            following, at = [], {}  # distinct bigrams by next occurrence, latest first; and those occurrences
            for k in range(len(pairs) - 1, -1, -1):
                p = pairs[k]
                if p in at:
                    following.remove(p)
                elif len(following) == most:
                    del at[following.pop(0)]
                following.append(p)
                at[p] = k
                if p in theirs:
                    both = np.cumsum([x in theirs for x in reversed(following)])
                    dice = 2.0 * both / (count[: len(both)] + m)
                    best = int(dice.argmax())
                    if dice[best] >= self.least:
                        found.append((float(dice[best]), name, k, at[following[-1 - best]]))
        return found

    def scan(self, text: str | None) -> tuple[str | None, float, int]:
        """(licence, coefficient, matching units) of a text."""
        lower = (text or "").lower()
        found, taken, words = [], [], []
        lines = lower.split("\n")
        for line in lines:
            own = _WORD.findall(line)
            if m := self.unit(set(zip(own, own[1:], strict=False))):
                found.append(m)
                taken.append((len(words), len(words) + len(own) - 1))
            words += own
        pairs = list(zip(words, words[1:], strict=False))
        if len(lines) > 1 and (m := self.unit(set(pairs))):
            found.append(m)
            taken.append((0, len(words) - 1))
        n, best = len(found), found
        for dice, name, first, last in sorted(self.passages(pairs), key=lambda x: (-x[0], x[2] - x[3], *x[1:])):
            best = [*best, (dice, name)] if best is found else best  # the first is the best passage
            if all(last + 1 < a or first > b for a, b in taken):
                taken.append((first, last + 1))
                n += 1
        top = min(best, key=lambda m: (-m[0], m[1])) if best else (0.0, None)
        return top[1], top[0], n


def scan(df: DataFrame, id_col: str = "doc_id", text: str = "text", templates: tuple[tuple[str, str], ...] = TEMPLATES, least: float = LEAST) -> DataFrame:
    """(doc_id, license, dice, n_matches) for every row."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scanner = Scanner(templates, least)
        for b in batches:
            cols = list(zip(*(scanner.scan(t.as_py()) for t in b.column(1)), strict=True)) or [[], [], []]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(cols[0], pa.string()), pa.array(cols[1], pa.float64()), pa.array(cols[2], pa.int64())], names=["doc_id", "license", "dice", "n_matches"])

    rows = df.select(F.col(id_col).cast("bigint").alias("doc_id"), F.col(text).cast("string").alias("text"))
    return rows.mapInArrow(run, "doc_id bigint, license string, dice double, n_matches bigint")


def op7_licenses(df: DataFrame) -> DataFrame:
    return scan(df)


def _values() -> str:
    quoted = lambda s: "'" + s.replace("'", "''") + "'"
    return ", ".join(f"({quoted(n)}, {quoted(t)})" for n, t in TEMPLATES)


SQL = f"""
WITH d AS (SELECT doc_id, lower(coalesce(text, '')) AS t FROM documents),
u AS (SELECT doc_id, unnest(CASE WHEN contains(t, chr(10)) THEN list_append(string_split(t, chr(10)), t) ELSE [t] END) AS unit FROM d),
w AS (SELECT doc_id, regexp_extract_all(unit, '[a-z0-9]+') AS ws FROM u),
a AS (SELECT doc_id, row_number() OVER () AS r, list_distinct(list_transform(range(1, len(ws)), lambda i: ws[i] || ' ' || ws[i + 1])) AS bs FROM w WHERE len(ws) > 1),
t AS (SELECT name, list_distinct(list_transform(range(1, len(ws)), lambda i: ws[i] || ' ' || ws[i + 1])) AS bs
      FROM (SELECT name, regexp_extract_all(lower(body), '[a-z0-9]+') AS ws FROM (VALUES {_values()}) v(name, body))),
m AS (SELECT doc_id, r, name, 2.0::DOUBLE * len(list_intersect(a.bs, t.bs)) / (len(a.bs) + len(t.bs)) AS dice
      FROM a JOIN t ON len(a.bs) * 1.2 >= len(t.bs) * 0.8 - 1e-9 AND len(a.bs) * 0.8 <= len(t.bs) * 1.2 + 1e-9),
b AS (SELECT doc_id, r, max(dice) AS dice, arg_min(name, (-dice, name)) AS name FROM m WHERE dice >= {LEAST} GROUP BY doc_id, r)
SELECT d.doc_id, arg_min(b.name, (-b.dice, b.name)) AS license, coalesce(max(b.dice), 0.0::DOUBLE) AS dice, count(b.r)::BIGINT AS n_matches
FROM d LEFT JOIN b USING (doc_id) GROUP BY d.doc_id
"""
