"""Licence scans by patience alignment.

Around each opener of a template, a window of the text is aligned with the template: words that
occur once in both are anchors, a longest increasing subsequence of them is kept, and the gaps
between anchors are aligned in the same way. Coverage is the share of the template's words that the
alignment reaches. A template has one opener more than words that a covered text may lack, so that no
change of words that keeps the coverage hides all of them. Spark's scan leaves out texts without any
opener, and only those.
"""

from __future__ import annotations

import re
from bisect import bisect_left
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass
from functools import cache, cached_property

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: The templates, by SPDX identifier or family; notices, single clauses, and whole licences.
TEMPLATES = {
    "MIT-line": "Released under the MIT License.",
    "Apache-2.0-line": "Licensed under the Apache License, Version 2.0.",
    "GPL-3.0-line": "This work is licensed under the GNU General Public License, version 3.",
    "CC-BY-NC-4.0-line": "Licensed under CC BY-NC 4.0.",
    "MIT": "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files, to deal in the Software without restriction",
    "Apache-2.0": "Licensed under the Apache License, Version 2.0 (the License); you may not use this file except in compliance with the License. You may obtain a copy of the License at",
    "GPL": "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation",
    "BSD": "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met",
    "MPL-2.0": "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0.",
    "CC": "This work is licensed under a Creative Commons Attribution License",
    "MIT-text": "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions: The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software. THE SOFTWARE IS PROVIDED \"AS IS\", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE.",
    "ISC-text": "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies. THE SOFTWARE IS PROVIDED \"AS IS\" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE.",
    "BSD-2-Clause-text": "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: 1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer. 2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution. THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS \"AS IS\" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE.",
    "Zlib-text": "This software is provided 'as-is', without any express or implied warranty. In no event will the authors be held liable for any damages arising from the use of this software. Permission is granted to anyone to use this software for any purpose, including commercial applications, and to alter it and redistribute it freely, subject to the following restrictions: 1. The origin of this software must not be misrepresented; you must not claim that you wrote the original software. If you use this software in a product, an acknowledgment in the product documentation would be appreciated but is not required. 2. Altered source versions must be plainly marked as such, and must not be misrepresented as being the original software. 3. This notice may not be removed or altered from any source distribution.",
}
MIN_COVERAGE, SLACK = 0.8, 0.25
#: Words that open windows only if a template has too few others. The result does not depend on them.
COMMON = frozenset("a an and any are as at by following for in is it may met not obtain of or person program provided source terms that the this to under use version with without work you".split())
_WORD = re.compile(r"[^\W_]+(?:[.\-][^\W_]+)*")


@dataclass(frozen=True)
class Template:
    name: str
    text: str

    @cached_property
    def words(self) -> list[str]:
        return _WORD.findall(self.text.lower())

    def least(self, min_coverage: float) -> int:
        """The words that an alignment must reach; at least one."""
        return next((k for k in range(1, len(self.words) + 1) if k >= min_coverage * len(self.words)), len(self.words) + 1)

    @cache
    def openers(self, min_coverage: float) -> list[tuple[str, int]]:
        """(word, its place) of the rarer words: of so many, an alignment that covers enough reaches at least one."""
        places = sorted(enumerate(self.words), key=lambda x: (x[1] in COMMON, -len(x[1]), x[0]))
        return [(w, i) for i, w in places[: len(self.words) - self.least(min_coverage) + 1]]


def align(a: list[str], b: list[str], a0: int = 0, a1: int | None = None, b0: int = 0, b1: int | None = None) -> list[tuple[int, int]]:
    """Pairs (i, j) of equal words a[i] = b[j], both increasing. Without recursion's depth: gaps wait on a list."""
    out, todo = [], [(a0, len(a) if a1 is None else a1, b0, len(b) if b1 is None else b1)]
    while todo:
        i0, i1, j0, j1 = todo.pop()
        while i0 < i1 and j0 < j1 and a[i0] == b[j0]:
            out.append((i0, j0))
            i0, j0 = i0 + 1, j0 + 1
        while i0 < i1 and j0 < j1 and a[i1 - 1] == b[j1 - 1]:
            i1, j1 = i1 - 1, j1 - 1
            out.append((i1, j1))
        if i0 >= i1 or j0 >= j1:
            continue
        ca, cb = Counter(a[i0:i1]), Counter(b[j0:j1])
        where = {b[j]: j for j in range(j0, j1) if cb[b[j]] == 1}
        pairs = [(i, where[a[i]]) for i in range(i0, i1) if ca[a[i]] == 1 and a[i] in where]
        tails, ends, back = [], [], []
        for n, (_, j) in enumerate(pairs):
            k = bisect_left(tails, j)
            back.append(ends[k - 1] if k else -1)
            if k == len(tails):
                tails.append(j), ends.append(n)
            else:
                tails[k], ends[k] = j, n
        chain, n = [], ends[-1] if ends else -1
        while n >= 0:
            chain.append(pairs[n])
            n = back[n]
        if not chain:
            continue
        out += chain
        edges = [(i0 - 1, j0 - 1), *reversed(chain), (i1, j1)]
        todo += [(p + 1, r, q + 1, s) for (p, q), (r, s) in zip(edges[:-1], edges[1:], strict=True)]
    return sorted(out)


def scan_text(text: str, templates: list[Template], min_coverage: float = MIN_COVERAGE) -> list[tuple[str, int, int, float]]:
    """(template, first word, word after the last, coverage), best first among those that overlap in the text."""
    words = _WORD.findall(text.lower())
    places: dict[str, list[int]] = {}
    opening = {t: t.openers(min_coverage) for t in templates}
    known = {w for x in opening.values() for w, _ in x}
    for i, w in enumerate(words):
        if w in known:
            places.setdefault(w, []).append(i)
    found = set()
    for t in templates:
        n = len(t.words)
        slack = max(1, int(n * SLACK))
        least, own = t.least(min_coverage), Counter(t.words)
        for word, at in opening[t]:
            for p in places.get(word, ()):
                lo, hi = max(0, p - at - slack), min(len(words), p - at + n + slack)
                if (own & Counter(words[lo:hi])).total() < least:
                    continue
                pairs = align(words, t.words, lo, hi)
                if len(pairs) >= least:
                    found.add((t.name, pairs[0][0], pairs[-1][0] + 1, round(len(pairs) / n, 6), len(pairs)))
    out: list[tuple] = []
    # The longest match of a place wins, and of equals the better covered, the earlier, the first name.
    for x in sorted(found, key=lambda x: (-x[4], -x[3], x[1], x[0])):
        if all(x[2] <= y[1] or y[2] <= x[1] for y in out):
            out.append(x)
    return sorted(x[:4] for x in out)


def _any_of(words: list[str]) -> str:
    """A pattern for any of the words, with common beginnings taken together, so that most places of a text fail at one character."""
    by: dict[str, list[str]] = {}
    for w in sorted(set(words)):
        by.setdefault(w[:1], []).append(w[1:])
    if "" in by:
        return ""  # a word ends here, and longer ones need no look
    return "(?:" + "|".join(re.escape(k) + _any_of(v) for k, v in by.items()) + ")"


def license_matches(docs: DataFrame, text: str = "text", doc_id: str = "doc_id", templates: dict[str, str] = TEMPLATES, min_coverage: float = MIN_COVERAGE) -> DataFrame:
    """doc_id, license, first_word, end_word, coverage: one row for each licence text in each row of docs.

    Null and empty texts have none. Repeated rows give repeated results. A null doc_id stays null.
    Templates without a word are refused.
    """
    known = [Template(k, v) for k, v in templates.items()]
    if bare := [t.name for t in known if not t.words]:
        raise ValueError(f"templates without a word: {bare}")
    openers = sorted({w for t in known for w, _ in t.openers(min_coverage)})

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = [(i.as_py(), *m) for i, b in zip(batch.column(0), batch.column(1), strict=True) for m in scan_text(b.as_py(), known, min_coverage)]
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), [pa.int64(), pa.string(), pa.int64(), pa.int64(), pa.float64()], strict=True)], ["doc_id", "license", "first_word", "end_word", "coverage"])

    rows = docs.select(docs[doc_id].cast("long").alias("doc_id"), docs[text].cast("string").alias("text"))
    # Within a run of ASCII letters and digits a word cannot begin, so only the beginnings of such runs are looked at.
    rows = rows.filter(F.col("text").rlike("(?iu)(?<![a-z0-9])" + _any_of(openers)))
    return rows.mapInArrow(run, "doc_id long, license string, first_word long, end_word long, coverage double")


def op2_query(spark, sf_dir: str) -> DataFrame:
    return license_matches(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text"))
