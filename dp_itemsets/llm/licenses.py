"""License scans by patience alignment.

A text and a template are aligned on the words that occur exactly once in
both: their longest increasing subsequence is kept, and each gap between two
kept words is aligned in the same way, where more words are unique.  Coverage
is the share of template words that found their place.  Licenses of a family
differ in a word or two ("Lesser", "NonCommercial", a version), so a finding
must hold just its template's words of that kind, and of several the one whose
span agrees best with its template names the license.

The alignment runs only where the words that text and template share could
reach the asked coverage at all, which loses nothing.
"""

from __future__ import annotations

from bisect import bisect_left
from collections import Counter
from collections.abc import Iterable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame

from .common import alnum_words, blocks, texts

#: Least share of a template's words for a finding, and least agreement of template and span.
COVERAGE = 0.8
#: A finding spans at most so many times its template's words.
STRETCH = 2.0

# Public license notices and statements, word for word.
TEMPLATES: dict[str, str] = {
    "Apache-2.0/statement": "Licensed under the Apache License, Version 2.0.",
    "Apache-2.0/notice": (
        "Licensed under the Apache License, Version 2.0 (the \"License\"); you may not use this file except in compliance with the License. "
        "You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0 Unless required by applicable law or agreed to in writing, "
        "software distributed under the License is distributed on an \"AS IS\" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. "
        "See the License for the specific language governing permissions and limitations under the License."
    ),
    "MIT/statement": "Released under the MIT License.",
    "MIT/text": (
        "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), "
        "to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, "
        "and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions: "
        "The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software. "
        "THE SOFTWARE IS PROVIDED \"AS IS\", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, "
        "FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER "
        "LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS "
        "IN THE SOFTWARE."
    ),
    "GPL-3.0/statement": "This work is licensed under the GNU General Public License, version 3.",
    "GPL-2.0/statement": "This work is licensed under the GNU General Public License, version 2.",
    "LGPL-3.0/statement": "This work is licensed under the GNU Lesser General Public License, version 3.",
    "LGPL-2.1/statement": "This work is licensed under the GNU Lesser General Public License, version 2.1.",
    "AGPL-3.0/statement": "This work is licensed under the GNU Affero General Public License, version 3.",
    "GPL-3.0/notice": (
        "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by "
        "the Free Software Foundation, either version 3 of the License, or (at your option) any later version. "
        "This program is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or "
        "FITNESS FOR A PARTICULAR PURPOSE. See the GNU General Public License for more details. "
        "You should have received a copy of the GNU General Public License along with this program. If not, see <https://www.gnu.org/licenses/>."
    ),
    "CC-BY-4.0/short": "Licensed under CC BY 4.0.",
    "CC-BY-SA-4.0/short": "Licensed under CC BY-SA 4.0.",
    "CC-BY-ND-4.0/short": "Licensed under CC BY-ND 4.0.",
    "CC-BY-NC-4.0/statement": "Licensed under CC BY-NC 4.0.",
    "CC-BY-NC-SA-4.0/short": "Licensed under CC BY-NC-SA 4.0.",
    "CC-BY-NC-ND-4.0/short": "Licensed under CC BY-NC-ND 4.0.",
    "CC-BY-4.0/statement": "This work is licensed under a Creative Commons Attribution 4.0 International License.",
    "CC-BY-SA-4.0/statement": "This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License.",
    "CC-BY-ND-4.0/statement": "This work is licensed under a Creative Commons Attribution-NoDerivatives 4.0 International License.",
    "CC-BY-NC-4.0/long statement": "This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International License.",
    "CC-BY-NC-SA-4.0/statement": "This work is licensed under a Creative Commons Attribution-NonCommercial-ShareAlike 4.0 International License.",
    "CC-BY-NC-ND-4.0/statement": "This work is licensed under a Creative Commons Attribution-NonCommercial-NoDerivatives 4.0 International License.",
    "BSD-2-Clause/text": (
        "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: "
        "Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer. "
        "Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation "
        "and/or other materials provided with the distribution. "
        "THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS \"AS IS\" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, "
        "THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS "
        "BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE "
        "GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, "
        "STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF "
        "SUCH DAMAGE."
    ),
    "ISC/text": (
        "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above "
        "copyright notice and this permission notice appear in all copies. "
        "THE SOFTWARE IS PROVIDED \"AS IS\" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF "
        "MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES "
        "WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN "
        "CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE."
    ),
    "MPL-2.0/notice": (
        "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, "
        "You can obtain one at https://mozilla.org/MPL/2.0/."
    ),
    "All-rights-reserved/statement": "All rights reserved.",
}

#: Words that tell public licenses of one family apart.  A finding holds just those of its template.
TELLING = frozenset((
    b"0", b"1", b"2", b"3", b"4", b"5", b"affero", b"apache", b"attribution", b"bsd", b"by", b"cc", b"commons", b"creative", b"gnu", b"international", b"lesser",
    b"library", b"mit", b"mozilla", b"mpl", b"nc", b"nd", b"noderivatives", b"noderivs", b"noncommercial", b"sa", b"sharealike", b"unported",
))


def _once(words: list[bytes], start: int, end: int) -> dict[bytes, int]:
    """Words that occur once in [start, end), with their place."""
    seen: dict[bytes, int] = {}
    for k in range(start, end):
        seen[words[k]] = -1 if words[k] in seen else k
    return {w: k for w, k in seen.items() if k >= 0}


def increasing(pairs: list[tuple[int, int]]) -> list[tuple[int, int]]:
    """The longest run of pairs, sorted by their first, whose seconds increase (patience piles)."""
    tops: list[int] = []
    piles: list[int] = []
    back = [-1] * len(pairs)
    for k, (_, b) in enumerate(pairs):
        at = bisect_left(tops, b)
        back[k] = piles[at - 1] if at else -1
        tops[at : at + 1], piles[at : at + 1] = [b], [k]
    out, k = [], piles[-1] if piles else -1
    while k >= 0:
        out.append(pairs[k])
        k = back[k]
    return out[::-1]


def align(text: list[bytes], template: list[bytes]) -> list[tuple[int, int]]:
    """Pairs (place in the text, place in the template) of aligned words, in order."""
    out: list[tuple[int, int]] = []
    todo = [(0, len(text), 0, len(template))]
    while todo:
        a, b, c, d = todo.pop()
        while a < b and c < d and text[a] == template[c] and (a, c) != (0, 0):  # gaps grow from their anchors inwards
            out.append((a, c))
            a, c = a + 1, c + 1
        while a < b and c < d and text[b - 1] == template[d - 1] and (b, d) != (len(text), len(template)):
            b, d = b - 1, d - 1
            out.append((b, d))
        if a >= b or c >= d:
            continue
        own, other = _once(text, a, b), _once(template, c, d)
        anchors = increasing(sorted((own[w], k) for w, k in other.items() if w in own))
        out += anchors
        for (e, f), (g, h) in zip([(a - 1, c - 1), *anchors], [*anchors, (b, d)], strict=True) if anchors else ():
            todo.append((e + 1, g, f + 1, h))
    return sorted(out)


def densest(pairs: list[tuple[int, int]], most: int) -> tuple[int, int]:
    """[first, last) of the pairs that hold the most within ``most`` consecutive text words, of equals the tightest, then the first."""
    best, key, first = (0, 0), (0, 0), 0
    for last in range(len(pairs)):
        while pairs[last][0] - pairs[first][0] >= most:
            first += 1
        now = (last + 1 - first, pairs[first][0] - pairs[last][0])
        if now > key:
            best, key = (first, last + 1), now
    return best


def telling(words: Iterable[bytes]) -> Counter:
    """The words that tell licenses apart, with their numbers."""
    return Counter(w for w in words if w in TELLING)


def _starts(words: list[bytes], size: int, step: int, first: int, last: int, need: Counter, least: float) -> Iterator[int]:
    """Starts of windows of ``size`` words, ``step`` apart, that share at least ``least`` words with the template."""
    for k in range(first, last, step):
        held = Counter(w for w in words[k : k + size] if w in need)
        if sum(min(n, held[w]) for w, n in need.items()) >= least:
            yield k


def _best_span(words: list[bytes], template: list[bytes], need: Counter, least: float, reach: int) -> tuple[float, float, int, int] | None:
    """(coverage, agreement, start, end) of the best finding of at most ``reach`` words, the first of equals.

    Every span of that size lies in a tile of twice the size, one starting at
    each multiple of it; tiles whose shared words can't reach the coverage hold
    none.  Where a template stands in a tile several times, none of its words is
    unique, so a tile without a finding is aligned in windows of one and a half
    times and of just the template's size.
    """
    found, size, own = None, len(template), telling(template)
    for tile in _starts(words, 2 * reach, reach, 0, len(words), need, least):
        for width in (2 * reach, size + size // 2, size):
            step = reach if width == 2 * reach else max(1, size // 8)
            here = False
            for low in _starts(words, width, step, tile, min(tile + reach, len(words)), need, least):
                pairs = align(words[low : low + width], template)
                first, last = densest(pairs, reach)
                if last - first < least:
                    continue
                start, end = low + pairs[first][0], low + pairs[last - 1][0] + 1
                # template words beyond the aligned ones count as missing, text words between them as put in
                if telling(words[start:end]) != own:
                    continue
                share, agreement = (last - first) / size, 2 * (last - first) / (size + end - start)
                if agreement < least / size:
                    continue
                here = True
                if found is None or (agreement, share) > (found[1], found[0]):
                    found = (share, agreement, start, end)
                if agreement == 1:
                    return found
            if here:
                break
    return found


def scan(words: list[bytes], templates: list[tuple[str, list[bytes], Counter]], coverage: float = COVERAGE, stretch: float = STRETCH) -> list[tuple[str, float, int, int]]:
    """(template, coverage, start, end) of each finding: what agrees best with its template first, then the longer template.

    Agreement is twice the aligned words over the words of template and span,
    so words put in count against a finding as missing ones do.
    """
    distinct, out = set(words), []
    counts: Counter | None = None
    for name, template, need in templates:
        least = coverage * len(template)
        if sum(n for w, n in need.items() if w in distinct) < least or any(w in TELLING and w not in distinct for w in need):
            continue
        counts = Counter(words) if counts is None else counts
        if sum(min(n, counts[w]) for w, n in need.items()) < least:
            continue
        found = _best_span(words, template, need, least, int(stretch * len(template)))
        if found:
            out.append((name, *found))
    size = {name: len(t) for name, t, _ in templates}
    out.sort(key=lambda f: (-f[2], -size[f[0]], f[0]))
    return [(name, share, start, end) for name, share, _, start, end in out]


def scan_licenses(docs: DataFrame, templates: dict[str, str] | None = None, coverage: float = COVERAGE) -> DataFrame:
    """One row per row of ``docs``: doc_id, license (the template that agrees best, or null), coverage, start, end, n_findings, findings.

    start and end count words of the text.  Null, empty and unlicensed texts
    have no findings and coverage 0.  All texts are scanned whole.
    """
    prepared = [(name, w, Counter(w)) for name, w in ((n, alnum_words(t.encode())) for n, t in (templates or TEMPLATES).items()) if w]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in blocks(batches):
            found = [scan(alnum_words(t), prepared, coverage) for t in texts(batch.column("text"))]
            best = [f[0] if f else (None, 0.0, None, None) for f in found]
            cols = [pa.array(c, k) for c, k in zip(zip(*best, strict=True), (pa.string(), pa.float64(), pa.int32(), pa.int32()), strict=True)]
            all_names = pa.array([[f[0] for f in x] for x in found], pa.list_(pa.string()))
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), *cols, pa.array([len(x) for x in found], pa.int32()), all_names], ["doc_id", "license", "coverage", "start", "end", "n_findings", "findings"])

    kind = docs.schema["doc_id"].dataType.simpleString()
    return docs.select("doc_id", "text").mapInArrow(run, f"doc_id {kind}, license string, coverage double, start int, end int, n_findings int, findings array<string>")
