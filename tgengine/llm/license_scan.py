"""License scan with winnowed fingerprints and banded alignment.

Texts and templates are taken as words. Every run of `GRAM` words is hashed and of each `WINNOW` neighbouring hashes the
smallest is kept as a fingerprint. The templates' fingerprints form an inverted index (hash -> template and place). A
fingerprint of a document that is in the index proposes the diagonal on which the template would lie; proposals of one
template on near diagonals are one candidate. The stretch of the document around it is aligned with the template within
a band: the most words matched in order. A candidate that covers at least `COVERAGE` of its template is reported with its
span, from the first to the last matched word; of overlapping reports the one with more matched words stays.

Templates are a parameter: a dictionary (name -> text) or a table of name and text, such as one of whole licenses; together
they may hold `MAX_TEMPLATE_BYTES`, as the index travels to the tasks. The built-in ones are whole short licenses and the notices
by which long ones are applied. Members of a family have templates of their own (two and three clauses; plain, lesser and network
versions), and the version that a text names within the span is reported beside the template. Any five words in a row that
text and template share give a common fingerprint; the band widens with the template, by one word in `WIDEN`. Null and empty texts have no
reports; texts shorter than a gram are compared as one gram; repeated rows are scanned alike; null ids and other columns
are carried or ignored.
"""

from __future__ import annotations

import re

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import map_rows, read

GRAM = 3
WINNOW = 3
BAND = 6
COVERAGE = 0.8
WORD = re.compile(r"[^\W_]+(?:\.\d+)*")
WIDEN = 40
#: Share of a template's fingerprints that must lie near one diagonal; at least one.
HITS = 0.1
MAX_TEMPLATE_BYTES = 32 << 20
_WARRANTY = "THE SOFTWARE IS PROVIDED \"AS IS\", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. "
_BSD_HEAD = "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: 1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer. 2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution. "
_BSD_NAME = "3. Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission. "
_BSD_TAIL = "THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS \"AS IS\" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE."
_ISC_TAIL = "THE SOFTWARE IS PROVIDED \"AS IS\" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE."


def _gnu(name: str, version: str = "3") -> str:
    return (
        f"This program is free software: you can redistribute it and/or modify it under the terms of the GNU {name} as published by the Free Software Foundation, either version {version} of the License, or (at your option) any later version. "
        f"This program is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE. See the GNU {name} for more details. "
        f"You should have received a copy of the GNU {name} along with this program. If not, see <https://www.gnu.org/licenses/>."
    )


def _creative(kind: str, version: str = "4.0") -> str:
    return f"This work is licensed under a Creative Commons {kind} {version} International License."


#: Short public licenses as a whole, and the notices of longer ones.
TEMPLATES = {
    "MIT-line": "Released under the MIT License.",
    "MIT": "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions: The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software. "
    + _WARRANTY + "IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE.",
    "ISC": "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies. " + _ISC_TAIL,
    "0BSD": "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted. " + _ISC_TAIL,
    "BSD-2-Clause": _BSD_HEAD + _BSD_TAIL,
    "BSD-3-Clause": _BSD_HEAD + _BSD_NAME + _BSD_TAIL,
    "Zlib": "This software is provided 'as-is', without any express or implied warranty. In no event will the authors be held liable for any damages arising from the use of this software. Permission is granted to anyone to use this software for any purpose, including commercial applications, and to alter it and redistribute it freely, subject to the following restrictions: 1. The origin of this software must not be misrepresented; you must not claim that you wrote the original software. If you use this software in a product, an acknowledgment in the product documentation would be appreciated but is not required. 2. Altered source versions must be plainly marked as such, and must not be misrepresented as being the original software. 3. This notice may not be removed or altered from any source distribution.",
    "BSL-1.0": "Permission is hereby granted, free of charge, to any person or organization obtaining a copy of the software and accompanying documentation covered by this license (the \"Software\") to use, reproduce, display, distribute, execute, and transmit the Software, and to prepare derivative works of the Software, and to permit third-parties to whom the Software is furnished to do so, all subject to the following: The copyright notices in the Software and this entire statement, including the above license grant, this restriction and the following disclaimer, must be included in all copies of the Software, in whole or in part, and all derivative works of the Software, unless such copies or derivative works are solely in the form of machine-executable object code generated by a source language processor. THE SOFTWARE IS PROVIDED \"AS IS\", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE, TITLE AND NON-INFRINGEMENT. IN NO EVENT SHALL THE COPYRIGHT HOLDERS OR ANYONE DISTRIBUTING THE SOFTWARE BE LIABLE FOR ANY DAMAGES OR OTHER LIABILITY, WHETHER IN CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE.",
    "Unlicense": "This is free and unencumbered software released into the public domain. Anyone is free to copy, modify, publish, use, compile, sell, or distribute this software, either in source code form or as a compiled binary, for any purpose, commercial or non-commercial, and by any means. In jurisdictions that recognize copyright laws, the author or authors of this software dedicate any and all copyright interest in the software to the public domain. We make this dedication for the benefit of the public at large and to the detriment of our heirs and successors. We intend this dedication to be an overt act of relinquishment in perpetuity of all present and future rights to this software under copyright law. THE SOFTWARE IS PROVIDED \"AS IS\", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE.",
    "Apache-line": "Licensed under the Apache License, Version 2.0.",
    "Apache-notice": "Licensed under the Apache License, Version 2.0 (the \"License\"); you may not use this file except in compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0 Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an \"AS IS\" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. See the License for the specific language governing permissions and limitations under the License.",
    "GPL-line": "This work is licensed under the GNU General Public License, version 3.",
    "GPL-notice": _gnu("General Public License"),
    "LGPL-notice": _gnu("Lesser General Public License"),
    "AGPL-notice": _gnu("Affero General Public License"),
    "MPL-notice": "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can obtain one at https://mozilla.org/MPL/2.0/.",
    "CC-BY-NC-line": "Licensed under CC BY-NC 4.0.",
    "CC-BY": _creative("Attribution"),
    "CC-BY-SA": _creative("Attribution-ShareAlike"),
    "CC-BY-NC": _creative("Attribution-NonCommercial"),
    "CC-BY-ND": _creative("Attribution-NoDerivatives"),
    "CC-BY-NC-SA": _creative("Attribution-NonCommercial-ShareAlike"),
    "CC-BY-NC-ND": _creative("Attribution-NonCommercial-NoDerivatives"),
}
VERSION = re.compile(r"v?(\d+(?:\.\d+)*)")


def words(text: str | None) -> list[str]:
    return WORD.findall((text or "").lower())


def _hashes(ids: np.ndarray) -> np.ndarray:
    n = max(1, len(ids) - GRAM + 1)
    out = np.zeros(n, dtype=np.uint64)
    for i in range(min(GRAM, len(ids))):
        out = (out * np.uint64(0x100000001B3) + ids[i : i + n].astype(np.uint64)) * np.uint64(0x9E3779B97F4A7C15)
        out ^= out >> np.uint64(32)
    return out


def winnow(ids: np.ndarray) -> np.ndarray:
    """Places of the fingerprints: the last smallest hash of each window."""
    h = _hashes(ids)
    if len(h) <= WINNOW:
        return np.array([len(h) - 1 - int(np.argmin(h[::-1]))])
    w = np.lib.stride_tricks.sliding_window_view(h, WINNOW)[:, ::-1]
    return np.unique(np.arange(len(w)) + WINNOW - 1 - w.argmin(axis=1))


class Index:
    def __init__(self, templates: dict[str, str]):
        self.words = {n: words(t) for n, t in templates.items() if words(t)}
        self.ids: dict[str, int] = {}
        for w in self.words.values():
            for x in w:
                self.ids.setdefault(x, len(self.ids) + 1)
        self.at: dict[int, list[tuple[str, int]]] = {}
        self.codes: dict[str, np.ndarray] = {}
        self.prints: dict[str, int] = {}
        for n, w in self.words.items():
            ids = self.code(w)
            h = _hashes(ids)
            self.codes[n] = ids
            self.prints[n] = len(winnow(ids))
            for p in winnow(ids).tolist():
                self.at.setdefault(int(h[p]), []).append((n, p))
        self.keys = np.array(sorted(self.at), dtype=np.uint64)

    def code(self, w: list[str]) -> np.ndarray:
        return np.fromiter((self.ids.get(x, 0) for x in w), dtype=np.int64, count=len(w))

    def candidates(self, ids: np.ndarray) -> set[tuple[str, int]]:
        """(template, diagonal), near diagonals taken once; a template of many fingerprints needs `HITS` of them, as a share, near one."""
        if not len(ids) or not ids.any():
            return set()
        places = winnow(ids)
        h = _hashes(ids)[places]
        known = np.isin(h, self.keys)
        near: dict[str, list[int]] = {}
        for p, x in zip(places[known].tolist(), h[known].tolist()):
            for n, q in self.at[x]:
                near.setdefault(n, []).append(p - q)
        out: set[tuple[str, int]] = set()
        for n, diagonals in near.items():
            d = np.sort(np.array(diagonals))
            reach = (BAND + len(self.words[n]) // WIDEN) // 2
            least = max(1, int(HITS * self.prints[n]))
            at = 0
            while at < len(d):
                end = int(np.searchsorted(d, d[at] + reach, side="right"))
                if end - at >= least:
                    out.add((n, int(d[(at + end - 1) // 2])))
                    at = end
                else:
                    at += 1
        return out


def named_version(w: list[str]) -> str | None:
    """The first number that stands as a version: after such a word, or after the license's name."""
    for before, x in zip(["", *w], w):
        m = VERSION.fullmatch(x)
        if m and (before in ("version", "v", "license", "nc", "nd", "sa", "by", "international") or x.startswith("v") or "." in x):
            return m[1]
    return None


def _farthest(t: np.ndarray, d: np.ndarray, diagonal: int, band: int) -> tuple[int, int, int]:
    """(matched, row, place) of the last pair of a longest match in order within the band; rows are computed as vectors over the band."""
    held = np.zeros(2 * band + 2, dtype=np.int64)
    best = (0, -1, -1)
    padded = np.full(len(t) + 2 * band + 1, -1, dtype=np.int64)  # d from place `diagonal - band` on
    lo, hi = max(0, diagonal - band), min(len(d), diagonal - band + len(padded))
    if lo < hi:
        padded[lo - diagonal + band : hi - diagonal + band] = d[lo:hi]
    for i, x in enumerate(t.tolist()):
        # the band moves one place to the right with each row
        now = np.maximum(held[1:], held[:-1] + (padded[i : i + 2 * band + 1] == x))
        now = np.maximum.accumulate(now)
        top = int(now[-1])
        if top > best[0]:
            best = (top, i, i + diagonal - band + int(now.argmax()))
        held[:-1] = now
        held[-1] = top
    return best


def align(t: np.ndarray, d: np.ndarray, diagonal: int, band: int = BAND) -> tuple[int, int, int]:
    """Most template words matched in order with |place - template place - diagonal| <= band: (matched, first, last + 1)."""
    m, i, j = _farthest(t, d, diagonal, band)
    if not m:
        return 0, 0, 0
    # backwards from the last pair, the first one
    _, back, place = _farthest(t[i::-1], d[j::-1], (j - i) - diagonal, band)
    return m, j - place, j + 1


def scan(text: str | None, index: Index, coverage: float = COVERAGE) -> list[dict]:
    w = words(text)
    found = []
    ids = index.code(w)
    for name, d in index.candidates(ids):
        t = index.words[name]
        m, a, b = align(index.codes[name], ids, d, BAND + len(t) // WIDEN)
        if m and m >= coverage * len(t):
            found.append({"license": name, "version": named_version(w[a:b]), "matched": m, "coverage": m / len(t), "first_word": a, "end_word": b})
    found.sort(key=lambda f: (-f["matched"], -f["coverage"], f["first_word"], f["license"]))
    kept: list[dict] = []
    for f in found:
        if all(f["end_word"] <= k["first_word"] or f["first_word"] >= k["end_word"] for k in kept):
            kept.append(f)
    return sorted(kept, key=lambda f: f["first_word"])


SPANS = "array<struct<license: string, version: string, matched: int, coverage: double, first_word: int, end_word: int>>"


def read_templates(table: DataFrame) -> dict[str, str]:
    """name -> text of a table, whose size is checked before any text comes to the driver."""
    size = table.agg(F.coalesce(F.sum(F.octet_length("text")), F.lit(0))).first()[0]
    if size > MAX_TEMPLATE_BYTES:
        raise ValueError(f"templates of {size} bytes; at most {MAX_TEMPLATE_BYTES} travel to the tasks")
    return {r["name"]: r["text"] for r in table.select("name", "text").collect() if r["name"] is not None}


def report(docs: DataFrame, templates: dict[str, str] | DataFrame | None = None, coverage: float = COVERAGE) -> DataFrame:
    """doc_id, n_spans, licenses (distinct, in order, comma-joined), best_coverage, spans of every row."""
    chosen = TEMPLATES if templates is None else read_templates(templates) if isinstance(templates, DataFrame) else templates

    def run(batches):
        index = Index(chosen)
        for b in batches:
            s = [scan(t, index, coverage) for t in b["text"]]
            yield {
                "doc_id": b["doc_id"], "n_spans": [len(x) for x in s], "licenses": [",".join(sorted({y["license"] for y in x})) for x in s],
                "best_coverage": [max((y["coverage"] for y in x), default=0.0) for x in s], "spans": s,
            }

    return map_rows(docs.select("doc_id", "text"), f"doc_id long, n_spans int, licenses string, best_coverage double, spans {SPANS}", run)


def op9_license_scan(spark, sf_dir: str) -> DataFrame:
    return report(read(spark, sf_dir, "documents"))
