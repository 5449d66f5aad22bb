"""License scans: winnowed fingerprints of templates pick candidates, a banded alignment measures them.

Templates are cut into words (runs of ASCII letters and digits, in lower case) and ``GRAM``-word grams; of each
window of grams the one with the least hash is a fingerprint, kept in an inverted index (hash -> template,
place). The index comes from the templates alone, a list that the caller gives, so it is bounded whatever the
corpus. A text's grams that the index holds are hits; hits of a template that lie near one diagonal form a candidate,
and a local alignment within a band around it gives matched words, coverage and the span in code points.

So a template is found wherever a text has ``GRAM`` + ``WINDOW`` - 1 of its words in a row (``GRAM``, for a short one).
A match counts two, a word left out, put in or changed takes one off: the band loses nothing unless more than
twice ``BAND`` words (an eighth of a long template) were put in or left out before a place. Of matches that end at one word the fullest is reported.

Null and empty texts have no matches, nor has an empty table; repeated rows are scanned each; very long texts are
scanned whole. Only doc_id and the text are read, so other columns never clash.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import types as T

from componentry.llm.words import text_blocks

GRAM = 3
WINDOW = 3
BAND = 8
COVERAGE = 0.8
#: templates of fewer words keep all their grams
SHORT = 12

# fixed values: wording of public licences and of the notices that refer to longer ones
TEMPLATES: dict[str, str] = {
    "mit-notice": "Released under the MIT License.",
    "apache-2.0-notice": "Licensed under the Apache License, Version 2.0.",
    "gpl-3.0-notice": "This work is licensed under the GNU General Public License, version 3.",
    "cc-by-nc-4.0-notice": "Licensed under CC BY-NC 4.0.",
    "cc-by-4.0-notice": "This work is licensed under a Creative Commons Attribution 4.0 International License.",
    "all-rights-reserved": "All rights reserved.",
    "mit": "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the Software), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions: The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software. THE SOFTWARE IS PROVIDED AS IS, WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE.",
    "mit-permission": "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the Software), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions: The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software.",
    "bsd-2-clause": "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: 1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer. 2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution. THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS AS IS AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE.",
    "bsd-3-clause": "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: 1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer. 2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution. 3. Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission. THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS AS IS AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE.",
    "isc": "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies. THE SOFTWARE IS PROVIDED AS IS AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE.",
    "zlib": "This software is provided as-is, without any express or implied warranty. In no event will the authors be held liable for any damages arising from the use of this software. Permission is granted to anyone to use this software for any purpose, including commercial applications, and to alter it and redistribute it freely, subject to the following restrictions: 1. The origin of this software must not be misrepresented; you must not claim that you wrote the original software. If you use this software in a product, an acknowledgment in the product documentation would be appreciated but is not required. 2. Altered source versions must be plainly marked as such, and must not be misrepresented as being the original software. 3. This notice may not be removed or altered from any source distribution.",
    "unlicense": "This is free and unencumbered software released into the public domain. Anyone is free to copy, modify, publish, use, compile, sell, or distribute this software, either in source code form or as a compiled binary, for any purpose, commercial or non-commercial, and by any means. In jurisdictions that recognize copyright laws, the author or authors of this software dedicate any and all copyright interest in the software to the public domain. We make this dedication for the benefit of the public at large and to the detriment of our heirs and successors. We intend this dedication to be an overt act of relinquishment in perpetuity of all present and future rights to this software under copyright law.",
    "bsl-1.0": "Permission is hereby granted, free of charge, to any person or organization obtaining a copy of the software and accompanying documentation covered by this license (the Software) to use, reproduce, display, distribute, execute, and transmit the Software, and to prepare derivative works of the Software, and to permit third-parties to whom the Software is furnished to do so, all subject to the following: The copyright notices in the Software and this entire statement, including the above license grant, this restriction and the following disclaimer, must be included in all copies of the Software, in whole or in part, and all derivative works of the Software, unless such copies or derivative works are solely in the form of machine-executable object code generated by a source language processor.",
    "apache-2.0": "Licensed under the Apache License, Version 2.0 (the License); you may not use this file except in compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0 Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an AS IS BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. See the License for the specific language governing permissions and limitations under the License.",
    "gpl-3.0": "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version. This program is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE. See the GNU General Public License for more details. You should have received a copy of the GNU General Public License along with this program. If not, see https://www.gnu.org/licenses/.",
    "lgpl-3.0": "This program is free software: you can redistribute it and/or modify it under the terms of the GNU Lesser General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version. This program is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE. See the GNU Lesser General Public License for more details. You should have received a copy of the GNU Lesser General Public License along with this program. If not, see https://www.gnu.org/licenses/.",
    "agpl-3.0": "This program is free software: you can redistribute it and/or modify it under the terms of the GNU Affero General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version. This program is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE. See the GNU Affero General Public License for more details. You should have received a copy of the GNU Affero General Public License along with this program. If not, see https://www.gnu.org/licenses/.",
    "mpl-2.0": "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can obtain one at http://mozilla.org/MPL/2.0/.",
}

_WORD = re.compile(r"[a-z0-9]+", re.ASCII)

MATCHES = T.StructType(
    [T.StructField("doc_id", T.LongType()), T.StructField("template", T.StringType())]
    + [T.StructField(n, T.LongType()) for n in ("matched_words", "template_words", "coverage_percent", "span_start", "span_end")]
)


def _lower(text: str) -> str:
    """ASCII letters in lower case; every other character keeps its place."""
    return text.translate(_UPPER)


_UPPER = {c: c + 32 for c in range(65, 91)}


def winnow(hashes: np.ndarray, window: int = WINDOW) -> np.ndarray:
    """Places of the fingerprints: the rightmost least hash of each window."""
    n = len(hashes)
    if n <= window:
        return np.array([n - 1 - int(np.argmin(hashes[::-1]))]) if n else np.zeros(0, np.int64)
    views = np.lib.stride_tricks.sliding_window_view(hashes, window)
    return np.unique(np.arange(n - window + 1) + window - 1 - np.argmin(views[:, ::-1], axis=1))


class TemplateIndex:
    def __init__(self, templates: dict[str, str], gram: int = GRAM, window: int = WINDOW):
        self.gram = gram
        self.names = list(templates)
        split = [_WORD.findall(_lower(t)) for t in templates.values()]
        vocabulary = {w: i for i, w in enumerate(sorted({w for t in split for w in t}), 1)}
        self.ids = vocabulary
        # short templates may follow one another closely; in long ones more words may be put in or left out
        self.bands = [max(1, min(len(t) // 4, max(BAND, len(t) // 8))) for t in split]
        self.words = [np.array([vocabulary[w] for w in t], np.int64) for t in split]
        index: dict[int, list[tuple[int, int]]] = {}
        for t, words in enumerate(self.words):
            h = self.grams(words)
            for p in winnow(h, window if len(words) >= SHORT else 1):
                index.setdefault(int(h[p]), []).append((t, int(p)))
        self.index = index
        self.keys = np.array(sorted(index), np.uint64)

    def grams(self, ids: np.ndarray) -> np.ndarray:
        """Hash of each gram, 0 where a word is in no template."""
        n = len(ids) - self.gram + 1
        if n <= 0:
            return np.zeros(0, np.uint64)
        h, ok = np.zeros(n, np.uint64), np.ones(n, bool)
        for k in range(self.gram):
            part = ids[k : k + n]
            ok &= part > 0
            h = h * np.uint64(0x9E3779B97F4A7C15) + part.astype(np.uint64) + np.uint64(k + 1)
        return np.where(ok, h ^ (h >> np.uint64(29)), np.uint64(0))

    def candidates(self, ids: np.ndarray) -> list[tuple[int, int]]:
        """(template, diagonal) of the groups of hits; a diagonal is text place less template place."""
        h = self.grams(ids)
        at = np.flatnonzero(np.isin(h, self.keys) & (h > 0))
        hits: dict[int, list[int]] = {}
        for p in at:
            for t, q in self.index[int(h[p])]:
                hits.setdefault(t, []).append(int(p) - q)
        out = []
        for t, diagonals in hits.items():
            last = None
            for d in sorted(diagonals):
                if last is None or d - last > self.bands[t]:
                    out.append((t, d))
                    last = d
        return out

    def align(self, t: int, ids: np.ndarray, diagonal: int) -> tuple[int, int, int]:
        """(matched words, first, last) of the best local alignment of template ``t`` within its band of the diagonal."""
        band = 2 * self.bands[t]
        want = self.words[t].tolist()
        text = ids[max(0, diagonal - band) : max(0, diagonal + len(want) + band + 1)].tolist()
        shift = max(0, diagonal - band)
        best = (0, 0, 0, 0)
        above: dict[int, tuple[int, int, int]] = {}
        for i, w in enumerate(want):
            row: dict[int, tuple[int, int, int]] = {}
            for j in range(max(0, i + diagonal - band - shift), min(len(text), i + diagonal + band + 1 - shift)):
                if text[j] == w:
                    s, m, a = above.get(j - 1, (0, 0, j))
                    cell = (s + 2, m + 1, a)
                else:
                    s, m, a = max(above.get(j - 1, (0, 0, j + 1)), above.get(j, (0, 0, j + 1)), row.get(j - 1, (0, 0, j + 1)))
                    cell = (s - 1, m, a) if s > 1 else (0, 0, j + 1)
                row[j] = cell
                if cell[:2] > best[:2]:
                    best = (*cell, j)
            above = row
        return best[1], best[2] + shift, best[3] + shift

    def scan(self, text: str, coverage: float = COVERAGE) -> list[tuple]:
        """(template, matched, words, percent, start, end) of each match, by start."""
        low = _lower(text)
        ids = np.fromiter((self.ids.get(w, 0) for w in _WORD.findall(low)), np.int64)
        found = self.candidates(ids)
        if not found:
            return []
        spans = [m.span() for m in _WORD.finditer(low)]
        best: dict[tuple[int, int], tuple] = {}
        for t, d in found:
            n = len(self.words[t])
            matched, first, last = self.align(t, ids, d)
            if matched >= max(GRAM, coverage * n):
                hit = (self.names[t], matched, n, 100 * matched // n, spans[first][0], spans[last][1])
                key = (t, last)
                if key not in best or hit[1] > best[key][1]:
                    best[key] = hit
        return sorted(best.values(), key=lambda x: (x[4], x[0]))


def license_scan(docs: DataFrame, templates: dict[str, str] | None = None, coverage: float = COVERAGE, text: str = "text") -> DataFrame:
    """A row for each match of a template in a row of ``docs``."""
    templates = templates or TEMPLATES

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        index = TemplateIndex(templates)
        for batch in batches:
            for a, b in text_blocks(batch, text):
                part = batch.slice(a, b - a)
                rows = [(d, *m) for d, t in zip(part["doc_id"].to_pylist(), part[text].to_pylist(), strict=True) if t for m in index.scan(t, coverage)]
                if rows:
                    cols = zip(*rows, strict=True)
                    yield pa.RecordBatch.from_arrays([pa.array(c, pa.string() if i == 1 else pa.int64()) for i, c in enumerate(cols)], names=MATCHES.names)

    return docs.select(docs["doc_id"].cast("long").alias("doc_id"), text).mapInArrow(run, MATCHES)


def op2_license_scans(spark: SparkSession, sf_dir: str) -> DataFrame:
    return license_scan(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text"))


__all__ = ["MATCHES", "TEMPLATES", "TemplateIndex", "license_scan", "op2_license_scans", "winnow"]
