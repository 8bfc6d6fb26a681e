"""License scan by conditional compression.

Blocks of words around license cues, across line ends and comment marks, are compressed with zstandard once alone and once
with each template as raw dictionary; the relative size reduction ranks the templates. A notice is confirmed by exact
wording: every template, whole licenses among them, is looked for word for word in every block, so a sentence that several licenses share
confirms none of them. What is left of a block around its confirmed notices gets the template of the ``contenders`` best
ranked that differs in the fewest words, with the words that differ.

Words are compared without case and punctuation; a star in a template stands for one to eight words. Null, empty and
unlicensed texts give no rows; repeated rows give repeated findings; where notices overlap the longest is taken, then the
first; an empty table gives an empty result; other columns are ignored. Texts of any length are scanned whole.
"""

from __future__ import annotations

import bisect
import difflib
import re

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

_AS_IS = "THIS SOFTWARE IS PROVIDED BY * \"AS IS\" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL * BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE."
_BSD = "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: 1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer. 2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution."
_WARRANTY = "This program is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE. See the GNU General Public License for more details."
# Notices and whole short licenses by identifier, in the usual wording.
TEMPLATES = {
    "MIT": [
        "Released under the MIT License.", "Licensed under the MIT License.",
        "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions: The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software. THE SOFTWARE IS PROVIDED \"AS IS\", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE.",
    ],
    "ISC": ["Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies. THE SOFTWARE IS PROVIDED \"AS IS\" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS."],
    "0BSD": ["Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted. THE SOFTWARE IS PROVIDED \"AS IS\" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS."],
    "BSD-2-Clause": ["Licensed under the BSD 2-Clause License.", f"{_BSD} {_AS_IS}"],
    "BSD-3-Clause": ["Licensed under the BSD 3-Clause License.", f"{_BSD} 3. Neither the name of * nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission. {_AS_IS}"],
    "Zlib": ["This software is provided 'as-is', without any express or implied warranty. In no event will the authors be held liable for any damages arising from the use of this software. Permission is granted to anyone to use this software for any purpose, including commercial applications, and to alter it and redistribute it freely, subject to the following restrictions"],
    "BSL-1.0": ["Distributed under the Boost Software License, Version 1.0."],
    "Apache-2.0": ["Licensed under the Apache License, Version 2.0", "Licensed under the Apache License, Version 2.0 (the \"License\"); you may not use this file except in compliance with the License. You may obtain a copy of the License at * Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an \"AS IS\" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. See the License for the specific language governing permissions and limitations under the License."],
    "GPL-3.0": ["This work is licensed under the GNU General Public License, version 3."],
    "GPL-3.0-or-later": [f"This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version. {_WARRANTY}"],
    "GPL-2.0": ["This work is licensed under the GNU General Public License, version 2."],
    "GPL-2.0-or-later": [f"This program is free software; you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation; either version 2 of the License, or (at your option) any later version. {_WARRANTY}"],
    "LGPL-2.1": ["This work is licensed under the GNU Lesser General Public License, version 2.1."],
    "LGPL-3.0": ["This work is licensed under the GNU Lesser General Public License, version 3."],
    "AGPL-3.0": ["This work is licensed under the GNU Affero General Public License, version 3."],
    "MPL-2.0": ["This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can obtain one at"],
    "CC0-1.0": ["To the extent possible under law, the author(s) have dedicated all copyright and related and neighboring rights to this software to the public domain worldwide."],
    "CC-BY-4.0": ["Licensed under CC BY 4.0.", "This work is licensed under a Creative Commons Attribution 4.0 International License."],
    "CC-BY-SA-4.0": ["Licensed under CC BY-SA 4.0.", "This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License."],
    "CC-BY-NC-4.0": ["Licensed under CC BY-NC 4.0.", "This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International License."],
    "CC-BY-ND-4.0": ["Licensed under CC BY-ND 4.0.", "This work is licensed under a Creative Commons Attribution-NoDerivatives 4.0 International License."],
    "Unlicense": ["This is free and unencumbered software released into the public domain. Anyone is free to copy, modify, publish, use, compile, sell, or distribute this software, either in source code form or as a compiled binary, for any purpose, commercial or non-commercial, and by any means."],
}
#: Words of which every template has one.
CUES = r"(?i)licen[sc]e|permission is|permission to use|redistributions? |public domain|mozilla public|without warrant"
_CUE = re.compile(CUES)
_WORD = re.compile(r"[\w.-]*\w|(?<!\S)\*(?!\S)")
#: Words that a star stands for, at most.
FREE = 8
SCHEMA = "doc_id long, block int, start long, end long, license string, reduction double, n_differences int, differences string, confirmed boolean"


def _words(text: str) -> list[str]:
    return [w.lower() for w in _WORD.findall(text) if w != "*"]


class Templates:
    """Templates with their compressors."""

    def __init__(self, templates: dict[str, list[str]], level: int = 3):
        import zstandard

        self._plain = zstandard.ZstdCompressor(level=level, write_content_size=False)
        self.entries = []
        for name, texts in templates.items():
            for text in texts:
                raw = zstandard.ZstdCompressionDict(text.replace("* ", "").encode(), dict_type=zstandard.DICT_TYPE_RAWCONTENT)
                press = zstandard.ZstdCompressor(level=level, dict_data=raw, write_content_size=False, write_dict_id=False)
                self.entries.append((name, [w.lower() for w in _WORD.findall(text)], press))
        self.longest = max(len(words) + FREE * words.count("*") for _, words, _ in self.entries)

    def ranked(self, block: str) -> list[tuple[float, int]]:
        """(relative size reduction, entry) of every template, best first."""
        data = block.encode()
        alone = len(self._plain.compress(data))
        return sorted(((1 - len(press.compress(data)) / alone, -k) for k, (_, _, press) in enumerate(self.entries)), reverse=True)

    def differences(self, block: str, entry: int) -> list[str]:
        """Template words that the block lacks or has other words for, where the template lies best in it."""
        words, want = _words(block), self.entries[entry][1]
        out = []
        matcher = difflib.SequenceMatcher(None, words, want, autojunk=False)
        steps = [s for s in matcher.get_opcodes() if s[3] < s[4]]
        first, last = (steps[0][3], steps[-1][4]) if steps else (0, 0)
        for tag, a, b, c, d in matcher.get_opcodes():
            if tag == "equal" or (want[c:d] == ["*"] and 0 < b - a <= FREE):
                continue
            if tag == "delete" and (c <= first or c >= last):
                continue  # text before or after the notice
            out.append(f"-{' '.join(want[c:d])} +{' '.join(words[a:b]) if c > first and d < last else ''}")
        return out

    @staticmethod
    def _ends(words: list[str], at: int, want: list[str]) -> int | None:
        """Place after the template if it stands at a place, each star taking as few words as it can."""
        stars = [k for k, w in enumerate(want) if w == "*"]
        parts = [want[a:b] for a, b in zip([0, *(k + 1 for k in stars)], [*stars, len(want)], strict=True)]
        if words[at : at + len(parts[0])] != parts[0]:
            return None
        at += len(parts[0])
        for part in parts[1:]:
            gap = next((g for g in range(1, FREE + 1) if words[at + g : at + g + len(part)] == part), None)
            if gap is None:
                return None
            at += gap + len(part)
        return at

    def exact(self, block: str) -> list[tuple[int, int, int]]:
        """(start, end, entry) of every template that stands word for word in the block, longest first where they overlap."""
        found = [m for m in _WORD.finditer(block) if m.group() != "*"]
        words, places = [m.group().lower() for m in found], {}
        for i, w in enumerate(words):
            places.setdefault(w, []).append(i)
        hits = [(i - e, i, k) for k, (_, want, _) in enumerate(self.entries) for i in places.get(want[0], ()) if (e := self._ends(words, i, want))]
        taken, out = set(), []
        for less, i, k in sorted(hits):
            if taken.isdisjoint(range(i, i - less)):
                taken.update(range(i, i - less))
                out.append((found[i].start(), found[i - less - 1].end(), k))
        return sorted(out)


def blocks(text: str, reach: int) -> list[tuple[int, int]]:
    """Spans of ``reach`` words on either side of each cue, across line ends; spans that touch are one."""
    words = [m.span() for m in re.finditer(r"\S+", text)]
    starts = [a for a, _ in words]
    spans: list[tuple[int, int]] = []
    for cue in _CUE.finditer(text):
        at = bisect.bisect_right(starts, cue.start()) - 1
        a, b = words[max(0, at - reach)][0], words[min(len(words) - 1, at + reach)][1]
        if spans and a <= spans[-1][1]:
            spans[-1] = (spans[-1][0], max(b, spans[-1][1]))
        else:
            spans.append((a, b))
    return spans


def scan(docs: DataFrame, templates: dict[str, list[str]] | None = None, contenders: int = 4, max_differences: int = 0) -> DataFrame:
    """A confirmed row for each notice that stands word for word in a block, with its own span; one row for each
    rest of the block with a cue: the best template, its size reduction and its exact wording differences.

    Of the ``contenders`` templates with the largest reduction the one with the fewest differing words wins; it is confirmed
    if it has at most ``max_differences``.
    """
    templates = templates or TEMPLATES

    def look(batches):
        known = Templates(templates)
        for batch in batches:
            rows = []
            for doc, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                for number, (a, b) in enumerate(blocks(text, 2 * known.longest)):
                    at, gain, whole = a, {-k: reduction for reduction, k in known.ranked(text[a:b])}, known.exact(text[a:b])
                    for c, d, k in [*whole, (b - a, b - a, None)]:
                        if _CUE.search(text, at, a + c):  # the rest of the block around its confirmed notices
                            best = None
                            for reduction, j in known.ranked(text[at : a + c])[:contenders]:
                                diff = known.differences(text[at : a + c], -j)
                                if best is None or (len(diff), -reduction) < (len(best[2]), -best[1]):
                                    best = (-j, reduction, diff)
                            rows.append((doc, number, at, a + c, known.entries[best[0]][0], round(best[1], 4), len(best[2]), "; ".join(best[2]), len(best[2]) <= max_differences))
                        if k is not None:
                            rows.append((doc, number, a + c, a + d, known.entries[k][0], round(gain[k], 4), 0, "", True))
                        at = a + d
            columns = list(zip(*rows, strict=True)) if rows else [[]] * 9
            kinds = (pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.string(), pa.float64(), pa.int32(), pa.string(), pa.bool_())
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds, strict=True)], [s.split()[0] for s in SCHEMA.split(", ")])

    return docs.select("doc_id", "text").where(F.col("text").rlike(CUES)).mapInArrow(look, SCHEMA)
