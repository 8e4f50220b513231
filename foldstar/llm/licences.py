"""Licence scan: normalised text against licence templates by the Dice coefficient of word bigrams.

Normalised text: lines that only state a copyright go, and so do comment marks, bullets and numbering at the
beginning of a line; what is left is lower-cased, spelling variants become one, and the words are runs of
letters, digits and plus signs (so quotes, dashes and line breaks do not count).

The licence of a text is that of its best run of words, wherever it begins and ends (`Scanner.window`);
lines, paragraphs and the whole text are such runs (`Scanner.text` compares these units only). A line
counts in n_lines if it matches on its own. With a and b distinct
bigrams and c in common, Dice is 2c / (a + b); since c <= min(a, b), a unit can reach the threshold t
only for templates with t / (2 - t) <= a / b <= (2 - t) / t. Units out of every template's bounds are
left after a count of words; the rest meet only templates within bounds that share a bigram.

The templates are a constant of this module, so what workers hold does not grow with the data. One
scan, no shuffle.

Defined cases: null and empty texts and units of fewer than two words match nothing; texts are taken
whole; ties go to the larger template (it may contain the smaller), then to the one listed first; repeated rows are scanned alike; an empty table gives
no rows; extra columns are not read.
"""

from __future__ import annotations

import re

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from foldstar.llm.shared import ship, table

THRESHOLD = 0.8

# Public licence texts and notices.
TEMPLATES = (
    ("MIT", "Released under the MIT License."),
    ("MIT", "This project is licensed under the MIT License."),
    ("MIT", "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions: The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software."),
    ("Apache-2.0", "Licensed under the Apache License, Version 2.0."),
    ("Apache-2.0", "Licensed under the Apache License, Version 2.0 (the \"License\"); you may not use this file except in compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0 Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an \"AS IS\" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied."),
    ("GPL-3.0", "This work is licensed under the GNU General Public License, version 3."),
    ("GPL-3.0", "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version."),
    ("GPL-2.0", "This work is licensed under the GNU General Public License, version 2."),
    ("LGPL-3.0", "This work is licensed under the GNU Lesser General Public License, version 3."),
    ("AGPL-3.0", "This work is licensed under the GNU Affero General Public License, version 3."),
    ("MPL-2.0", "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can obtain one at http://mozilla.org/MPL/2.0/."),
    ("BSD-3-Clause", "Licensed under the BSD 3-Clause License."),
    ("BSD-2-Clause", "Licensed under the BSD 2-Clause License."),
    ("BSD-2-Clause", "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: 1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer. 2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution."),
    ("ISC", "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies."),
    ("CC-BY-4.0", "Licensed under CC BY 4.0."),
    ("CC-BY-SA-4.0", "Licensed under CC BY-SA 4.0."),
    ("CC-BY-NC-4.0", "Licensed under CC BY-NC 4.0."),
    ("CC-BY-ND-4.0", "Licensed under CC BY-ND 4.0."),
    ("CC0-1.0", "Released under CC0 1.0."),
    ("Unlicense", "This is free and unencumbered software released into the public domain."),
    ("MIT", "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions: The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software. THE SOFTWARE IS PROVIDED \"AS IS\", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE."),
    ("BSD-2-Clause", "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: 1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer. 2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution. THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS \"AS IS\" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE."),
    ("BSD-3-Clause", "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: 1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer. 2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution. 3. Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission. THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS \"AS IS\" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE."),
    ("BSD-3-Clause", "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: 1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer. 2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution. 3. Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission."),
    ("ISC", "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies. THE SOFTWARE IS PROVIDED \"AS IS\" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE."),
    ("Zlib", "This software is provided 'as-is', without any express or implied warranty. In no event will the authors be held liable for any damages arising from the use of this software. Permission is granted to anyone to use this software for any purpose, including commercial applications, and to alter it and redistribute it freely, subject to the following restrictions: 1. The origin of this software must not be misrepresented; you must not claim that you wrote the original software. If you use this software in a product, an acknowledgment in the product documentation would be appreciated but is not required. 2. Altered source versions must be plainly marked as such, and must not be misrepresented as being the original software. 3. This notice may not be removed or altered from any source distribution."),
    ("BSL-1.0", "Permission is hereby granted, free of charge, to any person or organization obtaining a copy of the software and accompanying documentation covered by this license (the \"Software\") to use, reproduce, display, distribute, execute, and transmit the Software, and to prepare derivative works of the Software, and to permit third-parties to whom the Software is furnished to do so, all subject to the following: The copyright notices in the Software and this entire statement, including the above license grant, this restriction and the following disclaimer, must be included in all copies of the Software, in whole or in part, and all derivative works of the Software, unless such copies or derivative works are solely in the form of machine-executable object code generated by a source language processor. THE SOFTWARE IS PROVIDED \"AS IS\", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE, TITLE AND NON-INFRINGEMENT. IN NO EVENT SHALL THE COPYRIGHT HOLDERS OR ANYONE DISTRIBUTING THE SOFTWARE BE LIABLE FOR ANY DAMAGES OR OTHER LIABILITY, WHETHER IN CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE."),
    ("Unlicense", "This is free and unencumbered software released into the public domain. Anyone is free to copy, modify, publish, use, compile, sell, or distribute this software, either in source code form or as a compiled binary, for any purpose, commercial or non-commercial, and by any means. In jurisdictions that recognize copyright laws, the author or authors of this software dedicate any and all copyright interest in the software to the public domain. We make this dedication for the benefit of the public at large and to the detriment of our heirs and successors. We intend this dedication to be an overt act of relinquishment in perpetuity of all present and future rights to this software under copyright law. THE SOFTWARE IS PROVIDED \"AS IS\", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE."),
    ("GPL-3.0", "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version. This program is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE. See the GNU General Public License for more details."),
    ("GPL-2.0", "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 2 of the License, or (at your option) any later version. This program is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE. See the GNU General Public License for more details."),
    ("LGPL-3.0", "This program is free software: you can redistribute it and/or modify it under the terms of the GNU Lesser General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version. This program is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE. See the GNU Lesser General Public License for more details."),
    ("AGPL-3.0", "This program is free software: you can redistribute it and/or modify it under the terms of the GNU Affero General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version. This program is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE. See the GNU Affero General Public License for more details."),
)

_WORD = re.compile(r"[^\W_]+\+*|\+").findall


_COPYRIGHT = re.compile(r"^[^\w\n]*(?:copyright\b|\(c\)|©)[^\n]{0,200}\b(?:19|20)\d\d\b[^\n]{0,200}$|^[^\w\n]*(?:copyright\b|©)[ \t]*(?:\(c\)|©)[^\n]{0,200}$", re.I | re.M)
_MARK = re.compile(r"^[ \t]*(?:(?:/\*+|\*+/?|//+|#+|;+|--+|<!--|rem\b)[ \t]*)*(?:(?:\(?(?:\d{1,2}|[a-z]|[ivx]{1,4})[.)]|[-+•*])[ \t]+)?", re.I | re.M)

# Spelling variants that are one word in licences.
VARIANTS = {
    "licence": "license", "licences": "licenses", "licenced": "licensed", "sublicence": "sublicense", "organisation": "organization", "recognise": "recognize",
    "authorised": "authorized", "acknowledgement": "acknowledgment", "merchantibility": "merchantability", "noninfringement": "noninfringement", "favour": "favor", "honour": "honor",
    "programme": "program", "whilst": "while", "utilisation": "utilization", "judgement": "judgment", "modelled": "modeled", "cancelled": "canceled",
}


def words_of(text: str) -> list[str]:
    """The words of a normalised text."""
    if "opyright" in text or "OPYRIGHT" in text or "(c)" in text or "(C)" in text or "©" in text:
        text = _COPYRIGHT.sub("", text)
    return [VARIANTS.get(w, w) for w in _WORD(_MARK.sub("", text).lower())]


def bigrams(words: list[str]) -> set[tuple[str, str]]:
    return set(zip(words, words[1:]))


class Scanner:
    """Templates by bigram, with the bounds that the threshold sets on a unit's size."""

    def __init__(self, templates=TEMPLATES, threshold: float = THRESHOLD):
        self.names = [n for n, _ in templates]
        grams = [bigrams(words_of(t)) for _, t in templates]
        self.sizes = [len(g) for g in grams]
        self.by_gram: dict[tuple[str, str], list[int]] = {}
        for i, g in enumerate(grams):
            for x in g:
                self.by_gram.setdefault(x, []).append(i)
        self.threshold = threshold
        ratio = threshold / (2 - threshold)
        self.bounds = [(ratio * b - 1e-9, b / ratio + 1e-9) for b in self.sizes]
        self.least, self.most = min(lo for lo, _ in self.bounds), max(hi for _, hi in self.bounds)
        # bytes are enough to tell that a short stretch has too few words: two characters a word but the last
        self.least_chars = 2 * int(self.least) + 1
        # a bigram occurs among the distinct ones once at least, so distinct sizes are what is bounded
        self.first = {x[0] for x in self.by_gram}

    def unit(self, text: str) -> tuple[float, int] | None:
        """Best (Dice, template) of a unit at or above the threshold."""
        if len(text) < self.least_chars:
            return None
        w = words_of(text)
        if len(w) - 1 < self.least or self.first.isdisjoint(w):
            return None
        g = bigrams(w)
        a = len(g)
        if not self.least <= a <= self.most:
            return None
        common: dict[int, int] = {}
        for x in g:
            for i in self.by_gram.get(x, ()):
                common[i] = common.get(i, 0) + 1
        best = None
        for i, c in common.items():
            lo, hi = self.bounds[i]
            if lo <= a <= hi:
                d = 2 * c / (a + self.sizes[i])
                if d >= self.threshold and (best is None or self._order((d, i)) < self._order(best)):
                    best = (d, i)
        return best

    def _order(self, found: tuple[float, int]) -> tuple:
        """Best first: the higher Dice, then the larger template (it may contain the smaller), then the one listed first."""
        return -found[0], -self.sizes[found[1]], found[1]

    def window(self, text: str | None) -> tuple[float, int] | None:
        """Best (Dice, template) of any run of words of a text at or above the threshold.

        A best run begins and ends with a bigram of the template, and its first bigram does not come again in
        it: leaving such ends out never lowers Dice. So runs start at shared bigrams and grow until their
        distinct bigrams pass the upper bound or the first one comes again: linear in the text.
        """
        w = words_of(text or "")
        if len(w) - 1 < self.least or self.first.isdisjoint(w):
            return None
        grams = list(zip(w, w[1:]))
        at: dict[int, list[int]] = {}
        for p, x in enumerate(grams):
            for i in self.by_gram.get(x, ()):
                at.setdefault(i, []).append(p)
        best = None
        for i in sorted(at, key=lambda i: (-self.sizes[i], i)):
            lo, hi = self.bounds[i]
            if len({grams[p] for p in at[i]}) < lo:  # c <= a: fewer in common cannot reach the threshold
                continue
            own = set(at[i])
            for p in at[i]:
                seen, c = set(), 0
                for q in range(p, len(grams)):
                    x = grams[q]
                    if x in seen:
                        if x == grams[p]:
                            break
                        continue
                    seen.add(x)
                    if len(seen) > hi:
                        break
                    if q in own:
                        c += 1
                        d = 2 * c / (len(seen) + self.sizes[i])
                        if d >= self.threshold and (best is None or d > best[0]):
                            best = (d, i)
        return best

    def whole(self, text: str | None) -> tuple[str | None, float, int]:
        """Licence and Dice of the best run of words, and number of lines that match on their own."""
        best = self.window(text)
        n = sum(self.unit(x) is not None for x in text.split("\n")) if best else 0
        return (None, 0.0, n) if best is None else (self.names[best[1]], best[0], n)

    def text(self, text: str | None) -> tuple[str | None, float, int]:
        """Licence, Dice and number of lines that match, for a whole text."""
        best, n = None, 0
        if not text:
            return None, 0.0, 0
        lines = text.split("\n")
        paragraphs, held = [], []
        for line in lines:
            got = self.unit(line)
            if got:
                n += 1
                if best is None or self._order(got) < self._order(best):
                    best = got
            if line.strip():
                held.append(line)
            elif held:
                paragraphs.append(held)
                held = []
        paragraphs.append(held)
        larger = ["\n".join(p) for p in paragraphs if len(p) > 1]
        if len(paragraphs) > 1:
            larger.append(text)
        for u in larger:
            got = self.unit(u)
            if got and (best is None or self._order(got) < self._order(best)):
                best = got
        return (None, 0.0, n) if best is None else (self.names[best[1]], best[0], n)


def scan(docs: DataFrame, key: str = "doc_id", text: str = "text", templates=TEMPLATES, threshold: float = THRESHOLD) -> DataFrame:
    """Per row: key, licence (null: none), dice, n_lines that match a template."""
    ship(docs.sparkSession)

    @F.pandas_udf("licence string, dice double, n_lines long")
    def judged(texts: pd.Series) -> pd.DataFrame:
        scanner = Scanner(templates, threshold)
        return pd.DataFrame([scanner.whole(t) for t in texts], columns=["licence", "dice", "n_lines"])

    return docs.select(F.col(f"`{key}`"), judged(F.col(f"`{text}`")).alias("_s")).select(F.col(f"`{key}`"), "_s.*")


def op10_licences(spark, sf_dir: str) -> DataFrame:
    return scan(table(spark, sf_dir, "documents").select("doc_id", "text"))
