"""Licence texts and notices, found by the Dice coefficient over word bigrams.

A text is normalised and cut into its lines, its paragraphs and itself as a whole.
Runs of consecutive lines, and so of paragraphs, are compared as well, for those
templates of which the text holds enough bigrams at all: a score of t takes
t / (2 - t) of a template's bigrams. A run is reported unless it overlaps a unit or
another run with a higher score, or with the same and no shorter.
Each of these is compared with the templates whose size allows the least score:
with a and b bigrams the coefficient is at most 2 min(a, b) / (a + b), so only
templates within a factor of (2 - t) / t of the unit's size are looked at, and
units outside the range of all templates are not even turned into bigrams.
"""

from __future__ import annotations

import bisect
import re
from collections.abc import Iterator
from itertools import islice

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import table, texts

# Public licence texts and the notices that their publishers suggest.
TEMPLATES = {
    "MIT": """Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated
documentation files (the "Software"), to deal in the Software without restriction, including without limitation the rights
to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to
whom the Software is furnished to do so, subject to the following conditions: The above copyright notice and this permission
notice shall be included in all copies or substantial portions of the Software. THE SOFTWARE IS PROVIDED "AS IS", WITHOUT
WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A
PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES
OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE
SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE.""",
    "ISC": """Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby
granted, provided that the above copyright notice and this permission notice appear in all copies. THE SOFTWARE IS PROVIDED
"AS IS" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF
MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL
DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE
OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE.""",
    "BSD-2-Clause": """Redistribution and use in source and binary forms, with or without modification, are permitted
provided that the following conditions are met: 1. Redistributions of source code must retain the above copyright notice,
this list of conditions and the following disclaimer. 2. Redistributions in binary form must reproduce the above copyright
notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the
distribution. THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS "AS IS" AND ANY EXPRESS OR IMPLIED
WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE
DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL,
EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE,
DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT
LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF
THE POSSIBILITY OF SUCH DAMAGE.""",
    "Zlib": """This software is provided 'as-is', without any express or implied warranty. In no event will the authors be
held liable for any damages arising from the use of this software. Permission is granted to anyone to use this software for
any purpose, including commercial applications, and to alter it and redistribute it freely, subject to the following
restrictions: 1. The origin of this software must not be misrepresented; you must not claim that you wrote the original
software. If you use this software in a product, an acknowledgment in the product documentation would be appreciated but is
not required. 2. Altered source versions must be plainly marked as such, and must not be misrepresented as being the original
software. 3. This notice may not be removed or altered from any source distribution.""",
    "Unlicense": """This is free and unencumbered software released into the public domain. Anyone is free to copy, modify,
publish, use, compile, sell, or distribute this software, either in source code form or as a compiled binary, for any purpose,
commercial or non-commercial, and by any means. In jurisdictions that recognize copyright laws, the author or
authors of this software dedicate any and all copyright interest in the software to the public domain. We make this dedication
for the benefit of the public at large and to the detriment of our heirs and successors. We intend this dedication to be an
overt act of relinquishment in perpetuity of all present and future rights to this software under copyright law. THE SOFTWARE
IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF
MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS BE LIABLE FOR ANY CLAIM,
DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE
SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE. For more information, please refer to <https://unlicense.org>""",
    "Unlicense opening": """This is free and unencumbered software released into the public domain. Anyone is free to copy, modify,
publish, use, compile, sell, or distribute this software, either in source code form or as a compiled binary, for any purpose,
commercial or non-commercial, and by any means.""",
    "BSL-1.0": """Permission is hereby granted, free of charge, to any person or organization obtaining a copy of the software
and accompanying documentation covered by this license (the "Software") to use, reproduce, display, distribute, execute, and
transmit the Software, and to prepare derivative works of the Software, and to permit third-parties to whom the Software is
furnished to do so, all subject to the following: The copyright notices in the Software and this entire statement, including
the above license grant, this restriction and the following disclaimer, must be included in all copies of the Software, in
whole or in part, and all derivative works of the Software, unless such copies or derivative works are solely in the form of
machine-executable object code generated by a source language processor. THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY
KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE,
TITLE AND NON-INFRINGEMENT. IN NO EVENT SHALL THE COPYRIGHT HOLDERS OR ANYONE DISTRIBUTING THE SOFTWARE BE LIABLE FOR ANY
DAMAGES OR OTHER LIABILITY, WHETHER IN CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR
THE USE OR OTHER DEALINGS IN THE SOFTWARE.""",
    "BSL-1.0 grant": """Permission is hereby granted, free of charge, to any person or organization obtaining a copy of the software
and accompanying documentation covered by this license (the "Software") to use, reproduce, display, distribute, execute, and
transmit the Software, and to prepare derivative works of the Software, and to permit third-parties to whom the Software is
furnished to do so, all subject to the following: The copyright notices in the Software and this entire statement, including
the above license grant, this restriction and the following disclaimer, must be included in all copies of the Software, in
whole or in part, and all derivative works of the Software, unless such copies or derivative works are solely in the form of
machine-executable object code generated by a source language processor.""",
    "Apache-2.0 header": """Licensed under the Apache License, Version 2.0 (the "License"); you may not use this file except
in compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0 Unless
required by applicable law or agreed to in writing, software distributed under the License is distributed on an "AS IS" BASIS,
WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. See the License for the specific language governing
permissions and limitations under the License.""",
    "GPL-3.0 header": """This program is free software: you can redistribute it and/or modify it under the terms of the GNU
General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any
later version. This program is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the
implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE. See the GNU General Public License for more details.
You should have received a copy of the GNU General Public License along with this program. If not, see
https://www.gnu.org/licenses/.""",
    "MPL-2.0 header": """This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the
MPL was not distributed with this file, You can obtain one at https://mozilla.org/MPL/2.0/.""",
    "Apache-2.0 notice": "Licensed under the Apache License, Version 2.0.",
    "MIT notice": "Released under the MIT License.",
    "MIT notice, licensed": "Licensed under the MIT License.",
    "BSD notice": "Released under the BSD License.",
    "GPL-3.0 notice": "This work is licensed under the GNU General Public License, version 3.",
    "GPL-2.0 notice": "This work is licensed under the GNU General Public License, version 2.",
    "CC-BY-4.0 notice": "Licensed under CC BY 4.0.",
    "CC-BY-SA-4.0 notice": "Licensed under CC BY-SA 4.0.",
    "CC-BY-NC-4.0 notice": "Licensed under CC BY-NC 4.0.",
    "CC-BY-4.0 sentence": "This work is licensed under a Creative Commons Attribution 4.0 International License.",
    "CC-BY-SA-4.0 sentence": "This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License.",
}

LEAST_DICE = 0.8
#: A copyright statement at the start of a line, up to the end of its sentence; what follows stays.
_COPYRIGHT = re.compile(r"^[ \t]*(?:copyright\b(?=[^\n]*(?:\d{4}|\(c\)|©|\bby\b))|\(c\)|©)[^\n]*?(?:(?<!\binc)(?<!\bltd)(?<!\bcorp)(?<!\bco)\.(?=\s|$)(?:[ \t]*all rights reserved\b\.?)?|$)", re.I | re.M)
_TOKEN = re.compile(r"[^\W_]+(?:\.\d+)*")
_PARAGRAPH = re.compile(r"\n[\x20\x09-\x0d]*\n")


def words(text: str) -> list[str]:
    """Lower-case words and numbers, without the copyright statements that lines start with."""
    return _TOKEN.findall(_COPYRIGHT.sub(" ", text).lower() if "opyr" in text.lower() or "©" in text or "(c)" in text.lower() else text.lower())


def bigrams(ws: list[str]) -> frozenset[tuple[str, str]]:
    return frozenset(zip(ws, ws[1:], strict=False))


class Scanner:
    def __init__(self, templates: dict[str, str] = TEMPLATES, least: float = LEAST_DICE):
        self.least = least
        self.templates = sorted((len(b), name, b) for name, t in templates.items() if (b := bigrams(words(t))))
        self.sizes = [t[0] for t in self.templates]
        self.wide = (2 - least) / least
        self.low, self.high = self.sizes[0] / self.wide, self.sizes[-1] * self.wide
        self.holders: dict[tuple[str, str], list[int]] = {}
        for i, (_, _, b) in enumerate(self.templates):
            for pair in b:
                self.holders.setdefault(pair, []).append(i)
        self.known = frozenset(self.holders)
        self.vocabulary = frozenset(w for _, _, b in self.templates for pair in b for w in pair)

    def match(self, ws: list[str]) -> tuple[float, str] | None:
        """Best score and its template for one unit; ties go to the larger template, then the earlier name."""
        # the set of bigrams is no larger than the number of words, and must not fall below the smallest template
        if len(ws) - 1 < self.low:
            return None
        own = bigrams(ws)
        n, best = len(own), None
        if n > self.high:
            return None
        for size, name, theirs in self.templates[bisect.bisect_left(self.sizes, n / self.wide) : bisect.bisect_right(self.sizes, n * self.wide)]:
            score = 2 * len(own & theirs) / (n + size)
            if score >= self.least and (best is None or (score, size) > (best[0], best[2])):
                best = (score, name, size)
        return best and best[:2]

    def units(self, text: str) -> Iterator[tuple[str, int, int]]:
        """Kind, start and length of the whole text, its paragraphs and its lines; equal spans once."""
        yield "text", 0, len(text)
        if "\n" not in text:
            return
        at = 0
        cuts = [m.span() for m in _PARAGRAPH.finditer(text)]
        if cuts:
            for end, after in [*cuts, (len(text), 0)]:
                yield "paragraph", at, end - at
                at = after
        at = 0
        for line in text.split("\n"):
            yield "line", at, len(line)
            at += len(line) + 1

    def runs(self, text: str) -> Iterator[tuple[float, int, int, str]]:
        """Score, start, length and template of runs of two or more lines."""
        lines, at = [], 0
        for line in text.split("\n"):
            if ws := words(line):
                lines.append((at, at + len(line), ws))
            at += len(line) + 1
        flat = [w for _, _, ws in lines for w in ws]
        held = [0] * len(self.templates)
        for pair in self.known.intersection(zip(flat, flat[1:], strict=False)):
            for i in self.holders[pair]:
                held[i] += 1
        for (size, name, theirs), n in zip(self.templates, held, strict=True):
            if n * self.wide < size:
                continue
            useful = [any(p in theirs for p in zip(ws, [*ws[1:], *(lines[i + 1][2][:1] if i + 1 < len(lines) else [])], strict=False)) for i, (_, _, ws) in enumerate(lines)]
            for first, (start, _, ws) in enumerate(lines):
                if not useful[first]:  # a run without this line scores higher
                    continue
                own, last = set(zip(ws, ws[1:], strict=False)), ws[-1]
                common = len(own & theirs)
                for _, end, more in islice(lines, first + 1, None) if len(own) <= size * self.wide else ():
                    new = {(last, more[0]), *zip(more, more[1:], strict=False)} - own
                    own |= new
                    common += len(new & theirs)
                    last = more[-1]
                    if len(own) > size * self.wide:
                        break
                    if new and (score := 2 * common / (len(own) + size)) >= self.least:
                        yield score, start, end - start, name

    def __call__(self, text: str) -> list[dict]:
        out, seen = [], set()
        for kind, start, length in self.units(text):
            if not length or (start, length) in seen:
                continue
            seen.add((start, length))
            if (found := self.match(words(text[start : start + length]))) is not None:
                out.append({"kind": kind, "start": start, "length": length, "licence": found[1], "dice": found[0]})
        if "\n" in text:
            for score, start, length, name in sorted(self.runs(text), key=lambda r: (-r[0], -r[2], r[1], r[3])):
                if all((m["dice"], m["length"]) < (score, length) or m["start"] + m["length"] <= start or start + length <= m["start"] for m in out):
                    out.append({"kind": "run", "start": start, "length": length, "licence": name, "dice": score})
        return out


_FOUND = "array<struct<kind string, start int, length int, licence string, dice double>>"


def licences(text: str | Column, templates: dict[str, str] | None = None, least: float = LEAST_DICE) -> Column:
    """The matches of one text, with spans in code points; none for null and empty texts."""

    def scan(column: Iterator[pd.Series]) -> Iterator[pd.Series]:
        scanner = Scanner(templates or TEMPLATES, least)
        for series in column:
            yield pd.Series([scanner(t) for t in texts(series)])

    scan.__annotations__ = {"column": Iterator[pd.Series], "return": Iterator[pd.Series]}
    return F.pandas_udf(scan, _FOUND).asNondeterministic()(text)


def op9_licence_dice(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One row for each document: its best match (ties: the earliest, then the longest), how many units matched, and all matches by place.

    Null and empty texts have no match; repeated rows stay; texts are scanned whole, however long.
    """
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    found = docs.select("doc_id", licences("text").alias("m"))
    first = F.array_sort("m", lambda a, b: F.when(a["dice"] > b["dice"], -1).when(a["dice"] < b["dice"], 1).when(a["start"] < b["start"], -1).when(a["start"] > b["start"], 1).otherwise(b["length"] - a["length"]))
    in_place = F.array_sort(F.transform("m", lambda m: F.struct(m["start"].alias("start"), m["length"].alias("length"), m["licence"].alias("licence"), m["dice"].alias("dice"), m["kind"].alias("kind"))))
    best = found.select("doc_id", F.size("m").alias("n_matches"), F.get(first, F.lit(0)).alias("best"), in_place.alias("matches"))
    return best.select("doc_id", "n_matches", "best.licence", "best.dice", "best.kind", "best.start", "best.length", "matches")
