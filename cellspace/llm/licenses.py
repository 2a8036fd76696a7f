"""Licence notices by template markup.

A template is wording with two kinds of markup, in the style of public licence lists: ``<<beginOptional>> ...
<<endOptional>>`` may be left out, and ``<<var;name="..";original="..";match="..">>`` stands for any run of tokens
whose joined text matches the pattern. It is compiled into a token automaton: an edge for each mandatory token, empty
edges around optional regions, and a looping edge for each replaceable region. A passage is accepted if the automaton
goes from start to end over it, so the mandatory wording must match token by token (case, punctuation, quotes and
spelling variants of "license" are folded, as matching guidelines for licences do).

Texts without any template's rarest mandatory token are dropped in the JVM; the automata run over the whole of the
others.
"""

from __future__ import annotations

import math
import re
from collections.abc import Iterator
from dataclasses import dataclass, field

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cellspace.llm.common import map_batches, pieces

TEMPLATES: dict[str, str] = {
    "apache-2.0-notice": 'Licensed under the Apache License<<beginOptional>>, Version 2.0<<endOptional>><<beginOptional>> (the "License")<<endOptional>>',
    "apache-2.0-header": 'Licensed under the Apache License, Version 2.0 (the "License"); you may not use this file except in compliance with the License. You may obtain a copy of the License at <<var;name="url";original="http";match=".{1,200}">> Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an "AS IS" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. See the License for the specific language governing permissions and limitations under the License.',
    "mit-notice": '<<beginOptional>>This <<var;name="thing";original="work";match="[a-z ]{1,40}">> is <<endOptional>><<var;name="verb";original="released";match="released|licensed|distributed|available">> under the <<beginOptional>>terms of the <<endOptional>>MIT License',
    "mit-text": 'Permission is hereby granted, free of charge, to any person obtaining a copy of <<var;name="what";original="this software";match=".{1,120}">> and associated documentation files (the "Software"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions: The above copyright notice and this permission notice <<beginOptional>>(including the next paragraph)<<endOptional>> shall be included in all copies or substantial portions of the Software. THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL <<var;name="holders";original="THE AUTHORS OR COPYRIGHT HOLDERS";match=".{1,160}">> BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE.',
    "isc-text": 'Permission to use, copy, modify, and<<beginOptional>>/or<<endOptional>> distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies. THE SOFTWARE IS PROVIDED "AS IS" AND <<var;name="holder";original="THE AUTHOR";match=".{1,160}">> DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL <<var;name="holder";original="THE AUTHOR";match=".{1,160}">> BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE.',
    "bsd-text": 'Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: <<beginOptional>>1. <<endOptional>>Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer. <<beginOptional>>2. <<endOptional>>Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution.<<beginOptional>> <<beginOptional>>3. <<endOptional>>Neither the name of <<var;name="owner";original="the copyright holder";match=".{1,120}">> nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission.<<endOptional>> THIS SOFTWARE IS PROVIDED BY <<var;name="by";original="THE COPYRIGHT HOLDERS AND CONTRIBUTORS";match=".{1,160}">> "AS IS" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL <<var;name="who";original="THE COPYRIGHT HOLDER OR CONTRIBUTORS";match=".{1,160}">> BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE.',
    "zlib-text": "This software is provided 'as-is', without any express or implied warranty. In no event will the <<var;name=\"who\";original=\"authors\";match=\".{1,80}\">> be held liable for any damages arising from the use of this software. Permission is granted to anyone to use this software for any purpose, including commercial applications, and to alter it and redistribute it freely, subject to the following restrictions: <<beginOptional>>1. <<endOptional>>The origin of this software must not be misrepresented; you must not claim that you wrote the original software. If you use this software in a product, an acknowledgment in the product documentation would be appreciated but is not required. <<beginOptional>>2. <<endOptional>>Altered source versions must be plainly marked as such, and must not be misrepresented as being the original software. <<beginOptional>>3. <<endOptional>>This notice may not be removed or altered from any source distribution.",
    "gpl-notice": '<<beginOptional>>This <<var;name="thing";original="work";match="[a-z ]{1,40}">> is <<endOptional>>licensed under the <<beginOptional>>terms of the <<endOptional>>GNU <<beginOptional>><<var;name="kind";original="Lesser";match="lesser|affero|library">> <<endOptional>>General Public License<<beginOptional>>, <<endOptional>><<beginOptional>>version <<var;name="n";original="3";match="[0-9.]{1,4}">><<endOptional>><<beginOptional>> or <<beginOptional>>(at your option) <<endOptional>>any later version<<endOptional>>',
    "gpl-header": 'This program is free software<<beginOptional>>:<<endOptional>> you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version <<var;name="n";original="3";match="[0-9.]{1,4}">> of the License, or (at your option) any later version. This program is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE. See the GNU General Public License for more details.',
    "cc-notice": '<<beginOptional>>This <<var;name="thing";original="work";match="[a-z ]{1,40}">> is <<endOptional>>licensed under <<beginOptional>>a <<endOptional>><<beginOptional>>the <<endOptional>><<var;name="family";original="CC";match="cc|creative commons( attribution)?">> <<var;name="kind";original="BY";match="by( nc)?( sa| nd)?|0|attribution[a-z 0-9.]{0,60}">> <<var;name="n";original="4.0";match="[1-4]\\.[05]">><<beginOptional>> International<<endOptional>><<beginOptional>> License<<endOptional>>',
    "mpl-2.0-notice": "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0.",
    "unlicense-notice": "This is free and unencumbered software released into the public domain.",
    "unlicense-text": 'This is free and unencumbered software released into the public domain. Anyone is free to copy, modify, publish, use, compile, sell, or distribute this software, either in source code form or as a compiled binary, for any purpose, commercial or non-commercial, and by any means. In jurisdictions that recognize copyright laws, the author or authors of this software dedicate any and all copyright interest in the software to the public domain. We make this dedication for the benefit of the public at large and to the detriment of our heirs and successors. We intend this dedication to be an overt act of relinquishment in perpetuity of all present and future rights to this software under copyright law. THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE.',
    "bsl-1.0-text": 'Permission is hereby granted, free of charge, to any person or organization obtaining a copy of the software and accompanying documentation covered by this license (the "Software") to use, reproduce, display, distribute, execute, and transmit the Software, and to prepare derivative works of the Software, and to permit third-parties to whom the Software is furnished to do so, all subject to the following: The copyright notices in the Software and this entire statement, including the above license grant, this restriction and the following disclaimer, must be included in all copies of the Software, in whole or in part, and all derivative works of the Software, unless such copies or derivative works are solely in the form of machine-executable object code generated by a source language processor.',
}

_TOKEN = re.compile(r"\d+(?:\.\d+)+|\w+", re.UNICODE)
_MARK = re.compile(r"<<(beginOptional|endOptional|var;[^>]*)>>")
_FIELD = re.compile(r'(\w+)="([^"]*)"')
_SAME = {"licence": "license", "licenced": "licensed", "licences": "licenses", "sub": "sub", "sublicence": "sublicense"}


def fold(token: str) -> str:
    t = token.lower()
    return _SAME.get(t, t)


def tokens_at(text: str) -> tuple[list[str], list[int], list[int]]:
    found = list(_TOKEN.finditer(text))
    return [fold(m.group()) for m in found], [m.start() for m in found], [m.end() for m in found]


@dataclass
class TokenAutomaton:
    """State 0 is the start, ``end`` accepts. ``step[s]`` is (token, next), ``empty[s]`` lists next states, ``loop[s]``
    is (pattern, next, most characters that the pattern can match) of a replaceable region."""

    step: dict[int, tuple[str, int]] = field(default_factory=dict)
    empty: dict[int, list[int]] = field(default_factory=dict)
    loop: dict[int, tuple[re.Pattern, int, float]] = field(default_factory=dict)
    end: int = 0
    mandatory: list[str] = field(default_factory=list)

    def closure(self, states: set[int]) -> set[int]:
        todo, seen = list(states), set(states)
        while todo:
            for n in self.empty.get(todo.pop(), ()):
                if n not in seen:
                    seen.add(n)
                    todo.append(n)
        return seen

    def starts(self) -> tuple[set[str], bool]:
        """Tokens that may come first; whether a replaceable region may."""
        first = self.closure({0})
        return {self.step[s][0] for s in first if s in self.step}, any(s in self.loop for s in first)

    def match(self, tokens: list[str], at: int) -> int:
        """End of the longest accepted run from ``at``, or -1."""
        plain, open_vars, best = self.closure({0}), set(), -1
        for s in plain & self.loop.keys():
            open_vars.add((s, at))
        k = at
        while True:
            if self.end in plain:
                best = k
            if k >= len(tokens) or not (plain or open_vars):
                return best
            token, moved, kept = tokens[k], set(), set()
            for s in plain:
                if s in self.step and self.step[s][0] == token:
                    moved.add(self.step[s][1])
            for s, since in open_vars:
                pattern, nxt, most = self.loop[s]
                filling = " ".join(tokens[since : k + 1])
                if pattern.fullmatch(filling):
                    moved.add(nxt)
                if len(filling) < most:
                    kept.add((s, since))
            k += 1
            plain, open_vars = self.closure(moved), kept
            for s in plain & self.loop.keys():
                open_vars.add((s, k))


def _most(pattern: str) -> float:
    """Characters of the longest text that a pattern matches."""
    most = re._parser.parse(pattern).getwidth()[1]
    return math.inf if most >= re._constants.MAXREPEAT else most


def compile_template(markup: str) -> TokenAutomaton:
    a, state, opened, at = TokenAutomaton(), 0, [], 0

    def words(text: str, state: int) -> int:
        for t in _TOKEN.findall(text):
            a.step[state] = (fold(t), state + 1)
            if not opened:
                a.mandatory.append(fold(t))
            state += 1
        return state

    for m in _MARK.finditer(markup):
        state = words(markup[at : m.start()], state)
        at, mark = m.end(), m.group(1)
        if mark == "beginOptional":
            a.empty.setdefault(state, []).append(state + 1)
            opened.append(state)
            state += 1
        elif mark == "endOptional":
            if not opened:
                raise ValueError("endOptional without beginOptional")
            a.empty.setdefault(state, []).append(state + 1)
            a.empty.setdefault(opened.pop(), []).append(state + 1)
            state += 1
        else:
            pattern = dict(_FIELD.findall(mark)).get("match", ".+")
            a.loop[state] = (re.compile(pattern, re.IGNORECASE), state + 1, _most(pattern))
            state += 1
    if opened:
        raise ValueError("beginOptional without endOptional")
    a.end = words(markup[at:], state)
    return a


def anchors(automata: dict[str, TokenAutomaton]) -> dict[str, str]:
    """For each template a mandatory token that few templates and fewer texts have."""
    common = {"the", "this", "of", "to", "and", "in", "or", "is", "any", "a", "use", "free", "under", "with", "for", "all", "public", "software", "by", "source", "code", "form", "permission"}
    out = {}
    for name, a in automata.items():
        if not a.mandatory:
            raise ValueError(f"{name} has no mandatory wording")
        out[name] = max(a.mandatory, key=lambda t: (t not in common, "licens" in t or "licenc" in t, len(t)))
    return out


def scan_text(text: str, automata: dict[str, TokenAutomaton], needed: dict[str, str]) -> list[tuple[str, int, int, int]]:
    """(template, first character, characters, tokens) of the longest matches, from left to right, that don't overlap
    one of the same template."""
    tokens, starts, ends = tokens_at(text)
    where: dict[str, list[int]] = {}
    for k, t in enumerate(tokens):
        where.setdefault(t, []).append(k)
    found = []
    for name, a in automata.items():
        if needed[name] not in where:
            continue
        first, anything = a.starts()
        at = range(len(tokens)) if anything else sorted(k for t in first for k in where.get(t, ()))
        free = 0
        for k in at:
            if k >= free and (end := a.match(tokens, k)) > k:
                found.append((name, starts[k], ends[end - 1] - starts[k], end - k))
                free = end
    return found


def license_scan(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", templates: dict[str, str] | None = None) -> DataFrame:
    """(id, license_id, at, length, tokens): every accepted passage, with its place in characters.

    A text may match several templates, or one more than once. Null and empty texts have no rows; a row with a null id
    gives rows with a null id; repeated rows give repeated rows. A passage that lacks or changes one mandatory token
    isn't accepted.
    """
    automata = {n: compile_template(t) for n, t in (TEMPLATES if templates is None else templates).items()}
    needed = anchors(automata)
    words = sorted({re.escape(t) for t in needed.values()} | {re.escape(k) for k, v in _SAME.items() if v in needed.values()})
    df = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text")).where(F.col("text").rlike("(?iu)" + "|".join(words)))
    kind = df.schema["id"].dataType.simpleString()

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part, texts in pieces(batches):
            ids = part.column(0).to_pylist()
            rows = [(i, *r) for i, t in zip(ids, texts, strict=True) for r in scan_text(t, automata, needed)]
            if rows:
                cols = list(zip(*rows, strict=True))
                types = [part.column(0).type, pa.string(), pa.int32(), pa.int32(), pa.int32()]
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, types, strict=True)], names=["id", "license_id", "at", "length", "tokens"])

    out = map_batches(df, kernel, f"id {kind}, license_id string, at int, length int, tokens int")
    return out.withColumnRenamed("id", id_col)
