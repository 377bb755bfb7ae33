"""Licence scans: segments of a text against licence templates by Dice coefficient over word bigrams.

A segment is a line, a paragraph (lines between blank ones), the whole text or, for each template, every window of as
many words as the template has over the words of the whole text, normalised to lower-case letters and digits. So notices
inside longer lines, and texts whose line ends or blank lines are lost or hold comment marks, are found too. With the coefficient at t or more, a segment of n distinct bigrams can only match templates of between
n * t / (2 - t) and n * (2 - t) / t bigrams; templates outside these bounds are not compared.
"""

from __future__ import annotations

import re
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Short licence notices and the openings of licence texts, by SPDX identifier.
TEMPLATES = {
    "Apache-2.0": ["Licensed under the Apache License, Version 2.0.", "Licensed under the Apache License, Version 2.0 (the \"License\"); you may not use this file except in compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0"],
    "MIT": ["Released under the MIT License.", "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions:"],
    "GPL-3.0": ["This work is licensed under the GNU General Public License, version 3.", "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version."],
    "CC-BY-NC-4.0": ["Licensed under CC BY-NC 4.0.", "This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International License."],
    "CC-BY-4.0": ["Licensed under CC BY 4.0.", "This work is licensed under a Creative Commons Attribution 4.0 International License."],
    "CC-BY-SA-4.0": ["Licensed under CC BY-SA 4.0.", "This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License."],
    "BSD-3-Clause": ["Released under the BSD 3-Clause License.", "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met:"],
    "MPL-2.0": ["This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0."],
    "Unlicense": ["This is free and unencumbered software released into the public domain."],
}
_CC = "Creative Commons {0} 4.0 International Public License. By exercising the Licensed Rights (defined below), You accept and agree to be bound by the terms and conditions of this Creative Commons {0} 4.0 International Public License (\"Public License\")."
#: Whole licence texts of MIT and BSD-3-Clause, and the heads of the long ones, which a whole text holds as a window.
FULL_TEXTS = {
    "MIT": [TEMPLATES["MIT"][1] + " The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software. THE SOFTWARE IS PROVIDED \"AS IS\", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE."],
    "BSD-3-Clause": [TEMPLATES["BSD-3-Clause"][1] + " 1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer. 2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution. 3. Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission. THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS \"AS IS\" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE."],
    "Unlicense": [TEMPLATES["Unlicense"][0] + " Anyone is free to copy, modify, publish, use, compile, sell, or distribute this software, either in source code form or as a compiled binary, for any purpose, commercial or non-commercial, and by any means."],
    "Apache-2.0": ["Apache License Version 2.0, January 2004 http://www.apache.org/licenses/ TERMS AND CONDITIONS FOR USE, REPRODUCTION, AND DISTRIBUTION"],
    "GPL-3.0": ["GNU GENERAL PUBLIC LICENSE Version 3, 29 June 2007. Copyright (C) 2007 Free Software Foundation, Inc. Everyone is permitted to copy and distribute verbatim copies of this license document, but changing it is not allowed."],
    "MPL-2.0": ["Mozilla Public License Version 2.0. 1. Definitions. 1.1. \"Contributor\" means each individual or legal entity that creates, contributes to the creation of, or owns Covered Software."],
    "CC-BY-4.0": [_CC.format("Attribution")],
    "CC-BY-SA-4.0": [_CC.format("Attribution-ShareAlike")],
    "CC-BY-NC-4.0": [_CC.format("Attribution-NonCommercial")],
}
_WORD = re.compile(r"[a-z0-9]+")


def bigrams(text: str) -> frozenset:
    """Distinct word bigrams of the normalised text; a single word stands for itself, no word gives none."""
    words = _WORD.findall(text.lower())
    return frozenset(zip(words, words[1:])) if len(words) > 1 else frozenset(words)


@lru_cache(maxsize=8)
def _prepared(templates: tuple) -> tuple[list, int]:
    own = sorted(((len(g), name, g) for name, text in templates if (g := bigrams(text))), key=lambda x: (x[0], x[1]))
    return own, own[-1][0] if own else 0


def best_match(text: str, templates: tuple, least: float) -> dict[str, float]:
    """Licence -> largest coefficient of any of its templates with this segment, where at least ``least``."""
    own, largest = _prepared(templates)
    grams = bigrams(text)
    n = len(grams)
    out: dict[str, float] = {}
    if not n or n > largest * (2 - least) / least:
        return out
    low, high = n * least / (2 - least), n * (2 - least) / least
    for size, name, g in own:
        if low <= size <= high:
            dice = 2 * len(grams & g) / (n + size)
            if dice >= least:
                out[name] = max(dice, out.get(name, 0.0))
    return out


@lru_cache(maxsize=8)
def _by_length(templates: tuple) -> tuple[list, dict]:
    """(words, name, bigrams) of every template of two words or more, and bigram -> numbers of the templates that hold it."""
    own = [(len(w), name, bigrams(text)) for name, text in templates if len(w := _WORD.findall(text.lower())) > 1]
    holders: dict[tuple, list[int]] = {}
    for k, (_, _, g) in enumerate(own):
        for x in g:
            holders.setdefault(x, []).append(k)
    return own, holders


def window_matches(text: str, templates: tuple, least: float) -> dict[str, float]:
    """Licence -> largest coefficient of any of its templates with a window of its length, where at least ``least``.

    A window of coefficient t or more shares n * t / (2 - t) of a template's n bigrams or more; texts and windows that hold
    fewer are not compared.
    """
    own, holders = _by_length(templates)
    words = _WORD.findall(text.lower())
    pairs = list(zip(words, words[1:]))
    held: dict[int, int] = {}
    for x in holders.keys() & set(pairs):
        for k in holders[x]:
            held[k] = held.get(k, 0) + 1
    out: dict[str, float] = {}
    for k, n in held.items():
        length, name, g = own[k]
        shared = len(g) * least / (2 - least)
        if n < shared:
            continue
        span = min(length - 1, len(pairs))
        upto = np.concatenate(([0], np.cumsum(np.fromiter((x in g for x in pairs), np.int64, len(pairs)))))
        for i in np.flatnonzero(upto[span:] - upto[: len(upto) - span] >= shared).tolist():
            grams = set(pairs[i : i + span])
            dice = 2 * len(grams & g) / (len(grams) + len(g))
            if dice >= least:
                out[name] = max(dice, out.get(name, 0.0))
                if dice == 1:
                    break
    return out


def segments(text: str):
    """The lines, paragraphs of several lines, and the whole text if it has several paragraphs; blank ones aside."""
    paragraphs = re.split(r"\n[^\S\n]*\n\s*", text)
    for p in paragraphs:
        lines = [l for l in p.split("\n") if l.strip()]
        yield from lines
        if len(lines) > 1:
            yield p
    if len(paragraphs) > 1:
        yield text


def scan(docs: DataFrame, templates: dict[str, list[str]] | None = None, least: float = 0.8, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, license, dice) for every row and licence with a segment or window of coefficient ``least`` or more.

    Null and empty texts match nothing; repeated rows each give their rows; other columns are not read. The templates
    are a fixed list on every executor; the pass over the texts has no shuffle.
    """
    given = [*TEMPLATES.items(), *FULL_TEXTS.items()] if templates is None else templates.items()
    pairs = tuple((name, t) for name, texts in given for t in texts)

    def find(batches):
        memo: dict[str, dict] = {}
        for b in batches:
            docs, names, scores = [], [], []
            for doc, text in zip(b.column(0).to_pylist(), b.column(1).to_pylist()):
                best = window_matches(text or "", pairs, least)
                for segment in segments(text or ""):
                    if len(segment) <= 200:
                        got = memo.get(segment)
                        if got is None:
                            got = best_match(segment, pairs, least)
                            if len(memo) > 50_000:
                                memo.clear()
                            memo[segment] = got
                    else:
                        got = best_match(segment, pairs, least)
                    for name, dice in got.items():
                        best[name] = max(dice, best.get(name, 0.0))
                for name in sorted(best):
                    docs.append(doc)
                    names.append(name)
                    scores.append(best[name])
            yield pa.RecordBatch.from_arrays([pa.array(docs, pa.int64()), pa.array(names, pa.string()), pa.array(scores, pa.float64())], ["doc_id", "license", "dice"])

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(find, "doc_id long, license string, dice double")
