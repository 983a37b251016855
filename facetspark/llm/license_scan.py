"""Licence scan: texts against licence templates by the Dice coefficient of word bigrams.

Lines, runs of consecutive paragraphs and the whole text are units. Words are lower-case letters, digits and
dots; a unit and a template are sets of word bigrams. Dice >= t bounds the sizes:
t / (2 - t) * |B| <= |A| <= (2 - t) / t * |B|, so units outside every template's bounds go,
and a unit meets only templates whose bounds it is in. From the bounds follows also how many
bigrams a match shares at least; a few marking words that such a share cannot avoid let all
other units go before any bigram is made. Everything is built-in expressions; the templates are a fixed list inside the plan.
"""

from __future__ import annotations

from dataclasses import dataclass
from functools import reduce
from math import ceil, floor
from operator import or_

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

# fixed values: notices and texts of public licences
TEMPLATES = {
    "Apache-2.0 notice": "Licensed under the Apache License, Version 2.0.",
    "Apache-2.0 header": "Licensed under the Apache License, Version 2.0 (the \"License\"); you may not use this file except in compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0 Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an \"AS IS\" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. See the License for the specific language governing permissions and limitations under the License.",
    "MIT notice": "Released under the MIT License.",
    "MIT text": "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions: The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software. THE SOFTWARE IS PROVIDED \"AS IS\", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE.",
    "ISC text": "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies.",
    "GPL-3.0 notice": "This work is licensed under the GNU General Public License, version 3.",
    "GPL-3.0 header": "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version.",
    "LGPL-2.1 notice": "This work is licensed under the GNU Lesser General Public License, version 2.1.",
    "AGPL-3.0 notice": "This work is licensed under the GNU Affero General Public License, version 3.",
    "BSD-3-Clause notice": "Use of this source code is governed by a BSD-style license that can be found in the LICENSE file.",
    "BSD-2-Clause text": "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution.",
    "MPL-2.0 header": "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can obtain one at http://mozilla.org/MPL/2.0/.",
    "CC-BY-4.0 notice": "This work is licensed under a Creative Commons Attribution 4.0 International License.",
    "CC-BY-SA-4.0 notice": "This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License.",
    "CC-BY-NC-4.0 notice": "Licensed under CC BY-NC 4.0.",
    "CC0-1.0 notice": "To the extent possible under law, the author has waived all copyright and related or neighboring rights to this work.",
    "Unlicense text": "This is free and unencumbered software released into the public domain.",
    "BSD-2-Clause full text": "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: 1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer. 2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution. THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS \"AS IS\" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE.",
    "BSD-3-Clause full text": "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: 1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer. 2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution. 3. Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission. THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS \"AS IS\" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE.",
    "ISC full text": "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies. THE SOFTWARE IS PROVIDED \"AS IS\" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE.",
    "Rights reserved": "All rights reserved.",
}


@dataclass(frozen=True)
class LicenseParams:
    dice: float = 0.8


def words_of(text: Column) -> Column:
    """Lower-case words of ASCII letters, digits, and dots between digits."""
    plain = F.regexp_replace(F.lower(text), r"[^a-z0-9.]+|\.(?![0-9])", " ")
    return F.filter(F.split(plain, " "), lambda w: w != "")


def python_words(text: str) -> list[str]:
    import re

    return [w for w in re.sub(r"[^a-z0-9.]+|\.(?![0-9])", " ", text.lower()).split(" ") if w]


def bigrams_of(words: Column) -> Column:
    return F.array_distinct(F.zip_with(F.slice(words, 1, F.size(words) - 1), F.slice(words, 2, F.size(words)), lambda a, b: F.concat_ws(" ", a, b)))


def marking_words(sets: dict[str, list[str]], low: dict[str, int], dice: float) -> list[str]:
    """Words of which every unit that matches some template holds at least one.

    A match shares at least dice / 2 * (least size + template size) bigrams, so it shares one
    of any set of template bigrams larger than the rest; the words are picked to touch so many.
    """
    open_ = {n: (set(s), len(s) - ceil(dice / 2 * (low[n] + len(s)) - 1e-9)) for n, s in sets.items()}
    touched = dict.fromkeys(sets, 0)
    chosen: list[str] = []
    while any(touched[n] <= spare for n, (_, spare) in open_.items()):
        gain: dict[str, int] = {}
        for n, (rest, spare) in open_.items():
            if touched[n] <= spare:
                for gram in rest:
                    for w in set(gram.split(" ")):
                        gain[w] = gain.get(w, 0) + len(w) ** 4  # long words are rarer
        word = max(gain, key=lambda w: (gain[w], w))
        chosen.append(word)
        for n, (rest, _) in open_.items():
            hit = {g for g in rest if word in g.split(" ")}
            touched[n] += len(hit)
            rest -= hit
    return chosen


def _best_dice(own: list[str], low: int, high: int) -> Column:
    """Highest Dice of the units in ``grams`` whose size is in the template's bounds, or 0."""
    known = F.array(*(F.lit(x) for x in own))
    inside = F.filter("grams", lambda g: (F.size(g) >= low) & (F.size(g) <= high))
    return F.coalesce(F.array_max(F.transform(inside, lambda g: F.round(2 * F.size(F.array_intersect(g, known)) / (F.size(g) + len(own)), 9))), F.lit(0.0))


def _runs(paragraphs: Column, most: int) -> Column:
    """Bigram sets of all runs of two or more consecutive paragraphs, each until it exceeds ``most``."""
    words = F.filter(F.transform(paragraphs, words_of), lambda w: F.size(w) > 0)
    empty = F.expr("named_struct('words', cast(array() as array<string>), 'n', 0, 'open', true, 'grams', cast(array() as array<array<string>>))")

    def grown(a, w):
        bind = lambda x, f: F.transform(F.array(x), f)[0]
        # once a run is too large, so is every longer one
        longer = lambda ws: bind(bigrams_of(ws), lambda g: F.struct(ws.alias("words"), (a["n"] + 1).alias("n"), (F.size(g) <= most).alias("open"), F.when((a["n"] > 0) & (F.size(g) <= most), F.array_append(a["grams"], g)).otherwise(a["grams"]).alias("grams")))
        return F.when(a["open"], bind(F.concat(a["words"], w), longer)).otherwise(a)

    from_here = lambda ws: F.transform(ws, lambda w, i: F.aggregate(F.slice(ws, i + 1, F.size(ws)), empty, grown, lambda a: a["grams"]))
    return F.flatten(F.flatten(F.transform(F.array(words), from_here)))


def scan_licenses(documents: DataFrame, p: LicenseParams = LicenseParams(), templates: dict[str, str] = TEMPLATES) -> DataFrame:
    """One row per input row: ``doc_id``, ``licenses`` (sorted names), ``best_license``, ``best_dice``.

    ``best_license`` is the template with the highest Dice over all units, the smaller name
    among equals; rows without a match have an empty list and nulls. A null or empty text
    matches nothing. Rows are judged one by one, repeated or without ``doc_id`` alike.
    """
    sets = {n: sorted({f"{a} {b}" for a, b in zip(w, w[1:])}) for n, t in templates.items() if len(w := python_words(t)) > 1}
    low = {n: ceil(p.dice / (2 - p.dice) * len(s) - 1e-9) for n, s in sets.items()}
    high = {n: floor((2 - p.dice) / p.dice * len(s) + 1e-9) for n, s in sets.items()}
    least, most = max(1, min(low.values())), max(high.values())
    marks = marking_words(sets, low, p.dice)
    # bound by a lambda, the lowered text is made once and not once for each word
    marked = lambda u: F.transform(F.array(F.lower(u)), lambda t: reduce(or_, (F.contains(t, F.lit(w)) for w in marks)))[0]
    none = F.array().cast("array<string>")
    texts = documents.select("doc_id", F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text")).withColumn("hit", marked(F.col("text")))
    lines, paragraphs = F.split("text", "\n"), F.split("text", "\n[ \t\r]*\n")
    units = F.concat(lines, F.when(F.size(paragraphs) > 1, paragraphs).otherwise(none), F.when(F.size(lines) > 1, F.array("text")).otherwise(none))
    several = F.when(F.col("hit") & (F.size(paragraphs) > 1), paragraphs).otherwise(none)
    shape = texts.select("doc_id", F.when(F.col("hit"), F.filter(units, marked)).otherwise(none).alias("units"), several.alias("paragraphs"))
    all_grams = F.concat(F.transform("units", lambda u: bigrams_of(words_of(u))), _runs(F.col("paragraphs"), most))
    grams = shape.select("doc_id", F.filter(all_grams, lambda g: (F.size(g) >= least) & (F.size(g) <= most)).alias("grams"))
    scores = []
    for name, own in sorted(sets.items()):
        scores.append(F.struct(_best_dice(own, low[name], high[name]).alias("dice"), F.lit(name).alias("name")))
    matched = F.filter(F.array(*scores), lambda x: x["dice"] >= p.dice)
    out = grams.select("doc_id", F.when(F.size("grams") > 0, matched).otherwise(F.expr("cast(array() as array<struct<dice:double,name:string>>)")).alias("m"))
    best = F.array_min(F.transform("m", lambda x: F.struct((-x["dice"]).alias("d"), x["name"].alias("name"))))
    return out.select("doc_id", F.array_sort(F.transform("m", lambda x: x["name"])).alias("licenses"), best["name"].alias("best_license"), (-best["d"]).alias("best_dice"))
