"""Licence scans: normalised text compared to licence templates by Dice coefficient.

The units of a document are its sentences and runs of up to ``RUN`` of them, its lines, its
blocks between blank lines and runs of up to ``RUN`` of those, and the whole text. A unit's
and a template's sets of word bigrams are compared if their sizes allow the threshold t:
|A| within [t/(2-t), (2-t)/t] of |B|. Before that, a unit must hold a word of the
template's necessary prefix: of its bigrams, all but (least overlap - 1) of the most
common, one at least has to be shared. A document without any such word makes no units.

DataFrame functions only, no shuffle. Templates are one literal in the plan (a chosen list;
several hundred licence texts are a few megabytes).

Defined cases: null and empty texts have no match (null licence, dice 0); ties go to the
larger template, then to the first in alphabetical order; repeated rows give repeated results;
units of fewer than two words have no bigrams and never match; no templates: no match.
"""

from __future__ import annotations

import json
import re
from collections.abc import Callable
from math import ceil

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

THRESHOLD = 0.8
#: Longest run of sentences or blocks that is one unit.
RUN = 6
_GAPS = r"[^\p{L}\p{N}]+"
#: Blank lines, also those of comment signs alone.
_BLANK = r"\n[ \t\r*#/;]*\n"

# Customary short notices of public licences; paragraphs of the short licence texts.
TEMPLATES = {
    "Apache-2.0": "Licensed under the Apache License, Version 2.0.",
    "Apache-2.0-header": 'Licensed under the Apache License, Version 2.0 (the "License"); you may not use this file except in compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0',
    "BSD-3-Clause": "Use of this source code is governed by a BSD-style license that can be found in the LICENSE file.",
    "BSD-clause-1": "Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer.",
    "BSD-clause-2": "Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution.",
    "BSD-clause-3": "Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission.",
    "BSD-disclaimer": 'THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS "AS IS" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE.',
    "BSD-intro": "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met:",
    "CC-BY-4.0": "This work is licensed under a Creative Commons Attribution 4.0 International License.",
    "CC-BY-NC-4.0": "Licensed under CC BY-NC 4.0.",
    "CC-BY-SA-4.0": "This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License.",
    "CC0-1.0": "To the extent possible under law, the author has dedicated all copyright and related and neighboring rights to this software to the public domain worldwide.",
    "GPL-3.0": "This work is licensed under the GNU General Public License, version 3.",
    "GPL-3.0-header": "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version.",
    "GPL-3.0-warranty": "This program is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE. See the GNU General Public License for more details.",
    "ISC-grant": "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies.",
    "ISC-warranty": 'THE SOFTWARE IS PROVIDED "AS IS" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE.',
    "MIT": "Released under the MIT License.",
    "MIT-header": "Use of this source code is governed by an MIT-style license that can be found in the LICENSE file.",
    "MIT-grant": 'Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the "Software"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions:',
    "MIT-notice": "The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software.",
    "MIT-warranty": 'THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE.',
    "MPL-2.0": "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can obtain one at http://mozilla.org/MPL/2.0/.",
    "UNLICENSE": "This is free and unencumbered software released into the public domain.",
}


#: Whole licence texts, from their paragraphs above.
_WHOLE = {
    "BSD-2-Clause-text": ("BSD-intro", "BSD-clause-1", "BSD-clause-2", "BSD-disclaimer"),
    "BSD-3-Clause-text": ("BSD-intro", "BSD-clause-1", "BSD-clause-2", "BSD-clause-3", "BSD-disclaimer"),
    "GPL-3.0-notice": ("GPL-3.0-header", "GPL-3.0-warranty"),
    "ISC-text": ("ISC-grant", "ISC-warranty"),
    "MIT-text": ("MIT-grant", "MIT-notice", "MIT-warranty"),
}
TEMPLATES |= {name: "\n\n".join(TEMPLATES[x] for x in parts) for name, parts in _WHOLE.items()}


def template_bigrams(text: str) -> list[str]:
    words = [w for w in re.split(r"[\W_]+", text.lower()) if w]
    return sorted({f"{a} {b}" for a, b in zip(words, words[1:])})


def prefix_words(bigrams: list[str], threshold: float) -> set[str]:
    """Words of which a unit has one if it reaches the threshold: the longer word of each prefix bigram. Bigrams with short words, the most common ones, come last."""
    b = len(bigrams)
    least = ceil(b * threshold / (2 - threshold) - 1e-9)  # the smallest overlap that any allowed unit can have
    order = sorted(bigrams, key=lambda g: (-max(map(len, g.split())), g))
    return {max(g.split(), key=lambda w: (len(w), w)) for g in order[: b - least + 1]}


def words_of(text: Column) -> Column:
    return F.filter(F.split(F.lower(text), _GAPS, -1), lambda w: w != "")


def runs(pieces: Column, near: Column, lengths: range, judge: Callable[[Column], Column]) -> Column:
    """judge(words) of each run of k pieces (arrays of words) that holds a word of ``near``, for each k; no run outlives its judgement."""
    # bound by a lambda: other expressions within one are evaluated for each element
    bound = F.array(F.struct(pieces.alias("p"), F.transform(pieces, lambda w: F.arrays_overlap(w, near)).alias("has")))

    def of(s: Column, k: int) -> Column:
        at = F.when(F.size(s["p"]) >= k, F.filter(F.sequence(F.lit(1), F.size(s["p"]) - k + 1), lambda i: F.exists(F.slice(s["has"], i, k), lambda x: x))).otherwise(F.array().cast("array<int>"))
        return F.filter(F.transform(at, lambda i: judge(F.flatten(F.slice(s["p"], i, k)))), lambda x: x.isNotNull())

    return F.transform(bound, lambda s: F.concat(*[of(s, k) for k in lengths]))[0]


def scan(docs: DataFrame, templates: dict[str, str] | None = None, *, id_col: str = "doc_id", text_col: str = "text", threshold: float = THRESHOLD) -> DataFrame:
    """doc_id, licence (of the best unit, else null), dice (in thousandths, rounded down), n_units (matching units)."""
    templates = TEMPLATES if templates is None else templates
    num, den = round(threshold * 1000), 1000
    made = [(name, grams) for name, text in sorted(templates.items()) if (grams := template_bigrams(text))]
    words = sorted(set().union(*(prefix_words(g, threshold) for _, g in made))) if made else []
    # |A| bounds, in integers: num * (|A| + |B|) <= 2 * den * min(|A|, |B|)
    largest = max((len(g) * (2 * den - num) // num for _, g in made), default=0)
    least = min((-(-len(g) * num // (2 * den - num)) for _, g in made), default=1)

    src = docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text"))
    near = F.array(*[F.lit(w) for w in words]) if words else F.array().cast("array<string>")
    cut = lambda x, by: F.transform(F.split(x, by, -1), words_of)
    parts = F.struct(
        cut(F.regexp_replace("text", r"([.!?])[ \t\r]+", "$1\n"), "\n").alias("sentences"),
        cut(F.col("text"), "\n").alias("lines"),
        cut(F.col("text"), _BLANK).alias("blocks"),
    )
    all_words = words_of(F.col("text"))
    table = F.from_json(F.lit(json.dumps([{"name": n, "g": g} for n, g in made])), "array<struct<name:string,g:array<string>>>")

    def scored(g: Column) -> Column:
        fit = F.filter(table, lambda t: num * (F.size(g) + F.size(t["g"])) <= 2 * den * F.least(F.size(g), F.size(t["g"])))
        both = F.transform(fit, lambda t: F.struct((-F.floor(2000 * F.size(F.array_intersect(g, t["g"])) / (F.size(g) + F.size(t["g"])) + 1e-9)).cast("long").alias("d"), (-F.size(t["g"])).alias("n"), t["name"].alias("name")))
        return F.array_min(F.filter(both, lambda x: x["d"] <= -num))

    def judged(words: Column) -> Column:
        grams = lambda w: F.array_distinct(F.transform(F.sequence(F.lit(0), F.size(w) - 2), lambda i: F.concat(w[i], F.lit(" "), w[i + 1])))
        some = F.filter(F.array(words), lambda w: F.size(w) >= least + 1)  # bound: its size is asked before its bigrams are made
        return F.array_min(F.transform(F.filter(F.transform(some, grams), lambda g: F.size(g).between(least, largest)), scored))

    # the parts are bound once by a lambda, and made only for documents that hold a prefix word
    units = F.transform(
        F.array(parts),
        lambda p: F.concat(runs(p["sentences"], near, range(1, RUN + 1), judged), runs(p["lines"], near, range(1, 2), judged), runs(p["blocks"], near, range(1, RUN + 1), judged), F.filter(F.array(judged(F.flatten(p["lines"]))), lambda x: x.isNotNull())),
    )[0]
    best = F.when(F.arrays_overlap(all_words, near), units)
    found = src.select("doc_id", F.coalesce(best, F.array().cast("array<struct<d:bigint,n:int,name:string>>")).alias("best"))
    top = F.array_min("best")
    return found.select("doc_id", top["name"].alias("licence"), F.coalesce(-top["d"], F.lit(0)).cast("long").alias("dice"), F.size("best").cast("long").alias("n_units"))


def sql(templates: dict[str, str] | None = None, threshold: float = THRESHOLD) -> str:
    """The same in DuckDB, without the prefix words: the bigrams that every unit shares with every template of a size that fits."""
    templates = TEMPLATES if templates is None else templates
    rows = ", ".join("('" + n.replace("'", "''") + "', '" + t.replace("'", "''") + "')" for n, t in sorted(templates.items()))
    grams = lambda w: f"list_distinct(list_transform(range(1, len({w})), lambda i: {w}[i] || ' ' || {w}[i + 1]))"
    words = lambda t: f"list_filter(regexp_split_to_array(lower({t}), '[^\\p{{L}}\\p{{N}}]+'), lambda x: x <> '')"
    cut = lambda x: f"list_transform({x}, lambda u: {words('u')})"
    run = lambda x, k: f"list_transform(range(1, len({x}) - {k - 2}), lambda i: flatten({x}[i : i + {k - 1}]))"
    each = ", ".join([run("s", k) for k in range(1, RUN + 1)] + ["l"] + [run("b", k) for k in range(1, RUN + 1)] + ["[flatten(l)]"])
    t = round(threshold * 1000)
    return f"""
WITH tpl AS (SELECT name, {grams("w")} AS g FROM (SELECT name, {words("body")} AS w FROM (VALUES {rows}) v(name, body))),
part AS (
  SELECT doc_id, {cut("string_split(regexp_replace(text, '([.!?])[ \\t\\r]+', '\\1' || chr(10), 'g'), chr(10))")} AS s, {cut("string_split(text, chr(10))")} AS l, {cut("regexp_split_to_array(text, '\\n[ \\t\\r*#/;]*\\n')")} AS b
  FROM documents
), unit AS (SELECT doc_id, unnest(list_concat({each})) AS w FROM part
), ug AS (SELECT doc_id, i, n, unnest(g) AS g FROM (SELECT doc_id, i, g, len(g) AS n FROM (SELECT doc_id, row_number() OVER () AS i, {grams("w")} AS g FROM unit WHERE len(w) >= 2))),
tg AS (SELECT name, n, unnest(g) AS g FROM (SELECT name, g, len(g) AS n FROM tpl)),
pair AS (
  SELECT doc_id, i, name, max(tg.n) AS tn, 2000 * count(*) // (max(ug.n) + max(tg.n)) AS d
  FROM ug JOIN tg ON ug.g = tg.g WHERE {t} * (ug.n + tg.n) <= 2000 * least(ug.n, tg.n) GROUP BY doc_id, i, name
), near AS (SELECT * FROM pair WHERE d >= {t}),
best AS (SELECT doc_id, arg_min(name, (-d, -tn, name)) AS licence, max(d) AS dice, count(DISTINCT i) AS n FROM near GROUP BY doc_id)
SELECT d.doc_id, licence, coalesce(dice, 0)::BIGINT AS dice, coalesce(n, 0)::BIGINT AS n_units
FROM documents d LEFT JOIN best b ON d.doc_id = b.doc_id
"""
