"""Licence scan: normalised passages against licence templates by Dice over word bigrams.

A passage is a line, a paragraph or the whole text. Only functions of Spark SQL are used: each
document is one row of one map stage, and nothing is shuffled. Size bounds prune templates: with
threshold t a passage of a bigrams can only match templates of a*t/(2-t) to a*(2-t)/t bigrams.
A passage that matches must also hold one of the few anchor words kept for each template: it shares
at least o = |T|*t/(2-t) of the template's bigrams, hence one of any |T|-o+1 of them. Both prunings are exact.
"""

from __future__ import annotations

import math
import re

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import text_of

DICE = 0.8

#: Licence notices and texts (fixed values; public licence wordings).
TEMPLATES: tuple[tuple[str, str], ...] = (
    ("Apache-2.0", "Licensed under the Apache License, Version 2.0."),
    ("Apache-2.0", 'Licensed under the Apache License, Version 2.0 (the "License"); you may not use this file except in compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0'),
    ("Apache-2.0", 'Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an "AS IS" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. See the License for the specific language governing permissions and limitations under the License.'),
    ("MIT", "Released under the MIT License."),
    ("MIT", "Licensed under the MIT License."),
    ("MIT", 'Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the "Software"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions:'),
    ("MIT", 'THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE.'),
    ("GPL-3.0", "This work is licensed under the GNU General Public License, version 3."),
    ("GPL-3.0", "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version."),
    ("GPL-2.0", "This program is free software; you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation; either version 2 of the License, or (at your option) any later version."),
    ("LGPL-3.0", "This library is free software; you can redistribute it and/or modify it under the terms of the GNU Lesser General Public License as published by the Free Software Foundation; either version 3 of the License, or (at your option) any later version."),
    ("CC-BY-NC-4.0", "Licensed under CC BY-NC 4.0."),
    ("CC-BY-4.0", "This work is licensed under a Creative Commons Attribution 4.0 International License."),
    ("CC-BY-NC-4.0", "This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International License."),
    ("CC-BY-SA-4.0", "This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License."),
    ("MPL-2.0", "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can obtain one at https://mozilla.org/MPL/2.0/."),
    ("ISC", "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies."),
    ("BSD-2-Clause", "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met:"),
    ("BSD-3-Clause", "Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission."),
    ("Unlicense", "This is free and unencumbered software released into the public domain."),
)


def normal_words(text: str) -> list[str]:
    """The words that the native normalisation gives, for templates and tests."""
    return re.sub(r"[\W_]+", " ", text.lower()).strip().split(" ")


def bigrams(words: list[str]) -> list[str]:
    return list(dict.fromkeys(f"{a} {b}" for a, b in zip(words, words[1:], strict=False)))


def anchors(templates=TEMPLATES, dice: float = DICE) -> list[str]:
    """First words of enough bigrams of each template that every match holds one of them."""
    rare = {"apache", "gnu", "mit", "mozilla", "creative", "licensed", "license", "cc", "nc", "software", "permission", "redistribution", "redistribute", "unencumbered", "merchantability"}
    out = set()
    for _, text in templates:
        grams = bigrams(normal_words(text))
        need = len(grams) - math.ceil(len(grams) * dice / (2 - dice) - 1e-9) + 1
        order = sorted(grams, key=lambda g: (g.split(" ")[0] not in rare, -len(g.split(" ")[0]), g))
        out |= {g.split(" ")[0] for g in order[:need]}
    return sorted(out)


def _strings(values) -> Column:
    return F.array(*[F.lit(v) for v in values])


def scan(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", dice: float = DICE, templates=TEMPLATES) -> DataFrame:
    """One row per input row: id, n_hits, licences, best_licence, best_dice.

    ``n_hits`` counts the different normalised passages that match a template; ``licences`` are
    the names found, sorted, joined by commas (empty if none); the best one has the highest Dice, ties go to
    the first by name; it is null where nothing matches. Null text counts as empty, repeated rows give
    equal rows, and only the id and text are read, so other names cannot clash.
    """
    known = F.array(*[F.struct(F.lit(name).alias("name"), F.lit(len(g)).alias("n"), _strings(g).alias("grams")) for name, g in ((name, bigrams(normal_words(t))) for name, t in templates)])
    sizes = [len(bigrams(normal_words(t))) for _, t in templates]
    low, high = min(sizes) * dice / (2 - dice), max(sizes) * (2 - dice) / dice
    body = F.regexp_replace(F.lower(text_of(text_col)), r"[^\p{L}\p{N}\n]+", " ")
    body = F.regexp_replace(F.regexp_replace(body, r" *\n *", "\n"), r"^[ \n]+|[ \n]+$", "")
    one_line = lambda c: F.translate(c, "\n", " ")
    lines = F.split(F.col("body"), r"\n+")
    paragraphs = F.transform(F.split(F.col("body"), r"\n{2,}"), one_line)
    whole = F.array(F.regexp_replace("body", r"\n+", " "))
    held = _strings(anchors(templates, dice))
    words = F.transform(F.array_distinct(F.concat(lines, paragraphs, whole)), lambda p: F.split(p, " "))
    # repeated bigrams count once, so a passage may have more words than the bound on bigrams: only the lower bound prunes here
    some = F.filter(words, lambda w: (F.size(w) > math.ceil(low - 1e-9)) & F.arrays_overlap(w, held))
    grams = F.transform(some, lambda w: F.array_distinct(F.transform(F.sequence(F.lit(1), F.size(w) - 1), lambda i: F.concat(F.element_at(w, i), F.lit(" "), F.element_at(w, i + 1)))))
    grams = F.filter(grams, lambda g: F.size(g) <= high + 1e-9)

    def best(g: Column) -> Column:
        near = F.filter(known, lambda t: (t["n"] >= F.size(g) * (dice / (2 - dice)) - 1e-9) & (t["n"] <= F.size(g) * ((2 - dice) / dice) + 1e-9))
        scored = F.transform(near, lambda t: F.struct((F.size(F.array_intersect(g, t["grams"])) * 2.0 / (F.size(g) + t["n"])).alias("dice"), t["name"].alias("name")))
        return F.filter(scored, lambda s: s["dice"] >= dice)

    base = docs.select(F.col(id_col).alias("id"), body.alias("body")).select("id", grams.alias("grams"))
    # most documents have no candidate passage and skip the comparison
    compared = F.filter(F.transform(F.col("grams"), best), lambda h: F.size(h) > 0)
    hits = base.select("id", F.when(F.size("grams") > 0, compared).alias("hits"))
    flat = F.flatten(F.coalesce(F.col("hits"), F.array().cast("array<array<struct<dice:double,name:string>>>")))
    first = F.element_at(F.array_sort(F.transform(flat, lambda h: F.struct((-h["dice"]).alias("minus"), h["name"].alias("name")))), 1)
    return hits.select(
        F.col("id").alias(id_col),
        F.greatest(F.coalesce(F.size("hits"), F.lit(0)), F.lit(0)).cast("long").alias("n_hits"),
        F.array_join(F.array_sort(F.array_distinct(F.transform(flat, lambda h: h["name"]))), ",").alias("licences"),
        F.when(F.size(flat) > 0, first["name"]).alias("best_licence"),
        F.when(F.size(flat) > 0, -first["minus"]).alias("best_dice"),
    )
