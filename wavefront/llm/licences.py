"""Licence scan: normalised text units against licence templates by the Dice coefficient of word bigrams.

DataFrame functions only. A unit is a whole text, a paragraph, a line, or a window of words of a template's size
(and a quarter more) that starts at one of the template's bigrams. Words are lower-cased runs of letters and
digits. For a threshold q a unit with |D| distinct bigrams can reach a template with |T| only if
|T| q / (2-q) <= |D| <= |T| (2-q) / q, so most units meet no template at all. A unit that reaches q also holds more
than |T| q / (2-q) of the template's bigrams; so words that together touch more than the remainder cannot all be
missing: texts without any such probe word are passed over before they are split into units.
"""

from __future__ import annotations

import math
import re

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

THRESHOLD = 0.8
_GAP = r"[^\p{L}\p{N}]+"
# Notices of public licences, as they are printed.
TEMPLATES: dict[str, tuple[str, ...]] = {
    "Apache-2.0": (
        "Licensed under the Apache License, Version 2.0.",
        'Licensed under the Apache License, Version 2.0 (the "License"); you may not use this file except in compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0 Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an "AS IS" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. See the License for the specific language governing permissions and limitations under the License.',
    ),
    "MIT": (
        "Released under the MIT License.",
        'Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the "Software"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions: The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software. THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE.',
    ),
    "ISC": (
        "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies.",
    ),
    "BSD": (
        "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution.",
    ),
    "GPL-3.0": (
        "This work is licensed under the GNU General Public License, version 3.",
        "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version.",
    ),
    "CC-BY-NC-4.0": ("Licensed under CC BY-NC 4.0.", "This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International License."),
    "CC-BY-4.0": ("This work is licensed under a Creative Commons Attribution 4.0 International License.",),
    "CC-BY-SA-4.0": ("This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License.",),
    "MPL-2.0": ("This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can obtain one at http://mozilla.org/MPL/2.0/.",),
}


# Words too common to tell a licence; taken as probes last.
COMMON = {"a", "an", "and", "any", "as", "at", "be", "by", "for", "from", "in", "is", "it", "may", "of", "on", "or", "that", "the", "this", "to", "under", "with", "you"}


def words(text: str) -> list[str]:
    return re.findall(r"[^\W_]+", text.lower())


def bigrams(text: str) -> list[str]:
    w = words(text)
    return sorted({f"{a} {b}" for a, b in zip(w, w[1:], strict=False)})


def probe_words(text: str, threshold: float) -> set[str]:
    """Rare-looking (long) words such that a text without any of them lacks too many bigrams to reach the threshold."""
    grams = set(bigrams(text))
    spare = len(grams) - math.ceil(len(grams) * threshold / (2 - threshold) - 1e-9)
    chosen: set[str] = set()
    lost: set[str] = set()
    for w in sorted(set(words(text)), key=lambda x: (x in COMMON, -len(x), x)):
        if len(lost) > spare:
            break
        touched = {g for g in grams if w in g.split(" ")} - lost
        if touched:
            chosen.add(w)
            lost |= touched
    return chosen


def _windows(seen: DataFrame, flat: list[tuple[str, list[str]]], sizes: list[int], threshold: float) -> DataFrame:
    """(doc_id, tk, licence, dice) of word windows over the whole text, for templates it holds enough bigrams of."""
    low = threshold / (2 - threshold)
    w = F.split(F.trim(F.regexp_replace(F.lower("text"), _GAP, " ")), " ")
    rows = seen.select("doc_id", F.xxhash64("text").alias("tk"), w.alias("w")).where(F.size("w") > 1)
    pairs = F.zip_with(F.slice("w", F.lit(1), F.size("w") - 1), F.slice("w", F.lit(2), F.size("w") - 1), lambda x, y: F.concat(x, F.lit(" "), y))
    every = F.array(*map(F.lit, sorted({g for _, grams in flat for g in grams})))
    rows = rows.select("doc_id", "tk", pairs.alias("g")).withColumn("hits", F.array_intersect("g", every))
    table = F.array(*(F.struct(F.lit(name).alias("licence"), F.array(*map(F.lit, g)).alias("t"), F.lit(m).alias("m")) for (name, g), m in zip(flat, sizes, strict=True)))
    met = rows.select("doc_id", "tk", "g", F.explode(F.filter(table, lambda x: F.size(F.array_intersect(x["t"], F.col("hits"))) >= F.size(x["t"]) * low)).alias("x"))
    starts = F.filter(F.sequence(F.lit(1), F.size("g")), lambda i: F.array_contains(F.col("x.t"), F.element_at(F.col("g"), i)))

    def dice(i, m):
        own = F.array_distinct(F.slice("g", i, m))
        return 2.0 * F.size(F.array_intersect(own, F.col("x.t"))) / (F.size(own) + F.size("x.t"))

    more = F.ceil(F.col("x.m") * 1.25).cast("int")
    best = F.array_max(F.transform(starts, lambda i: F.greatest(dice(i, F.col("x.m")), dice(i, more))))
    return met.select("doc_id", "tk", F.col("x.licence").alias("licence"), best.alias("dice")).where(F.col("dice") >= threshold)


def scan(docs: DataFrame, threshold: float = THRESHOLD, templates: dict[str, tuple[str, ...]] | None = None) -> DataFrame:
    """The best licence of each row of ``docs(doc_id, text, ...)``.

    Returns ``doc_id, licence, dice``, a row for each input row: the template with the highest Dice coefficient of at
    least ``threshold`` over the row's units and word windows (ties: least licence name), nulls where none reaches it. Null, empty and
    one-word texts reach none; null or repeated doc_ids are rows like any other; other columns are ignored; an empty
    table gives an empty result. Templates are a short list and stand in the plan as literals.
    """
    flat = [(name, bigrams(t)) for name, texts in sorted((templates or TEMPLATES).items()) for t in texts]
    probes = sorted(set().union(*(probe_words(t, threshold) for texts in (templates or TEMPLATES).values() for t in texts)))
    low = threshold / (2 - threshold)
    most, least = max(len(g) for _, g in flat) / low, min(len(g) for _, g in flat) * low
    text = F.col("text").cast("string")
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text.alias("text"))
    seen = rows.where(F.arrays_overlap(F.split(F.lower("text"), _GAP), F.array(*map(F.lit, probes))))
    parts = F.array_distinct(F.flatten(F.array(F.array("text"), F.split("text", r"\n\s*\n"), F.split("text", r"\n"))))
    units = seen.select("doc_id", F.xxhash64("text").alias("tk"), F.explode(parts).alias("unit"))
    w = F.split(F.trim(F.regexp_replace(F.lower("unit"), _GAP, " ")), " ")
    units = units.select("doc_id", "tk", w.alias("w")).where((F.size("w") - 1 >= least) & (F.size(F.array_distinct("w")) - 1 <= most))
    pairs = F.zip_with(F.slice("w", F.lit(1), F.size("w") - 1), F.slice("w", F.lit(2), F.size("w") - 1), lambda x, y: F.concat(x, F.lit(" "), y))
    units = units.select("doc_id", "tk", F.array_distinct(pairs).alias("g"))
    table = F.array(*(F.struct(F.lit(name).alias("licence"), F.array(*map(F.lit, g)).alias("t")) for name, g in flat))
    met = units.withColumn("n", F.size("g")).select("doc_id", "tk", "g", "n", F.explode(F.filter(table, lambda x: (F.col("n") >= F.size(x["t"]) * low) & (F.col("n") <= F.size(x["t"]) / low))).alias("x"))
    dice = 2.0 * F.size(F.array_intersect("g", "x.t")) / (F.col("n") + F.size("x.t"))
    met = met.select("doc_id", "tk", F.col("x.licence").alias("licence"), dice.alias("dice")).where(F.col("dice") >= threshold)
    # the highest coefficient, then the least name: two maxima that both combine map-side
    met = met.unionByName(_windows(seen, flat, [len(words(t)) - 1 for _, texts in sorted((templates or TEMPLATES).items()) for t in texts], threshold))
    best = met.groupBy("doc_id", "tk", "licence").agg(F.max("dice").alias("dice")).groupBy("doc_id", "tk").agg(F.max("dice").alias("dice"), F.min_by("licence", F.struct(-F.col("dice"), "licence")).alias("licence"))
    best = best.select(F.col("doc_id").alias("d2"), F.col("tk").alias("t2"), "licence", "dice")
    keyed = rows.select("doc_id", F.xxhash64("text").alias("tk"))
    return keyed.join(best, F.col("doc_id").eqNullSafe(F.col("d2")) & (F.col("tk") == F.col("t2")), "left").select("doc_id", "licence", "dice")
