"""Licence scans with built-in functions only: Dice coefficient over word bigrams against licence templates.

A document's lines, paragraphs and whole text are compared with each template after both are normalised. Two bounds make this
cheap and lose nothing. A unit whose number of bigrams is too far from the template's cannot reach the threshold. And a unit
that reaches it holds at least one of any b - o + 1 of the template's b bigrams, where o is the overlap it needs, so a text
without the rarest word of each of these has no unit to compare.
"""

from __future__ import annotations

import math
import re

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

THRESHOLD = 0.8

#: Notices and passages of common public licences, by name.
TEMPLATES = {
    "Apache-2.0 line": "Licensed under the Apache License, Version 2.0.",
    "Apache-2.0 notice": """Licensed under the Apache License, Version 2.0 (the "License"); you may not use this file except in compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0 Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an "AS IS" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. See the License for the specific language governing permissions and limitations under the License.""",
    "BSD-3-Clause conditions": "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met:",
    "CC-BY-4.0 line": "Licensed under CC BY 4.0.",
    "CC-BY-NC-4.0 line": "Licensed under CC BY-NC 4.0.",
    "CC-BY-SA-4.0 line": "This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License.",
    "GPL-2.0 line": "This work is licensed under the GNU General Public License, version 2.",
    "GPL-3.0 line": "This work is licensed under the GNU General Public License, version 3.",
    "GPL-3.0 notice": "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version.",
    "ISC permission": "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies.",
    "MIT line": "Released under the MIT License.",
    "MIT permission": """Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the "Software"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions:""",
    "MPL-2.0 notice": "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can obtain one at http://mozilla.org/MPL/2.0/.",
}


def words_of(text: str) -> list[str]:
    return re.sub("[^a-z0-9]+", " ", text.lower()).split()


def bigrams_of(text: str) -> set[str]:
    words = words_of(text)
    return {f"{a} {b}" for a, b in zip(words, words[1:])}


def size_bounds(n: int, threshold: float) -> tuple[int, int]:
    """Numbers of bigrams of a unit that can reach the threshold against a template of n."""
    return math.ceil(threshold * n / (2 - threshold) - 1e-9), math.floor((2 - threshold) * n / threshold + 1e-9)


def anchors(templates: dict[str, str], threshold: float) -> list[str]:
    """Words of which each text that reaches the threshold with some template holds at least one."""
    out: set[str] = set()
    for text in templates.values():
        grams = sorted(bigrams_of(text), key=lambda g: (-max(map(len, g.split())), g))
        need = len(grams) - max(1, math.ceil(threshold * len(grams) / (2 - threshold) - 1e-9)) + 1
        out |= {max(g.split(), key=len) for g in grams[:need]}
    return sorted(w for w in out if not any(v != w and v in w for v in out))


def bigrams(unit: Column) -> Column:
    words = F.split(F.trim(F.regexp_replace(F.lower(unit), "[^a-z0-9]+", " ")), " ")
    pairs = F.zip_with(F.slice(words, F.lit(1), F.size(words) - 1), F.slice(words, F.lit(2), F.size(words)), lambda a, b: F.concat_ws(" ", a, b))
    return F.when(F.size(words) > 1, F.array_distinct(pairs)).otherwise(F.array().cast("array<string>"))


def scan(documents: DataFrame, templates: dict[str, str] = TEMPLATES, threshold: float = THRESHOLD) -> DataFrame:
    """doc_id, license, dice, matched, licenses for every row.

    `licenses` lists every template that a line, a paragraph or the whole text reaches, by name; `license` is the one with the
    highest coefficient, the last by name among equals, and null where none is reached. Null and empty texts match nothing;
    rows with one doc_id are scanned one by one; an empty table gives an empty result; other columns are not read.
    """
    usable = {k: v for k, v in templates.items() if len(words_of(v)) > 1}
    known = F.array(*(F.struct(F.lit(name).alias("name"), F.array(*map(F.lit, sorted(bigrams_of(t)))).alias("grams"), F.lit(size_bounds(len(bigrams_of(t)), threshold)[0]).alias("low"),
                               F.lit(size_bounds(len(bigrams_of(t)), threshold)[1]).alias("high")) for name, t in sorted(usable.items())))
    folded = F.lower(F.col("text"))
    possible = F.lit(False)
    for word in anchors(usable, threshold):
        possible = possible | F.contains(folded, F.lit(word))
    units = F.array_distinct(F.concat(F.split("text", "\n", -1), F.split("text", r"\n\s*\n", -1), F.array("text")))
    grams = F.filter(F.transform(units, bigrams), lambda g: F.size(g) > 0)

    def compared(g: Column) -> Column:
        near = F.filter(known, lambda t: (F.size(g) >= t["low"]) & (F.size(g) <= t["high"]))
        return F.transform(near, lambda t: F.struct((F.lit(2.0) * F.size(F.array_intersect(g, t["grams"])) / (F.size(g) + F.size(t["grams"]))).alias("dice"), t["name"].alias("name")))

    reached = F.filter(F.flatten(F.transform(grams, compared)), lambda x: x["dice"] >= threshold)
    found = documents.select("doc_id", F.when(possible, reached).alias("reached"))
    best = F.array_max("reached")
    return found.select("doc_id", best["name"].alias("license"), F.coalesce(best["dice"], F.lit(0.0)).alias("dice"), (F.coalesce(F.size("reached"), F.lit(0)) > 0).alias("matched"),
                        F.coalesce(F.array_join(F.array_sort(F.array_distinct(F.transform("reached", lambda x: x["name"]))), ","), F.lit("")).alias("licenses"))


def oracle_sql(templates: dict[str, str] = TEMPLATES, threshold: float = THRESHOLD) -> str:
    """The same in DuckDB, comparing every unit with every template without either bound."""
    rows = ", ".join("('{}', [{}])".format(name, ", ".join(f"'{g}'" for g in sorted(bigrams_of(t)))) for name, t in sorted(templates.items()))
    return f"""
WITH templates(name, grams) AS (VALUES {rows}),
units AS (SELECT doc_id, unnest(list_distinct(list_concat(string_split(text, chr(10)), string_split_regex(text, '\\n\\s*\\n'), [text]))) AS unit FROM documents),
words AS (SELECT doc_id, string_split(trim(regexp_replace(lower(unit), '[^a-z0-9]+', ' ', 'g')), ' ') AS w FROM units),
grams AS (SELECT doc_id, list_distinct(list_transform(generate_series(1, len(w) - 1), lambda i: w[i] || ' ' || w[i + 1])) AS g FROM words WHERE len(w) > 1),
reached AS (SELECT doc_id, name, 2.0::DOUBLE * len(list_intersect(g, t.grams)) / (len(g) + len(t.grams)) AS dice FROM grams, templates t
            WHERE 2.0::DOUBLE * len(list_intersect(g, t.grams)) / (len(g) + len(t.grams)) >= {threshold}),
best AS (SELECT doc_id, max(struct_pack(dice := dice, name := name)) AS b, string_agg(DISTINCT name, ',' ORDER BY name) AS licenses FROM reached GROUP BY doc_id)
SELECT d.doc_id, b.b.name AS license, coalesce(b.b.dice, 0.0::DOUBLE) AS dice, b.doc_id IS NOT NULL AS matched, coalesce(b.licenses, '') AS licenses
FROM documents d LEFT JOIN best b USING (doc_id)"""
