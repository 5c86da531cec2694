"""Licence notices and licence texts by Dice coefficient over word bigrams, in DataFrame expressions only.

Units of a text are its lines, each two lines in a row, its paragraphs (between empty lines), and the
sentences of its paragraphs, which may run over several lines. Each is normalised (lower case, runs of other than letters
and digits become a space); equal units of a text count once. A unit is compared with every template as sets of word
bigrams. The licences of the best template are the unit's if it reaches the threshold; if several licences have the
best value, they are named together ("A or B"), unless another unit of the text names one of them alone.

Three prunings lose nothing: a unit of n bigrams is compared only with templates whose size allows the threshold, and
texts as well as units are looked at only if they hold one of the bigrams of which every unit that reaches the threshold
shares at least one; these are found by one pattern, a tree of their common beginnings.

Defined cases: null and empty texts, and units of fewer than two words, match nothing; rows of one doc_id count as one
text's; per (doc_id, licence) there is one row, with the best Dice and its unit (of equals the first in order of text); an
empty table or no template gives no rows; extra columns are ignored.
"""

from __future__ import annotations

import math
import re

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

THRESHOLD = 0.8

_GPL = (
    "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License"
    " as published by the Free Software Foundation, either version {} of the License, or (at your option) any later version."
)
_BSD = (
    "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following"
    " conditions are met:"
)
_BSD_END = (
    "This software is provided by the copyright holders and contributors \"as is\" and any express or implied warranties, including,"
    " but not limited to, the implied warranties of merchantability and fitness for a particular purpose are disclaimed."
)

#: Usual notice sentences and opening sentences of public licences; fixed values.
TEMPLATES = {
    "Apache-2.0": [
        "Licensed under the Apache License, Version 2.0.",
        "Licensed under the Apache License, Version 2.0 (the \"License\"); you may not use this file except in compliance with the License.",
        "Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an"
        " \"AS IS\" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied.",
    ],
    "BSD-2-Clause": ["This software is released under the BSD 2-Clause License.", _BSD, _BSD_END],
    "BSD-3-Clause": [
        "This software is released under the BSD 3-Clause License.", _BSD, _BSD_END,
        "Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products"
        " derived from this software without specific prior written permission.",
    ],
    "CC-BY-4.0": ["This work is licensed under a Creative Commons Attribution 4.0 International License."],
    "CC-BY-NC-4.0": ["Licensed under CC BY-NC 4.0."],
    "CC-BY-SA-4.0": ["Licensed under CC BY-SA 4.0."],
    "GPL-2.0": ["This work is licensed under the GNU General Public License, version 2.", _GPL.format(2)],
    "GPL-3.0": ["This work is licensed under the GNU General Public License, version 3.", _GPL.format(3)],
    "ISC": [
        "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted,"
        " provided that the above copyright notice and this permission notice appear in all copies."
    ],
    "LGPL-3.0": [
        "This work is licensed under the GNU Lesser General Public License, version 3.", _GPL.replace("General", "Lesser General").format(3)
    ],
    "MIT": [
        "Released under the MIT License.",
        "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files"
        " (the \"Software\"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify,"
        " merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is"
        " furnished to do so, subject to the following conditions:",
        "The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software.",
        "The software is provided \"as is\", without warranty of any kind, express or implied, including but not limited to the warranties"
        " of merchantability, fitness for a particular purpose and noninfringement.",
    ],
    "MPL-2.0": ["This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0."],
    "Unlicense": [
        "This is free and unencumbered software released into the public domain.",
        "Anyone is free to copy, modify, publish, use, compile, sell, or distribute this software, either in source code form or as a"
        " compiled binary, for any purpose, commercial or non-commercial, and by any means.",
    ],
}


def _words(text: str) -> list[str]:
    return re.sub(r"[\W_]+", " ", text.lower()).split()


def bigrams_of(text: str) -> list[str]:
    words = _words(text)
    return sorted({f"{a} {b}" for a, b in zip(words, words[1:])})


def least_shared(n: int, threshold: float) -> int:
    """Bigrams that any unit reaching the threshold shares with a template of ``n``: from 2o >= t(a + n) and a >= o."""
    return max(1, math.ceil(threshold * n / (2 - threshold) - 1e-9))


def size_bounds(n: int, threshold: float) -> tuple[int, int]:
    """Sizes of units that can reach the threshold with a template of ``n`` bigrams."""
    return least_shared(n, threshold), math.floor(n * (2 - threshold) / threshold + 1e-9)


def anchors(texts: list[str], threshold: float) -> list[str]:
    """For each template, its longest bigrams, as many as make a match without any of them impossible."""
    out: set[str] = set()
    for text in texts:
        grams = sorted(bigrams_of(text), key=lambda g: (-len(g), g))
        out.update(grams[: len(grams) - least_shared(len(grams), threshold) + 1])
    return sorted(out)


def one_of(words: list[str]) -> str:
    """A pattern of any of the words, their common beginnings written once."""
    tails: dict[str, list[str]] = {}
    for w in words:
        if w:
            tails.setdefault(w[0], []).append(w[1:])
    ways = [re.escape(c) + one_of(rest) for c, rest in sorted(tails.items())]
    if not ways:
        return ""
    some = ways[0] if len(ways) == 1 else f"(?:{'|'.join(ways)})"
    return f"(?:{some})?" if "" in words else some


def normal(c: Column) -> Column:
    return F.trim(F.regexp_replace(F.lower(c), r"[^\p{L}\p{N}]+", " "))


def with_units(df: DataFrame) -> DataFrame:
    """doc_id and the distinct normalised ``units`` of each text; every line is cut out once, neighbours are zipped to it."""
    breaks = F.split("text", r"\r?\n[ \t]*\r?\n")
    df = df.select("doc_id", F.split("text", "[\r\n]+").alias("lines"), breaks.alias("blocks"))
    both = lambda a, b: F.concat_ws(" ", a, b)
    two = F.zip_with(F.slice("lines", 1, F.size("lines") - 1), F.slice("lines", 2, F.size("lines") - 1), both)
    df = df.withColumn("two", F.when(F.size("lines") > 1, two).otherwise(F.array().cast("array<string>")))
    df = df.withColumn("blocks", F.transform("blocks", lambda b: F.regexp_replace(b, "[\r\n]+", " ")))
    cut = lambda b: F.split(F.regexp_replace(b, r"([.!?])[ \t]+", "$1\n"), "\n")
    sentences = F.flatten(F.transform("blocks", cut))
    every = F.transform(F.concat("lines", "two", "blocks", sentences), normal)
    return df.select("doc_id", F.array_distinct(every).alias("units"))


def _flat(templates: dict[str, list[str]] | None) -> list[tuple[str, str]]:
    templates = TEMPLATES if templates is None else templates
    return [(k, t) for k, v in sorted(templates.items()) for t in ([v] if isinstance(v, str) else v) if bigrams_of(t)]


def scan(docs: DataFrame, templates: dict[str, list[str]] | None = None, *, threshold: float = THRESHOLD) -> DataFrame:
    """One row per document and licence found: doc_id, licence, dice, unit. ``templates``: licence to one text or several."""
    flat = _flat(templates)
    if not flat:
        return docs.select("doc_id").filter("false").selectExpr("doc_id", "'' licence", "0d dice", "'' unit")
    named = f"(?:^| ){one_of(anchors([t for _, t in flat], threshold))}(?: |$)"
    possible = docs.select("doc_id", "text").filter(normal(F.col("text")).rlike(named))
    units = with_units(possible).select("doc_id", F.explode("units").alias("unit")).filter(F.col("unit").rlike(named))
    w = F.split("unit", " ")  # two words at least, as the unit holds a bigram
    pairs = F.zip_with(F.slice(w, 1, F.size(w) - 1), F.slice(w, 2, F.size(w) - 1), lambda a, b: F.concat_ws(" ", a, b))
    units = units.select("doc_id", "unit", F.array_distinct(pairs).alias("grams"))
    found = []
    for name, text in flat:
        own = bigrams_of(text)
        low, high = size_bounds(len(own), threshold)
        both = F.size(F.array_intersect("grams", F.array(*[F.lit(g) for g in own])))
        dice = F.lit(2.0) * both / (F.size("grams") + F.lit(len(own)))
        found.append(F.when(F.size("grams").between(low, high), F.struct(dice.alias("dice"), F.lit(name).alias("licence"))))
    # a row per template that fits: no later filter is moved in front of what is computed here
    hits = units.select("doc_id", "unit", F.explode(F.array(*found)).alias("f")).select("doc_id", "unit", "f.dice", "f.licence")
    hits = hits.filter(F.col("dice") >= threshold)
    per_unit = hits.groupBy("doc_id", "unit").agg(F.max("dice").alias("dice"), F.collect_set(F.struct("dice", "licence")).alias("f"))
    names = F.array_sort(F.transform(F.filter("f", lambda x: x["dice"] == F.col("dice")), lambda x: x["licence"]))
    hits = per_unit.select("doc_id", "unit", "dice", names.alias("names"))
    best = hits.groupBy("doc_id", "names").agg(F.min(F.struct((-F.col("dice")).alias("d"), "unit")).alias("x"))
    # at most one entry per set of licences and document
    per = best.groupBy("doc_id").agg(F.collect_list(F.struct("names", "x")).alias("all"))
    alone = F.flatten(F.transform(F.filter("all", lambda a: F.size(a["names"]) == 1), lambda a: a["names"]))
    kept = F.filter("all", lambda a: (F.size(a["names"]) == 1) | ~F.arrays_overlap(a["names"], alone))
    rows = per.select("doc_id", F.explode(kept).alias("a"))
    return rows.select("doc_id", F.array_join("a.names", " or ").alias("licence"), (-F.col("a.x.d")).alias("dice"), F.col("a.x.unit").alias("unit"))


def oracle(templates: dict[str, list[str]] | None = None, threshold: float = THRESHOLD) -> str:
    """The same in DuckDB SQL without pruning, over all units of ``documents``."""
    quoted = lambda g: "'" + g.replace("'", "''") + "'"
    rows = ", ".join(f"('{k}', [{', '.join(quoted(g) for g in bigrams_of(t))}])" for k, t in _flat(templates))
    return rf"""
WITH template(licence, own) AS (VALUES {rows}),
doc AS (SELECT doc_id, regexp_split_to_array(text, '[\r\n]+') AS lines, regexp_split_to_array(text, '\r?\n[ \t]*\r?\n') AS blocks FROM documents WHERE text IS NOT NULL),
cut AS (SELECT doc_id, lines, list_transform(blocks, lambda b: regexp_replace(b, '[\r\n]+', ' ', 'g')) AS blocks FROM doc),
unit AS (SELECT doc_id, unnest(lines || list_transform(range(1, len(lines)), lambda i: lines[i] || ' ' || lines[i + 1]) || blocks
  || flatten(list_transform(blocks, lambda b: string_split(regexp_replace(b, '([.!?])[ \t]+', '\1' || chr(10), 'g'), chr(10))))) AS unit FROM cut),
plain AS (SELECT DISTINCT doc_id, trim(regexp_replace(lower(unit), '[^\p{{L}}\p{{N}}]+', ' ', 'g')) AS unit FROM unit),
word AS (SELECT *, string_split(unit, ' ') AS w FROM plain),
gram AS (SELECT doc_id, unit, list_distinct(list_transform(range(1, len(w)), lambda i: w[i] || ' ' || w[i + 1])) AS grams FROM word WHERE len(w) > 1),
pair AS (SELECT doc_id, unit, licence, 2.0::DOUBLE * len(list_intersect(grams, own)) / (len(grams) + len(own)) AS dice FROM gram, template),
best AS (SELECT *, max(dice) OVER (PARTITION BY doc_id, unit) AS top FROM pair WHERE dice >= {threshold}),
named AS (SELECT doc_id, unit, top AS dice, list_sort(list(DISTINCT licence)) AS names FROM best WHERE dice = top GROUP BY doc_id, unit, top),
per AS (SELECT doc_id, names, max(dice) AS dice, min_by(unit, {{'d': -dice, 'u': unit}}) AS unit FROM named GROUP BY doc_id, names)
SELECT doc_id, array_to_string(names, ' or ') AS licence, dice, unit FROM per p WHERE len(names) = 1
  OR NOT EXISTS (SELECT 1 FROM per q WHERE q.doc_id = p.doc_id AND len(q.names) = 1 AND list_contains(p.names, q.names[1]))
"""
