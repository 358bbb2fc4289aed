"""Licence scan: normalised text against licence templates by Dice coefficient over word bigrams, DataFrame functions only.

The units compared are the lines, the paragraphs and the whole of each text. The size bound is exact: a Dice of t needs
t/(2-t)*|B| <= |A| <= (2-t)/t*|B| distinct bigrams, so a template whose size is outside is never intersected.

Defined results: null and empty texts match nothing (licence null, dice 0, 0 matches); equal dice goes to the template
that is listed first; units alike in their normalised words count once; repeated rows give equal results; every row gives one
row; of a very long text only units within the size bounds are compared, and its words are held by one task.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from . import common

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"

# Notices and short licence texts in common use, by SPDX name.
TEMPLATES: list[tuple[str, str]] = [
    ("Apache-2.0", "Licensed under the Apache License, Version 2.0."),
    ("Apache-2.0", 'Licensed under the Apache License, Version 2.0 (the "License"); you may not use this file except in compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0'),
    ("MIT", "Released under the MIT License."),
    ("MIT", "This software is licensed under the MIT License."),
    ("MIT", 'Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the "Software"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions: The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software.'),
    ("GPL-3.0", "This work is licensed under the GNU General Public License, version 3."),
    ("GPL-3.0", "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version."),
    ("GPL-2.0", "This program is free software; you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation; either version 2 of the License, or (at your option) any later version."),
    ("LGPL-3.0", "Licensed under the GNU Lesser General Public License, version 3."),
    ("AGPL-3.0", "Licensed under the GNU Affero General Public License, version 3."),
    ("BSD-3-Clause", "Licensed under the BSD 3-Clause License."),
    ("BSD-2-Clause", "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met"),
    ("ISC", "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies."),
    ("MPL-2.0", "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can obtain one at http://mozilla.org/MPL/2.0/."),
    ("CC-BY-4.0", "Licensed under CC BY 4.0."),
    ("CC-BY-SA-4.0", "Licensed under CC BY-SA 4.0."),
    ("CC-BY-NC-4.0", "Licensed under CC BY-NC 4.0."),
    ("CC-BY-4.0", "This work is licensed under a Creative Commons Attribution 4.0 International License."),
    ("CC0-1.0", "This work is dedicated to the public domain under CC0 1.0 Universal."),
    ("Unlicense", "This is free and unencumbered software released into the public domain."),
]


def bigrams_of(text: str) -> list[str]:
    """The normaliser and shingler once more for templates, on the driver: ASCII lower case, runs of [a-z0-9], neighbours."""
    words = "".join(c if c in LOWER + "0123456789" else " " for c in text.translate(str.maketrans(UPPER, LOWER))).split()
    return sorted({f"{a} {b}" for a, b in zip(words, words[1:], strict=False)})


def normalised_words(text: Column) -> Column:
    plain = F.trim(F.regexp_replace(F.translate(text, UPPER, LOWER), "[^a-z0-9]+", " "))
    return F.split(plain, " ")


def scan(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", threshold: float = 0.8, templates: list[tuple[str, str]] | None = None) -> DataFrame:
    """(doc_id, license, dice, n_matches): the best template over all units of the text, and how many units match any."""
    sets = [(name, bigrams_of(text)) for name, text in (templates or TEMPLATES)]
    text = common.text_or_empty(text_col)
    least = threshold / (2 - threshold) * (1 - 1e-9)  # a hair lower, so that rounding cannot prune an exact tie
    floor, ceiling = least * min(len(b) for _, b in sets), max(len(b) for _, b in sets) / least
    units = F.array_distinct(F.concat(F.split(text, "\n"), F.split(text, r"\n[ \t]*\n"), F.array(text)))

    def best(words: Column) -> Column:
        """(dice, -index) of the best template for a unit's words, by size bounds and intersections."""
        n = F.size(words)
        neighbours = F.zip_with(F.slice(words, F.lit(1), n - 1), F.slice(words, F.lit(2), n - 1), lambda a, b: F.concat_ws(" ", a, b))

        def against(grams: Column) -> Column:
            size = F.size(grams)
            scores = []
            for i, (_, grams_b) in enumerate(sets):
                m = len(grams_b)
                dice = 2.0 * F.size(F.array_intersect(grams, F.array(*map(F.lit, grams_b)))) / (size + m)
                inside = (size >= least * m) & (size * least <= m)
                scores.append(F.struct(F.when(inside, dice).otherwise(0.0).alias("dice"), F.lit(-i).alias("at")))
            return F.greatest(*scores)

        none = F.struct(F.lit(0.0).alias("dice"), F.lit(-len(sets)).alias("at"))
        made = F.element_at(F.transform(F.array(F.array_distinct(neighbours)), lambda g: F.when(F.size(g) <= ceiling, against(g)).otherwise(none)), 1)
        return F.when(n - 1 >= floor, made).otherwise(none)

    scored = F.transform(F.array_distinct(F.transform(units, normalised_words)), best)
    rows = docs.select(docs[id_col].alias("doc_id"), F.filter(scored, lambda s: s.dice >= threshold).alias("hits"))
    top = F.array_max("hits")
    names = F.array(*[F.lit(name) for name, _ in sets])
    return rows.select(
        "doc_id",
        F.when(F.size("hits") > 0, F.element_at(names, 1 - top["at"])).alias("license"),
        F.when(F.size("hits") > 0, F.round(top["dice"], 6)).otherwise(F.lit(0.0)).alias("dice"),
        F.size("hits").cast("long").alias("n_matches"),
    )


def oracle(threshold: float = 0.8) -> str:
    """DuckDB SQL for scan() over documents: every unit against every template, without size bounds."""
    rows = ",\n".join(f"({i}, '{name}', [{', '.join(repr(g) for g in bigrams_of(text))}])" for i, (name, text) in enumerate(TEMPLATES))
    return f"""
WITH templates(pos, name, grams) AS (VALUES {rows}),
units AS (
  SELECT doc_id, unnest(list_distinct(list_concat(string_split(coalesce(text, ''), chr(10)),
         list_concat(regexp_split_to_array(coalesce(text, ''), '\\n[ \\t]*\\n'), [coalesce(text, '')])))) AS unit
  FROM documents),
worded AS (
  SELECT DISTINCT doc_id, string_split(trim(regexp_replace(translate(unit, '{UPPER}', '{LOWER}'), '[^a-z0-9]+', ' ', 'g')), ' ') AS words FROM units),
grammed AS (
  SELECT doc_id, words, list_distinct([words[i] || ' ' || words[i + 1] for i in generate_series(1, len(words) - 1)]) AS grams FROM worded WHERE len(words) > 1),
scored AS (
  SELECT g.doc_id, t.pos, t.name, 2.0 * len(list_intersect(g.grams, t.grams)) / (len(g.grams) + len(t.grams)) AS dice,
         row_number() OVER (PARTITION BY g.doc_id, g.words ORDER BY 2.0 * len(list_intersect(g.grams, t.grams)) / (len(g.grams) + len(t.grams)) DESC, t.pos) AS place
  FROM grammed g, templates t),
hits AS (SELECT doc_id, pos, name, dice FROM scored WHERE place <= 1 AND dice >= {threshold}),
best AS (SELECT doc_id, arg_max(name, dice * 1e6 - pos) AS license, max(dice) AS dice, count(*) AS n FROM hits GROUP BY doc_id)
SELECT d.doc_id, b.license, CAST(coalesce(round(b.dice, 6), 0) AS DOUBLE) AS dice, CAST(coalesce(b.n, 0) AS BIGINT) AS n_matches
FROM documents d LEFT JOIN best b ON d.doc_id = b.doc_id"""
