"""License scans: MinHash bands over overlapping text windows, in SQL functions only.

Templates are grouped by length; a group whose templates have at most M words is searched in windows of
2M words that start every M words, so some window holds any occurrence whole. Each window's MinHash values are bands of one row:
a window that holds SHARE of a template's shingles has at least similarity J with it, and 1 - (1 - J)**BANDS is
above 0.99 for the shortest template of each group (collision_bound states it). Windows and templates that agree in a
band are verified by the exact share of the template's shingles in the window.

Templates may be of any length, full licence texts included: the groups go on by doubling. A window is only hashed if it
holds one of GATE_WORDS, as long as uncovered_templates finds that every match has one; else all windows are.

Edge cases: null and empty texts match nothing; a null doc_id is carried; repeated rows (same id and text)
are reported once; of several places of a template the best, then first, is given; an empty table gives
an empty result; further columns are ignored.
"""

from __future__ import annotations

import re

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from hgpart.llm.tables import lean_parser

SHARE = 0.8
SHINGLE = 5
BANDS = 96
#: Longest template of each group of lengths, in words; longer ones make groups of twice the length before.
GROUPS = (8, 16, 48, 160)

#: Notices by licence.
TEMPLATES = [
    ("MIT", "Released under the MIT License."),
    ("MIT", "This project is licensed under the terms of the MIT license."),
    ("MIT", "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions: The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software."),
    ("Apache-2.0", "Licensed under the Apache License, Version 2.0."),
    ("Apache-2.0", "Licensed under the Apache License, Version 2.0 (the \"License\"); you may not use this file except in compliance with the License. You may obtain a copy of the License at"),
    ("GPL-3.0", "This work is licensed under the GNU General Public License, version 3."),
    ("GPL-3.0", "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version."),
    ("GPL-2.0", "This program is free software; you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation; either version 2 of the License, or (at your option) any later version."),
    ("LGPL-3.0", "This library is licensed under the GNU Lesser General Public License, version 3."),
    ("AGPL-3.0", "This work is licensed under the GNU Affero General Public License, version 3."),
    ("BSD", "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer."),
    ("ISC", "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies."),
    ("MPL-2.0", "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0."),
    ("CC-BY-NC-4.0", "Licensed under CC BY-NC 4.0."),
    ("CC-BY-4.0", "This work is licensed under a Creative Commons Attribution 4.0 International License."),
    ("CC-BY-SA-4.0", "This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License."),
    ("Unlicense", "This is free and unencumbered software released into the public domain."),
    ("BSD-3-Clause", "Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission."),
    ("Zlib", "This software is provided 'as-is', without any express or implied warranty. In no event will the authors be held liable for any damages arising from the use of this software."),
    ("BSL-1.0", "Distributed under the Boost Software License, Version 1.0."),
    ("EPL-2.0", "This program and the accompanying materials are made available under the terms of the Eclipse Public License 2.0."),
    ("Apache-2.0", "Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an \"AS IS\" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. See the License for the specific language governing permissions and limitations under the License."),
    ("GPL", "This program is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE. See the GNU General Public License for more details."),
    ("CC0-1.0", "To the extent possible under law, the author has waived all copyright and related or neighboring rights to this work."),
]
#: A text that matches a template holds one of these words.
GATE_WORDS = ["license", "licensed", "copyright", "permission", "redistribution", "redistributions", "redistribute", "software", "sublicense", "unencumbered", "warranty", "damages", "accompanying"]
_WORD = r"[\p{L}\p{N}]+"


def template_words(text: str) -> list[str]:
    return re.findall(r"[^\W_]+", text.lower())


def shingles(words: list[str]) -> set[str]:
    return {" ".join(words[i : i + SHINGLE]) for i in range(max(1, len(words) - SHINGLE + 1))}


def group_of(n: int) -> int:
    """The group of templates of n words: the most words that one of it has."""
    m = next((m for m in GROUPS if n <= m), GROUPS[-1])
    while m < n:
        m *= 2
    return m


def uncovered_templates(templates=TEMPLATES) -> list[str]:
    """Templates of which SHARE of the shingles could be met without any of GATE_WORDS; should be none."""
    gate, found = set(GATE_WORDS), []
    for _, text in templates:
        have = shingles(template_words(text))
        if have != {""} and sum(not gate & set(s.split()) for s in have) >= SHARE * len(have):
            found.append(text)
    return found


def collision_bound(templates=TEMPLATES) -> float:
    """Least probability that a window with a match shares a band with its template."""
    least = 1.0
    for _, t in templates:
        n = len(template_words(t))
        m = group_of(n)
        have = len(shingles(template_words(t)))
        need = -(-SHARE * have // 1)
        least = min(least, 1 - (1 - need / (2 * m - SHINGLE + 1 + have - need)) ** BANDS)
    return least


def _shingles_sql(w: str) -> str:
    joined = ", ".join(f"{w}[i + {k}]" for k in range(SHINGLE))
    return f"CASE WHEN size({w}) >= {SHINGLE} THEN array_distinct(transform(sequence(0, size({w}) - {SHINGLE}), i -> concat_ws(' ', {joined}))) ELSE array(array_join({w}, ' ')) END"


def _bands_sql(s: str) -> str:
    return f"transform(sequence(0, {BANDS - 1}), b -> xxhash64(b, array_min(transform({s}, x -> xxhash64(x, b)))))"


def template_table(spark: SparkSession, templates=TEMPLATES) -> DataFrame:
    """template_id, license, m (group), t_shingles: one row per template."""
    rows = [(k, name, group_of(len(w)), w) for k, (name, t) in enumerate(templates) if (w := template_words(t))]
    return spark.createDataFrame(rows, "template_id int, license string, m int, w array<string>").select("template_id", "license", "m", F.expr(_shingles_sql("w")).alias("t_shingles"))


@lean_parser
def scan(docs: DataFrame, templates=TEMPLATES) -> DataFrame:
    """doc_id, license, template_id, containment, first_word: the templates that each text holds."""
    spark = docs.sparkSession
    held = template_table(spark, templates)
    # the list of templates is part of the program: its bands are few and broadcast
    keyed = held.withColumn("t_bands", F.expr(_bands_sql("t_shingles")))
    keyed = F.broadcast(keyed.select("*", F.explode("t_bands").alias("band")))
    groups = sorted({group_of(len(template_words(t))) for _, t in templates})
    gated = not uncovered_templates(templates)
    gate = "'" + "', '".join(GATE_WORDS) + "'"
    texts = docs.select("doc_id", F.xxhash64("text").alias("text_hash"), F.lower(F.col("text").cast("string")).alias("t"))
    if gated:
        texts = texts.filter(F.col("t").rlike("|".join(GATE_WORDS)))
    words = texts.select("doc_id", "text_hash", F.regexp_extract_all("t", F.lit(f"({_WORD})"), F.lit(1)).alias("w")).filter(F.size("w") > 0)
    if gated:
        words = words.withColumn("at", F.expr(f"transform(filter(transform(w, (x, i) -> struct(x in ({gate}) as g, i as i)), s -> s.g), s -> s.i)"))
        starts = "array_distinct(flatten(transform(at, p -> array(p div {m} * {m}, greatest(p div {m} - 1, 0L) * {m}))))"
    else:
        starts = "transform(sequence(0, (size(w) - 1) div {m}), k -> k * {m})"
    # slices are cut before they are laid out in rows, so that no row carries its whole text
    cut = ", ".join(f"transform({starts.format(m=m)}, s -> struct({m} as m, cast(s as int) as s, slice(w, cast(s as int) + 1, {2 * m}) as v))" for m in groups)
    windows = words.select("doc_id", "text_hash", F.explode_outer(F.expr(f"concat({cut})")).alias("x")).filter("x is not null").select("doc_id", "text_hash", "x.m", "x.s", "x.v")
    signed = windows.select("doc_id", "text_hash", "m", "s", "v", F.expr(_shingles_sql("v")).alias("w_shingles")).withColumn("bands", F.expr(_bands_sql("w_shingles")))
    # explode_outer, as for explode the optimiser would compute all bands once more to drop empty lists
    met = signed.select("*", F.explode_outer("bands").alias("band")).join(keyed, ["m", "band"])
    # a window and a template that agree in several bands are verified once, at the first of these
    met = met.filter(F.expr("band = array_intersect(bands, t_bands)[0]"))
    verified = met.withColumn("containment", F.size(F.array_intersect("t_shingles", "w_shingles")) / F.size("t_shingles")).filter(F.col("containment") >= SHARE)
    place = F.col("s") + F.expr("array_min(transform(array_intersect(t_shingles, w_shingles), x -> array_position(transform(sequence(0, greatest(size(v) - 5, 0)), i -> concat_ws(' ', slice(v, i + 1, 5))), x))) - 1")
    return (
        verified.withColumn("first_word", place.cast("int"))
        .groupBy("doc_id", "text_hash", "template_id", "license")
        .agg(F.min(F.struct((-F.col("containment")).alias("c"), "first_word")).alias("b"))
        .select("doc_id", "license", "template_id", (-F.col("b.c")).alias("containment"), F.col("b.first_word").alias("first_word"))
    )


def scan_sql(templates=TEMPLATES) -> str:
    """The scan in DuckDB SQL, without hashes: every window against every template of its group."""
    quoted = lambda t: "'" + t.replace("'", "''") + "'"
    held = [(k, name, group_of(len(w)), sorted(shingles(w))) for k, (name, t) in enumerate(templates) if (w := template_words(t))]
    values = ", ".join(f"({k}, {quoted(name)}, {m}, [{', '.join(map(quoted, x))}])" for k, name, m, x in held)
    groups = ", ".join(str(m) for m in sorted({m for _, _, m, _ in held}))
    joined = " || ' ' || ".join(f"v[i + {k}]" for k in range(SHINGLE))
    return f"""
WITH p(template_id, license, m, t) AS (VALUES {values}),
w AS (SELECT doc_id, text, regexp_extract_all(lower(text), '[\\p{{L}}\\p{{N}}]+') AS w FROM (SELECT DISTINCT doc_id, text FROM documents WHERE text IS NOT NULL)),
g AS (SELECT doc_id, text, w, m, unnest(range(0, len(w), m)) AS s FROM w, (SELECT unnest([{groups}]) AS m)),
v AS (SELECT doc_id, text, m, s, w[s + 1 : s + 2 * m] AS v FROM g),
a AS MATERIALIZED (SELECT doc_id, text, m, s, CASE WHEN len(v) >= {SHINGLE} THEN list_transform(range(1, len(v) - {SHINGLE} + 2), lambda i: {joined}) ELSE [array_to_string(v, ' ')] END AS a FROM v),
c AS (SELECT doc_id, text, template_id, license, s, a, t, len(list_intersect(t, a))::DOUBLE / len(t) AS containment FROM a JOIN p USING (m)),
f AS (SELECT *, s + list_min(list_transform(list_intersect(t, a), lambda x: list_position(a, x))) - 1 AS first_word FROM c WHERE containment >= {SHARE})
SELECT doc_id, license, template_id, containment, first_word::INT AS first_word FROM f
QUALIFY row_number() OVER (PARTITION BY doc_id, text, template_id ORDER BY containment DESC, first_word) = 1
"""
