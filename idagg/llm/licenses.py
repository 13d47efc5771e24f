"""Licence scans: normalised text against licence templates by the Dice coefficient over sets of word bigrams.

Units are each line and, where a text has several lines, the whole text (line number -1). A unit of n distinct bigrams can reach the
threshold s with a template of m only if s / (2 - s) * m <= n <= (2 - s) / s * m, so templates of other sizes are pruned before any
bigrams are compared. Texts and lines without any of a few words, of which every match must hold one, are pruned before that. All of it is native expressions in one map over the scan: no shuffle, no Python; the templates are a constant.

Normalised: lower case, every run of characters that are neither letters nor digits is one space, trimmed.

Edge cases: null or empty texts and units of fewer than two words match nothing; one row for each template that a unit matches, ties
included; repeated rows and repeated lines are each reported.
"""

from __future__ import annotations

import json
from functools import reduce
from operator import or_

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

THRESHOLD = 0.8

# Notices by which works commonly name their licence, and the openings of common licence texts.
TEMPLATES = [
    ("Apache-2.0", "Licensed under the Apache License, Version 2.0."),
    ("Apache-2.0", 'Licensed under the Apache License, Version 2.0 (the "License"); you may not use this file except in compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0 Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an "AS IS" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. See the License for the specific language governing permissions and limitations under the License.'),
    ("MIT", "Released under the MIT License."),
    ("MIT", "Licensed under the MIT License."),
    ("MIT", 'Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the "Software"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions: The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software.'),
    ("GPL-3.0", "This work is licensed under the GNU General Public License, version 3."),
    ("GPL-3.0", "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version."),
    ("GPL-2.0", "This program is free software; you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation; either version 2 of the License, or (at your option) any later version."),
    ("LGPL-2.1", "This library is free software; you can redistribute it and/or modify it under the terms of the GNU Lesser General Public License as published by the Free Software Foundation; either version 2.1 of the License, or (at your option) any later version."),
    ("MPL-2.0", "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can obtain one at http://mozilla.org/MPL/2.0/."),
    ("BSD", "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met:"),
    ("ISC", "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies."),
    ("Unlicense", "This is free and unencumbered software released into the public domain."),
    ("CC-BY-NC-4.0", "Licensed under CC BY-NC 4.0."),
    ("CC-BY-NC-4.0", "This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International License."),
    ("CC-BY-4.0", "Licensed under CC BY 4.0."),
    ("CC-BY-4.0", "This work is licensed under a Creative Commons Attribution 4.0 International License."),
    ("CC-BY-SA-4.0", "This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License."),
    ("CC0-1.0", "To the extent possible under law, the author has waived all copyright and related or neighboring rights to this work."),
]


def _normalised(c):
    """Lower-case words with a space before and after each."""
    return F.concat(F.lit(" "), F.regexp_replace(F.lower(c), r"[^\p{L}\p{N}]+", " "), F.lit(" "))


def _bigrams(words: str) -> str:
    return f"array_distinct(transform(sequence(0, size({words}) - 2), i -> concat({words}[i], ' ', {words}[i + 1])))"


def _templates() -> list[tuple[int, str, list[str]]]:
    import re

    out = []
    for k, (name, text) in enumerate(TEMPLATES):
        w = re.sub(r"[\W_]+", " ", text.lower()).strip().split(" ")
        out.append((k, name, list(dict.fromkeys(f"{a} {b}" for a, b in zip(w, w[1:], strict=False)))))
    return out


def needles(threshold: float = THRESHOLD) -> list[str]:
    """Words of which every unit that matches any template holds at least one.

    A match shares at least s / 2 * (1 + s / (2 - s)) of the template's bigrams. So where fewer bigrams than that are free of the
    chosen words, a match holds one of them. Greedy choice, the longer words first among equals."""
    share = threshold / 2 * (1 + threshold / (2 - threshold))
    open_ = {k: set(b) for k, _, b in _templates()}
    room = {k: share * len(b) - 1e-9 for k, _, b in _templates()}  # free bigrams must be fewer
    chosen: list[str] = []
    while open_ := {k: b for k, b in open_.items() if len(b) >= room[k]}:
        gain: dict[str, float] = {}
        for k, b in open_.items():
            for pair in b:
                for w in set(pair.split(" ")):
                    gain[w] = gain.get(w, 0) + min(len(w), 10) ** 2 / (len(b) - room[k] + 1)
        best = max(gain, key=lambda w: (round(gain[w], 9), len(w), w))
        chosen.append(best)
        open_ = {k: {p for p in b if best not in p.split(" ")} for k, b in open_.items()}
    return chosen


def scan(docs: DataFrame, threshold: float = THRESHOLD, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, line_no, license_id, template_no, dice): a row for each template that a unit matches."""
    low, high = threshold / (2 - threshold) - 1e-9, (2 - threshold) / threshold + 1e-9
    listed = [{"k": k, "name": name, "m": len(b), "b": b} for k, name, b in _templates()]
    known = F.from_json(F.lit(json.dumps(listed)), "array<struct<k int, name string, m int, b array<string>>>")  # folded to a constant
    least = min(len(b) for *_, b in _templates()) * low
    # Generators stand between the steps, so the optimiser doesn't copy an expensive step into each use of its result
    def held(c):
        return reduce(or_, (F.contains(c, F.lit(f" {n} ")) for n in needles(threshold)))

    whole = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text"), F.explode(F.array(_normalised(F.col("text")))).alias("norm"))
    whole = whole.where(held("norm"))
    units = whole.select("id", "norm", F.explode(F.array(F.split("text", "\n"))).alias("lines")).select(
        "id", F.size("lines").alias("n"),
        F.posexplode(F.when(F.size("lines") > 1, F.concat(F.transform("lines", _normalised), F.array("norm"))).otherwise(F.array("norm"))).alias("at", "unit"))
    words = units.where(held("unit")).select("id", "n", "at", F.explode(F.array(F.split(F.expr("trim(unit)"), " "))).alias("w")).where(
        (F.size("w") > 1) & (F.size("w") - 1 >= F.lit(least)))
    sized = words.select(
        "id", F.when(F.col("at") == F.col("n"), F.lit(-1)).otherwise(F.col("at")).alias("line_no"), F.explode(F.array(F.expr(_bigrams("w")))).alias("b"))
    most = max(len(b) for *_, b in _templates()) * high
    sized = sized.where(F.size("b").between(least, most))
    fits = F.filter(known, lambda t: (F.size("b") >= t["m"] * F.lit(low)) & (F.size("b") <= t["m"] * F.lit(high)))
    scored = F.transform(fits, lambda t: F.struct(
        t["name"].alias("license_id"), t["k"].alias("template_no"),
        F.round(F.lit(2.0) * F.size(F.array_intersect(F.col("b"), t["b"])) / (F.size("b") + t["m"]), 6).alias("dice")))
    return sized.select("id", "line_no", F.explode(F.filter(scored, lambda x: x["dice"] >= threshold)).alias("x")).select(
        F.col("id").alias(id_col), "line_no", "x.license_id", "x.template_no", "x.dice")


def oracle(threshold: float = THRESHOLD) -> str:
    """The same scan of documents as DuckDB SQL, without pruning."""
    q = lambda s: "'" + s.replace("'", "''") + "'"
    rows = ", ".join(f"({k}, {q(name)}, {q(text)})" for k, (name, text) in enumerate(TEMPLATES))
    normal = "trim(regexp_replace(lower({}), '[^\\p{{L}}\\p{{N}}]+', ' ', 'g'))"
    pairs = "list_distinct([w[i] || ' ' || w[i + 1] for i in range(1, len(w))])"
    return f"""
WITH t AS (SELECT k, name, string_split({normal.format('text')}, ' ') AS w FROM (VALUES {rows}) AS v(k, name, text)),
tb AS (SELECT k, name, {pairs} AS b FROM t),
d AS (SELECT doc_id, text, string_split(text, chr(10)) AS lines FROM documents WHERE text IS NOT NULL),
u AS (
  SELECT doc_id, unnest(range(len(lines))) AS line_no, unnest(lines) AS unit FROM d
  UNION ALL SELECT doc_id, -1, text FROM d WHERE len(lines) > 1),
uw AS (SELECT doc_id, line_no, string_split({normal.format('unit')}, ' ') AS w FROM u),
ub AS (SELECT doc_id, line_no, {pairs} AS b FROM uw WHERE len(w) > 1)
SELECT doc_id, CAST(line_no AS INTEGER) AS line_no, name AS license_id, CAST(k AS INTEGER) AS template_no,
       round(2.0::DOUBLE * len(list_intersect(ub.b, tb.b)) / (len(ub.b) + len(tb.b)), 6) AS dice
FROM ub JOIN tb ON len(ub.b) <= 10 * len(tb.b) AND len(tb.b) <= 10 * len(ub.b)
WHERE round(2.0::DOUBLE * len(list_intersect(ub.b, tb.b)) / (len(ub.b) + len(tb.b)), 6) >= {threshold}
"""
