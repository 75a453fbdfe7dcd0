"""Licence scan: normalised text against licence templates by the Dice coefficient over word bigrams.

A document is scanned in units: lines, sentences (also those that run over lines), paragraphs, runs of consecutive sentences and of
consecutive paragraphs, and as a whole, so that a notice is found wherever it stands, wrapped, in parts or more than once. A unit is
compared only with templates whose size lets the coefficient reach the threshold: 2 * min(a, b) >= t * (a + b), in distinct bigrams.

Before a text is cut up it must hold (the beginning of a word that is) one of the ``keywords``: words that lie in so many bigrams of each
template that a unit without any of them can't reach the threshold. So nearly all texts cost one regular expression, and none is lost.

Defined results: null and empty texts match nothing (license null, dice 0.0); among equal coefficients the first template in the list
wins; repeated rows give repeated rows; other columns are ignored. The scan is one narrow projection without a shuffle.
"""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import load

THRESHOLD = 0.8
#: Consecutive sentences and paragraphs that are taken together at most; a whole text is one more unit.
SENTENCES, PARAGRAPHS = 8, 4
#: Words that are in most texts of some language ("mit" in German ones) and therefore poor keywords; single digits are as poor.
COMMON = frozenset("a above all an and any are as at be but by can do following for from has have in is it may mit more must no not of on one only or other out see shall that the this to under use used which with without work you your".split())
_PERMIT = "to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions:"
_AS_IS = 'THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE.'
#: Public licence notices and texts.
TEMPLATES = (
    ("MIT", "Released under the MIT License."),
    ("MIT", "Licensed under the MIT License."),
    ("MIT", f"Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), {_PERMIT} The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software. {_AS_IS}"),
    ("Apache-2.0", "Licensed under the Apache License, Version 2.0."),
    ("Apache-2.0", 'Licensed under the Apache License, Version 2.0 (the "License"); you may not use this file except in compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0 Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an "AS IS" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. See the License for the specific language governing permissions and limitations under the License.'),
    ("GPL-3.0", "This work is licensed under the GNU General Public License, version 3."),
    ("GPL-3.0", "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version. This program is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE. See the GNU General Public License for more details."),
    ("GPL-2.0", "This work is licensed under the GNU General Public License, version 2."),
    ("CC-BY-NC-4.0", "Licensed under CC BY-NC 4.0."),
    ("CC-BY-4.0", "Licensed under CC BY 4.0."),
    ("CC-BY-4.0", "This work is licensed under a Creative Commons Attribution 4.0 International License."),
    ("CC-BY-SA-4.0", "Licensed under CC BY-SA 4.0."),
    ("BSD-3-Clause", "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met"),
    ("ISC", "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies."),
)


def _quoted(text: str) -> str:
    return "'" + text.replace("\\", "\\\\").replace("'", "\\'") + "'"


def grams_sql(words: str) -> str:
    return f"CASE WHEN size({words}) < 2 THEN array() ELSE array_distinct(transform(sequence(0, size({words}) - 2), i -> concat({words}[i], ' ', {words}[i + 1]))) END"


def words_of(text: str) -> str:
    """Lower-cased letter and digit runs of a string expression."""
    return f"filter(split({text}, '[^\\\\p{{L}}\\\\p{{N}}]+'), x -> x != '')"


def keywords(templates: list[list[str]], threshold: float) -> list[str]:
    """Words of the templates (as lists of bigrams) such that each unit that reaches the threshold with one of them holds a word.

    Such a unit has t n / (2 - t) of the template's n bigrams at least, so words that lie in more than the rest of them will do.
    """
    chosen: set[str] = set()
    for grams in templates:
        pairs = [set(g.split(" ")) for g in grams]
        spare = len(grams) - math.ceil(threshold * len(grams) / (2 - threshold) - 1e-9)
        left = [p for p in pairs if not p & chosen]
        while len(pairs) - len(left) <= spare:
            words = {w for p in left for w in p}
            best = max(sorted(words), key=lambda w: (w not in COMMON and len(w) > 1, sum(w in p for p in left), len(w)))
            chosen.add(best)
            left = [p for p in left if best not in p]
    return sorted(chosen)


def alternatives(words: list[str]) -> str:
    """A regular expression of the words (letters and digits only) that shares their beginnings, so that few are tried at a place."""
    ends = "" in words
    by: dict[str, list[str]] = {}
    for w in sorted(set(words) - {""}):
        by.setdefault(w[0], []).append(w[1:])
    if not by:
        return ""
    found = "(?:" + "|".join(c + alternatives(rest) for c, rest in by.items()) + ")"
    return found + "?" if ends else found


def units_sql(low: str) -> str:
    """SQL for the distinct units of a lower-cased string expression (a name, as it is used several times)."""
    let = lambda x, name, body: f"transform(array({x}), {name} -> {body})[0]"
    runs = lambda x, most: f"flatten(transform(sequence(2, {most}), m -> CASE WHEN size({x}) < m THEN array() ELSE transform(sequence(1, size({x}) - m + 1), i -> array_join(slice({x}, i, m), ' ')) END))"
    lines = f"split({low}, '\\n'), split(regexp_replace({low}, '([.!?])[ \\t]+', '$1\\n'), '\\n')"
    sentences = f"split(regexp_replace({low}, '([.!?])[ \\t\\r\\n]+|\\n[ \\t\\r]*\\n', '$1\u0001'), '\u0001')"
    paragraphs = f"split({low}, '\\n[ \\t\\r]*\\n')"
    body = f"array_distinct(concat({lines}, ss, {runs('ss', SENTENCES)}, pp, {runs('pp', PARAGRAPHS)}, array({low})))"
    return let(sentences, "ss", let(paragraphs, "pp", body))


def scan(docs: DataFrame, templates=TEMPLATES, threshold: float = THRESHOLD) -> DataFrame:
    """doc_id, license, dice, template (its position)."""
    spark = docs.sparkSession
    known = spark.createDataFrame([(i, x) for i, (_, x) in enumerate(templates)], "i int, x string")
    sized = known.select("i", F.expr(f"transform(array({words_of('lower(x)')}), w -> {grams_sql('w')})[0]").alias("g")).orderBy("i").collect()  # constants: one row for each template
    least = min(len(r.g) for r in sized) * threshold / (2 - threshold)
    literal = "array(" + ", ".join(f"named_struct('i', {-r.i}, 'n', {len(r.g)}, 'g', array({', '.join(map(_quoted, r.g))}))" for r in sized) + ")"
    pattern = _quoted("(?<![a-z0-9])" + alternatives(keywords([list(r.g) for r in sized], threshold)))
    dice = f"transform(filter(known, t -> 2 * least(t.n, size(g)) >= {threshold}D * (t.n + size(g))), t -> named_struct('d', 2.0D * size(array_intersect(t.g, g)) / (t.n + size(g)), 'i', t.i))"
    of_unit = f"transform(array({words_of('u')}), w -> CASE WHEN size(w) <= {least} THEN NULL ELSE transform(array({grams_sql('w')}), g -> array_max({dice}))[0] END)[0]"
    low = docs.select("doc_id", F.lower(F.coalesce("text", F.lit(""))).alias("low"), F.expr(literal).alias("known"))
    units = f"CASE WHEN low RLIKE {pattern} THEN filter(transform(array(low), x -> {units_sql('x')})[0], u -> u RLIKE {pattern}) ELSE array() END"
    best = f"array_max(transform({units}, u -> {of_unit}))"
    return (
        low.select("doc_id", F.expr(best).alias("b"))
        .select("doc_id", F.when(F.col("b.d") >= threshold, F.col("b")).alias("b"))
        .select(
            "doc_id",
            F.when(F.col("b").isNotNull(), F.get(F.array(*(F.lit(name) for name, _ in templates)), -F.col("b.i"))).alias("license"),
            F.coalesce("b.d", F.lit(0.0)).alias("dice"),
            (-F.col("b.i")).alias("template"),
        )
    )


def op5_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan(load(spark, sf_dir, "documents"))


def _sql() -> str:
    rows = ", ".join(f"({i}, '{name}', '" + text.replace("'", "''") + "')" for i, (name, text) in enumerate(TEMPLATES))
    grams = "list_distinct(list_transform(range(1, len(w)), lambda i: w[i] || ' ' || w[i + 1]))"
    runs = lambda x, most: f"flatten(list_transform(range(2, {most + 1}), lambda m: list_transform(range(1, len({x}) - m + 2), lambda i: array_to_string({x}[i:i + m - 1], ' '))))"
    return rf"""
WITH t AS (SELECT i, name, {grams} AS g FROM (SELECT i, name, regexp_extract_all(lower(x), '[\p{{L}}\p{{N}}]+') AS w FROM (VALUES {rows}) AS v(i, name, x))),
d AS MATERIALIZED (SELECT row_number() OVER () AS rid, doc_id, lower(coalesce(text, '')) AS low FROM documents),
cut AS MATERIALIZED (SELECT rid, low, string_split(regexp_replace(low, '([.!?])[ \t\r\n]+|\n[ \t\r]*\n', '\1' || chr(1), 'g'), chr(1)) AS ss, regexp_split_to_array(low, '\n[ \t\r]*\n') AS pp FROM d),
u AS (SELECT DISTINCT rid, unnest(list_concat(list_concat(list_concat(string_split(low, chr(10)), string_split(regexp_replace(low, '([.!?])[ \t]+', '\1' || chr(10), 'g'), chr(10))),
  list_concat(ss, {runs('ss', SENTENCES)})), list_concat(list_concat(pp, {runs('pp', PARAGRAPHS)}), [low]))) AS x FROM cut),
ug AS MATERIALIZED (SELECT rid, {grams} AS g FROM (SELECT rid, regexp_extract_all(x, '[\p{{L}}\p{{N}}]+') AS w FROM u)),
h AS (SELECT rid, t.i, 2.0::DOUBLE * len(list_intersect(t.g, ug.g)) / (len(t.g) + len(ug.g)) AS dice FROM ug, t WHERE 2 * least(len(t.g), len(ug.g)) >= {THRESHOLD} * (len(t.g) + len(ug.g))),
b AS (SELECT rid, i, dice FROM h WHERE dice >= {THRESHOLD} QUALIFY row_number() OVER (PARTITION BY rid ORDER BY dice DESC, i) = 1)
SELECT d.doc_id, t.name AS license, coalesce(b.dice, 0.0)::DOUBLE AS dice, b.i::INT AS template
FROM d LEFT JOIN b USING (rid) LEFT JOIN t ON t.i = b.i"""


QUERIES = {"op5_license_scan": op5_license_scan}
SQL = {"op5_license_scan": _sql()}
