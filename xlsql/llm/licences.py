"""Licence scans with DataFrame functions only: Dice coefficient over word bigrams against licence templates."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Least Dice coefficient of a match.
DICE = 0.8

# Short public licence texts and notices. Longer licences can be given as a table of templates.
TEMPLATES = {
    "MIT": """Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the "Software"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions: The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software. THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE.""",
    "MIT-notice": "Released under the MIT License.",
    "ISC": """Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies. THE SOFTWARE IS PROVIDED "AS IS" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE.""",
    "BSD-2-Clause": """Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: 1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer. 2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution. THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS "AS IS" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED.""",
    "Apache-2.0-notice": """Licensed under the Apache License, Version 2.0 (the "License"); you may not use this file except in compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0 Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an "AS IS" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. See the License for the specific language governing permissions and limitations under the License.""",
    "Apache-2.0-line": "Licensed under the Apache License, Version 2.0.",
    "GPL-3.0-notice": """This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version. This program is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE. See the GNU General Public License for more details.""",
    "GPL-3.0-line": "This work is licensed under the GNU General Public License, version 3.",
    "CC-BY-NC-4.0-line": "Licensed under CC BY-NC 4.0.",
    "CC-BY-4.0-line": "This work is licensed under a Creative Commons Attribution 4.0 International License.",
    "MPL-2.0-notice": "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can obtain one at https://mozilla.org/MPL/2.0/.",
    "Unlicense-notice": "This is free and unencumbered software released into the public domain. Anyone is free to copy, modify, publish, use, compile, sell, or distribute this software, either in source code form or as a compiled binary, for any purpose, commercial or non-commercial, and by any means.",
}


def default_templates(spark: SparkSession) -> DataFrame:
    """licence, text."""
    rows = F.array(*[F.struct(F.lit(k).alias("licence"), F.lit(v).alias("text")) for k, v in TEMPLATES.items()])
    return spark.range(1).select(F.explode(rows).alias("t")).select("t.licence", "t.text")


def normal(text: Column, other: str = r"[^\p{L}\p{N}]+") -> Column:
    """Normal form: lower-case runs of letters and digits with spaces for what ``other`` matches (``licence`` spelt ``license``)."""
    return F.replace(F.regexp_replace(F.lower(F.coalesce(text, F.lit(""))), other, " "), F.lit("licence"), F.lit("license"))


def words(text: Column) -> Column:
    return F.split(F.trim(normal(text)), " ")


def anchor_words(templates: DataFrame, dice: float) -> set[str]:
    """Words of which every match has at least one.

    A match shares c >= b dice / (2 - dice) of a template's b bigrams, so it cannot miss a set of more than b - c of them. The longest words
    whose bigrams make up such a set are taken from each template.
    """
    out: set[str] = set()
    for r in templates.select("grams").collect():
        pairs = [g.split(" ") for g in r["grams"]]
        spare = len(pairs) - math.ceil(len(pairs) * dice / (2 - dice) - 1e-9)
        covered: set[int] = set()
        for word in sorted({w for p in pairs for w in p}, key=lambda w: (-len(w), w)):
            if len(covered) > spare:
                break
            out.add(word)
            covered |= {i for i, p in enumerate(pairs) if word in p}
    return out


def bigrams(parts: Column) -> Column:
    """Distinct neighbouring pairs; a text of one word has that word as its only one, an empty text none."""
    pairs = F.zip_with(F.slice(parts, 1, F.size(parts) - 1), F.slice(parts, 2, F.size(parts) - 1), lambda a, b: F.concat_ws(" ", a, b))
    return F.when(F.size(parts) > 1, F.array_distinct(pairs)).otherwise(F.filter(parts, lambda w: w != ""))


def licence_matches(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", templates: DataFrame | None = None, dice: float = DICE) -> DataFrame:
    """doc_id, part, licence, score: best template of every whole text (part -1) and every line (its number) at ``dice`` or more.

    Dice is 2c / (a + b) over distinct bigrams. A unit of a bigrams can only reach ``dice`` against templates of b bigrams with
    a dice / (2 - dice) <= b <= a (2 - dice) / dice: units outside all templates' bounds are dropped before their bigrams are made, and each
    unit meets only templates within its own. Texts and units without an anchor word (``anchor_words``) cannot match and end earlier. Ties go to the first name. Lines of the same text in one document and repeated rows each have their row.
    Null and empty texts match nothing; other columns are ignored.
    """
    return _matches(docs, doc_id, text, templates, dice, False).select("doc_id", "part", "licence", "score")


def licence_passages(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", templates: DataFrame | None = None, dice: float = DICE) -> DataFrame:
    """doc_id, part, licence, score: what ``licence_matches`` finds, and stretches of words over several lines or within one (part -2).

    A stretch within a matched unit, or one that holds a matched line of its own licence, is not told again. Templates of one word match units only.
    """
    return _matches(docs, doc_id, text, templates, dice, True).select("doc_id", "part", "licence", "score")


def _windows(hits: Column, b: Column, total: Column, dice: float) -> Column:
    """Best windows of ``dice`` or more that do not overlap: struct of the score's negative, first and last place, first and last line.

    ``hits`` are the places of a template's bigrams in order. A best window begins and ends with one of them, for a foreign bigram at an end
    only lowers the coefficient, and spans at most (2 - dice) / dice as many places as the template. Foreign bigrams count once for each place.
    """
    least = F.ceil(b * (dice / (2 - dice)) - F.lit(1e-9)).cast("int")
    reach = F.floor(total * ((2 - dice) / dice) + F.lit(1e-9)).cast("int")
    many = F.size(hits)

    def window(i: Column, j: Column) -> Column:
        shared = F.size(F.array_distinct(F.transform(F.slice(hits, i + 1, j - i + 1), lambda h: h["gram"])))
        score = 2.0 * shared / (shared + (hits[j]["pos"] - hits[i]["pos"]) - (j - i) + b)
        return F.struct((-score).alias("worse"), hits[i]["pos"].alias("begin"), hits[j]["pos"].alias("end"), hits[i]["line"].alias("first"), hits[j]["after"].alias("last"))

    def from_place(i: Column) -> Column:
        ends = F.filter(F.sequence(i + least - 1, F.least(many, i + reach) - 1), lambda j: hits[j]["pos"] - hits[i]["pos"] < reach)
        return F.filter(F.transform(ends, lambda j: window(i, j)), lambda w: -w["worse"] >= dice)

    found = F.array_sort(F.flatten(F.transform(F.sequence(F.lit(0), many - least), from_place)))
    apart = lambda taken, w: ~F.exists(taken, lambda x: (x["begin"] <= w["end"]) & (w["begin"] <= x["end"]))
    return F.aggregate(found, F.slice(found, 1, 0), lambda taken, w: F.when(apart(taken, w), F.concat(taken, F.array(w))).otherwise(taken))


def _matches(docs: DataFrame, doc_id: str, text: str, templates: DataFrame | None, dice: float, passages: bool) -> DataFrame:
    """doc_id, part, licence, score of whole texts and lines, with ``passages`` of stretches too."""
    spark = docs.sparkSession
    t = (templates if templates is not None else default_templates(spark)).select("licence", words(F.col("text")).alias("w")).withColumn("grams", bigrams(F.col("w"))).where(F.size("grams") > 0)
    t = t.select("licence", "grams", F.size("grams").alias("b"), (F.size("w") - 1).alias("total"))
    low, high, total = t.agg(F.min("b"), F.max("b"), F.sum("b")).first()
    if not total:
        return docs.select(F.col(doc_id).alias("doc_id"), F.lit(0).alias("part"), F.lit("").alias("licence"), F.lit(0.0).alias("score")).where("false")
    if total > 2_000_000:
        raise ValueError("templates must be few enough to be sent to every task")
    ratio = (2 - dice) / dice
    anchors = F.array(*[F.lit(x) for x in sorted(anchor_words(t, dice))])
    norm = normal(F.col(text), r"[^\p{L}\p{N}\n]+")
    held = docs.select(F.monotonically_increasing_id().alias("row"), F.col(doc_id).alias("doc_id"), norm.alias("norm"))
    held = held.where(F.arrays_overlap(F.split("norm", "[ \n]"), anchors))
    unit = lambda i, c: F.struct(i.alias("part"), F.trim(c).alias("unit"))
    lines = F.when(F.col("norm").contains("\n"), F.transform(F.split("norm", "\n"), lambda x, i: unit(i, x))).otherwise(F.array().cast("array<struct<part:int,unit:string>>"))
    whole = F.array(unit(F.lit(-1), F.regexp_replace("norm", "[ \n]+", " ")))
    # the whole text again, for stretches of it: its bigrams keep their places and lines
    again = [F.array(unit(F.lit(-2), F.col("norm")))] if passages else []
    held = held.select("row", "doc_id", F.explode(F.concat(whole, lines, *again)).alias("u")).select("row", "doc_id", "u.part", "u.unit", F.split(F.trim(F.regexp_replace("u.unit", "[ \n]+", " ")), " ").alias("w"))
    held = held.where((F.size("w") >= low / ratio) & F.arrays_overlap("w", anchors))
    held = held.withColumn("grams", F.when(F.col("part") > -2, bigrams(F.col("w")))).withColumn("a", F.size("grams")).where((F.col("part") == -2) | (F.col("a") >= low / ratio) & (F.col("a") <= high * ratio))
    place = lambda g, i, x, y: F.struct(g.alias("gram"), i.cast("int").alias("pos"), x.cast("int").alias("line"), y.cast("int").alias("after"))
    plain = F.transform("grams", lambda g: place(g, F.lit(0), F.lit(0), F.lit(0)))
    if passages:
        number = F.flatten(F.transform(F.split("unit", "\n"), lambda x, i: F.transform(F.filter(F.split(x, " "), lambda y: y != ""), lambda _: i)))
        held = held.withColumn("n", F.when(F.col("part") == -2, number))
        w, n = F.col("w"), F.col("n")
        pair = F.zip_with(F.slice(w, 1, F.size(w) - 1), F.slice(w, 2, F.size(w) - 1), lambda x, y: F.concat_ws(" ", x, y))
        placed = F.when(F.size(w) > 1, F.transform(pair, lambda g, i: place(g, i, n[i], n[i + 1])))
        plain = F.when(F.col("part") == -2, placed).otherwise(plain)
    pieces = held.select("row", "doc_id", "part", "a", F.explode(plain).alias("x")).select("row", "doc_id", "part", "a", "x.*")
    seeds = F.broadcast(t.select("licence", "b", "total", F.explode("grams").alias("gram")))
    met = pieces.join(seeds, "gram").where((F.col("part") == -2) | (F.col("b") <= F.col("a") * ratio) & (F.col("b") >= F.col("a") / ratio))
    hits = [F.array_sort(F.collect_list(F.when(F.col("part") == -2, F.struct("pos", "gram", "line", "after")))).alias("hits"), F.first("total").alias("total")] if passages else []
    scores = met.groupBy("row", "doc_id", "part", "licence").agg((2.0 * F.count("*") / (F.first("a") + F.first("b"))).alias("score"), F.first("b").alias("b"), *hits)
    if not passages:
        best = scores.where(F.col("score") >= dice).groupBy("row", "doc_id", "part").agg(F.min_by("licence", F.struct((-F.col("score")).alias("s"), F.col("licence").alias("l"))).alias("licence"), F.max("score").alias("score"))
        return best.select("doc_id", "part", "licence", "score")
    enough = (F.col("part") == -2) & (F.size("hits") >= F.col("b") * (1 / ratio) - 1e-9)
    spans = F.when(enough, _windows(F.col("hits"), F.col("b"), F.col("total"), dice))
    own = F.array(F.struct((-F.col("score")).alias("worse"), F.lit(0).alias("begin"), F.lit(0).alias("end"), F.col("part").alias("first"), F.col("part").alias("last")))
    found = scores.where((F.col("part") > -2) & (F.col("score") >= dice) | enough).select("row", "doc_id", "part", "licence", F.explode(F.when(F.col("part") > -2, own).otherwise(spans)).alias("s"))
    # the best template of each unit, then stretches that no unit tells
    found = found.select("row", "doc_id", F.struct(F.col("part"), F.col("s.worse").alias("worse"), "licence", "s.first", "s.last", "s.begin", "s.end").alias("m"))
    all_of = found.groupBy("row", "doc_id").agg(F.array_sort(F.collect_list("m")).alias("m"))
    told = F.filter("m", lambda x, i: (x["part"] > -2) & ((i == 0) | (F.col("m")[F.greatest(i - 1, F.lit(0))]["part"] != x["part"])))
    all_of = all_of.withColumn("told", told)
    inside = lambda x: F.exists("told", lambda u: (u["part"] == -1) | (x["first"] <= u["part"]) & (u["part"] <= x["last"]) & ((x["first"] == x["last"]) | (u["licence"] == x["licence"])))
    # a stretch within a better one of another template is not told
    rival = lambda x: F.exists("m", lambda y: (y["part"] == -2) & (y["licence"] != x["licence"]) & (y["begin"] <= x["begin"]) & (x["end"] <= y["end"]) & ((y["worse"] < x["worse"]) | (y["worse"] == x["worse"]) & (y["licence"] < x["licence"])))
    rest = F.filter("m", lambda x: (x["part"] == -2) & ~inside(x) & ~rival(x))
    return all_of.select("doc_id", F.explode(F.concat("told", rest)).alias("m")).select("doc_id", "m.part", "m.licence", (-F.col("m.worse")).alias("score"))


def licence_report(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", **options) -> DataFrame:
    """doc_id, licence, n_matches, best_score for each document and licence found in it."""
    found = licence_passages(docs, doc_id, text, **options)
    return found.groupBy("doc_id", "licence").agg(F.count("*").alias("n_matches"), F.round(F.max("score"), 6).alias("best_score"))
