"""Licence scans by the Dice coefficient over word bigrams.

A text is normalised (lower case; everything but letters and digits parts words) and cut into units: its lines, its
paragraphs where it has blank lines, and the text as a whole; for templates that none of these match, windows slide over
the running words, of any length up to the size bound in bigrams, and count as units where they lie a template's size
apart. A unit matches a template if twice the number of their
common distinct word bigrams is at least DICE of the sum of their numbers of distinct bigrams. Two bounds follow from
that and prune without loss: the sizes must be in the ratio DICE/(2-DICE) at least, and a unit must hold so many of the
template's bigrams that it holds a word of any selection of all but so many of them; the longest words are selected.

Only DataFrame functions; one pass without a shuffle, but for the best unit of each text and template.

Defined results: null and empty texts match nothing; repeated rows (equal ids) give one result, and so do all rows without
an id; other columns are ignored; templates of fewer than two words are refused.
"""

from __future__ import annotations

import math
import re

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from facetsel.llm.common import table

DICE = 0.8

# Public licence notices and texts.
TEMPLATES = {
    "apache-2.0 notice": "Licensed under the Apache License, Version 2.0.",
    "cc-by-4.0 notice": "Licensed under CC BY 4.0.",
    "cc-by-nc-4.0 notice": "Licensed under CC BY-NC 4.0.",
    "cc-by-sa-4.0 notice": "Licensed under CC BY-SA 4.0.",
    "gpl-3.0 notice": "This work is licensed under the GNU General Public License, version 3.",
    "mit notice": "Released under the MIT License.",
    "proprietary notice": "All rights reserved. Do not copy or distribute.",
    "apache-2.0 header": """Licensed under the Apache License, Version 2.0 (the "License"); you may not use this file except in
        compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0
        Unless required by applicable law or agreed to in writing, software distributed under the License is distributed
        on an "AS IS" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. See the License for
        the specific language governing permissions and limitations under the License.""",
    "gpl-3.0 header": """This program is free software: you can redistribute it and/or modify it under the terms of the GNU
        General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your
        option) any later version. This program is distributed in the hope that it will be useful, but WITHOUT ANY
        WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE. See the GNU
        General Public License for more details. You should have received a copy of the GNU General Public License along
        with this program. If not, see <https://www.gnu.org/licenses/>.""",
    "isc": """Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby
        granted, provided that the above copyright notice and this permission notice appear in all copies. THE SOFTWARE IS
        PROVIDED "AS IS" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED
        WARRANTIES OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT,
        INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER
        IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR
        PERFORMANCE OF THIS SOFTWARE.""",
    "mit": """Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated
        documentation files (the "Software"), to deal in the Software without restriction, including without limitation the
        rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to
        permit persons to whom the Software is furnished to do so, subject to the following conditions: The above copyright
        notice and this permission notice shall be included in all copies or substantial portions of the Software. THE
        SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE
        WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS
        OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR
        OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE.""",
}


def template_words(text: str) -> list[str]:
    return re.findall(r"[^\W_]+", text.lower())


def template_bigrams(text: str) -> list[str]:
    w = template_words(text)
    return sorted({f"{a} {b}" for a, b in zip(w, w[1:], strict=False)})


def telling_words(bigrams: list[str], dice: float) -> set[str]:
    """Words one of which any matching unit holds: it lacks fewer bigrams than are selected here."""
    shared = math.ceil(dice / (2 - dice) * len(bigrams) - 1e-9)
    longest = sorted((max(b.split(), key=lambda w: (len(w), w)) for b in bigrams), key=lambda w: (-len(w), w))
    return set(longest[: len(bigrams) - shared + 1])


def words_of(text: Column) -> Column:
    return F.array_remove(F.split(F.lower(text), r"[^\p{L}\p{N}]+"), "")


def _pairs(w: Column) -> Column:
    return F.zip_with(F.slice(w, 1, F.greatest(F.size(w) - 1, F.lit(0))), F.slice(w, 2, F.size(w)), lambda a, b: F.concat(a, F.lit(" "), b))


def _windows(docs: DataFrame, known: Column, telling: list[str], dice: float) -> DataFrame:
    """(doc_id, licence, dice, n): the best window of each text (doc_id, t) and template, and how many places match, of texts
    that hold enough of a template's bigrams for any unit to match.

    A best window begins with a bigram of the template, and holds so many of them that those from its first one on must
    lie close together; few places pass this. Arrays of one element are exploded so that a thing is computed once."""
    cut = docs.select("doc_id", F.explode(F.array(words_of(F.col("t")))).alias("w")).where(F.arrays_overlap("w", F.array(*map(F.lit, telling))))
    cut = cut.select("doc_id", F.explode(F.array(_pairs(F.col("w")))).alias("g"))
    cut = cut.select("doc_id", "g", F.explode(F.array(F.array_distinct("g"))).alias("b"))
    held = F.filter(known, lambda x: F.size(F.array_intersect(x["b"], F.col("b"))) >= dice / (2 - dice) * F.size(x["b"]) - 1e-9)
    cut = cut.select("doc_id", "g", F.explode(held).alias("x")).select("doc_id", "g", F.col("x.licence").alias("licence"), F.col("x.b").alias("tb"))
    places = F.filter(F.transform("g", lambda x, i: F.when(F.array_contains("tb", x), i)), F.isnotnull)
    cut = cut.select("*", F.explode(F.array(places)).alias("at"))
    most = F.floor((2 - dice) / dice * F.size("tb") + 1e-9).cast("int")
    need = F.ceil(dice / (2 - dice) * F.size("tb") - 1e-9).cast("int")
    begins = F.filter("at", lambda i, k: F.coalesce(F.get("at", k + need - 1) - i < most, F.lit(False)))
    cut = cut.select("*", F.explode(F.array(begins)).alias("begins")).where(F.size("begins") > 0)

    def state(seen: Column, common: Column, best: Column) -> Column:
        return F.struct(seen.alias("seen"), common.alias("common"), best.alias("best"))

    def longer(window: Column, x: Column) -> Column:
        seen, common = F.array_append(window["seen"], x), window["common"] + F.array_contains("tb", x).cast("int")
        now = 2.0 * common / (F.size(window["seen"]) + 1 + F.size("tb"))
        return F.when(F.array_contains(window["seen"], x), window).otherwise(state(seen, common, F.greatest(window["best"], now)))

    def best(i: Column) -> Column:
        return F.aggregate(F.slice("g", i + 1, most), state(F.array().cast("array<string>"), F.lit(0), F.lit(0.0)), longer)["best"]

    found = F.filter(F.transform("begins", lambda i: F.struct(best(i).alias("dice"), i.alias("i"))), lambda x: x["dice"] >= dice)
    cut = cut.select("doc_id", "licence", "tb", F.explode(F.array(found)).alias("found")).where(F.size("found") > 0)
    none = F.struct(F.lit(0).alias("n"), F.lit(None).cast("int").alias("last"))
    apart = lambda s, x: F.coalesce(x["i"] - s["last"] >= F.size("tb"), F.lit(True))
    counted = F.aggregate("found", none, lambda s, x: F.when(apart(s, x), F.struct((s["n"] + 1).alias("n"), x["i"].alias("last"))).otherwise(s))
    return cut.select("doc_id", "licence", F.array_max("found")["dice"].alias("dice"), counted["n"].cast("long").alias("n"))


def scan(docs: DataFrame, templates: dict[str, str] = TEMPLATES, dice: float = DICE, text: str = "text", key: str = "doc_id") -> DataFrame:
    """(doc_id, licence, dice, n_units): for each text and template that match, the best coefficient and the number of
    units that match."""
    grams = {k: template_bigrams(v) for k, v in templates.items()}
    if not grams or min(map(len, grams.values())) < 1:
        raise ValueError("a template needs two words")
    telling = sorted(set().union(*(telling_words(b, dice) for b in grams.values())))
    t = F.col(text)
    units = F.concat(F.split(t, "\n"), F.when(F.contains(t, F.lit("\n\n")), F.split(t, r"\n\s*\n")).otherwise(F.array().cast("array<string>")), F.when(F.contains(t, F.lit("\n")), F.array(t)).otherwise(F.array().cast("array<string>")))
    held = docs.where(t.isNotNull()).select(F.col(key).alias("doc_id"), F.explode(units).alias("unit")).select("doc_id", words_of(F.col("unit")).alias("w"))
    held = held.where(F.arrays_overlap("w", F.array(*map(F.lit, telling))))
    held = held.where(F.size("w") > 1).select("doc_id", F.array_distinct(_pairs(F.col("w"))).alias("b"))
    known = F.array(*[F.struct(F.lit(k).alias("licence"), F.array(*map(F.lit, b)).alias("b")) for k, b in sorted(grams.items())])
    fits = F.filter(known, lambda x: (F.size(x["b"]) >= dice / (2 - dice) * F.size("b") - 1e-9) & (F.size("b") >= dice / (2 - dice) * F.size(x["b"]) - 1e-9))
    near = held.select("doc_id", "b", F.explode(fits).alias("x"))
    near = near.select("doc_id", F.col("x.licence").alias("licence"), (2.0 * F.size(F.array_intersect("b", "x.b")) / (F.size("b") + F.size("x.b"))).alias("dice"))
    slid = _windows(docs.select(F.col(key).alias("doc_id"), t.alias("t")), known, telling, dice)
    near = near.select("*", F.lit(1).cast("long").alias("n"), F.lit(False).alias("slid")).unionByName(slid.select("*", F.lit(True).alias("slid")))
    best = near.where(F.col("dice") >= dice).groupBy("doc_id", "licence", "slid").agg(F.max("dice").alias("dice"), F.sum("n").alias("n_units"))
    first = best.groupBy("doc_id", "licence").agg(F.min_by(F.struct("dice", "n_units"), "slid").alias("x"))
    return first.select("doc_id", "licence", "x.dice", "x.n_units")


def op8_licences(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan(table(spark, sf_dir, "documents"))


def _sql() -> str:
    """All units against all templates of a size that can match."""
    rows = ", ".join("('{}', [{}])".format(k, ", ".join(f"'{b}'" for b in template_bigrams(v))) for k, v in TEMPLATES.items())
    return rf"""
WITH t(licence, tb) AS (VALUES {rows}),
u AS (
  SELECT doc_id, unnest(list_concat(string_split(text, chr(10)),
         CASE WHEN contains(text, chr(10) || chr(10)) THEN regexp_split_to_array(text, '\n\s*\n') ELSE [] END,
         CASE WHEN contains(text, chr(10)) THEN [text] ELSE [] END)) AS unit FROM documents WHERE text IS NOT NULL),
w AS (SELECT doc_id, list_filter(regexp_split_to_array(lower(unit), '[^\p{{L}}\p{{N}}]+'), lambda x: x <> '') AS w FROM u),
b AS (SELECT doc_id, list_distinct(list_transform(range(1, len(w)), lambda i: w[i] || ' ' || w[i + 1])) AS b FROM w WHERE len(w) > 1),
d AS (SELECT doc_id, licence, 2.0 * len(list_intersect(b, tb)) / (len(b) + len(tb)) AS dice FROM b, t WHERE least(len(b), len(tb)) >= {DICE / (2 - DICE)} * greatest(len(b), len(tb)) - 1e-9)
SELECT doc_id, licence, CAST(max(dice) AS DOUBLE) AS dice, count(*) AS n_units FROM d WHERE dice >= {DICE} GROUP BY ALL
"""


OP8_SQL = _sql()
