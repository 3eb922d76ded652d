"""License scan on DataFrame functions only: Dice coefficient of word bigrams against licence templates.

A text is scanned as a whole, by paragraph, by line, by sentence and by runs of consecutive paragraphs, so that a
licence of several paragraphs inside a longer document and a notice inside a line of prose are units too. A unit of a
bigrams can only reach Dice t against a template of b if t/(2-t) <= a/b <= (2-t)/t, so templates outside that size bound
are pruned before any bigram is compared, and runs end where they outgrow the largest template. All of it is one
projection of each row: nothing is exchanged, and rows that share a key do not meet.
"""

from __future__ import annotations

import json
import math
import re

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

DICE = 0.8
#: What parts paragraphs and sentences; the same for Spark and for SQL.
PARAGRAPHS, SENTENCES = r"\n[ \t\r]*\n", r"[.!?][ \t\r\n]+"
#: Notices and short licences as their stewards publish them.
TEMPLATES = {
    "Apache-2.0-notice": "Licensed under the Apache License, Version 2.0.",
    "Apache-2.0-header": "Licensed under the Apache License, Version 2.0 (the \"License\"); you may not use this file except in compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0 Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an \"AS IS\" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. See the License for the specific language governing permissions and limitations under the License.",
    "MIT-notice": "Released under the MIT License.",
    "MIT": "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions: The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software. THE SOFTWARE IS PROVIDED \"AS IS\", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE.",
    "GPL-3.0-notice": "This work is licensed under the GNU General Public License, version 3.",
    "GPL-3.0-header": "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version. This program is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE. See the GNU General Public License for more details.",
    "CC-BY-NC-4.0-notice": "Licensed under CC BY-NC 4.0.",
    "CC-BY-SA-4.0-notice": "This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License.",
    "ISC": "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies.",
    "BSD-notice": "Use of this source code is governed by a BSD-style license that can be found in the LICENSE file.",
}


def bigrams(text: str) -> list[str]:
    """Distinct bigrams of the words of a text, words being runs of a-z and 0-9 of its lower case.

    >>> bigrams("Released under the MIT License.")
    ['mit license', 'released under', 'the mit', 'under the']
    """
    words = re.findall("[a-z0-9]+", text.lower())
    return sorted({f"{a} {b}" for a, b in zip(words, words[1:], strict=False)})


#: Words of ordinary prose, which tell least.
COMMON = frozenset("a an and any as at be by can file for found from in is it not of on or that the this to under use which with without work you".split())


def telling_words(templates: dict[str, str], dice: float) -> list[str]:
    """Words of which every unit that reaches `dice` against some template holds one at least, long words first.

    >>> telling_words({"x": "Released under the MIT License."}, 0.8)
    ['released', 'license']
    """
    out: list[str] = []
    for t in templates.values():
        grams = bigrams(t)
        wanted = len(grams) - math.ceil(dice * len(grams) / (2 - dice) - 1e-9) + 1
        hit: set[str] = {g for g in grams if set(g.split()) & set(out)}
        for w in sorted({w for g in grams for w in g.split()}, key=lambda w: (w in COMMON, -len(w), [-ord(c) for c in w])):
            if len(hit) >= wanted:
                break
            if w not in out:
                out.append(w)
                hit |= {g for g in grams if w in g.split()}
    return out


def _bounds(templates: dict[str, str], dice: float) -> tuple[int, int]:
    sizes = [len(bigrams(t)) for t in templates.values()]
    return int(min(sizes) * dice / (2 - dice)), int(max(sizes) * (2 - dice) / dice) + 1


def scan(df: DataFrame, key: str = "doc_id", text: str = "text", templates: dict[str, str] | None = None, dice: float = DICE) -> DataFrame:
    """Rows (key, licence, dice, n_hits): the best template of each row, and how many templates reach `dice`.

    Ties go to the name that sorts last. Rows without a hit, with a null or empty text or of one word have a null
    licence and dice and 0 hits. Every row is judged by its own text: repeated rows each give a row, rows of one key and
    rows with a null key too; an empty table gives none; other columns are ignored.
    """
    templates = templates or TEMPLATES
    low, high = _bounds(templates, dice)
    telling = "|".join(telling_words(templates, dice))
    norm = lambda x: F.trim(F.regexp_replace(F.lower(x), "[^a-z0-9]+", " "))
    words = lambda x: F.length(x) - F.length(F.replace(x, F.lit(" "), F.lit(""))) + 1
    t = F.coalesce(F.col(text), F.lit(""))
    rows = df.select(F.col(key).alias("__k"), F.when(F.lower(t).rlike(f"(?:^|[^a-z0-9])(?:{telling})(?:$|[^a-z0-9])"), t).alias("__t"))
    parts = F.filter(F.transform(F.split("__t", PARAGRAPHS), norm), lambda x: x != "")
    singles = F.concat(F.array(norm(F.col("__t"))), *[F.transform(F.split("__t", cut), norm) for cut in ("\n", SENTENCES)])
    rows = rows.withColumn("__p", parts).withColumn("__s", singles)
    # Words before each paragraph, so that a run's words are one difference; every paragraph has one at least.
    rows = rows.withColumn("__n", F.transform("__p", words))
    rows = rows.withColumn("__b", F.aggregate("__n", F.array(F.lit(0)), lambda a, n: F.concat(a, F.array(F.element_at(a, -1) + n))))
    count = F.size("__p")
    run = lambda i: F.transform(
        F.filter(F.sequence(i, F.least(count, i + high)), lambda j: (j >= i) & (F.get("__b", j) - F.get("__b", i - 1) <= high)),
        lambda j: F.array_join(F.slice("__p", i, j - i + 1), " "),
    )
    runs = F.when(count > 0, F.flatten(F.transform(F.sequence(F.lit(1), count), run)))
    units = F.array_distinct(F.concat("__s", "__p", F.coalesce(runs, F.array().cast("array<string>"))))
    # Distinct bigrams are at most the blanks of the normalised unit; a unit of fewer is pruned before it is cut up.
    # A unit of more words than bigrams may repeat itself, so nothing but a run is pruned above by words.
    rows = rows.withColumn("__u", F.filter(units, lambda u: (words(u) > low) & u.rlike(f"(?:^| )(?:{telling})(?:$| )")))
    pairs = lambda w: F.array_distinct(F.zip_with(F.slice(w, 1, F.size(w) - 1), F.slice(w, 2, F.size(w) - 1), lambda a, b: F.concat(a, F.lit(" "), b)))
    cut = F.filter(F.transform("__u", lambda u: F.split(u, " ")), lambda w: F.size(w) > 1)
    rows = rows.withColumn("__g", F.filter(F.transform(cut, pairs), lambda g: F.size(g).between(low, high)))
    known = F.from_json(F.lit(json.dumps([{"name": k, "n": len(bigrams(v)), "grams": bigrams(v)} for k, v in sorted(templates.items())])), "array<struct<name:string,n:int,grams:array<string>>>")
    near = lambda g: F.filter(known, lambda x: (F.size(g) * (2 - dice) >= x["n"] * dice) & (F.size(g) * dice <= x["n"] * (2 - dice)))
    scored = lambda g: F.transform(near(g), lambda x: F.struct((F.lit(2.0) * F.size(F.array_intersect(g, x["grams"])) / (F.size(g) + x["n"])).alias("dice"), x["name"].alias("name")))
    rows = rows.withColumn("__h", F.filter(F.flatten(F.transform("__g", scored)), lambda x: x["dice"] >= dice))
    best = F.array_max("__h")
    hits = F.size(F.array_distinct(F.transform("__h", lambda x: x["name"])))
    return rows.select(F.col("__k").alias(key), best["name"].alias("licence"), best["dice"].alias("dice"), F.when(F.col("__h").isNull(), 0).otherwise(hits).cast("long").alias("n_hits"))


def report(df: DataFrame) -> DataFrame:
    return scan(df)


def report_sql() -> str:
    rows = ", ".join("('{}', [{}])".format(k, ", ".join("'" + g + "'" for g in bigrams(v))) for k, v in sorted(TEMPLATES.items()))
    norm = lambda x: f"trim(regexp_replace(lower({x}), '[^a-z0-9]+', ' ', 'g'))"
    return f"""
WITH t(name, grams) AS (VALUES {rows}),
d AS (SELECT row_number() OVER () AS r, doc_id, coalesce(text, '') AS text FROM documents),
p AS (SELECT r, list_filter(list_transform(regexp_split_to_array(text, '{PARAGRAPHS}'), lambda x: {norm('x')}), lambda x: x <> '') AS p FROM d),
i AS (SELECT r, p, unnest(range(1, len(p) + 1)) AS i FROM p),
w AS (SELECT r, p, i, sum(len(string_split(p[i], ' '))) OVER (PARTITION BY r ORDER BY i) AS upto, len(string_split(p[i], ' ')) AS own FROM i),
u AS (
SELECT r, {norm('text')} AS u FROM d
UNION SELECT r, {norm('unnest(list_concat(regexp_split_to_array(text, ' + chr(39) + SENTENCES + chr(39) + '), string_split(text, chr(10))))')} FROM d
UNION SELECT r, unnest(p) FROM p
UNION SELECT a.r, array_to_string(a.p[a.i:b.i], ' ') FROM w a JOIN w b ON a.r = b.r AND a.i < b.i AND b.upto - a.upto + a.own <= {_bounds(TEMPLATES, DICE)[1]}),
g AS (SELECT r, list_distinct(list_transform(range(1, len(w)), lambda i: w[i] || ' ' || w[i + 1])) AS g FROM (SELECT r, string_split(u, ' ') AS w FROM u) WHERE len(w) > 1),
s AS (SELECT r, name, 2.0::DOUBLE * len(list_intersect(g, grams)) / (len(g) + len(grams)) AS dice FROM g JOIN t ON len(g) * {2 - DICE} >= len(grams) * {DICE} AND len(g) * {DICE} <= len(grams) * {2 - DICE}),
b AS (SELECT r, max((dice, name)) AS h, count(DISTINCT name) AS n_hits FROM s WHERE dice >= {DICE} GROUP BY r)
SELECT doc_id, h[2] AS licence, h[1] AS dice, coalesce(n_hits, 0)::BIGINT AS n_hits FROM d LEFT JOIN b USING (r)
"""
