"""Licence scan: lines, paragraphs, whole texts and windows of words against licence templates by Dice over word bigrams."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

# Public licence notices and texts, in the wording their publishers ask for.
TEMPLATES: dict[str, tuple[str, ...]] = {
    "MIT": (
        "Released under the MIT License.",
        "Licensed under the MIT License.",
        "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated"
        " documentation files (the \"Software\"), to deal in the Software without restriction, including without"
        " limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of"
        " the Software, and to permit persons to whom the Software is furnished to do so, subject to the following"
        " conditions: The above copyright notice and this permission notice shall be included in all copies or"
        " substantial portions of the Software. THE SOFTWARE IS PROVIDED \"AS IS\", WITHOUT WARRANTY OF ANY KIND,"
        " EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A"
        " PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR"
        " ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM,"
        " OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE.",
    ),
    "Apache-2.0": (
        "Licensed under the Apache License, Version 2.0.",
        "Licensed under the Apache License, Version 2.0 (the \"License\"); you may not use this file except in"
        " compliance with the License. You may obtain a copy of the License at"
        " http://www.apache.org/licenses/LICENSE-2.0 Unless required by applicable law or agreed to in writing,"
        " software distributed under the License is distributed on an \"AS IS\" BASIS, WITHOUT WARRANTIES OR"
        " CONDITIONS OF ANY KIND, either express or implied. See the License for the specific language governing"
        " permissions and limitations under the License.",
    ),
    "GPL-3.0": (
        "This work is licensed under the GNU General Public License, version 3.",
        "Licensed under the GNU General Public License, version 3.",
        "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General"
        " Public License as published by the Free Software Foundation, either version 3 of the License, or (at your"
        " option) any later version. This program is distributed in the hope that it will be useful, but WITHOUT ANY"
        " WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE. See the"
        " GNU General Public License for more details. You should have received a copy of the GNU General Public"
        " License along with this program. If not, see <https://www.gnu.org/licenses/>.",
    ),
    "BSD": (
        "Redistribution and use in source and binary forms, with or without modification, are permitted provided that"
        " the following conditions are met: 1. Redistributions of source code must retain the above copyright notice,"
        " this list of conditions and the following disclaimer. 2. Redistributions in binary form must reproduce the"
        " above copyright notice, this list of conditions and the following disclaimer in the documentation and/or"
        " other materials provided with the distribution.",
        "Redistribution and use in source and binary forms, with or without modification, are permitted provided that"
        " the following conditions are met: 1. Redistributions of source code must retain the above copyright notice,"
        " this list of conditions and the following disclaimer. 2. Redistributions in binary form must reproduce the"
        " above copyright notice, this list of conditions and the following disclaimer in the documentation and/or"
        " other materials provided with the distribution. THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND"
        " CONTRIBUTORS \"AS IS\" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED"
        " WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE"
        " COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR"
        " CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF"
        " USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN"
        " CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF"
        " THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE.",
    ),
    "ISC": (
        "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is"
        " hereby granted, provided that the above copyright notice and this permission notice appear in all copies.",
        "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is"
        " hereby granted, provided that the above copyright notice and this permission notice appear in all copies."
        " THE SOFTWARE IS PROVIDED \"AS IS\" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE"
        " INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR"
        " ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF"
        " USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF"
        " OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE.",
    ),
    "CC-BY-NC-4.0": (
        "Licensed under CC BY-NC 4.0.",
        "This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International License.",
    ),
    "CC-BY-4.0": (
        "Licensed under CC BY 4.0.",
        "This work is licensed under a Creative Commons Attribution 4.0 International License.",
    ),
    "CC-BY-SA-4.0": (
        "Licensed under CC BY-SA 4.0.",
        "This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License.",
    ),
    "proprietary": ("All rights reserved.",),
}


def _bigrams(df: DataFrame, col: str) -> DataFrame:
    """`df` with b: the word bigrams of `col` in order, as hashes; normalised to lower-case letters and digits."""
    words = F.array_remove(F.split(F.lower(col), "[^\\p{L}\\p{N}]+"), "")
    return (
        df.withColumn("_w", words)
        .withColumn(
            "b",
            F.expr(
                "slice(zip_with(_w, slice(_w, 2, size(_w)), (x, y) ->"
                " if(y is null, 0L, xxhash64(x, y))), 1, greatest(size(_w) - 1, 0))"
            ),
        )
        .drop("_w")
    )


def scanned(
    docs: DataFrame,
    id_col: str = "doc_id",
    text_col: str = "text",
    least: float = 0.8,
    window_from: int = 20,
    templates=TEMPLATES,
) -> DataFrame:
    """(id, license, dice, n_units) of every document and licence that match.

    A unit is a line, a block between blank lines, or the whole text, each distinct unit of a document once, or
    a window of words for a form of `window_from` bigrams or more; it matches a template if the Dice
    coefficient of their sets of word bigrams is `least` or more. Sizes
    m and n can only match if m lies within n*least/(2-least) and n*(2-least)/least: templates are listed under
    the sizes they admit, and a unit meets only those of its own size. The list is as long as the
    templates, whatever the input.

    Windows find licences spread over lines and paragraphs, set in comments, or inside longer lines. A
    match has at least n*least/(2-least) of the template's bigrams, so only texts with as many are looked at, and
    at least one of the template's first n*(2-2*least)/(2-least)+1: where one of those stands in the text, the window
    as long as the template begins where the template would. So there are at most as many windows as words.

    Null and empty texts and units of one word match nothing. Rows that repeat an id are taken together: the
    best Dice and the sum of units. Templates of one licence that tie count as separate units. Other
    columns are not read, whatever their names.
    """
    spark = docs.sparkSession
    rows = [(name, n, t) for name, ts in templates.items() for n, t in enumerate(ts)]
    listed = (
        _bigrams(spark.createDataFrame(rows, "license string, form int, t string"), "t")
        .withColumn("tg", F.array_distinct("b"))
        .withColumn("n", F.size("tg"))
    )
    shared, most = least / (2 - least), (2 - least) / least
    admitted = listed.select("license", "tg", "n").withColumn(
        "m",
        F.explode(
            F.sequence(
                F.ceil(F.col("n") * shared - 1e-9).cast("int"),
                F.floor(F.col("n") * most + 1e-9).cast("int"),
            )
        ),
    )
    texts = docs.where(F.col(text_col).isNotNull()).select(F.col(id_col).alias("id"), F.col(text_col).alias("text"))
    units = texts.select(
        "id",
        F.explode(
            F.array_distinct(F.concat(F.split("text", "\n"), F.split("text", "\n[ \t\r]*\n"), F.array("text")))
        ).alias("unit"),
    )
    # a generator is a barrier: filters and join keys on the bigrams are not computed anew below it
    once = _bigrams(units, "unit").select("id", F.explode(F.array(F.array_distinct("b"))).alias("g"))
    grams = once.withColumn("m", F.size("g")).where("m > 0")
    dice = 2 * F.size(F.array_intersect("g", "tg")) / (F.col("m") + F.col("n"))
    whole = grams.join(F.broadcast(admitted), "m").select("id", "license", dice.alias("dice"))

    # one row a template: as many as the templates, whatever the input
    long = [
        (
            r["license"],
            r["b"],
            r["tg"],
            math.ceil(r["n"] * shared - 1e-9),
            {x: r["b"].index(x) for x in r["tg"][: int(r["n"] * (1 - shared) + 1e-9) + 1]},
        )
        for r in listed.where(F.col("n") >= window_from).collect()
    ]
    if not long:
        return _best(whole.where(F.col("dice") >= least))
    kinds = spark.createDataFrame(
        [(i, name, len(tb), tg, seeds) for i, (name, tb, tg, _, seeds) in enumerate(long)],
        "i int, license string, length int, tg array<bigint>, seeds map<bigint, int>",
    )
    near = F.filter(
        F.lit(list(range(len(long)))),
        lambda i: F.size(F.array_intersect("b", F.element_at(F.lit([tg for _, _, tg, _, _ in long]), i + 1)))
        >= F.element_at(F.lit([need for *_, need, _ in long]), i + 1),
    )
    spread = (
        _bigrams(texts, "text")
        .select("id", F.explode(F.array("b")).alias("b"))
        .where(F.size("b") > 0)
        .select("id", "b", F.explode(near).alias("i"))
        .join(F.broadcast(kinds), "i")
    )
    aligned = F.filter(F.transform("b", lambda x, p: p - F.try_element_at("seeds", x)), lambda at: at.isNotNull())
    starts = F.array_distinct(F.transform(aligned, lambda at: F.greatest(at, F.lit(0))))

    def window(at):
        part = F.slice("b", at + 1, F.col("length"))
        return 2 * F.size(F.array_intersect(part, F.col("tg"))) / (F.size(F.array_distinct(part)) + F.size("tg"))

    windows = spread.select("id", "license", F.explode(F.transform(starts, window)).alias("dice"))
    return _best(whole.unionByName(windows).where(F.col("dice") >= least))


def _best(found: DataFrame) -> DataFrame:
    """The best Dice of every document and licence, and how many units have matched."""
    return found.groupBy("id", "license").agg(F.max("dice").alias("dice"), F.count(F.lit(1)).alias("n_units"))


def oracle(least: float = 0.8, window_from: int = 20, templates=TEMPLATES) -> str:
    """DuckDB SQL of the same rows."""
    values = ", ".join(
        "('{}', '{}')".format(name, t.replace("'", "''")) for name, ts in templates.items() for t in ts
    )
    shared, most = least / (2 - least), (2 - least) / least

    def grams(col: str) -> str:
        return (
            f"list_filter(string_split_regex(lower({col}), '[^\\p{{L}}\\p{{N}}]+'), lambda x: x <> '') as w,"
            " list_transform(list_zip(w[1:len(w) - 1], w[2:]), lambda p: p[1] || ' ' || p[2]) as b,"
            " list_distinct(b) as g"
        )

    return f"""
with t as (select license, {grams("t")} from (values {values}) v(license, t)),
u as (select doc_id, unnest(list_distinct(list_concat(string_split(text, chr(10)),
  string_split_regex(text, '\\n[ \\t\\r]*\\n'), [text]))) as unit from documents where text is not null),
g as materialized (select doc_id, {grams("unit")} from u),
n as materialized (select doc_id, g, len(g) as m from g where m > 0),
z as materialized (select license, g, b, len(g) as n, row_number() over () as i from t),
d as (select doc_id, license, 2 * len(list_intersect(n.g, z.g)) / (m + n) as dice from n join z
  on m >= n * {shared!r} - 1e-9 and m <= n * {most!r} + 1e-9),
f as materialized (select row_number() over () as r, doc_id, {grams("text")} from documents where text is not null),
seed as materialized (select i, x, list_position(any_value(b), x) - 1 as rank, any_value(n) as n from
  (select i, b, n, unnest(list_distinct(b)) as x from z where n >= {window_from}) group by i, x
  qualify row_number() over (partition by i order by rank) <= floor(any_value(n) * {1 - shared!r} + 1e-9) + 1),
k as materialized (select r, doc_id, i, license, f.b, z.b as tb, z.g as tg, n from f join z
  on n >= {window_from} and len(list_intersect(f.g, z.g)) >= n * {shared!r} - 1e-9),
q as (select r, i, unnest(b) as x, generate_subscripts(b, 1) - 1 as p from k),
s as (select distinct r, q.i, greatest(0, p - rank) as start from q join seed on seed.i = q.i and seed.x = q.x),
e as (select doc_id, license, list_distinct(b[start + 1:start + len(tb)]) as part, tg, n
  from s join k on k.r = s.r and k.i = s.i),
o as (select doc_id, license, dice from d union all
  select doc_id, license, 2 * len(list_intersect(part, tg)) / (len(part) + n) from e)
select doc_id, license, max(dice) as dice, count(*) as n_units from o where dice >= {least} group by all"""
