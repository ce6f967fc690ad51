"""Licence scan: units of text compared to licence templates by Dice's coefficient over word bigrams.

A unit is a line, a paragraph of several lines, or a whole text of several paragraphs; for a licence that none of a
document's units has, also any run of several lines, so that licences inside longer texts are found. Normalised text has A-Z lowered
and every run of other characters than a-z and 0-9 as one space. A coefficient of t asks for sizes that differ by a
factor of (2 - t) / t at most, so units are dropped by size for all templates, and pairs for each, before any bigram is
compared. DataFrame functions only; the bigrams that meet no template's are gone before the first shuffle.
"""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from clipflow.llm.common import materialise

THRESHOLD = 0.8
MOST_BIGRAMS = 100_000  # of all templates

#: Public licence texts and the notices by which works refer to them.
TEMPLATES = {
    "MIT": "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions: The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software. THE SOFTWARE IS PROVIDED \"AS IS\", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE.",
    "ISC": "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies. THE SOFTWARE IS PROVIDED \"AS IS\" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE.",
    "BSD-2-Clause": "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution. THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS \"AS IS\" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE.",
    "BSD-2-Clause-conditions": "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution.",
    "Apache-2.0-header": "Licensed under the Apache License, Version 2.0 (the \"License\"); you may not use this file except in compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0 Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an \"AS IS\" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. See the License for the specific language governing permissions and limitations under the License.",
    "GPL-3.0-header": "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version. This program is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE. See the GNU General Public License for more details.",
    "Unlicense": "This is free and unencumbered software released into the public domain. Anyone is free to copy, modify, publish, use, compile, sell, or distribute this software, either in source code form or as a compiled binary, for any purpose, commercial or non-commercial, and by any means. In jurisdictions that recognize copyright laws, the author or authors of this software dedicate any and all copyright interest in the software to the public domain. We make this dedication for the benefit of the public at large and to the detriment of our heirs and successors. We intend this dedication to be an overt act of relinquishment in perpetuity of all present and future rights to this software under copyright law. THE SOFTWARE IS PROVIDED \"AS IS\", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE. For more information, please refer to http://unlicense.org/",
    "Unlicense-header": "This is free and unencumbered software released into the public domain. Anyone is free to copy, modify, publish, use, compile, sell, or distribute this software, either in source code form or as a compiled binary, for any purpose, commercial or non-commercial, and by any means.",
    "Apache-2.0-notice": "Licensed under the Apache License, Version 2.0.",
    "MIT-notice": "Released under the MIT License.",
    "GPL-3.0-notice": "This work is licensed under the GNU General Public License, version 3.",
    "CC-BY-NC-4.0-notice": "Licensed under CC BY-NC 4.0.",
    "CC-BY-4.0-notice": "This work is licensed under a Creative Commons Attribution 4.0 International License.",
    "CC-BY-SA-4.0-notice": "This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License.",
    "All-rights-reserved": "All rights reserved.",
}

_NORMAL = "trim(regexp_replace(translate({}, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^a-z0-9]+', ' '))"
_BIGRAMS = "transform(sequence(1, size({0}) - 1), i -> concat(element_at({0}, i), ' ', element_at({0}, i + 1)))"


def template_bigrams(spark: SparkSession, templates: dict[str, str] = TEMPLATES) -> DataFrame:
    """licence, bigram, c (its count), m (bigrams in the template): as many rows as the templates have bigrams."""
    values = ", ".join("('{}', '{}')".format(n, t.replace("'", "\\'")) for n, t in templates.items())
    rows = spark.sql(f"SELECT licence, split({_NORMAL.format('body')}, ' ') AS w FROM VALUES {values} AS t(licence, body)").where("size(w) > 1")
    rows = rows.select("licence", F.explode(F.expr(_BIGRAMS.format("w"))).alias("bigram"), F.expr("size(w) - 1").alias("m"))
    return rows.groupBy("licence", "m", "bigram").agg(F.count(F.lit(1)).alias("c"))


def units(docs: DataFrame, low: int, high: int, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, unit (number within its kind, after its kind), w (words): units of ``low`` to ``high`` bigrams."""
    text = F.coalesce(F.col(text_col), F.lit(""))
    rows = docs.select(F.col(id_col).alias("doc_id"), text.alias("t"))
    whole = "filter(array(t), x -> x RLIKE '\\\\n[ \\\\t\\\\r]*\\\\n')"
    paragraphs = "filter(split(t, '\\\\n[ \\\\t\\\\r]*\\\\n'), x -> contains(btrim(x, ' \n\t\r'), '\\n'))"
    kinds = f"concat(transform(split(t, '\\n'), x -> struct('line' AS kind, x AS body)), transform({paragraphs}, x -> struct('paragraph' AS kind, x AS body)), transform({whole}, x -> struct('text' AS kind, x AS body)))"
    cut = rows.select("doc_id", F.posexplode(F.expr(kinds)).alias("unit", "u")).select("doc_id", "unit", F.expr(f"split({_NORMAL.format('u.body')}, ' ')").alias("w"))
    return cut.where(F.expr("size(w) - 1").between(low, high))


def _literal(grams: set[str]) -> str:
    return "array(" + ", ".join(f"'{g}'" for g in sorted(grams)) + ")"


def _may_hold(words: str, templates: dict[str, str], threshold: float) -> str:
    """A condition that holds for all words with a unit that reaches the threshold: enough distinct bigrams of a template.

    Dice of t asks for t / (2 - t) of a template's bigrams; repeats of one count as if all were there.
    """
    asked, every = ["false"], set()
    for text in templates.values():
        w = _words(text)
        grams = {f"{a} {b}" for a, b in zip(w, w[1:])}
        if grams:
            need = max(1, math.ceil((len(w) - 1) * threshold / (2 - threshold) - (len(w) - 1 - len(grams)) - 1e-9))
            asked.append(f"size(array_intersect(h, {_literal(grams)})) >= {need}")
            every |= grams
    hits = f"array_intersect({_BIGRAMS.format('z')}, {_literal(every)})"
    # the words are bound once: written out in the bigrams' function they would be split anew for each
    return f"exists(array({words}), z -> size(z) > 1 AND exists(array({hits}), h -> {' OR '.join(asked)}))"


def runs(docs: DataFrame, low: int, high: int, templates: dict[str, str], threshold: float, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, unit (below 0), w: runs of two or more lines with words, of ``low`` to ``high`` bigrams, that may match."""
    lines = f"filter(transform(split({text_col}, '\\n'), x -> split({_NORMAL.format('x')}, ' ')), x -> x[0] <> '')"
    rows = docs.select(F.col(id_col).alias("doc_id"), F.expr(lines).alias("l")).where("size(l) > 1")
    starts = rows.select("doc_id", "l", F.explode(F.expr("sequence(1, size(l) - 1)")).alias("i")).select("doc_id", "i", F.expr(f"slice(l, i, {high + 1})").alias("l"))
    starts = starts.withColumn("v", F.expr(f"slice(flatten(l), 1, {high + 1})")).where(_may_hold("v", templates, threshold))
    cut = starts.select("doc_id", "i", "l", F.explode(F.expr("sequence(2, size(l))")).alias("j"))
    cut = cut.where(F.expr("aggregate(slice(l, 1, j), -1, (a, x) -> a + size(x))").between(low, high))
    return cut.select("doc_id", F.expr(f"-(i * {high + 2} + j)").alias("unit"), F.expr("flatten(slice(l, 1, j))").alias("w"))


def matches(docs: DataFrame, templates: dict[str, str] = TEMPLATES, threshold: float = THRESHOLD, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, unit, licence, dice: all pairs of a unit and a template that reach the threshold.

    Null, empty and one-word texts match nothing; rows of one id are one document, null ids included. Templates beyond
    ``MOST_BIGRAMS`` in all are refused, as their bigrams are broadcast.
    """
    spark = docs.sparkSession
    if sum(len(_words(t)) for t in templates.values()) > MOST_BIGRAMS:
        raise ValueError(f"templates of more than {MOST_BIGRAMS} words")
    known = template_bigrams(spark, templates)
    ratio = (2 - threshold) / threshold
    sizes = [len(_words(t)) - 1 for t in templates.values()]
    low, high = max(1, int(min(sizes) / ratio)), int(max(sizes) * ratio) + 1
    split = docs.select(F.col(id_col).alias("doc_id"), F.coalesce(F.col(text_col), F.lit("")).alias("t")).withColumn("_words", F.expr(f"split({_NORMAL.format('t')}, ' ')"))
    some = materialise(split.where(_may_hold("_words", templates, threshold)).select("doc_id", "t"), "licence-candidates")
    cut = units(some, low, high, "doc_id", "t").unionByName(runs(some, low, high, templates, threshold, "doc_id", "t"))
    grams = cut.select("doc_id", "unit", F.expr("size(w) - 1").alias("n"), F.explode(F.expr(_BIGRAMS.format("w"))).alias("bigram"))
    near = (F.col("n") <= F.col("m") * ratio + 1e-9) & (F.col("m") <= F.col("n") * ratio + 1e-9)
    met = grams.join(F.broadcast(known), "bigram").where(near)  # the templates' bigrams: fixed by this module or the caller's table
    shared = met.groupBy("doc_id", "unit", "n", "licence", "m", "bigram", "c").agg(F.count(F.lit(1)).alias("k"))
    dice = shared.groupBy("doc_id", "unit", "n", "licence", "m").agg(F.sum(F.least("k", "c")).alias("s"))
    reach = dice.select("doc_id", "unit", "licence", (2 * F.col("s") / (F.col("n") + F.col("m"))).alias("dice")).where(F.col("dice") >= threshold)
    # a run counts where no unit has its licence, and of a document's runs the best; of equals the first
    of = Window.partitionBy("doc_id", "licence")
    reach = reach.withColumn("_units", F.max("unit").over(of)).withColumn("_best", F.row_number().over(of.orderBy(F.desc("dice"), F.desc("unit"))))
    return reach.where("unit >= 0 OR (_units < 0 AND _best = 1)").drop("_units", "_best")


def _words(text: str) -> list[str]:
    lowered = "".join(c.lower() if c.isascii() else " " for c in text)
    return "".join(c if c.isalnum() else " " for c in lowered).split()


def scan(docs: DataFrame, templates: dict[str, str] = TEMPLATES, threshold: float = THRESHOLD, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: doc_id, licence (of the best match; ties: the first name; null: none), dice, n_units.

    ``n_units`` counts units with a match. Null, empty and one-word texts match nothing. Rows that repeat an id, or have
    none, are judged by their own texts and returned each. An empty table gives no rows. Other columns are not read.
    """
    key = F.struct(F.col(id_col).alias("id"), F.xxhash64(F.coalesce(F.col(text_col), F.lit(""))).alias("text"))
    rows = docs.select(F.col(id_col).alias("doc_id"), key.alias("key"), F.col(text_col).alias("text"))
    best = matches(rows, templates, threshold, "key", "text").groupBy(F.col("doc_id").alias("key")).agg(
        F.min(F.struct((-F.col("dice")).alias("d"), "licence")).alias("b"), F.count_distinct("unit").alias("n_units")
    )
    best = best.select(F.col("key.id").alias("_id"), F.col("key.text").alias("_text"), "b", "n_units")
    ids = rows.select("doc_id", "key")
    return ids.join(best, F.col("key.id").eqNullSafe(F.col("_id")) & (F.col("key.text") == F.col("_text")), "left").select(
        "doc_id", F.col("b.licence").alias("licence"), F.round(-F.col("b.d"), 6).alias("dice"), F.coalesce("n_units", F.lit(0)).alias("n_units")
    )
