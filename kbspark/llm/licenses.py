"""License scans: texts against license templates by the Dice coefficient of word bigrams. DataFrame only.

Units are a document's lines, its paragraphs (parted by blank lines) and the whole text. A unit is normalised
(case, punctuation, copyright lines), its distinct word bigrams are taken, and it is compared with templates
whose number of bigrams lets the coefficient reach the threshold: 2 * min(a, b) / (a + b) >= t bounds a between
b * t / (2 - t) and b * (2 - t) / t. A unit that reaches it has one of the template's few necessary bigrams (the rarest
among templates), so templates are filed under these with their bounds, a few numbers a row: units without any
such bigram are left out first, the others meet the templates filed under theirs if their size is within bounds, and
only then sets are compared.

Defined cases: a null or empty text has no units and no license; units of one word have no bigram; ties go to
the larger template, then to the first by name; a document with several licenses reports its best and how
many units matched; repeated rows are reported as often as they occur.
"""

from __future__ import annotations

from fractions import Fraction
from math import ceil, floor

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from kbspark.llm.common import cut, if_few

# Notices by which texts state their license, and short licenses' full texts, by SPDX name.
TEMPLATES = [
    ("MIT", "Released under the MIT License."),
    ("MIT", "Licensed under the MIT License."),
    ("MIT", "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions: The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software."),
    ("Apache-2.0", "Licensed under the Apache License, Version 2.0."),
    ("Apache-2.0", "Licensed under the Apache License, Version 2.0 (the \"License\"); you may not use this file except in compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0"),
    ("GPL-3.0", "This work is licensed under the GNU General Public License, version 3."),
    ("GPL-3.0", "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version."),
    ("GPL-2.0", "This work is licensed under the GNU General Public License, version 2."),
    ("LGPL-3.0", "This work is licensed under the GNU Lesser General Public License, version 3."),
    ("CC-BY-NC-4.0", "Licensed under CC BY-NC 4.0."),
    ("CC-BY-4.0", "Licensed under CC BY 4.0."),
    ("CC-BY-SA-4.0", "Licensed under CC BY-SA 4.0."),
    ("CC-BY-4.0", "This work is licensed under a Creative Commons Attribution 4.0 International License."),
    ("BSD-3-Clause", "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer."),
    ("ISC", "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies."),
    ("MPL-2.0", "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can obtain one at http://mozilla.org/MPL/2.0/."),
]


WARRANTY = "OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE."
BSD_HEAD = "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met:"
BSD_1 = "1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer."
BSD_2 = "2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution."
BSD_3 = "3. Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission."
BSD_TAIL = "THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS \"AS IS\" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE."
ISC_GRANT = "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted"
ISC_TAIL = "THE SOFTWARE IS PROVIDED \"AS IS\" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE."
MIT_GRANT = TEMPLATES[2][1].split(" The above copyright")[0]
MIT_NOTICE = "The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software."
MIT_TAIL = "THE SOFTWARE IS PROVIDED \"AS IS\", WITHOUT WARRANTY OF ANY KIND, EXPRESS " + WARRANTY
#: Whole licenses, by paragraphs, as their files part them.
WHOLE = {
    "MIT": ["MIT License", MIT_GRANT, MIT_NOTICE, MIT_TAIL],
    "ISC": [ISC_GRANT + ", provided that the above copyright notice and this permission notice appear in all copies.", ISC_TAIL],
    "0BSD": [ISC_GRANT + ".", ISC_TAIL],
    "BSD-2-Clause": [BSD_HEAD, BSD_1, BSD_2, BSD_TAIL],
    "BSD-3-Clause": [BSD_HEAD, BSD_1, BSD_2, BSD_3, BSD_TAIL],
}
# A whole text is a template, and so is each of its paragraphs that no other license here has.
TEMPLATES += [(name, "\n\n".join(parts)) for name, parts in WHOLE.items()]
TEMPLATES += [(name, part) for name, parts in WHOLE.items() for part in parts if sum(part in other for other in WHOLE.values()) == 1 and len(part.split()) > 5]


def read_templates(spark: SparkSession, path: str) -> list[tuple[str, str]]:
    """Templates from a folder of text files, named by license, such as a published license list: a parameter for scan."""
    name = F.regexp_extract(F.input_file_name(), r"([^/]+?)(?:\.txt)?$", 1)
    return [(r[0], r[1]) for r in spark.read.text(path, wholetext=True).select(name, "value").orderBy(name).collect()]


def normal_words(text: Column) -> Column:
    bare = F.regexp_replace(F.lower(text), r"(?m)^\s*(?:copyright|\(c\)|©).*$", " ")
    return F.array_remove(F.split(F.regexp_replace(bare, r"[^\p{L}\p{N}]+", " "), " "), "")


def bigrams(words: Column) -> Column:
    n = F.size(words)
    return F.when(n > 1, F.array_distinct(F.transform(F.sequence(F.lit(1), n - 1), lambda i: F.concat_ws(" ", F.element_at(words, i), F.element_at(words, i + 1))))).otherwise(F.array().cast("array<string>"))


FILED = 1_000_000  # filed bigrams that are broadcast at most; beyond, the join is a shuffle
BYTES = 16 << 20  # of templates' bigrams that are broadcast at most


def templates_frame(spark: SparkSession, templates: list[tuple[str, str]] | None = None) -> DataFrame:
    rows = [(i, name, text) for i, (name, text) in enumerate(templates or TEMPLATES)]
    return spark.createDataFrame(rows, "template int, license string, body string")


def bounds(b: int, t: float) -> tuple[int, int]:
    """The least and the most bigrams of a unit that can reach t; in fractions, so that units exactly at t stay."""
    exact = Fraction(str(t))
    return max(1, ceil(b * exact / (2 - exact))), floor(b * (2 - exact) / exact)


def scan(docs: DataFrame, templates: list[tuple[str, str]] | None = None, threshold: float = 0.8, literals: int = 5_000) -> DataFrame:
    """doc_id, license, dice (6 places), unit (line, paragraph or text), unit_no and n_matches of all documents.

    Up to `literals` necessary bigrams are looked for inside the scan of the texts; more by a join.
    """
    spark = docs.sparkSession
    made = templates_frame(spark, templates).withColumn("ws", normal_words(F.col("body"))).select("template", "license", bigrams(F.col("ws")).alias("grams"))
    known = made.collect()  # the templates themselves, a list given in code
    # How many templates have a bigram: the rarer ones come first in a template's prefix.
    often: dict[str, int] = {}
    for r in known:
        for g in r["grams"]:
            often[g] = often.get(g, 0) + 1
    filed = []
    for r in known:
        b = len(r["grams"])
        low, high = bounds(b, threshold)
        # At least this many of the template's bigrams are in any unit that reaches the threshold.
        least = ceil(Fraction(str(threshold)) * (low + b) / 2)
        filed += [(g, r["template"], low, high) for g in sorted(r["grams"], key=lambda g: (often[g], g))[: b - least + 1]]
    postings = spark.createDataFrame(filed, "gram string, template int, low int, high int")
    sets = spark.createDataFrame([(r["template"], r["license"], r["grams"]) for r in known], "template int, license string, tgrams array<string>")
    needed, shortest = sorted({f[0] for f in filed}), min((f[2] for f in filed), default=1)

    text = F.coalesce(F.col("text"), F.lit(""))
    part = lambda kind, xs: F.transform(xs, lambda x, i: F.struct(F.lit(kind).alias("unit"), i.alias("unit_no"), normal_words(x).alias("ws")))
    lines, paragraphs = F.split(text, "\n"), F.split(text, r"\n[ \t]*\n")
    several = lambda xs: F.when(F.size(xs) > 1, xs).otherwise(F.array().cast("array<string>"))
    units = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64(text).alias("key"), F.inline(F.concat(part("line", several(lines)), part("paragraph", several(paragraphs)), part("text", F.array(text)))))
    worded = units.where(F.size("ws") > shortest)
    # Exploding an array of one keeps the filter below from being pushed under the bigrams, which would build them anew for each word.
    grams = worded.select("doc_id", "key", "unit", "unit_no", F.explode(F.array(bigrams(F.col("ws")))).alias("grams"))
    unit = ["doc_id", "key", "unit", "unit_no"]
    filed_under = lambda df: df.select(*unit, F.size("grams").alias("n"), F.explode("grams").alias("gram")).join(if_few(postings, FILED), "gram").where(F.col("n").between(F.col("low"), F.col("high")))
    names = dict(zip(unit, ("d", "k", "u", "o"), strict=True))
    same_unit = F.col("doc_id").eqNullSafe(F.col("d")) & (F.col("key") == F.col("k")) & (F.col("unit") == F.col("u")) & (F.col("unit_no") == F.col("o"))
    size = sum(len(g) for r in known for g in r["grams"])
    by_size = [(n, t) for t, (low, high) in {f[1]: f[2:] for f in filed}.items() for n in range(low, high + 1)]
    if len(needed) <= literals and len(by_size) <= FILED and size <= BYTES:
        # Few templates: units with a necessary bigram meet all templates of their size at once, in the scan of the texts.
        near = grams.where(F.arrays_overlap("grams", F.array(*map(F.lit, needed)).cast("array<string>"))).withColumn("n", F.size("grams"))
        met = near.join(F.broadcast(spark.createDataFrame(by_size, "n int, template int")), "n")
    else:  # the units that meet a filed template are found first, then read again
        pairs = cut(filed_under(grams).select(*unit, "template").distinct().withColumnsRenamed(names))
        met = grams.join(if_few(pairs, FILED), same_unit).select(*unit, "grams", "template")
    same = F.size(F.array_intersect("grams", "tgrams"))
    scored = met.join(F.broadcast(sets) if size <= BYTES else sets, "template").withColumn("dice", F.round(2 * same / (F.size("grams") + F.size("tgrams")), 6)).where(F.col("dice") >= threshold)
    best = F.max_by(F.struct("license", "dice", "unit", "unit_no"), F.struct("dice", F.size("tgrams"), -F.col("template"), -F.col("unit_no"), "unit"))
    found = scored.groupBy("doc_id", "key").agg(best.alias("best"), F.count_distinct("unit", "unit_no").alias("n_matches"))
    found = found.select(F.col("doc_id").alias("d"), F.col("key").alias("k"), "best", "n_matches")
    base = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64(text).alias("key"))
    out = base.join(found, F.col("doc_id").eqNullSafe(F.col("d")) & (F.col("key") == F.col("k")), "left")
    return out.select("doc_id", F.col("best.license").alias("license"), F.col("best.dice").alias("dice"), F.col("best.unit").alias("unit"), F.col("best.unit_no").alias("unit_no"), F.coalesce("n_matches", F.lit(0)).cast("long").alias("n_matches"))
