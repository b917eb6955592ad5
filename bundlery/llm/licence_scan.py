"""Licence scan by Dice coefficient over word bigrams, in DataFrame operations.

Normalised texts (lower-case letters and digits) are compared with templates.
A statement is a window of as many words as the template has, or fewer where the
text ends, that begins with one of the template's bigrams; line breaks and signs
play no part, so wrapped notices and notices inside a line are found alike.  Its
Dice coefficient counts bigrams with their copies.  Bounds cut the work before
any window is compared, and none loses a match:

* anchors: of each template, words are chosen so that the bigrams without any
  of them are too few for the threshold; a text without an anchor goes no further;
* sizes: ``Dice >= t`` needs ``t / (2 - t) <= |a| / |b|``, for a text as a whole
  and for the bigrams that a window shares;
* an inverted index of the templates' bigrams, a broadcast of fixed size, leaves
  of each text only what it shares with a template;
* cells: a template's windows begin in one stretch of its own length and end in
  the next, so windows are compared within two cells, however long the text.

Windows of several templates can overlap: the best one stays, so that a
statement counts for the licence that it is closest to.
"""

from __future__ import annotations

import re
from collections import Counter

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

#: Licence statements that are looked for, a template for each paragraph (fixed values).
TEMPLATES = (
    ("apache-2.0", "Licensed under the Apache License, Version 2.0."),
    ("mit", "Released under the MIT License."),
    ("mit", "This project is licensed under the MIT License."),
    ("gpl-3.0", "This work is licensed under the GNU General Public License, version 3."),
    ("gpl-2.0", "This work is licensed under the GNU General Public License, version 2."),
    ("lgpl-3.0", "This work is licensed under the GNU Lesser General Public License, version 3."),
    ("agpl-3.0", "This work is licensed under the GNU Affero General Public License, version 3."),
    ("bsd-3-clause", "Released under the BSD 3-Clause License."),
    ("bsd-2-clause", "Released under the BSD 2-Clause License."),
    ("mpl-2.0", "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0."),
    ("mpl-2.0", "Licensed under the Mozilla Public License, Version 2.0."),
    ("epl-2.0", "This program and the accompanying materials are made available under the terms of the Eclipse Public License 2.0."),
    ("cc-by-nc-4.0", "Licensed under CC BY-NC 4.0."),
    ("cc-by-sa-4.0", "Licensed under CC BY-SA 4.0."),
    ("cc-by-nd-4.0", "Licensed under CC BY-ND 4.0."),
    ("cc-by-4.0", "Licensed under CC BY 4.0."),
    ("cc-by-4.0", "This work is licensed under a Creative Commons Attribution 4.0 International License."),
    ("cc-by-sa-4.0", "This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License."),
    ("cc-by-nc-4.0", "This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International License."),
    ("cc-by-nd-4.0", "This work is licensed under a Creative Commons Attribution-NoDerivatives 4.0 International License."),
    ("cc0-1.0", "Released under CC0 1.0 Universal, no rights reserved."),
    ("all-rights-reserved", "All rights reserved."),
    # headers of files
    ("apache-2.0", 'Licensed under the Apache License, Version 2.0 (the "License"); you may not use this file except in compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0'),
    ("apache-2.0", 'Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an "AS IS" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. See the License for the specific language governing permissions and limitations under the License.'),
    ("gpl-3.0", "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version."),
    ("gpl-2.0", "This program is free software; you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation; either version 2 of the License, or (at your option) any later version."),
    ("lgpl-2.1", "This library is free software; you can redistribute it and/or modify it under the terms of the GNU Lesser General Public License as published by the Free Software Foundation; either version 2.1 of the License, or (at your option) any later version."),
    ("agpl-3.0", "This program is free software: you can redistribute it and/or modify it under the terms of the GNU Affero General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version."),
    ("gpl", "This program is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE. See the GNU General Public License for more details."),
    # paragraphs of full texts
    ("mit", 'Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the "Software"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions:'),
    ("mit", "The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software."),
    ("mit", 'THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE.'),
    ("bsd", "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met:"),
    ("bsd", "Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer."),
    ("bsd", "Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution."),
    ("bsd-3-clause", "Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission."),
    ("isc", "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies."),
    ("zlib", "Permission is granted to anyone to use this software for any purpose, including commercial applications, and to alter it and redistribute it freely, subject to the following restrictions:"),
    ("bsl-1.0", 'Permission is hereby granted, free of charge, to any person or organization obtaining a copy of the software and accompanying documentation covered by this license (the "Software") to use, reproduce, display, distribute, execute, and transmit the Software, and to prepare derivative works of the Software, and to permit third-parties to whom the Software is furnished to do so, all subject to the following:'),
    ("unlicense", "This is free and unencumbered software released into the public domain."),
    ("unlicense", "Anyone is free to copy, modify, publish, use, compile, sell, or distribute this software, either in source code form or as a compiled binary, for any purpose, commercial or non-commercial, and by any means."),
    ("gpl-3.0", "The GNU General Public License is a free, copyleft license for software and other kinds of works."),
    ("lgpl-3.0", "This version of the GNU Lesser General Public License incorporates the terms and conditions of version 3 of the GNU General Public License, supplemented by the additional permissions listed below."),
    ("agpl-3.0", "The GNU Affero General Public License is a free, copyleft license for software and other kinds of works, specifically designed to ensure cooperation with the community in the case of network server software."),
)
THRESHOLD = 0.8
#: Words that are too frequent in other text to be anchors where there is a choice (fixed values).
COMMON = frozenset("a above accompanying all an and any anyone are as at available be below but by can code commercial conditions contributors copies copy distribute distributed either even express following for form forms free from general granted hereby implied in including international is it its kind law made materials may means met modify more must name names no not notice of on or other out particular permissions person program provided public purpose reproduce rights see shall source specific subject terms that the this to under use used useful version will with without work works writing you your".split())


def normal_words(statement: str) -> list[str]:
    return re.sub("[^a-z0-9]+", " ", statement.lower()).split()


def _bigrams(words: list[str]) -> list[str]:
    return [f"{a} {b}" for a, b in zip(words, words[1:])]


def anchors(threshold: float) -> list[str]:
    """Words of which every window that matches some template has one."""
    bigrams = [_bigrams(normal_words(t)) for _, t in TEMPLATES]
    often = Counter(w for b in bigrams for w in {w for x in b for w in x.split()})
    chosen: set[str] = set()
    for b in sorted(bigrams, key=len):
        while sum(not chosen & set(x.split()) for x in b) >= threshold / (2 - threshold) * len(b):
            free = {w for x in b for w in x.split()} - chosen
            chosen.add(max(free, key=lambda w: (w not in COMMON and len(w) > 1, len(w) > 4, often[w], len(w), w)))
    return sorted(chosen)


def _index(threshold: float) -> list[tuple]:
    """``template, licence, bigram, copies, size, least``: the templates' bigrams."""
    out = []
    for i, (name, text) in enumerate(TEMPLATES):
        grams = _bigrams(normal_words(text))
        out += [(i, name, g, c, len(grams), threshold / (2 - threshold) * len(grams) - 1e-9) for g, c in sorted(Counter(grams).items())]
    return out


def _shared(inside: Column) -> Column:
    """Bigrams that a window shares with its template, with their copies."""
    kinds = F.array_distinct(F.transform(inside, lambda y: F.struct(y["g"].alias("g"), y["copies"].alias("copies"))))
    return F.aggregate(kinds, F.lit(0), lambda n, k: n + F.least(k["copies"], F.size(F.filter(inside, lambda y: y["g"] == k["g"]))))


def scan_licences(docs: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """``doc_id, licence, n_statements, best_dice`` of each document and licence.

    A window counts where its Dice coefficient is ``threshold`` or more.  Of
    windows with common words the best stays: the one of the highest
    coefficient, then of the longer template, then of the earlier one, then the
    first in the text.  Null texts, and texts of fewer than two words, match
    nothing.  Rows that share a doc_id are counted together.
    """
    spark = docs.sparkSession
    need = anchors(threshold)
    templates = F.broadcast(spark.createDataFrame(_index(threshold), "template int, licence string, g string, copies int, size int, least double"))
    lowered = F.lower(F.col("text").cast("string"))
    words = F.filter(F.split(F.regexp_replace(lowered, "[^a-z0-9]+", " "), " "), lambda w: w != "")
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), words.alias("w"), F.monotonically_increasing_id().alias("row"))
    texts = texts.where(F.arrays_overlap("w", F.array(*map(F.lit, need))))
    pairs = F.filter(F.zip_with("w", F.slice("w", 2, 1 << 30), lambda a, b: F.concat(a, F.lit(" "), b)), lambda g: g.isNotNull())
    grams = texts.select("row", "doc_id", F.size("w").alias("n"), F.posexplode(pairs).alias("p", "g")).withColumn("n", F.col("n") - 1)
    hits = grams.join(templates, "g").where(F.col("n") >= F.col("least")).withColumn("at", F.floor(F.col("p") / F.col("size")).cast("int"))
    # a hit begins windows of its own cell, and may end those of the cell before
    parts = F.filter(F.array(F.struct(F.col("at").alias("cell"), F.lit(True).alias("own")), F.struct((F.col("at") - 1).alias("cell"), F.lit(False).alias("own"))), lambda x: x["cell"] >= 0)
    dealt = hits.withColumn("part", F.explode(parts)).select("*", F.col("part.cell").alias("cell"), F.col("part.own").alias("own"))
    cells = dealt.groupBy("row", "doc_id", "n", "template", "licence", "size", "least", "cell").agg(F.sort_array(F.collect_list(F.struct("p", "g", "copies", "own"))).alias("hits"))
    cells = cells.where(F.size("hits") >= F.col("least"))
    starts = F.transform(
        F.filter("hits", lambda x: x["own"]),
        lambda x: F.struct(x["p"].alias("lo"), F.filter("hits", lambda y: (y["p"] >= x["p"]) & (y["p"] < x["p"] + F.col("size"))).alias("inside")),
    )
    windows = F.transform(F.filter(starts, lambda x: F.size(x["inside"]) >= F.col("least")), lambda x: F.struct(x["lo"].alias("lo"), _shared(x["inside"]).alias("both")))
    found = cells.select("row", "doc_id", "template", "licence", "size", "n", F.explode(windows).alias("x"))
    length = F.least("size", F.col("n") - F.col("x.lo"))
    found = found.select("row", "doc_id", "template", "licence", "size", F.col("x.lo").alias("lo"), (F.col("x.lo") + length).alias("hi"), (F.lit(2.0) * F.col("x.both") / (F.col("size") + length)).alias("dice"))
    found = found.where(F.col("dice") >= threshold - 1e-12)
    # windows that reach into each other are judged together, apart from all others
    before = W.partitionBy("row").orderBy("lo", "hi").rowsBetween(W.unboundedPreceding, -1)
    fresh = found.withColumn("new", F.when(F.col("lo") <= F.max("hi").over(before), 0).otherwise(1))
    chains = fresh.withColumn("chain", F.sum("new").over(W.partitionBy("row").orderBy("lo", "hi").rowsBetween(W.unboundedPreceding, 0)))
    item = F.struct((-F.col("dice")).alias("order"), (-F.col("size")).alias("long"), "template", "lo", "hi", "licence")
    best = F.aggregate(
        F.sort_array(F.collect_list(item)),
        F.array().cast("array<struct<order:double,long:int,template:int,lo:int,hi:int,licence:string>>"),
        lambda held, x: F.when(F.exists(held, lambda y: (x["lo"] <= y["hi"]) & (y["lo"] <= x["hi"])), held).otherwise(F.concat(held, F.array(x))),
    )
    kept = chains.groupBy("row", "doc_id", "chain").agg(best.alias("kept")).select("doc_id", F.explode("kept").alias("x"))
    return kept.groupBy("doc_id", F.col("x.licence").alias("licence")).agg(F.count("*").alias("n_statements"), F.round(F.max(-F.col("x.order")), 6).alias("best_dice"))


def _quoted(s: str) -> str:
    return "'" + s.replace("'", "''") + "'"


def oracle(threshold: float = THRESHOLD) -> str:
    """The scan as DuckDB SQL, over all windows of all texts, without anchors or cells."""
    rows = ", ".join(f"({i}, {_quoted(name)}, {_quoted(t)})" for i, (name, t) in enumerate(TEMPLATES))

    def words(source: str) -> str:
        return f"list_filter(string_split(regexp_replace(lower({source}), '[^a-z0-9]+', ' ', 'g'), ' '), lambda w: w <> '')"

    return f"""
WITH RECURSIVE bodies AS (SELECT template, licence, {words("body")} AS w FROM (VALUES {rows}) v(template, licence, body)),
ngrams AS (SELECT template, licence, len(w) - 1 AS size, unnest(list_transform(range(1, len(w)), lambda i: w[i] || ' ' || w[i + 1])) AS g FROM bodies),
templates AS (SELECT template, licence, size, g, count(*) AS copies FROM ngrams GROUP BY ALL),
texts AS (SELECT row_number() OVER () AS r, doc_id, {words("text")} AS w FROM documents),
grams AS (SELECT r, doc_id, len(w) - 1 AS n, unnest(range(0, len(w) - 1)) AS p, unnest(list_transform(range(1, len(w)), lambda i: w[i] || ' ' || w[i + 1])) AS g FROM texts WHERE len(w) > 1),
hits AS (SELECT r, doc_id, n, p, template, licence, size, g, copies FROM grams JOIN templates USING (g)),
likely AS (SELECT *, count(*) OVER (PARTITION BY r, template ORDER BY p RANGE BETWEEN CURRENT ROW AND size - 1 FOLLOWING) AS reach FROM hits),
counted AS (SELECT s.r, s.doc_id, s.n, s.template, s.licence, s.size, s.p, y.g, least(any_value(y.copies), count(*)) AS same
            FROM likely s JOIN hits y ON y.r = s.r AND y.template = s.template AND y.p BETWEEN s.p AND s.p + s.size - 1
            WHERE s.reach >= {threshold / (2 - threshold)} * s.size - 1e-9 GROUP BY ALL),
windows AS (SELECT r, doc_id, template, licence, size, p AS lo, p + least(size, n - p) AS hi, 2.0 * sum(same) / (size + least(size, n - p)) AS dice
            FROM (SELECT * FROM counted) GROUP BY r, doc_id, template, licence, size, p, n),
listed AS (SELECT r, doc_id, list({{'licence': licence, 'lo': lo, 'hi': hi, 'dice': dice}} ORDER BY dice DESC, size DESC, template, lo) AS ws FROM windows WHERE dice >= {threshold} - 1e-12 GROUP BY r, doc_id),
walk AS (SELECT r, doc_id, ws, 1 AS i, ws[1:1] AS kept FROM listed
         UNION ALL SELECT r, doc_id, ws, i + 1, CASE WHEN len(list_filter(kept, lambda y: y.lo <= ws[i + 1].hi AND ws[i + 1].lo <= y.hi)) = 0 THEN list_append(kept, ws[i + 1]) ELSE kept END FROM walk WHERE i < len(ws)),
done AS (SELECT doc_id, unnest(kept) AS x FROM walk WHERE i = len(ws))
SELECT doc_id, x.licence AS licence, count(*) AS n_statements, round(max(x.dice), 6) AS best_dice FROM done GROUP BY 1, 2"""
