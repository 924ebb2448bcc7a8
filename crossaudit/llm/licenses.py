"""Licence scan: TF-IDF cosine of headers and licence files to templates, and inheritance from the nearest ancestor directory
(native DataFrame operations only).

Every line of a text and every block of lines between blank ones (a wrapped header, a paragraph of a licence file) is a sparse TF-IDF vector over
its words, with document frequencies counted over all files; the best template at or above a cosine threshold names the file's
licence. Whole texts are read and nothing gates them but an exact bound: a vector's norm is at least what its template words and one
for each other word make of it, so only those whose cosine may reach the threshold get their exact norm. A licence file speaks for its
directory: by its name, or because at least half of its words are words of templates in lines or blocks that match. Files without a licence of their own take
that of the nearest ancestor directory that has one. Directories are resolved once each, by joining their ancestor paths, before files look theirs up.
"""

from __future__ import annotations

import re
from collections import Counter

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from crossaudit.functions.storage import materialize
from crossaudit.llm.places import only_needed
from crossaudit.llm.words import free_names

NEAR = 0.6
NAMED = r"(?i)(^|/)(un)?(licen[cs]e|copying|copyright|notice)[^/]*$"
WORD = "[a-z0-9]+"
BLANK = "\n[ \t\r]*\n"
#: Words without weight.
STOP = ("a", "an", "and", "any", "are", "as", "at", "be", "by", "for", "from", "in", "is", "it", "may", "not", "of", "on", "or", "that", "the", "this", "to", "with", "you")

#: Sentences and paragraphs by which licences are commonly granted.
TEMPLATES = (
    ("MIT", "Released under the MIT License."),
    ("MIT", "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the Software), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions:"),
    ("MIT", "SPDX-License-Identifier: MIT"),
    ("Apache-2.0", "Licensed under the Apache License, Version 2.0."),
    ("Apache-2.0", "Licensed under the Apache License, Version 2.0 (the License); you may not use this file except in compliance with the License."),
    ("Apache-2.0", "Licensed under the Apache License, Version 2.0 (the License); you may not use this file except in compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0 Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an AS IS BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. See the License for the specific language governing permissions and limitations under the License."),
    ("Apache-2.0", "SPDX-License-Identifier: Apache-2.0"),
    ("GPL-3.0", "This work is licensed under the GNU General Public License, version 3."),
    ("GPL-3.0", "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version."),
    ("GPL-3.0", "SPDX-License-Identifier: GPL-3.0-or-later"),
    ("LGPL-3.0", "Licensed under the GNU Lesser General Public License, version 3."),
    ("AGPL-3.0", "Licensed under the GNU Affero General Public License, version 3."),
    ("BSD-3-Clause", "Use of this source code is governed by a BSD-style license that can be found in the LICENSE file."),
    ("BSD-3-Clause", "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met:"),
    ("BSD-3-Clause", "SPDX-License-Identifier: BSD-3-Clause"),
    ("ISC", "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies."),
    ("MPL-2.0", "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can obtain one at http://mozilla.org/MPL/2.0/."),
    ("CC-BY-4.0", "Licensed under CC BY 4.0."),
    ("CC-BY-4.0", "This work is licensed under a Creative Commons Attribution 4.0 International License."),
    ("CC-BY-SA-4.0", "Licensed under CC BY-SA 4.0."),
    ("CC-BY-NC-4.0", "Licensed under CC BY-NC 4.0."),
    ("CC-BY-NC-4.0", "This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International License."),
    ("CC0-1.0", "Released into the public domain under CC0 1.0 Universal."),
    ("Unlicense", "This is free and unencumbered software released into the public domain."),
    ("proprietary", "All rights reserved."),
    ("proprietary", "Copyright. All rights reserved. Proprietary and confidential."),
)


def template_words() -> list[tuple[int, str, str, int]]:
    """``template, licence, word, n``: how often each word that has weight stands in each template."""
    bags = [Counter(w for w in re.findall(WORD, text.lower()) if w not in STOP) for _, text in TEMPLATES]
    return [(k, name, w, n) for k, ((name, _), bag) in enumerate(zip(TEMPLATES, bags, strict=True)) for w, n in sorted(bag.items())]


_UNIT = ("path", "h", "block", "line")


def _found(lines: Column) -> Column:
    """Words that have weight, in order."""
    return F.filter(F.regexp_extract_all(lines, F.lit(f"({WORD})"), 1), lambda w: ~w.isin(*STOP))


def units(files: DataFrame) -> DataFrame:
    """``path, h, block, n_lines, block_words, line, words`` of every line; ``h`` tells texts of one path apart."""
    rows = files.select("path", F.xxhash64("text").alias("h"), F.posexplode(F.split(F.lower("text"), BLANK)).alias("block", "body"))
    rows = rows.select("path", "h", "block", F.transform(F.split("body", "\n"), _found).alias("lines"))
    total = F.aggregate("lines", F.lit(0), lambda s, x: s + F.size(x))
    return rows.select("path", "h", "block", F.size("lines").alias("n_lines"), total.alias("block_words"), F.posexplode("lines").alias("line", "words"))


def _counted(rows: DataFrame) -> DataFrame:
    """``path, h, block, line, unit_words, word, n`` of lines, and of blocks of several lines as line -1, from rows with ``word``."""
    keys = ["path", "h", "block", "line", "n_lines", "line_words", "block_words", "word"]
    lines = materialize(rows.groupBy(*keys).agg(F.count(F.lit(1)).alias("n")), "licence-words")
    blocks = lines.where("n_lines > 1").groupBy("path", "h", "block", "block_words", "word").agg(F.sum("n").alias("n"))
    return lines.select(*_UNIT, F.col("line_words").alias("unit_words"), "word", "n").unionByName(blocks.select("path", "h", "block", F.lit(-1).alias("line"), F.col("block_words").alias("unit_words"), "word", "n"))


def _words(files: DataFrame) -> DataFrame:
    return units(files).select("path", "h", "block", "line", "n_lines", F.size("words").alias("line_words"), "block_words", F.explode("words").alias("word"))


def frequencies(files: DataFrame) -> DataFrame:
    """``word, df``: the number of paths with the word in any of their texts, for every word of the corpus.

    A row's words are told apart within the row, so what is shuffled is combined by word; where rows share a path, what is
    counted twice is taken off again.
    """
    own = F.array_distinct(_found(F.lower("text")))
    df = files.select(F.explode(own).alias("word")).groupBy("word").agg(F.count(F.lit(1)).alias("df"))
    shared = materialize(files.groupBy("path").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("path"), "licence-shared")
    if not shared.isEmpty():
        again = only_needed(shared, files, F.col("path")).select("path", F.explode(own).alias("word")).groupBy("path", "word").agg(F.count(F.lit(1)).alias("n"))
        df = df.unionByName(again.where("n > 1").groupBy("word").agg((-F.sum(F.col("n") - 1)).alias("df"))).groupBy("word").agg(F.sum("df").alias("df"))
    return materialize(df, "licence-df")


def _idf(df: DataFrame, rows: DataFrame, files: int) -> DataFrame:
    """``word, idf`` of the words of ``rows`` over ``files`` files."""
    return df.join(rows.select("word").distinct(), "word", "left_semi").select("word", (F.log(F.lit(1.0 + files) / (1 + F.col("df"))) + 1).alias("idf"))


def matches(files: DataFrame, near: float = NEAR) -> DataFrame:
    """``path, h, block, line, unit_words, template, licence, similarity`` of lines and blocks (line -1) as near as that to a template;
    ``unit_words`` are those of its words that templates have.

    Null and empty texts have none; rows that share a path and a text are one file with its words twice, which changes no cosine.
    """
    spark = files.sparkSession
    files = files.select("path", "text")
    n = files.select("path").distinct().count()
    table = F.broadcast(spark.createDataFrame(template_words(), "template int, licence string, word string, tn int"))  # fixed size
    known = F.broadcast(table.select("word").distinct())
    some = _counted(_words(files).join(known, "word"))
    df = frequencies(files)
    idf = materialize(_idf(df, known, n), "licence-idf")
    unseen = F.log(F.lit(1.0 + n)) + 1  # a template's word that no file has still counts in the template's norm
    weights = table.join(idf, "word", "left").withColumn("x", F.col("tn") * F.coalesce("idf", unseen))
    weights = weights.join(weights.groupBy("template").agg(F.sqrt(F.sum(F.col("x") * F.col("x"))).alias("norm")), "template").select("template", "licence", "word", (F.col("x") / F.col("norm")).alias("weight"))
    weights = F.broadcast(materialize(weights, "licence-templates"))
    vectors = some.join(F.broadcast(idf), "word").withColumn("x", F.col("n") * F.col("idf"))
    least = vectors.groupBy(*_UNIT, "unit_words").agg(F.sum(F.col("x") * F.col("x")).alias("t"), F.sum("n").alias("m"))
    dots = vectors.join(weights, "word").groupBy(*_UNIT, "template", "licence").agg(F.sum(F.col("x") * F.col("weight")).alias("dot"))
    maybe = dots.join(least, list(_UNIT)).where(F.col("dot") >= F.lit(near - 1e-6) * F.sqrt(F.col("t") + F.col("unit_words") - F.col("m")))
    maybe = materialize(maybe.select(*_UNIT, F.col("m").alias("unit_words"), "template", "licence", "dot"), "licence-maybe")
    # the exact norms of what is left, with the frequencies of all their words
    again = only_needed(maybe.select("h"), files, F.xxhash64("text"))
    every = materialize(_counted(_words(again)).join(maybe.select(*_UNIT).distinct(), list(_UNIT), "left_semi"), "licence-every")
    idf = _idf(df, every, n)
    norms = every.join(idf, "word").groupBy(*_UNIT).agg(F.sqrt(F.sum(F.pow(F.col("n") * F.col("idf"), 2.0))).alias("norm"))
    out = maybe.join(norms, list(_UNIT)).withColumn("similarity", F.round(F.col("dot") / F.col("norm"), 6))
    return out.where(F.col("similarity") >= near).select(*_UNIT, "unit_words", "template", "licence", "similarity")


def best_templates(found: DataFrame) -> DataFrame:
    """``path, licence, similarity``: best template of any line or block of a file; ties by template order. No rows give none."""
    best = found.groupBy("path").agg(F.min(F.struct((-F.col("similarity")).alias("s"), "template", "licence")).alias("b"))
    return best.select("path", F.col("b.licence").alias("licence"), (-F.col("b.s")).alias("similarity"))


def licence_files(files: DataFrame, found: DataFrame) -> DataFrame:
    """``path`` of files that speak for their directory: by name, or if half of their words are words of templates in lines or blocks that match."""
    unit = found.select(*_UNIT, "unit_words").distinct()
    words = unit.groupBy("path").agg(F.greatest(F.sum(F.when(F.col("line") >= 0, F.col("unit_words")).otherwise(0)), F.sum(F.when(F.col("line") < 0, F.col("unit_words")).otherwise(0))).alias("matched"))
    own = only_needed(found.select("h"), files.select("path", "text"), F.xxhash64("text")).dropDuplicates(["path", "text"])
    total = units(own).where("line = 0").groupBy("path").agg(F.sum("block_words").alias("total"))
    share = words.join(total, "path").where(F.col("path").rlike(NAMED) | (F.col("matched") * 2 >= F.col("total")))
    return share.select("path")


def directory(path: Column) -> Column:
    """All but the last part; the root is the empty path, a null path has none."""
    return F.when(F.instr(path, "/") > 0, F.regexp_replace(path, "/[^/]*$", "")).when(path.isNotNull(), F.lit(""))


def ancestors(path: Column) -> Column:
    """The directory itself and all above it, down to the empty root; array of ``depth, dir``."""
    parts = F.filter(F.split(path, "/"), lambda x: x != "")
    return F.transform(F.sequence(F.lit(0), F.size(parts)), lambda k: F.struct(k.alias("depth"), F.array_join(F.slice(parts, F.lit(1), k), "/").alias("dir")))


def scan(files: DataFrame, near: float = NEAR) -> DataFrame:
    """``files`` (``path, text`` and other columns of any name) with ``licence_found, similarity, origin, from_dir`` in place of any of these names.

    ``origin`` is ``own``, ``inherited`` or ``none``. Of several licence files in a directory the first path speaks.
    Null and empty texts have no licence of their own; null paths inherit nothing and have none. Rows with the same path are read as
    one file. An empty table gives an empty result.
    """
    given = files.drop("licence_found", "similarity", "origin", "from_dir")
    files = given.select("path", "text")
    found = materialize(matches(files, near), "licence-found")
    own = materialize(best_templates(found), "licence-own")
    dirs = own.join(licence_files(files, found), "path", "left_semi")
    speakers = dirs.groupBy(directory(F.col("path")).alias("dir")).agg(F.min(F.struct("path", "licence")).alias("f"))
    speakers = materialize(speakers.select(F.col("dir").alias("speaker_dir"), F.col("f.licence").alias("speaks")), "licence-dirs")
    places = files.where("path is not null").select(directory(F.col("path")).alias("place")).distinct()
    up = places.select("place", F.explode(ancestors(F.col("place"))).alias("a")).select("place", "a.depth", "a.dir")
    nearest = up.join(speakers, F.col("dir") == F.col("speaker_dir")).groupBy("place").agg(F.max(F.struct("depth", "dir", "speaks")).alias("n"))
    nearest = nearest.select("place", F.col("n.dir").alias("near_dir"), F.col("n.speaks").alias("near_licence"))
    a, b, c, d, e, f = free_names(given, "own_path", "own_licence", "own_similarity", "near_place", "near_dir", "near_licence")
    out = given.join(own.toDF(a, b, c), given["path"] == F.col(a), "left").join(nearest.toDF(d, e, f), directory(given["path"]) == F.col(d), "left")
    origin = F.when(F.col(b).isNotNull(), "own").when(F.col(f).isNotNull(), "inherited").otherwise("none")
    return out.select(
        *[given[x] for x in given.columns], F.coalesce(b, f).alias("licence_found"), F.col(c).alias("similarity"), origin.alias("origin"),
        F.when(origin == "inherited", F.col(e)).alias("from_dir"),
    )


def document_path(source: Column, doc_id: Column) -> Column:
    """Where a document would lie: sources hold folders of 4,096 ids, these hold folders of 64."""
    part = lambda n: F.coalesce(F.floor(doc_id / n).cast("string"), F.lit("x"))
    return F.concat_ws("/", F.coalesce(source, F.lit("none")), part(4096), part(64), F.coalesce(doc_id.cast("string"), F.lit("x")))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    """op10: licence of every document, its own or its folder's."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", document_path(F.col("source"), F.col("doc_id")).alias("path"), "text")
    return scan(docs).select("doc_id", "path", F.col("licence_found").alias("licence"), "similarity", "origin", "from_dir")


def oracle() -> str:
    """The same in one piece of SQL, with the template words as rows."""
    values = ", ".join(f"({k}, '{name}', '{w}', {n})" for k, name, w, n in template_words())
    stop = ", ".join(f"'{w}'" for w in STOP)
    unit = "path, block, line"
    return rf"""
WITH t(template, licence, word, tn) AS (VALUES {values}),
d AS (SELECT doc_id, coalesce(source, 'none') || '/' || CAST(doc_id // 4096 AS VARCHAR) || '/' || CAST(doc_id // 64 AS VARCHAR) || '/' || CAST(doc_id AS VARCHAR) AS path, text FROM documents),
k AS (SELECT path, generate_subscripts(string_split_regex(lower(text), '\n[ \t\r]*\n'), 1) AS block, unnest(string_split_regex(lower(text), '\n[ \t\r]*\n')) AS body FROM d),
l AS (SELECT path, block, generate_subscripts(string_split(body, chr(10)), 1) AS line, unnest(string_split(body, chr(10))) AS line_text, len(string_split(body, chr(10))) AS n_lines FROM k),
w AS (SELECT path, block, line, n_lines, unnest(list_filter(regexp_extract_all(line_text, '{WORD}'), lambda x: x NOT IN ({stop}))) AS word FROM l),
c AS (SELECT path, block, line, word, count(*) AS n FROM w GROUP BY ALL UNION ALL SELECT path, block, -1, word, count(*) FROM w WHERE n_lines > 1 GROUP BY path, block, word),
i AS (SELECT word, ln((1.0::DOUBLE + (SELECT count(DISTINCT path) FROM d)) / (1 + count(DISTINCT path))) + 1 AS idf FROM w GROUP BY word),
v AS (SELECT {unit}, word, n, n * idf AS x FROM c JOIN i USING (word)),
n AS (SELECT {unit}, sqrt(sum(x * x)) AS norm, sum(n) FILTER (word IN (SELECT word FROM t)) AS unit_words FROM v GROUP BY {unit}),
tx AS (SELECT template, licence, word, tn * coalesce(idf, ln(1.0::DOUBLE + (SELECT count(DISTINCT path) FROM d)) + 1) AS x FROM t LEFT JOIN i USING (word)),
tw AS (SELECT template, licence, word, x / sqrt(sum(x * x) OVER (PARTITION BY template)) AS weight FROM tx),
q AS (SELECT {unit}, template, licence, sum(x * weight) AS dot FROM v JOIN tw USING (word) GROUP BY {unit}, template, licence),
m AS (SELECT {unit}, template, licence, unit_words, round(dot / norm, 6) AS similarity FROM q JOIN n USING ({unit}) WHERE round(dot / norm, 6) >= {NEAR}),
o AS (SELECT path, licence, similarity FROM m QUALIFY row_number() OVER (PARTITION BY path ORDER BY similarity DESC, template) = 1),
h AS (SELECT path, greatest(sum(CASE WHEN line >= 0 THEN unit_words ELSE 0 END), sum(CASE WHEN line < 0 THEN unit_words ELSE 0 END)) AS words FROM (SELECT DISTINCT {unit}, unit_words FROM m) GROUP BY path),
z AS (SELECT path, count(*) AS total FROM w GROUP BY path),
f AS (SELECT regexp_replace(path, '/[^/]*$', '') AS dir, arg_min(o.licence, path) AS licence FROM o JOIN h USING (path) JOIN z USING (path) WHERE h.words * 2 >= z.total GROUP BY 1),
p AS (SELECT DISTINCT regexp_replace(path, '/[^/]*$', '') AS place FROM d),
a AS (SELECT place, f.dir, f.licence, row_number() OVER (PARTITION BY place ORDER BY length(f.dir) DESC) AS r FROM p JOIN f ON place = f.dir OR starts_with(place, f.dir || '/'))
SELECT d.doc_id, d.path, coalesce(o.licence, a.licence) AS licence, o.similarity,
       CASE WHEN o.licence IS NOT NULL THEN 'own' WHEN a.licence IS NOT NULL THEN 'inherited' ELSE 'none' END AS origin,
       CASE WHEN o.licence IS NULL THEN a.dir END AS from_dir
FROM d LEFT JOIN o USING (path) LEFT JOIN a ON a.place = regexp_replace(d.path, '/[^/]*$', '') AND a.r = 1
"""
