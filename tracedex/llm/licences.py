"""Licence scans (operator 6): TF-IDF cosine to templates and inheritance along directories; DataFrame functions only.

Units are the lines of a file that carry a licence cue, scored against header templates, and the whole text of a licence file, scored
against all templates, whole licences among them. A line without any cue word is no notice, by definition: leaving out only the
lines that the templates' weights rule out cost more than the limit (see the README). Each distinct unit is
scored once (a line that a third of all files carry is one row), by sparse TF-IDF cosine against the
templates, whose terms and weights are a small table of fixed size. A file's own licence is its best unit's best
template above the threshold; a notice that only reserves all rights counts where no unit names a licence. A file without
one inherits from the nearest ancestor directory that has a licence file; ancestors are found by joining the distinct
directories' path prefixes. A bare copyright line states no terms, so its file inherits.

Defined cases: null text has no unit; null paths have no directory and inherit nothing; ties go to the template that comes
first by name, and to the first path of several licence files of a directory; repeated rows are kept; unmatched files have nulls; other
columns, however named, pass untouched, but for those named like the five results, which are replaced.
"""

from __future__ import annotations

import math
import re
from collections import Counter

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from tracedex.llm.common import table

#: Names and characteristic sentences of public licences.
TEMPLATES = [
    ("Apache-2.0", "Licensed under the Apache License, Version 2.0."),
    ("Apache-2.0", 'Licensed under the Apache License, Version 2.0 (the "License"); you may not use this file except in compliance with the License.'),
    ("BSD-3-Clause", "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met"),
    ("BSD-3-Clause", "Licensed under the BSD 3-Clause License."),
    ("CC-BY-4.0", "Licensed under CC BY 4.0."),
    ("CC-BY-4.0", "This work is licensed under the Creative Commons Attribution 4.0 International License."),
    ("CC-BY-NC-4.0", "Licensed under CC BY-NC 4.0."),
    ("CC-BY-NC-4.0", "This work is licensed under the Creative Commons Attribution-NonCommercial 4.0 International License."),
    ("CC0-1.0", "To the extent possible under law, the author has dedicated all copyright and related rights to the public domain worldwide."),
    ("GPL-3.0", "This work is licensed under the GNU General Public License, version 3."),
    ("GPL-3.0", "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License."),
    ("ISC", "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted."),
    ("LGPL-3.0", "This library is licensed under the GNU Lesser General Public License, version 3."),
    ("MIT", "Released under the MIT License."),
    ("MIT", "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files."),
    ("MPL-2.0", "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0."),
    ("Proprietary", "Copyright. All rights reserved. No part may be reproduced without permission."),
    ("Proprietary", "All rights reserved."),
]
SENTENCES = 17  # the templates above the short notice: they alone set the weights of their words
#: Licences that an SPDX line can name; all versions of a family stand beside each other, so that no line goes to the wrong one.
SPDX = [f"CC-{kind}-{v}" for kind in ("BY", "BY-NC", "BY-NC-ND", "BY-NC-SA", "BY-ND", "BY-SA") for v in ("1.0", "2.0", "2.5", "3.0", "4.0")]
SPDX += "0BSD AGPL-1.0 AGPL-3.0 Apache-1.0 Apache-1.1 Apache-2.0 BSD-1-Clause BSD-2-Clause BSD-3-Clause BSD-4-Clause BSL-1.0 CC0-1.0 EPL-1.0 EPL-2.0 EUPL-1.0 EUPL-1.1 EUPL-1.2 GPL-1.0 GPL-2.0 GPL-3.0 ISC LGPL-2.0 LGPL-2.1 LGPL-3.0 MIT MIT-0 MPL-1.0 MPL-1.1 MPL-2.0 Unlicense Zlib".split()
TEMPLATES += [(name, f"SPDX-License-Identifier: {name}") for name in SPDX]
TEMPLATES += [(name, f"SPDX-License-Identifier: {name}-{which}") for name in SPDX if "GPL" in name for which in ("only", "or-later")]
#: A line that reserves all rights, with any holder and years before it, is one notice.
RESERVED = r"(?i)^[^a-z0-9]*((copyright|\(c\)|©).*[^a-z0-9])?all rights reserved[^a-z0-9]*$"
#: Words of which a notice has one.
CUE = r"(?i)licen[cs]|copyright|spdx|public domain|rights reserved|creative commons|permission is hereby|permission to use|free software|redistribution and use"
LICENCE_NAME = r"(?i)(^|/)(licen[cs]e|copying|notice|unlicense)[^/]*$"
THRESHOLD = 0.6
SALTS = 16
#: Whole texts of short public licences, without their copyright lines; only whole licence files are compared with them.
WHOLE = [
    ("MIT", """MIT License. Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the "Software"), to deal
in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the
Software is furnished to do so, subject to the following conditions: The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software.
THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT
SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR
OTHER DEALINGS IN THE SOFTWARE."""),
    ("ISC", """ISC License. Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission
notice appear in all copies. THE SOFTWARE IS PROVIDED "AS IS" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE
AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS
ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE."""),
    ("BSD-2-Clause", """BSD 2-Clause License. Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: 1. Redistributions of
source code must retain the above copyright notice, this list of conditions and the following disclaimer. 2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the
following disclaimer in the documentation and/or other materials provided with the distribution. THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS "AS IS" AND ANY EXPRESS OR IMPLIED WARRANTIES,
INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT,
INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY
THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE."""),
    ("Zlib", """zlib License. This software is provided 'as-is', without any express or implied warranty. In no event will the authors be held liable for any damages arising from the use of this software.
Permission is granted to anyone to use this software for any purpose, including commercial applications, and to alter it and redistribute it freely, subject to the following restrictions: 1. The origin of this software
must not be misrepresented; you must not claim that you wrote the original software. If you use this software in a product, an acknowledgment in the product documentation would be appreciated but is not required. 2.
Altered source versions must be plainly marked as such, and must not be misrepresented as being the original software. 3. This notice may not be removed or altered from any source distribution."""),
    ("Unlicense", """This is free and unencumbered software released into the public domain. Anyone is free to copy, modify, publish, use, compile, sell, or distribute this software, either in source code form or
as a compiled binary, for any purpose, commercial or non-commercial, and by any means. In jurisdictions that recognize copyright laws, the author or authors of this software dedicate any and all copyright interest in
the software to the public domain. We make this dedication for the benefit of the public at large and to the detriment of our heirs and successors. We intend this dedication to be an overt act of relinquishment in
perpetuity of all present and future rights to this software under copyright law."""),
]
#: What the three-clause text has beside the two-clause one.
THIRD = "Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission."
WHOLE += [("BSD-3-Clause", dict(WHOLE)["BSD-2-Clause"].replace("BSD 2-Clause", "BSD 3-Clause") + " 3. " + THIRD)]


def _terms(text: str) -> list[str]:
    return re.findall("[a-z0-9]+", text.lower())


def vectors() -> tuple[list[tuple[str, int, bool, str, float]], dict[str, float], float]:
    """((licence, template, whole, term, weight / norm), idf of terms, idf of unseen terms)."""
    every = [(name, False, Counter(_terms(t))) for name, t in TEMPLATES] + [(name, True, Counter(_terms(t))) for name, t in WHOLE]
    idf: dict[str, float] = {}
    for some in (every[len(TEMPLATES) :], every[SENTENCES : len(TEMPLATES)], every[:SENTENCES]):
        idf |= {w: round(math.log((1 + len(some)) / (1 + n)) + 1, 9) for w, n in Counter(w for _, _, b in some for w in b).items()}
    unseen = round(math.log(1 + SENTENCES) + 1, 9)
    rows = []
    for k, (name, whole, bag) in enumerate(every):
        norm = math.sqrt(sum((n * idf[w]) ** 2 for w, n in bag.items()))
        rows += [(name, k, whole, w, n * idf[w] / norm) for w, n in sorted(bag.items())]
    return rows, idf, unseen


def terms(text: Column) -> Column:
    return F.array_remove(F.split(F.lower(text), "[^a-z0-9]+"), "")


def classify(units: DataFrame) -> DataFrame:
    """unit, whole, licence, score for the distinct non-null `unit` texts that reach the threshold; `whole` (none: false) says that a unit is a whole file."""
    spark = units.sparkSession
    rows, idf, unseen = vectors()
    weights = spark.createDataFrame(rows, "licence string, template int, file boolean, term string, weight double")
    known = spark.createDataFrame(list(idf.items()), "term string, idf double")
    each = units.select("unit", F.col("whole") if "whole" in units.columns else F.lit(False).alias("whole")).filter("unit is not null").distinct()
    each = each.withColumn("key", F.sha2("unit", 256))  # a long text stands in one row, not beside every term of it
    counted = each.select("key", "whole", F.explode(terms(F.col("unit"))).alias("term")).groupBy("key", "whole", "term").agg(F.count("*").alias("n"))
    counted = counted.join(F.broadcast(known), "term", "left").select("key", "whole", "term", (F.col("n") * F.coalesce("idf", F.lit(unseen))).alias("w"))
    norms = counted.groupBy("key", "whole").agg(F.sqrt(F.sum(F.col("w") * F.col("w"))).alias("norm"))
    dots = counted.join(F.broadcast(weights), "term").filter("whole or not file").groupBy("key", "whole", "licence", "template").agg(F.sum(F.col("w") * F.col("weight")).alias("dot"))
    scored = dots.join(norms, ["key", "whole"]).select("key", "whole", "licence", F.round(F.col("dot") / F.col("norm"), 6).alias("score")).filter(F.col("score") >= THRESHOLD)
    best = scored.groupBy("key", "whole").agg(F.min(F.struct((-F.col("score")).alias("s"), "licence")).alias("b"))
    return each.join(best, ["key", "whole"]).select("unit", "whole", F.col("b.licence").alias("licence"), (-F.col("b.s")).alias("score"))


RESULTS = ["own_licence", "own_score", "licence", "licence_from", "licence_path"]


def scan(files: DataFrame) -> DataFrame:
    """`files` (path, text, others) with own_licence, own_score, licence, licence_from (`own`, `inherited` or null), licence_path."""
    names = [c for c in files.columns if c.lower() not in RESULTS]
    base = files.select(F.struct(*names).alias("row"), F.col("path").alias("path"), F.col("text").alias("text"))
    is_file = F.coalesce(F.col("path").rlike(LICENCE_NAME), F.lit(False))
    line = lambda x: F.struct(x.alias("unit"), F.lit(False).alias("whole"))
    lines = F.when(F.col("text").rlike(CUE), F.transform(F.filter(F.split("text", "\n"), lambda x: x.rlike(CUE)), line))
    none = F.array().cast("array<struct<unit:string,whole:boolean>>")
    whole = F.when(is_file & F.col("text").isNotNull(), F.array(F.struct(F.col("text").alias("unit"), F.lit(True).alias("whole"))))
    units = F.concat(F.coalesce(lines, none), F.coalesce(whole, none))
    with_units = base.select("path", F.explode(units).alias("u")).select("path", "u.unit", "u.whole")
    with_units = with_units.withColumn("unit", F.when(F.col("unit").rlike(RESERVED), F.lit("All rights reserved.")).otherwise(F.col("unit"))).distinct().checkpoint()  # few lines, used twice: texts are read once
    # a line that very many files carry meets its licence in as many tasks as there are salts
    salted = with_units.withColumn("salt", F.pmod(F.xxhash64("path"), F.lit(SALTS)).cast("int"))
    known = classify(with_units).withColumn("salt", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
    matched = salted.join(known, ["unit", "whole", "salt"])
    own = matched.groupBy("path").agg(F.min(F.struct((F.col("licence") == "Proprietary").alias("last"), (-F.col("score")).alias("s"), "licence")).alias("b")).select("path", F.col("b.licence").alias("own_licence"), (-F.col("b.s")).alias("own_score"))
    folder = F.when(F.col("path").contains("/"), F.regexp_replace("path", "/[^/]*$", "")).otherwise(F.when(F.col("path").isNotNull(), F.lit("")))
    givers = own.filter(F.col("path").rlike(LICENCE_NAME)).select(folder.alias("folder"), F.struct("path", "own_licence").alias("g")).groupBy("folder").agg(F.min("g").alias("g"))
    folders = base.select(folder.alias("folder")).filter("folder is not null").distinct()
    parts = F.split("folder", "/")
    depths = F.sequence(F.lit(0), F.size(parts))
    ancestors = folders.select("folder", F.explode(F.transform(depths, lambda d: F.struct(d.alias("depth"), F.array_join(F.slice(parts, 1, d), "/").alias("at")))).alias("a")).select("folder", "a.depth", "a.at")
    nearest = ancestors.join(givers.withColumnRenamed("folder", "at"), "at").groupBy("folder").agg(F.max(F.struct("depth", "g")).alias("m")).select("folder", F.col("m.g.path").alias("giver"), F.col("m.g.own_licence").alias("given"))
    joined = base.select("row", "path", folder.alias("folder")).join(own, "path", "left").join(nearest, "folder", "left")
    has = F.col("own_licence").isNotNull()
    return joined.select(
        "row", "own_licence", "own_score", F.coalesce("own_licence", "given").alias("licence"),
        F.when(has, F.lit("own")).when(F.col("given").isNotNull(), F.lit("inherited")).alias("licence_from"), F.when(has, F.col("path")).otherwise(F.col("giver")).alias("licence_path"),
    ).select("row.*", *RESULTS)


#: `documents` have no paths. The query lays them out as source/<thousand>/<hundred>/<id>.txt; of those that speak of a licence, a third are licence files, of the hundred,
#: of the thousand or of the source.
LAYOUT = """concat(coalesce(source, 'none'), case when {file} and doc_id % 9 = 0 then '' when {file} and doc_id % 9 = 3 then concat('/', cast(doc_id div 1000 as string)) else concat('/', cast(doc_id div 1000 as string), '/', cast(doc_id div 100 as string)) end,
    case when {file} then concat('/LICENSE.', cast(doc_id as string)) else concat('/', cast(doc_id as string), '.txt') end)""".format(file="(doc_id % 3 = 0 and coalesce(text, '') rlike '(?i)licen[cs]')")


def op6_licence_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Own and inherited licence of every document."""
    docs = table(spark, sf_dir, "documents").select("doc_id", F.expr(LAYOUT).alias("path"), "text")
    return scan(docs).drop("text")


def _oracle() -> str:
    """The three levels of the layout are walked one by one."""
    rows, idf, unseen = vectors()
    weights = ", ".join(f"('{a}', {b}, {w}, '{c}', {d!r}::DOUBLE)" for a, b, w, c, d in rows)
    known = ", ".join(f"('{w}', {v!r}::DOUBLE)" for w, v in idf.items())
    return rf"""
WITH weights(licence, template, file, term, weight) AS (VALUES {weights}), known(term, idf) AS (VALUES {known}),
l AS (SELECT doc_id, text, coalesce(source, 'none') AS one, doc_id // 1000 AS two, doc_id // 100 AS three, doc_id % 3 = 0 AND regexp_matches(coalesce(text, ''), '(?i)licen[cs]') AS is_file FROM documents),
f AS (SELECT *, CASE WHEN is_file AND doc_id % 9 = 0 THEN 1 WHEN is_file AND doc_id % 9 = 3 THEN 2 ELSE 3 END AS level, CASE WHEN is_file THEN 'LICENSE.' || doc_id ELSE doc_id || '.txt' END AS name FROM l),
p AS (SELECT *, CASE level WHEN 1 THEN one WHEN 2 THEN one || '/' || two ELSE one || '/' || two || '/' || three END AS folder FROM f),
u0 AS (SELECT * FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS unit, false AS whole FROM p) WHERE regexp_matches(unit, '{CUE}') UNION ALL SELECT doc_id, text, true FROM p WHERE is_file AND text IS NOT NULL),
u AS (SELECT DISTINCT doc_id, whole, CASE WHEN regexp_matches(unit, '{RESERVED}') THEN 'All rights reserved.' ELSE unit END AS unit FROM u0),
t AS (SELECT unit, whole, term, count(*) AS n FROM (SELECT unit, whole, unnest(regexp_extract_all(lower(unit), '[a-z0-9]+')) AS term FROM (SELECT DISTINCT unit, whole FROM u)) GROUP BY ALL),
w AS (SELECT unit, whole, t.term, n * coalesce(idf, {unseen!r}::DOUBLE) AS w FROM t LEFT JOIN known USING (term)),
norms AS (SELECT unit, whole, sqrt(sum(w * w)) AS norm FROM w GROUP BY unit, whole),
s AS (SELECT unit, whole, licence, template, round(sum(w * weight) / any_value(norm), 6) AS score FROM w JOIN weights USING (term) JOIN norms USING (unit, whole) WHERE whole OR NOT file GROUP BY unit, whole, licence, template),
o AS (SELECT doc_id, licence AS own_licence, score AS own_score FROM (SELECT doc_id, licence, score, row_number() OVER (PARTITION BY doc_id ORDER BY licence = 'Proprietary', score DESC, licence) AS k FROM u JOIN s USING (unit, whole) WHERE score >= {THRESHOLD}) WHERE k = 1),
g AS (SELECT folder, name, level, own_licence AS given FROM (SELECT folder, name, level, own_licence, row_number() OVER (PARTITION BY folder ORDER BY name) AS k FROM p JOIN o USING (doc_id) WHERE is_file) WHERE k = 1),
a AS (SELECT doc_id, g.folder || '/' || g.name AS giver, given, row_number() OVER (PARTITION BY doc_id ORDER BY g.level DESC) AS k FROM p JOIN g ON g.level <= p.level AND g.folder = CASE g.level WHEN 1 THEN one WHEN 2 THEN one || '/' || two ELSE one || '/' || two || '/' || three END)
SELECT p.doc_id, p.folder || '/' || p.name AS path, own_licence, own_score, coalesce(own_licence, given) AS licence,
       CASE WHEN own_licence IS NOT NULL THEN 'own' WHEN given IS NOT NULL THEN 'inherited' END AS licence_from,
       CASE WHEN own_licence IS NOT NULL THEN p.folder || '/' || p.name ELSE giver END AS licence_path
FROM p LEFT JOIN o USING (doc_id) LEFT JOIN (SELECT * FROM a WHERE k = 1) b USING (doc_id)
"""


ORACLE = _oracle()
