"""License scans in DataFrame operations: sparse TF-IDF cosine to templates, then inheritance by directory.

Units are the lines of a text that have a cue (CUES); its paragraphs of several lines that have one, if it has several
paragraphs (headers that run over lines, paragraphs of licence texts); and licence files (by their name) as a whole. Terms are lower-case letters
and digits; a term's weight is its count times ln((1 + N) / (1 + df)) + 1 over all N units of the corpus, in which
equal texts are one. Templates are short notices, titles and whole texts. The text's licence is the template with the
best cosine of its units, from `LEAST` on; one that says under which licence it stands (SAYS), but matches no template,
has the licence `unknown`. A file without one takes that of the nearest directory above it, its own first, which holds
a licence file with a licence.

Defined results: every row gives one row, whatever its id (null and repeated ones too: a row is judged by its text and
path); null text is an empty one, null paths belong to no directory; equal cosines (to six places) go to the template
first by name; of a directory's licence files the name first in order counts, of equal names the licence first by name;
an empty table gives no rows; further columns are ignored.
"""

from __future__ import annotations

import math
import re

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import written

LEAST = 0.6
# fixed values: notices, titles and texts of licences
_BSD = "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: 1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer. 2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution."
_BSD_NAMES = "3. Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission."
_BSD_END = "THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS AS IS AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE."
_GNU = "This program is free software: you can redistribute it and/or modify it under the terms of the GNU {0} as published by the Free Software Foundation, either version {1} of the License, or (at your option) any later version. This program is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE. See the GNU {0} for more details. You should have received a copy of the GNU {0} along with this program."
TEMPLATES = {
    "AGPL-3.0": ["Licensed under the GNU Affero General Public License, version 3", "GNU AFFERO GENERAL PUBLIC LICENSE Version 3, 19 November 2007", _GNU.format("Affero General Public License", 3), "SPDX-License-Identifier: AGPL-3.0-or-later", "SPDX-License-Identifier: AGPL-3.0-only"],
    "Apache-2.0": [
        "Licensed under the Apache License, Version 2.0", "Apache License Version 2.0, January 2004 http://www.apache.org/licenses/", "Apache License Version 2.0, January 2004", "SPDX-License-Identifier: Apache-2.0",
        "Licensed under the Apache License, Version 2.0 (the License); you may not use this file except in compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0 Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an AS IS BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. See the License for the specific language governing permissions and limitations under the License.",
        "TERMS AND CONDITIONS FOR USE, REPRODUCTION, AND DISTRIBUTION 1. Definitions. License shall mean the terms and conditions for use, reproduction, and distribution as defined by Sections 1 through 9 of this document. Licensor shall mean the copyright owner or entity authorized by the copyright owner that is granting the License.",
        "2. Grant of Copyright License. Subject to the terms and conditions of this License, each Contributor hereby grants to You a perpetual, worldwide, non-exclusive, no-charge, royalty-free, irrevocable copyright license to reproduce, prepare Derivative Works of, publicly display, publicly perform, sublicense, and distribute the Work and such Derivative Works in Source or Object form.",
    ],
    "BSD-2-Clause": ["SPDX-License-Identifier: BSD-2-Clause", "Released under the BSD 2-Clause License", f"{_BSD} {_BSD_END}"],
    "BSD-3-Clause": ["SPDX-License-Identifier: BSD-3-Clause", "Use of this source code is governed by a BSD-style license", "Released under the BSD 3-Clause License", f"{_BSD} {_BSD_NAMES} {_BSD_END}"],
    "BSL-1.0": ["Distributed under the Boost Software License, Version 1.0", "Boost Software License - Version 1.0 - August 17th, 2003", "SPDX-License-Identifier: BSL-1.0"],
    "CC-BY-4.0": ["This work is licensed under a Creative Commons Attribution 4.0 International License", "Licensed under CC BY 4.0", "SPDX-License-Identifier: CC-BY-4.0"],
    "CC-BY-NC-4.0": ["This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International License", "Licensed under CC BY-NC 4.0", "SPDX-License-Identifier: CC-BY-NC-4.0"],
    "CC-BY-NC-ND-4.0": ["This work is licensed under a Creative Commons Attribution-NonCommercial-NoDerivatives 4.0 International License", "Licensed under CC BY-NC-ND 4.0", "SPDX-License-Identifier: CC-BY-NC-ND-4.0"],
    "CC-BY-NC-SA-4.0": ["This work is licensed under a Creative Commons Attribution-NonCommercial-ShareAlike 4.0 International License", "Licensed under CC BY-NC-SA 4.0", "SPDX-License-Identifier: CC-BY-NC-SA-4.0"],
    "CC-BY-ND-4.0": ["This work is licensed under a Creative Commons Attribution-NoDerivatives 4.0 International License", "Licensed under CC BY-ND 4.0", "SPDX-License-Identifier: CC-BY-ND-4.0"],
    "CC-BY-SA-4.0": ["This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License", "Licensed under CC BY-SA 4.0", "SPDX-License-Identifier: CC-BY-SA-4.0"],
    "CC0-1.0": ["CC0 1.0 Universal public domain dedication", "SPDX-License-Identifier: CC0-1.0"],
    "EPL-2.0": ["This program and the accompanying materials are made available under the terms of the Eclipse Public License 2.0", "Eclipse Public License - v 2.0", "SPDX-License-Identifier: EPL-2.0"],
    "GPL-2.0": ["This program is licensed under the GNU General Public License, version 2", "GNU GENERAL PUBLIC LICENSE Version 2, June 1991", _GNU.format("General Public License", 2), "SPDX-License-Identifier: GPL-2.0-only"],
    "GPL-3.0": ["This work is licensed under the GNU General Public License, version 3", "GNU GENERAL PUBLIC LICENSE Version 3, 29 June 2007", _GNU.format("General Public License", 3), "SPDX-License-Identifier: GPL-3.0-or-later"],
    "ISC": [
        "Released under the ISC License", "SPDX-License-Identifier: ISC",
        "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies. THE SOFTWARE IS PROVIDED AS IS AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE.",
    ],
    "LGPL-3.0": ["Licensed under the GNU Lesser General Public License, version 3", "GNU LESSER GENERAL PUBLIC LICENSE Version 3, 29 June 2007", _GNU.format("Lesser General Public License", 3), "SPDX-License-Identifier: LGPL-3.0-only"],
    "MIT": [
        "Released under the MIT License", "SPDX-License-Identifier: MIT", "Licensed under the MIT license",
        "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the Software), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions: The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software. THE SOFTWARE IS PROVIDED AS IS, WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE.",
        "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the Software), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions:",
    ],
    "MPL-2.0": ["This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0", "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can obtain one at http://mozilla.org/MPL/2.0/.", "Mozilla Public License Version 2.0", "SPDX-License-Identifier: MPL-2.0"],
    "Unlicense": ["This is free and unencumbered software released into the public domain", "SPDX-License-Identifier: Unlicense"],
    "Zlib": ["Released under the zlib License", "SPDX-License-Identifier: Zlib"],
}
CUES = ("licens", "licenc", "copyright", "public domain", "all rights reserved")
SAYS = "licen[sc]ed under|released under the [a-z0-9 .-]*licen[sc]e|spdx-license-identifier"
FILES = r"(?i)^(licen[cs]e|copying|unlicense|notice)([.-].*)?$"
PARAGRAPH = "\n[ \t\r]*\n"


def _terms(col):
    return F.regexp_extract_all(F.lower(col), F.lit("[a-z0-9]+"), 0)


def units(files: DataFrame) -> DataFrame:
    """k, unit, says, terms of the lines (unit: line number), licence files (-1) and paragraphs (below) of files(k, name, text), once for each k."""
    has = lambda c: F.exists(F.array(*map(F.lit, CUES)), lambda q: F.contains(c, q))
    some = files.where(has(F.lower("text")))
    lines = some.select("k", F.posexplode(F.split("text", "\n")).alias("unit", "part"))
    lines = lines.where(has(F.lower("part"))).select("k", "unit", F.lower("part").rlike(SAYS).alias("says"), "part")
    blocks = some.select("k", F.split("text", PARAGRAPH).alias("parts")).where(F.size("parts") > 1).select("k", F.posexplode("parts").alias("at", "part"))
    blocks = blocks.where(F.contains("part", F.lit("\n")) & has(F.lower("part"))).select("k", (-2 - F.col("at")).alias("unit"), F.lit(False).alias("says"), "part")
    whole = files.where(F.col("name").rlike(FILES)).select("k", F.lit(-1).alias("unit"), F.lit(False).alias("says"), F.col("text").alias("part"))
    return lines.union(blocks).union(whole).select("k", "unit", "says", _terms(F.col("part")).alias("terms")).dropDuplicates(["k", "unit"])


def template_weights(total: int, df: dict[str, int]) -> list[tuple[str, str, float]]:
    """(term, template, weight) of the templates' unit vectors; their number is bounded by TEMPLATES."""
    out = []
    for name, texts in TEMPLATES.items():
        for i, t in enumerate(texts):
            tf: dict[str, int] = {}
            for term in re.findall("[a-z0-9]+", t.lower()):
                tf[term] = tf.get(term, 0) + 1
            w = {term: n * (math.log((1.0 + total) / (1.0 + df.get(term, 0))) + 1.0) for term, n in tf.items()}
            norm = math.sqrt(sum(x * x for x in w.values()))
            out += [(term, f"{name}#{i}", x / norm) for term, x in w.items()]
    return out


def own_licenses(files: DataFrame, least: float = LEAST) -> DataFrame:
    """k, license, cosine of the texts that name a licence."""
    spark = files.sparkSession
    found = written(units(files), "units")
    total = found.count()
    counts = written(found.select("k", "unit", F.explode("terms").alias("term")).groupBy("k", "unit", "term").agg(F.count("*").alias("tf")), "terms")
    df = counts.groupBy("term").agg(F.count("*").alias("df"))
    names = sorted({x for v in TEMPLATES.values() for t in v for x in re.findall("[a-z0-9]+", t.lower())})
    own = {r.term: r.df for r in df.where(F.col("term").isin(names)).collect()}  # a row for each template term
    known = spark.createDataFrame(template_weights(total, own), "term string, template string, tw double")
    idf = F.log(F.lit(1.0 + total) / (1.0 + F.col("df"))) + 1.0
    weights = written(counts.join(df, "term").select("k", "unit", "term", (F.col("tf") * idf).alias("w")), "weights")
    norm = weights.groupBy("k", "unit").agg(F.sqrt(F.sum(F.col("w") * F.col("w"))).alias("n"))
    dots = weights.join(F.broadcast(known), "term").groupBy("k", "unit", "template").agg(F.sum(F.col("w") * F.col("tw")).alias("dot"))
    cosine = dots.join(norm, ["k", "unit"]).select("k", F.substring_index("template", "#", 1).alias("license"), F.round(F.col("dot") / F.col("n"), 6).alias("cosine")).where(F.col("cosine") >= least)
    best = cosine.select("k", F.struct((-F.col("cosine")).alias("c"), "license").alias("b"))
    said = found.where("says").select("k", F.struct(F.lit(1.0).alias("c"), F.lit("unknown").alias("license")).alias("b"))
    best = best.union(said).groupBy("k").agg(F.min("b").alias("b"))
    return best.select("k", F.col("b.license").alias("license"), F.when(F.col("b.c") <= 0, -F.col("b.c")).alias("cosine"))


def scan(docs: DataFrame, id_col: str = "doc_id", path_col: str = "path", text_col: str = "text", least: float = LEAST) -> DataFrame:
    """doc_id, path, license, cosine, basis (header: of the text itself; directory: inherited; none), license_dir."""
    path = docs[path_col].cast("string")
    folder, name = F.regexp_replace(path, "/?[^/]*$", ""), F.substring_index(path, "/", -1)
    text = F.coalesce(docs[text_col], F.lit(""))
    files = docs.select(docs[id_col].cast("long").alias("id"), path.alias("path"), folder.alias("dir"), name.alias("name"), text.alias("text"), F.unhex(F.md5(F.concat(F.when(name.rlike(FILES), "1").otherwise("0"), text))).alias("k"))
    own = written(own_licenses(files, least), "licences")
    slim = files.select("id", "path", "dir", "name", "k")
    # a directory's licence: that of its licence file
    held = slim.where(F.col("name").rlike(FILES)).join(own, "k")
    held = held.groupBy("dir").agg(F.min(F.struct("name", "license")).getField("license").alias("inherited"))
    dirs = slim.where(F.col("dir").isNotNull()).select("dir").distinct()
    parts = F.split("dir", "/")
    above = dirs.select("dir", F.explode(F.sequence(F.lit(0), F.size(parts))).alias("depth"), parts.alias("parts"))
    above = above.select("dir", "depth", F.array_join(F.slice("parts", F.lit(1), F.col("depth")), "/").alias("up")).where((F.col("depth") > 0) | (F.col("dir") != ""))
    near = written(above.join(held.withColumnRenamed("dir", "up"), "up").groupBy("dir").agg(F.max_by("inherited", "depth").alias("inherited"), F.max_by("up", "depth").alias("license_dir")), "near")
    out = slim.join(own, "k", "left").join(near, "dir", "left")
    basis = F.when(F.col("license").isNotNull(), "header").when(F.col("inherited").isNotNull(), "directory").otherwise("none")
    return out.select(F.col("id").alias("doc_id"), "path", F.coalesce("license", "inherited").alias("license"), "cosine", basis.alias("basis"), F.when(F.col("license").isNull(), F.col("license_dir")).alias("license_dir"))


def placed(docs: DataFrame) -> DataFrame:
    """documents with a path: the table has none, so ids are laid out in a tree, its licence files at round numbers."""
    i = F.col("doc_id")
    a, b, c = (F.concat(F.lit(p), F.floor(i / n).cast("string")) for p, n in (("a", 4096), ("b", 512), ("c", 64)))
    file = F.concat(i.cast("string"), F.lit(".txt"))
    path = F.when(i % 4096 == 0, F.concat_ws("/", F.lit("corpus"), a, F.lit("LICENSE"))).when(i % 512 == 0, F.concat_ws("/", F.lit("corpus"), a, b, F.lit("LICENSE"))).when(i % 64 == 0, F.concat_ws("/", F.lit("corpus"), a, b, c, F.lit("LICENSE")))
    return docs.withColumn("path", F.when(i.isNotNull(), F.coalesce(path, F.concat_ws("/", F.lit("corpus"), a, b, c, file))))


def op3_licenses(spark, sf_dir):
    return scan(placed(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")))


def _sql() -> str:
    values = ", ".join(f"('{k}', {i}, '{t}')" for k, v in TEMPLATES.items() for i, t in enumerate(v))
    cue = lambda c: "(" + " OR ".join(f"contains({c}, '{q}')" for q in CUES) + ")"
    return f"""
WITH files AS (
  SELECT doc_id AS id, coalesce(text, '') AS text,
    CASE WHEN doc_id % 4096 = 0 THEN 'corpus/a' || (doc_id // 4096) WHEN doc_id % 512 = 0 THEN 'corpus/a' || (doc_id // 4096) || '/b' || (doc_id // 512)
      ELSE 'corpus/a' || (doc_id // 4096) || '/b' || (doc_id // 512) || '/c' || (doc_id // 64) END AS dir,
    CASE WHEN doc_id % 64 = 0 THEN 'LICENSE' ELSE doc_id || '.txt' END AS name FROM documents),
texts AS (SELECT DISTINCT text, name = 'LICENSE' AS file, md5(CASE WHEN name = 'LICENSE' THEN '1' ELSE '0' END || text) AS k FROM files),
lines AS (SELECT k, unnest(string_split(text, chr(10))) AS part, generate_subscripts(string_split(text, chr(10)), 1) - 1 AS unit FROM texts WHERE {cue("lower(text)")}),
paragraphs AS (SELECT k, unnest(a) AS part, -1 - generate_subscripts(a, 1) AS unit FROM (SELECT k, regexp_split_to_array(text, '{PARAGRAPH}') AS a FROM texts WHERE {cue("lower(text)")}) WHERE len(a) > 1),
units AS (SELECT k, unit, regexp_matches(lower(part), '{SAYS}') AS says, regexp_extract_all(lower(part), '[a-z0-9]+') AS terms FROM lines WHERE {cue("lower(part)")}
  UNION ALL SELECT k, unit, false, regexp_extract_all(lower(part), '[a-z0-9]+') FROM paragraphs WHERE {cue("lower(part)")} AND contains(part, chr(10))
  UNION ALL SELECT k, -1, false, regexp_extract_all(lower(text), '[a-z0-9]+') FROM texts WHERE file),
total AS (SELECT count(*) AS total FROM units),
counts AS (SELECT k, unit, term, count(*) AS tf FROM (SELECT k, unit, unnest(terms) AS term FROM units) GROUP BY ALL),
idf AS (SELECT term, ln((1.0 + total)::DOUBLE / (1.0 + count(*))::DOUBLE) + 1 AS idf FROM counts, total GROUP BY term, total),
templates(license, variant, t) AS (VALUES {values}),
known AS (SELECT license, variant, term, count(*) AS ttf FROM (SELECT license, variant, unnest(regexp_extract_all(lower(t), '[a-z0-9]+')) AS term FROM templates) GROUP BY ALL),
tw AS (SELECT license, variant, k.term, ttf * coalesce(idf, ln((1.0 + total)::DOUBLE) + 1) AS tw FROM known k CROSS JOIN total LEFT JOIN idf USING (term)),
tn AS (SELECT license, variant, sqrt(sum(tw * tw)) AS tn FROM tw GROUP BY ALL),
w AS (SELECT k, unit, term, tf * idf AS w FROM counts JOIN idf USING (term)),
n AS (SELECT k, unit, sqrt(sum(w * w)) AS n FROM w GROUP BY ALL),
best AS (SELECT k, license, max(round(dot / tn / n, 6)) AS cosine FROM (SELECT k, unit, license, variant, sum(w * tw) AS dot FROM w JOIN tw USING (term) GROUP BY ALL) JOIN tn USING (license, variant) JOIN n USING (k, unit) GROUP BY k, license),
own AS (SELECT k, license, cosine FROM (SELECT * FROM best WHERE cosine >= {LEAST} UNION ALL SELECT DISTINCT k, 'unknown', NULL FROM units WHERE says) QUALIFY row_number() OVER (PARTITION BY k ORDER BY cosine DESC NULLS LAST, license) = 1),
placed AS (SELECT *, md5(CASE WHEN name = 'LICENSE' THEN '1' ELSE '0' END || text) AS k FROM files),
held AS (SELECT dir, arg_min(license, (name, license)) AS inherited FROM placed JOIN own USING (k) WHERE name = 'LICENSE' GROUP BY dir),
near AS (SELECT d.dir, arg_max(h.inherited, length(h.dir)) AS inherited, arg_max(h.dir, length(h.dir)) AS license_dir
  FROM (SELECT DISTINCT dir FROM files) d JOIN held h ON d.dir = h.dir OR starts_with(d.dir, h.dir || '/') GROUP BY d.dir)
SELECT id AS doc_id, dir || '/' || name AS path, coalesce(license, inherited) AS license, cosine,
  CASE WHEN license IS NOT NULL THEN 'header' WHEN inherited IS NOT NULL THEN 'directory' ELSE 'none' END AS basis,
  CASE WHEN license IS NULL THEN license_dir END AS license_dir
FROM placed LEFT JOIN own USING (k) LEFT JOIN near USING (dir)
"""


OP3_SQL = _sql()
