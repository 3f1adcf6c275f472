"""Licence scans (DataFrame functions only): TF-IDF cosine of headers and licence files to templates, and inheritance from ancestor directories.

A text is looked at in units: its lines, its sentences (over line breaks), its paragraphs, and the whole. A unit is a sparse
vector over its terms, weighted by inverse document frequency over the whole corpus; terms outside the templates weigh most.
It is a licence unit of the template of largest cosine, if that is at least COSINE. A text with a licence unit is licensed by
its best one. A text of which licence units of one kind (the whole text is one) hold half of the words is a licence file: its
directory, and what lies below without a licence nearer, inherits it through joins on path prefixes.
"""

from __future__ import annotations

import math
import re

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from runloom.llm.common import written

#: Licence names, header sentences, and the texts of licences and of their usual notices.
TEMPLATES = (
    ("Apache-2.0", "Licensed under the Apache License, Version 2.0."),
    ("MIT", "Released under the MIT License."),
    ("MIT", "Permission is hereby granted, free of charge, to any person obtaining a copy of this software."),
    ("BSD-3-Clause", "Redistribution and use in source and binary forms, with or without modification, are permitted."),
    ("GPL-3.0", "This work is licensed under the GNU General Public License, version 3."),
    ("GPL-2.0", "This work is licensed under the GNU General Public License, version 2."),
    ("LGPL-3.0", "This work is licensed under the GNU Lesser General Public License, version 3."),
    ("AGPL-3.0", "This work is licensed under the GNU Affero General Public License, version 3."),
    ("MPL-2.0", "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0."),
    ("CC-BY-4.0", "Licensed under CC BY 4.0."),
    ("CC-BY-SA-4.0", "Licensed under CC BY-SA 4.0."),
    ("CC-BY-NC-4.0", "Licensed under CC BY-NC 4.0."),
    ("CC0-1.0", "Dedicated to the public domain under CC0 1.0."),
    ("LicenseRef-Proprietary", "All rights reserved."),
    ("LicenseRef-Proprietary", "Copyright. All rights reserved. Do not copy or redistribute without permission."),
    ("Apache-2.0", 'Licensed under the Apache License, Version 2.0 (the "License"); you may not use this file except in compliance with the License.'),
    ("Apache-2.0", 'Licensed under the Apache License, Version 2.0 (the "License"); you may not use this file except in compliance with the License. You may obtain a copy of the License at '
     'http://www.apache.org/licenses/LICENSE-2.0 Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an "AS IS" BASIS, WITHOUT WARRANTIES OR '
     "CONDITIONS OF ANY KIND, either express or implied. See the License for the specific language governing permissions and limitations under the License."),
    ("MIT", "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction, "
     "including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, "
     "subject to the following conditions: The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software. THE SOFTWARE IS PROVIDED \"AS IS\", "
     "WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR "
     "COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER "
     "DEALINGS IN THE SOFTWARE."),
    ("ISC", "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in "
     "all copies. THE SOFTWARE IS PROVIDED \"AS IS\" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE "
     "AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER "
     "TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE."),
    ("BSD-2-Clause", "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: 1. Redistributions of source code must retain "
     "the above copyright notice, this list of conditions and the following disclaimer. 2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following "
     "disclaimer in the documentation and/or other materials provided with the distribution. THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS \"AS IS\" AND ANY EXPRESS OR IMPLIED WARRANTIES, "
     "INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, "
     "INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) "
     "HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF THE "
     "POSSIBILITY OF SUCH DAMAGE."),
    ("BSD-3-Clause", "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: 1. Redistributions of source code must retain "
     "the above copyright notice, this list of conditions and the following disclaimer. 2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following "
     "disclaimer in the documentation and/or other materials provided with the distribution. 3. Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products "
     "derived from this software without specific prior written permission. THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS \"AS IS\" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT "
     "LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, "
     "INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED "
     "AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF "
     "SUCH DAMAGE."),
    ("Zlib", "This software is provided 'as-is', without any express or implied warranty. In no event will the authors be held liable for any damages arising from the use of this software. Permission is granted to "
     "anyone to use this software for any purpose, including commercial applications, and to alter it and redistribute it freely, subject to the following restrictions: 1. The origin of this software must not be "
     "misrepresented; you must not claim that you wrote the original software. If you use this software in a product, an acknowledgment in the product documentation would be appreciated but is not required. 2. "
     "Altered source versions must be plainly marked as such, and must not be misrepresented as being the original software. 3. This notice may not be removed or altered from any source distribution."),
    ("Unlicense", "This is free and unencumbered software released into the public domain. Anyone is free to copy, modify, publish, use, compile, sell, or distribute this software, either in source code form or as a "
     "compiled binary, for any purpose, commercial or non-commercial, and by any means."),
    ("GPL-3.0", "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the "
     "License, or (at your option) any later version. This program is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A "
     "PARTICULAR PURPOSE. See the GNU General Public License for more details. You should have received a copy of the GNU General Public License along with this program. If not, see <https://www.gnu.org/licenses/>."),
    ("GPL-2.0", "This program is free software; you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation; either version 2 of the "
     "License, or (at your option) any later version. This program is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A "
     "PARTICULAR PURPOSE. See the GNU General Public License for more details."),
    ("LGPL-3.0", "This program is free software: you can redistribute it and/or modify it under the terms of the GNU Lesser General Public License as published by the Free Software Foundation, either version 3 of "
     "the License, or (at your option) any later version."),
    ("AGPL-3.0", "This program is free software: you can redistribute it and/or modify it under the terms of the GNU Affero General Public License as published by the Free Software Foundation, either version 3 of "
     "the License, or (at your option) any later version."),
    ("MPL-2.0", "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can obtain one at https://mozilla.org/MPL/2.0/."),
)
SPLIT = "[^a-z0-9]+"
#: How texts are cut, by kind of unit: a sentence ends with its mark or an empty line; empty lines of comments divide paragraphs too.
UNITS = (("line", "\n"), ("sentence", r"(?<=[.!?:;])\s+|\n[ \t]*\n"), ("paragraph", r"\n[ \t#*/;-]*\n"))
WORDS = r"[^\x20\x09-\x0D]+"
COSINE = 0.75
#: Share of a text's words in licence units of one kind that makes it a licence file.
FILE_SHARE = 0.5
#: Parts into which every directory's documents are dealt when they inherit: one directory may hold a third of all rows.
SALTS = 16


def _terms(text: Column) -> Column:
    return F.array_remove(F.array_distinct(F.split(F.lower(text), SPLIT)), "")


def _python_terms(text: str) -> list[str]:
    return sorted({t for t in re.split(SPLIT, text.lower()) if t})


def _literals(words) -> Column:
    return F.array(*[F.lit(t) for t in words])


def _document_frequency(docs: DataFrame, vocabulary: list[str]) -> tuple[dict[str, int], int]:
    """Documents holding each template term (a row per term), and all documents, in one pass."""
    # the empty term stands for the document itself
    rows = docs.select(F.explode(F.concat(F.array(F.lit("")), F.coalesce(F.array_intersect(_terms(F.col("text")), _literals(vocabulary)), F.array().cast("array<string>")))).alias("term"))
    counts = {r["term"]: r["count"] for r in rows.groupBy("term").count().collect()}
    return counts, counts.get("", 0)


def weights(counts: dict[str, int], total: int) -> tuple[dict[str, float], float]:
    """Inverse document frequency of the template terms, and that of a term in no template."""
    idf = {t: 1 + math.log((1 + total) / (1 + counts.get(t, 0))) for t in {t for _, text in TEMPLATES for t in _python_terms(text)}}
    return idf, 1 + math.log(1 + total)


def _numbered(kind: str, cut: str) -> Column:
    return F.transform(F.split("text", cut), lambda x, i: F.struct(F.lit(kind).alias("kind"), i.alias("unit"), x.alias("part")))


def licence_units(docs: DataFrame) -> DataFrame:
    """doc_id, n_words, kind, unit (its number), licence, cosine, words (the template's at most) of every licence unit of docs (doc_id, text)."""
    spark = docs.sparkSession
    vectors = [(k, name, _python_terms(t)) for k, (name, t) in enumerate(TEMPLATES)]
    vocabulary = sorted({t for _, _, terms in vectors for t in terms})
    idf, rare = weights(*_document_frequency(docs, vocabulary))
    sizes = [len(re.findall(WORDS, text)) for _, text in TEMPLATES]
    norms = {k: math.sqrt(sum(idf[t] ** 2 for t in terms)) for k, _, terms in vectors}
    # terms without any of which no unit can reach COSINE: from the heaviest down, until the rest is too light for every template
    strong: set[str] = set()
    for k, _, terms in vectors:
        by_weight = sorted(terms, key=lambda t: (-idf[t], t))
        while math.sqrt(sum(idf[t] ** 2 for t in terms if t not in strong)) >= COSINE * norms[k]:
            strong.add(next(t for t in by_weight if t not in strong))
    # a unit of more distinct terms is too long for COSINE with any template: every term weighs 1 at least
    most = math.floor((max(norms.values()) / COSINE) ** 2)
    holds = lambda terms: F.arrays_overlap(terms, _literals(sorted(strong)))
    parts = [_numbered(kind, cut) for kind, cut in UNITS]
    whole = F.array(F.struct(F.lit("text").alias("kind"), F.lit(0).alias("unit"), F.col("text").alias("part")))
    n_words = lambda c: F.regexp_count(c, F.lit(WORDS))
    near = docs.filter(holds(_terms(F.col("text")))).select("doc_id", F.monotonically_increasing_id().alias("row"), n_words("text").alias("n_words"), F.explode(F.concat(*parts, whole)).alias("u"))
    units = near.select("doc_id", "row", "n_words", "u.*").withColumn("terms", _terms(F.col("part"))).filter((F.size("terms") <= most) & holds(F.col("terms")))
    known = F.array_intersect("terms", _literals(vocabulary))
    others = ((F.size("terms") - F.size(known)) * F.lit(rare**2)).alias("others")
    by_unit = ["doc_id", "row", "n_words", "kind", "unit", "words", "others"]
    terms = units.select(*by_unit[:5], n_words("part").alias("words"), others, F.explode(known).alias("term"))
    # products with the templates, term by term; template -1 sums the unit's own length
    weighed = [(t, idf[t] ** 2, [(-1, None, None, None), *((k, name, norms[k], sizes[k]) for k, name, own in vectors if t in own)]) for t in vocabulary]
    table = spark.createDataFrame(weighed, "term string, square double, templates array<struct<k:int,licence:string,norm:double,size:int>>")
    dots = terms.join(F.broadcast(table), "term").select(*by_unit, "square", F.explode("templates").alias("t")).groupBy(*by_unit, "t").agg(F.sum("square").alias("dot"))
    length = F.sqrt(F.max(F.when(F.col("t.k") < 0, F.col("dot"))) + F.col("others")).alias("length")
    scored = dots.groupBy(*by_unit).agg(length, F.collect_list(F.when(F.col("t.k") >= 0, F.struct("t", "dot"))).alias("found")).withColumn("x", F.explode("found"))
    scored = scored.withColumn("cosine", F.round(F.col("x.dot") / (F.col("length") * F.col("x.t.norm")), 9)).filter(F.col("cosine") >= COSINE)
    best = scored.groupBy(*by_unit).agg(F.max_by(F.struct("x.t.licence", "cosine", "x.t.size"), F.struct("cosine", -F.col("x.t.k"))).alias("b"))
    return best.select("doc_id", "n_words", "kind", "unit", "b.licence", "b.cosine", F.least("words", "b.size").alias("words"))


def _nearest(dirs: DataFrame, files: DataFrame) -> DataFrame:
    """dir, near (the nearest licensed directory on its way up, and that one's licence): a row a directory, however many documents it holds."""
    steps = F.expr("transform(sequence(0, IF(dir = '', 0, size(split(dir, '/')))), d -> struct(d AS depth, substring_index(dir, '/', d) AS above))")
    above = dirs.select("dir", F.explode(steps).alias("s")).select("dir", "s.*").join(files.withColumnRenamed("dir", "above"), "above")
    return above.groupBy("dir").agg(F.max_by(F.struct("above", "of_dir"), "depth").alias("near"))


def scan(docs: DataFrame, path: Column | None = None) -> DataFrame:
    """doc_id, path, licence, cosine, origin, n_lines, licence_dir of every document.

    origin: "header" (a licence unit of its own), "file" (a licence file), "inherited" (from licence_dir) or null. n_lines: its
    licence lines, or sentences or paragraphs where these are more. path: default source/lang/doc_id. Null and empty texts
    have no units of their own and may inherit; documents sharing an id share their licence units; ties go to lines, then to
    the earlier one; a null path has no directory. Other columns are not read.
    """
    path = F.concat_ws("/", "source", "lang", "doc_id") if path is None else path
    units = written(licence_units(docs.select("doc_id", F.col("text").cast("string").alias("text"))).distinct(), "licence-units")
    order = F.when(F.col("kind") == "line", 3).when(F.col("kind") == "sentence", 2).when(F.col("kind") == "paragraph", 1).otherwise(0)
    kinds = units.groupBy("doc_id", "kind").agg(
        F.max_by(F.struct("licence", "cosine"), F.struct("cosine", -F.col("unit"))).alias("own"), F.count(F.lit(1)).alias("n"), F.sum("words").alias("words"), F.max("n_words").alias("n_words")
    )
    is_file = F.max(F.col("words") >= FILE_SHARE * F.col("n_words"))
    own = kinds.groupBy(F.col("doc_id").alias("own_id")).agg(F.max_by("own", F.struct("own.cosine", order)).alias("own"), F.max("n").alias("n_lines"), is_file.alias("is_file"))
    own = written(own, "licence-own")
    parent = F.when(F.instr("path", "/") > 0, F.expr("substring_index(path, '/', size(split(path, '/')) - 1)")).when(F.col("path").isNotNull(), F.lit(""))
    slim = docs.select("doc_id", path.alias("path")).withColumn("dir", parent)  # no texts
    same = F.col("doc_id").eqNullSafe(F.col("own_id"))
    files = slim.filter("path IS NOT NULL").join(own.filter("is_file"), same).groupBy("dir").agg(F.max_by("own", F.struct(F.col("own.cosine"), "path")).alias("of_dir"))
    near = _nearest(slim.filter("dir IS NOT NULL").select("dir").distinct(), written(files, "licence-dirs"))
    dealt = near.select(F.col("dir").alias("near_dir"), "near", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))).alias("near_salt"))
    joined = slim.join(own, same, "left").withColumn("salt", F.pmod(F.xxhash64("doc_id", "path"), F.lit(SALTS)).cast("int"))
    out = joined.join(dealt, (F.when(F.col("own").isNull(), F.col("dir")) == F.col("near_dir")) & (F.col("salt") == F.col("near_salt")), "left")
    origin = F.when(F.col("own").isNotNull(), F.when(F.col("is_file"), "file").otherwise("header")).when(F.col("near").isNotNull(), "inherited")
    return out.select(
        "doc_id", "path", F.coalesce("own.licence", "near.of_dir.licence").alias("licence"), F.coalesce("own.cosine", "near.of_dir.cosine").alias("cosine"),
        origin.alias("origin"), F.coalesce("n_lines", F.lit(0)).cast("long").alias("n_lines"), F.when(F.col("own").isNull(), F.col("near.above")).alias("licence_dir"),
    )
