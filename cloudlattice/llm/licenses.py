"""License scans with MinHash bands over overlapping text windows, in DataFrame operations only.

Templates are sorted into classes by length: class ``c`` holds those of up to ``c``
shingles and more than ``c / 2``. A document is read in windows of ``2 c`` shingles
that start every ``c``, so an occurrence of a template of the class lies whole in
some window. If a window holds ``CONTAINED`` of a template's shingles their Jaccard
similarity is at least 0.4 / 2.1, and ``BANDS`` bands of one row collide with a
probability of over 0.9999. Windows and templates meet in a join on class, band and
minimum; the templates so retrieved are verified by exact containment.

Windows without any shingle of any template can't hold one and are never built.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from cloudlattice.llm.work import load

WORDS = 5
CONTAINED = 0.8
BANDS = 48

_WARRANTY = (
    "THE SOFTWARE IS PROVIDED \"AS IS\", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, "
    "FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER "
    "LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE."
)
_BSD = (
    "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: "
    "1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer. "
    "2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution. "
)
_BSD_WARRANTY = (
    "THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS \"AS IS\" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF "
    "MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, "
    "SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) "
    "HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, "
    "EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE."
)

# fixed values: license texts and the notices that documents carry, by license
TEMPLATES = (
    ("MIT", "Released under the MIT License."),
    (
        "MIT",
        "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software "
        "without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons "
        "to whom the Software is furnished to do so, subject to the following conditions: The above copyright notice and this permission notice shall be included in all copies or substantial "
        "portions of the Software. " + _WARRANTY,
    ),
    ("Apache-2.0", "Licensed under the Apache License, Version 2.0."),
    (
        "Apache-2.0",
        "Licensed under the Apache License, Version 2.0 (the \"License\"); you may not use this file except in compliance with the License. You may obtain a copy of the License at "
        "http://www.apache.org/licenses/LICENSE-2.0 Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an \"AS IS\" BASIS, "
        "WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. See the License for the specific language governing permissions and limitations under the License.",
    ),
    ("GPL-3.0", "This work is licensed under the GNU General Public License, version 3."),
    (
        "GPL-3.0",
        "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either "
        "version 3 of the License, or (at your option) any later version. This program is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied "
        "warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE. See the GNU General Public License for more details.",
    ),
    ("CC-BY-NC-4.0", "Licensed under CC BY-NC 4.0."),
    ("CC-BY-NC-4.0", "This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International License"),
    ("CC-BY-4.0", "This work is licensed under a Creative Commons Attribution 4.0 International License"),
    ("CC-BY-SA-4.0", "This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License"),
    ("BSD-2-Clause", _BSD + _BSD_WARRANTY),
    ("BSD-3-Clause", _BSD + "3. Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission. " + _BSD_WARRANTY),
    (
        "ISC",
        "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission "
        "notice appear in all copies. THE SOFTWARE IS PROVIDED \"AS IS\" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF "
        "MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, "
        "DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE.",
    ),
    (
        "Zlib",
        "This software is provided 'as-is', without any express or implied warranty. In no event will the authors be held liable for any damages arising from the use of this software. "
        "Permission is granted to anyone to use this software for any purpose, including commercial applications, and to alter it and redistribute it freely, subject to the following "
        "restrictions: 1. The origin of this software must not be misrepresented; you must not claim that you wrote the original software. If you use this software in a product, an "
        "acknowledgment in the product documentation would be appreciated but is not required. 2. Altered source versions must be plainly marked as such, and must not be misrepresented as "
        "being the original software. 3. This notice may not be removed or altered from any source distribution.",
    ),
    (
        "Unlicense",
        "This is free and unencumbered software released into the public domain. Anyone is free to copy, modify, publish, use, compile, sell, or distribute this software, either in source "
        "code form or as a compiled binary, for any purpose, commercial or non-commercial, and by any means.",
    ),
    ("MPL-2.0", "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can obtain one at http://mozilla.org/MPL/2.0/."),
)


def bound(value: Column, body) -> Column:
    """``body`` of ``value``, which is evaluated once and not again for every element that ``body`` visits."""
    return F.transform(F.array(value), body)[0]


def shingles(text: Column) -> Column:
    """Hashes of the runs of five words; words are the runs of a-z and 0-9 of the lower-cased text."""

    def runs(words: Column) -> Column:
        last = F.size(words) - WORDS + 1
        return F.when(last >= 1, F.transform(F.sequence(F.lit(1), last), lambda i: F.xxhash64(F.slice(words, i, WORDS)))).otherwise(F.array().cast("array<bigint>"))

    return bound(F.array_remove(F.split(F.lower(text), "[^a-z0-9]+"), ""), runs)


def minima(values: Column) -> Column:
    """The smallest hash of the values under each of the seeded hash functions."""
    return bound(values, lambda v: F.transform(F.sequence(F.lit(0), F.lit(BANDS - 1)), lambda j: F.array_min(F.transform(v, lambda x: F.xxhash64(x, j)))))


def catalogue(spark: SparkSession, templates=TEMPLATES) -> DataFrame:
    """template, license, its distinct shingles, class and minima; as small as the list of templates."""
    rows = spark.createDataFrame([(k, name, text) for k, (name, text) in enumerate(templates)], "template int, license string, text string")
    rows = rows.select("template", "license", F.array_distinct(shingles(F.col("text"))).alias("wanted")).where(F.size("wanted") > 0)
    class_ = F.pow(F.lit(2.0), F.ceil(F.log2(F.size("wanted").cast("double")))).cast("int")
    return rows.withColumn("class", class_).withColumn("minima", minima(F.col("wanted")))


def scan(docs: DataFrame, templates=TEMPLATES, contained: float = CONTAINED) -> DataFrame:
    """doc_id, license, containment (the largest of its templates and windows), for every match.

    Null and short texts match nothing; repeated rows give one match; an empty table
    an empty result; other columns of the input are ignored.
    """
    spark = docs.sparkSession
    known = catalogue(spark, templates)
    held = known.select("class", "wanted").collect()  # bounded by the list of templates
    every, classes = sorted({x for r in held for x in r["wanted"]}), sorted({r["class"] for r in held})
    telling = F.filter(F.transform("s", lambda x, i: F.when(x.isin(every), i)), lambda i: i.isNotNull())
    found = docs.select("doc_id", shingles(F.col("text")).alias("s")).where(F.exists("s", lambda x: x.isin(every))).withColumn("hits", telling)

    def starts(c: int) -> Column:
        """The two windows of class ``c`` that each telling place lies in, in order, once."""
        cells = F.array_distinct(F.flatten(F.transform("hits", lambda i: F.array(F.floor(i / c), F.floor(i / c) - 1))))
        return F.transform(F.filter(cells, lambda k: k >= 0), lambda k: F.struct(F.lit(c).alias("class"), (k * c + 1).cast("int").alias("from")))

    windows = found.withColumn("w", F.explode(F.concat(*[starts(c) for c in classes]))).select("doc_id", F.col("w.class").alias("class"), F.array_distinct(F.slice("s", F.col("w.from"), F.col("w.class") * 2)).alias("window"))
    signed = windows.withColumn("mine", minima(F.col("window"))).select("*", F.posexplode("mine").alias("band", "value"))
    index = known.select("*", F.posexplode("minima").alias("band", "value"))  # a row for each template and band
    # a window and a template that agree in several bands are compared once, in the first of them
    first = F.array_position(F.zip_with("mine", "minima", lambda a, b: a == b), True) - 1
    retrieved = signed.join(F.broadcast(index), ["class", "band", "value"]).where(F.col("band") == first)
    share = F.size(F.array_intersect("window", "wanted")) / F.size("wanted")
    return retrieved.withColumn("containment", share).where(F.col("containment") >= contained).groupBy("doc_id", "license").agg(F.max("containment").alias("containment"))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan(load(spark, sf_dir, "documents"))


def oracle(templates=TEMPLATES, contained: float = CONTAINED) -> str:
    """The same matches by plain comparison of every window of every class with every template."""
    quoted = lambda t: t.replace("'", "''")
    values = ", ".join(f"({k}, '{name}', '{quoted(text)}')" for k, (name, text) in enumerate(templates))
    words = lambda t: f"list_filter(regexp_split_to_array(lower({t}), '[^a-z0-9]+'), lambda w: w <> '')"
    runs = lambda w: f"list_transform(range(1, greatest(len({w}) - {WORDS - 2}, 1)), lambda i: array_to_string({w}[i:i + {WORDS - 1}], ' '))"
    return f"""
WITH t AS (SELECT template, license, list_distinct({runs('w')}) AS wanted FROM (SELECT template, license, {words('text')} AS w FROM (VALUES {values}) v(template, license, text))),
c AS (SELECT *, CAST(pow(2, ceil(log2(len(wanted)))) AS INTEGER) AS class FROM t WHERE len(wanted) > 0),
d AS (SELECT doc_id, {runs('w')} AS s FROM (SELECT doc_id, {words('text')} AS w FROM documents WHERE text IS NOT NULL)),
telling AS (SELECT DISTINCT unnest(wanted) AS x FROM c),
near AS (SELECT * FROM d WHERE list_has_any(s, (SELECT list(x) FROM telling))),
w AS (SELECT doc_id, class, s[k * class + 1 : k * class + 2 * class] AS win FROM (SELECT doc_id, s, class, unnest(range(0, CAST(ceil(len(s) / class) AS BIGINT) + 1)) AS k FROM near, (SELECT DISTINCT class FROM c))),
m AS (SELECT doc_id, license, len(list_intersect(list_distinct(win), wanted)) / len(wanted) AS containment FROM w JOIN c USING (class))
SELECT doc_id, license, max(containment) AS containment FROM m WHERE containment >= {contained} GROUP BY doc_id, license"""
