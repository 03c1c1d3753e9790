"""License scans by canonical digest lookup.

A text is brought to a canonical form (case, punctuation, blanks, wrapping, copyright lines and equivalent spellings no longer matter) and its SHA-256 is looked up, by a
hash join, among those of known licence texts, with and without their titles. Whole documents are looked up; so are their paragraphs and lines, since licences and notices
are often a part of a longer text. A paragraph of a known text stands for its licence if no other licence has it. Only parts whose canonical length is that of a known one
are looked up, which loses none.

Null or empty text: digest of the empty form, no licence. Parts and texts of any length are compared whole. Rows are judged each for itself; notices are listed
in order of name, each once. An empty table, of documents or of licences, gives no matches. Other columns do not matter.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import durable, join_unique

# Short notices of well-known licences.
NOTICES: tuple[tuple[str, str], ...] = (
    ("Apache-2.0", "Licensed under the Apache License, Version 2.0."),
    ("Apache-2.0", "Licensed under the Apache License, Version 2.0 (the \"License\"); you may not use this file except in compliance with the License."),
    ("MIT", "Released under the MIT License."),
    ("MIT", "Licensed under the MIT License."),
    ("MIT", "This project is licensed under the terms of the MIT license."),
    ("CC-BY-NC-4.0", "Licensed under CC BY-NC 4.0."),
    ("CC-BY-NC-4.0", "This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International License."),
    ("CC-BY-4.0", "Licensed under CC BY 4.0."),
    ("CC-BY-4.0", "This work is licensed under a Creative Commons Attribution 4.0 International License."),
    ("CC-BY-SA-4.0", "Licensed under CC BY-SA 4.0."),
    ("CC0-1.0", "To the extent possible under law, the author has waived all copyright and related or neighboring rights to this work."),
    ("GPL-3.0", "This work is licensed under the GNU General Public License, version 3."),
    ("GPL-3.0", "Licensed under the GNU General Public License v3.0."),
    ("GPL-2.0", "This work is licensed under the GNU General Public License, version 2."),
    ("LGPL-3.0", "This work is licensed under the GNU Lesser General Public License, version 3."),
    ("AGPL-3.0", "This work is licensed under the GNU Affero General Public License, version 3."),
    ("MPL-2.0", "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0."),
    ("BSD-3-Clause", "Use of this source code is governed by a BSD-style license that can be found in the LICENSE file."),
    ("ISC", "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies."),
    ("Unlicense", "This is free and unencumbered software released into the public domain."),
)

# Texts of well-known licences, paragraph by paragraph, without titles and copyright lines; and the titles that they go by.
_MIT_GRANT = """Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the "Software"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so{}"""
_MIT_AS_IS = """THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE."""
_ISC_GRANT = """Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted{}"""
_ISC_AS_IS = """THE SOFTWARE IS PROVIDED "AS IS" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE."""
_BSD = (
    "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met:",
    "1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer.",
    "2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution.",
)
_BSD_NAME = "3. Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission."
_BSD_AS_IS = """THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS "AS IS" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE."""
TEXTS: tuple[tuple[str, tuple[str, ...], tuple[str, ...]], ...] = (
    ("MIT", ("MIT License", "The MIT License", "The MIT License (MIT)"), (_MIT_GRANT.format(", subject to the following conditions:"), "The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software.", _MIT_AS_IS)),
    ("MIT-0", ("MIT No Attribution",), (_MIT_GRANT.format("."), _MIT_AS_IS)),
    ("ISC", ("ISC License", "The ISC License"), (_ISC_GRANT.format(", provided that the above copyright notice and this permission notice appear in all copies."), _ISC_AS_IS)),
    ("0BSD", ("BSD Zero Clause License", "Zero-Clause BSD"), (_ISC_GRANT.format("."), _ISC_AS_IS)),
    ("BSD-2-Clause", ("BSD 2-Clause License", "The 2-Clause BSD License"), (*_BSD, _BSD_AS_IS)),
    ("BSD-3-Clause", ("BSD 3-Clause License", "The 3-Clause BSD License"), (*_BSD, _BSD_NAME, _BSD_AS_IS)),
    ("Zlib", ("zlib License", "The zlib/libpng License"), (
        "This software is provided 'as-is', without any express or implied warranty. In no event will the authors be held liable for any damages arising from the use of this software.",
        "Permission is granted to anyone to use this software for any purpose, including commercial applications, and to alter it and redistribute it freely, subject to the following restrictions:",
        "1. The origin of this software must not be misrepresented; you must not claim that you wrote the original software. If you use this software in a product, an acknowledgment in the product documentation would be appreciated but is not required.",
        "2. Altered source versions must be plainly marked as such, and must not be misrepresented as being the original software.",
        "3. This notice may not be removed or altered from any source distribution.")),
    ("Unlicense", ("The Unlicense",), (
        "This is free and unencumbered software released into the public domain.",
        "Anyone is free to copy, modify, publish, use, compile, sell, or distribute this software, either in source code form or as a compiled binary, for any purpose, commercial or non-commercial, and by any means.",
        "In jurisdictions that recognize copyright laws, the author or authors of this software dedicate any and all copyright interest in the software to the public domain. We make this dedication for the benefit of the public at large and to the detriment of our heirs and successors. We intend this dedication to be an overt act of relinquishment in perpetuity of all present and future rights to this software under copyright law.",
        _MIT_AS_IS.replace(" AUTHORS OR COPYRIGHT HOLDERS", " AUTHORS"),
        "For more information, please refer to <https://unlicense.org>")),
    ("Apache-2.0", ("Apache License, Version 2.0",), (
        "Licensed under the Apache License, Version 2.0 (the \"License\"); you may not use this file except in compliance with the License. You may obtain a copy of the License at",
        "https://www.apache.org/licenses/LICENSE-2.0",
        "Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an \"AS IS\" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. See the License for the specific language governing permissions and limitations under the License.")),
)
#: Shortest paragraph (code points) of a known text that stands for its licence.
LEAST_PARAGRAPH = 40


def catalogue() -> list[tuple[str, str, bool]]:
    """License, text, and whether it stands for the licence wherever it is a paragraph or line: TEXTS with and without title, their paragraphs, and NOTICES."""
    rows = [(name, "\n\n".join((*title, *body)), False) for name, titles, body in TEXTS for title in ((), *((t,) for t in titles))]
    holders: dict[str, set[str]] = {}
    for name, _, body in TEXTS:
        for p in body:
            holders.setdefault(p, set()).add(name)
    rows += [(min(names), p, True) for p, names in holders.items() if len(names) == 1 and len(p) >= LEAST_PARAGRAPH]
    rows += [(name, body[0], True) for name, _, body in TEXTS if len(body) == 1]
    return rows + [(name, notice, True) for name, notice in NOTICES]


# Spellings that count as equal, applied in this order to lower-case words.
SPELLINGS: tuple[tuple[str, str], ...] = (
    ("licence", "license"), ("licences", "licenses"), ("licenced", "licensed"), ("sublicence", "sublicense"), ("sub license", "sublicense"), ("non commercial", "noncommercial"), ("merchantibility", "merchantability"),
    ("organisation", "organization"), ("favour", "favor"), ("neighbouring", "neighboring"), ("whilst", "while"), ("copyright owner", "copyright holder"),
    ("per cent", "percent"), ("wilful", "willful"), ("http", "https"), ("v", "version"), ("holders", "holder"), ("acknowledgement", "acknowledgment"), ("recognise", "recognize"),
)

# A line that only states a copyright: an optional comment sign, the word or sign, and a year or holder.
COPYRIGHT_LINE = r"(?m)^[ \t/*#;-]*(copyright|\(c\)|©)[ \t]+(\(c\)|©|[0-9]{4}|by )[^\n]*$"
NOT_WORD = "[^a-z0-9\u0080-\U0010ffff\n]+"
LINE_ENDS = "[ \n]*\n[ \n]*"
BROADCAST_LICENSES = 100_000


def _respelled(x: Column) -> Column:
    # two blanks between words, so that neighbouring spellings do not share one
    for old, new in SPELLINGS:
        x = F.replace(x, F.lit(f" {old.replace(' ', '  ')} "), F.lit(f" {new.replace(' ', '  ')} "))
    return F.regexp_replace(x, " v(?=[0-9])", " version  ")


def _lined(text: Column) -> Column:
    """Lines of respelled words, with two blanks between words."""
    x = F.regexp_replace(F.lower(F.coalesce(text, F.lit(""))), COPYRIGHT_LINE, " ")
    x = F.regexp_replace(F.replace(x, F.lit("&"), F.lit(" and ")), NOT_WORD, "  ")
    return _respelled(F.concat(F.lit(" "), F.replace(x, F.lit("\n"), F.lit(" \n ")), F.lit(" ")))


def _squeezed(x: Column) -> Column:
    return F.trim(F.regexp_replace(x, "[ \n]+", " "))


def _whole(lined: Column) -> Column:
    return _squeezed(_respelled(F.regexp_replace(lined, LINE_ENDS, "  ")))


def canonical(text: Column) -> Column:
    """The form of a text that is compared: lower-case words with one space between."""
    return _whole(_lined(text))


def paragraphs(lined: Column) -> Column:
    """Paragraphs of a text as of _lined: what empty lines part."""
    return F.split(lined, "\n[ \n]*\n", -1)


def known(spark: SparkSession, listed: list[tuple[str, str, bool]] | None = None) -> DataFrame:
    """license, digest, length and part (whether parts of documents are looked up) of the canonical forms of known texts (catalogue() if none are given), each form once."""
    rows = spark.createDataFrame(catalogue() if listed is None else listed, "license string, notice string, part boolean").withColumn("c", canonical(F.col("notice")))
    return rows.select("license", "part", F.sha2("c", 256).alias("digest"), F.length("c").alias("length")).groupBy("digest").agg(F.min("license").alias("license"), F.first("length").alias("length"), F.max("part").alias("part"))


def scan_licenses(docs: DataFrame, licenses: DataFrame | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row for each row of docs: id, digest (of the whole text's canonical form), license (the whole text's, or null), notices (licences with a known text that is a paragraph or line of it)."""
    licenses = known(docs.sparkSession) if licenses is None else licenses
    # The catalogue is a curated list: its size is checked here. Beyond the bound Spark joins as it sees fit, and parts are told by the range of lengths alone.
    n, low, high = licenses.agg(F.count(F.lit(1)), F.min(F.when(F.col("part"), F.col("length"))), F.max(F.when(F.col("part"), F.col("length")))).first()
    lengths = [r["length"] for r in licenses.where("part").select("length").distinct().collect()] if n <= BROADCAST_LICENSES else None
    table = licenses.select(F.col("digest").alias("known"), "license", "part")
    table = F.broadcast(table) if n <= BROADCAST_LICENSES else table
    lined = docs.select(F.col(f"`{id_col}`").alias("id"), _lined(F.col(f"`{text_col}`")).alias("lined"))

    def of_known_length(parts: Column, form: Callable[[Column], Column]) -> Column:
        near = F.filter(parts, lambda x: F.length(x).between(low or 0, 2 * (high or -1) + 8))  # blanks are doubled at most, but for those of line ends
        formed = F.transform(near, form)
        return F.filter(formed, lambda c: F.length(c).isin(lengths) if lengths else F.length(c).between(low or 0, high or -1))

    parts = F.concat(of_known_length(F.split("lined", "\n", -1), _squeezed), of_known_length(F.transform(paragraphs(F.col("lined")), lambda p: F.regexp_replace(p, LINE_ENDS, "  ")), _whole))
    rows = durable(lined.select("id", F.sha2(_whole(F.col("lined")), 256).alias("digest"), F.array_distinct(F.transform(parts, lambda c: F.sha2(c, 256))).alias("lines")))  # read twice below, and small
    whole = rows.join(table.drop("part"), F.col("digest") == F.col("known"), "left").drop("known")
    # Rows with parts to look up are few; each is known again by its id and digest, and equal rows have equal notices.
    looked = rows.where(F.size("lines") > 0).select("id", "digest", F.explode("lines").alias("line")).join(table.where("part").withColumnRenamed("license", "notice"), F.col("line") == F.col("known"))
    notices = looked.groupBy(F.col("id").alias("n_id"), F.col("digest").alias("n_digest")).agg(F.array_sort(F.collect_set("notice")).alias("notices"))
    done = join_unique(whole, notices, {"id": "n_id", "digest": "n_digest"}, "left")
    return done.select(F.col("id").alias(id_col), "digest", "license", F.coalesce("notices", F.array().cast("array<string>")).alias("notices"))
