"""Licence scan by canonical digests, in DataFrame functions only.

A known licence is its whole text, its standard header of several lines, or a whole one-line notice; both sides are brought to one canonical form (lower case, copyright
lines and list marks dropped, equivalent spellings made equal, everything but letters and digits collapsed) and hash-joined by SHA-256.
The units looked up are every document as a whole (a title line before a licence body may stand or not), every one of its lines as a whole, and,
for known texts of `LONG` words or more, every stretch of the canonical document that begins like the text and has its length; so a licence file, a
licence line, and a licence or header inside a longer document are found however they are wrapped, indented or commented. Shorter notices never match as parts of a line.

Null and empty texts have no unit and get no licence; copies of a row are each reported; further columns of the input
are not read. An empty table gives an empty result. The table of known licences has a fixed size, so it is broadcast."""

from __future__ import annotations

import re

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import row_keys, table, text_or_empty

# Notices under which the licences are declared, with their public identifiers.
NOTICES = [
    ("Apache-2.0", "Licensed under the Apache License, Version 2.0"),
    ("Apache-2.0", 'Licensed under the Apache License, Version 2.0 (the "License")'),
    ("MIT", "Released under the MIT License"),
    ("MIT", "Licensed under the MIT License"),
    ("MIT", "The MIT License"),
    ("GPL-3.0-only", "This work is licensed under the GNU General Public License, version 3"),
    ("GPL-2.0-only", "This work is licensed under the GNU General Public License, version 2"),
    ("CC-BY-NC-4.0", "Licensed under CC BY-NC 4.0"),
    ("CC-BY-4.0", "Licensed under CC BY 4.0"),
    ("CC-BY-SA-4.0", "Licensed under CC BY-SA 4.0"),
    ("CC0-1.0", "This work is released under CC0 1.0"),
    ("MPL-2.0", "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can obtain one at https://mozilla.org/MPL/2.0/."),
    ("MIT", """Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the "Software"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions: The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software. THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE."""),
    ("ISC", """Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies. THE SOFTWARE IS PROVIDED "AS IS" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE."""),
    ("BSD-2-Clause", """Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met:
1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer.
2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution.
THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS "AS IS" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE."""),
    ("BSD-3-Clause", """Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met:
1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer.
2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution.
3. Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission.
THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS "AS IS" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE."""),
    ("0BSD", """Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted. THE SOFTWARE IS PROVIDED "AS IS" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE."""),
    ("Unlicense", """This is free and unencumbered software released into the public domain. Anyone is free to copy, modify, publish, use, compile, sell, or distribute this software, either in source code form or as a compiled binary, for any purpose, commercial or non-commercial, and by any means. In jurisdictions that recognize copyright laws, the author or authors of this software dedicate any and all copyright interest in the software to the public domain. We make this dedication for the benefit of the public at large and to the detriment of our heirs and successors. We intend this dedication to be an overt act of relinquishment in perpetuity of all present and future rights to this software under copyright law. THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE. For more information, please refer to <https://unlicense.org>"""),
    ("Zlib", """This software is provided 'as-is', without any express or implied warranty. In no event will the authors be held liable for any damages arising from the use of this software. Permission is granted to anyone to use this software for any purpose, including commercial applications, and to alter it and redistribute it freely, subject to the following restrictions:
1. The origin of this software must not be misrepresented; you must not claim that you wrote the original software. If you use this software in a product, an acknowledgment in the product documentation would be appreciated but is not required.
2. Altered source versions must be plainly marked as such, and must not be misrepresented as being the original software.
3. This notice may not be removed or altered from any source distribution."""),
    ("BSL-1.0", """Permission is hereby granted, free of charge, to any person or organization obtaining a copy of the software and accompanying documentation covered by this license (the "Software") to use, reproduce, display, distribute, execute, and transmit the Software, and to prepare derivative works of the Software, and to permit third-parties to whom the Software is furnished to do so, all subject to the following: The copyright notices in the Software and this entire statement, including the above license grant, this restriction and the following disclaimer, must be included in all copies of the Software, in whole or in part, and all derivative works of the Software, unless such copies or derivative works are solely in the form of machine-executable object code generated by a source language processor. THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE, TITLE AND NON-INFRINGEMENT. IN NO EVENT SHALL THE COPYRIGHT HOLDERS OR ANYONE DISTRIBUTING THE SOFTWARE BE LIABLE FOR ANY DAMAGES OR OTHER LIABILITY, WHETHER IN CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE."""),
    ("Apache-2.0", """Licensed under the Apache License, Version 2.0 (the "License"); you may not use this file except in compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0 Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an "AS IS" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. See the License for the specific language governing permissions and limitations under the License."""),
    ("GPL-2.0-or-later", """This program is free software; you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation; either version 2 of the License, or (at your option) any later version. This program is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE. See the GNU General Public License for more details."""),
    ("GPL-3.0-or-later", """This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version. This program is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE. See the GNU General Public License for more details."""),
    ("AGPL-3.0-or-later", """This program is free software: you can redistribute it and/or modify it under the terms of the GNU Affero General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version. This program is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE. See the GNU Affero General Public License for more details."""),
    ("LGPL-2.1-or-later", """This library is free software; you can redistribute it and/or modify it under the terms of the GNU Lesser General Public License as published by the Free Software Foundation; either version 2.1 of the License, or (at your option) any later version. This library is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE. See the GNU Lesser General Public License for more details."""),
]
# Long licences by identifier, beginning and length of the canonical text (up to the end of its terms) and its SHA-256.
DIGESTS = [
    ("Apache-2.0", "apache license 2 0 january 2004 www apache org l", 8795, "0b01bfa19111691c8b967dd11cb8ddc341bf84826212222345a3257db3a6b31f"),
    ("Artistic-1.0-Perl", "the artistic license preamble the intent of this", 5716, "a0a87a997f049b5024b7be16abcba7b81b3e408b170d934145a5507628b76755"),
    ("CC0-1.0", "creative commons legal code cc0 1 0 universal cr", 6663, "29d4c14e673c3e5a54b0348eb8b3441c6f70bbd557ea091a8241f31b77d9bfa6"),
    ("GFDL-1.2", "gnu free documentation license 1 2 november 2002", 19237, "66f8f8396f2f698275c49aac47f1e78154be4f4f735de3eebdb19a3252d241d9"),
    ("GFDL-1.3", "gnu free documentation license 1 3 3 november 20", 21646, "a83ebf9eac521bba296bcf5a232ca20786c61e65628bc053f4a7e0864f5e95a4"),
    ("GPL-1.0", "gnu general public license 1 february 1989 51 fr", 9268, "e96e0db25862b818422338fe3fd19baa81c470fda8d84c5d12e88d76245fc035"),
    ("GPL-2.0", "gnu general public license 2 june 1991 51 frankl", 14332, "7f7e8d8cae1701248d5095af89c5f8a3460096a705451723ea886f176b2ba0d5"),
    ("GPL-3.0", "gnu general public license 3 29 june 2007 everyo", 30678, "138b3700fc3b4feac8a54ef11ca8d3831983937c104c0c0996c65128f5fb500b"),
    ("LGPL-2.0", "gnu library general public license 2 june 1991 5", 22052, "3ad2309aaf38dd0eab03945c2885ade517e93c9d1319738c39efc5916ad13330"),
    ("LGPL-2.1", "gnu lesser general public license 2 1 february 1", 23090, "406106f27fb055189805d3f19f7961323d6a7b75e93982b006ceeca1812d5893"),
    ("LGPL-3.0", "gnu lesser general public license 3 29 june 2007", 6848, "4f0f2d1a78969f36e9e4f18f3092ede535f8b2ee6cd22e2b7c178a8d24443547"),
    ("MPL-1.1", "mozilla public license 1 1 definitions 1 0 1 com", 22064, "126fac75122d69326c0ed878d1bf8fcc5a89c5cd4becd6951f1176e0e7af355d"),
    ("MPL-2.0", "mozilla public license 2 0 definitions 1 1 contr", 14154, "6a95b677a2e446b653ab379508a8bb7a300861ce02739aedc2c7dc098d3b2220"),
]
# Spellings held to be equal, applied in this order to lower-case text without punctuation.
SPELLINGS = [(r"\blicence", "license"), (r"\bversion\b|\bver\b|\bv (?=[0-9])", ""), (r"\bsub licen[sc]e\b", "sublicense"), (r"\bnon infringement\b", "noninfringement"), (r"\bcopyright owner", "copyright holder"), (r"\ball rights reserved\b", ""), (r"\bhttps?\b", ""), (r"\bfavour", "favor"), (r" +", " ")]
COPYRIGHT_LINE = r"(?m)^[^\p{L}\n]*(copyright\s*(\(c\)|©|[0-9<\[]|by )|\(c\)\s*[0-9<\[]|©)[^\n]*$"
LIST_MARK = r"(?m)^[^\p{L}\p{N}\n]*(\(?[0-9]{1,2}[.)]|\(?[a-z][.)])\s"
# Titles that may stand before a licence body, and how such bodies begin.
TITLE = r"^(the )?(mit|expat|isc|zlib|zlib libpng|bsd|bsd [0-9] clause|[0-9] clause bsd|zero clause bsd|0bsd|bsd zero clause|new bsd|modified bsd|simplified bsd|revised bsd|boost software|unlicense)( license)?( mit| expat)?( 1 0 august 17th 2003)? (permission|redistribution|this software|this is free)"
LONG, HEAD = 30, 48


def canonical(text: Column) -> Column:
    """The canonical form of a text: copyright lines and list marks out, lower case, only letters and digits with single blanks, equal spellings."""
    out = F.regexp_replace(F.lower(text), COPYRIGHT_LINE, " ")
    out = F.regexp_replace(out, LIST_MARK, " ")
    out = F.regexp_replace(out, r"[^\p{L}\p{N}]+", " ")
    for pattern, by in SPELLINGS:
        out = F.regexp_replace(out, pattern, by)
    return F.trim(out)


def anchors(notices: list[tuple[str, str]] | None = None, size: int = 5) -> list[str]:
    """Fragments of which every unit that can match must hold one. They are beginnings of words that no spelling rule makes
    or changes within the fragment, so canonical forms keep them; the fewest that cover all notices, chosen greedily."""
    made = [re.sub(r"\W", "", by)[:size] for _, by in SPELLINGS if re.sub(r"\W", "", by)]
    taken = {m for m in made if m != "licen"} | {"copyr", "sub l", "versi"}
    left = [{w[:size] for w in re.findall(r"[a-z]+", text.lower()) if len(w) >= size} - taken for _, text in notices or [*NOTICES, *((d[0], d[1]) for d in DIGESTS)]]
    out: list[str] = []
    while left:
        if not all(left):
            return []
        out.append(max(sorted(set().union(*left)), key=lambda f: sum(f in x for x in left)))
        left = [x for x in left if out[-1] not in x]
    return out


def holds_anchor(text: Column, fragments: list[str]) -> Column:
    """Whether a lower-case text holds a fragment; with none, everything is looked up."""
    found = F.lit(not fragments)
    for f in fragments:
        found = found | F.contains(text, F.lit(f))
    return found


def known_licenses(spark: SparkSession, notices: list[tuple[str, str]] | None = None) -> DataFrame:
    """(digest, license, head, length): one row for each canonical form; of equal forms the first identifier in order counts. head and length are null for
    forms of less than `LONG` words, which are not looked up inside documents."""
    known = spark.createDataFrame(notices or NOTICES, "license string, text string").select("license", canonical(F.col("text")).alias("c"))
    known = known.select(F.sha2("c", 256).alias("digest"), "license", *(F.when(F.size(F.split("c", " ")) >= LONG, x).alias(n) for x, n in ((F.substring("c", 1, HEAD), "head"), (F.length("c"), "length"))))
    if notices is None:
        known = known.unionByName(spark.createDataFrame([(d, a, h, n) for a, h, n, d in DIGESTS], "digest string, license string, head string, length int"))
    return known.groupBy("digest").agg(F.min("license").alias("license"), F.first("head").alias("head"), F.first("length").alias("length"))


def stretches(c: Column, heads: Column) -> Column:
    """All stretches of a canonical text that begin with a head at a word and have its length, with the place where they begin."""

    def of(h: Column) -> Column:
        gaps = F.transform(F.split(c, h["head"]), F.char_length)
        starts = F.transform(F.sequence(F.lit(1), F.size(gaps) - 1), lambda i: F.aggregate(F.slice(gaps, 1, i), F.lit(1), lambda x, y: x + y) + (i - 1) * F.char_length(h["head"]))
        whole = F.filter(starts, lambda p: ((p == 1) | (F.substring(c, p - 1, 1) == " ")) & F.substring(c, p + h["length"], 1).isin("", " ") & (F.char_length(c) >= p + h["length"] - 1))
        return F.when(F.contains(c, h["head"]), F.transform(whole, lambda p: F.struct((-1 - p).alias("pos"), F.substring(c, p, h["length"]).alias("unit"), F.lit(True).alias("done")))).otherwise(F.array().cast("array<struct<pos:int,unit:string,done:boolean>>"))

    return F.flatten(F.transform(heads, of))


def scan_licenses(docs: DataFrame, known: DataFrame, id_col: str = "doc_id", text_col: str = "text", fragments: list[str] | None = None) -> DataFrame:
    """fragments: anchors() of the known licences, or none for a table of unknown origin. Per row with a match: id, licenses (sorted, distinct), n_units (places with a match), whole_text (the whole document is a licence)."""
    text = text_or_empty(text_col)
    heads = known.where("head is not null").select("head", "length").distinct().orderBy("head", "length").collect()  # of fixed size, like the table
    head_list = F.array(*[F.struct(F.lit(r["head"]).alias("head"), F.lit(r["length"]).alias("length")) for r in heads]) if heads else F.array().cast("array<struct<head:string,length:int>>")
    lines = F.transform(F.filter(F.split(text, "\n"), lambda x: F.char_length(x) > 0), lambda x, i: F.struct(i.alias("pos"), x.alias("unit"), F.lit(False).alias("done")))
    docs = docs.where(holds_anchor(F.lower(text), fragments or [])).select(F.col(id_col).alias("_id"), *row_keys(id_col, text_col), canonical(text).alias("_c"), lines.alias("_lines"))
    whole = F.array(F.struct(F.lit(-1).alias("pos"), F.regexp_replace("_c", TITLE, "$6").alias("unit"), F.lit(True).alias("done")))
    rows = docs.select("_id", "_k1", "_k2", F.explode(F.concat(whole, "_lines", stretches(F.col("_c"), head_list))).alias("u"))
    rows = rows.where(F.col("u.done") | holds_anchor(F.lower("u.unit"), fragments or []))
    digests = rows.select("_id", "_k1", "_k2", F.col("u.pos").alias("pos"), F.when(F.col("u.done"), F.col("u.unit")).otherwise(canonical(F.col("u.unit"))).alias("c")).where("c <> ''")
    hits = digests.withColumn("digest", F.sha2("c", 256)).drop("c").join(F.broadcast(known.select("digest", "license")), "digest")
    # copies of a row meet here: their hits are counted by position first, so a hot row arrives already summed
    once = hits.groupBy("_k1", "_k2", "_id", "pos", "license").agg(F.count("*").alias("copies"))
    per_row = once.groupBy("_k1", "_k2", "_id").agg(F.sort_array(F.collect_set("license")).alias("licenses"), F.count("*").alias("n_units"), F.max(F.col("pos") == -1).alias("whole_text"), F.max("copies").alias("copies"))
    repeated = per_row.select("*", F.explode(F.array_repeat(F.lit(1), F.col("copies").cast("int"))).alias("_"))
    return repeated.select(F.col("_id").alias(id_col), "licenses", "n_units", "whole_text")


def op5_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return scan_licenses(docs, known_licenses(spark), fragments=anchors()).select("doc_id", F.array_join("licenses", ",").alias("licenses"), "n_units", "whole_text")


def _sql_canonical(x: str) -> str:
    out = f"regexp_replace(lower({x}), '{COPYRIGHT_LINE}', ' ', 'g')"
    out = f"regexp_replace({out}, '{LIST_MARK}', ' ', 'g')"
    out = f"regexp_replace({out}, '[^\\p{{L}}\\p{{N}}]+', ' ', 'g')"
    for pattern, by in SPELLINGS:
        pattern = r"\bv ([0-9])" if "(?=" in pattern else pattern
        if pattern.startswith(r"\bv "):
            out = f"regexp_replace(regexp_replace({out}, '\\bversion\\b|\\bver\\b', '', 'g'), '{pattern}', '\\1', 'g')"
        else:
            out = f"regexp_replace({out}, '{pattern}', '{by}', 'g')"
    return f"trim({out})"


SQL = f"""
WITH notices AS (SELECT l, {_sql_canonical("t")} AS c FROM (VALUES {", ".join("('" + a + "', '" + b.replace("'", "''") + "')" for a, b in NOTICES)}) v(l, t)),
texts AS (SELECT sha256(c) AS digest, l, CASE WHEN len(string_split(c, ' ')) >= {LONG} THEN substr(c, 1, {HEAD}) END AS head, length(c) AS n FROM notices
  UNION ALL SELECT * FROM (VALUES {", ".join(f"('{d}', '{a}', '{h}', {n})" for a, h, n, d in DIGESTS)}) v(digest, l, head, n)),
known AS (SELECT digest, min(l) AS license FROM texts GROUP BY 1),
heads AS (SELECT DISTINCT head, n FROM texts WHERE head IS NOT NULL),
docs AS MATERIALIZED (SELECT row_number() OVER () AS r, doc_id, coalesce(text, '') AS text, {_sql_canonical("coalesce(text, '')")} AS c FROM documents),
found AS (SELECT r, doc_id, c, head, n, generate_subscripts(string_split(c, head), 1) AS i, string_split(c, head) AS gaps FROM docs JOIN heads ON contains(c, head)),
starts AS (SELECT r, doc_id, c, n, CAST(1 + list_sum(list_transform(gaps[1:i], lambda g: length(g))) + (i - 1) * length(head) AS BIGINT) AS p FROM found WHERE i < len(gaps)),
units AS (SELECT r, doc_id, -1 AS pos, regexp_replace(c, '{TITLE}', '\\6') AS c FROM docs
  UNION ALL SELECT r, doc_id, generate_subscripts(string_split(text, chr(10)), 1), {_sql_canonical("unnest(string_split(text, chr(10)))")} FROM docs
  UNION ALL SELECT r, doc_id, -1 - p, substr(c, p, n) FROM starts WHERE (p = 1 OR substr(c, p - 1, 1) = ' ') AND substr(c, p + n, 1) IN ('', ' ') AND length(c) >= p + n - 1),
hits AS (SELECT DISTINCT r, doc_id, pos, license FROM units JOIN known ON digest = sha256(c) WHERE c <> '')
SELECT doc_id, array_to_string(list_sort(list(DISTINCT license)), ',') AS licenses, count(*) AS n_units, bool_or(pos = -1) AS whole_text FROM hits GROUP BY r, doc_id
"""
