"""Licence scan by canonical digests, in DataFrame operations only.

A text is made canonical (lower case, no copyright lines, one spelling of words that have two, no punctuation, single spaces)
and digested; digests are hash-joined with those of known licences, made canonical by the same expressions. Known texts are a
parameter, so their side of the join is small and is broadcast. ``identify`` joins whole texts;
``notices`` looks up the lines of each text in the same way, within its row, and finds licence notices inside documents.

Defined results: a null text counts as empty; a text that is empty once canonical matches nothing; a null id is an id like any
other; rows are independent whatever ids they share, so equal texts agree and others keep their own result; of licences with equal
canonical texts the first in order of name counts; an empty table gives an empty result; further columns pass through ``identify``.
"""

from __future__ import annotations

import re
from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from adaptivejoin.llm.common import table

#: Lines about copyright with what every such line contains, and spellings that licence matching takes as equal.
COPYRIGHT_LINE = r"(?m)^[^a-z0-9\n]*(copyright|\(c\)|©|all rights reserved)[^\n]*$"
COPYRIGHT_SIGNS = ("copyright", "(c)", "©", "all rights reserved")
SPELLINGS = (
    ("authoris", "authoriz"), ("organis", "organiz"), ("recognis", "recogniz"), ("utilis", "utiliz"), ("customis", "customiz"), ("favour", "favor"), ("labour", "labor"),
    ("endeavour", "endeavor"), ("licenc", "licens"), ("sub-licens", "sublicens"), ("sub licens", "sublicens"), ("offence", "offense"), ("defence", "defense"),
    ("acknowledgement", "acknowledgment"), ("judgement", "judgment"), ("cancell", "cancel"), ("labell", "label"), ("catalogue", "catalog"), ("analogue", "analog"),
    ("non-commercial", "noncommercial"), ("non commercial", "noncommercial"), ("whilst", "while"), ("https:", "http:"),
)
NOT_WORDS = r"[^a-z0-9\x80-\x{10FFFF}]+"

_PERMISSION = "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions:"
_BSD_OPENING = "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met:"
_BSD_SOURCE = "Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer."
_BSD_BINARY = "Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution."
_BSD_WARRANTY = "THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS \"AS IS\" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE."
_ISC_WARRANTY = "THE SOFTWARE IS PROVIDED \"AS IS\" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE."

_AS_IS = "THE SOFTWARE IS PROVIDED \"AS IS\", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE."
_MIT = f"{_PERMISSION}\n\nThe above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software.\n\n{_AS_IS}"
_MIT_0 = f"{_PERMISSION.removesuffix(', subject to the following conditions:')}.\n\n{_AS_IS}"
_ISC_GRANT = "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted"
_ISC = f"{_ISC_GRANT}, provided that the above copyright notice and this permission notice appear in all copies.\n\n{_ISC_WARRANTY}"
_BSD_2 = f"{_BSD_OPENING}\n\n1. {_BSD_SOURCE}\n\n2. {_BSD_BINARY}\n\n{_BSD_WARRANTY}"
_BSD_3 = f"{_BSD_OPENING}\n\n1. {_BSD_SOURCE}\n\n2. {_BSD_BINARY}\n\n3. Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission.\n\n{_BSD_WARRANTY}"
_ZLIB = "This software is provided 'as-is', without any express or implied warranty. In no event will the authors be held liable for any damages arising from the use of this software.\n\nPermission is granted to anyone to use this software for any purpose, including commercial applications, and to alter it and redistribute it freely, subject to the following restrictions:\n\n1. The origin of this software must not be misrepresented; you must not claim that you wrote the original software. If you use this software in a product, an acknowledgment in the product documentation would be appreciated but is not required.\n\n2. Altered source versions must be plainly marked as such, and must not be misrepresented as being the original software.\n\n3. This notice may not be removed or altered from any source distribution."
_BOOST = "Permission is hereby granted, free of charge, to any person or organization obtaining a copy of the software and accompanying documentation covered by this license (the \"Software\") to use, reproduce, display, distribute, execute, and transmit the Software, and to prepare derivative works of the Software, and to permit third-parties to whom the Software is furnished to do so, all subject to the following:\n\nThe copyright notices in the Software and this entire statement, including the above license grant, this restriction and the following disclaimer, must be included in all copies of the Software, in whole or in part, and all derivative works of the Software, unless such copies or derivative works are solely in the form of machine-executable object code generated by a source language processor.\n\nTHE SOFTWARE IS PROVIDED \"AS IS\", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE, TITLE AND NON-INFRINGEMENT. IN NO EVENT SHALL THE COPYRIGHT HOLDERS OR ANYONE DISTRIBUTING THE SOFTWARE BE LIABLE FOR ANY DAMAGES OR OTHER LIABILITY, WHETHER IN CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE."
_UNLICENSE = f"This is free and unencumbered software released into the public domain.\n\nAnyone is free to copy, modify, publish, use, compile, sell, or distribute this software, either in source code form or as a compiled binary, for any purpose, commercial or non-commercial, and by any means.\n\nIn jurisdictions that recognize copyright laws, the author or authors of this software dedicate any and all copyright interest in the software to the public domain. We make this dedication for the benefit of the public at large and to the detriment of our heirs and successors. We intend this dedication to be an overt act of relinquishment in perpetuity of all present and future rights to this software under copyright law.\n\n{_AS_IS.replace('AUTHORS OR COPYRIGHT HOLDERS', 'AUTHORS')}\n\nFor more information, please refer to <https://unlicense.org>"

#: Known licences, with and without the title that often stands above them, and one-line notices that name one.
LICENCES: Sequence[tuple[str, str]] = (
    ("MIT", _MIT), ("MIT", f"MIT License\n\n{_MIT}"), ("MIT", f"The MIT License (MIT)\n\n{_MIT}"),
    ("MIT-0", _MIT_0), ("MIT-0", f"MIT No Attribution\n\n{_MIT_0}"),
    ("ISC", _ISC), ("ISC", f"ISC License\n\n{_ISC}"),
    ("0BSD", f"{_ISC_GRANT}.\n\n{_ISC_WARRANTY}"), ("0BSD", f"BSD Zero Clause License\n\n{_ISC_GRANT}.\n\n{_ISC_WARRANTY}"),
    ("BSD-2-Clause", _BSD_2), ("BSD-2-Clause", f"BSD 2-Clause License\n\n{_BSD_2}"),
    ("BSD-3-Clause", _BSD_3), ("BSD-3-Clause", f"BSD 3-Clause License\n\n{_BSD_3}"),
    ("Zlib", _ZLIB), ("Zlib", f"zlib License\n\n{_ZLIB}"),
    ("BSL-1.0", f"Boost Software License - Version 1.0 - August 17th, 2003\n\n{_BOOST}"), ("Unlicense", _UNLICENSE),
)
IDENTIFIERS = (
    "0BSD", "AGPL-3.0-only", "AGPL-3.0-or-later", "Apache-2.0", "BSD-2-Clause", "BSD-3-Clause", "BSL-1.0", "CC-BY-4.0", "CC-BY-SA-4.0", "CC0-1.0", "EPL-2.0",
    "GPL-2.0-only", "GPL-2.0-or-later", "GPL-3.0-only", "GPL-3.0-or-later", "ISC", "LGPL-2.1-only", "LGPL-2.1-or-later", "LGPL-3.0-only", "LGPL-3.0-or-later", "MIT", "MIT-0", "MPL-2.0", "Unlicense", "Zlib",
)
NOTICES: Sequence[tuple[str, str]] = (
    ("MIT", "Released under the MIT License."), ("MIT", "Licensed under the MIT License."),
    ("Apache-2.0", "Licensed under the Apache License, Version 2.0."),
    ("GPL-3.0", "This work is licensed under the GNU General Public License, version 3."),
    ("CC-BY-NC-4.0", "Licensed under CC BY-NC 4.0."),
    *((name, f"SPDX-License-Identifier: {name}") for name in IDENTIFIERS),
)


def folded(text: Column) -> Column:
    """Lower case, without copyright lines, in one spelling; line breaks stay."""
    t = F.lower(F.coalesce(text, F.lit("")))
    about = F.lit(False)
    for sign in COPYRIGHT_SIGNS:
        about = about | t.contains(sign)
    t = F.when(about, F.regexp_replace(t, COPYRIGHT_LINE, "")).otherwise(t)
    for form, other in SPELLINGS:
        t = F.replace(t, F.lit(form), F.lit(other))
    return t


def canonical(text: Column) -> Column:
    return _spaced(folded(text))


def _spaced(t: Column) -> Column:
    return F.trim(F.regexp_replace(t, NOT_WORDS, " "))


def _longest_word(text: str) -> str:
    """A word that any text with the same canonical form contains once it is folded."""
    t = text.lower()
    for form, other in SPELLINGS:
        t = t.replace(form, other)
    return max(re.findall("[a-z0-9]+", t), key=len)


def digest(text: Column) -> Column:
    """SHA-256 of the canonical text; null if nothing is left of it."""
    c = canonical(text)
    return F.when(c != "", F.sha2(c, 256))


def _entries(texts: Sequence[tuple[str, str]]) -> Column:
    """The known texts and their digests, in order of name: constants, which the planner computes once."""
    return F.array(*[F.struct(F.lit(k).alias("license_id"), digest(F.lit(v)).alias("known_digest")) for k, v in sorted(texts)])


def known(spark: SparkSession, texts: Sequence[tuple[str, str]]) -> DataFrame:
    """(license_id, known_digest), one row for each distinct digest."""
    rows = spark.range(1).select(F.explode(_entries(texts)).alias("e")).select("e.license_id", "e.known_digest")
    return rows.groupBy("known_digest").agg(F.min("license_id").alias("license_id"))


def _identified(rows: DataFrame, texts: Sequence[tuple[str, str]]) -> DataFrame:
    """``rows`` with the licence whose digest is theirs; the known side has a row for each text of a parameter."""
    return rows.join(F.broadcast(known(rows.sparkSession, texts)), F.col("digest") == F.col("known_digest"), "left").drop("known_digest")


def identify(df: DataFrame, texts: Sequence[tuple[str, str]] = LICENCES, text_col: str = "text") -> DataFrame:
    """(row, digest, license_id): the licence that a whole text is, or null; ``row`` holds the input's own columns."""
    own = df.select(F.struct(*[F.col(f"`{c}`") for c in df.columns]).alias("row"), digest(F.col(f"`{text_col}`")).alias("digest"))
    return _identified(own, texts)


def _notices_in(t: Column, texts: Sequence[tuple[str, str]]) -> Column:
    """The notices among the lines of a folded text, as an array of (line, license_id). Only texts with the longest word of one are
    cut into lines."""
    likely = F.lit(False)
    for word in sorted({_longest_word(x) for _, x in texts}):
        likely = likely | t.contains(word)
    entries = _entries(texts)

    def named(line: Column) -> Column:
        c = _spaced(line)
        d = F.when(c != "", F.sha2(c, 256))
        return F.get(F.filter(entries, lambda e: e["known_digest"] == d), 0)["license_id"]

    found = F.transform(F.split(t, "\n", -1), lambda line, i: F.struct(i.alias("line"), named(line).alias("license_id")))
    return F.when(likely, F.filter(found, lambda x: x["license_id"].isNotNull()))


def notices(df: DataFrame, texts: Sequence[tuple[str, str]] = NOTICES, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, line, license_id) of the lines that are a known notice."""
    t = df.select(F.col(id_col).alias("doc_id"), folded(F.col(text_col)).alias("t"))
    return t.select("doc_id", F.inline(_notices_in(F.col("t"), texts)))


def scan(df: DataFrame) -> DataFrame:
    """(doc_id, digest, license_id, n_notices, notice_ids) of every row: what the whole text is, and notices among its lines. One pass:
    a text is folded once, and its lines are looked up within the row."""
    t = df.select("doc_id", folded(F.col("text")).alias("t"))
    c = t.select("doc_id", _spaced(F.col("t")).alias("c"), _notices_in(F.col("t"), NOTICES).alias("inside"))
    own = c.select("doc_id", F.when(F.col("c") != "", F.sha2("c", 256)).alias("digest"), "inside")
    ids = F.array_join(F.array_sort(F.array_distinct(F.transform("inside", lambda x: x["license_id"]))), ",")
    return _identified(own, LICENCES).select("doc_id", "digest", "license_id", F.coalesce(F.size("inside"), F.lit(0)).cast("long").alias("n_notices"), F.coalesce(ids, F.lit("")).alias("notice_ids"))


def query(spark, sf_dir: str) -> DataFrame:
    return scan(table(spark, sf_dir, "documents"))


def _canonical_sql(column: str) -> str:
    out = f"regexp_replace(lower(coalesce({column}, '')), '{COPYRIGHT_LINE}', '', 'g')"
    for form, other in SPELLINGS:
        out = f"replace({out}, '{form}', '{other}')"
    return f"trim(regexp_replace({out}, '{NOT_WORDS}', ' ', 'g'))"


def _known_sql(texts: Sequence[tuple[str, str]]) -> str:
    rows = ", ".join("('" + k + "', '" + v.replace("'", "''") + "')" for k, v in texts)
    return f"SELECT sha256(c) AS known_digest, min(license_id) AS license_id FROM (SELECT license_id, {_canonical_sql('t')} AS c FROM (VALUES {rows}) v(license_id, t)) GROUP BY 1"


ORACLE = f"""
WITH licences AS ({_known_sql(LICENCES)}), known_notices AS ({_known_sql(NOTICES)}),
whole AS (SELECT doc_id, CASE WHEN c <> '' THEN sha256(c) END AS digest FROM (SELECT doc_id, {_canonical_sql('text')} AS c FROM documents)),
lines AS (SELECT doc_id, k, {_canonical_sql('l')} AS c FROM (SELECT doc_id, unnest(ls) AS l, generate_subscripts(ls, 1) AS k FROM (SELECT doc_id, string_split(text, chr(10)) AS ls FROM documents))),
inside AS (
  SELECT doc_id, count(DISTINCT k) AS n, string_agg(DISTINCT license_id, ',' ORDER BY license_id) AS ids
  FROM lines JOIN known_notices ON c <> '' AND sha256(c) = known_digest GROUP BY doc_id
)
SELECT w.doc_id, w.digest, l.license_id, coalesce(i.n, 0) AS n_notices, coalesce(i.ids, '') AS notice_ids
FROM whole w LEFT JOIN licences l ON w.digest = l.known_digest LEFT JOIN inside i ON w.doc_id = i.doc_id
"""
