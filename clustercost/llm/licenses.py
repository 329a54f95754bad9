"""Licence scans: canonical digests of entire texts, looked up by a hash join.

Canonical form, in Spark expressions only: lower case; copyright lines and
rights-reserved lines go; equivalent spellings become one; everything but letters and
digits becomes one space.  Two texts match when the SHA-256 digests of their canonical
forms are equal, so a match concerns the entire text.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Equivalent spellings, the later ones become the first.
SPELLINGS = (
    ("license", "licence"),
    ("licenses", "licences"),
    ("licensed", "licenced"),
    ("sublicense", "sublicence", "sub license"),
    ("noncommercial", "non commercial"),
    ("noninfringement", "non infringement"),
    ("holder", "owner"),
    ("holders", "owners"),
    ("fulfill", "fulfil"),
    ("favor", "favour"),
    ("judgment", "judgement"),
    ("organization", "organisation"),
    ("authorize", "authorise"),
    ("authorized", "authorised"),
)

#: Texts of well-known short licences and notices.
MIT = """Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the "Software"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions:

The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software.

THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE."""
ISC = """Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies.

THE SOFTWARE IS PROVIDED "AS IS" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE."""
ZERO_BSD = """Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted.

THE SOFTWARE IS PROVIDED "AS IS" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE."""
BSD_HEAD = """Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met:

1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer.

2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution."""
BSD_NAMES = """3. Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission."""
BSD_TAIL = """THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS "AS IS" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE."""
BSD_2 = "\n\n".join((BSD_HEAD, BSD_TAIL))
BSD_3 = "\n\n".join((BSD_HEAD, BSD_NAMES, BSD_TAIL))
ZLIB = """This software is provided 'as-is', without any express or implied warranty. In no event will the authors be held liable for any damages arising from the use of this software.

Permission is granted to anyone to use this software for any purpose, including commercial applications, and to alter it and redistribute it freely, subject to the following restrictions:

1. The origin of this software must not be misrepresented; you must not claim that you wrote the original software. If you use this software in a product, an acknowledgment in the product documentation would be appreciated but is not required.

2. Altered source versions must be plainly marked as such, and must not be misrepresented as being the original software.

3. This notice may not be removed or altered from any source distribution."""
UNLICENSE = """This is free and unencumbered software released into the public domain.

Anyone is free to copy, modify, publish, use, compile, sell, or distribute this software, either in source code form or as a compiled binary, for any purpose, commercial or non-commercial, and by any means.

In jurisdictions that recognize copyright laws, the author or authors of this software dedicate any and all copyright interest in the software to the public domain. We make this dedication for the benefit of the public at large and to the detriment of our heirs and successors. We intend this dedication to be an overt act of relinquishment in perpetuity of all present and future rights to this software under copyright law.

THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE.

For more information, please refer to <https://unlicense.org/>"""
KNOWN = (
    ("BSD-2-Clause", BSD_2),
    ("BSD-2-Clause", "BSD 2-Clause License\n\n" + BSD_2),
    ("BSD-3-Clause", BSD_3),
    ("BSD-3-Clause", "BSD 3-Clause License\n\n" + BSD_3),
    ("Zlib", ZLIB),
    ("Zlib", "zlib License\n\n" + ZLIB),
    ("Unlicense", UNLICENSE),
    ("MIT", MIT),
    ("MIT", "MIT License\n\n" + MIT),
    ("ISC", ISC),
    ("ISC", "ISC License\n\n" + ISC),
    ("0BSD", ZERO_BSD),
    ("MIT", "Released under the MIT License."),
    ("MIT", "Licensed under the MIT License."),
    ("Apache-2.0", "Licensed under the Apache License, Version 2.0."),
    ("GPL-3.0", "This work is licensed under the GNU General Public License, version 3."),
    ("CC-BY-NC-4.0", "Licensed under CC BY-NC 4.0."),
    ("CC-BY-4.0", "Licensed under CC BY 4.0."),
)

#: Lines that go.  A copyright line names a year or bears a sign.
COPYRIGHT_LINE = r"(?m)^[^\p{L}\p{N}\n]*(copyright[^\n]*([0-9]{4}|©|\(c\))[^\n]*|\(c\)[^\n]*|©[^\n]*)$"
RESERVED_LINE = r"(?m)^[^\p{L}\p{N}\n]*all rights reserved[^\p{L}\p{N}\n]*$"


def canonical(text: Column) -> Column:
    """The canonical form of a text column; null stays null."""
    low = F.lower(text)
    low = F.regexp_replace(low, COPYRIGHT_LINE, " ")
    low = F.regexp_replace(low, RESERVED_LINE, " ")
    low = F.replace(low, F.lit("&"), F.lit(" and "))
    # each word has spaces of its own, so that equivalents next to each other are all found
    low = F.concat(F.lit(" "), F.replace(F.trim(F.regexp_replace(low, r"[^\p{L}\p{N}]+", " ")), F.lit(" "), F.lit("  ")), F.lit(" "))
    for one, *others in SPELLINGS:
        for other in others:
            low = F.replace(low, F.lit(f" {other.replace(' ', '  ')} "), F.lit(f" {one} "))
    return F.trim(F.replace(low, F.lit("  "), F.lit(" ")))


def digest(text: Column) -> Column:
    return F.sha2(canonical(text), 256)


def known_licenses(spark: SparkSession, texts: tuple[tuple[str, str], ...] | list[tuple[str, str]] = KNOWN) -> DataFrame:
    """``digest, license``, one row for each digest (the first name in order where texts collide)."""
    rows = spark.createDataFrame(list(texts), "license string, text string")
    return rows.groupBy(digest(F.col("text")).alias("digest")).agg(F.min("license").alias("license"))


def licenses_in(spark: SparkSession, folder: str) -> DataFrame:
    """``digest, license`` of the whole text files of a folder, named by their files: for long licences, beside ``known_licenses``."""
    files = spark.read.text(folder, wholetext=True).select(F.regexp_extract(F.col("_metadata.file_name"), r"^(.*?)(?:\.txt)?$", 1).alias("license"), F.col("value").alias("text"))
    return files.groupBy(digest(F.col("text")).alias("digest")).agg(F.min("license").alias("license"))


def scan_licenses(documents: DataFrame, known: DataFrame) -> DataFrame:
    """Per document row: ``doc_id, n_chars, digest, license`` (null where no known text matches).

    Null texts have no digest and no licence; a text without letters and digits has the digest
    of the empty form and matches nothing; repeated rows are looked up each for itself; an
    empty table gives no rows; further columns are not read.  The lookup table is joined by
    digest, by broadcast only where Spark's own size check allows it.
    """
    docs = documents.select("doc_id", F.length("text").cast("bigint").alias("n_chars"), digest(F.col("text")).alias("digest"))
    usable = known.where(F.col("digest") != F.sha2(F.lit(""), 256)).select("digest", "license")
    return docs.join(usable, "digest", "left").select("doc_id", "n_chars", "digest", "license")


def canonical_sql(column: str) -> str:
    """The same form as a DuckDB expression."""
    low = f"regexp_replace(regexp_replace(lower({column}), '{COPYRIGHT_LINE}', ' ', 'g'), '{RESERVED_LINE}', ' ', 'g')"
    low = f"' ' || replace(trim(regexp_replace(replace({low}, '&', ' and '), '[^\\p{{L}}\\p{{N}}]+', ' ', 'g')), ' ', '  ') || ' '"
    for one, *others in SPELLINGS:
        for other in others:
            low = f"replace({low}, ' {other.replace(' ', '  ')} ', ' {one} ')"
    return f"trim(replace({low}, '  ', ' '))"


def scan_sql() -> str:
    quoted = lambda x: "'" + x.replace("'", "''") + "'"
    values = ", ".join(f"({quoted(a)}, {quoted(b)})" for a, b in KNOWN)
    return f"""
WITH k AS (SELECT sha256({canonical_sql('text')}) AS digest, min(license) AS license FROM (VALUES {values}) t(license, text) GROUP BY 1)
SELECT d.doc_id, length(d.text)::BIGINT AS n_chars, d.digest, k.license
FROM (SELECT doc_id, text, sha256({canonical_sql('text')}) AS digest FROM documents) d
LEFT JOIN k ON d.digest = k.digest AND k.digest <> sha256('')
"""


def scan_lines(documents: DataFrame, known: DataFrame) -> DataFrame:
    """Licence lines: ``doc_id, license, n`` by the same lookup of each line's digest."""
    lines = documents.select("doc_id", F.explode(F.split("text", "\n")).alias("line")).where(F.col("line").rlike(r"(?i)licen[cs]|permission"))
    usable = known.where(F.col("digest") != F.sha2(F.lit(""), 256))
    return lines.select("doc_id", digest(F.col("line")).alias("digest")).join(usable, "digest").groupBy("doc_id", "license").agg(F.count("*").alias("n"))
