"""License scans by canonical digests.

A text is brought to a canonical form: notices of a holder or of reserved rights go
(a line that begins with a copyright mark and a sign, a year or a blank to fill in, up to
a sentence on the license in it), then letters become lower case, equivalent spellings
one spelling, and everything else than letters and digits a single space, line breaks and
comment marks included. The SHA-256 of that form is looked up among the digests of known
licenses, which are those of whole public texts (with and without their headings) and of
usual notices. Entire documents and entire lines are looked up; with the built-in table
only those with a cue word, which every known text has; with a caller's table all.

The table of known digests is as long as the lists below, so it is broadcast.

Nulls: a null text matches nothing. An empty table gives an empty result. Repeated
rows are judged each; other columns are dropped. A very long text is hashed whole, by the
task that holds its row.
"""

from __future__ import annotations

import hashlib
import re
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

# Patterns of the canonical form, in the order in which they apply.
SENTENCE = r"\.[^\S\n]+(licen[cs]ed|released|distributed|permission|redistribution|this)"  # opens a line of its own
COPYRIGHT_LINE = r"(?m)^[^a-z0-9\n]*((portions )?copyright\s*(\(c\)|©|\d{4}|[\[<{])|(\(c\)|©)\s*(\d{4}|[\[<{])|all rights reserved\W*$)[^\n]*$"
SPELLINGS = [
    ("licence", "license"), ("sub-license", "sublicense"), ("non-infringement", "noninfringement"), ("organisation", "organization"),
    ("behaviour", "behavior"), ("favour", "favor"), ("authorisation", "authorization"), ("recognise", "recognize"), ("whilst", "while"),
    ("acknowledgement", "acknowledgment"), ("per cent", "percent"), ("copyright owner", "copyright holder"), ("http:", "https:"), ("&", " and "),
]
OTHER = r"[^a-z0-9]+"
CUE = r"(?i)(licen[cs]e|copyright|permission|redistribut|warrant|public domain)"

# Texts of known licenses and notices.
_PERMISSIVE_END = (
    'THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF '
    "MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY "
    "CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE "
    "SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE."
)
_ISC_END = (
    'THE SOFTWARE IS PROVIDED "AS IS" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF '
    "MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES "
    "WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR "
    "IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE."
)
_BSD_2 = (
    "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met:\n"
    "1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer.\n"
    "2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the "
    "documentation and/or other materials provided with the distribution.\n"
)
_BSD_3 = (
    "3. Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this "
    "software without specific prior written permission.\n"
)
_BSD_END = (
    'THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS "AS IS" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED '
    "TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR "
    "CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, "
    "PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF "
    "LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS "
    "SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE."
)
_ZLIB = (
    "This software is provided 'as-is', without any express or implied warranty. In no event will the authors be held liable for any damages arising "
    "from the use of this software.\nPermission is granted to anyone to use this software for any purpose, including commercial applications, and to "
    "alter it and redistribute it freely, subject to the following restrictions:\n1. The origin of this software must not be misrepresented; you must "
    "not claim that you wrote the original software. If you use this software in a product, an acknowledgment in the product documentation would be "
    "appreciated but is not required.\n2. Altered source versions must be plainly marked as such, and must not be misrepresented as being the original "
    "software.\n3. This notice may not be removed or altered from any source distribution."
)
_UNLICENSE = (
    "This is free and unencumbered software released into the public domain.\nAnyone is free to copy, modify, publish, use, compile, sell, or distribute "
    "this software, either in source code form or as a compiled binary, for any purpose, commercial or non-commercial, and by any means.\nIn "
    "jurisdictions that recognize copyright laws, the author or authors of this software dedicate any and all copyright interest in the software to the "
    "public domain. We make this dedication for the benefit of the public at large and to the detriment of our heirs and successors. We intend this "
    "dedication to be an overt act of relinquishment in perpetuity of all present and future rights to this software under copyright law.\n"
    'THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF '
    "MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER "
    "LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER "
    "DEALINGS IN THE SOFTWARE."
)
# Headings under which whole texts stand.
HEADINGS = {
    "MIT": ["MIT License", "The MIT License", "The MIT License (MIT)"],
    "ISC": ["ISC License", "The ISC License"],
    "0BSD": ["BSD Zero Clause License", "Zero-Clause BSD"],
    "BSD-2-Clause": ["BSD 2-Clause License", "The BSD 2-Clause License"],
    "BSD-3-Clause": ["BSD 3-Clause License", "The BSD 3-Clause License"],
    "Zlib": ["zlib License", "The zlib License"],
    "Unlicense": ["The Unlicense"],
}
KNOWN = [
    ("MIT", "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation "
     'files (the "Software"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, '
     "distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the "
     "following conditions:\nThe above copyright notice and this permission notice shall be included in all copies or substantial portions of the "
     "Software.\n" + _PERMISSIVE_END),
    ("ISC", "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided "
     "that the above copyright notice and this permission notice appear in all copies.\n" + _ISC_END),
    ("0BSD", "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted.\n" + _ISC_END),
    ("BSD-2-Clause", _BSD_2 + _BSD_END),
    ("BSD-3-Clause", _BSD_2 + _BSD_3 + _BSD_END),
    ("Zlib", _ZLIB),
    ("Unlicense", _UNLICENSE),
    ("Unlicense", _UNLICENSE + "\nFor more information, please refer to <https://unlicense.org/>"),
    ("MIT", "Released under the MIT License."),
    ("MIT", "Licensed under the MIT License."),
    ("Apache-2.0", "Licensed under the Apache License, Version 2.0."),
    ("CC0-1.0", "This work is dedicated to the public domain."),
    *[(f"GPL-{v}.0", f"This work is licensed under the GNU General Public License, version {v}.") for v in (1, 2, 3)],
    *[(f"CC-{k.replace(' ', '-')}-{v}", f"Licensed under CC {k} {v}.") for k in ("BY", "BY-SA", "BY-NC", "BY-ND", "BY-NC-SA", "BY-NC-ND") for v in ("3.0", "4.0")],
]

#: SHA-256 of the canonical form of long public license texts, as Debian's base system carries them.
LONG_TEXTS = {
    "4a6318c7afd8feed8c4463ea5ae0f2f609d433928a8b17f31104c8e7743de2c5": "Apache-2.0",
    "08f1dc258c8f9e175155356aa1dd0dead8cfdec586bc1bb4c8b1452699a91702": "Artistic-1.0-Perl",
    "96bdc7f63190fb4bd1ae584b890300ed7517d858b34c945642a3b9b2f1612a5f": "CC0-1.0",
    "1c057ea35084eb195331cec1a49fca335c176422a7726a9a23636906fd4e241f": "GFDL-1.2",
    "7e8edd3abe6258bb82bb853d91a0c24fcd9976894fd0592747354cffe1cb18e7": "GFDL-1.3",
    "8f586b09c093668e2db772bdcfc1d5dc0b03e0e862fccbff035e1bf134e9b224": "GPL-1.0",
    "efe73660e5476cf0368fc0fc143f624ff9d1b73c4484b14a9969dd20c5786821": "GPL-2.0",
    "a8cd54d6683aa630f0b8d05d56184ad91dc486756da2df61c94d3e4e8d5ecb68": "GPL-3.0",
    "61af4dcea4e412e8ccfb8877fd2762bd6d962f8d42a9fa2c06cf7b4613f2c908": "LGPL-2.0",
    "4d55922bdeafabde164d75448bbfb0b474bf952bbb541325364010900acd9891": "LGPL-2.1",
    "aae2b222477171fb64e298e7965e768a9a6f85320646b266c94399ac029d42be": "LGPL-3.0",
    "26ba73e836ecb04fe87d5eca80ca27cff1afa2d7683455be1517bd23b8d27986": "MPL-1.1",
    "4019e4c8fe9ede57c538b37b3332dc097a88c163e273bb6905d38316e63c2eb6": "MPL-2.0",
}


def canonical(text: str) -> str:
    """The canonical form of a text, for the known ones."""
    text = re.sub(COPYRIGHT_LINE, "", re.sub(SENTENCE, r".\n\1", text.lower()))
    for old, new in SPELLINGS:
        text = text.replace(old, new)
    return re.sub(OTHER, " ", text).strip(" ")


def canonical_column(text: Column) -> Column:
    """The same form as a column."""
    lowered = F.regexp_replace(F.regexp_replace(F.lower(text), SENTENCE, ".\n$1"), COPYRIGHT_LINE, "")
    spelled = reduce(lambda c, s: F.replace(c, F.lit(s[0]), F.lit(s[1])), SPELLINGS, lowered)
    return F.trim(F.regexp_replace(spelled, OTHER, " "))


def digests(known: list[tuple[str, str]] | None = None) -> dict[str, str]:
    """Digest to license name, of a caller's texts or of the built-in ones; canonical texts without words are left out."""
    if known is None:
        known = KNOWN + [(name, f"{heading}\n{text}") for name, text in KNOWN if "\n" in text for heading in HEADINGS[name]]
        return LONG_TEXTS | digests(known)
    return {hashlib.sha256(c.encode()).hexdigest(): name for name, text in known if (c := canonical(text))}


def _table(spark: SparkSession, known: dict[str, str], prefix: str) -> DataFrame:
    if not known:
        return spark.createDataFrame([], f"{prefix}_digest string, {prefix} string")
    entries = F.array(*[F.struct(F.lit(d).alias(f"{prefix}_digest"), F.lit(n).alias(prefix)) for d, n in known.items()])
    return F.broadcast(spark.range(0, 1, 1, 1).select(F.inline(entries)))


def scan_licenses(docs: DataFrame, text: str = "text", key: str = "doc_id", known: dict[str, str] | None = None) -> DataFrame:
    """(key, license, line_licenses): the license that the whole text is, and those that a line of it is, sorted and distinct.

    ``known`` are a caller's digests; their texts need no cue, so all texts and lines are looked up.
    """
    cue = CUE if known is None else "(?s)."
    known = digests() if known is None else known
    spark = docs.sparkSession
    rows = docs.select(F.col(key).alias("key"), F.coalesce(F.col(text), F.lit("")).alias("text"))
    has_cue = lambda c: F.regexp_like(c, F.lit(cue))
    digest = lambda c: F.sha2(canonical_column(c), 256)
    # a document without a cue is no known text, and its lines are not looked at
    lines = F.when(has_cue(F.col("text")), F.filter(F.split("text", "\n"), has_cue)).otherwise(F.array().cast("array<string>"))
    seen = rows.select("key", F.when(has_cue(F.col("text")), digest(F.col("text"))).alias("d"), F.transform(lines, digest).alias("l"))
    names = F.map_from_arrays(*[F.array(*map(F.lit, x)).cast("array<string>") for x in (known, known.values())])
    by_line = F.array_join(F.sort_array(F.array_distinct(F.filter(F.transform("l", lambda x: F.try_element_at(names, x)), lambda x: x.isNotNull()))), ",")
    whole = seen.join(_table(spark, known, "license"), F.col("d") == F.col("license_digest"), "left")
    return whole.select("key", "license", by_line.alias("line_licenses"))


def op1_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Licenses that whole documents and single lines of them are."""
    return scan_licenses(spark.read.parquet(f"{sf_dir}/documents.parquet")).withColumnRenamed("key", "doc_id")


def _sql() -> str:
    """The scan in DuckDB's dialect."""
    quote = lambda x: "'" + x.replace("'", "''") + "'"
    form = reduce(lambda c, s: f"replace({c}, {quote(s[0])}, {quote(s[1])})", SPELLINGS, f"regexp_replace(regexp_replace(lower(x), {quote(SENTENCE)}, '.' || chr(10) || '\\1', 'g'), {quote(COPYRIGHT_LINE)}, '', 'g')")
    form = f"sha256(trim(regexp_replace({form}, {quote(OTHER)}, ' ', 'g'), ' '))"
    values = ", ".join(f"({quote(d)}, {quote(n)})" for d, n in digests().items())
    return f"""
WITH known(digest, name) AS (VALUES {values}),
t AS (SELECT doc_id, row_number() OVER () AS k, coalesce(text, '') AS x FROM documents),
whole AS (SELECT k, {form} AS digest FROM t WHERE regexp_matches(x, {quote(CUE)})),
line AS (SELECT k, unnest(string_split(x, chr(10))) AS x FROM t WHERE regexp_matches(x, {quote(CUE)})),
hit AS (SELECT k, string_agg(DISTINCT name, ',' ORDER BY name) AS names FROM (SELECT k, {form} AS digest FROM line WHERE regexp_matches(x, {quote(CUE)})) JOIN known USING (digest) GROUP BY k)
SELECT doc_id, known.name AS license, coalesce(hit.names, '') AS line_licenses
FROM t LEFT JOIN whole USING (k) LEFT JOIN known USING (digest) LEFT JOIN hit ON hit.k = t.k
"""


OP1_SQL = _sql()
