"""License scans by canonical digests of entire texts, with DataFrame functions only.

A text is normalised - copyright lines go, A-Z to lower case, equivalent spellings to one of them, every run of punctuation and white
space to one space - and its SHA-256 is looked up among the digests of known licence texts, normalised alike.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

_WARRANTY = (
    'THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF '
    "MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, "
    "DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR "
    "OTHER DEALINGS IN THE SOFTWARE."
)
_ISC_WARRANTY = (
    'THE SOFTWARE IS PROVIDED "AS IS" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND '
    "FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, "
    "DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE."
)
_BSD_HEAD = "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met:\n"
_BSD_TWO = (
    "1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer.\n"
    "2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other "
    "materials provided with the distribution.\n"
)
_BSD_THREE = (
    "3. Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific "
    "prior written permission.\n"
)
_BSD_TAIL = (
    'THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS "AS IS" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED '
    "WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, "
    "INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR "
    "PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) "
    "ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE."
)
#: Public licence texts and notices, without their copyright lines.
KNOWN = {
    "MIT": "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the "
    "Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons "
    "to whom the Software is furnished to do so, subject to the following conditions:\n\nThe above copyright notice and this permission notice shall be included in all copies or substantial "
    "portions of the Software.\n\n" + _WARRANTY,
    "ISC": "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this "
    "permission notice appear in all copies.\n\n" + _ISC_WARRANTY,
    "0BSD": "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted.\n\n" + _ISC_WARRANTY,
    "BSD-2-Clause": _BSD_HEAD + _BSD_TWO + _BSD_TAIL,
    "BSD-3-Clause": _BSD_HEAD + _BSD_TWO + _BSD_THREE + _BSD_TAIL,
    "Apache-2.0": 'Licensed under the Apache License, Version 2.0 (the "License"); you may not use this file except in compliance with the License. You may obtain a copy of the License at '
    'http://www.apache.org/licenses/LICENSE-2.0 Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an "AS IS" BASIS, WITHOUT '
    "WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. See the License for the specific language governing permissions and limitations under the License.",
    "Apache-2.0 (line)": "Licensed under the Apache License, Version 2.0.",
    "MPL-2.0": "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can obtain one at "
    "https://mozilla.org/MPL/2.0/.",
    "CC-BY-NC-4.0 (line)": "Licensed under CC BY-NC 4.0.",
    "SPDX MIT": "SPDX-License-Identifier: MIT",
    "SPDX Apache-2.0": "SPDX-License-Identifier: Apache-2.0",
}
#: Titles that may stand before a text.
TITLES = {
    "MIT": ["MIT License", "The MIT License", "The MIT License (MIT)"],
    "ISC": ["ISC License", "The ISC License", "ISC License (ISC)"],
    "0BSD": ["BSD Zero Clause License", "Zero-Clause BSD", "BSD Zero Clause License (0BSD)"],
    "BSD-2-Clause": ["BSD 2-Clause License", 'BSD 2-Clause "Simplified" License', "The BSD 2-Clause License", "Simplified BSD License"],
    "BSD-3-Clause": ["BSD 3-Clause License", 'BSD 3-Clause "New" or "Revised" License', "The BSD 3-Clause License", "New BSD License"],
}
#: Canonical digests of whole long texts as their publishers give them, made by known_digests of the texts (read_texts).
DIGESTS = {
    "Apache-2.0": "84ed161685d232dab5187a7a7101279668d583e8fcead2d41433e4fd4a1dbe68",
    "CC0-1.0": "96bdc7f63190fb4bd1ae584b890300ed7517d858b34c945642a3b9b2f1612a5f",
    "GFDL-1.2": "58b6ebdf2bd26f81dd551d8efda909bfbc8914ce77996a5c289c28616b91ceeb",
    "GFDL-1.3": "c4f8ea2b5247ab1ff721ce8255137250d4c14f50a0fb68c00fd793f496ced65e",
    "GPL-1.0": "ec8a6b7d70e9f225b63d3962ed5b4721373f5535d7b967a06722b0d621f6892a",
    "GPL-2.0": "331b500eb3c5ee796906547305df82fff4a35b3aa03c1d3ea84d32078292b2e6",
    "GPL-3.0": "3c39b58d51baf32b2a21a55c429305f51cfd82e53cad05134293933580b4cd84",
    "LGPL-2.0": "61af4dcea4e412e8ccfb8877fd2762bd6d962f8d42a9fa2c06cf7b4613f2c908",
    "LGPL-2.1": "4d55922bdeafabde164d75448bbfb0b474bf952bbb541325364010900acd9891",
    "LGPL-3.0": "aae2b222477171fb64e298e7965e768a9a6f85320646b266c94399ac029d42be",
    "MPL-1.1": "f77c59051c0127d677dcce7ba0d4733294974749a7b4155250912498d92767d6",
    "MPL-2.0": "9e79a7d513376f6fa1500e4df4f6276c6e7e61c5c3e28dcdb1acee24033acc56",
}
#: Fixed values: (pattern, replacement) for equivalent spellings, in lower case. Applied to both sides alike.
SPELLINGS = [
    ("licence", "license"), ("sub license", "sublicense"), ("sub-license", "sublicense"), ("noncommercial", "non-commercial"), ("acknowledgement", "acknowledgment"), ("fulfil ", "fulfill "),
    ("merchantibility", "merchantability"), ("copyright owner", "copyright holder"), ("per cent", "percent"), ("web site", "website"), ("https:", "http:"),
]
_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
#: A line that claims copyright: the word or sign at its start, after comment marks, and a year, a holder or the sign; or all rights reserved.
_CLAIMS = "^[ \\t#*/;%-]*(?:(?:copyright|\\(c\\)|\u00a9) (?:\\(c\\)|\u00a9|[0-9]{4}|by )[^\\n]*|copyright: [^\\n]*|copyright the [^\\n]*(?:authors|contributors|developers|project|foundation|team)\\.?[ \\t]*|\\(c\\) [^\\n]*|all rights reserved\\.?[ \\t]*)$"
_MARKS = "[\\x00-\\x2F\\x3A-\\x40\\x5B-\\x60\\x7B-\\x7F\u2018\u2019\u201c\u201d\u2013\u2014]+"
_IZE = "(organ|author|recogn|util|minim|maxim|initial|custom|emphas)is(e|ed|es|ing|ation|ations)\\b"


def canonical(text: Column) -> Column:
    """The normalised text; null and texts of marks only become the empty string."""
    out = F.translate(F.coalesce(text, F.lit("")), _UPPER, _LOWER)
    out = F.regexp_replace(out, F.lit("(?md)" + _CLAIMS), F.lit(""))
    for old, new in SPELLINGS:
        out = F.replace(out, F.lit(old), F.lit(new))
    out = F.regexp_replace(out, F.lit(_IZE), F.lit("$1iz$2"))
    return F.trim(F.regexp_replace(out, F.lit(_MARKS), F.lit(" ")))


def catalogue(licenses: dict[str, str] | None = None) -> list[tuple[str, str]]:
    """(license_id, text) of each licence, with each of the titles known for it and without."""
    texts = KNOWN if licenses is None else licenses
    return [(name, (title + "\n\n" if title else "") + text) for name, text in texts.items() for title in ["", *(TITLES.get(name, []) if licenses is None else [])]]


def read_texts(spark: SparkSession, path: str) -> DataFrame:
    """(license_id, text) of a folder of licence texts, a file each, named by the file."""
    return spark.read.text(path, wholetext=True).select(F.regexp_extract(F.input_file_name(), r"([^/]+?)(?:\.txt)?$", 1).alias("license_id"), F.col("value").alias("text"))


def known_digests(spark: SparkSession, licenses: dict[str, str] | DataFrame | None = None) -> DataFrame:
    """license_id, digest for each licence: of licences with one canonical text the first name stays.

    licenses: texts by name, or a table (license_id, text) as read_texts gives; by default the texts and digests known here.
    """
    rows = licenses if isinstance(licenses, DataFrame) else spark.createDataFrame(catalogue(licenses), "license_id string, text string")
    found = rows.select("license_id", F.sha2(canonical(F.col("text")).cast("binary"), 256).alias("digest"))
    if licenses is None and DIGESTS:
        found = found.unionByName(spark.createDataFrame(list(DIGESTS.items()), "license_id string, digest string"))
    return found.groupBy("digest").agg(F.min("license_id").alias("license_id"))


def scan_documents(docs: DataFrame, licenses: dict[str, str] | DataFrame | None = None) -> DataFrame:
    """doc_id, canon_bytes, canon_sha256, license_id (null if unknown), is_license for every row of docs(doc_id, text).

    A null or empty text has the empty canonical text and is no licence. Null or repeated doc_ids stay rows; extra columns are
    ignored. Map-only but for a broadcast of the digests, as many as licences are given.
    """
    spark = docs.sparkSession
    text = docs.select(F.col("doc_id").cast("long").alias("doc_id"), canonical(F.col("text")).alias("c"))
    keyed = text.select("doc_id", F.octet_length("c").cast("long").alias("canon_bytes"), F.sha2(F.col("c").cast("binary"), 256).alias("canon_sha256"))
    known = known_digests(spark, licenses).select(F.col("digest").alias("canon_sha256"), "license_id")
    return keyed.join(F.broadcast(known), "canon_sha256", "left").select("doc_id", "canon_bytes", "canon_sha256", "license_id", F.col("license_id").isNotNull().alias("is_license"))


def remove_licenses(docs: DataFrame, licenses: dict[str, str] | DataFrame | None = None) -> DataFrame:
    """docs without the rows whose entire text is a known licence."""
    known = known_digests(docs.sparkSession, licenses).select("digest")
    return docs.join(F.broadcast(known), F.sha2(canonical(F.col("text")).cast("binary"), 256) == F.col("digest"), "left_anti")


def oracle_sql() -> str:
    quote = lambda s: "'" + s.replace("'", "''") + "'"

    def canon(x: str) -> str:
        x = f"regexp_replace(translate(coalesce({x}, ''), '{_UPPER}', '{_LOWER}'), {quote("(?m)" + _CLAIMS)}, '', 'g')"
        for old, new in SPELLINGS:
            x = f"replace({x}, {quote(old)}, {quote(new)})"
        x = f"regexp_replace({x}, {quote(_IZE)}, '\\1iz\\2', 'g')"
        return f"trim(regexp_replace({x}, {quote(_MARKS)}, ' ', 'g'), ' ')"

    known = ", ".join(f"({quote(k)}, {quote(v)})" for k, v in catalogue())
    digests = ", ".join(f"({quote(k)}, {quote(v)})" for k, v in DIGESTS.items())
    return f"""
WITH d AS (SELECT doc_id, {canon('text')} AS c FROM documents),
k AS (SELECT canon_sha256, min(id) AS license_id FROM (SELECT id, sha256({canon('t')}) AS canon_sha256 FROM (VALUES {known}) AS v(id, t) UNION ALL SELECT * FROM (VALUES {digests}) AS x(id, h)) GROUP BY 1),
e AS (SELECT doc_id, CAST(strlen(c) AS BIGINT) AS canon_bytes, sha256(c) AS canon_sha256 FROM d)
SELECT doc_id, canon_bytes, canon_sha256, license_id, license_id IS NOT NULL AS is_license FROM e LEFT JOIN k USING (canon_sha256)
"""
