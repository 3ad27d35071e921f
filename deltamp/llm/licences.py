"""Licence scan by canonical digests, with DataFrame functions only.

A licence text is brought to a canonical form: lower case, notices of copyright and of reserved rights taken
out, equivalent spellings made equal, and everything but letters and digits turned into one space. The digest of
the whole form is looked up in a table of known digests (a hash join; the table is broadcast below its size bound).
The same is done for each line of a text, which finds short declarations within other documents.

Known forms are a parameter: ``KNOWN`` holds short licences and declarations as texts, ``DIGESTS`` the digests of the
canonical forms of long ones (Apache, Artistic, CC0, the GPL, LGPL, GFDL and MPL families, with and without the appendix
on how to apply them). A notice goes up to the end of its line or to the words that a licence begins with, so a
text on one line keeps what follows. A text that lacks letters after normalisation (a copyright line alone) matches nothing.

Defined cases: a null or empty text has an empty form and matches nothing; a form known under two names gives the
smaller one; repeated rows give a row each; an empty table gives no rows; other columns are not carried on.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import BROADCAST_BYTES, read

#: Equivalent spellings, fixed values: each first word is written as the second.
SPELLINGS = (("licence", "license"), ("licences", "licenses"), ("licenced", "licensed"), ("sublicence", "sublicense"), ("organisation", "organization"), ("recognise", "recognize"), ("authorised", "authorized"), ("behaviour", "behavior"), ("noncommercial", "non commercial"), ("whilst", "while"))

_NOTICE = r"(?:\bcopyright\b|\(c\)|©)[^\n]{0,60}?(?:\d{4}|\(c\)|©)[^\n]{0,160}?(\n|\z|\b(?:permission is|redistribution and|licensed under)\b)"
_RESERVED = r"\ball rights reserved\b"

_MIT = """Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the "Software"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions:
The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software.
THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE."""
_ISC = """Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies.
THE SOFTWARE IS PROVIDED "AS IS" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE."""

_BSD2 = """Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met:
1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer.
2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution.
%sTHIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS "AS IS" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE."""
_BSD3 = "3. Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission.\n"
_ZLIB = """This software is provided 'as-is', without any express or implied warranty. In no event will the authors be held liable for any damages arising from the use of this software.
Permission is granted to anyone to use this software for any purpose, including commercial applications, and to alter it and redistribute it freely, subject to the following restrictions:
1. The origin of this software must not be misrepresented; you must not claim that you wrote the original software. If you use this software in a product, an acknowledgment in the product documentation would be appreciated but is not required.
2. Altered source versions must be plainly marked as such, and must not be misrepresented as being the original software.
3. This notice may not be removed or altered from any source distribution."""

#: Digests of canonical forms of long texts, fixed values: name and SHA-256.
DIGESTS: tuple[tuple[str, str], ...] = (
    ("Apache-2.0", "95f35d79ea3bab75c250549d6a03cef242e0547d78c99e26fcede49936fb0184"),
    ("Apache-2.0", "37599287c15c2f2ec060c3c3b55bdf69e3bc7a8aeeb9cd57e18800088789538a"),
    ("Apache-2.0", "f45538b138cf9aea39fa205de037a0bede8305e68281650e7ab809a8b3ebb2f0"),
    ("Artistic-1.0-Perl", "08f1dc258c8f9e175155356aa1dd0dead8cfdec586bc1bb4c8b1452699a91702"),
    ("CC0-1.0", "96bdc7f63190fb4bd1ae584b890300ed7517d858b34c945642a3b9b2f1612a5f"),
    ("GFDL-1.2", "5379e6f33e826ba185b23fd11a414555c2161fda481478babd1e73a3ae098a71"),
    ("GFDL-1.3", "93d6108daecdddc5f284cf8f2512fb0d72f6e9ee12381feb9704ba194b00c3e6"),
    ("GPL-1.0", "99787965f814e5a0c5522ca06ad4b386e1c53dd443f8ca3d07dddf3102b6b302"),
    ("GPL-1.0", "af30c0af27b90ec812acdb040f3dcc944a87cd893456690efe35063f39e3eeeb"),
    ("GPL-1.0", "74d0cd23803c9754c36f6ca0e1af411b418ed6b6564e757472bf0d870a1b5d1b"),
    ("GPL-2.0", "39c702bd5e934ba747a73aee50bef73799ecdd08c9e61c47b990c65fbae8d41b"),
    ("GPL-2.0", "c67cc53030ae25fe2e2f0143b59060eca5ad89da8d2beca1445641234d29fc88"),
    ("GPL-2.0", "1551b61aa183f987ecceedd8966ec1e9b2da3848f8862c2adedc0d82f41904ca"),
    ("GPL-3.0", "2821a1f94004b80cca22b624cd028fef4b213bf4051ac6c499334336c1cb9ec2"),
    ("GPL-3.0", "a601c7a43ed7d7d12415e9011c9263c7c82cb8795e32169fab1cbc0676ed6ac5"),
    ("GPL-3.0", "a6065906c6484911a55e3d25c30ed0b6113799cd1fe643624fad83617d49db45"),
    ("LGPL-2.0", "61af4dcea4e412e8ccfb8877fd2762bd6d962f8d42a9fa2c06cf7b4613f2c908"),
    ("LGPL-2.0", "430627da7218a92ab4a6d75d5140cdb70ee750be7a53f913299b37e0d1b0eea2"),
    ("LGPL-2.0", "504542bce5421b0f5a7e63ddb55443ccb300b27a65ba6bfc1370fed16a3af260"),
    ("LGPL-2.1", "4d55922bdeafabde164d75448bbfb0b474bf952bbb541325364010900acd9891"),
    ("LGPL-2.1", "bf2f0c6bf1c47b3b1e3cbedeefecddd1e7db21d1919858d45c2f918efaf426df"),
    ("LGPL-2.1", "48d2010e70a815a564f914b0c7c1e80d7a6843793348fed3684c957112fe0aa4"),
    ("LGPL-3.0", "aae2b222477171fb64e298e7965e768a9a6f85320646b266c94399ac029d42be"),
    ("MPL-1.1", "4be4a6251869e153404f424bbd1c116ada60f8969d5610b406e2a430e206b0bc"),
    ("MPL-2.0", "f82071285728ca3ec7685ee9bc4acdae0b8267142a4d20b8f1805eabedb4a98a"),
    ("MPL-2.0", "075fcdf87448c49dbad8c5f7963f0eb6907a3d8eae1b431ba2988508499ec0de"),
    ("BSD-3-Clause", "21ce5e311a0ef74591e636cf6d0a236029bcaa0ee86324ac68d5748657aa8651"),
)

#: Known texts and declarations, fixed values: name and text.
KNOWN = (
    ("MIT", _MIT), ("MIT", "MIT License\n" + _MIT), ("MIT", "The MIT License\n" + _MIT), ("ISC", _ISC), ("ISC", "ISC License\n" + _ISC),
    ("BSD-2-Clause", _BSD2 % ""), ("BSD-3-Clause", _BSD2 % _BSD3), ("Zlib", _ZLIB),
    ("MIT", "Released under the MIT License."), ("MIT", "Licensed under the MIT License."),
    ("Apache-2.0", "Licensed under the Apache License, Version 2.0."), ("GPL-3.0", "This work is licensed under the GNU General Public License, version 3."),
    ("CC-BY-NC-4.0", "Licensed under CC BY-NC 4.0."), ("CC-BY-4.0", "Licensed under CC BY 4.0."), ("CC0-1.0", "Dedicated to the public domain under CC0 1.0."),
)


def _let(rows: DataFrame, name: str, value: Column) -> DataFrame:
    """``rows`` with a column that is computed once: neither a filter nor a later use brings the expression along again."""
    return rows.select("*", F.explode_outer(F.array(value)).alias(name))


def canonical(rows: DataFrame, text: str, out: str) -> DataFrame:
    """``rows`` with the canonical form of a text column. Notices and spellings are replaced only where a plain search finds one."""
    rows = _let(rows, "_low", F.lower(F.coalesce(F.col(text), F.lit(""))))
    low = F.col("_low")
    noticed = F.contains(low, F.lit("copyright")) | F.contains(low, F.lit("\u00a9")) | F.contains(low, F.lit("(c)")) | F.contains(low, F.lit("all rights reserved"))
    rows = _let(rows, "_clear", F.when(noticed, F.regexp_replace(F.regexp_replace(low, _RESERVED, " "), _NOTICE, " $1")).otherwise(low))
    rows = _let(rows, "_plain", F.trim(F.regexp_replace("_clear", r"[^\p{L}\p{N}]+", " ")))
    spelled = F.col("_plain")
    for a, b in SPELLINGS:
        spelled = F.regexp_replace(spelled, rf"\b{a}\b", b)
    some = r"\b(?:" + "|".join(a for a, _ in SPELLINGS) + r")\b"
    return _let(rows, out, F.when(F.col("_plain").rlike(some), spelled).otherwise(F.col("_plain"))).drop("_low", "_clear", "_plain")


def with_digest(rows: DataFrame, text: str) -> DataFrame:
    """``rows`` with the digest of the canonical form instead of the text; null if the form has no letter."""
    rows = canonical(rows, text, "_form")
    return _let(rows, "digest", F.when(F.col("_form").rlike(r"\p{L}"), F.sha2("_form", 256))).drop(text, "_form")


def known_digests(spark: SparkSession, known: list[tuple[str, str]] | tuple = KNOWN) -> DataFrame:
    """digest and licence of known texts."""
    rows = spark.createDataFrame(list(known), "licence string, text string")
    given = with_digest(rows, "text").where("digest IS NOT NULL").select("digest", "licence")
    if known is KNOWN and DIGESTS:
        given = given.union(spark.createDataFrame([(d, n) for n, d in DIGESTS], "digest string, licence string"))
    return given.groupBy("digest").agg(F.min("licence").alias("licence"))


def scan(docs: DataFrame, known: DataFrame | None = None, text: str = "text", key: str = "doc_id") -> DataFrame:
    """doc_id, text_licence (of the whole text, null if unknown) and line_licences (sorted, of its lines) of every row."""
    known = known if known is not None else known_digests(docs.sparkSession)
    rows = known.agg(F.count("*"), F.max(F.length("licence"))).first()
    side = F.broadcast(known) if rows[0] * (64 + (rows[1] or 0)) * 2 <= BROADCAST_BYTES else known
    base = docs.select(F.col(key).alias("doc_id"), F.xxhash64(text).alias("h"), F.col(text).alias("t"))
    lines = base.select("doc_id", "h", F.explode(F.array_distinct(F.split(F.coalesce("t", F.lit("")), r"\r?\n"))).alias("l"))
    lines = with_digest(lines, "l").where("digest IS NOT NULL").join(side, "digest").groupBy("doc_id", "h").agg(F.sort_array(F.collect_set("licence")).alias("line_licences"))
    whole = with_digest(base, "t").join(side, "digest", "left").select("doc_id", "h", F.col("licence").alias("text_licence"))
    both = whole.join(lines.toDF("_k", "_h", "line_licences"), (F.col("h") == F.col("_h")) & F.col("doc_id").eqNullSafe(F.col("_k")), "left")
    return both.select("doc_id", "text_licence", F.coalesce("line_licences", F.array().cast("array<string>")).alias("line_licences"))


def op7_licences(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = scan(read(spark, sf_dir, "documents"))
    return found.select("doc_id", "text_licence", F.size("line_licences").cast("long").alias("n_licences"), F.array_join("line_licences", ",").alias("line_licences"))


def _sql_form(c: str) -> str:
    e = f"regexp_replace(regexp_replace(lower(coalesce({c}, '')), '{_RESERVED}', ' ', 'g'), '{_NOTICE}', ' \\1', 'g')"
    e = f"trim(regexp_replace({e}, '[^\\p{{L}}\\p{{N}}]+', ' ', 'g'))"
    for a, b in SPELLINGS:
        e = f"regexp_replace({e}, '\\b{a}\\b', '{b}', 'g')"
    return e


def _sql_known() -> str:
    quote = lambda x: "'" + x.replace("'", "''") + "'"
    return ", ".join(f"({quote(a)}, {quote(b)})" for a, b in KNOWN)


OP7_SQL = f"""
WITH k AS (SELECT h, min(licence) AS licence FROM (SELECT licence, sha256({_sql_form("text")}) AS h FROM (VALUES {_sql_known()}) v(licence, text) UNION ALL SELECT * FROM (VALUES {", ".join(f"('{n}', '{d}')" for n, d in DIGESTS)}) w(licence, h)) GROUP BY h),
l AS (SELECT doc_id, unnest(string_split(coalesce(text, ''), chr(10))) AS t FROM documents),
m AS (SELECT doc_id, count(DISTINCT licence) AS n, string_agg(DISTINCT licence, ',' ORDER BY licence) AS s FROM (SELECT doc_id, sha256({_sql_form("t")}) AS h FROM l) JOIN k USING (h) GROUP BY doc_id)
SELECT d.doc_id, k.licence AS text_licence, coalesce(m.n, 0)::BIGINT AS n_licences, coalesce(m.s, '') AS line_licences
FROM (SELECT doc_id, sha256({_sql_form("text")}) AS h FROM documents) d LEFT JOIN k USING (h) LEFT JOIN m USING (doc_id)
"""
