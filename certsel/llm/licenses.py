"""Licence recognition by canonical digest: whole texts are normalised and hash-joined to digests of known licences."""

from __future__ import annotations

import hashlib
import re

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import text_or_empty

# Equivalent spellings, as used when licence texts are compared.
SPELLINGS = {
    "acknowledgement": "acknowledgment", "analogue": "analog", "analyse": "analyze", "artefact": "artifact", "authorisation": "authorization",
    "authorised": "authorized", "cancelled": "canceled", "catalogue": "catalog", "centre": "center", "copyright holder": "copyright owner",
    "favour": "favor", "fulfil ": "fulfill ", "initialise": "initialize", "judgement": "judgment", "labelling": "labeling", "licence": "license",
    "merchantability": "merchantability", "noncommercial": "non commercial", "organisation": "organization", "percent": "per cent",
    "practise": "practice", "programme": "program", "realise": "realize", "recognise": "recognize", "sub license": "sublicense", "utilisation": "utilization",
    "whilst": "while", "wilful": "willful", "http ": "https ",
}
COPYRIGHT_LINE = r"(?m)^[ \t*#/;-]*(?:copyright\b|\(c\)|©|all rights reserved)[^\n]*$"
#: The lines that are cut: as above, but 'copyright' that is a part of the wording (notice, holder, owner, or the line's last word) stays.
NOTICE_LINE = (r"(?m)^[ \t*#/;-]*(?:copyright\b(?![ \t\r]*(?:\n|\z|(?:notice|holder|owner)s?\b(?![ \t]*:)))|\(c\)|©|all rights reserved)[^\n]*$")
PUNCTUATION = r"[\x00-\x2F\x3A-\x60\x7B-\x7F\xA0-\xBF\x{2010}-\x{2027}]+"

# Texts of public licences that are short enough to state whole.
_WARRANTY_MIT = """THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE
WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE
LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION
WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE."""
_GRANT_MIT = """Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files
(the "Software"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish,
distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so"""
_WARRANTY_ISC = """THE SOFTWARE IS PROVIDED "AS IS" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED
WARRANTIES OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES
OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION,
ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE."""
_WARRANTY_BSD = """THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS "AS IS" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT
NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT
HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED
TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF
LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS
SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE."""
_TWO_CLAUSES = """Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following
conditions are met: 1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following
disclaimer. 2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in
the documentation and/or other materials provided with the distribution."""
_THIRD_CLAUSE = """3. Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products
derived from this software without specific prior written permission."""
KNOWN = {
    "MIT": f"MIT License\n\n{_GRANT_MIT}, subject to the following conditions:\n\nThe above copyright notice and this permission notice shall be "
           f"included in all copies or substantial portions of the Software.\n\n{_WARRANTY_MIT}",
    "MIT-0": f"MIT No Attribution\n\n{_GRANT_MIT}.\n\n{_WARRANTY_MIT}",
    "ISC": "ISC License\n\nPermission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, "
           f"provided that the above copyright notice and this permission notice appear in all copies.\n\n{_WARRANTY_ISC}",
    "0BSD": "Zero-Clause BSD\n\nPermission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby "
            f"granted.\n\n{_WARRANTY_ISC}",
    "BSD-2-Clause": f"BSD 2-Clause License\n\n{_TWO_CLAUSES}\n\n{_WARRANTY_BSD}",
    "BSD-3-Clause": f"BSD 3-Clause License\n\n{_TWO_CLAUSES}\n\n{_THIRD_CLAUSE}\n\n{_WARRANTY_BSD}",
    "notice-MIT": "Released under the MIT License.",
    "notice-Apache-2.0": "Licensed under the Apache License, Version 2.0.",
    "notice-GPL-3.0": "This work is licensed under the GNU General Public License, version 3.",
    "notice-CC-BY-NC-4.0": "Licensed under CC BY-NC 4.0.",
}


def canonical(text: Column) -> Column:
    """Lower case, no copyright notices, punctuation and blanks as single spaces, one spelling."""
    t = F.regexp_replace(F.lower(text), NOTICE_LINE, "")
    t = F.concat(F.lit(" "), F.trim(F.regexp_replace(t, PUNCTUATION, " ")), F.lit(" "))
    for variant, usual in SPELLINGS.items():
        if variant != usual:
            t = F.replace(t, F.lit(variant), F.lit(usual))
    return F.trim(t)


def digest_of(text: str) -> str:
    """The same in plain Python: digests of the known texts, and the check of the expression."""
    t = re.sub(NOTICE_LINE.replace(r"\z", r"\Z"), "", text.lower())
    t = " " + re.sub(PUNCTUATION.replace(r"\x{2010}-\x{2027}", "‐-‧"), " ", t).strip(" ") + " "
    for variant, usual in SPELLINGS.items():
        t = t.replace(variant, usual)
    return hashlib.sha256(t.strip(" ").encode("utf-8", "replace")).hexdigest()


def known_digests(spark: SparkSession, texts: dict[str, str] | None = None) -> DataFrame:
    """(digest, license_id), one row per digest: the first id in order, where two texts have one canonical form."""
    table = {}
    for name, text in sorted((KNOWN if texts is None else texts).items()):
        table.setdefault(digest_of(text), name)
    return spark.createDataFrame(sorted(table.items()), "digest string, license_id string")


def scan(docs: DataFrame, known: DataFrame | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, digest, license_id for every document; license_id is null where the whole text is no known licence.

    Null and empty texts, and texts of punctuation alone, have the digest of the empty text and no licence.  Repeated rows give equal rows.
    known: (digest, license_id), sent to all tasks only where Spark's own estimate of its size allows it.
    """
    known = known_digests(docs.sparkSession) if known is None else known
    known = known.dropDuplicates(["digest"]).where(F.col("digest") != hashlib.sha256(b"").hexdigest())
    d = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.sha2(canonical(text_or_empty(F.col(text_col).cast("string"))), 256).alias("digest"))
    return d.join(known, "digest", "left").select("doc_id", "digest", "license_id")


def passages(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, line, license_id): the known texts that are a line of a document by themselves, lines counted from 0.

    Null texts have no lines; repeated rows give equal rows.  The digests are few, and only lines that are one of them are returned.
    """
    known = known_digests(docs.sparkSession)
    d = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.posexplode(F.split(F.col(text_col).cast("string"), "\n")).alias("line", "part")).where(F.length("part") >= 16)
    d = d.withColumn("digest", F.sha2(canonical(F.col("part")), 256))
    return d.join(F.broadcast(known), "digest").select("doc_id", F.col("line").cast("long").alias("line"), "license_id")


def passages_sql() -> str:
    """passages() in DuckDB SQL."""
    whole = sql()
    head, _, _ = whole.partition("\nSELECT doc_id")
    head = head.replace("SELECT doc_id, sha256", "SELECT doc_id, line, sha256").replace(
        "FROM documents)", "FROM (SELECT doc_id, unnest(range(len(p))) AS line, unnest(p) AS text FROM (SELECT doc_id, string_split(text, chr(10)) AS p FROM documents)) WHERE length(text) >= 16)")
    return head + "\nSELECT doc_id, line, license_id FROM d JOIN k USING (digest)"


def sql() -> str:
    """The scan in DuckDB SQL, which has no look-ahead: it still cuts every line that starts with 'copyright'."""
    q = lambda x: "'" + x.replace("'", "''") + "'"
    t = f"' ' || trim(regexp_replace(regexp_replace(lower(coalesce(text, '')), {q(COPYRIGHT_LINE)}, '', 'g'), {q(PUNCTUATION)}, ' ', 'g')) || ' '"
    for variant, usual in SPELLINGS.items():
        if variant != usual:
            t = f"replace({t}, {q(variant)}, {q(usual)})"
    table = {}
    for name, text in sorted(KNOWN.items()):
        table.setdefault(digest_of(text), name)
    rows = ", ".join(f"({q(a)}, {q(b)})" for a, b in table.items())
    return f"""WITH d AS (SELECT doc_id, sha256(trim({t})) AS digest FROM documents), k(digest, license_id) AS (VALUES {rows})
SELECT doc_id, d.digest, license_id FROM d LEFT JOIN k USING (digest)"""
