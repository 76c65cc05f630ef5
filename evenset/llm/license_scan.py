"""Licence scans by canonical digest.

A text is brought to a canonical form (ASCII case, copyright lines, punctuation and white space, equivalent
spellings) and its SHA-256 is looked up among the digests of known licence texts. Whole texts are compared,
so a match means that the document is that licence and nothing else. Short licences and notices are known by their
texts, long ones by their digests; a table of texts may be passed instead.

Defined cases: a null text is empty, has the digest of the empty form and matches nothing; two known texts of
one canonical form give the name that sorts first; repeated rows are looked up each.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .shared import read_table

# Whole words, or pairs of words, taken as equal (the left is rewritten to the right).
SPELLINGS = (
    ("licence", "license"),
    ("licences", "licenses"),
    ("licenced", "licensed"),
    ("sublicence", "sublicense"),
    ("authorise", "authorize"),
    ("authorised", "authorized"),
    ("authorisation", "authorization"),
    ("organisation", "organization"),
    ("recognise", "recognize"),
    ("recognised", "recognized"),
    ("favour", "favor"),
    ("honour", "honor"),
    ("acknowledgement", "acknowledgment"),
    ("judgement", "judgment"),
    ("fulfil", "fulfill"),
    ("sub license", "sublicense"),
    ("non commercial", "noncommercial"),
    ("non infringement", "noninfringement"),
    ("http", "https"),
)
COPYRIGHT = r"(^|\n)[^a-z0-9\n(]*(copyright[ \t]+(\(c\)|©|[0-9<\[{])|\(c\)[ \t]+[0-9]|©)[^\n]*"
NOT_WORD = r"[^a-z0-9\x{80}-\x{10FFFF}]+"
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
# Typographic quotes and dashes become spaces like other punctuation.
QUOTES = "‘’“”–— "

_WARRANTY = (
    'THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT '
    "LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO "
    "EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER "
    "IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR "
    "THE USE OR OTHER DEALINGS IN THE SOFTWARE."
)
_SOURCE = (
    "1. Redistributions of source code must retain the above copyright notice, this list of conditions and the "
    "following disclaimer.\n"
)
_BINARY = (
    "2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the "
    "following disclaimer in the documentation and/or other materials provided with the distribution.\n"
)
_HOLDERS = (
    'THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS "AS IS" AND ANY EXPRESS OR IMPLIED '
    "WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A "
    "PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY "
    "DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, "
    "PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER "
    "CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR "
    "OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH "
    "DAMAGE."
)
# Texts of known licences and of short licence notices.
KNOWN = (
    (
        "MIT",
        "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and "
        'associated documentation files (the "Software"), to deal in the Software without restriction, '
        "including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, "
        "and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, "
        "subject to the following conditions:\nThe above copyright notice and this permission notice shall be "
        "included in all copies or substantial portions of the Software.\n" + _WARRANTY,
    ),
    (
        "ISC",
        "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee "
        "is hereby granted, provided that the above copyright notice and this permission notice appear in all "
        'copies.\nTHE SOFTWARE IS PROVIDED "AS IS" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS '
        "SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR "
        "BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER "
        "RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER "
        "TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE.",
    ),
    (
        "BSD-2-Clause",
        "Redistribution and use in source and binary forms, with or without modification, are permitted provided "
        "that the following conditions are met:\n" + _SOURCE + _BINARY + _HOLDERS,
    ),
    (
        "BSD-3-Clause",
        "Redistribution and use in source and binary forms, with or without modification, are permitted provided "
        "that the following conditions are met:\n" + _SOURCE + _BINARY + "3. Neither the name of the copyright "
        "holder nor the names of its contributors may be used to endorse or promote products derived from this "
        "software without specific prior written permission.\n" + _HOLDERS,
    ),
    (
        "Zlib",
        "This software is provided 'as-is', without any express or implied warranty. In no event will the authors "
        "be held liable for any damages arising from the use of this software.\nPermission is granted to anyone to "
        "use this software for any purpose, including commercial applications, and to alter it and redistribute it "
        "freely, subject to the following restrictions:\n1. The origin of this software must not be "
        "misrepresented; you must not claim that you wrote the original software. If you use this software in a "
        "product, an acknowledgment in the product documentation would be appreciated but is not required.\n"
        "2. Altered source versions must be plainly marked as such, and must not be misrepresented as being the "
        "original software.\n3. This notice may not be removed or altered from any source distribution.",
    ),
    ("Apache-2.0-notice", "Licensed under the Apache License, Version 2.0."),
    ("MIT-notice", "Released under the MIT License."),
    ("CC-BY-NC-4.0-notice", "Licensed under CC BY-NC 4.0."),
    ("GPL-3.0-notice", "This work is licensed under the GNU General Public License, version 3."),
)


# Digests of the canonical forms of longer licences, each of the whole published text.
DIGESTS = (
    ("Apache-2.0", "7dc0ccfedfe9cf9e59c97a3e43eea7b035a0e7a7be84d714acef36eb5c9fb4bc"),
    ("Artistic-1.0-Perl", "08f1dc258c8f9e175155356aa1dd0dead8cfdec586bc1bb4c8b1452699a91702"),
    ("CC0-1.0", "cccf7894e1b9f4ba9f97728bf0c5baf9e07bc2ac93da7a51556451b1fb2b868e"),
    ("GFDL-1.2", "5379e6f33e826ba185b23fd11a414555c2161fda481478babd1e73a3ae098a71"),
    ("GFDL-1.3", "93d6108daecdddc5f284cf8f2512fb0d72f6e9ee12381feb9704ba194b00c3e6"),
    ("GPL-1.0", "8f586b09c093668e2db772bdcfc1d5dc0b03e0e862fccbff035e1bf134e9b224"),
    ("GPL-2.0", "efe73660e5476cf0368fc0fc143f624ff9d1b73c4484b14a9969dd20c5786821"),
    ("GPL-3.0", "a8cd54d6683aa630f0b8d05d56184ad91dc486756da2df61c94d3e4e8d5ecb68"),
    ("LGPL-2.0", "61af4dcea4e412e8ccfb8877fd2762bd6d962f8d42a9fa2c06cf7b4613f2c908"),
    ("LGPL-2.1", "4d55922bdeafabde164d75448bbfb0b474bf952bbb541325364010900acd9891"),
    ("LGPL-3.0", "aae2b222477171fb64e298e7965e768a9a6f85320646b266c94399ac029d42be"),
    ("MPL-1.1", "3f0343dd4f3b064be36e0c6584737c9b7bb5c322721694563f9009e088ce96d1"),
    ("MPL-2.0", "9eab7902f21bef0326dee4ed0cae1402c781cbf1f8e3dbeed6fbe176d641bb13"),
)


def canonical(text: Column) -> Column:
    """The form in which texts are compared."""
    t = F.translate(F.coalesce(text, F.lit("")), UPPER + QUOTES, LOWER + " " * len(QUOTES))
    t = F.regexp_replace(t, COPYRIGHT, "\n")
    # two spaces between words, so that neighbours never share the space that ends one and begins the other
    t = F.concat(F.lit(" "), F.trim(F.regexp_replace(t, NOT_WORD, "  ")), F.lit(" "))
    for a, b in SPELLINGS:
        t = F.replace(t, F.lit(_spaced(a)), F.lit(_spaced(b)))
    return F.trim(F.replace(t, F.lit("  "), F.lit(" ")))


def _spaced(words: str) -> str:
    return " " + words.replace(" ", "  ") + " "


def known_digests(texts: DataFrame) -> DataFrame:
    """license, text -> digest, license; one row per digest."""
    return texts.groupBy(F.sha2(canonical(F.col("text")).cast("binary"), 256).alias("digest")).agg(
        F.min("license").alias("license")
    )


def scan_licenses(
    docs: DataFrame, known: DataFrame | None = None, *, id_col: str = "doc_id", text_col: str = "text"
) -> DataFrame:
    """doc_id, digest, license (null: none known) of every row. known: (license, text) instead of the built-in
    texts and digests; Spark decides by its size how it is joined."""
    if known is None:
        spark = docs.sparkSession
        digests = known_digests(spark.createDataFrame(list(KNOWN), "license string, text string")).unionByName(
            spark.createDataFrame(list(DIGESTS), "license string, digest string")
        )
    else:
        digests = known_digests(known)
    rows = docs.select(
        F.col(id_col).alias("__id"), F.sha2(canonical(F.col(text_col)).cast("binary"), 256).alias("digest")
    )
    return rows.join(digests, "digest", "left").select(F.col("__id").alias("doc_id"), "digest", "license")


def op5_license_digests(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan_licenses(read_table(spark, sf_dir, "documents"))


def _sql() -> str:
    quoted = lambda s: "'" + s.replace("'", "''") + "'"

    def form(col: str) -> str:
        t = f"translate(coalesce({col}, ''), {quoted(UPPER + QUOTES)}, {quoted(LOWER + ' ' * len(QUOTES))})"
        t = f"regexp_replace({t}, {quoted(COPYRIGHT)}, chr(10), 'g')"
        t = f"' ' || trim(regexp_replace({t}, {quoted(NOT_WORD)}, '  ', 'g')) || ' '"
        for a, b in SPELLINGS:
            t = f"replace({t}, {quoted(_spaced(a))}, {quoted(_spaced(b))})"
        return f"sha256(trim(replace({t}, '  ', ' ')))"

    texts = ", ".join(f"({quoted(n)}, {quoted(t)})" for n, t in KNOWN)
    digests = ", ".join(f"({quoted(n)}, {quoted(d)})" for n, d in DIGESTS)
    return (
        f"WITH k AS (SELECT {form('t')} AS digest, min(n) AS license FROM (VALUES {texts}) AS x(n, t) GROUP BY 1 "
        f"UNION ALL SELECT digest, license FROM (VALUES {digests}) AS y(license, digest)), "
        f"d AS (SELECT doc_id, {form('text')} AS digest FROM documents) "
        "SELECT doc_id, digest, license FROM d LEFT JOIN k USING (digest)"
    )


OP5_SQL = _sql()
