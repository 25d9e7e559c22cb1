"""License scan: canonical digests of entire texts, joined with digests of known licenses.

A unit, a document's whole text or one of its lines, becomes canonical: letters become lower
case, copyright lines go, punctuation and white space become single spaces, and equivalent
spellings become one. Its SHA-256 is then looked up among those of known licenses and notices
by a hash join. DataFrame functions only.

Spellings change a text's length within known limits, so units whose length can't become that
of any known text are left out before they are respelled and hashed.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: A list of known texts of at most this many rows is broadcast.
BROADCAST_KNOWN = 100_000
COPYRIGHT_LINE = r"(?md)^[ \t]*(?:copyright|\(c\)|©)[^\n]*$"
#: Characters other than a-z, 0-9 and non-ASCII ones, the copyright sign among them; one space alone stays as it is.
_OTHER = r"a-z0-9\x{80}-\x{A8}\x{AA}-\x{10FFFF}"
PUNCTUATION = rf" *[^{_OTHER} \n][^{_OTHER}\n]*| {{2,}}"

# Equivalent spellings, between words of a canonical text.
SPELLINGS = [
    ("licence", "license"), ("licences", "licenses"), ("licenced", "licensed"), ("sublicence", "sublicense"), ("sub license", "sublicense"), ("sub licence", "sublicense"),
    ("non infringement", "noninfringement"), ("merchantibility", "merchantability"), ("organisation", "organization"),
    ("acknowledgement", "acknowledgment"), ("favour", "favor"), ("whilst", "while"), ("per cent", "percent"), ("copyright holder", "copyright owner"),
    ("copyright holders", "copyright owners"), ("https", "http"),
]

# Public license texts and the notices that stand for longer ones.
_MIT_GRANT = (
    "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the "
    '"Software"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, '
    "distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to "
    "the following conditions:\n\nThe above copyright notice and this permission notice shall be included in all copies or substantial portions "
    'of the Software.\n\nTHE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE '
    "WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE "
    "LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN "
    "CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE."
)
_ISC_GRANT = "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted"
_ISC_REST = (
    'THE SOFTWARE IS PROVIDED "AS IS" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF '
    "MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY "
    "DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, "
    "ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE."
)
_BSD_START = (
    "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are "
    "met:\n\n1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer.\n\n"
    "2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the "
    "documentation and/or other materials provided with the distribution."
)
_BSD_THIRD = (
    "\n\n3. Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from "
    "this software without specific prior written permission."
)
_BSD_REST = (
    '\n\nTHIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS "AS IS" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT '
    "LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT "
    "HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT "
    "LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY "
    "THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE "
    "OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE."
)
_ZLIB = (
    "This software is provided 'as-is', without any express or implied warranty. In no event will the authors be held liable for any damages "
    "arising from the use of this software.\n\nPermission is granted to anyone to use this software for any purpose, including commercial "
    "applications, and to alter it and redistribute it freely, subject to the following restrictions:\n\n1. The origin of this software must not "
    "be misrepresented; you must not claim that you wrote the original software. If you use this software in a product, an acknowledgment in the "
    "product documentation would be appreciated but is not required.\n2. Altered source versions must be plainly marked as such, and must not be "
    "misrepresented as being the original software.\n3. This notice may not be removed or altered from any source distribution."
)
KNOWN = [
    ("MIT", "MIT License\n\n" + _MIT_GRANT),
    ("MIT", "The MIT License\n\n" + _MIT_GRANT),
    ("MIT", "The MIT License (MIT)\n\n" + _MIT_GRANT),
    ("MIT", _MIT_GRANT),
    ("ISC", "ISC License\n\n" + _ISC_GRANT + ", provided that the above copyright notice and this permission notice appear in all copies.\n\n" + _ISC_REST),
    ("ISC", _ISC_GRANT + ", provided that the above copyright notice and this permission notice appear in all copies.\n\n" + _ISC_REST),
    ("0BSD", _ISC_GRANT + ".\n\n" + _ISC_REST),
    ("0BSD", "BSD Zero Clause License\n\n" + _ISC_GRANT + ".\n\n" + _ISC_REST),
    ("BSD-2-Clause", _BSD_START + _BSD_REST),
    ("BSD-2-Clause", "BSD 2-Clause License\n\n" + _BSD_START + _BSD_REST),
    ("BSD-3-Clause", _BSD_START + _BSD_THIRD + _BSD_REST),
    ("BSD-3-Clause", "BSD 3-Clause License\n\n" + _BSD_START + _BSD_THIRD + _BSD_REST),
    ("Zlib", _ZLIB),
    ("Zlib", "zlib License\n\n" + _ZLIB),
    ("MIT", "Released under the MIT License."),
    ("MIT", "Licensed under the MIT License."),
    ("Apache-2.0", "Licensed under the Apache License, Version 2.0."),
    ("Apache-2.0", "Released under the Apache License, Version 2.0."),
    ("CC-BY-NC-4.0", "Licensed under CC BY-NC 4.0."),
    ("CC-BY-4.0", "Licensed under CC BY 4.0."),
    ("CC-BY-SA-4.0", "Licensed under CC BY-SA 4.0."),
    ("GPL-3.0", "This work is licensed under the GNU General Public License, version 3."),
    ("GPL-2.0", "This work is licensed under the GNU General Public License, version 2."),
]


# Fixed values: (license, length, SHA-256) of the canonical forms of whole public license texts that are too long to
# print here, taken from the files of a Linux distribution's folder of common licenses.
KNOWN_DIGESTS = [
    ("Apache-2.0", 9700, "6ab5deeb4b2c14f4681b97d03ec0d6cf046968b552bd6e2efe1721910b2e5e9e"),
    ("Artistic-1.0-Perl", 5675, "2f167bea4d7639ee1f5ffbcbba2bb4bf72ff80c3110eea9e21bf6668fc99e8f8"),
    ("BSD-3-Clause-UC", 1381, "3d151449461c0c776e892a4dc41cac0d251eb00c9fc49d2d48802d9bed818fe9"),
    ("CC0-1.0", 6691, "cccf7894e1b9f4ba9f97728bf0c5baf9e07bc2ac93da7a51556451b1fb2b868e"),
    ("GFDL-1.2", 19512, "84d1ed915e17aaa5b82f4ee40ec049ee8ad206bf2e5d2d146d1218be88602bbd"),
    ("GFDL-1.3", 21875, "d4a4f0fa89572488be676840e1bf655767a7dc5085a138f4abd486d1c1f5ae67"),
    ("GPL-1.0", 11762, "37f380f152339f34a15db620545eb53f0b5c7d9e6a9542aa09ed0d22f186920f"),
    ("GPL-2.0", 17049, "5147a46525fc36b30edbb3469564d4930add19b5b86c56d8d58e084575fd474a"),
    ("GPL-3.0", 33264, "43953244a50a8d661a10c68647c60eb8039eb5306b9336c785f4fb9acb1a0c76"),
    ("LGPL-2.0", 23933, "82b9c718a1edbbe60a4f5828e6e8c8390d714f09bfee18638761bb3f8fdff504"),
    ("LGPL-2.1", 25020, "8972cc10118fe8a142e8b2d34ba122d3a2c710126a256b6786246af9ae4cd5a6"),
    ("LGPL-3.0", 7104, "aae2b222477171fb64e298e7965e768a9a6f85320646b266c94399ac029d42be"),
    ("MPL-1.1", 22339, "f77c59051c0127d677dcce7ba0d4733294974749a7b4155250912498d92767d6"),
    ("MPL-2.0", 14271, "95f6a0d094cf3da6a140310541c7b576789031b600469b70877b34f97918e4c9"),
]


def _plain(text: Column) -> Column:
    """Lower case without copyright lines and punctuation; line ends stay."""
    text = F.lower(text)
    marked = F.contains(text, F.lit("copyright")) | F.contains(text, F.lit("(c)")) | F.contains(text, F.lit("©"))
    return F.regexp_replace(F.when(marked, F.regexp_replace(text, COPYRIGHT_LINE, "")).otherwise(text), PUNCTUATION, " ")


def _lines(plain: Column) -> Column:
    return F.transform(F.split(plain, "\n"), lambda x: F.trim(x))  # a bare F.trim would take the index as well


def _joined(lines: Column) -> Column:
    return F.array_join(F.filter(lines, lambda x: x != ""), " ")


def _respelled(unit: Column) -> Column:
    unit = F.concat(F.lit(" "), F.replace(unit, F.lit(" "), F.lit("  ")), F.lit(" "))  # a border of its own for each word
    for other, chosen in SPELLINGS:
        unit = F.replace(unit, F.lit(_bordered(other)), F.lit(_bordered(chosen)))
    return F.trim(F.replace(unit, F.lit("  "), F.lit(" ")))


def _bordered(words: str) -> str:
    return f" {words.replace(' ', '  ')} "


def canonical(text: Column) -> Column:
    """A text in canonical form; null stays null."""
    return _respelled(_joined(_lines(_plain(text))))


def _length_ranges(sizes: list[int]) -> list[tuple[int, int]]:
    """Lengths before respelling from which some known length can come, as few ranges."""
    shrink = min(1.0, *(len(b) / len(a) for a, b in SPELLINGS))
    grow = max(1.0, *(len(b) / len(a) for a, b in SPELLINGS))
    ranges: list[tuple[int, int]] = []
    for k in sorted(sizes):
        low, high = int(k / grow), int(k / shrink) + 1
        if ranges and low <= ranges[-1][1]:
            ranges[-1] = (ranges[-1][0], max(high, ranges[-1][1]))
        else:
            ranges.append((low, high))
    return ranges


def known_frame(spark: SparkSession, known: list[tuple[str, str]] | None = None, texts: DataFrame | None = None) -> DataFrame:
    """Known licenses as (license, digest, size), one license a digest.

    By default the texts and digests listed here: whole texts of MIT, ISC, 0BSD, BSD, Zlib, Apache, Artistic, CC0,
    GFDL, GPL, LGPL and MPL licenses, and notices. ``texts`` adds a table (license, text) of further whole texts.
    """
    listed = F.array(*(F.struct(F.lit(name).alias("license"), F.lit(text).alias("text")) for name, text in known or KNOWN))
    rows = spark.range(1).select(F.inline(listed))
    if texts is not None:
        rows = rows.unionByName(texts.select("license", "text"))
    rows = rows.select("license", canonical(F.col("text")).alias("text")).where("text <> ''")
    rows = rows.select("license", F.sha2("text", 256).alias("digest"), F.length("text").alias("size"))
    if known is None:
        given = F.array(*(F.struct(F.lit(n).alias("license"), F.lit(d).alias("digest"), F.lit(k).alias("size")) for n, k, d in KNOWN_DIGESTS))
        rows = rows.unionByName(spark.range(1).select(F.inline(given)))
    return rows.groupBy("digest", "size").agg(F.min("license").alias("license"))


def scan_licenses(docs: DataFrame, known: DataFrame, id_col: str = "doc_id", text_col: str = "text", broadcast_known: int = BROADCAST_KNOWN) -> DataFrame:
    """(id, license, notices, license_lines) of each document.

    ``license`` names the known text that the document is as a whole, else null; ``notices`` are
    the names of those that single lines of it are, sorted and joined by a comma, else null;
    ``license_lines`` counts such lines. Null and empty texts, and texts of punctuation or
    copyright lines alone, match nothing. Null ids and repeated rows stay; an empty table gives
    no rows.
    """
    if known.limit(broadcast_known + 1).count() <= broadcast_known:
        known = F.broadcast(known)
    key = F.sha2(F.col(text_col), 256).alias("key")
    ranges = _length_ranges([r[0] for r in known.select("size").distinct().collect()])

    def possible(unit: Column) -> Column:
        n, any_range = F.length(unit), F.lit(False)
        for low, high in ranges:
            any_range = any_range | n.between(low, high)
        return any_range

    lines = docs.select(key, _lines(_plain(F.col(text_col))).alias("lines"))
    units = F.concat(F.array(_joined(F.col("lines"))), F.col("lines"))
    numbered = F.transform(units, lambda x, i: F.struct(i.alias("line"), x.alias("unit")))
    found = (
        lines.select("key", F.inline(F.filter(numbered, lambda u: possible(u["unit"]))))
        .where("unit <> ''")
        .select("key", "line", F.sha2(_respelled(F.col("unit")), 256).alias("digest"))
        .join(known.select("digest", "license"), "digest")
        .select("key", "line", "license")
        .distinct()
        .groupBy("key")
        .agg(
            F.max(F.when(F.col("line") == 0, F.col("license"))).alias("license"),
            F.array_join(F.sort_array(F.collect_set(F.when(F.col("line") > 0, F.col("license")))), ",").alias("notices"),
            F.count(F.when(F.col("line") > 0, 1)).alias("license_lines"),
        )
    )
    return (
        docs.select(F.col(id_col).alias("id"), key)
        .join(found, "key", "left")
        .select("id", "license", F.when(F.col("notices") != "", F.col("notices")).alias("notices"), F.coalesce("license_lines", F.lit(0)).cast("bigint").alias("license_lines"))
    )


def oracle_sql() -> str:
    """The same scan of ``documents`` as DuckDB SQL."""

    def lines(text: str) -> str:
        text = f"regexp_replace(lower({text}), '{COPYRIGHT_LINE.replace('(?md)', '(?m)')}', '', 'g')"
        return f"list_transform(string_split(regexp_replace({text}, '{PUNCTUATION}', ' ', 'g'), chr(10)), lambda x: trim(x, ' '))"

    def joined(lines: str) -> str:
        return f"array_to_string(list_filter({lines}, lambda x: x <> ''), ' ')"

    def respelled(text: str) -> str:
        text = f"' ' || replace({text}, ' ', '  ') || ' '"
        for other, chosen in SPELLINGS:
            text = f"replace({text}, '{_bordered(other)}', '{_bordered(chosen)}')"
        return f"trim(replace({text}, '  ', ' '), ' ')"

    values = ", ".join("('{}', '{}')".format(a, b.replace("'", "''")) for a, b in KNOWN)
    digests = ", ".join(f"('{name}', '{digest}')" for name, _, digest in KNOWN_DIGESTS)
    return f"""
WITH listed(license, text) AS (VALUES {values}),
given(license, digest) AS (VALUES {digests}),
known AS (SELECT digest, min(license) AS license FROM (SELECT license, sha256({respelled(joined(lines("text")))}) AS digest FROM listed UNION ALL SELECT license, digest FROM given) GROUP BY 1),
rows AS (SELECT row_number() OVER () AS k, doc_id, {lines("text")} AS lines FROM documents),
units AS (
  SELECT k, 0 AS line, {joined("lines")} AS unit FROM rows
  UNION ALL
  SELECT k, unnest(range(1, len(lines) + 1)) AS line, unnest(lines) AS unit FROM rows
),
forms AS (SELECT k, line, {respelled("unit")} AS unit FROM units WHERE unit IS NOT NULL),
hits AS (SELECT k, line, license FROM forms JOIN known ON sha256(unit) = digest WHERE unit <> ''),
sums AS (
  SELECT k, max(CASE WHEN line = 0 THEN license END) AS license,
         string_agg(DISTINCT CASE WHEN line > 0 THEN license END, ',' ORDER BY CASE WHEN line > 0 THEN license END) AS notices,
         count(CASE WHEN line > 0 THEN 1 END) AS n
  FROM hits GROUP BY k
)
SELECT doc_id, license, notices, coalesce(n, 0) AS license_lines FROM rows LEFT JOIN sums ON rows.k = sums.k
"""
