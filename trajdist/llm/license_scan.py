"""Licence scans by canonical digests, in DataFrame operations only.

A text is brought into a canonical form (lower case, no copyright lines, no punctuation, one spelling of
equivalent words), hashed as a whole, and joined by hash to the digests of known licences, which are made by the
same expression.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Rows of known digests up to which they are broadcast; beyond, they are joined by shuffle.
BROADCAST_ROWS = 500_000

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
#: A line that names the holder: it differs in every copy and says nothing about the terms.
COPYRIGHT_LINE = r"\n[^a-z0-9\n]*((portions )?copyright[ \t]*(\(c\)|\x{A9}|[0-9]|<|\[|:|by )|\(c\)[ \t]*[0-9]|\x{A9}|all rights reserved)[^\n]*"
PUNCTUATION = r"[\x00-/:-`{-\x{7F}\x{A0}\x{A9}\x{AB}\x{BB}\x{2010}-\x{2015}\x{2018}-\x{201F}\x{2022}\x{2026}]+"

# Spellings that count as equal, each pattern with what replaces it; @1 stands for the first group.
# Every word stands between spaces of its own.
SPELLINGS = (
    (" ([a-z]+)is(e|ed|es|er|ers|ing|ation|ations) ", " @1iz@2 "),
    (" ([a-z]+)ys(e|ed|es|ing) ", " @1yz@2 "),
    (" (col|fav|lab|behavi|hon|endeav)our([a-z]*) ", " @1or@2 "),
    (" (licen|offen|defen|preten|practi)c(e|es|ed|ing|or|ors) ", " @1s@2 "),
    (" (cent|met|lit|theat|calib)re(s?) ", " @1er@2 "),
    (" (cancel|label|model|signal|travel)l(ed|ing) ", " @1@2 "),
    (" (catal|anal|dial)ogue(s?) ", " @1og@2 "),
    (" (judg|acknowledg)ement(s?) ", " @1ment@2 "),
    (" (fulfil|wilful)l?(s|ly|ment)? ", " @1@2 "),
    (" (sub)  (licens[a-z]+) ", " @1@2 "),
    (" (non)  (commercial|infring[a-z]+) ", " @1@2 "),
    (" (copyright)  (owner|holder)(s?) ", " @1  holder@3 "),
    (" (programme|artefact|whilst|per  cent|https|grey) ", None),
)
# Single words of the last pattern.
SINGLE = {"programme": "program", "artefact": "artifact", "whilst": "while", "per  cent": "percent", "https": "http", "grey": "gray"}


def canonical(text: Column) -> Column:
    """Words between single spaces.  A null text has none."""
    out = F.concat(F.lit("\n"), F.translate(F.coalesce(text, F.lit("")), UPPER, LOWER))
    out = F.regexp_replace(out, COPYRIGHT_LINE, "\n")
    out = F.concat(F.lit(" "), F.regexp_replace(out, PUNCTUATION, "  "), F.lit(" "))
    for pattern, new in SPELLINGS:
        if new is not None:
            out = F.regexp_replace(out, pattern, new.replace("@", "$"))
    for word, new in SINGLE.items():
        out = F.replace(out, F.lit(f" {word} "), F.lit(f" {new} "))
    return F.trim(F.regexp_replace(out, "  +", " "))


def digest(text: Column) -> Column:
    return F.sha2(canonical(text), 256)


_MIT = """Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the "Software"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions:
The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software.
THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE."""
_ISC = """Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies.
THE SOFTWARE IS PROVIDED "AS IS" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE."""
_BSD_HEAD = """Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met:
1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer.
2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution."""
_BSD_THIRD = """3. Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission."""
_BSD_TAIL = """THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS "AS IS" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE."""
_ZLIB = """This software is provided 'as-is', without any express or implied warranty. In no event will the authors be held liable for any damages arising from the use of this software.
Permission is granted to anyone to use this software for any purpose, including commercial applications, and to alter it and redistribute it freely, subject to the following restrictions:
1. The origin of this software must not be misrepresented; you must not claim that you wrote the original software. If you use this software in a product, an acknowledgment in the product documentation would be appreciated but is not required.
2. Altered source versions must be plainly marked as such, and must not be misrepresented as being the original software.
3. This notice may not be removed or altered from any source distribution."""

# Public licence texts by their identifiers, without titles and copyright lines.
KNOWN = {
    "MIT": _MIT,
    "ISC": _ISC,
    "BSD-2-Clause": f"{_BSD_HEAD}\n{_BSD_TAIL}",
    "BSD-3-Clause": f"{_BSD_HEAD}\n{_BSD_THIRD}\n{_BSD_TAIL}",
    "Zlib": _ZLIB,
}
#: Titles that copies may carry before the text.
TITLES = {"MIT": ("MIT License", "The MIT License"), "ISC": ("ISC License",), "BSD-2-Clause": ("BSD 2-Clause License",), "BSD-3-Clause": ("BSD 3-Clause License",), "Zlib": ("zlib License",)}

#: Canonical digests of longer public licences, made from /usr/share/common-licenses: the whole text, and where it has a
#: line that ends the terms, the text up to that line and before it.
DIGESTS = {
    "Apache-2.0": (
        "327c1ba82b5806f96c825efbeacb3b6bd6849edd96c5dbbc903e86a5adb3e3e4",
        "67ab7d8d481e387cbf4447c840bc8bd4f46e520d94f86982e49a4d97317199c3",
        "e4668562b2eadb44825f219695a37cef64ff57d40d54e793658d08887601537b",
    ),
    "Artistic-1.0-Perl": ("065afd054b7b3891100d80895d113a7c684cbc25122fa1c526244c852fe5a9ba",),
    "CC0-1.0": ("b096badc0168abbd7a6496f3097d3b3e33b5d3d54dbc0990a1eb8341c549c075",),
    "GFDL-1.2": ("d50c72f802fd65b68fefdacc125a5dc5d60d876b08089cc01d65e48fc4ddee5e",),
    "GFDL-1.3": ("c136842c3bb94c66f9158ddea107c935e305b1f3d74c98797ad031c4abf1d065",),
    "GPL-1.0": (
        "21e3b11fb32f9accb80f03d21737ce50fc0069dbfe86cd50e387340fada525d6",
        "b6f369bdd84e6de75aa454489b778914b3d31b942699818c08c8b6b8e362011e",
        "e7f731585e9d5909ec57e449337d50f61b84236e4c90cb5a8ee4b32d9e8bb200",
    ),
    "GPL-2.0": (
        "4bcb950653ff617d0bb56b6426cfaea3eb41fe0664ad811753e30d52508cafeb",
        "80e9b42142b79bb8a9f7fa8acecad289012c8d60a8feb9af774d6da139121f08",
        "86c6867bbd61dd0c5d135090990b167c1e0032dbec2ecec0cc6d9150461d31cf",
    ),
    "GPL-3.0": (
        "4e55c75daee918cdb49fdca24c0ddb7c951b6d8ba923bab02b343d77ac45f473",
        "b5c5cfe06f2169a1cc905202a26affb702f8d0a8bd32ce510fa866468800f29b",
        "c72b372d31476460d5f6ea7021a0db3d15aa96bcf3f6c69ffdcd606e4ed47c5e",
    ),
    "LGPL-2.0": (
        "05bd90fc63b3dc9da2fb17e13c42b5749278f3d22242ebf4c31d37922c51cd86",
        "7db3ed4089cdd5c7277a4678137a808a11bd6da5e504efc357b6819585e29826",
        "c34d7c67c6bed7512e8c956fcda453369c50d0f573c9910560c243db0cc6fc49",
    ),
    "LGPL-2.1": (
        "a5b9a354affa859f8f4e601263c1b26857a267f46a51a8fa99b68f7eb7992bf8",
        "e53e78749bf942e74720c742260ed6e337805f21afecde25fccb2f55065c6af5",
        "f2986f69bfa7d4a1cbb1e853daa269e79108bc0bea13c16908369a421ae86fc1",
    ),
    "LGPL-3.0": ("9111884d93a72b30a3d024876dab3d755949ac2cfab230268a4169a93b86560c",),
    "MPL-1.1": ("689ed28ba5266ba6495d500b912a16fb2d446ed229dabae10d2c2af56461bb72",),
    "MPL-2.0": ("c5e9fad60229272dec55ca65993d68b5305368110b17c326ee36d8c54fc5edea",),
}


# One-line notices and what they name.  All of them hold the letters "licen".
NOTICES = {
    "Released under the MIT License.": "MIT", "Licensed under the MIT License.": "MIT", "This project is licensed under the MIT License.": "MIT",
    "Licensed under the Apache License, Version 2.0.": "Apache-2.0", "Licensed under the Apache License, Version 2.0 (the \"License\");": "Apache-2.0",
    "This work is licensed under the GNU General Public License, version 3.": "GPL-3.0", "Licensed under the GNU General Public License, version 2.": "GPL-2.0",
    "Licensed under CC BY-NC 4.0.": "CC-BY-NC-4.0", "Licensed under CC BY 4.0.": "CC-BY-4.0", "Licensed under CC BY-SA 4.0.": "CC-BY-SA-4.0",
}


def notices(text: Column, known: dict[str, str]) -> Column:
    """Names of the notices (canonical digest to name) that stand in a text as whole lines, sorted."""
    lines = F.filter(F.split(F.coalesce(text, F.lit("")), "\n"), lambda l: F.lower(l).contains("licen"))
    names = F.create_map(*(F.lit(x) for kv in known.items() for x in kv))
    met = F.array_intersect(F.transform(lines, digest), F.array(*map(F.lit, known)))
    return F.array_sort(F.array_distinct(F.transform(met, lambda x: F.element_at(names, x))))


def known_notices(spark: SparkSession) -> dict[str, str]:
    """Canonical digest of each notice: a small fixed table."""
    rows = spark.createDataFrame(list(NOTICES.items()), "text string, name string").select(digest(F.col("text")).alias("d"), "name").collect()
    return {r.d: r.name for r in sorted(rows)}


def known_licenses(spark: SparkSession, texts: dict[str, str] | None = None) -> DataFrame:
    """license, digest: of the given texts, or of KNOWN with and without its titles and DIGESTS."""
    if texts is not None:
        rows = list(texts.items())
    else:
        rows = [(k, t) for k, text in KNOWN.items() for t in (text, *(f"{title}\n{text}" for title in TITLES[k]))]
    found = spark.createDataFrame(rows, "license string, text string") if rows else spark.createDataFrame([], "license string, text string")
    digests = found.select(digest(F.col("text")).alias("digest"), "license")
    if texts is None:
        digests = digests.unionByName(spark.createDataFrame([(d, k) for k, ds in DIGESTS.items() for d in ds], "digest string, license string"))
    return digests.groupBy("digest").agg(F.min("license").alias("license"))


def scan(docs: DataFrame, known: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per input row: its id, digest of the canonical text, n_canonical_words, license (null if none is known), and
    notices (names of known one-line notices in it).

    Null and empty texts have no words and no licence.  Of two known names with one digest, the first in order.
    Repeated rows get the same answer each; other columns are not looked at.
    """
    found = notices(F.col(text_col), known_notices(docs.sparkSession))
    rows = docs.select(F.col(id_col).alias("_id"), canonical(F.col(text_col)).alias("_c"), found.alias("notices"))
    rows = rows.select("_id", "notices", F.sha2("_c", 256).alias("digest"), F.when(F.col("_c") == "", 0).otherwise(F.length("_c") - F.length(F.replace("_c", F.lit(" "), F.lit(""))) + 1).cast("long").alias("n_canonical_words"))
    names = known.where(F.col("digest") != F.sha2(F.lit(""), 256)).groupBy("digest").agg(F.min("license").alias("license"))
    names = F.broadcast(names) if names.limit(BROADCAST_ROWS + 1).count() <= BROADCAST_ROWS else names
    return rows.join(names, "digest", "left").select(F.col("_id").alias(id_col), "digest", "n_canonical_words", "license", "notices")


def canonical_sql(text: str) -> str:
    """The same form in DuckDB."""
    out = f"chr(10) || translate(coalesce({text}, ''), '{UPPER}', '{LOWER}')"
    out = f"regexp_replace({out}, '{COPYRIGHT_LINE}', chr(10), 'g')"
    out = f"' ' || regexp_replace({out}, '{PUNCTUATION}', '  ', 'g') || ' '"
    for pattern, new in SPELLINGS:
        if new is not None:
            out = f"regexp_replace({out}, '{pattern}', '{new.replace('@', chr(92))}', 'g')"
    for word, new in SINGLE.items():
        out = f"replace({out}, ' {word} ', ' {new} ')"
    return f"trim(regexp_replace({out}, '  +', ' ', 'g'))"


def scan_sql() -> str:
    quoted = lambda s: "'" + s.replace("'", "''") + "'"
    rows = ", ".join(f"({quoted(k)}, {quoted(t)})" for k, text in KNOWN.items() for t in (text, *(f"{title}\n{text}" for title in TITLES[k])))
    lines = ", ".join(f"({quoted(k)}, {quoted(v)})" for k, v in NOTICES.items())
    longer = ", ".join(f"('{d}', '{k}')" for k, ds in DIGESTS.items() for d in ds)
    return f"""WITH k AS (SELECT digest, min(license) AS license FROM (SELECT sha256({canonical_sql('text')}) AS digest, license FROM (VALUES {rows}) AS t(license, text) UNION ALL SELECT * FROM (VALUES {longer}) AS t(digest, license)) GROUP BY 1),
    n AS (SELECT DISTINCT sha256({canonical_sql('text')}) AS digest, name FROM (VALUES {lines}) AS t(text, name)),
    l AS (SELECT doc_id, line FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents) WHERE contains(lower(line), 'licen')),
    m AS (SELECT doc_id, string_agg(DISTINCT name, ',' ORDER BY name) AS notices FROM l JOIN n ON n.digest = sha256({canonical_sql('line')}) GROUP BY doc_id),
    d AS (SELECT doc_id, {canonical_sql('text')} AS c FROM documents)
    SELECT d.doc_id, sha256(c) AS digest, CAST(CASE WHEN c = '' THEN 0 ELSE length(c) - length(replace(c, ' ', '')) + 1 END AS BIGINT) AS n_canonical_words, license, coalesce(notices, '') AS notices
    FROM d LEFT JOIN k ON k.digest = sha256(c) LEFT JOIN m ON m.doc_id = d.doc_id"""
