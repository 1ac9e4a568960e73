"""Canonical digest lookup of licence texts.

A text is lower-cased, loses its copyright lines and punctuation, has equivalent spellings unified, and
is hashed with SHA-256; entire texts are hash-joined to the digests of known licence texts, each also under
its usual titles, without its numbers or its appendix. The legal codes of CC BY 4.0 and CC BY-NC 4.0 are not
among them (their notices are): pass them in ``known``. A line is a copyright line where a sign, a year, "by" or a
name follows; a wrapped sentence that happens to begin with the word stays. One-line
notices are whole texts too: every line of a document is canonicalised the same way and looked up among
the digests of known notices, inside the row, so that nothing is shuffled.

Edge cases: null and empty texts have the digest of the empty text and no licence; repeated rows give
repeated results; an empty table gives none; extra columns are kept unless they carry a result's name,
which the result replaces.
"""

from __future__ import annotations

import pkgutil
import re

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from softlanes.llm.shared import load

# Spellings that count as the same word.
SPELLINGS = [
    ("licence", "license"), ("licences", "licenses"), ("licenced", "licensed"), ("sublicence", "sublicense"), ("sublicences", "sublicenses"), ("sub license", "sublicense"),
    ("non commercial", "noncommercial"), ("copyright holder", "copyright owner"), ("copyright holders", "copyright owners"),
    ("organisation", "organization"), ("merchantibility", "merchantability"), ("whilst", "while"),
]

# One-line notices.
NOTICES = {
    "Apache-2.0": ["Licensed under the Apache License, Version 2.0.", "SPDX-License-Identifier: Apache-2.0"],
    "MIT": ["Released under the MIT License.", "Licensed under the MIT License.", "SPDX-License-Identifier: MIT"],
    "GPL-3.0": [
        "This work is licensed under the GNU General Public License, version 3.",
        "Licensed under the GNU General Public License, version 3.", "SPDX-License-Identifier: GPL-3.0-only",
    ],
    "CC-BY-NC-4.0": ["Licensed under CC BY-NC 4.0.", "This work is licensed under CC BY-NC 4.0."],
    "CC-BY-4.0": ["Licensed under CC BY 4.0.", "This work is licensed under CC BY 4.0."],
    "BSD-3-Clause": ["SPDX-License-Identifier: BSD-3-Clause", "Released under the BSD 3-Clause License."],
}

_AS_IS = (
    'THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO '
    "THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE "
    "AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, "
    "TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE."
)
_AUTHOR = (
    'THE SOFTWARE IS PROVIDED "AS IS" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL '
    "IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, "
    "INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN "
    "AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR "
    "PERFORMANCE OF THIS SOFTWARE."
)
# Whole licence texts, without their copyright lines.
TEXTS = {
    "MIT": "MIT License\n\nPermission is hereby granted, free of charge, to any person obtaining a copy of this software "
    'and associated documentation files (the "Software"), to deal in the Software without restriction, including without '
    "limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the "
    "Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions:\n\n"
    "The above copyright notice and this permission notice shall be included in all copies or substantial portions of the "
    "Software.\n\n" + _AS_IS,
    "ISC": "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby "
    "granted, provided that the above copyright notice and this permission notice appear in all copies.\n\n" + _AUTHOR,
    "0BSD": "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby "
    "granted.\n\n" + _AUTHOR,
}


_BSD_HEAD = (
    "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the "
    "following conditions are met:\n\n1. Redistributions of source code must retain the above copyright notice, this list of "
    "conditions and the following disclaimer.\n\n2. Redistributions in binary form must reproduce the above copyright notice, "
    "this list of conditions and the following disclaimer in the documentation and/or other materials provided with the "
    "distribution.\n\n"
)
_BSD_NAMES = "3. Neither the name of {} nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission.\n\n"
_BSD_TAIL = (
    'THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS "AS IS" AND ANY EXPRESS OR IMPLIED WARRANTIES, '
    "INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE "
    "DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT {} OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, "
    "SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR "
    "SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, "
    "WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE "
    "OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE."
)
# Files of ``license_texts`` by licence id.
FILES = {
    "Apache-2.0": "Apache-2.0", "GPL-3.0": "GPL-3.0", "GPL-2.0": "GPL-2.0", "LGPL-3.0": "LGPL-3.0", "LGPL-2.1": "LGPL-2.1",
    "MPL-2.0": "MPL-2.0", "MPL-1.1": "MPL-1.1", "CC0-1.0": "CC0-1.0", "BSD-3-Clause": "BSD-3-Clause-Regents",
}
# Titles the short texts go by.
TITLES = {
    "MIT": ["MIT License", "The MIT License", "The MIT License (MIT)", "MIT License (MIT)"],
    "ISC": ["ISC License", "The ISC License", "ISC License (ISC)", "The ISC License (ISC)"],
    "0BSD": ["BSD Zero Clause License", "Zero-Clause BSD", "Zero-Clause BSD License", "BSD 0-Clause License"],
    "BSD-2-Clause": ["BSD 2-Clause License", "The BSD 2-Clause License", 'BSD 2-Clause "Simplified" License', "Simplified BSD License"],
    "BSD-3-Clause": ["BSD 3-Clause License", "The BSD 3-Clause License", 'BSD 3-Clause "New" or "Revised" License', "New BSD License", "BSD License"],
}


def whole_texts() -> list[tuple[str, str]]:
    """(licence id, text) of every whole text in its usual forms."""
    short = [(k, text.removeprefix("MIT License\n\n")) for k, text in TEXTS.items()]
    short += [("BSD-2-Clause", _BSD_HEAD + _BSD_TAIL.format(who)) for who in ("HOLDER", "OWNER", "HOLDERS")]
    short += [
        ("BSD-3-Clause", _BSD_HEAD + _BSD_NAMES.format(name) + _BSD_TAIL.format(who))
        for name in ("the copyright holder", "the copyright holders") for who in ("HOLDER", "OWNER", "HOLDERS")
    ]
    out = []
    for k, file in FILES.items():
        text = pkgutil.get_data("softlanes.llm", f"license_texts/{file}.txt").decode()
        if k in TITLES:
            short.append((k, text.replace("All rights reserved.", "", 1)))
            continue
        ending = re.split(r"(?<=END OF TERMS AND CONDITIONS)\s", text, maxsplit=1)[0]
        out += [(k, text), (k, ending), (k, ending.replace("END OF TERMS AND CONDITIONS", ""))]
    for k, text in short:
        bodies = [text, re.sub(r"(?m)^\s*\d\. ", "", text)] if k.startswith("BSD") else [text]
        out += [(k, f"{title}\n\n{rights}{body}") for body in bodies for title in ("", *TITLES[k]) for rights in ("", "All rights reserved.\n\n")]
    return out


def known_texts() -> list[tuple[str, str]]:
    """(licence id, text): whole texts first, then notices, which are whole texts of one line."""
    return [*whole_texts(), *((k, line) for k, lines in NOTICES.items() for line in lines)]


_YEAR = r"[\[<{(]?[ \t]*(?i:\d{4}|year|yyyy)"
_NO_NAME = r"(?i:holder|owner|notice|licen[cs]e|law|treat|statement|and|or|permission|right|interest|protect|infring)"
_NAME = r"\p{Lu}[\p{Ll}.]"
_MARKED = rf"(©|\((?i:c)\)|{_YEAR}|(?i:by)\b"
COPYRIGHT_LINE = (
    rf"(^|\n)[^\p{{L}}\p{{N}}\n]*((?i:copyright)[ \t:,]*{_MARKED}|(?!{_NO_NAME}[a-z]*){_NAME})|©|\((?i:c)\)[ \t]*({_YEAR}|(?i:copyright)))[^\n]*"
)


def canonical(text: Column) -> Column:
    """Words of ``text`` without its copyright lines, in lower case, spellings unified, one space between them."""
    text = F.regexp_replace(F.coalesce(text, F.lit("")), COPYRIGHT_LINE, "\n")
    # two spaces between words: every word has its own on either side, so neighbours are both found in one pass
    text = F.concat(F.lit(" "), F.regexp_replace(F.lower(text), r"[^\p{L}\p{N}]+", "  "), F.lit(" "))
    for other, usual in SPELLINGS:
        text = F.replace(text, F.lit(f" {other.replace(' ', '  ')} "), F.lit(f" {usual.replace(' ', '  ')} "))
    return F.trim(F.replace(text, F.lit("  "), F.lit(" ")))


def canonical_digest(text: Column) -> Column:
    return F.sha2(canonical(text).cast("binary"), 256)


def known_digests(spark, texts: list[tuple[str, str]]) -> DataFrame:
    """``(digest, license)``, one row per distinct canonical text: a fixed, small list."""
    rows = spark.createDataFrame(texts, "license string, body string")
    return rows.select(canonical_digest(F.col("body")).alias("digest"), "license").groupBy("digest").agg(F.min("license").alias("license"))


def scan_licenses(df: DataFrame, text: str = "text", known: list[tuple[str, str]] | None = None) -> DataFrame:
    """Add ``canonical_sha256``, ``license`` (of the whole text, else null) and ``notices`` (sorted ids of whole
    lines that are known notices, comma-joined, else null)."""
    known = known_texts() if known is None else known
    table = known_digests(df.sparkSession, known).collect()  # the known list, not the corpus
    lookup = F.create_map(*[F.lit(x) for r in table for x in (r.digest, r.license)])
    lines = F.transform(F.split(F.coalesce(F.col(text), F.lit("")), "\n"), lambda line: F.try_element_at(lookup, canonical_digest(line)))
    found = F.array_sort(F.array_distinct(F.filter(lines, lambda x: x.isNotNull())))
    own = df.drop("canonical_sha256", "license", "notices")
    out = own.withColumn("canonical_sha256", canonical_digest(F.col(text)))
    out = out.withColumn("notices", F.when(F.size(found) > 0, F.array_join(found, ",")))
    joined = df.sparkSession.createDataFrame([(r.digest, r.license) for r in table], "canonical_sha256 string, license string")
    return out.join(F.broadcast(joined), "canonical_sha256", "left")


def op2_license_scan(spark, sf_dir: str) -> DataFrame:
    """Every document with the digest of its canonical text and the licences found."""
    docs = load(spark, sf_dir, "documents").select("doc_id", "text")
    return scan_licenses(docs).select("doc_id", "canonical_sha256", "license", "notices")


def oracle_op2() -> str:
    """The scan line by line: a line goes where a mark or a year follows the word, or a name that is no common word."""

    def sql(text: str) -> str:
        head = r"^[^\p{L}\p{N}]*"
        word = head + r"(?i:copyright)[ \t:,]*"
        marked = rf"{head}((?i:copyright)[ \t:,]*{_MARKED})|©|\((?i:c)\)[ \t]*({_YEAR}|(?i:copyright)))"
        goes = f"(regexp_matches(l, '{marked}') OR (regexp_matches(l, '{word}{_NAME}') AND NOT regexp_matches(l, '{word}{_NO_NAME}')))"
        out = f"array_to_string(list_filter(string_split(coalesce({text}, ''), chr(10)), lambda l: NOT {goes}), chr(10))"
        out = rf"' ' || regexp_replace(lower({out}), '[^\p{{L}}\p{{N}}]+', ' ', 'g') || ' '"
        for other, usual in SPELLINGS:  # neighbours share a space: the second pass finds what the first passed over
            out = f"replace(replace({out}, ' {other} ', ' {usual} '), ' {other} ', ' {usual} ')"
        return f"sha256(trim({out}, ' '))"

    quote = lambda x: "'" + x.replace("'", "''") + "'"
    values = ", ".join(f"({quote(k)}, {quote(body)})" for k, body in known_texts())
    return f"""
    WITH known AS (SELECT {sql('body')} AS digest, min(license) AS license FROM (VALUES {values}) t(license, body) GROUP BY 1),
    whole AS (SELECT doc_id, text, {sql('text')} AS canonical_sha256 FROM documents),
    lines AS (SELECT DISTINCT doc_id, {sql('line')} AS digest FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS line FROM documents)),
    notices AS (SELECT doc_id, string_agg(DISTINCT license, ',' ORDER BY license) AS notices FROM lines JOIN known USING (digest) GROUP BY doc_id)
    SELECT w.doc_id, w.canonical_sha256, k.license, n.notices
    FROM whole w LEFT JOIN known k ON k.digest = w.canonical_sha256 LEFT JOIN notices n ON n.doc_id = w.doc_id"""
