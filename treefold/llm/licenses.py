"""Licence scans by canonical digest, in DataFrame operations only.

A text loses its copyright lines and is brought to a canonical form (case,
punctuation, line breaks, equivalent spellings); its digest is hash-joined to
the digests of known licences, so only a document that is a whole licence text
is named. Lines that are a known one-line notice are reported beside that.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import text_or_empty

# Public licence texts, notices and equivalent spellings.
_AS_IS = (
    'THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF '
    "MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY "
    "CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE "
    "SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE."
)
_AUTHOR_DISCLAIMS = (
    'THE SOFTWARE IS PROVIDED "AS IS" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF '
    "MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES "
    "WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF "
    "OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE."
)
_BSD_HEAD = "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met:"
_BSD_SOURCE = "Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer."
_BSD_BINARY = (
    "Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the "
    "documentation and/or other materials provided with the distribution."
)
_BSD_NAME = "Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission."
_BSD_TAIL = (
    'THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS "AS IS" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED '
    "TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR "
    "CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, "
    "PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF "
    "LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS "
    "SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE."
)
LICENSE_TEXTS = (
    (
        "MIT",
        "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files "
        '(the "Software"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, '
        "distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the "
        "following conditions:\nThe above copyright notice and this permission notice shall be included in all copies or substantial portions of the "
        "Software.\n" + _AS_IS,
    ),
    ("BSD-2-Clause", "\n".join((_BSD_HEAD, "1. " + _BSD_SOURCE, "2. " + _BSD_BINARY, _BSD_TAIL))),
    ("BSD-3-Clause", "\n".join((_BSD_HEAD, "1. " + _BSD_SOURCE, "2. " + _BSD_BINARY, "3. " + _BSD_NAME, _BSD_TAIL))),
    (
        "ISC",
        "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the "
        "above copyright notice and this permission notice appear in all copies.\n" + _AUTHOR_DISCLAIMS,
    ),
    ("0BSD", "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted.\n" + _AUTHOR_DISCLAIMS),
    (
        "Zlib",
        "This software is provided 'as-is', without any express or implied warranty. In no event will the authors be held liable for any damages "
        "arising from the use of this software.\nPermission is granted to anyone to use this software for any purpose, including commercial "
        "applications, and to alter it and redistribute it freely, subject to the following restrictions:\n1. The origin of this software must not be "
        "misrepresented; you must not claim that you wrote the original software. If you use this software in a product, an acknowledgment in the "
        "product documentation would be appreciated but is not required.\n2. Altered source versions must be plainly marked as such, and must not be "
        "misrepresented as being the original software.\n3. This notice may not be removed or altered from any source distribution.",
    ),
)
_MIT_GRANT = (
    "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files "
    '(the "Software"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, '
    "distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so."
)
LICENSE_TEXTS += (
    ("MIT-0", _MIT_GRANT + "\n" + _AS_IS),
    (
        "Unlicense",
        "This is free and unencumbered software released into the public domain.\n\nAnyone is free to copy, modify, publish, use, compile, sell, or "
        "distribute this software, either in source code form or as a compiled binary, for any purpose, commercial or non-commercial, and by any means.\n\n"
        "In jurisdictions that recognize copyright laws, the author or authors of this software dedicate any and all copyright interest in the software "
        "to the public domain. We make this dedication for the benefit of the public at large and to the detriment of our heirs and successors. We intend "
        "this dedication to be an overt act of relinquishment in perpetuity of all present and future rights to this software under copyright law.\n\n"
        'THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF '
        "MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER "
        "LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER "
        "DEALINGS IN THE SOFTWARE.\n\nFor more information, please refer to <https://unlicense.org>",
    ),
)
#: Lines that stand above a licence text or not.
LICENSE_TITLES = (
    ("MIT", "MIT License"),
    ("MIT", "The MIT License"),
    ("MIT", "The MIT License (MIT)"),
    ("MIT-0", "MIT No Attribution"),
    ("BSD-2-Clause", "BSD 2-Clause License"),
    ("BSD-3-Clause", "BSD 3-Clause License"),
    ("ISC", "ISC License"),
    ("0BSD", "BSD Zero Clause License"),
    ("Zlib", "zlib License"),
    ("Unlicense", "The Unlicense"),
)
#: Canonical digests of long licence texts (see text_digests); "body" ends before the advice on how to apply the licence.
LICENSE_DIGESTS = (
    ("Apache-2.0", "whole", "04e64e0427d80fdde16fa8415931bf2c09bc943f13ec322a09df188bf23a3543"),
    ("Apache-2.0", "body", "119e2da0e9ec849d113a40405b338c1bbbd2ef9194c22bf2740fa4e195411c40"),
    ("Artistic-1.0-Perl", "whole", "e963bc30f4d3c45f45030c34409ee37315564625649c1394e32bb5ddd99e01b2"),
    ("BSD-3-Clause", "whole", "21ce5e311a0ef74591e636cf6d0a236029bcaa0ee86324ac68d5748657aa8651"),
    ("CC0-1.0", "whole", "cccf7894e1b9f4ba9f97728bf0c5baf9e07bc2ac93da7a51556451b1fb2b868e"),
    ("GFDL-1.2", "whole", "1c057ea35084eb195331cec1a49fca335c176422a7726a9a23636906fd4e241f"),
    ("GFDL-1.3", "whole", "7e8edd3abe6258bb82bb853d91a0c24fcd9976894fd0592747354cffe1cb18e7"),
    ("GPL-1.0", "whole", "8f586b09c093668e2db772bdcfc1d5dc0b03e0e862fccbff035e1bf134e9b224"),
    ("GPL-1.0", "body", "6375a768fd262bf5281905a9585411d2d0fb4ea15cb08cfcba49f73fedb82abc"),
    ("GPL-2.0", "whole", "efe73660e5476cf0368fc0fc143f624ff9d1b73c4484b14a9969dd20c5786821"),
    ("GPL-2.0", "body", "e1270b653c300290e7c039142bccb8776f9b5d14e8a05bc4e87dc7d1614a3b34"),
    ("GPL-3.0", "whole", "a8cd54d6683aa630f0b8d05d56184ad91dc486756da2df61c94d3e4e8d5ecb68"),
    ("GPL-3.0", "body", "ac6b52d57c0104e687039148f7b8e370e04c9bb5705bb786f8ef814eb65e8636"),
    ("LGPL-2.0", "whole", "61af4dcea4e412e8ccfb8877fd2762bd6d962f8d42a9fa2c06cf7b4613f2c908"),
    ("LGPL-2.0", "body", "504542bce5421b0f5a7e63ddb55443ccb300b27a65ba6bfc1370fed16a3af260"),
    ("LGPL-2.1", "whole", "4d55922bdeafabde164d75448bbfb0b474bf952bbb541325364010900acd9891"),
    ("LGPL-2.1", "body", "48d2010e70a815a564f914b0c7c1e80d7a6843793348fed3684c957112fe0aa4"),
    ("LGPL-3.0", "whole", "aae2b222477171fb64e298e7965e768a9a6f85320646b266c94399ac029d42be"),
    ("MPL-1.1", "whole", "26ba73e836ecb04fe87d5eca80ca27cff1afa2d7683455be1517bd23b8d27986"),
    ("MPL-2.0", "whole", "f82071285728ca3ec7685ee9bc4acdae0b8267142a4d20b8f1805eabedb4a98a"),
)
LICENSE_NOTICES = (
    ("Apache-2.0", "Licensed under the Apache License, Version 2.0."),
    ("GPL-3.0", "This work is licensed under the GNU General Public License, version 3."),
    ("GPL-2.0", "This work is licensed under the GNU General Public License, version 2."),
    ("CC-BY-4.0", "Licensed under CC BY 4.0."),
    ("CC-BY-SA-4.0", "Licensed under CC BY-SA 4.0."),
    ("CC-BY-NC-4.0", "Licensed under CC BY-NC 4.0."),
    ("CC-BY-ND-4.0", "Licensed under CC BY-ND 4.0."),
    ("CC-BY-NC-SA-4.0", "Licensed under CC BY-NC-SA 4.0."),
    ("CC0-1.0", "Licensed under CC0 1.0."),
    ("MIT", "Licensed under the MIT License."),
    ("MIT", "Released under the MIT License."),
    ("BSD-3-Clause", "Licensed under the BSD 3-Clause License."),
    ("MPL-2.0", "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0."),
)
#: Whole words.
EQUIVALENT_WORDS = (
    ("acknowledgement", "acknowledgment"),
    ("acknowledgements", "acknowledgments"),
    ("analogue", "analog"),
    ("artefact", "artifact"),
    ("artefacts", "artifacts"),
    ("behaviour", "behavior"),
    ("cancelled", "canceled"),
    ("catalogue", "catalog"),
    ("centre", "center"),
    ("copyright owner", "copyright holder"),
    ("favour", "favor"),
    ("favourite", "favorite"),
    ("fulfil", "fulfill"),
    ("fulfilment", "fulfillment"),
    ("judgement", "judgment"),
    ("labelling", "labeling"),
    ("licence", "license"),
    ("licences", "licenses"),
    ("licenced", "licensed"),
    ("merchantibility", "merchantability"),
    ("non commercial", "noncommercial"),
    ("non infringement", "noninfringement"),
    ("per cent", "percent"),
    ("programme", "program"),
    ("programmes", "programs"),
    ("sub license", "sublicense"),
    ("sub licensable", "sublicensable"),
    ("sub licenses", "sublicenses"),
    ("whilst", "while"),
    ("wilful", "willful"),
)
#: Beginnings of words.
EQUIVALENT_STEMS = (
    ("authoris", "authoriz"),
    ("customis", "customiz"),
    ("initialis", "initializ"),
    ("optimis", "optimiz"),
    ("organis", "organiz"),
    ("realis", "realiz"),
    ("recognis", "recogniz"),
    ("utilis", "utiliz"),
)
# End of fixed values.

_SIGN = r"(\(c\)|©|&copy;)"
_YEAR = r"(19|20)[0-9]{2}"
#: A lower-cased line that only says whose the text is; a line of a licence that begins with "copyright notice" is none.
COPYRIGHT_LINE = (
    rf"^[^\p{{L}}\p{{N}}(©&]*((copyright|copr\.?)\s*(:|by\s|{_SIGN}|[\[<{{]).*|{_SIGN}\s*(copyright|by\s).*|copyright\s.*{_YEAR}.*|{_SIGN}.*{_YEAR}.*|all rights reserved[^\p{{L}}\p{{N}}]*)$"
)
_NOT_WORD = r"[^\p{L}\p{N}]+"


def _words(text: Column) -> Column:
    return F.btrim(F.regexp_replace(F.lower(text), _NOT_WORD, " "))


def canonical_words(text: Column) -> Column:
    """Lower-cased words parted by one blank, equivalent spellings made one."""
    # two blanks around each word, so that neighbours do not share one
    apart = F.concat(F.lit(" "), F.replace(_words(text), F.lit(" "), F.lit("  ")), F.lit(" "))
    for found, used in EQUIVALENT_WORDS:
        apart = F.replace(apart, F.lit(f" {found.replace(' ', '  ')} "), F.lit(f" {used.replace(' ', '  ')} "))
    for found, used in EQUIVALENT_STEMS:
        apart = F.replace(apart, F.lit(f" {found}"), F.lit(f" {used}"))
    return F.btrim(F.replace(apart, F.lit("  "), F.lit(" ")))


def canonical_line(line: Column) -> Column:
    """The form in which lines are compared with notices."""
    return F.replace(_words(line), F.lit("licence"), F.lit("license"))


def _own_lines(text: Column) -> Column:
    return F.filter(F.split(text, "\n", -1), lambda line: ~F.lower(line).rlike(COPYRIGHT_LINE))


def canonical_text(text: Column) -> Column:
    """All words of the text but its copyright lines, in canonical form; how it was wrapped into lines does not matter."""
    return canonical_words(F.array_join(_own_lines(text), " "))


def text_digests(texts: DataFrame) -> DataFrame:
    """(license, text) -> (license, canonical_sha256): how entries of LICENSE_DIGESTS are made."""
    return texts.select("license", F.sha2(canonical_text(F.col("text")), 256).alias("canonical_sha256"))


def known_digests(spark, texts=None, titles=None, digests=None) -> DataFrame:
    """(license, canonical_sha256): fixed texts with and without their titles, and fixed digests; a short table."""
    texts = LICENSE_TEXTS if texts is None else texts
    titles = LICENSE_TITLES if titles is None else titles
    rows = [*texts, *[(name, f"{title}\n{text}") for name, text in texts for of, title in titles if of == name]]
    made = text_digests(spark.createDataFrame(rows, "license string, text string"))
    fixed = [(name, digest) for name, _, digest in (LICENSE_DIGESTS if digests is None else digests)]
    return made.unionAll(spark.createDataFrame(fixed, "license string, canonical_sha256 string")).groupBy("canonical_sha256").agg(F.min("license").alias("license"))


def scan_licenses(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", texts=None, notices=LICENSE_NOTICES) -> DataFrame:
    """One row per input row: doc_id, canonical_sha256, license, notices.

    license names the known licence whose canonical text is the whole document's;
    notices lists, sorted and without repeats, the licences whose notice is a
    line of it. A null text is empty and matches nothing; empty tables give no
    rows; other columns are ignored, rows that repeat an id are scanned each.
    Only the fixed tables are broadcast.
    """
    spark = docs.sparkSession
    by_digest = known_digests(spark, texts)
    marks = spark.createDataFrame(list(notices), "license string, text string").select("license", canonical_line(F.col("text")).alias("line")).collect()
    wanted = F.create_map(*[F.lit(x) for r in marks for x in (r["line"], r["license"])])
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), text_or_empty(text_col).alias("text"))
    # only a line that speaks of a licence can be a notice
    lines = F.filter(F.split("text", "\n", -1), lambda line: F.lower(line).rlike("licen[cs]e"))
    named = F.array_sort(F.array_distinct(F.filter(F.transform(lines, lambda line: F.try_element_at(wanted, canonical_line(line))), lambda x: x.isNotNull())))
    scanned = rows.select("doc_id", F.sha2(canonical_text(F.col("text")), 256).alias("canonical_sha256"), named.alias("notices"))
    return scanned.join(F.broadcast(by_digest), "canonical_sha256", "left").select("doc_id", "canonical_sha256", "license", "notices")


def oracle() -> str:
    """The same scan as DuckDB SQL, with notices joined by commas."""

    def quoted(value: str) -> str:
        return "'" + value.replace("'", "''") + "'"

    def words(text: str) -> str:
        return f"trim(regexp_replace(lower({text}), {quoted(_NOT_WORD)}, ' ', 'g'))"

    def canonical(text: str) -> str:
        out = f"' ' || replace({words(text)}, ' ', '  ') || ' '"
        for found, used in EQUIVALENT_WORDS:
            out = f"replace({out}, {quoted(' ' + found.replace(' ', '  ') + ' ')}, {quoted(' ' + used.replace(' ', '  ') + ' ')})"
        for found, used in EQUIVALENT_STEMS:
            out = f"replace({out}, {quoted(' ' + found)}, {quoted(' ' + used)})"
        return f"trim(replace({out}, '  ', ' '))"

    def table(entries) -> str:
        return ", ".join("(" + ", ".join(map(quoted, entry)) + ")" for entry in entries)

    def line(text: str) -> str:
        return f"replace({words(text)}, 'licence', 'license')"

    return f"""
        WITH texts(license, text) AS (VALUES {table(LICENSE_TEXTS)}), titles(license, title) AS (VALUES {table(LICENSE_TITLES)}),
        marks(license, text) AS (VALUES {table(LICENSE_NOTICES)}), digests(license, part, canonical_sha256) AS (VALUES {table(LICENSE_DIGESTS)}),
        every AS (
            SELECT true AS doc, row_number() OVER () AS nr, doc_id, NULL AS license, coalesce(text, '') AS text FROM documents
            UNION ALL SELECT false, row_number() OVER (), NULL, license, text FROM (
                SELECT license, text FROM texts UNION ALL SELECT license, title || chr(10) || text FROM titles JOIN texts USING (license))
        ), cut AS (SELECT *, string_split(text, chr(10)) AS lines FROM every),
        canon AS (
            SELECT doc, doc_id, license, lines, sha256({canonical(f"array_to_string(list_filter(lines, lambda l: NOT regexp_matches(lower(l), {quoted(COPYRIGHT_LINE)})), ' ')")}) AS canonical_sha256 FROM cut
        ), known AS (
            SELECT canonical_sha256, min(license) AS license FROM (SELECT canonical_sha256, license FROM canon WHERE NOT doc UNION ALL SELECT canonical_sha256, license FROM digests) GROUP BY ALL
        ), found AS (
            SELECT doc_id, string_agg(DISTINCT m.license, ',' ORDER BY m.license) AS notices
            FROM (SELECT doc_id, unnest(lines) AS line FROM canon WHERE doc) l JOIN (SELECT license, {line("text")} AS key FROM marks) m ON {line("l.line")} = m.key GROUP BY doc_id
        )
        SELECT doc_id, canon.canonical_sha256, known.license AS license, coalesce(notices, '') AS notices
        FROM canon LEFT JOIN known USING (canonical_sha256) LEFT JOIN found USING (doc_id) WHERE doc
    """
