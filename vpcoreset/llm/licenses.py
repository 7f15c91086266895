"""License scans by canonical digest lookup, in DataFrame expressions only.

A text is made canonical and its SHA-256 is looked up among the digests of known license texts, made canonical by the same
expression: lower case; copyright lines, list marks at the begin of lines and a title at the begin of the text dropped; punctuation of any
script, comment marks among it, turned to spaces; equivalent spellings unified, the names of owners in the usual clauses among them; spaces
collapsed. The catalogue is a fixed list, texts where they are short and digests alone where they are long, so its table is broadcast.

Three things are looked up, all by entire text: the document; each of its lines that may be a notice (all known ones hold the
word); and, in documents with blank lines, each run of up to ``RUN`` paragraphs, which finds a license at the head of
a file or between other text.

Defined results: one row for each input row, repeated rows included; null counts as empty; a text
with nothing left has the digest of the empty string and no license. Columns other than id and
text are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

# Spellings that count as one (variant, canonical).
SPELLINGS = (
    ("licence", "license"), ("licences", "licenses"), ("licenced", "licensed"), ("sublicence", "sublicense"),
    ("sub license", "sublicense"), ("sub licence", "sublicense"), ("non commercial", "noncommercial"), ("non infringement", "noninfringement"),
    ("copyright owner", "copyright holder"), ("copyright owners", "copyright holders"), ("merchantibility", "merchantability"),
    ("organisation", "organization"), ("behaviour", "behavior"), ("favour", "favor"), ("fulfil", "fulfill"), ("judgement", "judgment"),
    ("labour", "labor"), ("acknowledgement", "acknowledgment"), ("programme", "program"), ("whilst", "while"), ("wilful", "willful"),
    ("per cent", "percent"), ("artefact", "artifact"), ("analogue", "analog"), ("authorisation", "authorization"), ("authorised", "authorized"),
)

_NO_WARRANTY = (
    'THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF '
    "MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY "
    "CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE "
    "SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE."
)
_ISC_TAIL = (
    'THE SOFTWARE IS PROVIDED "AS IS" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF '
    "MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES "
    "WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF "
    "OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE."
)
_BSD_HEAD = (
    "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: "
    "\n1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer. "
    "\n2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the "
    "documentation and/or other materials provided with the distribution. "
)
_BSD_TAIL = (
    'THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS "AS IS" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED '
    "TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR "
    "CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, "
    "PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF "
    "LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS "
    "SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE."
)

# Known license texts and notices.
KNOWN = (
    ("MIT", "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the "
     '"Software"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, '
     "distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the "
     "following conditions: The above copyright notice and this permission notice shall be included in all copies or substantial portions of the "
     "Software. " + _NO_WARRANTY),
    ("ISC", "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the "
     "above copyright notice and this permission notice appear in all copies. " + _ISC_TAIL),
    ("0BSD", "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted. " + _ISC_TAIL),
    ("BSD-2-Clause", _BSD_HEAD + _BSD_TAIL),
    ("BSD-3-Clause", _BSD_HEAD + "\n3. Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products "
     "derived from this software without specific prior written permission. " + _BSD_TAIL),
    ("MIT-0", "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the "
     '"Software"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, '
     "distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so. " + _NO_WARRANTY),
    ("Zlib", "This software is provided 'as-is', without any express or implied warranty. In no event will the authors be held liable for any damages "
     "arising from the use of this software. Permission is granted to anyone to use this software for any purpose, including commercial applications, "
     "and to alter it and redistribute it freely, subject to the following restrictions: "
     "\n1. The origin of this software must not be misrepresented; you must not claim that you wrote the original software. If you use this software in "
     "a product, an acknowledgment in the product documentation would be appreciated but is not required. "
     "\n2. Altered source versions must be plainly marked as such, and must not be misrepresented as being the original software. "
     "\n3. This notice may not be removed or altered from any source distribution."),
    ("Unlicense", "This is free and unencumbered software released into the public domain. Anyone is free to copy, modify, publish, use, compile, sell, or "
     "distribute this software, either in source code form or as a compiled binary, for any purpose, commercial or non-commercial, and by any means. "
     "In jurisdictions that recognize copyright laws, the author or authors of this software dedicate any and all copyright interest in the software to "
     "the public domain. We make this dedication for the benefit of the public at large and to the detriment of our heirs and successors. We intend this "
     "dedication to be an overt act of relinquishment in perpetuity of all present and future rights to this software under copyright law. "
     'THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, '
     "FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN "
     "AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE. "
     "For more information, please refer to <https://unlicense.org>"),
    ("BSL-1.0", "Boost Software License - Version 1.0 - August 17th, 2003 Permission is hereby granted, free of charge, to any person or organization "
     'obtaining a copy of the software and accompanying documentation covered by this license (the "Software") to use, reproduce, display, distribute, '
     "execute, and transmit the Software, and to prepare derivative works of the Software, and to permit third-parties to whom the Software is furnished to "
     "do so, all subject to the following: The copyright notices in the Software and this entire statement, including the above license grant, this "
     "restriction and the following disclaimer, must be included in all copies of the Software, in whole or in part, and all derivative works of the "
     "Software, unless such copies or derivative works are solely in the form of machine-executable object code generated by a source language processor. "
     'THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, '
     "FITNESS FOR A PARTICULAR PURPOSE, TITLE AND NON-INFRINGEMENT. IN NO EVENT SHALL THE COPYRIGHT HOLDERS OR ANYONE DISTRIBUTING THE SOFTWARE BE LIABLE "
     "FOR ANY DAMAGES OR OTHER LIABILITY, WHETHER IN CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR "
     "OTHER DEALINGS IN THE SOFTWARE."),
    ("Apache-2.0", 'Licensed under the Apache License, Version 2.0 (the "License"); you may not use this file except in compliance with the License. You may '
     "obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0 Unless required by applicable law or agreed to in writing, software "
     'distributed under the License is distributed on an "AS IS" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. See '
     "the License for the specific language governing permissions and limitations under the License."),
    ("Apache-2.0", "Licensed under the Apache License, Version 2.0."),
    ("MIT", "Released under the MIT License."),
    ("MIT", "Licensed under the MIT License."),
    ("GPL-3.0-only", "This work is licensed under the GNU General Public License, version 3."),
    ("GPL-2.0-only", "This work is licensed under the GNU General Public License, version 2."),
    ("CC-BY-NC-4.0", "Licensed under CC BY-NC 4.0."),
    ("CC-BY-4.0", "Licensed under CC BY 4.0."),
    ("CC-BY-SA-4.0", "Licensed under CC BY-SA 4.0."),
    ("MPL-2.0", "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0."),
    ("BSD-3-Clause", "Licensed under the BSD 3-Clause License."),
)

# Digests of the canonical forms of long texts, whole and, where it has an appendix, up to the end of its terms.
DIGESTS = (
    ("Apache-2.0", "df0f75ddc52c0f9d6793127f4aeb40593498539ca5525cbab747e9c6733003a6"),
    ("Apache-2.0", "a6d12277a8172bb36d8b3c59a42145e62bbb2f148e5e6d5c0fda3c56b14652ec"),
    ("Apache-2.0", "c804e5be9fa7c15bab2a4f4d66b587187be51de0cb3ad93ef20d685870268725"),
    ("Artistic-1.0-Perl", "4834e699353522cfb463bd8b374752ecf02156bb3f5dfb53d0edb502a112a651"),
    ("BSD-3-Clause", "1ff9c8e9b5283ec732f679694eed7f7ffeb6431e54a037aac6f493a1812e9c5e"),
    ("CC0-1.0", "888ab175b43ed137ae3c3f8f32a1f0e1677fe31f7a9f09890c39b11b1934ad6c"),
    ("GFDL-1.2", "66c938a4f3d2114cc3d60f4233a4f26e8c730064aa767788d4745dedea334da1"),
    ("GFDL-1.3", "3c375c0e780727eaa9ddb17a7fa022a4b0b7ed527f12a3da106f47b622a3b3f1"),
    ("GPL-1.0", "8e55a396b3dde2d2c3b83a828d0dcb3df1893ffa64d355d5329551ad1b33172d"),
    ("GPL-1.0", "fd4023b6759b9c21d0aa52eeb184484e4f57aaeb5a456760e417027b04126264"),
    ("GPL-1.0", "3e2d93b3b4e51d1730b9688bc0ac9eccb172068d50cdd0a81d6000d6dda13c96"),
    ("GPL-2.0", "2793e3e53325e684d7fae46e68e633ada62d21e6fde965c743d7841746d7ba97"),
    ("GPL-2.0", "bd40cc44e06b546df0f3357cec11104bd8c377e684c50779472ee8c79007500a"),
    ("GPL-2.0", "f060f5db316d38265bcc6bb0fb223fbdd4f39ea9c2027be09c03bb423a9598db"),
    ("GPL-3.0", "afabb4884c87bfcf01c72bd36caeb201377261aa5fe0379e7251324897d5645e"),
    ("GPL-3.0", "a2790cd13a69215db50c483a7194cdcdc9473928f70d2c2e6ca84c787b4b8de4"),
    ("GPL-3.0", "0c756dc22851cb63325862aabae753c6cbe64d3d1451a46e23e328209325ccbe"),
    ("LGPL-2.0", "4917d3d16c95b9ed7028cb23991d9b0aed15a222d1938ae58dcc2d9287efc5fb"),
    ("LGPL-2.0", "700b5be7ea21cccaa9257cd9b26d3f9be4628978d375eb4f5eef9792ce812447"),
    ("LGPL-2.0", "96fd22575a1073b95c433846a35a0d44597efa60ad30929254c39da27fc57fce"),
    ("LGPL-2.1", "6854c7d91ad1cc7defef51027dac78ea4cbc444cba21aa032347362318916b8c"),
    ("LGPL-2.1", "3641373af7eed12e3e429b4235ff1092b856606ddc012309815970a74ca071a4"),
    ("LGPL-2.1", "42f8a14a7070eb0ed3c3071a47b80452745e09a18db7230cc3646d264f73a650"),
    ("LGPL-3.0", "06dd0bbc351a22d4cdb46b62218641d9f675ccd37c406714439819f8aeecc9e2"),
    ("MPL-1.1", "0b40eb2ffd1e9291836a92562377492bab8f8cd090589f99b378c2c86b6e37c8"),
    ("MPL-2.0", "a64e7b09e84ed98929faf12d13770c23a2548b3285c09472dbf8b804769ab4b7"),
)

#: A line that names an owner or a year; lines of a wrapped text that merely begin with the word stay.
COPYRIGHT_LINE = r"(^|\n)[ \t/*#;%-]*(copyright[ \t]*(\(c\)|©|:|[0-9]|by )|\(c\)|©|all rights reserved)[^\n]*"
#: Numbers and letters of lists.
LIST_MARK = r"(^|\n)([ \t/*#;%-]*)(\(?[0-9]{1,2}[.)]|\(?[a-z][.)])[ \t]+"
NOT_WORD = r"[^\p{L}\p{M}\p{N}]+"
TITLE = (
    r"^(the )?((new |simplified |modified |revised )?bsd( [0-9] clause| zero clause)?|mit|mit 0|mit no attribution|isc|zlib|x11|expat|unlicense|boost software|apache|mozilla public|gnu (lesser |library )?general public)"
    r" license( mit| isc| expat)?( version [0-9]( [0-9])?)?( |$)")
#: Clauses with the name of an owner: (what a text must hold, pattern, canonical form). Other wildcards there are none.
OWNERS = (
    ("neither the name", "neither the names? of .{1,120}? (nor|or) the names of (its|any|their) contributors", "neither the name of the owner nor the names of its contributors"),
    ("and contributors as is", "provided by .{1,120}? and contributors as is", "provided by the owner and contributors as is"),
    ("in no event shall", "in no event shall .{1,120}? be liable", "in no event shall the owner be liable"),
)
VARIANT = "(^| )(" + "|".join(a for a, _ in SPELLINGS) + ")( |$)"
RUN = 8
TRIGGER = "permission|redistribution|warrant|licen[cs]e|unencumbered"


def _once(value: Column, use) -> Column:
    """use(value), with value worked out, and spelt out in the plan, once although use may read it often."""
    return F.element_at(F.transform(F.array(value), use), 1)


def _plain(low: Column) -> Column:
    """Words of a text in lower case without copyright lines and list marks."""
    owned = low.contains("copyright") | low.contains("(c)") | low.contains("©") | low.contains("all rights reserved")
    bare = F.when(owned, F.regexp_replace(low, COPYRIGHT_LINE, "\n")).otherwise(low)
    bare = _once(bare, lambda x: F.when(low.rlike(TRIGGER), F.regexp_replace(x, LIST_MARK, "$1")).otherwise(x))
    return F.trim(F.regexp_replace(bare, NOT_WORD, " "))


def _usual(plain: Column) -> Column:
    one = plain
    for variant, usual in SPELLINGS:  # twice: a match takes its spaces, so neighbours need a second turn
        for _ in range(2):
            one = F.regexp_replace(one, f"(^| ){variant}( |$)", f"$1{usual}$2")
    return F.when(plain.rlike(VARIANT), one).otherwise(plain)


def _unnamed(held: str, pattern: str, usual: str):
    return lambda x: F.when(x.contains(held), F.regexp_replace(x, pattern, usual)).otherwise(x)


def canonical(text: Column) -> Column:
    """The form of a text of which the digest is taken; only letters and digits are left, single spaces between words.

    A condition repeats the text that it tests, so each step is bound by ``_once``: without that the expression grows threefold with every step.
    """
    one = _once(F.translate(F.coalesce(text, F.lit("")), "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"), _plain)
    one = _once(one, _usual)
    for owner in OWNERS:
        one = _once(one, _unnamed(*owner))
    return F.regexp_replace(one, TITLE, "")


def known_digests(spark) -> DataFrame:
    """(digest, license) of the catalogue; as many rows as it has entries, whatever the input."""
    rows = spark.createDataFrame([(a, b) for a, b in KNOWN], "license string, known string")
    texts = rows.select(F.sha2(canonical(F.col("known")), 256).alias("digest"), "license")
    return texts.unionByName(spark.createDataFrame([(d, a) for a, d in DIGESTS], "digest string, license string")).groupBy("digest").agg(F.min("license").alias("license"))


def scan_licenses(docs: DataFrame, *, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, digest, license, notices, blocks): the license that the entire text is, those that its lines announce, and those whose text runs of its paragraphs are."""
    known = sorted((r["digest"], r["license"]) for r in known_digests(docs.sparkSession).collect())
    catalogue = docs.sparkSession.createDataFrame(known, "digest string, license string")
    held = F.create_map(*[x for row in known for x in map(F.lit, row)])
    names = lambda digests: F.array_join(F.array_sort(F.array_distinct(F.filter(F.transform(digests, lambda x: held[x]), lambda x: x.isNotNull()))), ",")
    text = F.coalesce(F.col(text_col), F.lit(""))
    low = F.translate(text, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    lines = F.filter(F.split(text, "\n", -1), lambda x: F.translate(x, "LICENS", "licens").rlike("licen[cs]e"))
    paragraphs = F.filter(F.transform(F.split(text, "\n[ \t\r]*\n", -1), canonical), lambda x: x != "")
    runs = lambda ps, k: F.transform(F.filter(F.sequence(F.lit(1), F.greatest(F.size(ps), F.lit(1))), lambda i: i + k - 1 <= F.size(ps)), lambda i: F.sha2(F.array_join(F.slice(ps, i, k), " "), 256))
    blocks = F.when(low.rlike(r"\n[ \t\r]*\n") & low.rlike(TRIGGER), _once(paragraphs, lambda ps: names(F.flatten(F.array(*[runs(ps, F.lit(k)) for k in range(1, RUN + 1)]))))).otherwise(F.lit(""))
    notices = F.when(low.rlike("licen[cs]e"), names(F.transform(lines, lambda x: F.sha2(canonical(x), 256)))).otherwise(F.lit(""))
    rows = docs.select(F.col(id_col).alias("id"), F.sha2(canonical(F.col(text_col)), 256).alias("digest"), notices.alias("notices"), blocks.alias("blocks"))
    return rows.join(F.broadcast(catalogue), "digest", "left").select(F.col("id").alias(id_col), "digest", "license", "notices", "blocks")


def _canonical_sql(x: str) -> str:
    low = f"translate(coalesce({x}, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"
    low = rf"regexp_replace({low}, '{COPYRIGHT_LINE}', chr(10), 'g')"
    low = rf"regexp_replace({low}, '{LIST_MARK}', CASE WHEN regexp_matches(lower({x}), '{TRIGGER}') THEN '\1' ELSE '\0' END, 'g')"
    one = rf"trim(regexp_replace({low}, '{NOT_WORD}', ' ', 'g'))"
    for variant, usual in SPELLINGS:
        for _ in range(2):
            one = rf"regexp_replace({one}, '(^| ){variant}( |$)', '\1{usual}\2', 'g')"
    for _, pattern, usual in OWNERS:
        one = f"regexp_replace({one}, '{pattern}', '{usual}', 'g')"
    return f"regexp_replace({one}, '{TITLE}', '')"


def licenses_sql() -> str:
    values = ", ".join("('{}', '{}')".format(a, b.replace("'", "''")) for a, b in KNOWN)
    digests = ", ".join(f"('{a}', '{d}')" for a, d in DIGESTS)
    windows = " UNION ALL ".join(
        f"SELECT doc_id, row_no, string_agg(c, ' ') OVER w AS run, count(*) OVER w AS n, {k} AS k FROM paras WINDOW w AS (PARTITION BY row_no ORDER BY pos ROWS BETWEEN CURRENT ROW AND {k - 1} FOLLOWING)" for k in range(1, RUN + 1))
    return f"""
WITH listed AS (SELECT license, sha256({_canonical_sql("known")}) AS digest FROM (VALUES {values}) t(license, known) UNION ALL SELECT * FROM (VALUES {digests}) d(license, digest)),
known AS (SELECT min(license) AS license, digest FROM listed GROUP BY digest),
docs AS (SELECT row_number() OVER () AS row_no, doc_id, coalesce(text, '') AS text FROM documents),
lined AS (SELECT row_no, unnest(string_split(text, chr(10))) AS line FROM docs),
noted AS (
  SELECT row_no, string_agg(DISTINCT license, ',' ORDER BY license) AS notices
  FROM (SELECT row_no, sha256({_canonical_sql("line")}) AS digest FROM lined WHERE regexp_matches(translate(line, 'LICENS', 'licens'), 'licen[cs]e')) JOIN known USING (digest) GROUP BY 1),
cut AS (SELECT row_no, doc_id, string_split_regex(text, '\n[ \t\r]*\n') AS ps FROM docs WHERE regexp_matches(text, '\n[ \t\r]*\n') AND regexp_matches(lower(text), '{TRIGGER}')),
numbered AS (SELECT row_no, doc_id, unnest(ps) AS part, unnest(range(len(ps))) AS pos FROM cut),
paras AS (SELECT * FROM (SELECT row_no, doc_id, pos, {_canonical_sql("part")} AS c FROM numbered) WHERE c <> ''),
windows AS ({windows}),
blocked AS (SELECT row_no, string_agg(DISTINCT license, ',' ORDER BY license) AS blocks FROM (SELECT row_no, sha256(run) AS digest FROM windows WHERE n = k) JOIN known USING (digest) GROUP BY 1),
whole AS (SELECT row_no, doc_id, sha256({_canonical_sql("text")}) AS digest FROM docs)
SELECT doc_id, digest, license, coalesce(notices, '') AS notices, coalesce(blocks, '') AS blocks
FROM whole LEFT JOIN known USING (digest) LEFT JOIN noted USING (row_no) LEFT JOIN blocked USING (row_no)
"""
