"""Licence scans by canonical digests.

A text is normalised (case, copyright lines, punctuation, equivalent spellings, white space) and
its digest is hash-joined with the digests of known licence texts and notices. Each entire document is
looked up, and so is each of its lines, as notices of one line stand within other text.
"""

from __future__ import annotations

import hashlib
import re

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ._common import materialize

_WARRANTY = (
    'THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, '
    "FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER "
    "LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE."
)
_GRANT = (
    "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal "
    "in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies "
    "of the Software, and to permit persons to whom the Software is furnished to do so"
)
_BSD_HEAD = (
    "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: "
    "1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer. "
    "2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation "
    "and/or other materials provided with the distribution. "
)
_BSD_THIRD = (
    "3. Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software "
    "without specific prior written permission. "
)
_BSD_TAIL = (
    'THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS "AS IS" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED '
    "WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, "
    "INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR "
    "PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) "
    "ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE."
)
_ISC_GRANT = "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted"
_ISC_TAIL = (
    'THE SOFTWARE IS PROVIDED "AS IS" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. '
    "IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, "
    "WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE."
)

# Published licence texts and notices, (identifier, kind, text).
KNOWN: list[tuple[str, str, str]] = [
    ("MIT", "text", f"{_GRANT}, subject to the following conditions: The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software. {_WARRANTY}"),
    ("MIT", "text", f"MIT License {_GRANT}, subject to the following conditions: The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software. {_WARRANTY}"),
    ("MIT", "text", f"The MIT License (MIT) {_GRANT}, subject to the following conditions: The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software. {_WARRANTY}"),
    ("MIT-0", "text", f"{_GRANT}. {_WARRANTY}"),
    ("BSD-2-Clause", "text", _BSD_HEAD + _BSD_TAIL),
    ("BSD-3-Clause", "text", _BSD_HEAD + _BSD_THIRD + _BSD_TAIL),
    ("ISC", "text", f"{_ISC_GRANT}, provided that the above copyright notice and this permission notice appear in all copies. {_ISC_TAIL}"),
    ("0BSD", "text", f"{_ISC_GRANT}. {_ISC_TAIL}"),
    ("WTFPL", "text", "Everyone is permitted to copy and distribute verbatim or modified copies of this license document, and changing it is allowed as long as the name is changed. "
     "DO WHAT THE FUCK YOU WANT TO PUBLIC LICENSE TERMS AND CONDITIONS FOR COPYING, DISTRIBUTION AND MODIFICATION 0. You just DO WHAT THE FUCK YOU WANT TO."),
    ("Apache-2.0", "notice", 'Licensed under the Apache License, Version 2.0 (the "License"); you may not use this file except in compliance with the License. You may obtain a copy of the License at '
     'http://www.apache.org/licenses/LICENSE-2.0 Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an "AS IS" BASIS, '
     "WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. See the License for the specific language governing permissions and limitations under the License."),
    ("Apache-2.0", "notice", "Licensed under the Apache License, Version 2.0."),
    ("Apache-2.0", "notice", "Released under the Apache License, Version 2.0."),
    ("MIT", "notice", "Released under the MIT License."),
    ("MIT", "notice", "Licensed under the MIT License."),
    ("BSD-3-Clause", "notice", "Licensed under the BSD 3-Clause License."),
    ("BSD-2-Clause", "notice", "Licensed under the BSD 2-Clause License."),
    ("GPL-3.0-only", "notice", "This work is licensed under the GNU General Public License, version 3."),
    ("GPL-2.0-only", "notice", "This work is licensed under the GNU General Public License, version 2."),
    ("MPL-2.0", "notice", "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can obtain one at http://mozilla.org/MPL/2.0/."),
    ("CC-BY-4.0", "notice", "Licensed under CC BY 4.0."),
    ("CC-BY-SA-4.0", "notice", "Licensed under CC BY-SA 4.0."),
    ("CC-BY-NC-4.0", "notice", "Licensed under CC BY-NC 4.0."),
    ("LicenseRef-all-rights-reserved", "notice", "All rights reserved."),
]

# Patterns of the normal form, in the order they are applied; $1 stands for a group.
_STEPS: list[tuple[str, str]] = [
    (r"(?m)^[ \t*#/;>-]*(?:copyright|\(c\)|©)[^\n]*$", " "),
    (r"[^\p{L}\p{N}]+", " "),
    (r"\b(sub ?)?licenc(e|es|ed|ing)\b", "$1licens$2"),
    (r"\bsub licens", "sublicens"),
    (r"\bnon (commercial|infring)", "non$1"),
    (r"is(ation|ations|ed)\b", "iz$1"),
    (r"\b(fav|hon|behavi|col)our", "$1or"),
    (r"\bhttps\b", "http"),
    (r"\bversion ([0-9])", "v $1"),
]

def canonical(text: str) -> str:
    """Normal form of a text in Python, as ``canonical_column`` has it in Spark."""
    import regex

    t = text.lower()
    for pattern, to in _STEPS:
        t = regex.sub(pattern, re.sub(r"\$(\d)", r"\\g<\1>", to), t)
    return t.strip(" ")


def canonical_column(text: Column) -> Column:
    """Normal form of a text column."""
    t = F.lower(text)
    for pattern, to in _STEPS:
        t = F.regexp_replace(t, pattern, to)
    return F.trim(t)


# Digests of the normal forms of full published licence texts, as distributed in /usr/share/common-licenses of Debian.
FULL_TEXTS: list[tuple[str, str]] = [
    ("Apache-2.0", "c9081eb4c32d1fea51072b4b640a3300c510479f37ccef5cd3882de827e28eb0"),
    ("Artistic-1.0-Perl", "bb8defd9569b21263e7d4937631aabf3f5e6675421526c14638e34953c17f788"),
    ("CC0-1.0", "cccf7894e1b9f4ba9f97728bf0c5baf9e07bc2ac93da7a51556451b1fb2b868e"),
    ("GFDL-1.2", "294920afafd8d56a68fcb7d3e58dbc90a639895976daa77745095128ba3a22f9"),
    ("GFDL-1.3", "72331336c0a87023c76d6dab33c04b9d1475abeb542943808a27c88ccc6a3838"),
    ("GPL-1.0", "aa432157910b2e0326a18007704d9eba3d89019ef4ea73fbad88cb12ce23a704"),
    ("GPL-2.0", "2439799e17b9018f365849fd611b0e233279311934c583dff221e7dc6a7cf347"),
    ("GPL-3.0", "24b68cadf2578f408edaac939b0cf129e97f867de4a3074a78ec64198b83ddd1"),
    ("LGPL-2.0", "85066ee51187bd76f8e13af18bf4f2e8a67059da071ee8f4241bd84f921edfa7"),
    ("LGPL-2.1", "e16bc5a70e8c73d3b5ea58aa992261e5456480214cbb2aa7fb765c79e8cfd3d8"),
    ("LGPL-3.0", "34de6bd0389d0ddbe4fa92b79ef8574e3d27ad21db12c89eb50c7de12a11ac5b"),
    ("MPL-1.1", "f0c6fc10b143fc4ff9938ec2e72683f4911feb29394d5d19429473421c88f530"),
    ("MPL-2.0", "cbde037c7e7fcfc8e0375a5564178a398d830b397516cc44db8db6d5070ac2d9"),
]


def known_digests(known: list[tuple[str, str, str]] | None = None) -> list[tuple[str, str, str]]:
    """``(digest, licence, kind)`` of the known texts, one row for each normal form; with the full texts' unless ``known`` is given."""
    out: dict[str, tuple[str, str, str]] = {}
    for licence, kind, text in known or KNOWN:
        d = hashlib.sha256(canonical(text).encode()).hexdigest()
        out.setdefault(d, (d, licence, kind))
    if known is None:
        for licence, d in FULL_TEXTS:
            out.setdefault(d, (d, licence, "text"))
    return list(out.values())


def digest_table(spark, known: list[tuple[str, str, str]] | None = None) -> DataFrame:
    """The known digests as a table ``(digest, licence, kind)``."""
    return spark.createDataFrame(known_digests(known), "digest string, licence string, kind string")


def scan(docs: DataFrame, known: DataFrame | None = None, id_col: str = "doc_id", text_col: str = "text", broadcast_rows: int = 100_000) -> DataFrame:
    """Licences per row: ``(id_col, whole_licence, licences, n_lines)``.

    ``whole_licence`` names the licence that the entire text is (null: none; the first by name if a digest
    has several), ``licences`` all that the text or a line of it matches, sorted, ``n_lines`` how many lines
    match. Every text and every line is normalised and joined with ``known(digest, licence)``, which is
    broadcast if it has at most ``broadcast_rows`` rows. Null and empty texts match nothing, null ids are ids like any
    other, repeated rows have equal results, an empty table an empty one; other columns are ignored.
    """
    known = (digest_table(docs.sparkSession) if known is None else known).select("digest", "licence").distinct()

    def sized(df: DataFrame) -> DataFrame:
        return F.broadcast(df) if df.limit(broadcast_rows + 1).count() <= broadcast_rows else df

    text = F.coalesce(F.col(text_col), F.lit(""))
    digest = lambda t: F.sha2(canonical_column(t).cast("binary"), 256)
    s = docs.select(F.col(id_col).alias("id"), F.xxhash64(text).alias("h"), F.octet_length(text).alias("size"), text.alias("t"))
    units = s.select("id", "h", "size", F.posexplode(F.concat(F.array(digest(F.col("t"))), F.transform(F.split("t", "\n"), digest))).alias("unit", "digest"))
    # equal rows find the same, so a row's matches are known by its id and text
    hits = materialize(units.join(sized(known), "digest").select("id", "h", "size", "unit", "licence").distinct(), "licence-hits")
    found = hits.groupBy("id", "h", "size").agg(
        F.min(F.when(F.col("unit") == 0, F.col("licence"))).alias("whole_licence"), F.sort_array(F.collect_set("licence")).alias("licences"),
        F.countDistinct(F.when(F.col("unit") > 0, F.col("unit"))).alias("n_lines"),
    )
    found = sized(materialize(found.select(F.col("id").alias("id2"), F.col("h").alias("h2"), F.col("size").alias("size2"), "whole_licence", "licences", "n_lines"), "licence-rows"))
    out = s.drop("t").join(found, F.col("id").eqNullSafe(F.col("id2")) & (F.col("h") == F.col("h2")) & (F.col("size") == F.col("size2")), "left")
    return out.select(F.col("id").alias(id_col), "whole_licence", F.coalesce("licences", F.array().cast("array<string>")).alias("licences"), F.coalesce("n_lines", F.lit(0)).alias("n_lines"))


def licence_scan(spark, sf_dir: str) -> DataFrame:
    """Query op7: licences of all documents; the list is joined by commas."""
    out = scan(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    return out.select("doc_id", "whole_licence", F.concat_ws(",", "licences").alias("licences"), "n_lines")


def _form(unit: str) -> str:
    """DuckDB expression of the normal form, written for itself."""
    t = rf"regexp_replace(lower({unit}), '(?m)^[ \t*#/;>-]*(?:copyright|\(c\)|©)[^\n]*$', ' ', 'g')"
    t = rf"regexp_replace({t}, '[^\p{{L}}\p{{N}}]+', ' ', 'g')"
    t = rf"regexp_replace(regexp_replace({t}, '\b(sub ?)?licenc(e|es|ed|ing)\b', '\1licens\2', 'g'), '\bsub licens', 'sublicens', 'g')"
    t = rf"regexp_replace(regexp_replace({t}, '\bnon (commercial|infring)', 'non\1', 'g'), 'is(ation|ations|ed)\b', 'iz\1', 'g')"
    t = rf"regexp_replace({t}, '\b(fav|hon|behavi|col)our', '\1or', 'g')"
    return rf"trim(regexp_replace(regexp_replace({t}, '\bhttps\b', 'http', 'g'), '\bversion ([0-9])', 'v \1', 'g'))"


def sql() -> str:
    """DuckDB SQL of the query, which normalises the known texts itself; of full texts it has the digests."""
    texts = ", ".join("('" + licence + "', '" + text.replace("'", "''") + "')" for licence, _, text in KNOWN)
    full = ", ".join(f"('{licence}', '{d}')" for licence, d in FULL_TEXTS)
    return f"""
WITH named(licence, t) AS (VALUES {texts}), full_text(licence, digest) AS (VALUES {full}),
k AS (SELECT DISTINCT digest, licence FROM (SELECT licence, sha256({_form('t')}) AS digest FROM named UNION ALL SELECT licence, digest FROM full_text)),
d AS (SELECT row_number() OVER () AS rid, doc_id, coalesce(text, '') AS t FROM documents),
u AS (SELECT rid, true AS whole, t AS unit FROM d UNION ALL
      SELECT rid, false AS whole, unnest(string_split(t, chr(10))) AS unit FROM d),
m AS (SELECT rid, whole, licence FROM u JOIN k ON k.digest = sha256({_form('unit')})),
a AS (SELECT rid, min(CASE WHEN whole THEN licence END) AS whole_licence, count(*) FILTER (NOT whole) AS n_lines FROM m GROUP BY rid),
l AS (SELECT rid, string_agg(licence, ',' ORDER BY licence) AS licences FROM (SELECT DISTINCT rid, licence FROM m) GROUP BY rid)
SELECT doc_id, whole_licence, coalesce(licences, '') AS licences, CAST(coalesce(n_lines, 0) AS BIGINT) AS n_lines
FROM d LEFT JOIN a USING (rid) LEFT JOIN l USING (rid)
"""
