"""Licence scans by canonical digests.

A text and each of its lines are brought to one canonical form (lower case, copyright lines out, one spelling for equivalent words, anything but
letters and digits to single spaces) and their SHA-256 is looked up in a table of known digests by a hash join. The known table is part of
the code, so its broadcast has a fixed size.

Nulls: a null or empty text has the digest of the empty text and no licence; a null id stays. Repeated rows give repeated rows. Notices are listed once
each. Lines are brought to canonical form whole, however long. Other columns of the input, whatever their names, aren't read. An empty table gives no rows.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from accord.llm.common import table

_AS_IS = 'THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE.'
_ISC_GRANT = "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted"
_ISC_END = 'THE SOFTWARE IS PROVIDED "AS IS" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE.'
_BSD_HEAD = "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: 1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer. 2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution."
_BSD_NAME = "3. Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission."
_BSD_END = 'THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS "AS IS" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE.'
_MIT_GRANT = 'Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the "Software"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions: The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software.'
_ZLIB = "This software is provided 'as-is', without any express or implied warranty. In no event will the authors be held liable for any damages arising from the use of this software. Permission is granted to anyone to use this software for any purpose, including commercial applications, and to alter it and redistribute it freely, subject to the following restrictions: 1. The origin of this software must not be misrepresented; you must not claim that you wrote the original software. If you use this software in a product, an acknowledgment in the product documentation would be appreciated but is not required. 2. Altered source versions must be plainly marked as such, and must not be misrepresented as being the original software. 3. This notice may not be removed or altered from any source distribution."
_APACHE = 'Licensed under the Apache License, Version 2.0 (the "License"); you may not use this file except in compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0 Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an "AS IS" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. See the License for the specific language governing permissions and limitations under the License.'

#: Public licence texts and notices, with and without their titles.
KNOWN = [
    ("MIT", f"{_MIT_GRANT} {_AS_IS}"),
    ("MIT", f"MIT License {_MIT_GRANT} {_AS_IS}"),
    ("MIT", f"The MIT License (MIT) {_MIT_GRANT} {_AS_IS}"),
    ("ISC", f"{_ISC_GRANT}, provided that the above copyright notice and this permission notice appear in all copies. {_ISC_END}"),
    ("ISC", f"ISC License {_ISC_GRANT}, provided that the above copyright notice and this permission notice appear in all copies. {_ISC_END}"),
    ("0BSD", f"{_ISC_GRANT}. {_ISC_END}"),
    ("0BSD", f"BSD Zero Clause License {_ISC_GRANT}. {_ISC_END}"),
    ("BSD-2-Clause", f"{_BSD_HEAD} {_BSD_END}"),
    ("BSD-2-Clause", f"BSD 2-Clause License {_BSD_HEAD} {_BSD_END}"),
    ("BSD-3-Clause", f"{_BSD_HEAD} {_BSD_NAME} {_BSD_END}"),
    ("BSD-3-Clause", f"BSD 3-Clause License {_BSD_HEAD} {_BSD_NAME} {_BSD_END}"),
    ("Zlib", _ZLIB),
    ("Zlib", f"zlib License {_ZLIB}"),
    ("Apache-2.0", _APACHE),
    ("Apache-2.0", "Licensed under the Apache License, Version 2.0."),
    ("Apache-2.0", "SPDX-License-Identifier: Apache-2.0"),
    ("MIT", "Released under the MIT License."),
    ("MIT", "Licensed under the MIT License."),
    ("MIT", "SPDX-License-Identifier: MIT"),
    ("BSD-2-Clause", "SPDX-License-Identifier: BSD-2-Clause"),
    ("BSD-3-Clause", "SPDX-License-Identifier: BSD-3-Clause"),
    ("GPL-3.0", "This work is licensed under the GNU General Public License, version 3."),
    ("GPL-3.0", "Licensed under the GNU General Public License, version 3."),
    ("GPL-3.0", "SPDX-License-Identifier: GPL-3.0-only"),
    ("CC-BY-NC-4.0", "Licensed under CC BY-NC 4.0."),
    ("CC-BY-NC-4.0", "This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International License."),
    ("CC-BY-4.0", "Licensed under CC BY 4.0."),
    ("CC-BY-4.0", "This work is licensed under a Creative Commons Attribution 4.0 International License."),
    ("CC-BY-SA-4.0", "Licensed under CC BY-SA 4.0."),
    ("CC0-1.0", "SPDX-License-Identifier: CC0-1.0"),
]

#: Spellings held to be the same, applied in this order to lower-case text; and what a copyright line begins with.
EQUIVALENT = [("licence", "license"), ("non-commercial", "noncommercial"), ("copyright owner", "copyright holder"), ("per cent", "percent"), ("acknowledgement", "acknowledgment"), ("merchantibility", "merchantability"), ("https://", "http://"), ("whilst", "while"), ("wilful", "willful")]
COPYRIGHT = r"(^|\n)[ \t]*(copyright|©|\(c\)|all rights reserved)[^\n]*"


def canonical(text: Column) -> Column:
    out = F.regexp_replace(F.lower(text), COPYRIGHT, "\n")
    for a, b in EQUIVALENT:
        out = F.replace(out, F.lit(a), F.lit(b))
    return F.trim(F.regexp_replace(out, r"[^\p{L}\p{N}]+", " "))


def digest(text: Column) -> Column:
    return F.sha2(canonical(text), 256)


def known(spark: SparkSession) -> DataFrame:
    """(licence, digest) of the known texts; of a fixed size."""
    rows = ", ".join(f"({_literal(a)}, {_literal(b)})" for a, b in KNOWN)
    return spark.sql(f"SELECT * FROM VALUES {rows} AS k(licence, text)").select("licence", digest(F.col("text")).alias("known_digest")).distinct()


def _literal(x: str) -> str:
    return "'" + x.replace("\\", "\\\\").replace("'", "\\'") + "'"


def scan(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """(key, digest, licence of the whole text or null, notices: the licences of single lines, sorted and comma-joined).

    Lines reach the join one by one and only those that are known leave it; matches are summed per row before they are dealt.
    """
    k, t = F.col(f"`{key}`"), F.col(f"`{text}`")
    rows = docs.select(k.alias("doc_id"), F.coalesce(t, F.lit("")).alias("whole"), F.xxhash64(k, t).alias("row"))
    spark = docs.sparkSession
    kept = F.filter(F.split("whole", "\n"), lambda x: x.rlike(r"\p{L}"))  # every known text has letters
    lines = rows.select("row", F.explode(kept).alias("line")).select("row", digest(F.col("line")).alias("known_digest"))
    found = lines.join(F.broadcast(known(spark)), "known_digest").groupBy("row").agg(F.concat_ws(",", F.array_sort(F.collect_set("licence"))).alias("notices"))
    out = rows.select("doc_id", "row", digest(F.col("whole")).alias("digest"))
    out = out.join(F.broadcast(known(spark)), F.col("digest") == F.col("known_digest"), "left").join(found, "row", "left")
    return out.select(F.col("doc_id").alias(key), "digest", "licence", F.coalesce("notices", F.lit("")).alias("notices"))


def op10_licences(spark, sf_dir: str) -> DataFrame:
    return scan(table(spark, sf_dir, "documents", "doc_id", "text"))


def _sql() -> str:
    def quoted(x: str) -> str:
        return "'" + x.replace("'", "''") + "'"

    def canon(x: str) -> str:
        out = rf"regexp_replace(lower({x}), '(^|\n)[ \t]*(copyright|©|\(c\)|all rights reserved)[^\n]*', chr(10), 'g')"
        for a, b in EQUIVALENT:
            out = f"replace({out}, {quoted(a)}, {quoted(b)})"
        return rf"trim(regexp_replace({out}, '[^\p{{L}}\p{{N}}]+', ' ', 'g'))"

    values = ", ".join(f"({quoted(a)}, {quoted(b)})" for a, b in KNOWN)
    return f"""
WITH k AS (SELECT DISTINCT licence, sha256({canon('t')}) AS dg FROM (VALUES {values}) v(licence, t)),
d AS (SELECT doc_id, coalesce(text, '') AS whole FROM documents),
l AS (SELECT doc_id, unnest(string_split(whole, chr(10))) AS line FROM d),
n AS (SELECT doc_id, string_agg(DISTINCT licence, ',' ORDER BY licence) AS notices FROM l JOIN k ON sha256({canon('line')}) = k.dg GROUP BY doc_id)
SELECT d.doc_id, sha256({canon('whole')}) AS digest, k.licence, coalesce(n.notices, '') AS notices
FROM d LEFT JOIN k ON sha256({canon('whole')}) = k.dg LEFT JOIN n ON n.doc_id = d.doc_id
"""


OP10_SQL = _sql()
