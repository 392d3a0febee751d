"""Licence scans by canonical digest.

A text is brought to a canonical form: lower case, copyright lines dropped,
equivalent spellings made one, punctuation and white space as single blanks.
A copyright line begins (after comment signs) with a copyright sign, or with the
word or ``(c)`` and then a sign or a year; lines of a licence's own sentences
that happen to begin with "copyright" stay, so it does not matter where a text
was wrapped. The digest of the whole form is hash-joined to the digests of known
licences. The same is done with every line, so notices inside a document are
found too.

The known texts are a parameter; they are few, and their number is checked
before they are broadcast (beyond ``MAX_BROADCAST`` the join shuffles) and
before lines look them up where they stand (beyond ``MAX_MAP`` lines are joined).
Long public licences are known by the digest of their canonical form alone
(``DIGESTS``). Null texts count as empty and match nothing, nor does a known text
with an empty form. Rows that repeat are each scanned. An empty table gives no
rows. Of known texts with equal forms the first id by code point stands for all.
Other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import materialize, table

MAX_BROADCAST, MAX_MAP = 10_000, 256

# Signs that stand for words, taken before punctuation goes.
SIGNS = (("https:", "http:"), ("&", " and "), ("(c)", " copyright "), ("©", " copyright "))
# Spellings that count as one, in the order in which they are applied to the words.
SPELLINGS = (
    ("licence", "license"), ("sub license", "sublicense"), ("non commercial", "noncommercial"), ("copyright owner", "copyright holder"),
    ("organisation", "organization"), ("favour", "favor"), ("merchantibility", "merchantability"), ("whilst", "while"), ("wilful", "willful"), ("per cent", "percent"),
)

# Public licence texts and notices that are looked up.
KNOWN = {
    "MIT": """Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the "Software"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions:
The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software.
THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE.""",
    "ISC": """Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies.
THE SOFTWARE IS PROVIDED "AS IS" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE.""",
    "Zlib": """This software is provided 'as-is', without any express or implied warranty. In no event will the authors be held liable for any damages arising from the use of this software.
Permission is granted to anyone to use this software for any purpose, including commercial applications, and to alter it and redistribute it freely, subject to the following restrictions:
1. The origin of this software must not be misrepresented; you must not claim that you wrote the original software. If you use this software in a product, an acknowledgment in the product documentation would be appreciated but is not required.
2. Altered source versions must be plainly marked as such, and must not be misrepresented as being the original software.
3. This notice may not be removed or altered from any source distribution.""",
    "BSD-2-Clause": """Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met:
1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer.
2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution.
THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS "AS IS" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE.""",
    "BSD-3-Clause": """Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met:
1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer.
2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution.
3. Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission.
THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS "AS IS" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE.""",
    "0BSD": """Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted.
THE SOFTWARE IS PROVIDED "AS IS" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE.""",
    "Unlicense": """This is free and unencumbered software released into the public domain.
Anyone is free to copy, modify, publish, use, compile, sell, or distribute this software, either in source code form or as a compiled binary, for any purpose, commercial or non-commercial, and by any means.
In jurisdictions that recognize copyright laws, the author or authors of this software dedicate any and all copyright interest in the software to the public domain. We make this dedication for the benefit of the public at large and to the detriment of our heirs and successors. We intend this dedication to be an overt act of relinquishment in perpetuity of all present and future rights to this software under copyright law.
THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE.
For more information, please refer to <https://unlicense.org/>""",
    "Apache-2.0-notice": "Licensed under the Apache License, Version 2.0.",
    "MIT-notice": "Released under the MIT License.",
    "GPL-3.0-notice": "This work is licensed under the GNU General Public License, version 3.",
    "CC-BY-NC-4.0-notice": "Licensed under CC BY-NC 4.0.",
    "CC-BY-4.0-notice": "Licensed under CC BY 4.0.",
    "CC-BY-SA-4.0-notice": "Licensed under CC BY-SA 4.0.",
    "CC0-notice": "To the extent possible under law, the author has waived all copyright and related or neighboring rights to this work.",
    "All-rights-reserved": "All rights reserved.",
}


# Digests of the canonical forms of public licences, whole texts as their stewards publish them.
DIGESTS = {
    "Apache-2.0": "47b515994eae3a3112a7dafacc3fc11e",
    "CC0-1.0": "93a180096f6cfcf2c0dd24f75c2eec48",
    "GPL-1.0": "8668a2b5848115b643ee3f44687e6dd6",
    "GPL-2.0": "858dd2a4fecaeaee081253f47806b102",
    "GPL-3.0": "329f814a00ccb52a305d4fd8c14dee3b",
    "LGPL-2.0": "74cf7fcef3b29a39165a795b2cad3a3a",
    "LGPL-2.1": "f998bc436710cfece156aaa84fd26dd4",
    "LGPL-3.0": "b31b7335bc37919e8cdd79154e04d88d",
    "MPL-1.1": "05ee2c349890fb85fe49a01458f65e8b",
    "MPL-2.0": "578f1ff1a6198e2c0c8a897a8ad8c2b9",
    "Artistic-1.0-Perl": "a8b0fb0c6e43a3b36bdc159e59dbfd1e",
    "GFDL-1.2": "7a0a547ecac612b526676be523eacf80",
    "GFDL-1.3": "7132e8380bc59358f27c3129a2136bf1",
}

COPYRIGHT_LINE = r"(?m)^[ \t/*#;%!-]*(?:©|copyright[ \t]*(?:\(c\)|©)|(?:copyright|\(c\))[ \t:,]*(?:\[yyyy\]|<year>|\{yyyy\}|[12][0-9]{3}))[^\n]*$"


def canonical(text: Column) -> Column:
    """The form whose digest is compared."""
    out = F.lower(F.coalesce(text, F.lit("")))
    out = F.regexp_replace(out, COPYRIGHT_LINE, " ")
    for a, b in SIGNS:
        out = F.replace(out, F.lit(a), F.lit(b))
    out = F.regexp_replace(out, r"[^\p{L}\p{N}]+", " ")
    for a, b in SPELLINGS:  # words only now, so it does not matter where a line ended
        out = F.replace(out, F.lit(a), F.lit(b))
    return F.trim(out)


def known_digests(spark: SparkSession, known: dict[str, str] | DataFrame, digests: dict[str, str] | None = None) -> DataFrame:
    """digest -> license_id of the known texts (a dict, or a DataFrame of license_id and text) and of further ``digests``."""
    rows = known if isinstance(known, DataFrame) else spark.createDataFrame(sorted(known.items()), "license_id string, text string")
    forms = rows.select("license_id", canonical(F.col("text")).alias("form")).filter("form <> '' and license_id is not null")
    forms = forms.select(F.md5("form").alias("digest"), "license_id")
    if digests:
        forms = forms.unionByName(spark.createDataFrame(sorted(digests.items()), "license_id string, digest string"))
    return forms.groupBy("digest").agg(F.min("license_id").alias("license_id"))


def scan_licenses(docs: DataFrame, known: dict[str, str] | DataFrame = KNOWN, further: dict[str, str] = DIGESTS) -> DataFrame:
    """Per document: doc_id, digest, license_id of the whole text (null if unknown), n_notices and notices (ids of its lines)."""
    spark = docs.sparkSession
    digests = known_digests(spark, known, further)
    if isinstance(known, dict):
        n = len(known) + len(further)
    else:
        digests = materialize(digests, "licenses")
        n = digests.limit(MAX_BROADCAST + 1).count()
    side = F.broadcast(digests) if n <= MAX_BROADCAST else digests
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce("text", F.lit("")).alias("text"))
    rows = rows.withColumn("digest", F.md5(canonical(F.col("text"))))
    whole = rows.join(side, "digest", "left")
    if n <= MAX_MAP:
        # few known digests: a literal map, so the lines of a text are looked up where they stand
        pairs = [(r["digest"], r["license_id"]) for r in digests.collect()]
        known_map = F.create_map(*[F.lit(v) for p in pairs for v in p]) if pairs else F.lit(None).cast("map<string,string>")
        ids = F.filter(F.transform(F.split("text", "\n", -1), lambda x: F.try_element_at(known_map, F.md5(canonical(x)))), lambda x: x.isNotNull())
        out = whole.withColumn("found", ids)
    else:
        lines = rows.select(F.xxhash64("text").alias("t1"), F.xxhash64(F.lit(5), "text").alias("t2"), F.posexplode(F.split("text", "\n", -1)).alias("pos", "line"))
        hits = lines.select("t1", "t2", "pos", F.md5(canonical(F.col("line"))).alias("digest")).join(side, "digest").distinct()
        found = hits.groupBy("t1", "t2").agg(F.collect_list("license_id").alias("found"))
        out = whole.withColumns({"t1": F.xxhash64("text"), "t2": F.xxhash64(F.lit(5), "text")}).join(found, ["t1", "t2"], "left")
        out = out.withColumn("found", F.coalesce("found", F.array().cast("array<string>")))
    return out.select("doc_id", "digest", "license_id", F.size("found").alias("n_notices"), F.array_join(F.array_sort(F.array_distinct("found")), ",").alias("notices"))


def op2_license_digests(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan_licenses(table(spark, sf_dir, "documents").select("doc_id", "text"))


def _canonical_sql(x: str) -> str:
    """The canonical form in DuckDB: line by line, by what a line begins with."""
    year = "'^[ \\t:,]*(\\[yyyy\\]|<year>|\\{yyyy\\}|[12][0-9]{3})'"
    head = "ltrim(line, ' \t/*#;%!-')"
    rest = f"ltrim(substr({head}, 10), ' \t')"
    named = f"(starts_with({head}, 'copyright') and (starts_with({rest}, '(c)') or starts_with({rest}, '©') or regexp_matches(substr({head}, 10), {year})))"
    signed = f"starts_with({head}, '©') or (starts_with({head}, '(c)') and regexp_matches(substr({head}, 4), {year}))"
    out = f"array_to_string(list_transform(string_split(lower({x}), chr(10)), lambda line: case when {named} or {signed} then ' ' else line end), chr(10))"
    for a, b in SIGNS:
        out = f"replace({out}, '{a}', '{b}')"
    out = f"regexp_replace({out}, '[^\\p{{L}}\\p{{N}}]+', ' ', 'g')"
    for a, b in SPELLINGS:
        out = f"replace({out}, '{a}', '{b}')"
    return f"trim({out})"


def _oracle() -> str:
    values = ", ".join("('{}', '{}')".format(k, v.replace("'", "''")) for k, v in sorted(KNOWN.items()))
    digests = ", ".join(f"('{k}', '{v}')" for k, v in sorted(DIGESTS.items()))
    return f"""
with known as (
  select digest, min(id) as license_id from (
    select md5({_canonical_sql('body')}) as digest, id from (values {values}) as k(id, body) union all select digest, id from (values {digests}) as d(id, digest)) group by 1),
whole as (select doc_id, coalesce(text, '') as text, md5({_canonical_sql("coalesce(text, '')")}) as digest from documents),
line as (select doc_id, md5({_canonical_sql('piece')}) as digest from (select doc_id, unnest(string_split(text, chr(10))) as piece from whole)),
hit as (select l.doc_id, count(*) as n, string_agg(distinct k.license_id, ',' order by k.license_id) as ids from line l join known k using (digest) group by 1)
select w.doc_id, w.digest, k.license_id, cast(coalesce(h.n, 0) as integer) as n_notices, coalesce(h.ids, '') as notices
from whole w left join known k using (digest) left join hit h using (doc_id)
"""


ORACLE = _oracle()
