"""Licence scans by canonical digest.

A text is normalised (case, copyright lines, punctuation, equivalent
spellings, title lines, white space) and its whole canonical form is hashed;
the digest is joined to the digests of known licence texts, some kept as texts
and the long ones as digests. The same is done for each line that can hold a
notice, so one-line notices inside a longer document are found as well. Only
built-in functions run; no Python sees a row.

Null and empty texts have the digest of the empty string and match nothing;
repeated rows give repeated results; texts of any length are hashed whole; of
known texts with one digest the first name counts; an empty table gives no
rows; an output replaces a column of its name.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from chargepath.llm.common import boxed, unboxed

# Public licence texts and notices, as published.
KNOWN = {
    "MIT": """Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the "Software"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions: The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software. THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE.""",
    "ISC": """Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies. THE SOFTWARE IS PROVIDED "AS IS" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE.""",
    "0BSD": """Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted. THE SOFTWARE IS PROVIDED "AS IS" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE.""",
    "BSD-2-Clause": """Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: 1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer. 2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution. THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS "AS IS" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE.""",
    "Apache-2.0": """Licensed under the Apache License, Version 2.0 (the "License"); you may not use this file except in compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0 Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an "AS IS" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. See the License for the specific language governing permissions and limitations under the License.""",
    "BSD-3-Clause": """Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: 1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer. 2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution. 3. Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission. THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS "AS IS" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE.""",
    "Zlib": """This software is provided 'as-is', without any express or implied warranty. In no event will the authors be held liable for any damages arising from the use of this software. Permission is granted to anyone to use this software for any purpose, including commercial applications, and to alter it and redistribute it freely, subject to the following restrictions: 1. The origin of this software must not be misrepresented; you must not claim that you wrote the original software. If you use this software in a product, an acknowledgment in the product documentation would be appreciated but is not required. 2. Altered source versions must be plainly marked as such, and must not be misrepresented as being the original software. 3. This notice may not be removed or altered from any source distribution.""",
    "Unlicense": """This is free and unencumbered software released into the public domain. Anyone is free to copy, modify, publish, use, compile, sell, or distribute this software, either in source code form or as a compiled binary, for any purpose, commercial or non-commercial, and by any means. In jurisdictions that recognize copyright laws, the author or authors of this software dedicate any and all copyright interest in the software to the public domain. We make this dedication for the benefit of the public at large and to the detriment of our heirs and successors. We intend this dedication to be an overt act of relinquishment in perpetuity of all present and future rights to this software under copyright law. THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE. For more information, please refer to <https://unlicense.org>""",
    "MPL-2.0 header": """This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can obtain one at https://mozilla.org/MPL/2.0/.""",
    "notice:MIT": "Released under the MIT License.",
    "notice:Apache-2.0": "Licensed under the Apache License, Version 2.0.",
    "notice:CC-BY-NC-4.0": "Licensed under CC BY-NC 4.0.",
    "notice:CC-BY-4.0": "Licensed under CC BY 4.0.",
    "notice:GPL-3.0": "This work is licensed under the GNU General Public License, version 3.",
    "notice:GPL-2.0": "This work is licensed under the GNU General Public License, version 2.",
}
# SPDX names whose one-line identifiers are notices as well.
SPDX = ("0BSD", "AGPL-3.0-only", "AGPL-3.0-or-later", "Apache-2.0", "BSD-2-Clause", "BSD-3-Clause", "BSL-1.0", "CC-BY-4.0", "CC-BY-SA-4.0", "CC0-1.0", "EPL-2.0", "GPL-2.0-only", "GPL-2.0-or-later", "GPL-3.0-only", "GPL-3.0-or-later", "ISC", "LGPL-2.1-only", "LGPL-2.1-or-later", "LGPL-3.0-only", "LGPL-3.0-or-later", "MIT", "MPL-2.0", "Unlicense", "Zlib")
KNOWN |= {f"notice:SPDX:{name}": f"SPDX-License-Identifier: {name}" for name in SPDX}
# Digests of the canonical forms of long public texts, as the Debian package base-files has them.
DIGESTS: dict[str, str] = {
    "Apache-2.0": "93651fc3b3c9c21033cf07999bdb593e0138192678d4743ddf7ee126fefab052",
    "Artistic-1.0-Perl": "bc4d0c00d493021b9f3b1041689fa28b4bf980cf2e37601f7cb475a7265e3b93",
    "CC0-1.0": "cccf7894e1b9f4ba9f97728bf0c5baf9e07bc2ac93da7a51556451b1fb2b868e",
    "GFDL-1.2": "bd8e32052e49e6b79fccbdd5dc03f7d40e45a8e895e3ecb79394b97961ffb127",
    "GFDL-1.3": "e7579a53c7b8214f091590d94bfe39deb978a080895ca5506448b8baf4f77985",
    "GPL-1.0": "37f380f152339f34a15db620545eb53f0b5c7d9e6a9542aa09ed0d22f186920f",
    "GPL-2.0": "ae2be2aaa68f5e52ef402874fc8c7c691879b445cb12e49d84f88168cc2d7dd6",
    "GPL-3.0": "42de4913c0ec220db6e274a84efcdc7a52715762d22943334032232048072bc1",
    "LGPL-2.0": "bea988245c65edbddad6f43ff12ca2472c232324e916d42648b90eac944d833e",
    "LGPL-2.1": "ed875dac9045cba09a17867210991f3a4a82f80b82096b054560a3a8dae9d692",
    "LGPL-3.0": "aae2b222477171fb64e298e7965e768a9a6f85320646b266c94399ac029d42be",
    "MPL-1.1": "1cfb6cca26abe2169c9c61164807107b2d4a0b64955a2cf2de46fad3483acda1",
    "MPL-2.0": "95f6a0d094cf3da6a140310541c7b576789031b600469b70877b34f97918e4c9",
}
# Title lines that stand above a licence's own words.
TITLES = ("MIT License", "The MIT License", "The MIT License (MIT)", "MIT License (MIT)", "ISC License", "The ISC License", "BSD Zero Clause License", "Zero-Clause BSD", "BSD 2-Clause License", "The 2-Clause BSD License", "Simplified BSD License", "BSD 3-Clause License", "The 3-Clause BSD License", "New BSD License", "Modified BSD License", "zlib License", "The zlib License", "The Unlicense", "Unlicense")
# Spellings taken as equal, British form first.
SPELLINGS = [("licence", "license"), ("licenced", "licensed"), ("sub  license", "sublicense"), ("non  commercial", "noncommercial"), ("non  infringement", "noninfringement"), ("merchantibility", "merchantability"), ("organisation", "organization"), ("authorised", "authorized"), ("copyright  holder", "copyright  owner")]


def _title_pattern() -> str:
    """Lines that are a title and nothing else, in lower case."""
    gap = "[^a-z0-9\\n]+"
    names = [gap.join("".join(c if c.isalnum() else " " for c in t.lower()).split()).replace("license", "licen[sc]e") for t in TITLES]
    return f"(?m)^[^a-z0-9\\n]*({'|'.join(sorted(names, key=len, reverse=True))})[^a-z0-9\\n]*$"


#: (pattern, replacement) in order, read alike by Java's regex and RE2. Words get two spaces between them, so that each has its own.
STEPS = [
    ("(?m)^[^a-z0-9\\n]*(copyright|\\(c\\)|©)[^\\n]*(19|20)[0-9][0-9][^\\n]*$", " "),
    ("(?m)^[^a-z0-9\\n]*(copyright[ \\t]*(\\(c\\)|©)|\\(c\\)[ \\t]|©)[^\\n]*$", " "),
    ("(?m)^[^a-z0-9\\n]*all rights reserved[^a-z0-9\\n]*$", " "),
    (_title_pattern(), " "),
    ("[^\\p{L}\\p{N}]+", "  "),
    *((f" {a}(s?) ", f" {b}$1 ") for a, b in SPELLINGS),
    (" +", " "),
]
#: Every line that can be known holds one of these in lower case.
HINT = "licen|permission|redistribut"


def canonical(text):
    """The canonical form of a text column."""
    out = F.lower(F.coalesce(text, F.lit("")))
    for pattern, by in STEPS:
        out = F.regexp_replace(out, pattern, by)
        if by == "  ":
            out = F.concat(F.lit(" "), out, F.lit(" "))
    return F.trim(out)


def known_digests(spark: SparkSession, known: dict[str, str] = KNOWN, digests: dict[str, str] = DIGESTS) -> DataFrame:
    """digest, license; one row for each known text (lists in this file)."""
    rows = spark.createDataFrame(sorted(known.items()), "license string, body string")
    made = rows.select(F.sha2(canonical(F.col("body")), 256).alias("digest"), "license")
    if digests:
        made = made.unionByName(spark.createDataFrame(sorted((v, k) for k, v in digests.items()), "digest string, license string"))
    return made.groupBy("digest").agg(F.min("license").alias("license"))


def digest_of(texts: DataFrame) -> DataFrame:
    """texts(license, body) -> license, digest: how a list of one's own is made."""
    return texts.select("license", F.sha2(canonical(F.col("body")), 256).alias("digest"))


def scan(docs: DataFrame, known: dict[str, str] = KNOWN, digests: dict[str, str] = DIGESTS) -> DataFrame:
    """docs -> docs + digest, license (whole text; else null), notices (sorted ids of lines)."""
    facts = known_digests(docs.sparkSession, known, digests)
    # The known list is a constant of a few rows, so it rides along as a map.
    lookup = F.create_map(*[F.lit(v) for r in facts.orderBy("digest").collect() for v in (r.digest, r.license)])
    text = F.coalesce(F.col("text"), F.lit(""))
    some = F.filter(F.array_distinct(F.split(text, "\n")), lambda x: F.lower(x).rlike(HINT))
    names = F.transform(some, lambda x: lookup[F.sha2(canonical(x), 256)])
    rows = boxed(docs, digest=F.sha2(canonical(F.col("text")), 256), notices=F.array_distinct(F.filter(names, lambda x: x.isNotNull())))
    rows = rows.join(F.broadcast(facts.select(F.col("digest").alias("known"), "license")), F.col("digest") == F.col("known"), "left")
    return unboxed(rows, digest=F.col("digest"), license=F.col("license"), notices=F.array_join(F.array_sort("notices"), ","))


def _sql_canonical(e: str) -> str:
    out = f"lower(coalesce({e}, ''))"
    for pattern, by in STEPS:
        quoted, put = pattern.replace("'", "''"), by.replace("$1", "\\1")
        out = f"regexp_replace({out}, '{quoted}', '{put}', 'g')"
        if by == "  ":
            out = f"(' ' || {out} || ' ')"
    return f"trim({out}, ' ')"


def scan_sql(known: dict[str, str] = KNOWN, digests: dict[str, str] = DIGESTS) -> str:
    rows = ", ".join("('{}', '{}')".format(k, v.replace("'", "''")) for k, v in sorted(known.items()))
    held = "".join(f" UNION ALL SELECT '{v}', '{k}'" for k, v in sorted(digests.items()))
    return f"""
WITH k AS (SELECT digest, min(license) AS license FROM (SELECT sha256({_sql_canonical('body')}) AS digest, license FROM (VALUES {rows}) v(license, body){held}) GROUP BY 1),
d AS (SELECT row_number() OVER () AS r, doc_id, text, sha256({_sql_canonical('text')}) AS digest FROM documents),
l AS (SELECT DISTINCT r, sha256({_sql_canonical('line')}) AS digest FROM (SELECT r, unnest(string_split(coalesce(text, ''), chr(10))) AS line FROM d) WHERE regexp_matches(lower(line), '{HINT}')),
n AS (SELECT r, string_agg(DISTINCT license, ',' ORDER BY license) AS notices FROM l JOIN k USING (digest) GROUP BY r)
SELECT d.doc_id, d.digest, k.license, coalesce(n.notices, '') AS notices
FROM d LEFT JOIN k USING (digest) LEFT JOIN n USING (r)"""
