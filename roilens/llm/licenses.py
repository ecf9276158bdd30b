"""Licence scans by canonical digest lookup, in Spark expressions only.

A text is made canonical line by line: quotes and dashes to ASCII, A-Z to lower case, copyright lines
dropped, punctuation and white space to single spaces, equivalent spellings to one.  The digest of
the canonical lines joined by a space is looked up among digests of known licences by a hash join, so
re-wrapped, re-punctuated or re-dated copies of a licence have the digest of the licence.  Every line
is looked up among the same digests by a second hash join.  The registry is a table of (known, body),
made canonical by the same expressions; a built-in list serves where none is given.  It is broadcast
while it has at most ``FEW_KNOWN`` rows and joined by a shuffle beyond that.

A null or empty text has the digest of nothing and no licence.  Repeated rows are repeated in the result.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import written

# Spellings that licence matching guidelines hold to be equivalent (canonical one last).
EQUIVALENT = (
    ("licence", "license"), ("licenced", "licensed"), ("sub licence", "sublicense"), ("sub license", "sublicense"), ("acknowledgement", "acknowledgment"),
    ("organisation", "organization"), ("authorisation", "authorization"), ("favour", "favor"), ("fulfilment", "fulfillment"),
    ("judgement", "judgment"), ("labour", "labor"), ("modelled", "modeled"), ("non commercial", "noncommercial"), ("per cent", "percent"),
    ("whilst", "while"), ("wilful", "willful"), ("copyright holder", "copyright owner"), ("copyright holders", "copyright owners"),
)

# Whole texts of short public licences.
TEXTS = {
    "MIT": """Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the "Software"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions:
The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software.
THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE.""",
    "ISC": """Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies.
THE SOFTWARE IS PROVIDED "AS IS" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE.""",
    "0BSD": """Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted.
THE SOFTWARE IS PROVIDED "AS IS" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE.""",
    "Zlib": """This software is provided 'as-is', without any express or implied warranty. In no event will the authors be held liable for any damages arising from the use of this software.
Permission is granted to anyone to use this software for any purpose, including commercial applications, and to alter it and redistribute it freely, subject to the following restrictions:
1. The origin of this software must not be misrepresented; you must not claim that you wrote the original software. If you use this software in a product, an acknowledgment in the product documentation would be appreciated but is not required.
2. Altered source versions must be plainly marked as such, and must not be misrepresented as being the original software.
3. This notice may not be removed or altered from any source distribution.""",
}

_BSD_END = """THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS "AS IS" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE."""
_BSD = """Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met:
1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer.
2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution."""
TEXTS |= {
    "BSD-2-Clause": f"{_BSD}\n{_BSD_END}",
    "BSD-3-Clause": f"{_BSD}\n3. Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission.\n{_BSD_END}",
}

# One-line notices by which a work names its licence.
NOTICES = (
    ("Apache-2.0", "Licensed under the Apache License, Version 2.0."), ("Apache-2.0", "SPDX-License-Identifier: Apache-2.0"),
    ("MIT", "Released under the MIT License."), ("MIT", "Licensed under the MIT License."), ("MIT", "SPDX-License-Identifier: MIT"),
    ("GPL-3.0", "This work is licensed under the GNU General Public License, version 3."), ("GPL-3.0", "SPDX-License-Identifier: GPL-3.0-only"),
    ("CC-BY-NC-4.0", "Licensed under CC BY-NC 4.0."), ("CC-BY-4.0", "Licensed under CC BY 4.0."), ("CC-BY-SA-4.0", "Licensed under CC BY-SA 4.0."),
    ("CC0-1.0", "This work is released under CC0 1.0."), ("BSD-3-Clause", "SPDX-License-Identifier: BSD-3-Clause"), ("MPL-2.0", "SPDX-License-Identifier: MPL-2.0"),
)

_FANCY, _PLAIN = "‘’“”–— ", "''\"\"-- "
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
#: A run of anything but ASCII letters, digits and characters outside ASCII.
PUNCTUATION = r"[^a-z0-9\x{80}-\x{10FFFF}]+"
COPYRIGHT = r"^[ \t\r]*(copyright|\(c\)|\x{a9}|all rights reserved)"


def canonical_line(line: Column) -> Column:
    """One line made canonical; an empty string if it is a copyright line or has nothing to compare."""
    plain = F.translate(line, _FANCY + UPPER, _PLAIN + LOWER)
    # two spaces between words, so that neighbours can both be replaced
    c = F.concat(F.lit(" "), F.regexp_replace(plain, PUNCTUATION, "  "), F.lit(" "))
    for other, one in EQUIVALENT:
        c = F.replace(c, F.lit(f" {other.replace(' ', '  ')} "), F.lit(f" {one.replace(' ', '  ')} "))
    c = F.trim(F.regexp_replace(c, " +", " "))
    return F.when(F.regexp_like(plain, F.lit(COPYRIGHT)), F.lit("")).otherwise(c)


def canonical_lines(text: Column) -> Column:
    """The canonical lines of a text that are not empty."""
    return F.filter(F.transform(F.split(F.coalesce(text, F.lit("")), "\n"), canonical_line), lambda x: x != "")


FEW_KNOWN = 100_000  # rows of the registry that are broadcast, some tens of bytes each


def built_in(spark: SparkSession) -> DataFrame:
    """(known, body): the whole texts and notices listed above."""
    return spark.createDataFrame([*TEXTS.items(), *NOTICES], "known string, body string")


def registry(bodies: DataFrame) -> DataFrame:
    """(digest, known): canonical digests of bodies (known, body); one row a digest, that of nothing left out."""
    lines = bodies.select("known", canonical_lines(F.col("body")).alias("l")).where(F.size("l") > 0)
    return lines.groupBy(F.md5(F.array_join("l", " ")).alias("digest")).agg(F.min("known").alias("known"))


def scan(docs: DataFrame, bodies: DataFrame | None = None) -> DataFrame:
    """doc_id, text_digest, license (of the whole text), notices (of lines), n_notices for every row.

    ``notices`` lists distinct licences in order, joined by commas; both are null where nothing is known.
    ``bodies`` (known, body) is the registry to look up in.  Rows are told apart by their place in a
    written table of digests, so that only rows with a known line are grouped.
    """
    known = written(registry(built_in(docs.sparkSession) if bodies is None else bodies), "licences")
    known = F.broadcast(known) if known.count() <= FEW_KNOWN else known
    base = docs.select("doc_id", canonical_lines(F.col("text")).alias("_lines")).select(
        F.monotonically_increasing_id().alias("_row"), "doc_id", F.md5(F.array_join("_lines", " ")).alias("text_digest"), F.transform("_lines", lambda x: F.md5(x)).alias("_digests")
    )
    base = written(base, "digests")
    lines = base.where(F.size("_digests") > 0).select("_row", F.explode("_digests").alias("_line"))
    found = lines.join(known, F.col("_line") == F.col("digest")).groupBy(F.col("_row").alias("_of")).agg(F.array_join(F.array_sort(F.collect_set("known")), ",").alias("notices"), F.count("*").alias("n"))
    whole = base.select("_row", "doc_id", "text_digest").join(known, F.col("text_digest") == F.col("digest"), "left").withColumnRenamed("known", "license")
    out = whole.join(found, F.col("_row") == F.col("_of"), "left")
    return out.select("doc_id", "text_digest", "license", "notices", F.coalesce("n", F.lit(0).cast("long")).alias("n_notices"))
