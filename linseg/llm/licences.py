"""Licence scans by canonical digests.

A text's canonical form has no letter case, no punctuation, no copyright lines, and one spelling for equivalent ones.
The digest of an entire canonical text is hash-joined to the digests of known licence texts; each canonical line is
joined the same way to known one-line notices.  Both tables of known digests are fixed lists, so they are broadcast.

Defined results: a null text is empty, and no known text has the empty digest; repeated rows are reported each; an
empty table gives no rows; texts of any length are digested whole; where two known texts share a digest the lesser name
counts; columns other than id and text are not read, whatever their names.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Equivalent spellings, applied in order to lower-case text (fixed values).
SPELLINGS = (
    ("licenc", "licens"), ("organis", "organiz"), ("authoris", "authoriz"), ("recognis", "recogniz"), ("favour", "favor"), ("behaviour", "behavior"),
    ("fulfil ", "fulfill "), ("judgement", "judgment"), ("non-commercial", "noncommercial"), ("sub-licens", "sublicens"), ("merchantibility", "merchantability"),
    ("https://", "http://"), ("&", " and "),
)
#: Lines that name holders and years: they differ between copies of one licence.
COPYRIGHT_LINE = r"(?m)^[^a-z0-9\n]*(copyright|\(c\)|\x{A9}|all rights reserved)[^\n]*$"
_OTHER = r"[^a-z0-9\n\x{80}-\x{10FFFF}]+"
_BREAK = r" *\n[ \n]*"

_UPPER, _LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"

_AS_IS = (
    'THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE'
)
_BSD_END = (
    'THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS "AS IS" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF '
    "MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, "
    "SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) "
    "HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS "
    "SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE."
)
_BSD_START = (
    "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met:\n"
    "1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer.\n"
    "2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution.\n"
)
_GRANT = (
    'Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the "Software"), to deal in the Software without '
    "restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so"
)
_AUTHOR = (
    'THE SOFTWARE IS PROVIDED "AS IS" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE '
    "AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, "
    "NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE."
)
#: Entire licence texts (fixed values); a parameter of ``scan``.
LICENCES = {
    "MIT-0": "MIT No Attribution\n" + _GRANT + ".\n" + _AS_IS + " AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE.",
    "0BSD": "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted.\n" + _AUTHOR,
    "Zlib": "zlib License\nThis software is provided 'as-is', without any express or implied warranty. In no event will the authors be held liable for any damages arising from the use of this software.\nPermission is granted to anyone to use this software for any purpose, including commercial applications, and to alter it and redistribute it freely, subject to the following restrictions:\n1. The origin of this software must not be misrepresented; you must not claim that you wrote the original software. If you use this software in a product, an acknowledgment in the product documentation would be appreciated but is not required.\n2. Altered source versions must be plainly marked as such, and must not be misrepresented as being the original software.\n3. This notice may not be removed or altered from any source distribution.",
    "BSL-1.0": "Boost Software License - Version 1.0 - August 17th, 2003\nPermission is hereby granted, free of charge, to any person or organization obtaining a copy of the software and accompanying documentation covered by this license (the \"Software\") to use, reproduce, display, distribute, execute, and transmit the Software, and to prepare derivative works of the Software, and to permit third-parties to whom the Software is furnished to do so, all subject to the following:\nThe copyright notices in the Software and this entire statement, including the above license grant, this restriction and the following disclaimer, must be included in all copies of the Software, in whole or in part, and all derivative works of the Software, unless such copies or derivative works are solely in the form of machine-executable object code generated by a source language processor.\n"
    + _AS_IS + ", TITLE AND NON-INFRINGEMENT. IN NO EVENT SHALL THE COPYRIGHT HOLDERS OR ANYONE DISTRIBUTING THE SOFTWARE BE LIABLE FOR ANY DAMAGES OR OTHER LIABILITY, WHETHER IN CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE.",
    "Unlicense": "This is free and unencumbered software released into the public domain.\nAnyone is free to copy, modify, publish, use, compile, sell, or distribute this software, either in source code form or as a compiled binary, for any purpose, commercial or non-commercial, and by any means.\nIn jurisdictions that recognize copyright laws, the author or authors of this software dedicate any and all copyright interest in the software to the public domain. We make this dedication for the benefit of the public at large and to the detriment of our heirs and successors. We intend this dedication to be an overt act of relinquishment in perpetuity of all present and future rights to this software under copyright law.\n"
    + _AS_IS + " AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE.\nFor more information, please refer to <https://unlicense.org>",
    "MIT": "MIT License\nCopyright (c)\nPermission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions:\nThe above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software.\n"
    + _AS_IS + " AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE.",
    "ISC": "ISC License\nPermission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies.\nTHE SOFTWARE IS PROVIDED \"AS IS\" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE.",
    "BSD-2-Clause": _BSD_START + _BSD_END,
    "BSD-3-Clause": _BSD_START + "3. Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission.\n" + _BSD_END,
}
#: A licence is the same with or without its title line.
TITLED = ("MIT", "MIT-0", "ISC", "Zlib", "BSL-1.0")
#: One-line notices (fixed values), the licence that each names.
NOTICES = {
    "Released under the MIT License.": "MIT",
    "Licensed under the MIT License.": "MIT",
    "SPDX-License-Identifier: MIT": "MIT",
    "Licensed under the Apache License, Version 2.0.": "Apache-2.0",
    "SPDX-License-Identifier: Apache-2.0": "Apache-2.0",
    "This work is licensed under the GNU General Public License, version 3.": "GPL-3.0",
    "Licensed under the GNU General Public License v3.0.": "GPL-3.0",
    "SPDX-License-Identifier: GPL-3.0-only": "GPL-3.0",
    "Licensed under CC BY-NC 4.0.": "CC-BY-NC-4.0",
    "Licensed under CC BY 4.0.": "CC-BY-4.0",
    "Licensed under CC BY-SA 4.0.": "CC-BY-SA-4.0",
    "This is free and unencumbered software released into the public domain.": "Unlicense",
}


def canonical(text: Column) -> Column:
    """Canonical lines, one line feed between two."""
    out = F.translate(F.coalesce(text, F.lit("")), _UPPER, _LOWER)
    out = F.regexp_replace(out, COPYRIGHT_LINE, "")
    for a, b in SPELLINGS:
        out = F.replace(out, F.lit(a), F.lit(b))
    out = F.regexp_replace(F.regexp_replace(out, _OTHER, " "), _BREAK, "\n")
    return F.trim(F.regexp_replace(out, r"^[ \n]+|[ \n]+$", ""))


def digest(lines: Column) -> Column:
    """Of an entire canonical text, whatever its line breaks."""
    return F.sha2(F.replace(lines, F.lit("\n"), F.lit(" ")), 256)


def with_untitled(licences: dict[str, str]) -> dict[str, str]:
    """Names by text, titled ones without their title line as well."""
    return {t: n for n, text in licences.items() for t in ([text, text.split("\n", 1)[1]] if n in TITLED else [text])}


def known(spark, texts: dict[str, str]) -> DataFrame:
    """known_digest, name; one row for each digest, the first name where several share it."""
    rows = spark.createDataFrame([(t, n) for t, n in texts.items()], "t string, n string")
    return rows.select(digest(canonical(F.col("t"))).alias("known_digest"), "n").groupBy("known_digest").agg(F.min("n").alias("name")).where(F.col("known_digest") != F.sha2(F.lit(""), 256))


def scan(docs: DataFrame, licences: dict[str, str] | None = None, notices: dict[str, str] | None = None, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Per row: doc_id, text_digest, license (of the entire text, else null), n_notices (lines), notices (names, sorted, joined by commas)."""
    spark = docs.sparkSession
    whole = known(spark, with_untitled(LICENCES) if licences is None else {v: k for k, v in licences.items()})
    lines = known(spark, NOTICES if notices is None else notices)
    row = docs.select(F.monotonically_increasing_id().alias("__row"), F.col(f"`{id_col}`").cast("long").alias("doc_id"), canonical(F.col(f"`{text_col}`")).alias("c"))
    found = (
        row.select("__row", "doc_id", digest(F.col("c")).alias("text_digest"), F.explode(F.split("c", "\n")).alias("line"))
        .withColumn("line_digest", F.sha2("line", 256))
        .join(F.broadcast(lines), F.col("line_digest") == F.col("known_digest"), "left")
        .groupBy("__row", "doc_id", "text_digest")
        .agg(F.count("name").alias("n_notices"), F.array_join(F.array_sort(F.collect_set("name")), ",").alias("notices"))
    )
    return found.join(F.broadcast(whole), F.col("text_digest") == F.col("known_digest"), "left").select("doc_id", "text_digest", F.col("name").alias("license"), "n_notices", "notices")


def _sql_text(x: str) -> str:
    return "'" + x.replace("'", "''") + "'"


def _sql_canonical(x: str) -> str:
    out = f"regexp_replace(translate(coalesce({x}, ''), '{_UPPER}', '{_LOWER}'), '{COPYRIGHT_LINE}', '', 'g')"
    for a, b in SPELLINGS:
        out = f"replace({out}, '{a}', '{b}')"
    return f"trim(regexp_replace(regexp_replace(regexp_replace({out}, '{_OTHER}', ' ', 'g'), '{_BREAK}', chr(10), 'g'), '^[ \\n]+|[ \\n]+$', '', 'g'), ' ')"


def oracle() -> str:
    """DuckDB SQL for ``scan`` with its defaults."""
    table = lambda d: ", ".join(f"({_sql_text(t)}, {_sql_text(n)})" for t, n in d.items())
    tail = "sha256(replace({}, chr(10), ' '))"
    return f"""
with whole as (select {tail.format(_sql_canonical("t"))} d, min(n) n from (values {table(with_untitled(LICENCES))}) x(t, n) group by 1),
lines as (select {tail.format(_sql_canonical("t"))} d, min(n) n from (values {table(NOTICES)}) x(t, n) group by 1),
c as (select row_number() over () r, doc_id, {_sql_canonical("text")} c from documents),
l as (select r, doc_id, {tail.format("c")} text_digest, sha256(unnest(string_split(c, chr(10)))) d from c)
select doc_id, text_digest, min(w.n) license, count(lines.n) n_notices, coalesce(string_agg(distinct lines.n, ',' order by lines.n), '') notices
from l left join lines on lines.d = l.d left join whole w on w.d = l.text_digest group by r, doc_id, text_digest
"""
