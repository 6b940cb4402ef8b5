"""Licence scan by canonical digests, in DataFrame functions alone.

A text is put into canonical form: lower case, copyright lines taken out,
everything but letters and digits made a blank, blanks run together, and
equivalent spellings made one. The form of an entire text, and that of each of
its lines, is hashed and joined with the digests of known licences: the
licence texts and the usual one-line notices, in the same form. The known
side is a fixed table of a few dozen rows, so it is broadcast.

Null and empty texts, and texts without letters or digits, match nothing.
Repeated rows are scanned one by one.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import shared

#: Spellings that count as one, from left to right.
SPELLINGS = (
    ("licence", "license"), ("sub licence", "sublicense"), ("sub license", "sublicense"), ("sub-license", "sublicense"),
    ("acknowledgement", "acknowledgment"), ("analogue", "analog"), ("authorisation", "authorization"), ("authorised", "authorized"), ("behaviour", "behavior"),
    ("calibre", "caliber"), ("centre", "center"), ("favour", "favor"), ("fulfil", "fulfill"), ("initialise", "initialize"), ("judgement", "judgment"),
    ("labelling", "labeling"), ("labour", "labor"), ("merchantibility", "merchantability"), ("modelled", "modeled"),
    ("non infringement", "noninfringement"), ("organisation", "organization"), ("organise", "organize"), ("practise", "practice"), ("programme", "program"),
    ("realise", "realize"), ("recognise", "recognize"), ("signalling", "signaling"), ("utilisation", "utilization"), ("whilst", "while"), ("wilful", "willful"),
    ("per cent", "percent"), ("copyright owner", "copyright holder"), ("https ", "http "), ("http www ", "http "),
)
#: Public licence texts.
TEXTS = {
    "MIT": """MIT License

Copyright (c) <year> <copyright holders>

Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the "Software"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions:

The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software.

THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE.""",
    "ISC": """ISC License

Copyright (c) <year> <copyright holders>

Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies.

THE SOFTWARE IS PROVIDED "AS IS" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE.""",
    "BSD-2-Clause": """Copyright (c) <year>, <copyright holders>

Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met:

1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer.

2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution.

THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS "AS IS" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE.""",
    "Zlib": """Copyright (c) <year> <copyright holders>

This software is provided 'as-is', without any express or implied warranty. In no event will the authors be held liable for any damages arising from the use of this software.

Permission is granted to anyone to use this software for any purpose, including commercial applications, and to alter it and redistribute it freely, subject to the following restrictions:

1. The origin of this software must not be misrepresented; you must not claim that you wrote the original software. If you use this software in a product, an acknowledgment in the product documentation would be appreciated but is not required.

2. Altered source versions must be plainly marked as such, and must not be misrepresented as being the original software.

3. This notice may not be removed or altered from any source distribution.""",
    "Unlicense": """This is free and unencumbered software released into the public domain.

Anyone is free to copy, modify, publish, use, compile, sell, or distribute this software, either in source code form or as a compiled binary, for any purpose, commercial or non-commercial, and by any means.

In jurisdictions that recognize copyright laws, the author or authors of this software dedicate any and all copyright interest in the software to the public domain. We make this dedication for the benefit of the public at large and to the detriment of our heirs and successors. We intend this dedication to be an overt act of relinquishment in perpetuity of all present and future rights to this software under copyright law.

THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE.

For more information, please refer to <https://unlicense.org>""",
    "BSD-3-Clause": """Copyright (c) <year>, <copyright holders>

Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met:

1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer.

2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution.

3. Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission.

THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS "AS IS" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE.""",
    "MIT-0": """MIT No Attribution

Copyright <year> <copyright holders>

Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the "Software"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so.

THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE.""",
    "0BSD": """Zero-Clause BSD

Copyright (c) <year> <copyright holders>

Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted.

THE SOFTWARE IS PROVIDED "AS IS" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE.""",
    "BSL-1.0": """Boost Software License - Version 1.0 - August 17th, 2003

Permission is hereby granted, free of charge, to any person or organization obtaining a copy of the software and accompanying documentation covered by this license (the "Software") to use, reproduce, display, distribute, execute, and transmit the Software, and to prepare derivative works of the Software, and to permit third-parties to whom the Software is furnished to do so, all subject to the following:

The copyright notices in the Software and this entire statement, including the above license grant, this restriction and the following disclaimer, must be included in all copies of the Software, in whole or in part, and all derivative works of the Software, unless such copies or derivative works are solely in the form of machine-executable object code generated by a source language processor.

THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE, TITLE AND NON-INFRINGEMENT. IN NO EVENT SHALL THE COPYRIGHT HOLDERS OR ANYONE DISTRIBUTING THE SOFTWARE BE LIABLE FOR ANY DAMAGES OR OTHER LIABILITY, WHETHER IN CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE.""",
    "Apache-2.0-header": """Copyright <year> <copyright holders>

Licensed under the Apache License, Version 2.0 (the "License"); you may not use this file except in compliance with the License. You may obtain a copy of the License at

http://www.apache.org/licenses/LICENSE-2.0

Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an "AS IS" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. See the License for the specific language governing permissions and limitations under the License.""",
    "GPL-3.0-or-later-header": """Copyright (C) <year> <copyright holders>

This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version.

This program is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE. See the GNU General Public License for more details.

You should have received a copy of the GNU General Public License along with this program. If not, see <https://www.gnu.org/licenses/>.""",
    "MPL-2.0-header": """This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can obtain one at https://mozilla.org/MPL/2.0/.""",
}
#: Titles under which texts stand, besides that of their first line.
TITLES = {"BSD-2-Clause": ("BSD 2-Clause License", 'The "Simplified BSD License"'), "BSD-3-Clause": ("BSD 3-Clause License", "The 3-Clause BSD License"), "MIT": ("The MIT License (MIT)", "The MIT License"), "Zlib": ("zlib License", "The zlib License"), "Unlicense": ("The Unlicense",), "0BSD": ("BSD Zero Clause License",)}
#: Names of licences for the one-line notices: (id, names).
NAMED = (
    ("MIT", ("MIT License",)), ("Apache-2.0", ("Apache License, Version 2.0", "Apache License 2.0")), ("GPL-3.0", ("GNU General Public License, version 3", "GNU General Public License v3.0", "GPL-3.0")),
    ("GPL-2.0", ("GNU General Public License, version 2", "GNU General Public License v2.0", "GPL-2.0")), ("LGPL-2.1", ("GNU Lesser General Public License, version 2.1",)), ("LGPL-3.0", ("GNU Lesser General Public License, version 3",)),
    ("AGPL-3.0", ("GNU Affero General Public License, version 3",)), ("MPL-2.0", ("Mozilla Public License, version 2.0", "Mozilla Public License 2.0")), ("BSD-2-Clause", ("BSD 2-Clause License",)), ("BSD-3-Clause", ("BSD 3-Clause License", "BSD License")),
    ("ISC", ("ISC License",)), ("Zlib", ("zlib License",)), ("Unlicense", ("Unlicense",)), ("EPL-2.0", ("Eclipse Public License, version 2.0",)), ("CC0-1.0", ("CC0 1.0", "Creative Commons Zero 1.0")),
    ("CC-BY-4.0", ("CC BY 4.0", "Creative Commons Attribution 4.0 International License")), ("CC-BY-SA-4.0", ("CC BY-SA 4.0", "Creative Commons Attribution-ShareAlike 4.0 International License")),
    ("CC-BY-NC-4.0", ("CC BY-NC 4.0", "Creative Commons Attribution-NonCommercial 4.0 International License")), ("CC-BY-ND-4.0", ("CC BY-ND 4.0",)), ("CC-BY-NC-SA-4.0", ("CC BY-NC-SA 4.0",)),
    ("all-rights-reserved", ()),
)
SENTENCES = ("{}", "Licensed under {}", "Licensed under the {}", "Released under the {}", "Released under {}", "This work is licensed under the {}", "This work is licensed under a {}", "This work is licensed under {}", "Distributed under the {}", "SPDX-License-Identifier: {}")
#: A line that starts, after marks, with a word for copyright.
COPYRIGHT = r"(^|\n)[^a-z0-9\n]*(?:copyright|\(c\)|©)[^\n]*"


def notices() -> list[tuple[str, str, str]]:
    """(id, kind, text) of everything known."""
    out = []
    for k, v in TEXTS.items():
        title, _, rest = v.partition("\n\n")
        bare = rest if rest and not title.endswith(".") and "copyright" not in title.lower() else v
        out += [(k, "text", x) for x in dict.fromkeys((v, bare, *(f"{t}\n\n{bare}" for t in TITLES.get(k, ()))))]
    for name, names in NAMED:
        out += [(name, "notice", s.format(x)) for s in SENTENCES for x in dict.fromkeys((*names, name))]
    return out + [("all-rights-reserved", "notice", "All rights reserved")]


def with_canonical(df: DataFrame, text: str, name: str) -> DataFrame:
    """df with the canonical form of a column under name (null for null) and the column gone.

    Each step is a column of its own, used in the next projection, so none is computed twice.
    """
    keep = [c for c in df.columns if c != text]
    low = df.select(*keep, F.lower(F.col(text)).alias("low"))
    lined = F.contains("low", F.lit("copyright")) | F.contains("low", F.lit("(c)")) | F.contains("low", F.lit("©"))
    clean = low.select(*keep, F.when(lined, F.regexp_replace("low", COPYRIGHT, "\n")).otherwise(F.col("low")).alias("low"))
    plain = clean.select(*keep, F.trim(F.regexp_replace("low", r"[^\p{L}\p{N}]+", " ")).alias("low"))
    spelt = F.col("low")
    for a, b in SPELLINGS:
        spelt = F.replace(spelt, F.lit(a), F.lit(b))
    return plain.select(*keep, spelt.alias(name))


def known(spark: SparkSession, texts: DataFrame | None = None) -> DataFrame:
    """(digest, licence) of all known texts and notices, and of the given texts (licence, text), each as it is and without a title in its first line."""
    rows = spark.createDataFrame(notices(), "licence string, kind string, text string").select("licence", "text")
    if texts is not None:
        # a first line that a blank line parts from the rest, and that says nothing of copyright and does not end in a full stop, is a title
        title = r"^\s*(?![^\n]*\.\s*\n)(?![^\n]*(?i:copyright|\(c\)|©))[^\n]+\r?\n\s*\n(?=[\s\S]*\S)"
        own = texts.where(F.col("text").isNotNull()).select("licence", "text")
        rows = rows.unionByName(own).unionByName(own.select("licence", F.regexp_replace("text", title, "").alias("text")))
    form = with_canonical(rows, "text", "form").where(F.length("form") > 0)
    return form.select(F.md5("form").alias("digest"), "licence").groupBy("digest").agg(F.min("licence").alias("licence"))


def scan(docs: DataFrame, text_col: str = "text", id_col: str = "doc_id", texts: DataFrame | None = None) -> DataFrame:
    """(id, text_digest, licence, notices): the digest of the entire text, the licence that it is, and the sorted licences of its lines that are notices.

    texts: further licence texts (licence, text), whose titles may be left out. Texts of docs are not shuffled: a row
    for each document and one for each line that is known are brought together.
    """
    rows, path = shared.put(known(docs.sparkSession, texts), "licences")
    own = docs.select(F.monotonically_increasing_id().alias("row"), F.col(f"`{id_col}`").alias("id"), F.coalesce(F.col(f"`{text_col}`"), F.lit("")).alias("t"))
    part = lambda whole, x: F.struct(F.lit(whole).alias("whole"), x.alias("s"))
    parts = own.select("row", "id", F.explode_outer(F.concat(F.array(part(True, F.col("t"))), F.transform(F.split("t", "\n"), lambda x: part(False, x)))).alias("p"))
    forms = with_canonical(parts.select("row", "id", F.col("p.whole").alias("whole"), F.col("p.s").alias("s")), "s", "form")
    # no filter on the form before the join: it would compute the form once more
    keyed = forms.select("row", "id", "whole", F.when(F.length("form") > 0, F.md5("form")).alias("digest"))
    hit = keyed.join(F.broadcast(rows.select("digest", "licence")), "digest", "left").where(F.col("whole") | F.col("licence").isNotNull())
    out = hit.groupBy("row").agg(
        F.max(F.when(F.col("whole"), F.struct("id", "digest", "licence"))).alias("own"),
        F.array_sort(F.collect_set(F.when(~F.col("whole"), F.col("licence")))).alias("n"),
    )
    return out.select(F.col("own.id").alias(id_col), F.col("own.digest").alias("text_digest"), F.col("own.licence").alias("licence"), F.array_join("n", ",").alias("notices"))


def op5(spark, sf_dir: str) -> DataFrame:
    """Per document: digest of its canonical text, the licence it is, and the licences its lines name."""
    return scan(shared.table(spark, sf_dir, "documents").select("doc_id", "text"))


def _sql_canonical(x: str) -> str:
    low = f"regexp_replace(lower({x}), '{COPYRIGHT}', chr(10), 'g')"
    form = f"trim(regexp_replace({low}, '[^\\p{{L}}\\p{{N}}]+', ' ', 'g'))"
    for a, b in SPELLINGS:
        form = f"replace({form}, '{a}', '{b}')"
    return form


def sql() -> str:
    """DuckDB SQL for op5."""
    values = ", ".join("('{}', '{}')".format(k, t.replace("'", "''")) for k, _, t in notices())
    return f"""
WITH raw(licence, text) AS (VALUES {values}),
k AS (SELECT md5({_sql_canonical("text")}) AS digest, min(licence) AS licence FROM raw GROUP BY 1),
d AS (SELECT row_number() OVER () AS r, doc_id, coalesce(text, '') AS t FROM documents),
w AS (SELECT r, doc_id, {_sql_canonical("t")} AS form FROM d),
l AS (SELECT r, {_sql_canonical("s")} AS form FROM (SELECT r, unnest(string_split(t, chr(10))) AS s FROM d)),
n AS (SELECT r, string_agg(DISTINCT licence, ',' ORDER BY licence) AS notices FROM l JOIN k ON l.form <> '' AND md5(l.form) = k.digest GROUP BY r)
SELECT w.doc_id, CASE WHEN w.form <> '' THEN md5(w.form) END AS text_digest, k.licence AS licence, coalesce(n.notices, '') AS notices
FROM w LEFT JOIN k ON w.form <> '' AND md5(w.form) = k.digest LEFT JOIN n ON n.r = w.r
"""
