"""Licences by digests of canonical texts. DataFrame and SQL operations only.

A text's canonical form is lower case, without copyright lines, in one spelling, each run of other characters than ASCII
letters and digits one space. Whole texts are hash-joined to the digests of known licences. Lines and paragraphs that
have an anchor word are hash-joined to the same table, so that notices inside a document are found too. The known table
comes from a rule (notices times names) and full texts: its size is a constant of this module. Longer licences come in as
a table of further texts, which may be of any size (see read_texts).
"""

from __future__ import annotations

import hashlib
import re

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Spellings that count as equal, the first to the second.
SPELLINGS = (
    ("licence", "license"), ("licenced", "licensed"), ("organisation", "organization"), ("favour", "favor"), ("honour", "honor"), ("authorised", "authorized"), ("recognised", "recognized"),
    ("whilst", "while"), ("programme", "program"), ("sub-license", "sublicense"), ("non-commercial", "noncommercial"), ("per cent", "percent"), ("http:", "https:"), ("(the \"license\")", ""),
)
#: Licence by identifier: names it goes by in notices.
NAMES = {
    "MIT": ("MIT License", "MIT"), "ISC": ("ISC License",), "Apache-2.0": ("Apache License, Version 2.0", "Apache License 2.0", "Apache-2.0"),
    "BSD-2-Clause": ("BSD 2-Clause License", "Simplified BSD License"), "BSD-3-Clause": ("BSD 3-Clause License", "New BSD License", "Modified BSD License"),
    "GPL-2.0": ("GNU General Public License, version 2", "GNU General Public License v2.0", "GPL-2.0", "GPLv2"), "GPL-3.0": ("GNU General Public License, version 3", "GNU General Public License v3.0", "GPL-3.0", "GPLv3"),
    "LGPL-2.1": ("GNU Lesser General Public License, version 2.1", "LGPL-2.1"), "LGPL-3.0": ("GNU Lesser General Public License, version 3", "LGPL-3.0"), "AGPL-3.0": ("GNU Affero General Public License, version 3", "AGPL-3.0"),
    "MPL-2.0": ("Mozilla Public License, version 2.0", "Mozilla Public License 2.0", "MPL-2.0"), "EPL-2.0": ("Eclipse Public License 2.0", "EPL-2.0"), "Unlicense": ("Unlicense",), "CC0-1.0": ("CC0 1.0", "CC0"),
    "CC-BY-4.0": ("CC BY 4.0", "Creative Commons Attribution 4.0 International License"), "CC-BY-SA-4.0": ("CC BY-SA 4.0", "Creative Commons Attribution-ShareAlike 4.0 International License"),
    "CC-BY-NC-4.0": ("CC BY-NC 4.0", "Creative Commons Attribution-NonCommercial 4.0 International License"), "CC-BY-ND-4.0": ("CC BY-ND 4.0", "Creative Commons Attribution-NoDerivatives 4.0 International License"),
    "CC-BY-NC-SA-4.0": ("CC BY-NC-SA 4.0", "Creative Commons Attribution-NonCommercial-ShareAlike 4.0 International License"),
}
NOTICES = (
    "{}", "Licensed under {}", "Licensed under the {}", "Released under {}", "Released under the {}", "This work is licensed under {}", "This work is licensed under the {}", "This work is licensed under a {}",
    "This project is licensed under the {}", "This software is licensed under the {}", "This file is licensed under the {}", "Distributed under the {}", "SPDX-License-Identifier: {}", "License: {}",
)
_GRANT = (
    "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions:",
    "The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software.",
    "THE SOFTWARE IS PROVIDED \"AS IS\", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE.",
)
_ISC = (
    "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies.",
    "THE SOFTWARE IS PROVIDED \"AS IS\" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE.",
)
_BSD = (
    "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met:",
    "{}Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer.",
    "{}Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution.",
)
_BSD_NAME = "{}Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission."
_BSD_END = "THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS \"AS IS\" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE."
_UNLICENSE = (
    "This is free and unencumbered software released into the public domain.",
    "Anyone is free to copy, modify, publish, use, compile, sell, or distribute this software, either in source code form or as a compiled binary, for any purpose, commercial or non-commercial, and by any means.",
    "In jurisdictions that recognize copyright laws, the author or authors of this software dedicate any and all copyright interest in the software to the public domain. We make this dedication for the benefit of the public at large and to the detriment of our heirs and successors. We intend this dedication to be an overt act of relinquishment in perpetuity of all present and future rights to this software under copyright law.",
    "THE SOFTWARE IS PROVIDED \"AS IS\", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE.",
    "For more information, please refer to <https://unlicense.org>",
)
_ZLIB = (
    "This software is provided 'as-is', without any express or implied warranty. In no event will the authors be held liable for any damages arising from the use of this software.",
    "Permission is granted to anyone to use this software for any purpose, including commercial applications, and to alter it and redistribute it freely, subject to the following restrictions:",
    "{}The origin of this software must not be misrepresented; you must not claim that you wrote the original software. If you use this software in a product, an acknowledgment in the product documentation would be appreciated but is not required.",
    "{}Altered source versions must be plainly marked as such, and must not be misrepresented as being the original software.",
    "{}This notice may not be removed or altered from any source distribution.",
)
_BOOST = (
    "Boost Software License - Version 1.0 - August 17th, 2003",
    "Permission is hereby granted, free of charge, to any person or organization obtaining a copy of the software and accompanying documentation covered by this license (the \"Software\") to use, reproduce, display, distribute, execute, and transmit the Software, and to prepare derivative works of the Software, and to permit third-parties to whom the Software is furnished to do so, all subject to the following:",
    "The copyright notices in the Software and this entire statement, including the above license grant, this restriction and the following disclaimer, must be included in all copies of the Software, in whole or in part, and all derivative works of the Software, unless such copies or derivative works are solely in the form of machine-executable object code generated by a source language processor.",
    "THE SOFTWARE IS PROVIDED \"AS IS\", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE, TITLE AND NON-INFRINGEMENT. IN NO EVENT SHALL THE COPYRIGHT HOLDERS OR ANYONE DISTRIBUTING THE SOFTWARE BE LIABLE FOR ANY DAMAGES OR OTHER LIABILITY, WHETHER IN CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE.",
)
_APACHE = (
    "Licensed under the Apache License, Version 2.0 (the \"License\"); you may not use this file except in compliance with the License. You may obtain a copy of the License at",
    "http://www.apache.org/licenses/LICENSE-2.0",
    "Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an \"AS IS\" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. See the License for the specific language governing permissions and limitations under the License.",
)


def _free_software(kind: str, thing: str, version: str) -> tuple[str, ...]:
    """The notice that GNU licences ask to put at the head of files."""
    return (
        f"This {thing} is free software: you can redistribute it and/or modify it under the terms of the GNU {kind} General Public License as published by the Free Software Foundation, either version {version} of the License, or (at your option) any later version.".replace("  ", " "),
        f"This {thing} is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE. See the GNU {kind} General Public License for more details.".replace("  ", " "),
        f"You should have received a copy of the GNU {kind} General Public License along with this {thing}. If not, see <https://www.gnu.org/licenses/>.".replace("  ", " "),
    )


_MPL = "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can obtain one at http://mozilla.org/MPL/2.0/."
_WTFPL = (
    "DO WHAT THE FUCK YOU WANT TO PUBLIC LICENSE", "Version 2, December 2004",
    "Everyone is permitted to copy and distribute verbatim or modified copies of this license document, and changing it is allowed as long as the name is changed.",
    "DO WHAT THE FUCK YOU WANT TO PUBLIC LICENSE TERMS AND CONDITIONS FOR COPYING, DISTRIBUTION AND MODIFICATION", "0. You just DO WHAT THE FUCK YOU WANT TO.",
)
#: Full texts and file heads: identifier and paragraphs. A paragraph that begins with braces has a number there, or a mark.
TEXTS = (
    ("MIT", ("MIT License", *_GRANT)), ("MIT", _GRANT), ("ISC", ("ISC License", *_ISC)), ("ISC", _ISC),
    ("BSD-2-Clause", (*_BSD, _BSD_END)), ("BSD-2-Clause", ("BSD 2-Clause License", *_BSD, _BSD_END)), ("BSD-3-Clause", (*_BSD, _BSD_NAME, _BSD_END)), ("BSD-3-Clause", ("BSD 3-Clause License", *_BSD, _BSD_NAME, _BSD_END)),
    ("0BSD", (_ISC[0].split(", provided")[0] + ".", _ISC[1])), ("0BSD", ("BSD Zero Clause License", _ISC[0].split(", provided")[0] + ".", _ISC[1])),
    ("MIT-0", (_GRANT[0].split(", subject")[0] + ".", _GRANT[2])), ("MIT-0", ("MIT No Attribution", _GRANT[0].split(", subject")[0] + ".", _GRANT[2])),
    ("Unlicense", _UNLICENSE), ("Zlib", _ZLIB), ("Zlib", ("zlib License", *_ZLIB)), ("BSL-1.0", _BOOST), ("WTFPL", _WTFPL), ("Apache-2.0", _APACHE), ("MPL-2.0", (_MPL,)),
    ("GPL-2.0", _free_software("", "program", "2")), ("GPL-3.0", _free_software("", "program", "3")), ("LGPL-2.1", _free_software("Lesser", "library", "2.1")), ("LGPL-3.0", _free_software("Lesser", "library", "3")), ("AGPL-3.0", _free_software("Affero", "program", "3")),
)
#: Every known text has one of these in its canonical form (checked below), so lines without any need no digest.
ANCHORS = ("licen", "mit", "apache", "gpl", "mpl", "epl", "cc", "software", "copies", "permission", "copyright", "source distribution", "you just do")
_COPYRIGHT = r"(?im)^[^\n\p{L}]*(?:copyright\b|\(c\)|©|all rights reserved)[^\n]*$"


def canonical_py(text: str) -> str:
    """The canonical form in Python, for the known table."""
    text = re.sub(r"(?im)^[^\na-z]*(?:copyright\b|\(c\)|©|all rights reserved)[^\n]*$", "", text).lower()
    for a, b in SPELLINGS:
        text = text.replace(a, b)
    return re.sub("[^a-z0-9]+", " ", text).strip()


def known() -> dict[str, str]:
    """Digest to licence identifier."""
    table = {n.format(name): key for key, names in NAMES.items() for name in names for n in NOTICES}
    table |= {f"{text} or later": key for text, key in list(table.items()) if key.startswith(("GPL", "LGPL", "AGPL"))}
    # A last paragraph that several texts share stands for the first of them.
    table |= {parts[-1].format(""): key for key, parts in reversed(TEXTS)}
    for first in (None, 0, 1):  # marks of the clauses: none that a canonical form has, or numbers from here
        for key, parts in TEXTS:
            at = [k for k, x in enumerate(parts) if x.startswith("{}")]
            table["\n\n".join(x.format(f"{at.index(k) + first}. " if k in at and first is not None else "") for k, x in enumerate(parts))] = key
    forms = {canonical_py(text): key for text, key in table.items()}
    assert all(any(a in form for a in ANCHORS) for form in forms)
    return {hashlib.sha256(form.encode()).hexdigest(): key for form, key in sorted(forms.items())}


def canonical(text: Column) -> Column:
    text = F.lower(F.regexp_replace(text, _COPYRIGHT, ""))
    for a, b in SPELLINGS:
        text = F.replace(text, F.lit(a), F.lit(b))
    return F.trim(F.regexp_replace(text, "[^a-z0-9]+", " "))


def read_texts(spark: SparkSession, folder: str, suffix: str = ".txt") -> DataFrame:
    """(license, text) of a folder of licence texts, one to a file that is named by the identifier."""
    name = F.regexp_replace(F.element_at(F.split(F.input_file_name(), "/"), -1), "\\Q" + suffix + "\\E$", "")
    return spark.read.option("wholetext", True).text(f"{folder}/*{suffix}").select(name.alias("license"), F.col("value").alias("text"))


def scan(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", more: DataFrame | None = None) -> DataFrame:
    """(doc_id, canonical_sha256, text_license, n_notices, notice_licenses), one row for each row of docs.

    text_license: the licence that the whole text is, empty if none. notice_licenses: those of lines and paragraphs, distinct,
    sorted, comma-joined; n_notices counts lines and paragraphs that match, one that is both only once. Null counts as empty;
    null and repeated ids keep a row each; other columns are not read. more: (license, text), further texts of which equal
    whole documents are found. No text is shuffled: what a text's parts matched comes back to it by the text's digest.
    """
    spark = docs.sparkSession
    known_ = spark.createDataFrame(list(known().items()), "digest string, license string")
    df = docs.select(F.col(id_col).alias("doc_id"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("text"))
    has = "(?i)" + "|".join(ANCHORS)
    parts = F.filter(F.array_union(F.split("text", "\n"), F.split("text", r"\n\s*\n")), lambda x: x.rlike(has))
    units = df.where(F.col("text").rlike(has)).select(F.sha2("text", 256).alias("__same"), F.posexplode(parts).alias("at", "unit"))
    met = units.select("__same", "at", F.sha2(canonical(F.col("unit")), 256).alias("digest")).join(F.broadcast(known_), "digest")
    # Copies give the same rows, which count once.
    notices = met.select("__same", "at", "license").distinct().groupBy("__same").agg(F.count("*").alias("n_notices"), F.array_join(F.array_sort(F.collect_set("license")), ",").alias("notice_licenses"))
    whole = F.broadcast(known_)
    if more is not None:
        texts = more.select(F.sha2(canonical(F.coalesce("text", F.lit(""))), 256).alias("digest"), "license").groupBy("digest").agg(F.min("license").alias("license"))
        whole = known_.unionByName(texts.join(F.broadcast(known_.select("digest")), "digest", "left_anti"))
    df = df.select("doc_id", F.sha2("text", 256).alias("__same"), F.sha2(canonical(F.col("text")), 256).alias("digest"))
    df = df.join(whole, "digest", "left").join(notices, "__same", "left")
    return df.select("doc_id", F.col("digest").alias("canonical_sha256"), F.coalesce("license", F.lit("")).alias("text_license"), F.coalesce("n_notices", F.lit(0)).cast("long").alias("n_notices"), F.coalesce("notice_licenses", F.lit("")).alias("notice_licenses"))


def oracle() -> str:
    """The same in DuckDB SQL."""
    quote = lambda x: "'" + x.replace("'", "''") + "'"
    values = ", ".join(f"({quote(d)}, {quote(k)})" for d, k in known().items())

    def form(x: str) -> str:
        x = f"lower(regexp_replace({x}, {quote(_COPYRIGHT)}, '', 'g'))"
        for a, b in SPELLINGS:
            x = f"replace({x}, {quote(a)}, {quote(b)})"
        return f"trim(regexp_replace({x}, '[^a-z0-9]+', ' ', 'g'))"

    return f"""
        WITH known(digest, license) AS (VALUES {values}),
        t AS (SELECT doc_id, coalesce(text, '') AS text FROM documents),
        u AS (SELECT DISTINCT doc_id, unnest(list_concat(string_split(text, chr(10)), regexp_split_to_array(text, '\\n\\s*\\n'))) AS unit FROM t),
        n AS (SELECT doc_id, license FROM u JOIN known ON digest = sha256({form('unit')})),
        g AS (SELECT doc_id, count(*) AS n, string_agg(DISTINCT license, ',' ORDER BY license) AS names FROM n GROUP BY doc_id),
        w AS (SELECT doc_id, sha256({form('text')}) AS digest FROM t)
        SELECT w.doc_id, w.digest AS canonical_sha256, coalesce(k.license, '') AS text_license, coalesce(g.n, 0) AS n_notices, coalesce(g.names, '') AS notice_licenses
        FROM w LEFT JOIN known k ON w.digest = k.digest LEFT JOIN g ON g.doc_id = w.doc_id
    """
