"""License scans by canonical digests, in DataFrame functions only.

A text, each of its paragraphs and lines, and each run of two to MOST_RUN paragraphs that begins where a longer known text may begin, is brought to a canonical form: lower case, no copyright lines, no punctuation, one spelling of
words that licences spell in several ways. The SHA-256 of the whole form is joined with the digests of known licence texts and notices.
The terms of long licences are known by digest alone: wherever a text's canonical form has the words that such terms begin with, as many characters as they are long
are hashed, however the text is wrapped, titled or surrounded.
Only documents, then units, that hold one of the catalogue's anchors go that far; every known text has an anchor, so none is missed.

Null and empty texts match nothing; a unit of copyright lines alone has no digest. Rows that repeat a doc_id are counted together. doc_id null is a group
of its own. Empty tables give empty results. Extra columns are ignored.
"""

from __future__ import annotations

import hashlib
import re

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Spellings that mean the same in licences, the one on the right is kept.
SPELLINGS = {
    "acknowledgement": "acknowledgment", "analogue": "analog", "analyse": "analyze", "artefact": "artifact", "authorisation": "authorization", "authorised": "authorized",
    "calibre": "caliber", "cancelled": "canceled", "catalogue": "catalog", "categorise": "categorize", "centre": "center", "customisation": "customization",
    "emphasised": "emphasized", "favour": "favor", "favourite": "favorite", "fulfil": "fulfill", "fulfilment": "fulfillment", "initialise": "initialize",
    "judgement": "judgment", "labelling": "labeling", "labour": "labor", "licence": "license", "licences": "licenses", "licenced": "licensed", "maximise": "maximize",
    "modelled": "modeled", "modelling": "modeling", "offence": "offense", "optimise": "optimize", "organisation": "organization", "organise": "organize",
    "practise": "practice", "programme": "program", "realise": "realize", "recognise": "recognize", "signalling": "signaling", "sub license": "sublicense",
    "utilisation": "utilization", "whilst": "while", "wilful": "willful", "non commercial": "noncommercial", "https": "http", "per cent": "percent", "copyright owner": "copyright holder",
}

_WARRANTY = (
    'THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND '
    "NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, "
    "OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE."
)
_ISC_USE = "Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted"
_ISC_WARRANTY = (
    'THE SOFTWARE IS PROVIDED "AS IS" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE '
    "AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, "
    "NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE."
)
_MIT = (
    'Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the "Software"), to deal in the Software without '
    "restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the "
    "Software is furnished to do so, subject to the following conditions: The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software. " + _WARRANTY
)
_BSD_USE = "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: "
_BSD_ONE = "Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer. "
_BSD_TWO = (
    "Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with "
    "the distribution. "
)
_BSD_THREE = (
    "Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission. "
)
_BSD_WARRANTY = (
    'THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS "AS IS" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND '
    "FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL "
    "DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, "
    "WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE."
)
_ZLIB = (
    "This software is provided 'as-is', without any express or implied warranty. In no event will the authors be held liable for any damages arising from the use of this software. Permission is "
    "granted to anyone to use this software for any purpose, including commercial applications, and to alter it and redistribute it freely, subject to the following restrictions: 1. The origin of "
    "this software must not be misrepresented; you must not claim that you wrote the original software. If you use this software in a product, an acknowledgment in the product documentation would be "
    "appreciated but is not required. 2. Altered source versions must be plainly marked as such, and must not be misrepresented as being the original software. 3. This notice may not be removed or "
    "altered from any source distribution."
)
_UNLICENSE = (
    "This is free and unencumbered software released into the public domain. Anyone is free to copy, modify, publish, use, compile, sell, or distribute this software, either in source code form or as "
    "a compiled binary, for any purpose, commercial or non-commercial, and by any means. In jurisdictions that recognize copyright laws, the author or authors of this software dedicate any and all "
    "copyright interest in the software to the public domain. We make this dedication for the benefit of the public at large and to the detriment of our heirs and successors. We intend this dedication "
    "to be an overt act of relinquishment in perpetuity of all present and future rights to this software under copyright law. "
) + _WARRANTY.replace("AUTHORS OR COPYRIGHT HOLDERS", "AUTHORS") + " For more information, please refer to <https://unlicense.org/>"
_APACHE_NOTICE = (
    'Licensed under the Apache License, Version 2.0 (the "License"); you may not use this file except in compliance with the License. You may obtain a copy of the License at '
    "http://www.apache.org/licenses/LICENSE-2.0 Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an \"AS IS\" BASIS, WITHOUT "
    "WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. See the License for the specific language governing permissions and limitations under the License."
)


def _gpl_notice(name: str, version: int) -> str:
    return (
        f"This program is free software: you can redistribute it and/or modify it under the terms of the {name} as published by the Free Software Foundation, either version {version} of the License, or "
        "(at your option) any later version. This program is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS "
        f"FOR A PARTICULAR PURPOSE. See the {name} for more details. You should have received a copy of the {name} along with this program. If not, see <https://www.gnu.org/licenses/>."
    )


#: Known texts and notices by licence id.
KNOWN = [
    ("MIT", "Released under the MIT License."),
    ("MIT", "This project is licensed under the MIT License."),
    ("MIT", "Licensed under the MIT License."),
    ("MIT", "SPDX-License-Identifier: MIT"),
    *(("MIT", title + _MIT) for title in ("", "MIT License ", "The MIT License ", "The MIT License (MIT) ")),
    ("ISC", "SPDX-License-Identifier: ISC"),
    ("ISC", _ISC_USE + ", provided that the above copyright notice and this permission notice appear in all copies. " + _ISC_WARRANTY),
    ("0BSD", _ISC_USE + ". " + _ISC_WARRANTY),
    ("Apache-2.0", "Licensed under the Apache License, Version 2.0."),
    ("Apache-2.0", 'Licensed under the Apache License, Version 2.0 (the "License").'),
    ("Apache-2.0", "SPDX-License-Identifier: Apache-2.0"),
    ("Apache-2.0", _APACHE_NOTICE),
    ("GPL-2.0", _gpl_notice("GNU General Public License", 2)),
    ("GPL-3.0", _gpl_notice("GNU General Public License", 3)),
    ("LGPL-3.0", _gpl_notice("GNU Lesser General Public License", 3)),
    ("AGPL-3.0", _gpl_notice("GNU Affero General Public License", 3)),
    *(("BSD-2-Clause", title + _BSD_USE + one + _BSD_ONE + two + _BSD_TWO + _BSD_WARRANTY) for title in ("", "BSD 2-Clause License ") for one, two in (("1. ", "2. "), ("", ""))),
    *(("BSD-3-Clause", title + _BSD_USE + one + _BSD_ONE + two + _BSD_TWO + three + _BSD_THREE + _BSD_WARRANTY) for title in ("", "BSD 3-Clause License ") for one, two, three in (("1. ", "2. ", "3. "), ("", "", ""))),
    *(("Zlib", title + _ZLIB) for title in ("", "zlib License ", "The zlib License ")),
    ("Unlicense", _UNLICENSE),
    ("GPL-2.0", "This work is licensed under the GNU General Public License, version 2."),
    ("GPL-3.0", "This work is licensed under the GNU General Public License, version 3."),
    ("GPL-3.0", "SPDX-License-Identifier: GPL-3.0-only"),
    ("GPL-3.0", "SPDX-License-Identifier: GPL-3.0-or-later"),
    ("AGPL-3.0", "This work is licensed under the GNU Affero General Public License, version 3."),
    ("LGPL-3.0", "This work is licensed under the GNU Lesser General Public License, version 3."),
    ("MPL-2.0", "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0."),
    ("MPL-2.0", "SPDX-License-Identifier: MPL-2.0"),
    ("BSD-2-Clause", "SPDX-License-Identifier: BSD-2-Clause"),
    ("BSD-3-Clause", "SPDX-License-Identifier: BSD-3-Clause"),
    ("BSD-3-Clause", "Released under the BSD License."),
    ("CC-BY-4.0", "Licensed under CC BY 4.0."),
    ("CC-BY-SA-4.0", "Licensed under CC BY-SA 4.0."),
    ("CC-BY-NC-4.0", "Licensed under CC BY-NC 4.0."),
    ("CC-BY-4.0", "This work is licensed under a Creative Commons Attribution 4.0 International License."),
    ("CC-BY-SA-4.0", "This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License."),
    ("CC-BY-NC-4.0", "This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International License."),
    ("CC0-1.0", "SPDX-License-Identifier: CC0-1.0"),
    ("Unlicense", "This is free and unencumbered software released into the public domain under the Unlicense."),
]
#: Licences whose terms are too long to be listed. Id, the first words of the terms, length and SHA-256 of their canonical form, without title, address and appendix.
TERMS: list[tuple[str, str, int, str]] = [
    ("Apache-2.0", "apache license version 2 0 january 2004 http", 8810, "0b8c1a9e0ec99ab3b27e123e667fe4843df4dd7e6c667ccdc634dd6878c5dd6c"),
    ("GPL-1.0", "preamble the license agreements of most software companies", 9195, "018aaaf7231e8a3c8e8a0800c7e593914a330040252f5dc554e1817d1a27f2d4"),
    ("GPL-2.0", "preamble the licenses for most software are designed", 14263, "98e760555ff723908d803b23140ebd264fee15e7615bf9486faa0f8f6596c34f"),
    ("GPL-3.0", "preamble the gnu general public license is a", 30801, "fad6d14122ae5943ea05f9e4d48194524a0b701f034fd22c7dded3e6c296c742"),
    ("LGPL-2.0", "preamble the licenses for most software are designed", 21927, "d4689245f0c71022ce729821274153c787fdebe2e92f0de1f6d3c23326a5f619"),
    ("LGPL-2.1", "preamble the licenses for most software are designed", 22974, "73ac55304afe4c219acdd0cb7683daf4fe3772c9b493da4a095d93a7789311d5"),
    ("LGPL-3.0", "this version of the gnu lesser general public", 6930, "3c109b32fc12cedb18f514c338498353cbbafbc7ad3aa3aed8c864396943f25a"),
    ("MPL-1.1", "1 definitions 1 0 1 commercial use means", 20849, "8e0d6bce1c9edcccd142522e83c6de084a68b9500d79e6741b8903df3316c55a"),
    ("MPL-2.0", "1 definitions 1 1 contributor means each individual", 13556, "fa31bb5fe4dacb07f1a4ad162be58edb552e9a96a500b68e081943eb2d3cfec5"),
    ("CC0-1.0", "statement of purpose the laws of most jurisdictions", 6182, "4f8ab63ace774f37529081c81e2730a88143bf70e67392bd3c3701bd0a175152"),
    ("GFDL-1.2", "0 preamble the purpose of this license is", 18160, "da4c85448f47d22603d951c573ac545a667904a5f6eab0104964d422566c7ed2"),
    ("GFDL-1.3", "0 preamble the purpose of this license is", 20632, "1fdd53f1ef0ad288d6e9388b799ce36ae0484d524c9a2d2408a6f2f8e6dc5cef"),
]
#: Each known text holds one of these in lower case.
ANCHORS = ("licen", "permission", "redistribution")
#: Texts of several paragraphs begin with one that holds one of these in lower case.
BEGINNINGS = ("permission is hereby granted", "permission to use", "redistribution and use", "mit license", "bsd 2-clause", "bsd 3-clause", "zlib license", "provided 'as-is'", "unencumbered software", "apache license", "is free software")
MOST_RUN = 8

#: Lines that name a copyright; a line of a wrapped sentence that happens to begin with the word has a letter after it and no year.
_COPYRIGHT = r"(?m)^[ \t#/*;-]*(©|\(c\)|copyright[ \t]*([^a-z \t\n]|[^\n]*[0-9]{4}))[^\n]*$"
_BREAK = r"\n[ \t\r]*\n"


def canonical(unit: Column) -> Column:
    out = F.regexp_replace(F.lower(unit), F.lit(_COPYRIGHT), F.lit(""))
    out = F.trim(F.regexp_replace(out, F.lit("[^a-z0-9]+"), F.lit(" ")))
    for old, new in SPELLINGS.items():
        out = F.regexp_replace(out, F.lit(rf"\b{old}\b"), F.lit(new))
    return out


def canonical_text(unit: str) -> str:
    """The same for one text of the catalogue."""
    out = re.sub("[^a-z0-9]+", " ", re.sub(_COPYRIGHT, "", unit.lower())).strip()
    for old, new in SPELLINGS.items():
        out = re.sub(rf"\b{old}\b", new, out)
    return out


def digests(known: list[tuple[str, str]] | None = None) -> dict[str, str]:
    """Licence id by digest. Refuses a text without an anchor."""
    out = {}
    for name, text in known or KNOWN:
        if not any(x in canonical_text(text) for x in ANCHORS):
            raise ValueError(f"no anchor in {text[:60]!r}")
        out[hashlib.sha256(canonical_text(text).encode()).hexdigest()] = name
    return out


def terms_of(name: str, text: str, words: int = 8) -> tuple[str, str, int, str]:
    """The entry of TERMS for a licence's whole terms: id, first words, length and digest of the canonical form."""
    form = canonical_text(text)
    if not any(x in form for x in ANCHORS):
        raise ValueError(f"no anchor in {text[:60]!r}")
    return name, " ".join(form.split()[:words]), len(form), hashlib.sha256(form.encode()).hexdigest()


def _terms(own: DataFrame, terms: list[tuple[str, str, int, str]]) -> DataFrame:
    """doc_id, unit and digest of every stretch that begins with the first words of known terms and is as long, in whole words. Spellings shorten a text by less than half."""
    form = F.col("_form")
    long = own.where(F.length("_text") >= min(n for _, _, n, _ in terms) // 2).select("doc_id", F.concat(F.lit(" "), canonical(F.col("_text"))).alias("_form"))

    def stretches(head: str, n: int) -> Column:
        parts = F.split(form, f" {head}")
        at = F.filter(F.sequence(F.lit(0), F.size(parts) - 1), lambda i: i > 0)
        bodies = F.transform(at, lambda i: F.rtrim(F.substring(F.concat(F.lit(head), F.array_join(F.slice(parts, i + 1, F.size(parts)), f" {head}")), 1, n + 1)))
        return F.filter(bodies, lambda body: F.length(body) == n)

    pairs = sorted({(head, n) for _, head, n, _ in terms})
    bodies = F.concat(*(stretches(head, n) for head, n in pairs))
    return long.select("doc_id", F.explode(bodies).alias("body")).select("doc_id", F.lit("terms").alias("unit"), F.sha2("body", 256).alias("digest"))


def scan(docs: DataFrame, text: str = "text", known: list[tuple[str, str]] | None = None, terms: list[tuple[str, str, int, str]] | None = None) -> DataFrame:
    """doc_id, license_id, unit (text, paragraphs, paragraph, line or terms) and n, how many of the document's units are that licence's."""
    terms = TERMS if terms is None else terms
    entries = digests(known) | {d: name for name, _, _, d in terms}
    catalogue = docs.sparkSession.createDataFrame(list(entries.items()), "digest string, license_id string")
    anchored = lambda c: F.greatest(*(F.contains(F.lower(c), F.lit(x)) for x in ANCHORS))
    own = docs.select("doc_id", F.col(text).alias("_text")).where(anchored(F.col("_text")))
    several = lambda pattern, unit: F.transform(F.split("_text", pattern), lambda x: F.struct(F.lit(unit).alias("unit"), x.alias("body")))
    begins = lambda c: F.greatest(*(F.contains(F.lower(c), F.lit(x)) for x in BEGINNINGS))
    paragraphs = F.split("_text", _BREAK)
    heads = F.filter(F.sequence(F.lit(1), F.size(paragraphs)), lambda i: begins(F.element_at(paragraphs, i)))
    run = lambda i, k: F.struct(F.lit("paragraphs").alias("unit"), F.array_join(F.slice(paragraphs, i, k), "\n\n").alias("body"))
    fits = lambda i: F.filter(F.sequence(F.lit(2), F.lit(MOST_RUN)), lambda k: i + k - 1 <= F.size(paragraphs))
    runs = F.flatten(F.transform(heads, lambda i: F.transform(fits(i), lambda k: run(i, k))))
    units = F.concat(F.array(F.struct(F.lit("text").alias("unit"), F.col("_text").alias("body"))), runs, several(_BREAK, "paragraph"), several("\n", "line"))
    found = own.select("doc_id", F.explode(F.filter(units, lambda x: anchored(x["body"]))).alias("u")).select("doc_id", "u.unit", F.sha2(canonical(F.col("u.body")), 256).alias("digest"))
    if terms:
        found = found.union(_terms(own, terms))
    return found.join(F.broadcast(catalogue), "digest").groupBy("doc_id", "license_id", "unit").agg(F.count(F.lit(1)).alias("n"))


def oracle() -> str:
    """The same scan in DuckDB's SQL."""

    def folded(x: str) -> str:
        out = f"trim(regexp_replace(regexp_replace(lower({x}), '{_COPYRIGHT}', '', 'g'), '[^a-z0-9]+', ' ', 'g'))"
        for old, new in SPELLINGS.items():
            out = f"regexp_replace({out}, '\\b{old}\\b', '{new}', 'g')"
        return out

    known = ", ".join(f"('{d}', '{name}')" for d, name in (digests() | {d: name for name, _, _, d in TERMS}).items())
    shapes = ", ".join(f"('{head}', {n})" for head, n in sorted({(head, n) for _, head, n, _ in TERMS}))
    has = lambda x: "(" + " or ".join(f"contains(lower({x}), '{a}')" for a in ANCHORS) + ")"
    begins = lambda x: "(" + " or ".join(f"contains(lower({x}), '{a.replace(chr(39), chr(39) * 2)}')" for a in BEGINNINGS) + ")"
    return f"""
    with own as (select doc_id, text from documents where {has("text")}),
    cut as (select doc_id, string_split_regex(text, '{_BREAK}') as p from own),
    heads as (select doc_id, p, unnest(range(1, len(p) + 1)) as i from cut),
    runs as (select doc_id, p, i, unnest(range(2, {MOST_RUN + 1})) as k from heads where {begins("p[i]")}),
    units as (
      select doc_id, 'text' as unit, text as body from own
      union all select doc_id, 'paragraphs', array_to_string(p[i:i + k - 1], chr(10) || chr(10)) from runs where i + k - 1 <= len(p)
      union all select doc_id, 'paragraph', unnest(string_split_regex(text, '{_BREAK}')) from own
      union all select doc_id, 'line', unnest(string_split(text, chr(10))) from own
    ), forms as (select doc_id, ' ' || {folded("text")} as form from own),
    parts as (select doc_id, form, head, size, string_split(form, ' ' || head) as p from forms, (values {shapes}) as shape(head, size) where contains(form, ' ' || head)),
    cuts as (select *, unnest(range(1, len(p))) as i from parts),
    stretches as (select doc_id, size, rtrim(substr(form, 2 + cast(list_sum([length(x) for x in p[:i]]) as bigint) + (i - 1) * (length(head) + 1), size + 1)) as body from cuts),
    found as (
      select doc_id, unit, sha256({folded("body")}) as digest from units where {has("body")}
      union all select doc_id, 'terms', sha256(body) from stretches where length(body) = size
    ),
    known(digest, license_id) as (values {known})
    select doc_id, license_id, unit, count(*) as n from found join known using (digest) group by all
    """
