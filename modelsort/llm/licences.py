"""Licence scan by canonical digest, in DataFrame functions only.

A text is brought to a canonical form: lower case, copyright lines gone,
punctuation and white space as single blanks, equivalent spellings of whole words
alike. The digest of the whole canonical text is then looked up among those of
known texts: whole licences (``licence_texts``) and short notices.
"""

from __future__ import annotations

from pathlib import Path

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Known texts up to this number are sent to every task; more are hash-joined by a shuffle.
BROADCAST_KNOWN = 10_000

# Patterns of the canonical form. The same pattern text serves Spark and DuckDB.
COPYRIGHT_LINE = r"(?m)^[ \t]*(?:[#*/;-]+[ \t]*)?(?:copyright[ \t:]*(?:\(c\)|©|<|\[|[0-9])[^\n]*|(?:\(c\)|©)[ \t]*[0-9<\[][^\n]*|all rights reserved\.?[ \t]*)$"
PUNCTUATION = r"[\x00-\x2f\x3a-\x60\x7b-\x7f“”‘’«»–—…©®™]+"
# Spellings of whole words that count as equal, as stems, the endings they are taken with, and what the stem becomes.
SPELLINGS = [
    ("(acknowledg|judg)ement", "s", "{1}ment"),
    ("(analog|catalog)ue", "s", "{1}"),
    ("(authori|capitali|categori|emphasi|initiali|maximi|organi|reali|recogni|utili)s", "e es ed er ers ing ation ations", "{1}z"),
    ("(analy)s", "e ed er ers ing", "{1}z"),
    ("(art)efact", "s", "{1}ifact"),
    ("(behavi|fav|hon|lab)our", "s ed able ing", "{1}or"),
    ("(calib|cent)re", "s", "{1}er"),
    ("(cancel|label|model)l", "ed ing", "{1}"),
    ("(fulfil)", "ment ments s", "{1}l"),
    ("(|sub)licence", "s d e es r rs", "{1}license"),
    ("(pract)ise", "s d", "{1}ice"),
    ("(program)me", "s", "{1}"),
    ("(non)  commercial", "", "{1}commercial"),
    ("(per)  cent", "", "{1}cent"),
    ("(sub)  licens", "e es ed ing or ee", "{1}licens"),
    ("(copyright)  owner", "s", "{1}  holder"),
    ("(while|whilst)", "", "while"),
    ("(http)s", "", "{1}"),
]
#: Stems whose bare form is no word of its own and needs one of the endings.
BOUND = {"(authori|capitali|categori|emphasi|initiali|maximi|organi|reali|recogni|utili)s", "(analy)s", "(cancel|label|model)l", "(sub)  licens"}
# How words that any of the spellings changes begin, so that most texts take one look.
WORDS_CHANGED = [
    *("acknowledgement analogue analys artefact authoris behaviour calibre cancelled cancelling capitalis catalogue categoris centre").split(),
    *("emphasis favour fulfil honour https initialis judgement labelled labelling labour licence maximis modelled modelling organis").split(),
    *("practise programme realis recognis sublicence utilis whilst").split(),
    *("copyright  owner", "non  commercial", "per  cent", "sub  licens"),
]

_WARRANTY = 'THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE.'
_MIT_GRANT = 'Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the "Software"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so'
_ISC_WARRANTY = 'THE SOFTWARE IS PROVIDED "AS IS" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE.'
_BSD_HEAD = "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: 1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer. 2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution."
_BSD_NAMES = " 3. Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission."
_BSD_WARRANTY = ' THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS "AS IS" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE.'
_APACHE_NOTICE = 'Licensed under the Apache License, Version 2.0 (the "License"); you may not use this file except in compliance with the License. You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0 Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an "AS IS" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. See the License for the specific language governing permissions and limitations under the License.'
_GPL_NOTICE = "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version. This program is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE. See the GNU General Public License for more details. You should have received a copy of the GNU General Public License along with this program. If not, see <https://www.gnu.org/licenses/>."
_ZLIB = "This software is provided 'as-is', without any express or implied warranty. In no event will the authors be held liable for any damages arising from the use of this software. Permission is granted to anyone to use this software for any purpose, including commercial applications, and to alter it and redistribute it freely, subject to the following restrictions: 1. The origin of this software must not be misrepresented; you must not claim that you wrote the original software. If you use this software in a product, an acknowledgment in the product documentation would be appreciated but is not required. 2. Altered source versions must be plainly marked as such, and must not be misrepresented as being the original software. 3. This notice may not be removed or altered from any source distribution."

#: Short texts and notices, by licence identifier.
KNOWN = [
    ("MIT", f"{_MIT_GRANT}, subject to the following conditions: The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software. {_WARRANTY}"),
    ("MIT", f"MIT License {_MIT_GRANT}, subject to the following conditions: The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software. {_WARRANTY}"),
    ("MIT", "Released under the MIT License."),
    ("MIT", "Licensed under the MIT License."),
    ("MIT", "SPDX-License-Identifier: MIT"),
    ("MIT-0", f"{_MIT_GRANT}. {_WARRANTY}"),
    ("ISC", f"Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies. {_ISC_WARRANTY}"),
    ("0BSD", f"Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted. {_ISC_WARRANTY}"),
    ("BSD-2-Clause", _BSD_HEAD + _BSD_WARRANTY),
    ("BSD-3-Clause", _BSD_HEAD + _BSD_NAMES + _BSD_WARRANTY),
    ("Zlib", _ZLIB),
    ("Apache-2.0", _APACHE_NOTICE),
    ("Apache-2.0", "Licensed under the Apache License, Version 2.0."),
    ("Apache-2.0", "SPDX-License-Identifier: Apache-2.0"),
    ("GPL-3.0-or-later", _GPL_NOTICE),
    ("GPL-3.0-only", "This work is licensed under the GNU General Public License, version 3."),
]


def spelling_patterns() -> list[tuple[str, str]]:
    """Patterns over words that stand between blanks of their own, and replacements with groups in braces."""
    out = []
    for stem, endings, new in SPELLINGS:
        some = "|".join([*endings.split(), *([] if stem in BOUND else [""])])
        out.append((f" {stem}({some}) ", f" {new}{{2}} "))
    return out


def _beginnings() -> str:
    """One pattern for all beginnings, told apart by their first letter."""
    by: dict[str, list[str]] = {}
    for word in WORDS_CHANGED:
        by.setdefault(word[0], []).append(word[1:])
    return " (?:" + "|".join(f"{c}(?:{'|'.join(rest)})" for c, rest in sorted(by.items())) + ")"


def canonical(text: Column) -> Column:
    """Canonical form of a whole text; a null is an empty text."""
    out = F.lower(F.coalesce(text.cast("string"), F.lit("")))
    out = F.regexp_replace(out, COPYRIGHT_LINE, " ")
    # Two blanks between words, so that each has one before and one behind it.
    out = F.concat(F.lit(" "), F.btrim(F.regexp_replace(out, PUNCTUATION, "  ")), F.lit(" "))
    spelt = out
    for pattern, new in spelling_patterns():
        spelt = F.regexp_replace(spelt, pattern, new.replace("{1}", "$1").replace("{2}", "$2"))
    return F.btrim(F.replace(F.when(out.rlike(_beginnings()), spelt).otherwise(out), F.lit("  "), F.lit(" ")))


def canonical_sql(text: str) -> str:
    """The same form as a DuckDB expression."""
    quote = lambda s: s.replace("'", "''")
    out = f"regexp_replace(lower(coalesce({text}, '')), '{quote(COPYRIGHT_LINE)}', ' ', 'g')"
    out = f"' ' || trim(regexp_replace({out}, '{quote(PUNCTUATION)}', '  ', 'g')) || ' '"
    for pattern, new in spelling_patterns():
        out = f"regexp_replace({out}, '{pattern}', '{new.replace('{1}', chr(92) + '1').replace('{2}', chr(92) + '2')}', 'g')"
    return f"trim(replace({out}, '  ', ' '))"


def known_texts() -> list[tuple[int, str, str]]:
    """Number, licence and text of all known texts: the short ones above and the whole licences beside this module."""
    files = sorted((Path(__file__).parent / "licence_texts").glob("*.txt"))
    found = [*KNOWN, *((f.stem, f.read_text("utf-8")) for f in files)]
    return [(i, name, text) for i, (name, text) in enumerate(found, 1)]


def known_table(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame(known_texts(), "n long, license_id string, text string")


def scan(docs: DataFrame, known: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Columns ``doc_id, canonical_chars, digest, license_id`` of each row of ``docs``.

    ``known`` has ``license_id, text``; rows with a null are left out, equal
    canonical texts under several ids give the least id. ``license_id`` is null
    where the text is no known one; texts that are empty in canonical form never
    are. Repeated rows each give a row, an empty table none.
    """
    form = F.col("__form")
    digests = known.where("license_id is not null and text is not null").select("license_id", canonical(F.col("text")).alias("__form")).where(form != "").groupBy(F.sha2(form, 256).alias("digest")).agg(F.min("license_id").alias("license_id"))
    if known.count() <= BROADCAST_KNOWN:
        digests = F.broadcast(digests)
    rows = docs.select(F.col(id_col).alias("doc_id"), canonical(F.col(text_col)).alias("__form")).select("doc_id", F.length("__form").cast("long").alias("canonical_chars"), F.sha2(form, 256).alias("digest"))
    return rows.join(digests, "digest", "left").select("doc_id", "canonical_chars", "digest", "license_id")
