"""Licence scan by canonical digest lookup, in DataFrame operations only.

A text is brought to a canonical form: A-Z lower, copyright lines and "all rights reserved" gone, equivalent spellings made
one, everything but letters and digits a single space. The SHA-256 of the whole canonical text is joined to the digests of
known licences; lines that are known licence notices are found in the same way, line by line.

Null texts count as empty and match nothing. Repeated rows give repeated rows; empty tables empty results.
"""

from __future__ import annotations

import re
from pathlib import Path

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import LOWER, UPPER

BROADCAST_ROWS = 100_000

#: Licence texts without their copyright lines, and one-line notices. The long texts are files.
LICENSES = {
    "MIT": """MIT License

Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the "Software"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions:

The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software.

THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE.""",
    "ISC": """ISC License

Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies.

THE SOFTWARE IS PROVIDED "AS IS" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS. IN NO EVENT SHALL THE AUTHOR BE LIABLE FOR ANY SPECIAL, DIRECT, INDIRECT, OR CONSEQUENTIAL DAMAGES OR ANY DAMAGES WHATSOEVER RESULTING FROM LOSS OF USE, DATA OR PROFITS, WHETHER IN AN ACTION OF CONTRACT, NEGLIGENCE OR OTHER TORTIOUS ACTION, ARISING OUT OF OR IN CONNECTION WITH THE USE OR PERFORMANCE OF THIS SOFTWARE.""",
    "BSD-2-Clause": """Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met:

1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer.

2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution.

THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS "AS IS" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED. IN NO EVENT SHALL THE COPYRIGHT HOLDER OR CONTRIBUTORS BE LIABLE FOR ANY DIRECT, INDIRECT, INCIDENTAL, SPECIAL, EXEMPLARY, OR CONSEQUENTIAL DAMAGES (INCLUDING, BUT NOT LIMITED TO, PROCUREMENT OF SUBSTITUTE GOODS OR SERVICES; LOSS OF USE, DATA, OR PROFITS; OR BUSINESS INTERRUPTION) HOWEVER CAUSED AND ON ANY THEORY OF LIABILITY, WHETHER IN CONTRACT, STRICT LIABILITY, OR TORT (INCLUDING NEGLIGENCE OR OTHERWISE) ARISING IN ANY WAY OUT OF THE USE OF THIS SOFTWARE, EVEN IF ADVISED OF THE POSSIBILITY OF SUCH DAMAGE.""",
    "Zlib": """This software is provided 'as-is', without any express or implied warranty. In no event will the authors be held liable for any damages arising from the use of this software.

Permission is granted to anyone to use this software for any purpose, including commercial applications, and to alter it and redistribute it freely, subject to the following restrictions:

1. The origin of this software must not be misrepresented; you must not claim that you wrote the original software. If you use this software in a product, an acknowledgment in the product documentation would be appreciated but is not required.
2. Altered source versions must be plainly marked as such, and must not be misrepresented as being the original software.
3. This notice may not be removed or altered from any source distribution.""",
    "Apache-2.0 notice": """Licensed under the Apache License, Version 2.0 (the "License"); you may not use this file except in compliance with the License. You may obtain a copy of the License at

http://www.apache.org/licenses/LICENSE-2.0

Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an "AS IS" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied. See the License for the specific language governing permissions and limitations under the License.""",
}


def _full_table() -> None:
    """Adds the texts of license_texts, and the forms in which a text goes about: with and without title, appendix or numbers."""
    for f in sorted((Path(__file__).parent / "license_texts").glob("*.txt")):
        LICENSES[f.stem] = f.read_text(encoding="utf-8")
        terms = re.split(r"(?m)^\s*(?:APPENDIX: |Appendix: )?How to apply (?:the Apache License|these terms) to your", LICENSES[f.stem], maxsplit=1, flags=re.I)
        if len(terms) > 1:
            LICENSES[f"{f.stem} terms"] = terms[0]
    two = LICENSES["BSD-2-Clause"]
    third = "3. Neither the name of the {} nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission.\n\nTHIS SOFTWARE"
    LICENSES["BSD-3-Clause"] = two.replace("THIS SOFTWARE", third.format("copyright holder"), 1)
    LICENSES["BSD-3-Clause university"] = LICENSES["BSD-3-Clause"].replace("of the copyright holder nor", "of the University nor").replace("THE COPYRIGHT HOLDERS AND", "THE REGENTS AND").replace("THE COPYRIGHT HOLDER OR", "THE REGENTS OR")
    for name, title in (("BSD-2-Clause", "BSD 2-Clause License"), ("BSD-3-Clause", "BSD 3-Clause License")):
        bulleted = re.sub(r"(?m)^\d\. ", "* ", LICENSES[name])
        LICENSES.update({f"{name} titled": f"{title}\n\n{LICENSES[name]}", f"{name} bulleted": bulleted, f"{name} titled, bulleted": f"{title}\n\n{bulleted}"})
    for name, title in (("MIT", "The MIT License (MIT)"), ("ISC", "The ISC License")):
        bare = LICENSES[name].partition("\n\n")[2]
        LICENSES.update({f"{name} untitled": bare, f"{name} titled": f"{title}\n\n{bare}"})


_full_table()
NOTICES = {
    "Licensed under the Apache License, Version 2.0.": "Apache-2.0",
    "Released under the MIT License.": "MIT",
    "Licensed under the MIT License.": "MIT",
    "Licensed under the BSD 3-Clause License.": "BSD-3-Clause",
    "Licensed under the BSD 2-Clause License.": "BSD-2-Clause",
    "This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License.": "GPL",
    "Licensed under the GNU General Public License v3.0.": "GPL-3.0",
    "Licensed under the GNU General Public License, Version 3.": "GPL-3.0",
    "Distributed under the terms of the GNU General Public License v2.": "GPL-2.0",
    "This work is licensed under a Creative Commons Attribution 4.0 International License.": "CC-BY-4.0",
    "Licensed under CC BY-SA 4.0.": "CC-BY-SA-4.0",
    "Licensed under the Mozilla Public License, Version 2.0.": "MPL-2.0",
    "SPDX-License-Identifier: Apache-2.0": "Apache-2.0",
    "SPDX-License-Identifier: MIT": "MIT",
}


def _full_notices() -> None:
    """Adds the usual sentences with every name of every licence and version."""
    names: dict[str, list[str]] = {
        "MIT": ["MIT License", "MIT"], "ISC": ["ISC License", "ISC"], "Zlib": ["zlib License", "zlib"], "Unlicense": ["Unlicense"], "BSL-1.0": ["Boost Software License 1.0", "Boost Software License, Version 1.0", "BSL-1.0"],
        "Apache-2.0": ["Apache License, Version 2.0", "Apache License 2.0", "Apache License v2.0", "Apache 2.0 License", "Apache-2.0"],
        "CC0-1.0": ["CC0 1.0", "CC0-1.0", "CC0 1.0 Universal", "Creative Commons CC0 1.0 Universal License"],
    }
    for n in (2, 3):
        names[f"BSD-{n}-Clause"] = [f"BSD {n}-Clause License", f"BSD {n}-Clause", f"{n}-Clause BSD License"]
    for v in ("1.1", "2.0"):
        names[f"MPL-{v}"] = [f"Mozilla Public License, Version {v}", f"Mozilla Public License {v}", f"Mozilla Public License v{v}", f"MPL {v}", f"MPL-{v}"]
    for short, title, versions in (("GPL", "GNU General Public License", ("1.0", "2.0", "3.0")), ("LGPL", "GNU Lesser General Public License", ("2.1", "3.0")), ("LGPL", "GNU Library General Public License", ("2.0",)), ("AGPL", "GNU Affero General Public License", ("3.0",))):
        for v in versions:
            for w in {v, v.removesuffix(".0")}:
                base = [f"{title}, version {w}", f"{title} version {w}", f"{title} v{w}", f"{title} {w}", f"{short} v{w}", f"{short}v{w}", f"{short}-{w}", f"GNU {short} v{w}"]
                names.setdefault(f"{short}-{v}", []).extend([*base, *[f"{b} only" for b in base]])
                names.setdefault(f"{short}-{v}-or-later", []).extend([*[f"{b} or later" for b in base], *[f"{b} or any later version" for b in base]])
    for kind, words in (("BY", "Attribution"), ("BY-SA", "Attribution-ShareAlike"), ("BY-NC", "Attribution-NonCommercial"), ("BY-ND", "Attribution-NoDerivatives"), ("BY-NC-SA", "Attribution-NonCommercial-ShareAlike"), ("BY-NC-ND", "Attribution-NonCommercial-NoDerivatives")):
        for v in ("1.0", "2.0", "2.5", "3.0", "4.0"):
            tail = {"4.0": "International", "3.0": "Unported"}.get(v, "Generic")
            names[f"CC-{kind}-{v}"] = [f"CC {kind} {v}", f"CC-{kind}-{v}", *[f"Creative Commons {words} {v}{e}" for e in ("", " License", f" {tail}", f" {tail} License", f" {tail} Public License")]]
    taken = {re.sub("[^a-z0-9]+", " ", k.lower()).strip() for k in NOTICES}
    for name, all_names in names.items():
        lines = [f"SPDX-License-Identifier: {name}"]
        for n in all_names:
            full = n if "licens" in n.lower() else f"{n} License"
            for way in ("Licensed under", "This work is licensed under", "This project is licensed under"):
                lines += [f"{way} {n}.", f"{way} the {n}.", *([f"{way} a {n}."] if n.startswith("Creative") else [])]
            for way in ("Released under", "Distributed under", "Distributed under the terms of"):
                lines += [f"{way} {full}.", f"{way} the {full}."]
            lines += [f"License: {n}", f"{full}."]
        for line in lines:
            form = re.sub("[^a-z0-9]+", " ", line.lower()).strip()
            if form not in taken:
                taken.add(form)
                NOTICES[line] = name


_full_notices()
#: Spellings that count as one, in canonical form after punctuation has gone.
EQUAL = [("licence", "license"), ("sub license", "sublicense"), ("non infringement", "noninfringement"), ("organisation", "organization"), ("acknowledgement", "acknowledgment"), ("per cent", "percent"), ("http", "https"), ("copyright owner", "copyright holder")]
#: Words of licence texts after "copyright", which don't begin a holder's name.
NO_HOLDER = ["act", "and", "disclaimer", "doctrine", "doctrines", "etc", "for", "holder", "holders", "if", "in", "interest", "interests", "is", "it", "law", "laws", "license", "licenses", "licence", "line", "notice", "notices", "of", "on", "or", "owner", "owners", "permission", "protection", "resulting", "right", "rights", "statement", "statements", "status", "that", "the", "treaty", "under"]


#: Words that begin the sentence after a copyright statement, where an initial or a short form ends it.
NEXT = ["all", "available", "distributed", "licensed", "permission", "redistribution", "released", "see", "spdx", "the", "this", "under", "use"]


def _other_word(words: list[str], begun: bool = False) -> str:
    """A pattern of the words of a-z that are none of these, without looking ahead (DuckDB can't)."""
    rest = {c: [w[1:] for w in words if w[:1] == c] for c in sorted({w[0] for w in words if w})}
    ways = [rf"[{''.join(c for c in LOWER if c not in rest)}][a-z]*"]
    ways += [rf"{c}(?:{_other_word(tails, True)})" for c, tails in rest.items()]
    return "|".join(ways + ([r"\b"] if begun and "" not in words else []))


def _copyright() -> str:
    """A mark at the start of a line, then a year or a holder, to the end of the statement or of the line.

    The foundation's statement is part of its licences and may be wrapped, so it may go over a line's end, as the reservation of all rights may."""
    year, gap = r"(?:19|20)[0-9]{2}\b", r"[\x20\t:,]*"
    the = rf"the[\x20\t]+(?:{_other_word(['document', 'library', 'program', 'software', 'work'])})"
    named = rf"(?:{year}|\b(?:{the}|{_other_word(['year', 'yyyy', *NO_HOLDER])})\b)"
    first = rf"copyright{gap}{year}|\(c\){gap}(?:copyright{gap})?{year}|(?:copyright{gap}(?:\(c\)|©){gap}|copyright[\x20\t:,]+|©{gap}(?:copyright{gap})?){named}"
    short = r"\b(?:[a-z]|inc|ltd|co|corp|jr|sr|dr|mr|mrs|st|bros|dept|univ|llc)\."
    inside = rf"(?:[^\n.]*(?:{short}[\x20\t]+(?:\b(?:{_other_word(NEXT)})\b|[^a-z\s.])|\.[^\s.])){{0,99}}"
    foundation = r"copyright\s+\(c\)\s+[0-9][0-9,\s]*free\s+software\s+foundation,\s+inc\.,?(?:\s+<https?://fsf\.org/>)?"
    return rf"(?m)^[^a-z0-9(©\n]*(?:{foundation}|(?:{first}){inside}[^\n.]*\.?)|\ball\s+rights\s+reserved\b"


COPYRIGHT = _copyright()


def canonical(text: Column) -> Column:
    t = F.translate(F.coalesce(text, F.lit("")), UPPER, LOWER)
    t = F.regexp_replace(F.regexp_replace(t, COPYRIGHT, " "), "all rights reserved", " ")
    t = F.regexp_replace(t, r"[^\p{L}\p{N}]+", " ")
    for a, b in EQUAL:
        t = F.regexp_replace(t, rf"\b{a}(s?)\b", f"{b}$1")
    return F.trim(t)


def known(spark: SparkSession, texts: dict[str, str]) -> DataFrame:
    """(digest, license) of texts; texts of one canonical form keep the first name."""
    df = spark.createDataFrame(sorted(texts.items()), "license string, text string")
    return df.select(F.sha2(canonical(F.col("text")), 256).alias("digest"), "license").groupBy("digest").agg(F.min("license").alias("license"))


def scan(docs: DataFrame, texts: dict[str, str] = LICENSES, notices: dict[str, str] = NOTICES) -> DataFrame:
    """docs with text_digest, license (of the whole text, or null), n_notices and notices (names in order, comma-joined)."""
    spark = docs.sparkSession
    whole = known(spark, texts)
    whole = F.broadcast(whole) if len(texts) <= BROADCAST_ROWS else whole
    lines = spark.createDataFrame(sorted(notices.items()), "text string, license string").select(canonical(F.col("text")).alias("t"), "license").collect()
    rows = sorted({r.t: r.license for r in lines}.items())
    # Two constants that the optimizer folds into one map; a literal for each notice is slow to plan.
    table = F.map_from_arrays(*[F.split(F.lit("\n".join(x)), "\n", -1) for x in zip(*rows, strict=True)]) if lines else F.create_map().cast("map<string,string>")
    text = F.coalesce(F.col("text"), F.lit(""))
    # Only lines with these letters can be notices, since every notice has them.
    maybe = F.filter(F.split(text, "\n"), lambda x: x.rlike("(?i)licen[sc]e|licensed|CC BY|SPDX"))
    found = F.filter(F.transform(maybe, lambda x: F.element_at(table, canonical(x))), lambda x: x.isNotNull())
    out = docs.withColumn("_notices", F.when(text.rlike("(?i)licen[sc]e"), found).otherwise(F.array().cast("array<string>")))
    out = out.withColumn("text_digest", F.sha2(canonical(F.col("text")), 256))
    joined = out.join(whole.withColumnRenamed("digest", "_digest"), F.col("text_digest") == F.col("_digest"), "left").drop("_digest")
    return joined.withColumn("n_notices", F.size("_notices").cast("long")).withColumn("notices", F.concat_ws(",", "_notices")).drop("_notices")
