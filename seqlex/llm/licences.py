"""Licence scans by sentence rules: known licence sentences, then ordered rules over their identifiers. DataFrame functions only.

In a text A-Z become lower case, and runs of anything but a-z, 0-9 and line breaks become one space; so wrapping, titles, list and comment markers and
neighbours don't matter. The known sentences are looked for as spans of whole words in it, from left to right, the longest where several begin. A `<name>` in a
sentence stands for one to twelve words. A notice ("licensed under the ...") is a verb phrase and the name of a licence, both known; "or later" after it belongs to it, and a "not" before
a sentence makes it unknown. A tag line must be a line of its own. The identifiers found, in the order of the text,
are matched against rules, each an ordered list of identifiers with anything between them; a rule that a longer matched rule shadows adds nothing, and
licences are reported once. There is no shuffle and no join: rules and sentences are constants of the plan.

Defined results: a null or empty text has no sentence and no licence. A sentence that repeats is listed each time. Very long texts are read
whole. Repeated rows are scanned alike; only `doc_id` and `text` are read.
"""

from __future__ import annotations

import re
import string

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

# Sentences of public licence texts, and their identifiers.
SENTENCES = {
    "apache2_title": ["Apache License Version 2.0, January 2004"],
    "apache2_terms": ["TERMS AND CONDITIONS FOR USE, REPRODUCTION, AND DISTRIBUTION"],
    "apache2_comply": ["you may not use this file except in compliance with the License", "you may not use this work except in compliance with the License"],
    "apache2_copy": ["You may obtain a copy of the License at http://www.apache.org/licenses/LICENSE-2.0", "You may obtain a copy of the License at https://www.apache.org/licenses/LICENSE-2.0"],
    "apache2_as_is": ['Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an "AS IS" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied'],
    "mit_grant": ['Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the "Software"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so'],
    "mit_include": ["The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software", "The above copyright notice and this permission notice (including the next paragraph) shall be included in all copies or substantial portions of the Software"],
    "mit_as_is": ['THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT'],
    "mit_liability": ["IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE"],
    "isc_grant": ["Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies", "Permission to use, copy, modify, and distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies"],
    "zero_grant": ["Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted"],
    "isc_as_is": ['THE SOFTWARE IS PROVIDED "AS IS" AND THE AUTHOR DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS', 'THE SOFTWARE IS PROVIDED "AS IS" AND <name> DISCLAIMS ALL WARRANTIES WITH REGARD TO THIS SOFTWARE INCLUDING ALL IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS'],
    "bsd_grant": ["Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met"],
    "bsd_source": ["Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer"],
    "bsd_binary": ["Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution"],
    "bsd_advertise": ["All advertising materials mentioning features or use of this software must display the following acknowledgement"],
    "bsd_endorse": ["Neither the name of <name> nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission", "The name of <name> may not be used to endorse or promote products derived from this software without specific prior written permission"],
    "bsd_as_is": ['THIS SOFTWARE IS PROVIDED BY THE COPYRIGHT HOLDERS AND CONTRIBUTORS "AS IS" AND ANY EXPRESS OR IMPLIED WARRANTIES, INCLUDING, BUT NOT LIMITED TO, THE IMPLIED WARRANTIES OF MERCHANTABILITY AND FITNESS FOR A PARTICULAR PURPOSE ARE DISCLAIMED'],
    "gnu_hope": ["distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE"],
    "mpl2_form": ["This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0"],
    "epl2_form": ["This program and the accompanying materials are made available under the terms of the Eclipse Public License 2.0"],
    "boost_grant": ['Permission is hereby granted, free of charge, to any person or organization obtaining a copy of the software and accompanying documentation covered by this license (the "Software") to use, reproduce, display, distribute, execute, and transmit the Software'],
    "boost_form": ["Distributed under the Boost Software License, Version 1.0"],
    "zlib_as_is": ["This software is provided 'as-is', without any express or implied warranty"],
    "zlib_grant": ["Permission is granted to anyone to use this software for any purpose, including commercial applications, and to alter it and redistribute it freely, subject to the following restrictions"],
    "zlib_origin": ["The origin of this software must not be misrepresented; you must not claim that you wrote the original software"],
    "ofl_form": ["This Font Software is licensed under the SIL Open Font License, Version 1.1"],
    "cc0_waiver": ["To the extent possible under law, the author has waived all copyright and related or neighboring rights to this work", "To the extent possible under law, <name> has waived all copyright and related or neighboring rights to"],
    "unlicense": ["This is free and unencumbered software released into the public domain"],
    "wtfpl": ["DO WHAT THE FUCK YOU WANT TO PUBLIC LICENSE"],
    "rights": ["All rights reserved"],
}
# How a notice begins, and the names by which it calls a licence, with the names of the GNU and Creative Commons families.
VERBS = ["licensed under", "released under", "distributed under", "available under", "published under", "provided under", "covered by", "governed by"]
NAMES = {
    "MIT": ["MIT License", "MIT Licence"],
    "Apache-2.0": ["Apache License, Version 2.0", "Apache License 2.0", "Apache 2.0 License", "Apache License v2.0", "Apache-2.0 License", "Apache Software License 2.0"],
    "BSD-3-Clause": ["BSD 3-Clause License", "3-Clause BSD License", "New BSD License", "BSD-3-Clause License"],
    "BSD-2-Clause": ["BSD 2-Clause License", "2-Clause BSD License", "Simplified BSD License", "BSD-2-Clause License"],
    "ISC": ["ISC License"],
    "MPL-2.0": ["Mozilla Public License, version 2.0", "Mozilla Public License 2.0", "Mozilla Public License, v. 2.0", "MPL 2.0", "MPL-2.0 License"],
    "EPL-2.0": ["Eclipse Public License 2.0", "Eclipse Public License, version 2.0", "Eclipse Public License v2.0"],
    "BSL-1.0": ["Boost Software License 1.0"],
    "Zlib": ["zlib License"],
    "Unlicense": ["Unlicense"],
    "CC0-1.0": ["CC0 1.0", "CC0 1.0 Universal", "Creative Commons Zero v1.0 Universal"],
}
GNU = {"GPL": ("GNU General Public License", "GNU GPL", "GPL"), "LGPL": ("GNU Lesser General Public License", "GNU LGPL", "LGPL"), "AGPL": ("GNU Affero General Public License", "GNU AGPL", "AGPL")}
GNU_VERSIONS = {"GPL": ("2", "3"), "LGPL": ("2.1", "3"), "AGPL": ("3",)}
COMMONS = {"": "Attribution", "-SA": "Attribution-ShareAlike", "-ND": "Attribution-NoDerivatives", "-NC": "Attribution-NonCommercial", "-NC-SA": "Attribution-NonCommercial-ShareAlike", "-NC-ND": "Attribution-NonCommercial-NoDerivatives"}
COMMONS_VERSIONS = ("2.0", "3.0", "4.0")

# Rules over sentences of texts, in order of precedence, as (rule, licence, identifiers in order).
RULES = [
    ("apache2_text", "Apache-2.0", ["apache2_title", "apache2_terms"]),
    ("apache2_header", "Apache-2.0", ["notice_apache_2_0", "apache2_comply", "apache2_copy"]),
    ("mit_text", "MIT", ["mit_grant", "mit_include", "mit_as_is"]),
    ("mit0_text", "MIT-0", ["mit_grant", "mit_as_is"]),
    ("isc_text", "ISC", ["isc_grant"]),
    ("zero_text", "0BSD", ["zero_grant", "isc_as_is"]),
    ("bsd4_text", "BSD-4-Clause", ["bsd_grant", "bsd_source", "bsd_binary", "bsd_advertise"]),
    ("bsd3_text", "BSD-3-Clause", ["bsd_grant", "bsd_source", "bsd_binary", "bsd_endorse"]),
    ("bsd2_text", "BSD-2-Clause", ["bsd_grant", "bsd_source", "bsd_binary"]),
    ("mpl2_header", "MPL-2.0", ["mpl2_form"]),
    ("epl2_header", "EPL-2.0", ["epl2_form"]),
    ("boost_text", "BSL-1.0", ["boost_grant"]),
    ("boost_header", "BSL-1.0", ["boost_form"]),
    ("zlib_text", "Zlib", ["zlib_as_is", "zlib_grant", "zlib_origin"]),
    ("ofl_header", "OFL-1.1", ["ofl_form"]),
    ("cc0_waiver", "CC0-1.0", ["cc0_waiver"]),
    ("unlicense_text", "Unlicense", ["unlicense"]),
    ("wtfpl_text", "WTFPL", ["wtfpl"]),
]
#: A rule that is part of others is not reported where one of these matches.
SHADOWS = {"bsd3_text": ["bsd4_text"], "bsd2_text": ["bsd3_text", "bsd4_text"], "mit0_text": ["mit_text"], "notice_apache_2_0": ["apache2_header"]}
SLOT, LATER = "<name>", "or later"


def normal(text: str) -> str:
    return " ".join(x if x == SLOT else re.sub("[^a-z0-9]+", " ", x).strip() for x in re.split(f"({SLOT})", text.lower())).replace("  ", " ").strip()


def key_of(licence: str) -> str:
    return normal(licence).replace(" ", "_")


def names() -> dict[str, list[str]]:
    """Names of each licence in notices; a GNU licence of which "or later" is said is one of its own."""
    out = {k: list(v) for k, v in NAMES.items()}
    for family, called in GNU.items():
        for v in GNU_VERSIONS[family]:
            spelled = [f"{c}{mid}{w}" for c in called for mid in (", version ", " version ", " v", " ") for w in {v, f"{v}.0" if "." not in v else v}]
            full = v if "." in v else f"{v}.0"
            out[f"{family}-{full}-only"] = spelled
            out[f"{family}-{full}-or-later"] = [f"{s} {LATER}" for s in spelled]
    for suffix, name in COMMONS.items():
        for v in COMMONS_VERSIONS:
            out[f"CC-BY{suffix}-{v}"] = [f"CC BY{suffix} {v}", f"Creative Commons {name} {v}", f"Creative Commons {name} {v} International", f"Creative Commons {name} {v} Unported"]
    return out


def sentences() -> dict[str, str]:
    """Identifier of each normalised sentence of a text. The GNU notices differ in the licence and its version only."""
    out = {normal(s): k for k, all_ in SENTENCES.items() for s in all_}
    for family, (full, *_) in GNU.items():
        for v in GNU_VERSIONS[family]:
            start = f"under the terms of the {full} as published by the Free Software Foundation"
            key = f"{family}-{v if '.' in v else v + '.0'}"
            out[normal(f"{start}, either version {v} of the License, or (at your option) any later version")] = f"notice_{key_of(key + '-or-later')}"
            out |= {normal(f"{start}, version {v}{tail}"): f"notice_{key_of(key + '-only')}" for tail in ("", " of the License")}
    return out


def notices() -> dict[str, str]:
    """Identifier of each normalised licence name, as it stands after a verb phrase."""
    return {normal(n): f"notice_{key_of(lic)}" for lic, called in names().items() for n in called}


def tags() -> dict[str, str]:
    every = dict.fromkeys([*names(), *(lic for _, lic, _ in RULES)])
    return {normal(f"SPDX-License-Identifier: {lic}"): f"tag_{key_of(lic)}" for lic in every}


def rules() -> list[tuple[str, str, list[str]]]:
    every = dict.fromkeys([*names(), *(lic for _, lic, _ in RULES)])
    return RULES + [(f"notice_{key_of(lic)}", lic, [f"notice_{key_of(lic)}"]) for lic in names()] + [(f"tag_{key_of(lic)}", lic, [f"tag_{key_of(lic)}"]) for lic in every]


def pattern(identifiers: list[str]) -> str:
    """Of a sequence written |a|b|c|: these identifiers in this order, anything between."""
    return r"\|" + r"\|(.*\|)?".join(identifiers) + r"\|"


GAP = "[ \\n]+"


def _words(phrases: list[list[str]]) -> str:
    """A pattern of these word lists by common beginnings; of several that match, the longest. A slot is tried last, and takes as few words as will do."""
    heads: dict[str, list[list[str]]] = {}
    for words in phrases:
        heads.setdefault(words[0], []).append(words[1:])
    parts = []
    for head, rests in sorted(heads.items(), key=lambda x: (x[0] == SLOT, x[0])):
        longer = [r for r in rests if r]
        more = f"(?:{GAP}{_words(longer)})" if longer else ""
        word = f"[a-z0-9]+(?:{GAP}[a-z0-9]+){{0,11}}?" if head == SLOT else head
        parts.append(word + more + ("?" if longer and len(longer) < len(rests) else ""))
    return f"(?:{'|'.join(parts)})"


NOTICE = f"(?:{'|'.join(v.replace(' ', GAP) for v in VERBS)}){GAP}(?:the{GAP})?(?:terms{GAP}of{GAP}(?:the{GAP})?)?(?:an?{GAP}|the{GAP})?"
MORE = f"(?:{GAP}or{GAP}(?:at{GAP}your{GAP}option{GAP}any{GAP}later|any{GAP}later|later)(?:{GAP}version)?)?"


def spans() -> str:
    """The pattern of all known sentences in a lower-cased text of words, spaces and line breaks."""
    split = lambda d: [s.split() for s in sorted(d) if not s.endswith(f" {LATER}")]
    return rf"\b(?:not{GAP})?(?:{_words(split(sentences()))}|{NOTICE}{_words(split(notices()))}\b{MORE})\b|(?m:^ ?{_words([s.split() for s in sorted(tags())]).replace(GAP, ' ')} ?$)"


def canonical() -> list[tuple[str, str]]:
    """Replacements that lead from a span, written with single spaces, to its entry in the table: the verb phrase goes, "or any later version" is "or later", and
    what fills a slot is the slot."""
    phrase = NOTICE.replace(GAP, " ")
    out = [(f"^{phrase}", ""), (r" or (?:at your option any later|any later|later)(?: version)?$", f" {LATER}")]
    for s in sorted(sentences()):
        if SLOT in s:
            before, after = s.split(SLOT)
            out.append((f"^{before}.+{after}$", s))
    return out


def known() -> dict[str, str]:
    """Identifier of each sentence as canonical() leaves it. Full sentences that end in "any later version" are cut alike."""
    cut = lambda s: re.sub(canonical()[1][0], f" {LATER}", s)
    return {cut(s): k for s, k in sentences().items()} | notices() | tags()


def scan(docs: DataFrame) -> DataFrame:
    """doc_id, n_found, sentence_ids (in order of the text), rules, licences (sorted)."""
    table = known()
    lower = F.translate(F.coalesce(F.col("text"), F.lit("")), string.ascii_uppercase, string.ascii_lowercase)
    found = F.regexp_extract_all(F.regexp_replace(lower, "[^a-z0-9\n]+", " "), F.lit(spans()), F.lit(0))
    entries = F.create_map(*[F.lit(x) for pair in sorted(table.items()) for x in pair])

    def name(span: Column) -> Column:
        span = F.trim(F.regexp_replace(span, "[^a-z0-9]+", " "))
        for what, to in canonical():
            span = F.regexp_replace(span, what, to)
        return F.try_element_at(entries, span)

    out = docs.select("doc_id", F.array_compact(F.transform(found, name)).alias("sentence_ids"))
    joined = F.concat(F.lit("|"), F.array_join("sentence_ids", "|"), F.lit("|"))
    by_rule = {r: ids for r, _, ids in rules()}
    tests = {r: pattern(ids) for r, ids in by_rule.items()}
    struct = "array<struct<rule:string,licence:string>>"

    def row(rule: str, licence: str) -> Column:
        ids = by_rule[rule]
        hit = F.array_contains("sentence_ids", ids[0]) if len(ids) == 1 else joined.rlike(tests[rule])
        for longer in SHADOWS.get(rule, ()):
            hit = hit & ~joined.rlike(tests[longer])
        return F.when(hit, F.struct(F.lit(rule).alias("rule"), F.lit(licence).alias("licence")))

    m = F.when(F.size("sentence_ids") > 0, F.array_compact(F.array(*[row(r, lic) for r, lic, _ in rules()]))).otherwise(F.array().cast(struct))
    out = out.select("doc_id", "sentence_ids", m.alias("m"))
    return out.select("doc_id", F.size("sentence_ids").cast("long").alias("n_found"), "sentence_ids", F.array_sort(F.transform("m", lambda x: x["rule"])).alias("rules"), F.array_sort(F.array_distinct(F.transform("m", lambda x: x["licence"]))).alias("licences"))


def oracle() -> str:
    """The same in DuckDB's SQL: its regular expressions, too, take the leftmost span and alternatives in their order."""
    pairs = ", ".join(f"('{k}', '{v}')" for k, v in sorted(known().items()))
    span = "trim(regexp_replace(s, '[^a-z0-9]+', ' ', 'g'))"
    for what, to in canonical():
        span = f"regexp_replace({span}, '{what}', '{to}')"
    tests = []
    for r, lic, ids in rules():
        test = f"contains(j, '|{ids[0]}|')" if len(ids) == 1 else f"regexp_matches(j, '{pattern(ids)}')"
        for longer in SHADOWS.get(r, ()):
            test += f" AND NOT regexp_matches(j, '{pattern(next(x for x in RULES if x[0] == longer)[2])}')"
        tests.append(f"CASE WHEN {test} THEN ['{r}', '{lic}'] END")
    return f"""
WITH k(s, id) AS (VALUES {pairs}), m AS (SELECT map_from_entries(list((s, id))) AS k FROM k),
f AS (SELECT doc_id, regexp_extract_all(regexp_replace(translate(coalesce(text, ''), '{string.ascii_uppercase}', '{string.ascii_lowercase}'), '[^a-z0-9\\n]+', ' ', 'g'), '{spans()}', 0) AS found FROM documents),
i AS (SELECT doc_id, list_filter(list_transform(found, lambda s: k[{span}]), lambda x: x IS NOT NULL) AS sentence_ids FROM f, m),
r AS (SELECT doc_id, sentence_ids, CASE WHEN len(sentence_ids) > 0 THEN list_filter([{", ".join(tests)}], lambda x: x IS NOT NULL) ELSE [] END AS m FROM (SELECT *, '|' || array_to_string(sentence_ids, '|') || '|' AS j FROM i))
SELECT doc_id, len(sentence_ids)::BIGINT AS n_found, sentence_ids, list_sort(list_transform(m, lambda x: x[1])) AS rules, list_sort(list_distinct(list_transform(m, lambda x: x[2]))) AS licences FROM r"""
