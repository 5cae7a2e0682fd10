"""Licence scan by sentence rules, in DataFrame functions alone.

A text is cut into sentences, which may run over lines and may follow a line without
an end mark: every range of its lines is looked up, from each line on the longest
first, and the next line after a hit. Each is normalised (lower case, anything but
letters, digits and ``.+-`` to one space), and known licence sentences become identifiers. The
identifiers of a document, in order, are matched against ordered licence rules: the
first rules are the most specific; what a rule matches is taken out before the next
looks. Sentences of no identifier do not break a sequence.

Only texts with a licence word are cut, and nothing is exchanged.

Defined cases: null and empty text hold nothing; equal ids and repeated rows are
scanned row by row; an empty table gives no rows; extra columns are ignored.
"""

from __future__ import annotations

import itertools
import re

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

#: Where a sentence ends: closing marks before white space, a colon at the end of a line, or an empty line.
BOUNDARY = r"[.!?;]+[\"')\]]*[ \t\r\n\f]+|:[ \t]*\r?\n|\n[ \t]*\n"
#: The same, but not after the "v." of a version.
CUT = rf"(?!(?<=\bv)\.[ \t\r\n\f]+[^a-z0-9]*[0-9])(?:{BOUNDARY})"
#: A licence sentence holds one of these, in lower case.
WORDS = r"licen[cs]e|copyright|warrant|redistribut|permission|permitted|public domain|liable|free software|reproduce the above|neither the name|general public|all rights|encumbered|hope that"

#: Sentences of public licence texts, by identifier.
SENTENCES: dict[str, tuple[str, ...]] = {
    "ApacheUnder2": ("Licensed under the Apache License, Version 2.0", 'Licensed under the Apache License, Version 2.0 (the "License")', "This work is licensed under the Apache License, Version 2.0", "Released under the Apache License, Version 2.0", "Licensed under the Apache 2.0 license"),
    "ApacheCompliance": ("you may not use this file except in compliance with the License",),
    "ApacheObtain": ("You may obtain a copy of the License at",),
    "ApacheAsIs": ('Unless required by applicable law or agreed to in writing, software distributed under the License is distributed on an "AS IS" BASIS, WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied',),
    "ApacheSee": ("See the License for the specific language governing permissions and limitations under the License",),
    "MitUnder": ("Released under the MIT License", "Licensed under the MIT License", "This work is licensed under the MIT License", "This project is licensed under the MIT License"),
    "MitGrant": ('Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the "Software"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions',),
    "MitNotice": ("The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software",),
    "AsIsSoftware": ('THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT',),
    "HoldersNotLiable": ("IN NO EVENT SHALL THE AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER LIABILITY, WHETHER IN AN ACTION OF CONTRACT, TORT OR OTHERWISE, ARISING FROM, OUT OF OR IN CONNECTION WITH THE SOFTWARE OR THE USE OR OTHER DEALINGS IN THE SOFTWARE",),
    "IscGrant": ("Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies",),
    "BsdGrant": ("Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met",),
    "BsdSource": ("Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer", "1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer"),
    "BsdBinary": ("Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution",),
    "BsdName": ("Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission",),
    "GplUnder2": ("This work is licensed under the GNU General Public License, version 2", "Licensed under the GNU General Public License, version 2", "Released under the GNU General Public License, version 2"),
    "GplUnder3": ("This work is licensed under the GNU General Public License, version 3", "Licensed under the GNU General Public License, version 3", "Released under the GNU General Public License, version 3"),
    "LgplUnder3": ("This work is licensed under the GNU Lesser General Public License, version 3", "Licensed under the GNU Lesser General Public License, version 3"),
    "AgplUnder3": ("This work is licensed under the GNU Affero General Public License, version 3", "Licensed under the GNU Affero General Public License, version 3"),
    "FreeSoftware": ("This program is free software",),
    "Gpl2OrLater": ("you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 2 of the License, or (at your option) any later version",),
    "Gpl3OrLater": ("you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version",),
    "GplOpen": ("you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation",),
    "OrLater2": ("either version 2 of the License, or (at your option) any later version",),
    "OrLater3": ("either version 3 of the License, or (at your option) any later version",),
    "GplHope": ("This program is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY",),
    "MplUnder2": ("This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0", "Licensed under the Mozilla Public License, version 2.0"),
    "Unencumbered": ("This is free and unencumbered software released into the public domain",),
    "PublicDomain": ("This work is in the public domain", "Released into the public domain"),
    "AllRights": ("All rights reserved",),
}
CC_KINDS = ("BY", "BY-SA", "BY-NC", "BY-ND", "BY-NC-SA", "BY-NC-ND")
CC_VERSIONS = ("2.0", "2.5", "3.0", "4.0")
SPDX = ("Apache-2.0", "MIT", "ISC", "BSD-2-Clause", "BSD-3-Clause", "GPL-2.0-only", "GPL-2.0-or-later", "GPL-3.0-only", "GPL-3.0-or-later", "LGPL-3.0-only", "AGPL-3.0-only", "MPL-2.0", "CC0-1.0", "Unlicense")
for _kind, _version in itertools.product(CC_KINDS, CC_VERSIONS):
    SENTENCES[f"Cc-{_kind}-{_version}"] = tuple(f"{intro} CC {_kind} {_version}{end}" for intro in ("Licensed under", "Released under", "This work is licensed under") for end in ("", " license"))

#: Ordered: licence, and the identifiers that show it; ``?`` marks one that may be missing.
RULES: list[tuple[str, tuple[str, ...]]] = [
    ("Apache-2.0", ("ApacheUnder2", "ApacheCompliance", "ApacheObtain?", "ApacheAsIs?", "ApacheSee?")),
    ("MIT", ("MitUnder?", "MitGrant", "MitNotice?", "AsIsSoftware?", "HoldersNotLiable?")),
    ("ISC", ("IscGrant", "AsIsSoftware?")),
    ("BSD-3-Clause", ("BsdGrant", "BsdSource", "BsdBinary", "BsdName")),
    ("BSD-2-Clause", ("BsdGrant", "BsdSource", "BsdBinary")),
    ("GPL-3.0-or-later", ("FreeSoftware?", "Gpl3OrLater", "GplHope?")),
    ("GPL-2.0-or-later", ("FreeSoftware?", "Gpl2OrLater", "GplHope?")),
    ("GPL-3.0-or-later", ("FreeSoftware?", "GplOpen", "OrLater3", "GplHope?")),
    ("GPL-2.0-or-later", ("FreeSoftware?", "GplOpen", "OrLater2", "GplHope?")),
    ("Unlicense", ("Unencumbered",)),
    ("Apache-2.0", ("ApacheUnder2",)),
    ("MIT", ("MitUnder",)),
    ("GPL-3.0-only", ("GplUnder3", "GplHope?")),
    ("GPL-2.0-only", ("GplUnder2", "GplHope?")),
    ("LGPL-3.0-only", ("LgplUnder3",)),
    ("AGPL-3.0-only", ("AgplUnder3",)),
    ("MPL-2.0", ("MplUnder2",)),
    ("public-domain", ("PublicDomain",)),
    *((f"CC-{k}-{v}", (f"Cc-{k}-{v}",)) for k, v in itertools.product(CC_KINDS, CC_VERSIONS)),
]
for _name in SPDX:
    SENTENCES[f"Spdx-{_name}"] = (f"SPDX-License-Identifier {_name}", f"SPDX-License-Identifier={_name}")
    RULES.append((_name, (f"Spdx-{_name}",)))


def normalised(sentence: str) -> str:
    """The form in which sentences are compared; the columns below do the same."""
    s = re.sub(r"[^a-z0-9.+-]+", " ", sentence.lower())
    return re.sub(r"^[ .+-]+|[ .+-]+$", "", s)


#: The same words, also where a line ends between two of them, and "released under", which some sentences have alone.
WRAPPED_WORDS = f"{WORDS}|released under".replace(" ", "[^a-z0-9]+")
KNOWN: dict[str, str] = {normalised(text): name for name, texts in SENTENCES.items() for text in texts}


#: A known sentence over one or more whole lines; longer ones first.
RANGES = "(?m)^(" + "|".join(re.escape(k).replace(r"\-", "-").replace(r"\ ", "[ \n]") for k in sorted(KNOWN, key=lambda k: (-len(k), k))) + ")$"


def rule_pattern(parts: tuple[str, ...]) -> str:
    """A rule over ``|A|B|...|``; each identifier owns the bar after it."""
    return r"\|" + "".join(f"({re.escape(p[:-1])}\\|)?" if p.endswith("?") else f"{re.escape(p)}\\|" for p in parts)


PATTERNS = [(name, rule_pattern(parts).replace("\\-", "-")) for name, parts in RULES]


def sentence_ids(text: Column) -> Column:
    """Identifiers of the licence sentences of a text, in order."""
    known = F.create_map(*[F.lit(x) for pair in KNOWN.items() for x in pair])
    sentences = F.filter(F.split(F.lower(text), CUT), lambda s: s.rlike(WRAPPED_WORDS))

    def ids_of(sentence: Column) -> Column:
        plain = F.regexp_replace(sentence, "[^a-z0-9.+\n-]+", " ")
        version = F.regexp_replace(plain, r"\bv\.[ ]*\n[ \n.+-]*(?=[0-9])", "v. ")
        lines = F.regexp_replace(F.regexp_replace(version, r"[ .+-]*\n[ \n.+-]*", "\n"), r"^[ \n.+-]+|[ \n.+-]+$", "")
        return F.transform(F.regexp_extract_all(lines, F.lit(RANGES), F.lit(1)), lambda k: F.element_at(known, F.replace(k, F.lit("\n"), F.lit(" "))))

    found = F.flatten(F.transform(sentences, ids_of))
    return F.when(F.lower(text).rlike(WRAPPED_WORDS), found).otherwise(F.array().cast("array<string>"))


def match_rules(ids: Column) -> Column:
    """``seq`` (identifiers that no rule took, between bars) and ``found`` (licences, in rule order)."""
    rules = F.array(*[F.struct(F.lit(n).alias("name"), F.lit(p).alias("pattern")) for n, p in PATTERNS])
    start = F.struct(F.concat(F.lit("|"), F.concat_ws("|", ids), F.lit("|")).alias("seq"), F.array().cast("array<string>").alias("found"))

    def step(acc: Column, rule: Column) -> Column:
        hit = F.regexp_like(acc["seq"], rule["pattern"])
        return F.struct(F.when(hit, F.regexp_replace(acc["seq"], rule["pattern"], F.lit("|"))).otherwise(acc["seq"]).alias("seq"), F.when(hit, F.concat(acc["found"], F.array(rule["name"]))).otherwise(acc["found"]).alias("found"))

    return F.when(F.size(ids) > 0, F.aggregate(rules, start, step)).otherwise(F.struct(F.lit("||").alias("seq"), F.array().cast("array<string>").alias("found")))


def scan(docs: DataFrame) -> DataFrame:
    """``doc_id, sentence_ids, licences, unmatched`` of every row; lists joined by commas."""
    with_ids = docs.select("doc_id", sentence_ids(F.coalesce(F.col("text").cast("string"), F.lit(""))).alias("ids"))
    matched = with_ids.select("doc_id", "ids", match_rules(F.col("ids")).alias("m"))
    left = F.filter(F.split("m.seq", r"\|"), lambda x: x != "")
    return matched.select("doc_id", F.size("ids").alias("n_sentences"), F.concat_ws(",", "ids").alias("sentence_ids"), F.concat_ws(",", F.array_distinct("m.found")).alias("licences"), F.concat_ws(",", left).alias("unmatched"))


def oracle_sql() -> str:
    """The same scan for DuckDB, whose regular expressions take the same lines whole."""
    quote = lambda s: "'" + s.replace("'", "''") + "'"
    known = "MAP {" + ", ".join(f"{quote(k)}: {quote(v)}" for k, v in KNOWN.items()) + "}"
    # RE2 has no look-behind: the dot of a version's "v." is masked while sentences are cut.
    mask = "chr(57344)"
    masked = f"regexp_replace(replace(lower(coalesce(text, '')), {mask}, ','), '(^|[^a-z0-9_])v\\.([ \\t\\r\\n\\f]+[^a-z0-9]*[0-9])', '\\1v' || {mask} || '\\2', 'g')"
    plain = f"regexp_replace(replace(s, {mask}, '.'), '[^a-z0-9.+\\n-]+', ' ', 'g')"
    version = f"regexp_replace({plain}, '\\bv\\.[ ]*\\n[ \\n.+-]*([0-9])', 'v. \\1', 'g')"
    lines = f"regexp_replace(regexp_replace({version}, '[ .+-]*\\n[ \\n.+-]*', chr(10), 'g'), '^[ \\n.+-]+|[ \\n.+-]+$', '', 'g')"
    steps, last = [], "s0"
    for k, (name, pattern) in enumerate(PATTERNS, 1):
        hit = f"regexp_matches(seq, {quote(pattern)})"
        steps.append(f"s{k} AS (SELECT doc_id, ids, CASE WHEN {hit} THEN regexp_replace(seq, {quote(pattern)}, '|', 'g') ELSE seq END AS seq, CASE WHEN {hit} AND NOT list_contains(found, {quote(name)}) THEN list_append(found, {quote(name)}) ELSE found END AS found FROM {last})")
        last = f"s{k}"
    return f"""WITH cut AS (SELECT doc_id, list_filter(regexp_split_to_array({masked}, {quote(BOUNDARY)}), lambda s: regexp_matches(replace(s, {mask}, '.'), {quote(WRAPPED_WORDS)})) AS sentences FROM documents),
known AS (SELECT {known} AS m),
named AS (SELECT doc_id, flatten(list_transform(sentences, lambda s: list_transform(regexp_extract_all({lines}, {quote(RANGES)}, 1), lambda k: m[replace(k, chr(10), ' ')]))) AS ids FROM cut, known),
s0 AS (SELECT doc_id, ids, '|' || array_to_string(ids, '|') || '|' AS seq, CAST([] AS VARCHAR[]) AS found FROM named),
{', '.join(steps)}
SELECT doc_id, CAST(len(ids) AS INTEGER) AS n_sentences, coalesce(array_to_string(ids, ','), '') AS sentence_ids, coalesce(array_to_string(found, ','), '') AS licences, coalesce(array_to_string(list_filter(string_split(seq, '|'), lambda x: x <> ''), ','), '') AS unmatched FROM {last}"""
