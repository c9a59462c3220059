"""Licence recognition by sentence rules, in DataFrame functions only.

A text is cut into lines and sentences ("v. 2.0" stays whole), normalised (A-Z
lowered, every run of other characters than letters and digits one space) and
what is a known licence sentence is found; it may be wrapped over lines (with comment signs before
each), but not over a blank line or a sentence's end.  Sentences that name a licence
("this file is licensed under the terms of the ...") are brought to one form first, whatever they
speak of and whichever verb they use.  The identifiers in text order, unknown sentences left out,
are then matched against ordered licence rules, longest rule first, and what a
rule has consumed is gone for later rules.

Defined results: null text counts as empty; a text without known sentences has
an empty list; a sentence that occurs twice is matched twice; repeated rows give
repeated results; a null doc_id stays null.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

# Known licence sentences in normal form, by identifier.
SENTENCES = {
    "mit-grant": ["permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files the software to deal in the software without restriction"],
    "mit-notice": ["the above copyright notice and this permission notice shall be included in all copies or substantial portions of the software", "the above copyright notice and this permission notice including the next paragraph shall be included in all copies or substantial portions of the software"],
    "as-is": ["the software is provided as is without warranty of any kind express or implied"],
    "apache-comply": ["you may not use this file except in compliance with the license"],
    "apache-copy": ["you may obtain a copy of the license at", "you may obtain a copy of the license at http www apache org licenses license 2 0", "you may obtain a copy of the license at https www apache org licenses license 2 0"],
    "apache-basis": ["unless required by applicable law or agreed to in writing software distributed under the license is distributed on an as is basis without warranties or conditions of any kind either express or implied"],
    "gpl-hope": ["this program is distributed in the hope that it will be useful but without any warranty", "this program is distributed in the hope that it will be useful but without any warranty without even the implied warranty of merchantability or fitness for a particular purpose"],
    "bsd-grant": ["redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met"],
    "bsd-source": ["redistributions of source code must retain the above copyright notice this list of conditions and the following disclaimer"],
    "bsd-binary": ["redistributions in binary form must reproduce the above copyright notice this list of conditions and the following disclaimer in the documentation and or other materials provided with the distribution"],
    "bsd-name": ["neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission"],
    "isc-grant": ["permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted provided that the above copyright notice and this permission notice appear in all copies"],
    "zlib-grant": ["permission is granted to anyone to use this software for any purpose including commercial applications and to alter it and redistribute it freely subject to the following restrictions"],
    "unlicense-free": ["this is free and unencumbered software released into the public domain"],
    "mpl-form": ["this source code form is subject to the terms of the mozilla public license v 2 0"],
    "reserved": ["all rights reserved"],
}
# The whole sentences of licences of which SENTENCES has the beginning.
WHOLE = {
    "mit-grant": SENTENCES["mit-grant"][0] + " including without limitation the rights to use copy modify merge publish distribute sublicense and or sell copies of the software and to permit persons to whom the software is furnished to do so subject to the following conditions",
    "as-is": SENTENCES["as-is"][0] + " including but not limited to the warranties of merchantability fitness for a particular purpose and noninfringement",
}
# Names of licences in normal form, by licence.
NAMES = {
    "MIT": ["mit license", "mit licence", "mit"],
    "Apache-2.0": ["apache license version 2 0", "apache license v2 0", "apache license 2 0", "apache 2 0 license", "apache 2 0"],
    "BSD-2-Clause": ["bsd 2 clause license", "2 clause bsd license", "simplified bsd license"],
    "BSD-3-Clause": ["bsd 3 clause license", "3 clause bsd license", "new bsd license", "modified bsd license"],
    "ISC": ["isc license"],
    "MPL-2.0": ["mozilla public license version 2 0", "mozilla public license v 2 0", "mozilla public license 2 0", "mpl 2 0"],
    "EPL-2.0": ["eclipse public license version 2 0", "eclipse public license 2 0", "eclipse public license v 2 0"],
    "BSL-1.0": ["boost software license version 1 0", "boost software license 1 0"],
    "Zlib": ["zlib license"],
    "Unlicense": ["unlicense"],
    "CC0-1.0": ["cc0 1 0", "cc0 1 0 universal", "creative commons cc0 1 0 universal license"],
}
# Parameters of rule-built names: the share-alike families and their versions, and the attribution family's parts.
FAMILIES = {"GPL": ("general public license", ("2 0", "3 0")), "LGPL": ("lesser general public license", ("2 1", "3 0")), "AGPL": ("affero general public license", ("3 0",))}
PARTS = {"BY": "attribution", "BY-SA": "attribution sharealike", "BY-NC": "attribution noncommercial", "BY-ND": "attribution noderivatives", "BY-NC-SA": "attribution noncommercial sharealike", "BY-NC-ND": "attribution noncommercial noderivatives"}


def _names() -> dict[str, str]:
    """Name in normal form to licence."""
    out = {name: licence for licence, names in NAMES.items() for name in names}
    for short, (long, versions) in FAMILIES.items():
        for version in versions:
            licence = f"{short}-{version.replace(' ', '.')}"
            for number in {version, version.removesuffix(" 0")}:
                for name in (f"gnu {long}", long, f"gnu {short.lower()}", short.lower()):
                    for v in (f" version {number}", f" v{number}", f" v {number}", f" {number}"):
                        out[name + v] = f"{licence}-only"
                        for later in (" or later", " or later version", " or any later version", " or at your option any later version"):
                            out[name + v + later] = f"{licence}-or-later"
                out[f"{short.lower()}v{number}"] = f"{licence}-only"
    for code, long in PARTS.items():
        for number in ("3 0", "4 0"):
            licence = f"CC-{code}-{number.replace(' ', '.')}"
            for name in (f"cc {code.lower().replace('-', ' ')} {number}", f"creative commons {long} {number} license", f"creative commons {long} {number} international license", f"creative commons {long} {number} unported license"):
                out[name] = licence
    return out


def _grants() -> dict[str, str]:
    """The share-alike families' own notices to identifier."""
    out = {}
    for short, (long, versions) in FAMILIES.items():
        for version in versions:
            for number in {version, version.removesuffix(" 0")}:
                head = f"this program is free software you can redistribute it and or modify it under the terms of the gnu {long} as published by the free software foundation"
                name = f"free-{short.lower()}-{version.replace(' ', '.')}"
                out[f"{head} either version {number} of the license or at your option any later version"] = f"{name}-or-later"
                out[f"{head} version {number} of the license"] = out[f"{head} version {number}"] = f"{name}-only"
        out[f"you should have received a copy of the gnu {long} along with this program"] = "gpl-received"
    return out


NAME_OF = _names()
#: Normal form to identifier; sentences that name a licence stand as "licensed under" and the name.
FORMS = {form: name for name, forms in SENTENCES.items() for form in forms} | {form: name for name, form in WHOLE.items()} | _grants() | {f"licensed under {name}": f"named-{licence}" for name, licence in NAME_OF.items()}
# Ordered rules, longest first where one begins another.
LONG_RULES = [
    ("Apache-2.0", ["named-Apache-2.0", "apache-comply", "apache-copy", "apache-basis"]),
    ("BSD-3-Clause", ["bsd-grant", "bsd-source", "bsd-binary", "bsd-name"]),
    ("BSD-2-Clause", ["bsd-grant", "bsd-source", "bsd-binary"]),
    ("MIT", ["mit-grant", "mit-notice", "as-is"]),
    ("MIT", ["mit-grant", "mit-notice"]),
    ("Apache-2.0", ["named-Apache-2.0", "apache-comply"]),
]
SHORT_RULES = [("ISC", ["isc-grant"]), ("Zlib", ["zlib-grant"]), ("Unlicense", ["unlicense-free"]), ("MPL-2.0", ["mpl-form"]), ("All-Rights-Reserved", ["reserved"])]


def _rules() -> list[tuple[str, list[str]]]:
    notices = sorted(set(_grants().values()) - {"gpl-received"})
    of = lambda name: name.removeprefix("free-").replace("lgpl", "LGPL").replace("agpl", "AGPL").replace("gpl", "GPL")
    family = [(of(n), [n, *rest]) for rest in (["gpl-hope", "gpl-received"], ["gpl-hope"], []) for n in notices]
    return LONG_RULES + family + SHORT_RULES + [(licence, [f"named-{licence}"]) for licence in sorted(set(NAME_OF.values()))]


RULES = _rules()
# What sentences that name a licence speak of, and their verbs.
SUBJECT = "(?:(?:this|the) (?:[a-z]+ ){1,3}(?:is|are) (?:dual )?|it is )?"
NAMED = SUBJECT + "(?:licensed|licenced|released|distributed|published|made available|available|provided) under (?:the )?(?:terms of )?(?:the )?"
NOTICE = "(?:this|the) [a-z]+ is (free software you can|distributed in the hope)"
AFTER = "(?: the license)?"
#: Every known sentence holds one of these, so other texts need no cutting.
HINT = r"(?i)licen[sc]e|rights|permission|warrant|redistribut|free[^a-z0-9]+software|public[^a-z0-9]+domain|[sdte][^a-z0-9]+under[^a-z0-9]"
#: A sentence's end or a blank line; no end is "v." before a number.
ENDS = r"(?:(?<!\bv)|(?=[.!?]+\s+[^0-9]))[.!?]+[\x20\x09-\x0D]|\n(?=[^a-z0-9\n]*\n)"
UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def _canonical(sentence: Column) -> Column:
    """One form for sentences that differ in what they speak of."""
    named = F.regexp_replace(sentence, f"^{NAMED}(.+?){AFTER}$", "licensed under $1")
    notice = F.regexp_replace(named, f"^{NOTICE}", "this program is $1")
    return F.regexp_replace(notice, "along with this [a-z]+$", "along with this program")


def identifiers(text: Column) -> Column:
    """array<string>: identifiers of the known sentences, in text order."""
    known = F.create_map(*[F.lit(x) for item in FORMS.items() for x in item])
    # "#" stands for a sentence's end or a blank line, "|" for another line's end
    ends = F.regexp_replace(F.translate(text, UPPER + "#|", LOWER + "  "), ENDS, "#")
    normal = F.regexp_replace(F.regexp_replace(F.replace(ends, F.lit("\n"), F.lit("|")), "[^a-z0-9#|]+", " "), " ?([#|]) ?", " $1 ")
    plain = [f for f in FORMS if not f.startswith("licensed under ")]
    plain = [f.replace("this program is free", "(?:this|the) [a-z]+ is free").replace("this program is distributed", "(?:this|the) [a-z]+ is distributed").replace("along with this program", "along with this [a-z]+") for f in plain]
    names = "|".join(sorted(NAME_OF, key=len, reverse=True))
    forms = "|".join([*sorted(plain, key=len, reverse=True), f"{NAMED}(?:{names}){AFTER}"]).replace(" ", r" (?:\| +)?")
    found = F.regexp_extract_all(F.concat(F.lit("# "), F.trim(normal), F.lit(" #")), F.lit(rf"(?<=[#|] )(?:{forms})(?= [#|])"), F.lit(0))
    ids = F.filter(F.transform(found, lambda s: F.try_element_at(known, _canonical(F.regexp_replace(s, r"[| ]+", " ")))), lambda i: i.isNotNull())
    return F.when(text.rlike(HINT), ids).otherwise(F.array().cast("array<string>"))


def scan_licenses(docs: DataFrame) -> DataFrame:
    """(doc_id, n_sentences, sentence_ids, licenses, n_licenses): one row per document, lists comma-joined in text order."""
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), identifiers(F.coalesce(F.col("text").cast("string"), F.lit(""))).alias("ids"))
    seq = F.concat(F.lit(" "), F.array_join(F.col("ids"), "  "), F.lit(" "))
    whole = seq
    for name, rule in RULES:
        whole = F.replace(whole, F.lit(" " + "  ".join(rule) + " "), F.lit(f" #{name} "))
    hits = F.when(F.size("ids") > 0, F.regexp_extract_all(whole, F.lit("#([^ ]+)"), F.lit(1))).otherwise(F.array().cast("array<string>"))
    return rows.select("doc_id", F.size("ids").cast("long").alias("n_sentences"), F.array_join("ids", ",").alias("sentence_ids"), F.array_join(hits, ",").alias("licenses"), F.size(hits).cast("long").alias("n_licenses"))


def oracle() -> str:
    """The same by sentences and lines in DuckDB; sentences wrapped over lines are tested apart."""
    known = ", ".join(f"('{form}', '{name}')" for form, name in FORMS.items())
    seq = "' ' || coalesce(string_agg(name, '  ' ORDER BY pos), '') || ' '"
    for name, rule in RULES:
        seq = f"replace({seq}, ' {'  '.join(rule)} ', ' #{name} ')"
    canonical = rf"regexp_replace(regexp_replace(regexp_replace(form, '^{NAMED}(.+?){AFTER}$', 'licensed under \1'), '^{NOTICE}', 'this program is \1'), 'along with this [a-z]+$', 'along with this program')"
    return rf"""WITH known(form, name) AS (VALUES {known}),
    d AS (SELECT row_number() OVER () AS r, doc_id, string_split(regexp_replace(coalesce(text, ''), '[.!?]+[\x20\x09-\x0D]|\n', chr(10), 'g'), chr(10)) AS parts FROM documents),
    p AS (SELECT r, unnest(range(1, len(parts) + 1)) AS pos, trim(regexp_replace(translate(unnest(parts), '{UPPER}', '{LOWER}'), '[^a-z0-9]+', ' ', 'g')) AS form FROM d),
    s AS (SELECT r, pos, {canonical} AS form FROM p),
    k AS (SELECT r, pos, name FROM s JOIN known USING (form)),
    q AS (SELECT r, count(*) AS n, string_agg(name, ',' ORDER BY pos) AS ids, {seq} AS seq FROM k GROUP BY r)
    SELECT doc_id, CAST(coalesce(n, 0) AS BIGINT) AS n_sentences, coalesce(ids, '') AS sentence_ids,
      coalesce(array_to_string(regexp_extract_all(seq, '#([^ ]+)', 1), ','), '') AS licenses, CAST(coalesce(len(regexp_extract_all(seq, '#([^ ]+)', 1)), 0) AS BIGINT) AS n_licenses
    FROM d LEFT JOIN q USING (r)"""
