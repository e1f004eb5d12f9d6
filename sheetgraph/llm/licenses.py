"""Licence scans by sentence rules, in column expressions alone.

A text is cut into sentences twice, by lines and with lines joined into paragraphs; sentences that hold a
licence word are normalised (lower case, letters, digits and dots only) and mapped to identifiers of known
licence sentences by equality. The table is made by the same cut and normalisation of the standard wordings,
so a wording that is cut has several identifiers. A licence rule is an ordered list of passages; it holds
where the document's identifiers, in either cut, contain those of its passages in that order. A rule whose list another matched rule's
list contains gives way to it.

Everything is a fold inside a row: no join, no shuffle. Texts without any licence word are settled by one
regular expression.

Defined results: null, empty and very long texts are treated whole; no licence word gives verdict `none`,
licence words without a known sentence `unknown`, one matched rule `known`, several `several`, known
sentences that complete no rule `partial`; repeated sentences count once for the rules' order.
"""

from __future__ import annotations

import re
from functools import reduce
from itertools import chain, product

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

WORDS = r"(?i)licen[sc]|copyright|rights reserved|warrant|permission|redistribut|public domain|creative commons|cc by|cc0|free software|spdx"


#: Where a sentence ends; the dot of "v. 2.0" ends none.
END = r"\n+|(?<=[!?;:])\s+|(?<=\.)(?<!\b[vV]\.)\s+"


def parts(text: str) -> list[str]:
    """The normalised sentences with a licence word of one line, as _cut and normalised give them."""
    out = []
    for s in re.split(END, text):
        if re.search(WORDS, s):
            plain = re.sub(r"[^a-z0-9.]+", " ", s.lower())
            out.append(re.sub(" +", " ", re.sub(r"\.+( |$)", r"\1", plain)).strip())
    return out


def _wordings() -> dict[str, list[str]]:
    """Identifier to the standard wordings of one passage; families are spelled out by loops over their versions."""
    out = {
        "rights-reserved": ["All rights reserved."],
        "mit-named": ["Released under the MIT License.", "Licensed under the MIT License.", "This project is licensed under the MIT License."],
        "mit-grant": ['Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the "Software"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions:'],
        "notice-kept": ["The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software."],
        "isc-grant": ["Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies."],
        "bsd-grant": ["Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met:"],
        "bsd-source": ["Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer."],
        "bsd-binary": ["Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution."],
        "bsd-endorse": ["Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission."],
        "as-is": ['THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT.'],
        "apache-comply": ["you may not use this file except in compliance with the License."],
        "unlicense": ["This is free and unencumbered software released into the public domain."],
        "gpl-hope": [f"This {what} is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE." for what in ("program", "library")],
        "mpl-2.0-named": ["This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0."],
        "cc0-waiver": ["To the extent possible under law, the author has waived all copyright and related or neighboring rights to this work."],
    }
    for v in ("1.1", "2.0"):
        leads = ("Licensed under the", "Released under the", "This work is licensed under the", "Distributed under the")
        out[f"apache-{v}-named"] = [f"{lead} Apache License, Version {v}{tail}" for lead in leads for tail in (".", ' (the "License");')]
    for family, name in (("gpl", "GNU General Public License"), ("lgpl", "GNU Lesser General Public License"), ("agpl", "GNU Affero General Public License")):
        for v in ("1", "2", "2.1", "3"):
            leads = ("Licensed under the", "Released under the", "This work is licensed under the", "This program is licensed under the")
            out[f"{family}-{v}-named"] = [f"{lead} {name}, version {v}." for lead in leads]
            out[f"{family}-{v}-later"] = [
                f"This {what} is free software; you can redistribute it and/or modify it under the terms of the {name} as published by the Free Software Foundation{mark} either version {v} of the License, or (at your option) any later version."
                for what in ("program", "library")
                for mark in (",", ";")
            ]
    names = {"by": "Attribution", "sa": "ShareAlike", "nc": "NonCommercial", "nd": "NoDerivatives"}
    area = {"2.0": "Generic", "2.5": "Generic", "3.0": "Unported", "4.0": "International"}
    for kind in ("by", "by-sa", "by-nc", "by-nd", "by-nc-sa", "by-nc-nd"):
        for v in area:
            short = [f"{lead} CC {kind.upper()} {v}." for lead in ("Licensed under", "This work is licensed under", "Released under")]
            long = "-".join(names[x] for x in kind.split("-"))
            out[f"cc-{kind}-{v}-named"] = [*short, f"This work is licensed under a Creative Commons {long} {v} {area[v]} License."]
    return out


def _rules(ids: set[str]) -> dict[str, list[str]]:
    """Licence name to the passages that make it out, in order."""
    out = {
        "MIT (named)": ["mit-named"],
        "MIT": ["mit-grant", "notice-kept", "as-is"],
        "ISC": ["isc-grant"],
        "BSD-2-Clause": ["bsd-grant", "bsd-source", "bsd-binary"],
        "BSD-3-Clause": ["bsd-grant", "bsd-source", "bsd-binary", "bsd-endorse"],
        "Apache-2.0 (header)": ["apache-2.0-named", "apache-comply"],
        "Unlicense": ["unlicense"],
        "MPL-2.0": ["mpl-2.0-named"],
        "CC0-1.0": ["cc0-waiver"],
        "All rights reserved": ["rights-reserved"],
    }
    for i in sorted(ids):
        if i.endswith("-named") and i.startswith(("apache", "gpl", "lgpl", "agpl", "cc-")):
            family, _, version = i.removesuffix("-named").rpartition("-")
            out[f"{family.upper() if family != 'apache' else 'Apache'}-{version}"] = [i]
        if i.endswith("-later"):
            family, version = i.split("-")[:2]
            out[f"{family.upper()}-{version}+"] = [i]
            out[f"{family.upper()}-{version}+ (notice)"] = [i, "gpl-hope"]
    return out


WORDINGS = _wordings()
RULES = _rules(set(WORDINGS))


def _sentences() -> tuple[dict[str, str], dict[str, list[list[str]]]]:
    """Normalised sentence to identifier, and passage to its lists of identifiers, one for each way to cut it.

    Every wording goes through the cut itself. A passage that stays whole gives its name to its sentence; the
    sentences of one that is cut have numbers behind it, and passages that share a sentence share its identifier.
    """
    table: dict[str, str] = {}
    ways: dict[str, list[list[str]]] = {}
    for name, wordings in WORDINGS.items():
        for w in wordings:
            cut = parts(w)
            for s in cut:
                table.setdefault(s, name if len(cut) == 1 else f"{name}.{len(table)}")
            way = [table[s] for s in cut]
            if way not in ways.setdefault(name, []):
                ways[name].append(way)
    return table, ways


SENTENCES, WAYS = _sentences()


def ways_of(rule: list[str]) -> list[list[str]]:
    """The lists of identifiers that a rule's passages can come to."""
    return [list(chain(*way)) for way in product(*[WAYS[name] for name in rule])]


def _contains(longer: list[str], shorter: list[str]) -> bool:
    it = iter(longer)
    return len(longer) > len(shorter) and all(x in it for x in shorter)


def normalised(sentence: F.Column) -> F.Column:
    plain = F.regexp_replace(F.lower(sentence), r"[^a-z0-9.]+", " ")
    return F.trim(F.regexp_replace(F.regexp_replace(plain, r"\.+( |$)", "$1"), " +", " "))


def _identifiers(sentences: F.Column) -> F.Column:
    known = F.create_map(*[F.lit(x) for pair in SENTENCES.items() for x in pair])
    return F.transform(sentences, lambda s: F.coalesce(F.try_element_at(known, s), F.lit("")))


def _cut(text: F.Column, joined: bool) -> F.Column:
    """Normalised sentences with a licence word, in order."""
    body = F.regexp_replace(text, r"(?<!\n)\n(?!\n)", " ") if joined else text
    parts = F.filter(F.split(body, END), lambda s: s.rlike(WORDS))
    return F.transform(parts, normalised)


def _ordered(rule: list[str]) -> str:
    """What finds a rule's identifiers in order in a line of `|`-enclosed ones."""
    return "|".join(".*".join(rf"\|{re.escape(x)}\|" for x in way) for way in ways_of(rule))


def scan(docs: DataFrame, key: str = "doc_id", text: str = "text") -> DataFrame:
    """doc_id, n_candidates, n_known, sentence_ids, licenses, verdict for every document."""
    t = F.col("__text")
    base = docs.select(F.col(key).alias("doc_id"), F.coalesce(F.col(text), F.lit("")).alias("__text"))
    none = F.array().cast("array<string>")
    base = base.select("doc_id", F.when(t.rlike(WORDS), t).alias("__text"))
    cut = base.select("doc_id", *[F.when(t.isNotNull(), _cut(t, j)).otherwise(none).alias(f"cut{int(j)}") for j in (False, True)])
    ids = cut.select("doc_id", F.size("cut0").alias("n_candidates"), _identifiers(F.col("cut0")).alias("ids0"), _identifiers(F.col("cut1")).alias("ids1"))
    ids = ids.select("doc_id", "n_candidates", *[F.filter(c, lambda x: x != "").alias(c) for c in ("ids0", "ids1")])
    any_known = (F.size("ids0") > 0) | (F.size("ids1") > 0)
    lines = F.concat_ws("\n", *[F.array_join(F.transform(c, lambda x: F.concat(F.lit("|"), x, F.lit("|"))), "") for c in ("ids0", "ids1")])
    ids = ids.withColumn("__lines", F.when(any_known, lines))
    hits = F.array(*[F.when(F.col("__lines").rlike(_ordered(r)), F.lit(name)) for name, r in RULES.items()])
    found = ids.withColumn("found", F.when(any_known, F.array_compact(hits)).otherwise(none))
    below = {name: [n for n, r in RULES.items() if _contains(r, rule)] for name, rule in RULES.items()}
    gone = [F.when(reduce(lambda a, b: a | b, [F.array_contains("found", n) for n in over]), F.lit(name)) for name, over in below.items() if over]
    licenses = F.array_sort(F.array_except("found", F.array_compact(F.array(*gone))))
    out = found.select("doc_id", "n_candidates", F.greatest(F.size("ids0"), F.size("ids1")).alias("n_known"), F.when(F.size("ids0") >= F.size("ids1"), F.col("ids0")).otherwise(F.col("ids1")).alias("sentence_ids"), licenses.alias("licenses"))
    n = F.size("licenses")
    verdict = F.when(n > 1, "several").when(n == 1, "known").when(F.col("n_known") > 0, "partial").when(F.col("n_candidates") > 0, "unknown").otherwise("none")
    return out.withColumn("verdict", verdict)
