"""Every licence rule holds on the licence's standard wording, on one line and wrapped in a comment block."""

import textwrap

from sheetgraph.llm import licenses

HOPE = "This {0} is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE."
GNU = {"GPL": "GNU General Public License", "LGPL": "GNU Lesser General Public License", "AGPL": "GNU Affero General Public License"}
CC = {"BY": "Attribution", "SA": "ShareAlike", "NC": "NonCommercial", "ND": "NoDerivatives"}
BSD = [
    "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met:",
    "1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer.",
    "2. Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution.",
]


def standard() -> list[tuple[str, list[str]]]:
    """Rule and the paragraphs of its licence's standard wording."""
    out = [
        ("MIT (named)", ["This project is licensed under the MIT License."]),
        ("MIT", [
            'Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the "Software"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions:',
            "The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software.",
            'THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT.',
        ]),
        ("ISC", ["Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies."]),
        ("BSD-2-Clause", BSD),
        ("BSD-3-Clause", [*BSD, "3. Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission."]),
        ("Apache-2.0 (header)", ['Licensed under the Apache License, Version 2.0 (the "License"); you may not use this file except in compliance with the License.']),
        ("Unlicense", ["This is free and unencumbered software released into the public domain."]),
        ("MPL-2.0", ["This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can obtain one at https://mozilla.org/MPL/2.0/."]),
        ("CC0-1.0", ["To the extent possible under law, the author has waived all copyright and related or neighboring rights to this work."]),
        ("All rights reserved", ["All rights reserved."]),
    ]
    out += [(f"Apache-{v}", [f"Licensed under the Apache License, Version {v}."]) for v in ("1.1", "2.0")]
    for short, name in GNU.items():
        for v in ("1", "2", "2.1", "3"):
            out.append((f"{short}-{v}", [f"This program is licensed under the {name}, version {v}."]))
            for what, mark, colon in (("program", ",", ":"), ("program", ";", ";"), ("library", ";", ";")):
                later = f"This {what} is free software{colon} you can redistribute it and/or modify it under the terms of the {name} as published by the Free Software Foundation{mark} either version {v} of the License, or (at your option) any later version."
                out += [(f"{short}-{v}+", [later]), (f"{short}-{v}+ (notice)", [later, HOPE.format(what)])]
    for kind in ("BY", "BY-SA", "BY-NC", "BY-ND", "BY-NC-SA", "BY-NC-ND"):
        for v, area in (("2.0", "Generic"), ("2.5", "Generic"), ("3.0", "Unported"), ("4.0", "International")):
            long = "-".join(CC[x] for x in kind.split("-"))
            out += [(f"CC-{kind}-{v}", [f"This work is licensed under CC {kind} {v}."]), (f"CC-{kind}-{v}", [f"This work is licensed under a Creative Commons {long} {v} {area} License."])]
    return out


def test_every_rule_on_its_standard_wording(spark):
    cases = standard()
    assert {name for name, _ in cases} == set(licenses.RULES)
    rows = []
    for k, (_, paragraphs) in enumerate(cases):
        rows.append((2 * k, "\n".join(paragraphs)))
        wrapped = "\n\n".join(textwrap.fill(p, 76, initial_indent=" * ", subsequent_indent=" * ") for p in paragraphs)
        rows.append((2 * k + 1, wrapped))
    got = {r.doc_id: r.licenses for r in licenses.scan(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    wrong = [(cases[i // 2][0], found) for i, found in sorted(got.items()) if found != [cases[i // 2][0]]]
    assert not wrong, f"{len(wrong)} of {len(rows)}: {wrong[:5]}"


def test_another_version_or_a_part_is_not_taken_for_a_licence(spark):
    texts = [
        "This Source Code Form is subject to the terms of the Mozilla Public License, v. 3.0.",
        "This program is free software; you can do as you like.",
        HOPE.format("program"),
        'Licensed under the Apache License, Version 3.0 (the "License"); you may not use this file except in compliance with the License.',
    ]
    out = licenses.scan(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")).collect()
    assert all(r.licenses == [] and r.verdict in ("partial", "unknown") for r in out)
