"""License scan by sentence rules, with DataFrame functions only.

Sentences are normalised (lower case, letters and digits only, single spaces) and mapped to identifiers of known licence
sentences, over line ends too; a text's identifiers, in order, are matched against ordered licence rules. Sentences that
are not known fall out, so a rule's sentences may have others between them. Both tables are parameters: what is here are
the headers and key sentences of common public licences.
"""

from __future__ import annotations

import re
from collections.abc import Mapping, Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from driftrank.llm import words as W

# Identifiers of licence sentences and their wordings.
SENTENCES = {
    "apache-2": ["Licensed under the Apache License, Version 2.0.", "Licensed under the Apache License, Version 2.0 (the \"License\");"],
    "apache-comply": ["you may not use this file except in compliance with the License."],
    "apache-copy": ["You may obtain a copy of the License at"],
    "mit": ["Released under the MIT License.", "Licensed under the MIT License.", "This project is licensed under the MIT License.", "SPDX-License-Identifier: MIT"],
    "mit-grant": ["Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions:"],
    "mit-notice": ["The above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software."],
    "gpl-3": ["This work is licensed under the GNU General Public License, version 3.", "SPDX-License-Identifier: GPL-3.0-only"],
    "gpl-3-later": ["This program is free software: you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version.", "SPDX-License-Identifier: GPL-3.0-or-later"],
    "gpl-2-later": ["This program is free software; you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation; either version 2 of the License, or (at your option) any later version.", "SPDX-License-Identifier: GPL-2.0-or-later"],
    "gpl-copy": ["You should have received a copy of the GNU General Public License along with this program."],
    "lgpl-21-later": ["This library is free software; you can redistribute it and/or modify it under the terms of the GNU Lesser General Public License as published by the Free Software Foundation; either version 2.1 of the License, or (at your option) any later version."],
    "agpl-3-later": ["This program is free software: you can redistribute it and/or modify it under the terms of the GNU Affero General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version."],
    "cc-by-nc-4": ["Licensed under CC BY-NC 4.0.", "This work is licensed under a Creative Commons Attribution-NonCommercial 4.0 International License."],
    "cc-by-4": ["Licensed under CC BY 4.0.", "This work is licensed under a Creative Commons Attribution 4.0 International License."],
    "cc-by-sa-4": ["Licensed under CC BY-SA 4.0.", "This work is licensed under a Creative Commons Attribution-ShareAlike 4.0 International License."],
    "cc-by-nd-4": ["Licensed under CC BY-ND 4.0.", "This work is licensed under a Creative Commons Attribution-NoDerivatives 4.0 International License."],
    "cc0-1": ["To the extent possible under law, the author has waived all copyright and related or neighboring rights to this work.", "SPDX-License-Identifier: CC0-1.0"],
    "bsd-grant": ["Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met:"],
    "bsd-source": ["Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer."],
    "bsd-binary": ["Redistributions in binary form must reproduce the above copyright notice, this list of conditions and the following disclaimer in the documentation and/or other materials provided with the distribution."],
    "bsd-endorse": ["Neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission."],
    "bsd-3": ["Licensed under the BSD 3-Clause License.", "SPDX-License-Identifier: BSD-3-Clause"],
    "bsd-2": ["Licensed under the BSD 2-Clause License.", "SPDX-License-Identifier: BSD-2-Clause"],
    "isc-grant": ["Permission to use, copy, modify, and/or distribute this software for any purpose with or without fee is hereby granted, provided that the above copyright notice and this permission notice appear in all copies."],
    "mpl-2": ["This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0."],
    "unlicense": ["This is free and unencumbered software released into the public domain."],
    "boost-1": ["Distributed under the Boost Software License, Version 1.0."],
    "epl-2": ["This program and the accompanying materials are made available under the terms of the Eclipse Public License 2.0"],
}
# Ordered rules over identifiers; the longer a rule, the earlier it is tried, and what it took is gone.
RULES = [
    ("BSD-3-Clause", "bsd-grant bsd-source bsd-binary bsd-endorse"),
    ("Apache-2.0", "apache-2 apache-comply apache-copy"),
    ("BSD-2-Clause", "bsd-grant bsd-source bsd-binary"),
    ("GPL-3.0-or-later", "gpl-3-later gpl-copy"),
    ("GPL-2.0-or-later", "gpl-2-later gpl-copy"),
    ("MIT", "mit-grant mit-notice"),
    ("Apache-2.0", "apache-2"),
    ("MIT", "mit"),
    ("MIT", "mit-grant"),
    ("GPL-3.0-only", "gpl-3"),
    ("GPL-3.0-or-later", "gpl-3-later"),
    ("GPL-2.0-or-later", "gpl-2-later"),
    ("LGPL-2.1-or-later", "lgpl-21-later"),
    ("AGPL-3.0-or-later", "agpl-3-later"),
    ("CC-BY-NC-4.0", "cc-by-nc-4"),
    ("CC-BY-4.0", "cc-by-4"),
    ("CC-BY-SA-4.0", "cc-by-sa-4"),
    ("CC-BY-ND-4.0", "cc-by-nd-4"),
    ("CC0-1.0", "cc0-1"),
    ("BSD-3-Clause", "bsd-3"),
    ("BSD-2-Clause", "bsd-2"),
    ("ISC", "isc-grant"),
    ("MPL-2.0", "mpl-2"),
    ("Unlicense", "unlicense"),
    ("BSL-1.0", "boost-1"),
    ("EPL-2.0", "epl-2"),
]
PERMISSIVE = {"Apache-2.0", "MIT", "BSD-3-Clause", "BSD-2-Clause", "CC-BY-4.0", "CC0-1.0", "ISC", "Unlicense", "BSL-1.0"}


def normal(sentence: str) -> str:
    return re.sub(r"[^\w]+|_", " ", sentence.lower()).strip()


def pieces(text: Column) -> Column:
    """A text normalised piece by piece, a line feed around each: cut after . ! ? : ; before white space, and at line ends."""
    cut = F.regexp_replace(F.lower(F.coalesce(text, F.lit(""))), r"(?<=[.!?:;])[ \t]+|[\r\n]+", "\n")
    return F.concat(F.lit("\n"), F.regexp_replace(cut, r"[^\p{L}\p{N}\n]+", " "), F.lit("\n"))


def identifiers(text: Column, sentences: Mapping[str, Sequence[str]] = SENTENCES) -> Column:
    """Identifiers of the known sentences of a text, in order, a blank around each ('' without any).

    A known sentence is any run of whole pieces that reads like it: its own stops and wrapped lines may cut it.
    """
    flat = {normal(s): k for k, v in sentences.items() for s in v}
    known = F.create_map(*(F.lit(x) for pair in flat.items() for x in pair))
    either = "|".join(s.replace(" ", r"[ \n]+") for s in sorted(flat, key=len, reverse=True))
    runs = F.regexp_extract_all(pieces(text), F.lit(rf"(?<=\n) ?(?:{either})(?= ?\n)"), F.lit(0))
    found = F.transform(runs, lambda s: F.element_at(known, F.trim(F.regexp_replace(s, r"[ \n]+", " "))))
    # two blanks between, so that neighbours do not share one
    return F.when(F.size(runs) > 0, F.concat(F.lit(" "), F.array_join(found, "  "), F.lit(" "))).otherwise(F.lit(""))


def scan(frame: DataFrame, sentences: Mapping[str, Sequence[str]] = SENTENCES, rules: Sequence[tuple[str, str]] = RULES, permissive=PERMISSIVE) -> DataFrame:
    """``frame`` with sentence_ids (string), licenses (distinct names by rule order) and permissive (null without any).

    A column of ``frame`` that has one of these names is replaced; rows and other columns stay as they are. Null and
    empty texts have no licence; repeated rows repeat their result. A rule longer than one sentence takes its sentences,
    so shorter rules do not find them again; rules are tried in the order given.
    """
    made = ("sentence_ids", "licenses", "permissive")
    out = frame.drop(*made).withColumn(made[0], identifiers(F.col("text"), sentences))
    rest, found = F.col(made[0]), []
    for name, rule in rules:
        ids = rule.split()
        if set(ids) - set(sentences):
            raise ValueError(f"rule of {name} has an unknown sentence")
        text = f" {'  '.join(ids)} "
        found.append(F.when(F.contains(rest, F.lit(text)), F.lit(name)))
        if len(ids) > 1:
            rest = F.replace(rest, F.lit(text), F.lit(" - "))
    out = out.withColumn(made[1], F.array_distinct(F.array_compact(F.array(*found))))
    bad = [n for n in sorted({n for n, _ in rules}) if n not in permissive]
    return out.withColumn(made[2], F.when(F.size(made[1]) > 0, ~F.arrays_overlap(made[1], F.array(*map(F.lit, bad)) if bad else F.array().cast("array<string>"))))


def op10_licenses(spark, sf_dir) -> DataFrame:
    return scan(W.docs(spark, sf_dir).select("doc_id", "text")).drop("text").withColumn("sentence_ids", F.trim(F.replace("sentence_ids", F.lit("  "), F.lit(" "))))
