"""Licence scans by known sentences in known orders.

A text is cut into pieces at line ends and after full stops, and each is normalised to lower-case
words and figures, so that comment marks fall away. A known sentence is found where it starts with a
piece and ends with one, the same or a later one, so that hard-wrapped notices match; a full stop within
breaks it, but for that of "v." before a version. Within a piece, a colon, a semicolon or the end of an
address may part sentences too. What is found, in order, is a sequence of identifiers, in which rules look for theirs. Rules are ordered, the
longest sequence first, and take what they match: a text of three clauses is not also one of two. All
of it is one narrow projection of SQL functions: nothing is shuffled, and texts without any of a few word
stems, one of which every known sentence has, are passed over by one search.

Result: a row for each document and rule that matches, with the licence, how often the rule matches
and the index of the piece where it first does. Edge cases: null and empty texts match nothing;
repeated rows match alike; sentences between those of a rule do not break it unless they are known
ones; an empty table gives an empty result; extra columns are not read.
"""

from __future__ import annotations

import re

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from beamrank.llm.common import text_or_empty

# Sentences of public licence notices, normalised, and the rules over them.
SENTENCES = {
    1: "released under the mit license",
    2: "licensed under the mit license",
    3: "permission is hereby granted free of charge to any person obtaining a copy of this software and associated documentation files the software to deal in the software without restriction including without limitation the rights to use copy modify merge publish distribute sublicense and or sell copies of the software and to permit persons to whom the software is furnished to do so subject to the following conditions",
    4: "the above copyright notice and this permission notice shall be included in all copies or substantial portions of the software",
    5: "the software is provided as is without warranty of any kind express or implied including but not limited to the warranties of merchantability fitness for a particular purpose and noninfringement",
    10: "licensed under the apache license version 2 0",
    11: "licensed under the apache license version 2 0 the license",
    12: "you may not use this file except in compliance with the license",
    13: "you may obtain a copy of the license at http www apache org licenses license 2 0",
    14: "unless required by applicable law or agreed to in writing software distributed under the license is distributed on an as is basis without warranties or conditions of any kind either express or implied",
    15: "see the license for the specific language governing permissions and limitations under the license",
    20: "this work is licensed under the gnu general public license version 3",
    21: "this program is free software you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation either version 3 of the license or at your option any later version",
    22: "this program is distributed in the hope that it will be useful but without any warranty without even the implied warranty of merchantability or fitness for a particular purpose",
    23: "see the gnu general public license for more details",
    30: "licensed under cc by nc 4 0",
    31: "licensed under cc by 4 0",
    32: "licensed under cc by sa 4 0",
    33: "this work is licensed under a creative commons attribution 4 0 international license",
    40: "redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met",
    41: "redistributions of source code must retain the above copyright notice this list of conditions and the following disclaimer",
    42: "redistributions in binary form must reproduce the above copyright notice this list of conditions and the following disclaimer in the documentation and or other materials provided with the distribution",
    43: "neither the name of the copyright holder nor the names of its contributors may be used to endorse or promote products derived from this software without specific prior written permission",
    50: "permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted provided that the above copyright notice and this permission notice appear in all copies",
    51: "permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted",
    60: "this program is free software you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation either version 2 of the license or at your option any later version",
    61: "this library is free software you can redistribute it and or modify it under the terms of the gnu lesser general public license as published by the free software foundation either version 2 1 of the license or at your option any later version",
    62: "this library is distributed in the hope that it will be useful but without any warranty without even the implied warranty of merchantability or fitness for a particular purpose",
    63: "see the gnu lesser general public license for more details",
    64: "this program is free software you can redistribute it and or modify it under the terms of the gnu lesser general public license as published by the free software foundation either version 3 of the license or at your option any later version",
    65: "this program is free software you can redistribute it and or modify it under the terms of the gnu affero general public license as published by the free software foundation either version 3 of the license or at your option any later version",
    66: "see the gnu affero general public license for more details",
    70: "this source code form is subject to the terms of the mozilla public license v 2 0",
    71: "if a copy of the mpl was not distributed with this file you can obtain one at http mozilla org mpl 2 0",
    72: "if a copy of the mpl was not distributed with this file you can obtain one at https mozilla org mpl 2 0",
    73: "this program and the accompanying materials are made available under the terms of the eclipse public license 2 0 which is available at https www eclipse org legal epl 2 0",
    74: "this software is provided as is without any express or implied warranty",
    75: "permission is granted to anyone to use this software for any purpose including commercial applications and to alter it and redistribute it freely subject to the following restrictions",
    76: "this is free and unencumbered software released into the public domain",
    77: "anyone is free to copy modify publish use compile sell or distribute this software either in source code form or as a compiled binary for any purpose commercial or non commercial and by any means",
    78: "the person who associated a work with this deed has dedicated the work to the public domain by waiving all of his or her rights to the work worldwide under copyright law including all related and neighboring rights to the extent allowed by law",
    79: "distributed under the boost software license version 1 0",
    80: "everyone is permitted to copy and distribute verbatim or modified copies of this license document and changing it is allowed as long as the name is changed",
    81: "permission to use copy modify and distribute this software and its documentation for any purpose without fee and without a written agreement is hereby granted provided that the above copyright notice and this paragraph and the following two paragraphs appear in all copies",
    82: "licensed under the educational community license version 2 0",
}
# What licences are called in one-sentence notices, and public short identifiers.
NAMES = {
    "AGPL-3.0-only": "gnu affero general public license version 3", "Apache-1.1": "apache license version 1 1", "Artistic-2.0": "artistic license 2 0",
    "BSD-2-Clause": "bsd 2 clause license", "BSD-3-Clause": "bsd 3 clause license", "BSL-1.0": "boost software license 1 0", "CC0-1.0": "cc0 1 0 universal public domain dedication",
    "CDDL-1.0": "common development and distribution license 1 0", "EPL-1.0": "eclipse public license 1 0", "EPL-2.0": "eclipse public license 2 0",
    "EUPL-1.2": "european union public licence 1 2", "GPL-2.0-only": "gnu general public license version 2", "ISC": "isc license", "LGPL-2.1-only": "gnu lesser general public license version 2 1",
    "LGPL-3.0-only": "gnu lesser general public license version 3", "MPL-1.1": "mozilla public license 1 1", "MPL-2.0": "mozilla public license 2 0", "MS-PL": "microsoft public license",
    "ODbL-1.0": "open database license 1 0", "OFL-1.1": "sil open font license version 1 1", "PostgreSQL": "postgresql license", "PSF-2.0": "python software foundation license version 2",
    "UPL-1.0": "universal permissive license 1 0", "Zlib": "zlib license", "CC-BY-ND-4.0": "creative commons attribution noderivatives 4 0 international license",
    "CC-BY-SA-4.0": "creative commons attribution sharealike 4 0 international license", "CC-BY-NC-4.0": "creative commons attribution noncommercial 4 0 international license",
    "CC-BY-NC-SA-4.0": "creative commons attribution noncommercial sharealike 4 0 international license",
}
SHORT = (
    "0BSD AFL-3.0 AGPL-3.0-only AGPL-3.0-or-later Apache-1.1 Apache-2.0 Artistic-2.0 BSD-2-Clause BSD-3-Clause BSL-1.0 BlueOak-1.0.0 CC-BY-4.0 CC-BY-NC-4.0 CC-BY-ND-4.0 CC-BY-SA-4.0 "
    "CC0-1.0 CDDL-1.0 ECL-2.0 EPL-1.0 EPL-2.0 EUPL-1.2 GPL-2.0-only GPL-2.0-or-later GPL-3.0-only GPL-3.0-or-later ISC LGPL-2.1-only LGPL-2.1-or-later LGPL-3.0-only LGPL-3.0-or-later "
    "MIT MIT-0 MPL-1.1 MPL-2.0 MS-PL NCSA ODbL-1.0 OFL-1.1 OSL-3.0 PostgreSQL PSF-2.0 Python-2.0 UPL-1.0 Unlicense WTFPL X11 Zlib"
).split()
NOTICES = ("licensed under the {}", "released under the {}", "this work is licensed under the {}", "this software is licensed under the {}", "this project is licensed under the {}", "distributed under the terms of the {}")
RULES = [
    ("mit-notice", "MIT", [1]),
    ("mit-notice-2", "MIT", [2]),
    ("mit-text", "MIT", [3, 4, 5]),
    ("apache-notice", "Apache-2.0", [10]),
    ("apache-header", "Apache-2.0", [11, 12, 13, 14, 15]),
    ("gpl-3-notice", "GPL-3.0-only", [20]),
    ("gpl-3-header", "GPL-3.0-or-later", [21, 22, 23]),
    ("gpl-2-header", "GPL-2.0-or-later", [60, 22, 23]),
    ("lgpl-2-1-header", "LGPL-2.1-or-later", [61, 62, 63]),
    ("lgpl-3-header", "LGPL-3.0-or-later", [64, 22, 63]),
    ("agpl-3-header", "AGPL-3.0-or-later", [65, 22, 66]),
    ("cc-by-nc-notice", "CC-BY-NC-4.0", [30]),
    ("cc-by-notice", "CC-BY-4.0", [31]),
    ("cc-by-sa-notice", "CC-BY-SA-4.0", [32]),
    ("cc-by-text", "CC-BY-4.0", [33]),
    ("bsd-3-text", "BSD-3-Clause", [40, 41, 42, 43]),
    ("bsd-2-text", "BSD-2-Clause", [40, 41, 42]),
    ("isc-text", "ISC", [50]),
    ("0bsd-text", "0BSD", [51]),
    ("mpl-2-header", "MPL-2.0", [70, 71]),
    ("mpl-2-header-https", "MPL-2.0", [70, 72]),
    ("epl-2-header", "EPL-2.0", [73]),
    ("zlib-text", "Zlib", [74, 75]),
    ("unlicense-text", "Unlicense", [76, 77]),
    ("cc0-deed", "CC0-1.0", [78]),
    ("boost-header", "BSL-1.0", [79]),
    ("wtfpl-text", "WTFPL", [80]),
    ("postgresql-text", "PostgreSQL", [81]),
    ("ecl-2-header", "ECL-2.0", [82]),
]


def _plain(text: str) -> str:
    return " ".join(re.findall("[a-z0-9]+", text.lower()))


def _made(sentence: str, rule: str, license_id: str) -> None:
    """A rule of one more sentence, unless it is known already."""
    if sentence not in SENTENCES.values():
        SENTENCES[max(SENTENCES) + 1] = sentence
        RULES.append((rule, license_id, [max(SENTENCES)]))


for _id, _name in NAMES.items():
    for _n, _form in enumerate(NOTICES):
        _made(_form.format(_name), f"{_id.lower()}-notice-{_n}", _id)
for _id in SHORT:
    _made(f"spdx license identifier {_plain(_id)}", f"{_id.lower()}-identifier", _id)

#: Every known sentence has one of these.
STEMS = ["licens", "licenc", "permission", "copyright", "warrant", "redistribut", "public domain", "permitted to copy", "anyone is free", "mpl was not", "distributed under"]

BREAK = r"\n+|(?<=[.!?])[ \t\r\f]+"
ADDRESS = r"(https?://[^ \t\r\f]+)[ \t\r\f]+"
PART = r"[:;]+(?:[ \t\r\f]+|$)"


def sentences(text: Column) -> Column:
    """Pieces: line ends, and white space after a full stop or the like, end one."""
    return F.split(text, BREAK)


def marked(text: Column) -> Column:
    """Normalised words, with <i> before each part of piece i and a dot after a part that a full stop or the like ends."""

    def part(x: Column, i: Column) -> Column:
        words = F.trim(F.regexp_replace(x, "[^a-z0-9]+", " "))
        stop = F.when(x.rlike("[.!?][^a-z0-9]*$"), ".").otherwise("")
        return F.when(words == "", "").otherwise(F.concat(F.lit("<"), i.cast("string"), F.lit(">"), words, stop))

    lines = F.transform(sentences(text), lambda s: F.regexp_replace(F.lower(s), ADDRESS, "$1; "))
    parts = F.transform(lines, lambda s, i: F.transform(F.split(s, PART), lambda x: part(x, i)))
    return F.array_join(F.flatten(parts), "")


def known_sentence(table: dict[int, str]) -> str:
    """A pattern of known sentences between marks, the longest first."""
    texts = sorted(table.values(), key=len, reverse=True)
    joined = [re.sub(" ", r"(?: |<\\d+>)", re.sub(r"\bv ", r"v[.]? ", s)) for s in texts]
    return r"<\d+>(?:" + "|".join(joined) + r")(?=[.<]|$)"


def scan_licenses(docs: DataFrame, table: dict[int, str] | None = None, rules: list[tuple[str, str, list[int]]] | None = None) -> DataFrame:
    """doc_id, license, rule, matches, first_sentence."""
    table, rules = table or SENTENCES, rules or RULES
    known = F.map_from_arrays(F.array(*[F.lit(s) for s in table.values()]), F.array(*[F.lit(k) for k in table]))
    likely = text_or_empty().rlike("(?i)" + "|".join(stem.replace(" ", "[^a-z0-9]+") for stem in STEMS))
    at = lambda x: F.regexp_extract(x, "^<([0-9]+)>", 1)
    words = lambda x: F.trim(F.regexp_replace(x, "[.]?<[0-9]+>", " "))
    found = F.regexp_extract_all(marked(F.col("text")), F.lit(known_sentence(table)), F.lit(0))
    # each as <identifier@piece>, in order
    tokens = F.transform(found, lambda x: F.concat(F.lit("<"), F.element_at(known, words(x)).cast("string"), F.lit("@"), at(x), F.lit(">")))
    seen = docs.where(likely).select("doc_id", F.array_join(tokens, "").alias("sequence")).where("sequence <> ''")
    ordered = sorted(rules, key=lambda r: -len(r[2]))
    either = "|".join("".join(f"<{i}@[0-9]+>" for i in ids) for _, _, ids in ordered)
    place = F.map_from_arrays(F.array(*[F.lit("".join(f"<{i}>" for i in ids)) for _, _, ids in ordered]), F.array(*[F.lit(n) for n in range(len(ordered))]))
    spans = F.regexp_extract_all("sequence", F.lit(either), F.lit(0))
    hit = F.transform(spans, lambda x: F.struct(F.element_at(place, F.regexp_replace(x, "@[0-9]+", "")).alias("n"), F.regexp_extract(x, "@([0-9]+)", 1).cast("int").alias("at")))
    taken = seen.select("doc_id", hit.alias("hit")).select("doc_id", "hit", F.explode(F.array_distinct("hit.n")).alias("n"))
    own = F.filter("hit", lambda h: h["n"] == F.col("n"))
    name = lambda k: F.element_at(F.array(*[F.lit(r[k]) for r in ordered]), F.col("n") + 1)
    return taken.select(
        "doc_id",
        name(1).alias("license"),
        name(0).alias("rule"),
        F.size(own).cast("bigint").alias("matches"),
        F.array_min(F.transform(own, lambda h: h["at"])).alias("first_sentence"),
    )
