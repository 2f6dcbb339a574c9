"""Exact deduplication, sharding, mixing and licence scans on odd inputs."""

from collections import Counter, defaultdict

import pytest
from pyspark.sql import functions as F

from beamrank.llm.common import connected_components
from beamrank.llm.exact_dedup import exact_dedup, exact_groups
from beamrank.llm.licenses import SENTENCES, STEMS, scan_licenses
from beamrank.llm.mixing import mix, mix_counts, source_targets
from beamrank.llm.sharding import histogram_splitters, shard_documents, write_shards

SCHEMA = "doc_id bigint, text string, source string, size string, shard string, text_sha256 string"


def odd(spark):
    rows = [(1, "a"), (2, "a"), (2, "a"), (None, "a"), (None, "b"), (None, "b"), (3, None), (4, ""), (5, "x " * 50_000)]
    rows += [(10 + i, "hot text") for i in range(300)]
    return spark.createDataFrame([(d, t, None if i % 3 else "s", "q", "q", "q") for i, (d, t) in enumerate(rows)], SCHEMA)


def test_exact_groups(spark):
    got = exact_groups(odd(spark), counters=10).collect()
    sizes = Counter(r["text_sha256"] for r in got)
    assert len(got) == 309 and all(r["group_size"] == sizes[r["text_sha256"]] for r in got)
    kept = [r for r in got if r["kept"]]
    assert len(kept) == len(sizes) and sorted(r["doc_id"] for r in kept if r["doc_id"] is not None) == [2, 4, 5, 309]
    assert all(r["doc_id"] == r["keep_id"] for r in kept)


@pytest.mark.parametrize("broadcast_rows", [1_000_000, 0])
def test_exact_dedup_keeps_one_row_of_each_text(spark, broadcast_rows):
    got = exact_dedup(odd(spark), counters=10, broadcast_rows=broadcast_rows)
    assert got.columns == odd(spark).columns
    assert sorted((r["doc_id"] or 0, r["text"] or "") for r in got.collect()) == [(0, "b"), (2, "a"), (4, ""), (5, "x " * 50_000), (309, "hot text")]


def test_shards_of_odd_rows(spark):
    got = shard_documents(odd(spark), shards=8).collect()
    slots = defaultdict(list)
    for r in got:
        slots[r["shard"]].append(r["slot"])
    assert len(got) == 309 and all(sorted(s) == list(range(len(s))) for s in slots.values())
    big = next(r for r in got if r["doc_id"] == 5)
    others = [sum(r["size"] for r in got if r["shard"] == s and r is not big) for s in range(8)]
    assert sum(others) + big["size"] == sum(r["size"] for r in got)


@pytest.mark.parametrize("probes", [2, 7, 64])
def test_splitters_are_the_nearest_boundaries(spark, probes):
    keys = [(i * i * 7919 + i) % (1 << 40) for i in range(200)] + [12345] * 20
    rows = spark.createDataFrame([(k, 1 + k % 11) for k in keys], "key bigint, size bigint")
    got = histogram_splitters(rows, 6, probes=probes)
    total, below, cuts = sum(1 + k % 11 for k in keys), 0, []
    for k in sorted(set(keys)):
        cuts.append((k, below))
        below += (1 + k % 11) * keys.count(k)
    cuts.append((1 << 60, below))
    for j, s in enumerate(got, 1):
        under = sum(1 + k % 11 for k in keys if k < s)
        assert abs(6 * under - total * j) == min(abs(6 * b - total * j) for _, b in cuts)


def test_written_shards(spark, tmp_path):
    docs = odd(spark).drop("shard")
    write_shards(docs, str(tmp_path / "s"), shards=4)
    back = spark.read.parquet(str(tmp_path / "s"))
    assert Counter(r["doc_id"] for r in back.collect()) == Counter(r["doc_id"] for r in docs.collect())


def test_targets_fill_up_to_the_limit(spark):
    sizes = spark.createDataFrame([("a", 10), ("b", 100), ("c", 1000), (None, 3), ("z", 0)], "source string, size bigint")
    got = {r["source"]: r["target"] for r in source_targets(sizes).collect()}
    size, weight = {"a": 10, "b": 100, "c": 1000, "z": 0, None: 3}, {"a": 5, "b": 2, "c": 1, "z": 5, None: 2}
    want, free = dict.fromkeys(size, 0.0), set(size)
    left = float(sum(size.values()))
    while left > 1e-9 and free:
        share = {s: left * weight[s] / sum(weight[f] for f in free) for s in free}
        left = 0.0
        for s, x in share.items():
            want[s] += x
            if want[s] >= 3 * size[s]:
                left += want[s] - 3 * size[s]
                want[s] = 3.0 * size[s]
                free.discard(s)
    assert got == pytest.approx(want)


def test_mixture(spark):
    docs = odd(spark)
    counts = mix_counts(docs).collect()
    assert all(0 <= r["copies"] <= 3 for r in counts)
    assert mix(docs).columns == docs.columns
    assert mix(docs).count() == sum(r["copies"] for r in counts)


def test_licenses(spark):
    mit = "Permission is hereby granted, free of charge, to any person obtaining a copy of this software and associated documentation files (the \"Software\"), to deal in the Software without restriction, including without limitation the rights to use, copy, modify, merge, publish, distribute, sublicense, and/or sell copies of the Software, and to permit persons to whom the Software is furnished to do so, subject to the following conditions"
    rows = [
        (1, f"Copyright me.\n{mit}:\n\nThe above copyright notice and this permission notice shall be included in all copies or substantial portions of the Software.\nSomething else. THE SOFTWARE IS PROVIDED \"AS IS\", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY, FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT."),
        (2, "Released under the MIT License. Words. released UNDER the MIT license!"),
        (3, "It was released under the MIT License."),
        (4, None),
        (5, ""),
        (2, "Licensed under CC BY-NC 4.0."),
    ]
    docs = spark.createDataFrame(rows, "doc_id bigint, text string").withColumn("license", F.lit(1))
    got = sorted(map(tuple, scan_licenses(docs).collect()))
    assert got == [(1, "MIT", "mit-text", 1, 1), (2, "CC-BY-NC-4.0", "cc-by-nc-notice", 1, 0), (2, "MIT", "mit-notice", 2, 0)]
    assert all(any(stem in s for stem in STEMS) for s in SENTENCES.values())


MIT = """Permission is hereby granted, free of charge, to any person obtaining a copy
of this software and associated documentation files (the "Software"), to deal
in the Software without restriction, including without limitation the rights
to use, copy, modify, merge, publish, distribute, sublicense, and/or sell
copies of the Software, and to permit persons to whom the Software is
furnished to do so, subject to the following conditions:

The above copyright notice and this permission notice shall be included in all
copies or substantial portions of the Software.

THE SOFTWARE IS PROVIDED "AS IS", WITHOUT WARRANTY OF ANY KIND, EXPRESS OR
IMPLIED, INCLUDING BUT NOT LIMITED TO THE WARRANTIES OF MERCHANTABILITY,
FITNESS FOR A PARTICULAR PURPOSE AND NONINFRINGEMENT. IN NO EVENT SHALL THE
AUTHORS OR COPYRIGHT HOLDERS BE LIABLE FOR ANY CLAIM, DAMAGES OR OTHER
LIABILITY.
"""
APACHE = """Licensed under the Apache License, Version 2.0 (the "License");
you may not use this file except in compliance with the License.
You may obtain a copy of the License at

    http://www.apache.org/licenses/LICENSE-2.0

Unless required by applicable law or agreed to in writing, software
distributed under the License is distributed on an "AS IS" BASIS,
WITHOUT WARRANTIES OR CONDITIONS OF ANY KIND, either express or implied.
See the License for the specific language governing permissions and
limitations under the License.
"""
GPL = """This program is free software: you can redistribute it and/or modify
it under the terms of the GNU General Public License as published by
the Free Software Foundation, either version 3 of the License, or
(at your option) any later version.

This program is distributed in the hope that it will be useful,
but WITHOUT ANY WARRANTY; without even the implied warranty of
MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE.  See the
GNU General Public License for more details.
"""
BSD = """Redistribution and use in source and binary forms, with or without
modification, are permitted provided that the following conditions are met:

1. Redistributions of source code must retain the above copyright notice, this
   list of conditions and the following disclaimer.

2. Redistributions in binary form must reproduce the above copyright notice,
   this list of conditions and the following disclaimer in the documentation
   and/or other materials provided with the distribution.

3. Neither the name of the copyright holder nor the names of its
   contributors may be used to endorse or promote products derived from
   this software without specific prior written permission.
"""
ISC = """Permission to use, copy, modify, and/or distribute this software for any
purpose with or without fee is hereby granted, provided that the above
copyright notice and this permission notice appear in all copies.
"""


@pytest.mark.parametrize(
    "form",
    [
        lambda t: t,
        lambda t: t.replace("\n", "\r\n"),
        lambda t: " ".join(t.split()),
        lambda t: "/*\n" + "".join(f" * {line}\n" for line in t.splitlines()) + " */",
        lambda t: "\n".join(t.split()),
    ],
    ids=["wrapped", "crlf", "one line", "comment", "a word a line"],
)
def test_licenses_in_their_usual_forms(spark, form):
    texts = [MIT, APACHE, GPL, BSD, ISC, BSD.split("3. ")[0], MIT + "\n" + MIT]
    docs = spark.createDataFrame([(i, form(t)) for i, t in enumerate(texts)], "doc_id bigint, text string")
    got = sorted((r["doc_id"], r["rule"], r["matches"]) for r in scan_licenses(docs).collect())
    assert got == [(0, "mit-text", 1), (1, "apache-header", 1), (2, "gpl-3-header", 1), (3, "bsd-3-text", 1), (4, "isc-text", 1), (5, "bsd-2-text", 1), (6, "mit-text", 2)]


def test_licenses_start_and_end_with_sentences(spark):
    rows = [
        (1, "First words here.\nAnother. Licensed under\nthe MIT License.\n"),
        (2, "Not licensed under\nthe MIT License."),
        (3, "Licensed under\nthe MIT License or another."),
        (4, "Licensed. Under\nthe MIT License."),
        (5, "Licensed under the Apache License, Version 2.0\n(the \"License\");"),
        (6, "It is ours; licensed under the MIT license: see below."),
    ]
    got = sorted(map(tuple, scan_licenses(spark.createDataFrame(rows, "doc_id bigint, text string")).collect()))
    assert got == [(1, "MIT", "mit-notice-2", 1, 2), (6, "MIT", "mit-notice-2", 1, 0)]


def test_components(spark):
    edges = [(i, i + 1) for i in range(1, 40)] + [(100, 200), (150, 200), (7, 7), (300, 1)]
    got = connected_components(spark.createDataFrame([(v,) for v in [*range(1, 42), 100, 150, 200, 300]], "v bigint"), spark.createDataFrame(edges, "a bigint, b bigint"))
    roots = {r["v"]: r["root"] for r in got.collect()}
    assert all(roots[v] == 1 for v in [*range(1, 41), 300]) and roots[41] == 41 and {roots[v] for v in (100, 150, 200)} == {100}


def test_empty(spark):
    none = odd(spark).where(F.lit(False))
    for f in (exact_groups, exact_dedup, shard_documents, mix_counts, mix, scan_licenses):
        assert f(none).collect() == []


ODD_NAMES = ["__own", "__id", "__rank", "__copies", "__seed", "a.b", "row", "own", "id", "h", "kept", "rate", "copies", "shard", "slot", "digest"]


def test_columns_of_any_name_pass_through(spark, tmp_path):
    from beamrank.llm.near_dedup import near_dedup
    from beamrank.llm.quality import keep_good

    rows = [(i, t, "s", *(f"{n}{i}" for n in ODD_NAMES)) for i, t in enumerate(["one two three", "one two three", "x y z", None, "x y z w"])]
    rows.append(rows[0])
    docs = spark.createDataFrame(rows, ["doc_id", "text", "source", *ODD_NAMES])
    labels = spark.createDataFrame([(0, 1)], "doc_id bigint, quality int")
    for stage in (exact_dedup, near_dedup, mix, lambda d: keep_good(d, labels)):
        got = stage(docs)
        assert got.columns == docs.columns
        assert {tuple(r) for r in got.collect()} <= set(rows) and got.count() > 0
    assert sorted(r["doc_id"] for r in exact_dedup(docs).collect()) == [1, 2, 3, 4]
    write_shards(docs, f"{tmp_path}/out", 2)
    back = spark.read.parquet(f"{tmp_path}/out")
    assert back.count() == 6 and set(docs.columns) < set(back.columns) and {"shard_", "slot_"} <= set(back.columns)


FULL = {
    "bsd-3-text": "Redistribution and use in source and binary forms, with or without modification, are permitted provided that the following conditions are met: 1. Redistributions of source code must retain the above copyright notice, this list of conditions and the following disclaimer.",
    "gpl-2-header": "This program is free software; you can redistribute it and/or modify it under the terms of the GNU General Public License as published by the Free Software Foundation; either version 2 of the License, or (at your option) any later version.\n\nThis program is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE. See the GNU General Public License for more details.",
    "lgpl-2-1-header": "This library is free software; you can redistribute it and/or modify it under the terms of the GNU Lesser General Public License as published by the Free Software Foundation; either version 2.1 of the License, or (at your option) any later version.\n\nThis library is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE. See the GNU Lesser General Public License for more details.",
    "agpl-3-header": "This program is free software: you can redistribute it and/or modify it under the terms of the GNU Affero General Public License as published by the Free Software Foundation, either version 3 of the License, or (at your option) any later version.\n\nThis program is distributed in the hope that it will be useful, but WITHOUT ANY WARRANTY; without even the implied warranty of MERCHANTABILITY or FITNESS FOR A PARTICULAR PURPOSE. See the GNU Affero General Public License for more details.",
    "mpl-2-header": "This Source Code Form is subject to the terms of the Mozilla Public License, v. 2.0. If a copy of the MPL was not distributed with this file, You can obtain one at http://mozilla.org/MPL/2.0/.",
    "epl-2-header": "This program and the accompanying materials are made available under the terms of the Eclipse Public License 2.0 which is available at https://www.eclipse.org/legal/epl-2.0/",
    "zlib-text": "This software is provided 'as-is', without any express or implied warranty. In no event will the authors be held liable.\n\nPermission is granted to anyone to use this software for any purpose, including commercial applications, and to alter it and redistribute it freely, subject to the following restrictions:",
    "unlicense-text": "This is free and unencumbered software released into the public domain.\n\nAnyone is free to copy, modify, publish, use, compile, sell, or distribute this software, either in source code form or as a compiled binary, for any purpose, commercial or non-commercial, and by any means.",
    "boost-header": "Distributed under the Boost Software License, Version 1.0.",
    "epl-2.0-notice-3": "This software is licensed under the Eclipse Public License 2.0.",
    "apache-2.0-identifier": "SPDX-License-Identifier: Apache-2.0",
    "bsd-3-clause-notice-4": "This project is licensed under the BSD 3-Clause License.",
}


def test_whole_texts_are_found_once(spark):
    import textwrap

    rows, want = [], []
    for mark, width, rule in [(m, w, r) for m in ("", "# ", " * ", "// ", "-- ") for w in (40, 78, 10_000) for r in list(FULL)[1:]]:
        lines = [mark + line for part in FULL[rule].split("\n\n") for line in [*textwrap.wrap(part, width, break_long_words=False, break_on_hyphens=False), ""]]
        want.append((len(rows), rule, 1))
        rows.append((len(rows), "\n".join(["Some words before.", *lines, "And words after."])))
    got = sorted((r["doc_id"], r["rule"], r["matches"]) for r in scan_licenses(spark.createDataFrame(rows, "doc_id bigint, text string")).collect())
    assert got == want


def test_rules_take_what_they_match(spark):
    three, two = "<a> <b> <c>", "<a> <b>"
    table, rules = {1: "license a", 2: "license b", 3: "license c"}, [("two", "T", [1, 2]), ("three", "H", [1, 2, 3]), ("last", "L", [3])]
    say = lambda t: t.replace("<a>", "License a.").replace("<b>", "License b.").replace("<c>", "License c.")
    rows = [(1, say(three)), (2, say(two)), (3, say(f"{two} {three} {two}")), (4, say("<c>")), (5, say("<b> <a>"))]
    got = sorted((r["doc_id"], r["rule"], r["matches"]) for r in scan_licenses(spark.createDataFrame(rows, "doc_id bigint, text string"), table, rules).collect())
    assert got == [(1, "three", 1), (2, "two", 1), (3, "three", 1), (3, "two", 2), (4, "last", 1)]


def test_every_known_sentence_has_a_stem_and_licences_are_many():
    import re

    from beamrank.llm.licenses import RULES

    assert all(re.search("|".join(STEMS), s) for s in SENTENCES.values())
    assert len(set(SENTENCES.values())) == len(SENTENCES) and len({r[1] for r in RULES}) >= 40
    assert {i for r in RULES for i in r[2]} == set(SENTENCES)


def test_groups_stay_whole_unless_larger_than_a_shard(spark):
    rows = [(i, f"text {i // 7} " * (1 + i % 3 * 0 + i // 7 % 5)) for i in range(700)] + [(1000 + i, "hot" * 20) for i in range(400)]
    got = shard_documents(spark.createDataFrame(rows, "doc_id bigint, text string"), 8).collect()
    texts, where, sizes = dict(rows), defaultdict(set), Counter()
    for r in got:
        where[texts[r["doc_id"]]].add(r["shard"])
        sizes[r["shard"]] += r["size"]
    share = sum(sizes.values()) / 8
    assert all(len(s) == 1 for t, s in where.items() if t != "hot" * 20) and len(where["hot" * 20]) > 1
    assert max(sizes.values()) - min(sizes.values()) < share / 2


def test_taken_words_come_near_targets(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    taken, target, size = Counter(), {}, Counter()
    for r in mix_counts(docs).collect():
        taken[r["source"]] += r["copies"] * r["size"]
        size[r["source"]] += r["size"]
        target[r["source"]] = r["target"]
        assert 0 <= r["copies"] <= 3
    assert abs(sum(target.values()) - sum(size.values())) < 1e-6 * sum(size.values())
    assert all(t <= 3 * size[s] + 1e-6 for s, t in target.items())
    assert all(abs(taken[s] - t) < 0.1 * t + 1 for s, t in target.items()), {s: (taken[s], t) for s, t in target.items()}


def test_repeated_and_long_rows_of_licences(spark):
    text = "word " * 400_000 + "\nLicensed under the MIT License.\n" + "word " * 400_000
    rows = [(1, text), (2, "Licensed under the MIT License."), (2, "Licensed under the MIT License.")]
    got = sorted(map(tuple, scan_licenses(spark.createDataFrame(rows, "doc_id bigint, text string")).collect()))
    assert got == [(1, "MIT", "mit-notice-2", 1, 1), (2, "MIT", "mit-notice-2", 1, 0), (2, "MIT", "mit-notice-2", 1, 0)]


def test_slots_are_gapless_where_many_rows_are_equal(spark):
    from beamrank.llm.sharding import histogram_shards

    rows = [(i, (7 << 20) + i % 1000 if i < 4000 else i * 7919 % (1 << 40), 16) for i in range(6000)]
    df = spark.createDataFrame(rows, "doc_id bigint, key bigint, size bigint")
    for piece_rows in (100, 10**6):
        by, keys = defaultdict(list), defaultdict(list)
        for r in histogram_shards(df, 3, piece_rows=piece_rows).collect():
            by[r["shard"]].append(r["slot"])
            keys[r["shard"]].append((r["slot"], r["key"], r["doc_id"]))
        assert all(sorted(x) == list(range(len(x))) for x in by.values()) and sum(map(len, by.values())) == 6000
        assert all([k[1:] for k in sorted(x)] == sorted(k[1:] for k in x) for x in keys.values())
