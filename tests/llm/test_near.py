"""Near-duplicate classes against comparison of all pairs."""

import random
from collections import Counter
from itertools import combinations

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from beamrank.llm.near_dedup import bag_minhash, near_classes, near_dedup, shingles
from beamrank.llm.textkit import mix64


def bag(text, k=5):
    words = (text or "").replace("\n", " ").split(" ")
    words = [w for w in words if w]
    if not words:
        return Counter()
    return Counter(tuple(words[i : i + k]) for i in range(max(1, len(words) - k + 1)))


def near(a, b):
    low, high = sum((a & b).values()), sum((a | b).values())
    return bool(high) and low / high >= 0.8


def brute(rows):
    root = list(range(len(rows)))
    bags = [bag(t) for _, t in rows]
    for i, j in combinations(range(len(rows)), 2):
        if (rows[i][1] or "") == (rows[j][1] or "") or near(bags[i], bags[j]):
            a, b = root[i], root[j]
            root = [a if r == b else r for r in root]
    least = {}
    for (d, _), r in zip(rows, root, strict=True):
        least[r] = min(least.get(r, d), d)
    return sorted((d, least[r]) for (d, _), r in zip(rows, root, strict=True))


def texts():
    random.seed(5)
    word = lambda: "".join(random.choice("abcdefgh") for _ in range(random.randint(2, 6)))
    rows = ["", None, "one", "one two", "one two", "a b c d e", "a b c d e f"]
    for _ in range(6):
        base = [word() for _ in range(120)]
        rows += [" ".join(base)] * 2
        for _ in range(25):
            other = list(base)
            for _ in range(random.choice([1, 2, 3, 5])):
                other[random.randrange(120)] = word()
            rows.append(" ".join(other))
    rows += ["x y z " * n for n in (10, 11, 12, 40, 41)]
    rows += ["word " * 3000, "word " * 2900]
    return list(enumerate(rows))


@pytest.mark.parametrize("block", [1024, 8])
def test_classes_equal_all_pairs(spark, block):
    rows = texts()
    docs = spark.createDataFrame([(d, t, "x", 1) for d, t in rows], "doc_id bigint, text string, h string, root int")
    got = near_classes(docs, block=block).select("doc_id", "class_id").collect()
    assert sorted(map(tuple, got)) == brute(rows)


def test_signature_is_unbiased():
    a, b = Counter({i: 1 + i % 7 for i in range(300)}), Counter({i: 1 + (3 * i) % 5 for i in range(100, 400)})
    true = sum((a & b).values()) / sum((a | b).values())
    rows = [(0, k, n) for k, n in a.items()] + [(1, k, n) for k, n in b.items()]
    owner, value, count = (np.array(x) for x in zip(*rows, strict=True))
    sig = bag_minhash(owner, mix64(value.astype(np.uint64) + np.uint64(7)), count, 2, 8000)
    assert abs((sig[0] == sig[1]).mean() - true) < 4 * np.sqrt(true * (1 - true) / 8000)


def test_shingles_count_repeats():
    owner, _, count = shingles(pa.array(["a b c d e f a b c d e", None, "q"]))
    assert sorted(count[owner == 0]) == [1, 1, 1, 1, 1, 2] and list(count[owner == 2]) == [1] and not (owner == 1).any()


def test_one_of_each_class_stays(spark):
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    twice = docs.union(docs.where("doc_id < 20"))
    classes = near_classes(docs)
    want = {r["doc_id"] for r in classes.where("kept").collect()}
    assert sorted(r["doc_id"] for r in near_dedup(twice).collect()) == sorted(want)
    assert near_dedup(docs).columns == docs.columns
    rows = [(r["doc_id"], r["text"]) for r in docs.collect()]
    assert sorted(map(tuple, classes.select("doc_id", "class_id").collect())) == brute(rows)


def test_empty_and_null_ids(spark):
    docs = spark.createDataFrame([(None, "a b c d e"), (3, "a b c d e"), (None, "other"), (None, None)], "doc_id bigint, text string")
    assert near_classes(docs.where(F.lit(False))).collect() == []
    assert near_dedup(docs.where(F.lit(False))).collect() == []
    got = sorted(map(str, near_classes(docs).select("doc_id", "class_id", "kept").collect()))
    assert len(got) == 4
    assert sorted(str(r["text"]) for r in near_dedup(docs).collect()) == ["None", "a b c d e", "other"]
