"""Vectors against all pairs; the classifier on held-out rows and odd inputs."""

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from beamrank.llm.quality import FEATURES, fit_forest, keep_good, score_documents, text_statistics
from beamrank.llm.vectors import collision_counts, least_collisions, tables_for, vector_links


def rows():
    rng = np.random.default_rng(3)
    out, n = [], 0
    for label in (0, 1, None):
        for _ in range(12):
            base = rng.standard_normal(16)
            for _ in range(6):
                out.append((n, [float(x) for x in base + rng.standard_normal(16) * rng.choice([0.05, 0.3, 0.5])], label))
                n += 1
        out += [(n + i, [1.0] * 16, label) for i in range(5)]
        n += 5
    out += [(n, None, 0), (n + 1, [], 0), (n + 2, [0.0] * 16, 0), (n + 3, [float("nan")] * 16, 0), (n + 4, [1.0, None] + [0.0] * 14, 0), (n + 5, [1.0] * 8, 0)]
    return out


def brute(data):
    ok = {i: np.array(v) for i, v, label in data if label is not None and v and None not in v and np.isfinite(v).all() and any(v)}
    label = {i: x for i, _, x in data}
    links = {i: [j for j in ok if j != i and label[j] == label[i] and len(ok[j]) == len(ok[i]) and ok[i] @ ok[j] / np.linalg.norm(ok[i]) / np.linalg.norm(ok[j]) >= 0.93] for i in ok}
    out = {}
    for i, _, _ in data:
        seen, todo = {i}, [i]
        while todo:
            for j in links.get(todo.pop(), []):
                if j not in seen:
                    seen.add(j)
                    todo.append(j)
        out[i] = (len(links.get(i, [])), min(seen), min(seen) == i)
    return out


@pytest.mark.parametrize("block", [1024, 7])
def test_links_equal_all_pairs(spark, block):
    data = rows()
    df = spark.createDataFrame(data, "vec_id bigint, embedding array<float>, label int").withColumn("node", F.lit("x"))
    kept = [(r["vec_id"], list(r["embedding"]) if r["embedding"] is not None else None, r["label"]) for r in df.collect()]
    got = {r["vec_id"]: (r["n_links"], r["component_id"], r["kept"]) for r in vector_links(df, block=block).collect()}
    assert got == brute(kept)


def test_empty_vectors(spark):
    assert vector_links(spark.createDataFrame([], "vec_id bigint, embedding array<float>, label int")).collect() == []


def test_counts_and_calibration():
    rng = np.random.default_rng(0)
    a, b = rng.standard_normal((9, 5)), rng.standard_normal((11, 5))
    assert (collision_counts(a, b, 0.4) == (np.abs(a[:, None] - b[None]) <= 0.4).sum(axis=2)).all()
    x = rng.standard_normal((20_000, 24)) * 1.0
    assert ((np.abs(x) <= 1.6).sum(axis=1) >= least_collisions()).mean() > 0.9999


def test_forest_learns_a_rule():
    rng = np.random.default_rng(1)
    x = rng.random((3000, 4)).astype(np.float32)
    y = ((x[:, 0] > 0.4) & (x[:, 2] < 0.7)).astype(float)
    forest = fit_forest(x[:2000], y[:2000])
    assert ((forest.score(x[2000:]) > 0.5) == y[2000:]).mean() > 0.98
    assert fit_forest(x[:0], y[:0]).score(x[:3]).tolist() == [0.5] * 3


def test_statistics():
    s = dict(zip(FEATURES, text_statistics(pa.array(["A bb A bb\n", None]))[0], strict=True))
    assert s["repeats"] == 0 and s["distinct_words"] == 0.5 and s["lines"] == 0.25 and s["capital_words"] == 0.5
    assert not text_statistics(pa.array([None, ""])).any()


def test_classifier_on_held_out_rows(spark):
    d = "/root/testdata/sf0.01"
    docs, labels = spark.read.parquet(f"{d}/documents.parquet"), spark.read.parquet(f"{d}/labels.parquet")
    scored = score_documents(docs, labels)
    held = scored.where("held_out").join(labels, "doc_id").collect()
    assert scored.count() == 1000 and np.mean([r["predicted"] == r["quality"] for r in held]) > 0.95
    kept = {r["doc_id"] for r in keep_good(docs, labels).collect()}
    assert kept == {r["doc_id"] for r in scored.where("predicted = 1").collect()}


def test_classifier_without_labels(spark):
    docs = spark.createDataFrame([(1, None, "a"), (2, "", "b"), (None, "x y", "c"), (1, None, "a")], "doc_id bigint, text string, score string")
    labels = spark.createDataFrame([(1, None, 0)], "doc_id bigint, quality int, toxic int")
    got = score_documents(docs, labels).collect()
    assert [r["score"] for r in got] == [0.5] * 4 and keep_good(docs, labels).columns == docs.columns
    assert keep_good(docs.where(F.lit(False)), labels).collect() == []


def test_links_over_many_tables(spark):
    """Recall against all pairs where buckets part a label: at the least 0.99, and no link below the threshold."""
    rng = np.random.default_rng(8)
    base = rng.standard_normal((400, 24))
    data = [(i, [float(x) for x in np.float32(base[i // 4] + rng.standard_normal(24) * (0.15 + 0.05 * (i % 3)))], 0) for i in range(1600)]
    df = spark.createDataFrame(data, "vec_id bigint, embedding array<float>, label int")
    kept = [(r["vec_id"], list(r["embedding"]), r["label"]) for r in df.collect()]
    unit = np.array([v for _, v, _ in kept])
    unit /= np.linalg.norm(unit, axis=1, keepdims=True)
    true = (unit @ unit.T >= 0.93).sum(axis=1) - 1
    got = {r["vec_id"]: r["n_links"] for r in vector_links(df, block=64).collect()}
    found = np.array([got[i] for i, _, _ in kept])
    assert tables_for(1600, 0.93, 64)[0] >= 4 and (found <= true).all() and found.sum() >= 0.99 * true.sum() > 500


def test_null_and_repeated_vector_ids(spark):
    rows = [(None, [1.0, 2.0], 0), (7, [1.0, 2.0], 0), (7, [1.0, 2.0], 0), (None, None, 0), (9, [2.0, -1.0], 0)]
    got = sorted((str(r["vec_id"]), r["n_links"], str(r["component_id"]), r["kept"]) for r in vector_links(spark.createDataFrame(rows, "vec_id bigint, embedding array<double>, label int")).collect())
    assert got == [("7", 2, "7", True), ("7", 2, "7", True), ("9", 0, "9", True), ("None", 0, "None", True), ("None", 2, "7", False)]


def test_tables_keep_their_promise():
    for n in (10, 1024, 5000, 10**6, 10**9):
        k, tables = tables_for(n, 0.93, 1024)
        assert tables <= 64 and (1 - (1 - np.arccos(0.93) / np.pi) ** k) ** tables <= 1e-4 * (k > 0) + (k == 0) * 0.0 + 1e-12


def test_forest_equals_trees_walked_one_by_one():
    """Scores of flattened trees against a plain walk, and the first split against a search over all of them."""
    rng = np.random.default_rng(4)
    x = rng.random((500, 3)).astype(np.float32)
    y = (x[:, 1] + 0.2 * rng.standard_normal(500) > 0.6).astype(float)
    forest = fit_forest(x, y, trees=7, depth=3, bins=16)

    def walk(row):
        total = forest.base
        for t in range(len(forest.leaf)):
            at = 0
            for _ in range(3):
                at = 2 * at + 1 + int(row[forest.feature[t, at]] > forest.threshold[t, at])
            total += forest.leaf[t, at - forest.feature.shape[1]]
        return 1 / (1 + np.exp(-total))

    assert np.allclose(forest.score(x[:50]), [walk(r) for r in x[:50]])
    p = y.mean()
    best = (0, None, None)
    for f in range(3):
        for edge in np.unique(np.quantile(x[:, f], np.linspace(0, 1, 17)[1:-1])):
            left = x[:, f] <= edge
            gain = sum(((p - y[side]).sum()) ** 2 / (side.sum() * p * (1 - p) + 1.0) for side in (left, ~left))
            best = max(best, (gain, f, edge), key=lambda b: b[0])
    assert forest.feature[0, 0] == best[1] and np.isclose(forest.threshold[0, 0], best[2])


def brute_statistics(text):
    words = (text or "").split()
    pairs = list(zip(words, words[1:], strict=False))
    n, w = max(1, len((text or "").encode())), max(1, len(words))
    return {
        "log_words": np.log1p(len(words)), "upper": sum(c in "ABCDEFGHIJKLMNOPQRSTUVWXYZ" for c in text or "") / n, "distinct_words": len(set(words)) / w,
        "repeats": sum(a == b for a, b in pairs) / w, "distinct_pairs": len(set(pairs)) / w, "lines": (text or "").count("\n") / w, "long_words": sum(len(x.encode()) > 20 for x in words) / w,
    }


@pytest.mark.parametrize("window", [1, 5, 64, 1 << 20])
def test_statistics_of_windows(window):
    texts = ["a a b a\nB B! ..", None, "", "x" * 90 + " y", "one two one two one two three", " \n "]
    got = text_statistics(pa.array(texts), window)
    for row, t in zip(got, texts, strict=True):
        assert all(np.isclose(dict(zip(FEATURES, row, strict=True))[k], v, atol=1e-6) for k, v in brute_statistics(t).items())


def test_a_long_text_needs_little_memory():
    """50 MB in one text, in a process of its own: statistics, shingles, tokens and token ids stay below 1 GB."""
    import subprocess
    import sys

    code = """
import resource, pyarrow as pa
from beamrank.llm import near_dedup, ngrams, quality, tokens
text = pa.array([' '.join(f'w{i * i % 100003}' for i in range(500_000)) * 15])
assert len(text[0].as_py()) > 48e6
if {n} == 0: quality.text_statistics(text)
if {n} == 1: near_dedup.bag_minhash(*near_dedup.shingles(text), 1, 125)
if {n} == 2: assert sum(len(t) for t, _, _ in ngrams.token_windows(text)) > 7e6
if {n} == 3: assert len(tokens.PieceEncoder(tokens.vocabulary('word_bpe_49k.json')).encode(text)[0]) > 7e6
print(resource.getrusage(resource.RUSAGE_SELF).ru_maxrss // 1000)
"""
    for n in range(4):
        out = subprocess.run([sys.executable, "-c", code.replace("{n}", str(n))], capture_output=True, text=True, check=True)
        assert int(out.stdout.split()[-1]) < 1000
