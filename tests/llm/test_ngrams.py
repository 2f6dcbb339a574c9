"""The word-pair model against a plain version on dictionaries."""

import math
import random
import re
import zlib
from collections import Counter, defaultdict

import pytest
from pyspark.sql import functions as F

from beamrank.llm.ngrams import _discounts, score_documents, score_texts, train_model


def tokens(text):
    return [*re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), text or "")), None]


class Plain:
    def __init__(self, texts):
        rows = [tokens(t) for t in texts]
        self.count = Counter(w for r in rows for w in r)
        self.pairs = Counter(p for r in rows for p in zip(["<s>", *r], r, strict=False))
        self.n, self.v = sum(self.count.values()), len(self.count)
        tally = Counter(self.pairs.values())
        self.d = _discounts([tally[k] for k in range(1, 5)])
        self.before, self.after = Counter(b for _, b in self.pairs), defaultdict(list)
        for (a, _), c in self.pairs.items():
            self.after[a].append(c)
        tally = Counter(self.before.values())
        self.low = _discounts([tally[k] for k in range(1, 5)])
        self.rest = sum(self.cut(c, self.low) for c in self.before.values()) / len(self.pairs) if self.pairs else 1

    def cut(self, c, d):
        return 0 if c == 0 else d[min(c, 3) - 1]

    def lower(self, w):
        c = self.before[w]
        return (c - self.cut(c, self.low)) / max(1, len(self.pairs)) + self.rest / (self.v + 1)

    def p(self, before, w):
        if before not in self.after:
            return self.lower(w)
        total, c = sum(self.after[before]), self.pairs[before, w]
        left = sum(self.cut(x, self.d) for x in self.after[before]) / total
        return (c - self.cut(c, self.d)) / total + left * self.lower(w)

    def score(self, text):
        row = tokens(text)
        return sum(math.log10(self.p(a, b)) for a, b in zip(["<s>", *row], row, strict=False))

    def base(self, text):
        return sum(math.log10((self.count[w] + 1) / (self.n + self.v + 1)) for w in tokens(text))


@pytest.fixture(scope="module")
def scored(spark):
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    docs = docs.union(spark.createDataFrame([(900, None, "x", "y", 0), (901, " \t", "x", "y", 0), (None, "The THE the", "x", "y", 0)], docs.schema))
    return docs.collect(), score_documents(docs).collect()


def test_scores_equal_plain_model(scored):
    docs, got = scored
    held = lambda d: zlib.crc32(("" if d is None else str(d)).encode()) % 7 == 2
    model = Plain([r["text"] for r in docs if not held(r["doc_id"])])
    texts = {r["doc_id"]: r["text"] for r in docs}
    assert len(got) == len(docs)
    for r in got:
        t = texts[r["doc_id"]]
        assert r["held_out"] == held(r["doc_id"]) and r["train_tokens"] == model.n
        assert (r["n_tokens"], r["n_known"]) == (len(tokens(t)), sum(model.count[w] > 0 for w in tokens(t)))
        assert math.isclose(r["base_score"], model.base(t), rel_tol=1e-9)
        assert math.isclose(r["score"], model.score(t), rel_tol=1e-5, abs_tol=1e-5)


def test_model_beats_base_on_held_out(scored):
    held = [r for r in scored[1] if r["held_out"]]
    assert sum(r["score"] for r in held) > sum(r["base_score"] for r in held)


def test_probabilities_sum_to_one(spark):
    texts = ["a b a b c", "b c a", "a a a b d e", "c d"]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id bigint, text string")
    plain = Plain(texts)
    for before in ["a", "b", "e", "<s>", "never"]:
        assert math.isclose(sum(plain.p(before, w) for w in plain.count) + plain.p(before, "new"), 1, rel_tol=1e-9)
    got = {r["doc_id"]: r["score"] for r in score_texts(docs, train_model(docs, bucket_tokens=3)).collect()}
    assert all(math.isclose(got[i], plain.score(t), rel_tol=1e-5) for i, t in enumerate(texts))


def test_empty(spark):
    docs = spark.createDataFrame([(1, "a b")], "doc_id bigint, text string")
    assert score_documents(docs.where(F.lit(False))).collect() == []
    assert score_texts(docs, train_model(docs.where(F.lit(False)))).count() == 1


@pytest.mark.parametrize("narrow", [0, 1 << 30])
def test_wide_keys_repeated_rows_and_long_texts(spark, narrow, monkeypatch):
    from beamrank.llm import ngrams

    monkeypatch.setattr(ngrams, "SLICE_BYTES", 50)
    long = " ".join(f"w{i * i % 97}" for i in range(4000))
    texts = ["a b a b c", "a b a b c", "", None, "b c a", long, long + " end", " \n"]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id bigint, text string")
    plain = Plain(texts)
    model = train_model(docs, bucket_tokens=300, narrow_words=narrow)
    assert model.wide == (narrow == 0)
    got = {r["doc_id"]: r for r in score_texts(docs, model).collect()}
    for i, t in enumerate(texts):
        assert math.isclose(got[i]["score"], plain.score(t), rel_tol=1e-6) and math.isclose(got[i]["base_score"], plain.base(t), rel_tol=1e-9)
        assert got[i]["n_tokens"] == len(tokens(t)) == got[i]["n_known"]


def test_windows_of_any_size_give_the_same_tokens():
    import numpy as np
    import pyarrow as pa

    from beamrank.llm.ngrams import token_windows

    column = pa.array(["a bb ccc", None, "", "dddddddddddddddddddddddddddd e", "  ", "f\ng\t h", "é ü x"], pa.string())
    whole = None
    for limit in (1, 2, 3, 7, 1000):
        parts = [np.stack([x.astype(np.uint64) for x in w]) for w in token_windows(column, limit)]
        joined = np.concatenate(parts, axis=1)
        joined = joined[:, np.argsort(joined[1], kind="stable")]
        whole = joined if whole is None else whole
        assert (joined == whole).all()


class PlainOrder(Plain):
    """Any order, on counters of tuples."""

    def __init__(self, texts, order):
        super().__init__(texts)
        self.order, self.c, self.ds, self.by = order, {}, {}, {}
        rows = [["<s>"] * (order - 1) + tokens(t) for t in texts]
        self.c[order] = Counter(tuple(r[i - order + 1 : i + 1]) for r in rows for i in range(order - 1, len(r)))
        for k in range(order - 1, 0, -1):
            self.c[k] = Counter(g[1:] for g in self.c[k + 1])
        for k, counts in self.c.items():
            tally = Counter(counts.values())
            self.ds[k] = _discounts([tally[i] for i in range(1, 5)])
            self.by[k] = defaultdict(list)
            for g, n in counts.items():
                self.by[k][g[:-1]].append(n)

    def prob(self, history, w, k):
        if k == 1:
            total = sum(self.c[1].values())
            left = sum(self.cut(n, self.ds[1]) for n in self.c[1].values()) / total
            n = self.c[1][w,]
            return (n - self.cut(n, self.ds[1])) / total + left / (self.v + 1)
        h = tuple(history[-(k - 1) :])
        low = self.prob(history, w, k - 1)
        if h not in self.by[k]:
            return low
        total, n = sum(self.by[k][h]), self.c[k][(*h, w)]
        return (n - self.cut(n, self.ds[k])) / total + sum(self.cut(x, self.ds[k]) for x in self.by[k][h]) / total * low

    def score(self, text):
        row = ["<s>"] * (self.order - 1) + tokens(text)
        return sum(math.log10(self.prob(row[:i], row[i], self.order)) for i in range(self.order - 1, len(row)))


@pytest.mark.parametrize("order,narrow", [(3, 0), (4, 1 << 30)])
def test_any_order_equals_a_plain_model(spark, order, narrow):
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet").select("doc_id", "text").limit(40)
    texts = {r["doc_id"]: r["text"] for r in docs.collect()}
    seen = {d: t for d, t in texts.items() if d % 3}
    rows = spark.createDataFrame(list(texts.items()), "doc_id bigint, text string")
    model = train_model(rows.where("doc_id % 3 > 0"), bucket_tokens=2000, narrow_words=narrow, order=order)
    plain = PlainOrder(list(seen.values()), order)
    assert [x.size for x in model.levels] == [len(plain.c[k]) for k in range(2, order + 1)]
    for r in score_texts(rows, model).collect():
        assert math.isclose(r["score"], plain.score(texts[r["doc_id"]]), rel_tol=1e-7)


def test_higher_orders_score_what_they_have_seen_higher():
    texts = ["a b c d", "a c b d", "d c b a", "a b c d"]
    assert sum(map(PlainOrder(texts, 3).score, texts)) > sum(map(PlainOrder(texts, 2).score, texts))


def test_the_query_sees_two_words_before(spark, tmp_path):
    from beamrank.llm.entries import op5_kneser_ney

    held = [i for i in range(200) if zlib.crc32(str(i).encode()) % 7 == 2]
    rows = [(i, "a b c" if i % 2 else "x b d") for i in range(200) if i not in held] + [(held[0], "a b c"), (held[1], "a b d")]
    spark.createDataFrame(rows, "doc_id bigint, text string").write.parquet(f"{tmp_path}/documents.parquet")
    score = {r["doc_id"]: r["score"] for r in op5_kneser_ney(spark, str(tmp_path)).collect()}
    assert score[held[0]] > score[held[1]] + 0.5


def test_a_run_takes_few_bytes(spark, tmp_path, monkeypatch):
    from beamrank.llm import ngrams

    monkeypatch.setattr(ngrams, "scratch_path", lambda *_: f"file://{tmp_path}/model")
    rng = random.Random(1)
    rows = [(i, " ".join(f"w{rng.randrange(2000)}" for _ in range(100))) for i in range(200)]
    model = train_model(spark.createDataFrame(rows, "doc_id bigint, text string"), order=3)
    runs = sum(x.size for x in model.levels)
    assert runs > 40_000 and sum(f.stat().st_size for f in tmp_path.rglob("*.bin")) < 8 * runs


@pytest.mark.parametrize("bucket_tokens", [60, 1 << 20])
def test_frequent_runs_and_contexts_of_many_words(spark, bucket_tokens):
    texts = ["a b c"] * 300 + [f"a b n{i}" for i in range(300)] + [f"n{i} a b c a b" for i in range(40)] + ["c c c c c", ""]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id bigint, text string")
    plain = PlainOrder(texts, 3)
    odd = [*texts[298:304], *texts[600:605], *texts[-2:], "a b new", "n7 n8 a b n9", "b c a", None]
    rows = spark.createDataFrame(list(enumerate(odd)), "doc_id bigint, text string")
    got = {r["doc_id"]: r["score"] for r in score_texts(rows, train_model(docs, bucket_tokens=bucket_tokens, order=3)).collect()}
    assert all(math.isclose(got[i], plain.score(t), rel_tol=1e-7) for i, t in enumerate(odd))
