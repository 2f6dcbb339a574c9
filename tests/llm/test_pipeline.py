"""The pipeline's stages against plain versions of each."""

from collections import Counter, defaultdict

import corpus_pipeline
from tests.llm.test_near import brute

from beamrank.llm.mixing import mix_counts
from beamrank.llm.quality import score_documents

SF = "/root/testdata/sf0.001"


def test_stages(spark, tmp_path):
    docs, labels = spark.read.parquet(f"{SF}/documents.parquet"), spark.read.parquet(f"{SF}/labels.parquet")
    kept = {}
    for name, stage in corpus_pipeline.STAGES:
        stage(spark, docs, SF).write.parquet(f"{tmp_path}/{name}")
        before, docs = docs, spark.read.parquet(f"{tmp_path}/{name}")
        kept[name] = docs
        if name != "pack":
            assert docs.columns == before.columns

    ids = lambda df: sorted(r["doc_id"] for r in df.select("doc_id").collect())
    raw = spark.read.parquet(f"{SF}/documents.parquet")
    good = sorted(r["doc_id"] for r in score_documents(raw, labels).where("predicted = 1").collect())
    assert ids(kept["quality"]) == good
    by_text = defaultdict(int)
    for r in kept["quality"].collect():
        by_text[r["text"]] = max(by_text[r["text"]], r["doc_id"])
    assert ids(kept["exact"]) == sorted(by_text.values())
    rows = [(r["doc_id"], r["text"]) for r in kept["exact"].collect()]
    assert ids(kept["near"]) == sorted({c for _, c in brute(rows)})
    copies = Counter({r["doc_id"]: r["copies"] for r in mix_counts(kept["near"]).collect() if r["copies"]})
    assert Counter(ids(kept["mixture"])) == copies
    pieces = kept["pack"].where("piece = 0").collect()
    assert Counter(r["doc_id"] for r in pieces) == copies


def test_run_gives_the_last_stage(spark):
    assert corpus_pipeline.run(spark, SF).columns == ["doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset"]


def odd(spark, empty=False):
    long = " ".join(f"word{i % 911}" for i in range(60_000))
    texts = [None, "", "   ", "one two three four five six", "one two three four five six", long, long + " end", "x", "x y", None, "same words again " * 30]
    rows = [(i if i != 6 else None, t, "en", ["a", "b", None][i % 3], len(t or ""), f"row {i}", i) for i, t in enumerate(texts)]
    rows += rows[:4]
    names = ["doc_id", "text", "lang", "source", "n_chars", "a.b", "__id"]
    return spark.createDataFrame([] if empty else rows, "doc_id bigint, text string, lang string, source string, n_chars bigint, `a.b` string, __id bigint"), names


def test_stages_on_odd_rows_and_empty_tables(spark, tmp_path):
    for empty in (False, True):
        docs, names = odd(spark, empty)
        for name, stage in corpus_pipeline.STAGES:
            stage(spark, docs, SF).write.parquet(f"{tmp_path}/{empty}-{name}")
            before, docs = docs, spark.read.parquet(f"{tmp_path}/{empty}-{name}")
            if name != "pack":
                assert docs.columns == names
            if name in ("quality", "exact", "near"):
                whole = {tuple(r) for r in before.collect()}
                assert {tuple(r) for r in docs.collect()} <= whole
            if empty:
                assert docs.count() == 0
        if not empty:
            assert all(r["length"] <= 2048 for r in docs.collect())


def test_near_stage_on_odd_rows_equals_all_pairs(spark):
    docs, _ = odd(spark)
    once = docs.dropDuplicates(["doc_id", "text"]).where("doc_id is not null")
    rows = [(r["doc_id"], r["text"]) for r in once.collect()]
    from beamrank.llm.near_dedup import near_dedup

    assert sorted(r["doc_id"] for r in near_dedup(once).collect()) == sorted({c for _, c in brute(rows)})
