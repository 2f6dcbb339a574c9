"""Packing and sorted tables against the library's own encoding."""

import zlib
from collections import defaultdict
from functools import cache

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from beamrank.llm.packing import pack_documents, packed_sequences, plan_best_fit
from beamrank.llm.sstable import encode_to_tables, lookup, read_tables, write_tables
from beamrank.llm.tokens import PieceEncoder, vocabulary

SF = "/root/testdata/sf0.001"
ODD = ["it's a DOG's <|endoftext|> b  c\n\n d!'s", None, "", "   ", "naïve Σας É 中文 😀\t12ab", "word " * 6000, "word " * 6000, "\n\nfoo \n bar"]


def crc(ids):
    return zlib.crc32(np.array(ids, "<u4").tobytes())


def odd_table(spark):
    rows = [(i if i != 3 else None, t, "x") for i, t in enumerate(ODD)] + [(5, ODD[5], "x")]
    return spark.createDataFrame(rows, "doc_id bigint, text string, length string")


@settings(max_examples=200, deadline=None)
@given(st.lists(st.one_of(st.none(), st.text(alphabet="aZ é'!.,<|>1 \n\t 中", max_size=40)), max_size=6))
def test_pieces_equal_whole_texts(texts):
    import pyarrow as pa

    for name in ("byte_bpe_50k.json", "word_bpe_49k.json"):
        ids, at = _coder(name).encode(pa.array(texts, pa.string()))
        for i, t in enumerate(texts):
            assert ids[at[i] : at[i + 1]].tolist() == _coder(name).tokenizer.encode(t or "", add_special_tokens=False).ids


@settings(max_examples=200, deadline=None)
@given(st.lists(st.lists(st.sampled_from(["<|endoftext|>", "<|startoftext|>", "<|EndOfText|>", "<|", " ", "\n", "\t", "  ", "\u00a0", "\u3000", "\u2003", "é", "ñandú", "中文", "😀", "don't", "Word", "12", "!?", "'s", "\u0301", "×"]), max_size=14).map("".join), max_size=4))
def test_short_windows_and_special_tokens(texts):
    import pyarrow as pa

    for name in ("byte_bpe_50k.json", "word_bpe_49k.json"):
        ids, at = _coder(name, 9).encode(pa.array(texts, pa.string()))
        for i, t in enumerate(texts):
            assert ids[at[i] : at[i + 1]].tolist() == _coder(name).tokenizer.encode(t, add_special_tokens=False).ids


@cache
def _coder(name, window=4 << 20):
    return PieceEncoder(vocabulary(name), cache_pieces=20, window=window)


def best_fit_by_items(lengths, capacity):
    rooms = []
    for n in sorted(lengths, reverse=True):
        fit = [r for r in rooms if r >= n]
        if fit:
            rooms.remove(min(fit))
            rooms.append(min(fit) - n)
        else:
            rooms.append(capacity - n)
    return len(rooms)


@settings(max_examples=150, deadline=None)
@given(st.lists(st.integers(1, 32), max_size=120))
def test_plan_is_best_fit_decreasing(lengths):
    histogram = defaultdict(int)
    for n in lengths:
        histogram[n] += 1
    steps, made = plan_best_fit(histogram, 32)
    assert made == best_fit_by_items(lengths, 32)
    used, ranks = defaultdict(list), defaultdict(list)
    for length, a, b, first, each, base in steps:
        ranks[length] += range(a, b)
        for k in range(b - a):
            used[first + k // each].append((base + k % each * length, length))
    assert {n: sorted(r) for n, r in ranks.items()} == {n: list(range(c)) for n, c in histogram.items()}
    for parts in used.values():
        at = 0
        for offset, length in sorted(parts):
            assert offset == at
            at += length
        assert at <= 32


@pytest.mark.parametrize("kind", ["table", "odd"])
def test_packing(spark, kind):
    docs = spark.read.parquet(f"{SF}/documents.parquet") if kind == "table" else odd_table(spark)
    rows = pack_documents(docs).collect()
    coder = Tokenizer.from_file(vocabulary("byte_bpe_50k.json"))
    expected = []
    for r in docs.select("doc_id", "text").collect():
        ids = coder.encode(r["text"] or "", add_special_tokens=False).ids + [0]
        first = (len(ids) - 1) % 2048 + 1
        cuts = [0, *range(first, len(ids) + 1, 2048)]
        expected += [(r["doc_id"], k, a, b - a, crc(ids[a:b])) for k, (a, b) in enumerate(zip(cuts, cuts[1:], strict=False))]
    order = lambda x: tuple((v is not None, v) for v in x)
    assert sorted(((*r[:5],) for r in rows), key=order) == sorted(expected, key=order)
    places = defaultdict(list)
    for r in rows:
        places[r["sequence_id"]].append((r["offset"], r["length"]))
    for parts in places.values():
        at = 0
        for offset, length in sorted(parts):
            assert offset == at
            at += length
        assert at <= 2048
    assert len(places) == best_fit_by_items([e[3] for e in expected], 2048)


def test_packed_sequences_hold_the_ids(spark):
    docs = odd_table(spark)
    got = packed_sequences(docs).collect()
    coder = Tokenizer.from_file(vocabulary("byte_bpe_50k.json"))
    total = sum(len(coder.encode(r["text"] or "", add_special_tokens=False).ids) + 1 for r in docs.collect())
    assert sum(len(r["ids"]) for r in got) == total and max(len(r["ids"]) for r in got) <= 2048


@pytest.mark.parametrize("kind", ["table", "odd"])
def test_sorted_tables(spark, kind):
    docs = spark.read.parquet(f"{SF}/documents.parquet") if kind == "table" else odd_table(spark)
    coder = Tokenizer.from_file(vocabulary("word_bpe_49k.json"))
    rows = sorted(docs.select("doc_id", "text").collect(), key=lambda r: (r["doc_id"] is not None, r["doc_id"]))
    expected, at = [], 0
    for r in rows:
        ids = coder.encode(r["text"] or "", add_special_tokens=False).ids + [1]
        expected.append((r["doc_id"], at, len(ids), crc(ids)))
        at += len(ids)
    got = encode_to_tables(spark, docs, shard_bytes=20_000).collect()
    assert sorted((tuple(r) for r in got), key=lambda r: r[1]) == expected


def test_lookup(spark, tmp_path):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    files = write_tables(docs, f"file://{tmp_path}/t", shard_bytes=50_000)
    assert files.count() > 3
    some = {r["doc_id"]: r["ids"] for r in read_tables(files).where("doc_id in (0, 77, 199)").collect()}
    assert lookup(files, [0, 77, 199, 10**9]) == {k: [v] for k, v in some.items()}


def test_empty_tables(spark):
    docs = odd_table(spark).where(F.lit(False))
    assert pack_documents(docs).collect() == []
    assert encode_to_tables(spark, docs).collect() == []
