"""Beams and rerankers against plain Python, on literals and on the line beams."""

from collections import defaultdict

import pytest
from pyspark.sql import functions as F

from beamrank.operators import beams, learned, metrics, rerank
from beamrank.plans import beam_queries, learned_queries, text_queries  # noqa: F401
from beamrank.plans.registry import QUERIES
from beamrank.sources.tables import beam_table, chat_beams, from_rows, line_beams

SF = "/root/testdata/sf0.01"

#: Beams of one, four and six items; ties, null scores, all or none correct or verified.
ROWS = [
    (1, 1, 11, True, False, 5.0),
    (2, 1, 21, False, False, 9.0), (2, 2, 22, True, True, 9.0), (2, 3, 23, False, True, None), (2, 4, 24, True, False, 10.0),
    (3, 1, 31, False, None, 1.0), (3, 2, 32, False, False, 1.0), (3, 3, 33, True, None, 0.0), (3, 4, 34, True, False, 1.0), (3, 5, 35, True, False, 1.0), (3, 6, 36, True, True, 7.0),
    (4, 1, 41, True, True, 3.0), (4, 2, 42, True, True, 3.0),
]


@pytest.fixture(scope="module")
def toy(spark):
    return from_rows(spark, ROWS)


def picks(df):
    return {r["beam_id"]: r["item_id"] for r in df.collect()}


def test_rerankers_by_hand(toy):
    assert picks(rerank.top1(toy)) == {1: 11, 2: 21, 3: 31, 4: 41}
    assert picks(rerank.verifier(toy)) == {1: 11, 2: 22, 3: 36, 4: 41}
    assert picks(rerank.waves(toy, lambda x: x)) == picks(rerank.verifier(toy))
    assert picks(rerank.by_score(toy)) == {1: 11, 2: 24, 3: 31, 4: 41}
    assert picks(rerank.hybrid(toy)) == {1: 11, 2: 21, 3: 36, 4: 41}
    assert picks(rerank.ceiling(toy)) == {1: 11, 2: 22, 3: 33, 4: 41}


def test_waves_judge_no_item_twice(toy, spark):
    judged = spark.sparkContext.accumulator(0)

    def verdicts(items):
        def run(batches):
            for b in batches:
                judged.add(len(b))
                yield b

        return items.mapInPandas(run, items.schema)

    assert picks(rerank.waves(toy, verdicts)) == picks(rerank.verifier(toy))
    assert judged.value <= toy.count()


@pytest.mark.parametrize("mode,k", [("replace_last", 5), ("replace_last", 2), ("front", 5), ("front", 2)])
def test_gold_from_outside_the_beam(spark, mode, k):
    beams_of = {1: "abcdef", 2: "bcdefa", 3: "xyz", 4: "bca", 5: "", 6: "pq"}
    gold = {1: "a", 2: "a", 3: "g", 4: "a", 5: "g"}
    items = spark.createDataFrame([(b, p, t) for b, row in beams_of.items() for p, t in enumerate(row, 1)], "beam_id bigint, pos int, sql string")
    golds = spark.createDataFrame(list(gold.items()), "beam_id bigint, sql string")
    got = {}
    for r in beams.insert_gold(items, golds, k, mode, "sql").collect():
        got.setdefault(r["beam_id"], {})[r["pos"]] = (r["sql"], r["is_gold"])
    for b, row in beams_of.items():
        want = list(row[:k])
        if b in gold and gold[b] not in want:
            want = [gold[b], *want][:k] if mode == "front" else [*want[: k - 1], gold[b]]
        assert [got.get(b, {})[p] for p in sorted(got.get(b, {}))] == [(t, t == gold.get(b)) for t in want]
        assert sorted(got.get(b, {})) == list(range(1, len(want) + 1))


def test_geometric_walk_from_the_first_correct_item(spark):
    rows = from_rows(spark, [(b, p, 10 * b + p, p >= 2 + b % 3, False, 1.0) for b in range(300) for p in range(1, 6)])
    plain = {(r["beam_id"], r["pos"]): r["new_pos"] for r in beams.reorder_geometric(rows, 5).collect()}
    assert all(p == n for (_, p), n in plain.items())
    moved = {}
    for r in beams.reorder_geometric(rows, 5, anchor="first_correct").collect():
        moved.setdefault(r["beam_id"], {})[r["pos"]] = r["new_pos"]
    shifts = []
    for b, at in moved.items():
        start, order = 2 + b % 3, [p for p, _ in sorted(at.items(), key=lambda x: x[1])]
        rest = [p for p in range(1, 6) if p != start]
        assert sorted(at.values()) == [1, 2, 3, 4, 5] and [p for p in order if p != start] == rest and at[start] >= start
        shifts.append(at[start] - start)
    assert 0.6 < sum(s == 0 for s in shifts) / len(shifts) < 0.8


def test_verdicts_of_all_or_none_give_top1(toy):
    assert picks(rerank.verifier(toy, F.lit(True))) == picks(rerank.verifier(toy, F.lit(False))) == picks(rerank.top1(toy))


def test_gold_goes_where_it_should(spark):
    rows = from_rows(spark, [(b, p, 10 * b + p, False, False, 1.0) for b, g in ((1, 1), (2, 5), (3, 6), (4, 2)) for p in range(1, 7)])
    rows = rows.withColumn("price", F.when(F.expr("(beam_id = 1 and pos = 1) or (beam_id = 2 and pos = 5) or (beam_id = 3 and pos = 6) or (beam_id = 4 and pos = 2)"), 2.0).otherwise(1.0))
    marked = beams.with_gold(rows)
    order = lambda df: {b: [i for _, i in sorted(x)] for b, x in _grouped(df).items()}
    assert order(beams.ensure_gold(marked, 5)) == {1: [11, 12, 13, 14, 15], 2: [21, 22, 23, 24, 25], 3: [31, 32, 33, 34, 36], 4: [41, 42, 43, 44, 45]}
    assert order(beams.ensure_gold(marked, 5, "front"))[3] == [36, 31, 32, 33, 34]
    assert order(beams.ensure_gold(marked, 2, "front")) == {1: [11, 12], 2: [25, 21], 3: [36, 31], 4: [41, 42]}


def _grouped(df):
    out = defaultdict(list)
    for r in df.collect():
        out[r["beam_id"]].append((r["pos"], r["item_id"]))
    return out


def test_geometric_order_equals_swaps(spark):
    import hashlib

    rows = beams.first_k(line_beams(spark, "/root/testdata/sf0.001"), 5)
    got = defaultdict(dict)
    right = {}
    for r in beams.reorder_geometric(rows).collect():
        got[r["beam_id"]][r["pos"]] = r["new_pos"]
        if r["pos"] == 1:
            right[r["beam_id"]] = r["correct"]
    for b, places in got.items():
        n = len(places)
        order, at = list(range(1, n + 1)), 0
        if right[b]:
            while at < n - 1 and int(hashlib.md5(f"{b}|{at + 1}".encode()).hexdigest()[:8], 16) / 2**32 >= 0.7:
                order[at], order[at + 1] = order[at + 1], order[at]
                at += 1
        assert {item: place for place, item in enumerate(order, 1)} == places


def test_geometric_shifts_follow_the_coin(spark):
    sized = line_beams(spark, SF).groupBy("beam_id").count()
    shift = beams.geometric_shift(F.col("beam_id").cast("string"), F.lit(5), 5)
    hist = {r["p"]: r["count"] for r in sized.select((shift + 1).alias("p")).groupBy("p").count().collect()}
    assert [hist[k] for k in range(1, 6)] == [10354, 3099, 885, 279, 126]


def test_golden_values_of_line_beams(spark):
    rows = line_beams(spark, SF).cache()
    right = lambda df: df.where("correct").count()
    assert rows.select("beam_id").distinct().count() == 14743 and beams.first_k(rows, 5).count() == 53914
    assert right(rerank.top1(rows)) == 4873 and right(rerank.verifier(rows)) == 4912
    assert right(rerank.selector(rows)) == 4863 and right(rerank.hybrid(rows)) == 4961
    assert rerank.binary_beams(rows).where("item_id_2 is null").count() == 3030
    curve = {r["k"]: r["covered"] for r in beams.gain_curve(rows).collect()}
    assert [curve[k] for k in range(1, 6)] == [4873, 7926, 9623, 10441, 10833] and curve[13] == 11058 == right(rerank.ceiling(rows))
    prf = metrics.prf(beams.first_k(rows, 5)).head()
    assert (prf["tp"], prf["fp"], prf["fn"], prf["tn"]) == (9911, 19923, 8025, 16055)
    rows.unpersist()


def test_golden_values_of_chat_beams(spark):
    rows = chat_beams(spark, SF)
    assert rows.count() == 233 and rows.select("beam_id").distinct().count() == 98
    assert rows.where("verified").count() == 112 and rows.where("correct").count() == 221 and rows.where("verified and correct").count() == 112


@pytest.mark.parametrize("name, sizes", [("selector5", [5]), ("selector2", [2]), ("selector_grid", [5, 5, 2, 2] * 2)])
def test_selectors_train_with_the_gold_item(spark, monkeypatch, name, sizes):
    trained = []

    def fit(train, features, label="correct"):
        trained.append(train.select("beam_id", "item_id", "new_pos", "correct").collect())
        return None

    monkeypatch.setattr(learned, "item_model", fit)
    monkeypatch.setattr(learned, "select_by_model", lambda model, df: df)
    QUERIES[name](spark, "/root/testdata/sf0.001")
    lines = defaultdict(list)
    for r in line_beams(spark, "/root/testdata/sf0.001").where("beam_id % 5 < 4").orderBy("pos").collect():
        lines[r["beam_id"]].append(r)
    assert len(trained) == len(sizes)
    for i, (rows, k) in enumerate(zip(trained, sizes)):
        got = defaultdict(dict)
        for r in rows:
            got[r["beam_id"]][r["item_id"]] = r["correct"]
        want = {}
        for b, items in lines.items():
            gold = max(items, key=lambda r: (r["price"], -r["pos"]))
            kept = items[:k] if gold in items[:k] else [gold, *items[: k - 1]]
            if len(sizes) == 1 or b % 2 == i % 2:
                want[b] = {r["item_id"]: r["correct"] or r is gold for r in kept}
        assert got == want and all(any(x.values()) for x in got.values())


@pytest.mark.parametrize("order", ["random", "geometric"])
def test_training_orders_hold_the_gold_item(spark, order):
    d = "/root/testdata/sf0.001"
    got = defaultdict(list)
    for r in QUERIES[f"selector_{order}_train_gold"](spark, d).collect():
        got[r["beam_id"]].append(r)
    front = defaultdict(dict)
    for r in QUERIES["gold_front5"](spark, d).where("beam_id % 5 < 4").collect():
        front[r["beam_id"]][r["item_id"]] = r["is_gold"]
    assert {b: {r["item_id"]: r["is_gold"] for r in rows} for b, rows in got.items()} == front
    for rows in got.values():
        assert sorted(r["pos"] for r in rows) == list(range(1, len(rows) + 1))
        assert [r["correct"] for r in rows if r["is_gold"]] == [True]


def test_matrix_has_every_reranker_on_every_system(spark):
    d = "/root/testdata/sf0.001"
    got = {(r["system"], r["reranker"]): r["accuracy"] for r in QUERIES["rerank_matrix_all"](spark, d).collect()}
    rows = line_beams(spark, d).cache()
    want = {}
    for system, rule in beam_queries.SYSTEM_RULES.items():
        own = rows.withColumn("correct", F.expr(rule))
        for name, f in rerank.RERANKERS.items():
            want[system, name] = f(own).agg(F.round(F.avg(F.col("correct").cast("int")), 6)).head()[0]
    rows.unpersist()
    assert got == pytest.approx(want)
    few = {(r["system"], r["reranker"]): r["accuracy"] for r in QUERIES["rerank_matrix"](spark, d).collect()}
    assert few == {k: v for k, v in got.items() if k[1] in beam_queries.MATRIX}


def test_chat_verifiers_read_the_whole_beam(spark, tmp_path):
    answers = {1: ["no", "no", "no", "no", "no", "no", "one two three"], 2: ["no", "one two three"], 3: ["no"] * 6}
    rows = [(c, t, role, text) for c, a in answers.items() for t, (role, text) in enumerate([("user", "one two three"), *(("assistant", x) for x in a)])]
    spark.createDataFrame(rows, "conv_id bigint, turn int, role string, text string").write.parquet(str(tmp_path / "conversations.parquet"))
    for name in ("rerank_verifier_noschema", "rerank_verifier_chat"):
        assert picks(QUERIES[name](spark, str(tmp_path))) == {1: 1007, 2: 2002, 3: 3001}


def test_measures_without_denominator_are_null(spark):
    row = metrics.prf(from_rows(spark, [(1, 1, 1, False, False, 0.0)])).head()
    assert row["precision"] is None and row["recall"] is None and row["f1"] is None


def test_any_generator_fits(toy):
    assert beam_table(toy) is toy
    with pytest.raises(ValueError):
        beam_table(toy.drop("pos"))
