"""Trained generators, verifiers and selectors on the catalogue."""

from beamrank.functions import sqlshape
from beamrank.operators import lattice, shapley
from beamrank.plans import measured_queries as M
from beamrank.plans.catalog import QUERIES

SF = "/root/testdata/sf0.001"


def test_spread_fits_equal_local_ones(spark):
    got = sorted((r["gold_id"], r["pos"], r["sql"], r["em"]) for r in lattice.generated(spark, lattice.configurations([("seq", 3)])).collect())
    assert got == sorted((g, p, q, em) for g, p, q, _, em in lattice.system("seq", 3))


def test_folds_keep_training_apart(monkeypatch):
    seen = []
    monkeypatch.setattr(lattice, "_rows", lambda items, *_: seen.extend(k for k, *_ in items) or (lattice.np.zeros((0, 1)), lattice.np.zeros(0)))
    lattice.train_generator("seq", 0, 2)
    assert seen and all(lattice.fold_of(g) != 2 for g in seen)


def test_beams_hold_distinct_candidates_and_the_algebra_backbone_parses():
    for b, m in lattice.ALL:
        for g, rows in lattice._by_question(lattice.system(b, m)).items():
            texts = [q for q, _ in rows]
            assert len(set(texts)) == len(texts) <= lattice.WIDTH and g in lattice.QUESTIONS
            if b == "alg":
                assert all(not q.startswith("selec ") for q in texts)


def test_synthetic_queries_have_no_duplicates_and_parse():
    rows = lattice.synthetic()
    assert len({(q, s) for _, q, s, _ in rows}) == len(rows) > 100
    assert all(sqlshape.parts(s) for _, _, s, _ in rows)


def test_verifiers_and_selectors_beat_the_plain_choice(spark):
    for origin in lattice.ORIGINS:
        rows = lattice.verifier_rows(origin)
        right = [(lattice.verdict(origin, True, g, q) >= 0.5) == ok for g, _, q, ok in rows]
        majority = max(sum(ok for *_, ok in rows), sum(not ok for *_, ok in rows))
        assert sum(right) > majority
        found = lattice._by_question(lattice.system(*lattice.ORIGINS[origin]))
        plain = sum(rows[0][1] for rows in found.values())
        for name in ("verifier", "selector", "hybrid"):
            assert sum(rows[lattice.rerank(name, origin, g, [q for q, _ in rows])][1] for g, rows in found.items()) > plain


def test_gold_query_is_in_every_training_beam():
    for origin in lattice.ORIGINS:
        rows = lattice.verifier_rows(origin)
        for g in lattice.QUESTIONS:
            own = [(pos, q, ok) for x, pos, q, ok in rows if x == g]
            assert any(ok for *_, ok in own) and [p for p, *_ in own] == list(range(1, len(own) + 1)) and len(own) <= 5


def test_measured_shapley_values_sum_to_the_gain(spark):
    scores = M.measured_scores(spark, SF).collect()
    value = {(r["backbone"], r["rr_origin"], r["metric"], r["mask"]): r["value"] for r in scores}
    assert len(value) == 2 * 2 * 2 * 16
    sums = {}
    for r in shapley.exact(M.measured_scores(spark, SF)).collect():
        key = (r["backbone"], r["rr_origin"], r["metric"])
        sums[key] = sums.get(key, 0) + r["phi"]
    assert all(abs(s - value[*k, 15] + value[*k, 0]) < 1e-4 for k, s in sums.items())


def test_training_on_synthetic_pairs_helps(spark):
    rows = {(r["backbone"], r["stages"]): r["em"] for r in QUERIES["two_stage_accuracy"](spark, SF).collect()}
    assert rows["seq", "both"] > rows["seq", "gold"] and rows["alg", "both"] > rows["alg", "gold"]
