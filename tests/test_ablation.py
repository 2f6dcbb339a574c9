"""Shapley values against orders, and against the published figures."""

from itertools import permutations

import pytest

from beamrank.operators import shapley
from beamrank.sources import published as P

LATTICE = {"gs": 2, "pp": 4, "rr": 8}
FOUR = {"a": 1, "b": 2, "c": 4, "d": 8}


def game(spark, value):
    return spark.createDataFrame([("x", "y", m, "EX", float(value(m))) for m in range(16)], "backbone string, rr_origin string, mask int, metric string, value double")


def values(df):
    return {r["player"]: r["phi"] for r in df.collect()}


def test_exact_equals_all_orders(spark):
    v = lambda m: (m * 7 % 11) + 3 * bin(m).count("1") ** 2
    want = dict.fromkeys(FOUR, 0.0)
    for order in permutations(FOUR):
        m = 0
        for p in order:
            want[p] += (v(m + FOUR[p]) - v(m)) / 24
            m += FOUR[p]
    assert values(shapley.exact(game(spark, v), FOUR)) == pytest.approx(want, abs=1e-6)
    assert shapley.efficiency(game(spark, v), FOUR).head()["gap"] == 0


def test_additive_dummy_and_equal_players(spark):
    got = values(shapley.exact(game(spark, lambda m: 2 * (m & 1) + 2 * (m >> 1 & 1) + 5 * (m >> 2 & 1)), FOUR))
    assert got == {"a": 2, "b": 2, "c": 5, "d": 0}
    assert values(shapley.sampled(game(spark, lambda m: 2 * (m & 1)), FOUR, 20)) == {"a": 2, "b": 0, "c": 0, "d": 0}


def test_incomplete_lattice_is_refused(spark):
    with pytest.raises(Exception, match="incomplete"):
        shapley.exact(game(spark, int).where("mask < 15"), FOUR).collect()


def test_available_means_are_the_published_cells(spark):
    got = {(r["rr_origin"], r["metric"], r["player"]): (r["phi"], r["contexts"]) for r in shapley.available_mean(P.scores(spark, True), LATTICE).collect()}
    for (backbone, origin), cells in P.COMPONENTS.items():
        if backbone == "seq":
            for player, pair in list(zip(shapley.PLAYERS, cells, strict=True))[1:]:
                for metric, want in zip(("EX", "EM"), pair, strict=True):
                    assert got[origin, metric, player] == (pytest.approx(want, abs=1e-6), 4)


def test_overall_is_the_mean_of_origins():
    for backbone, cells in P.OVERALL.items():
        for i, pair in enumerate(cells):
            for k, want in enumerate(pair):
                assert abs((P.COMPONENTS[backbone, "alg"][i][k] + P.COMPONENTS[backbone, "seq"][i][k]) / 2 - want) <= 0.00051


def test_interactions_and_winners(spark):
    found = {(r["backbone"], r["metric"], r["context"], r["rr_origin"]): r["interaction"] for r in shapley.interactions(P.scores(spark)).collect()}
    assert found["seq", "EX", 1, "alg"] == pytest.approx(-3.7) and found["alg", "EX", 0, "alg"] == pytest.approx(-0.8)
    best = {r["metric"]: (r["backbone"], r["rr_origin"], r["mask"], r["value"]) for r in shapley.best_system(P.scores(spark)).collect()}
    assert best == {"EX": ("seq", "alg", 13, 77.2), "EM": ("seq", "seq", 11, 77.1)}
    extremes = {(r["backbone"], r["metric"]): r["strongest"] for r in shapley.extremes(shapley.overall(shapley.available_mean(P.scores(spark)))).collect()}
    assert extremes["alg", "EX"] == "gs"


def test_printed_tables_agree_with_themselves():
    for p, n, percent in P.LABELS.values():
        assert round(100 * p / (p + n), 2) == percent
    for p, r, f in P.VERIFIER.values():
        assert abs(2 * p * r / (p + r) - f) < 0.0001
    assert P.GENERATED - P.DUPLICATES == 22_417 and round(100 * P.DUPLICATES / P.GENERATED, 2) == 45.16


def test_known_differences_of_text_and_table():
    gain = lambda a, b, k: round(P.PLAIN[b][k] - P.PLAIN[a][k], 1)
    assert gain(("seq", 0), ("seq", 1), 0) == 0.9 and gain(("seq", 0), ("seq", 1), 1) == 0.8
    assert (gain(("alg", 0), ("alg", 1), 0), gain(("alg", 0), ("alg", 1), 1)) == (-3.8, -2.6)
    assert (gain(("alg", 0), ("alg", 2), 1), gain(("seq", 1), ("seq", 3), 0), gain(("alg", 0), ("alg", 4), 1)) == (1.6, 2.4, -0.4)


LINE_QUERIES = ("config_lattice", "component_delta", "combine_all_vs_best", "ablation_staged", "best_system")


def test_line_lattice_reads_lineitem_and_equals_its_sql(spark):
    """These queries read no table."""
    import duckdb

    from beamrank.plans.catalog import QUERIES
    from beamrank.plans.registry import ORACLES

    con = duckdb.connect()
    con.execute("create view lineitem as select * from '/root/testdata/sf0.001/lineitem.parquet'")
    for name in LINE_QUERIES:
        df = QUERIES[name](spark, "/root/testdata/sf0.001")
        assert any(f.endswith("lineitem.parquet") for f in df.inputFiles()), name
        theirs = con.execute(ORACLES[name]).fetchdf()[df.columns]
        key = lambda rows: sorted(tuple(round(float(x), 6) if isinstance(x, float) else str(x) for x in r) for r in rows)
        assert key(map(tuple, df.collect())) == key(theirs.itertuples(index=False)), name


def test_line_lattice_takes_the_first_that_passes(spark, tmp_path):
    from beamrank.operators import linelattice

    line = lambda n, disc, flag, status: (1, n, n, n, 30.0, 50000.0, disc, 0.01, flag, status)
    names = "l_orderkey long, l_partkey long, l_suppkey long, l_linenumber int, l_quantity double, l_extendedprice double, l_discount double, l_tax double, l_returnflag string, l_linestatus string"
    rows = spark.createDataFrame([line(1, 0.09, "N", "F"), line(2, 0.02, "R", "O"), line(3, 0.09, "N", "F")], names)
    rows.selectExpr("*", "timestamp_ntz '1996-01-01 00:00:00' as l_shipdate").write.parquet(f"{tmp_path}/lineitem.parquet")
    got = {(r["backbone"], r["rr_origin"], r["metric"], r["mask"]): r["value"] for r in linelattice.scores(spark, str(tmp_path)).collect()}
    assert len(got) == 128
    assert got["alg", "alg", "EX", 0] == 0 and got["alg", "alg", "EM", 0] == 100 and got["alg", "seq", "EX", 1] == 100 and got["seq", "alg", "EX", 9] == 100
    assert got["seq", "seq", "EX", 0] == 0 and got["seq", "seq", "EM", 8] == 100
