"""Clauses, component match, execution match, the IR and preprocessing."""

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from beamrank.functions import sqlshape, tokens
from beamrank.operators import execute, generators
from beamrank.plans import relational_queries, text_queries  # noqa: F401
from beamrank.plans.registry import QUERIES
from beamrank.plans.sql_queries import FOREIGN_KEYS, OWNER
from beamrank.sources.catalogue import GOLD

SF = "/root/testdata/sf0.001"


def test_all_gold_queries_parse():
    assert all(sqlshape.parts(q) for _, _, q, _ in GOLD)
    assert sqlshape.parts("selec a from t") is None and sqlshape.parts(None) is None and sqlshape.parts("select a from t where (b = 1") is None


def test_components_do_not_mind_order_or_alias():
    same = [
        ("select a from t where x = 1 and y < 2", "select a from t where y < 2 and x = 1"),
        ("select count(*) as n from t", "select count(*) as m from t"),
        ("select a from t where x between 1 and 2", "select a from t where x >= 1 and x <= 2"),
        ("select a from t join u on p = q", "select a from u join t on q = p"),
    ]
    for a, b in same:
        assert sqlshape.parts(a) == sqlshape.parts(b)
    for a, b in [("select a from t where x = 1", "select a from t where x = 2"), ("select a from t", "select distinct a from t"), ("select a from t where x = 1 or y = 2", "select a from t where x = 1 and y = 2")]:
        assert sqlshape.parts(a) != sqlshape.parts(b)
    assert sqlshape.parts(sqlshape.mask_literals("select a from t where x = 'q' and y = 2")) == sqlshape.parts(sqlshape.mask_literals("select a from t where x = 'r' and y = 7"))


def test_execution_match(spark):
    gold = "select r_name from region"
    texts = {
        "same": "select r_name as x from region order by r_name desc",
        "fewer": "select r_name from region where r_regionkey > 0",
        "twice": "select r_name from region union all select r_name from region",
        "nulls": "select cast(null as string) from region",
        "syntax": "selec r_name from region",
        "column": "select r_nme from region",
        "write": "drop table region",
    }
    prints = execute.fingerprints(spark, SF, [gold, *texts.values()])
    assert {k for k, q in texts.items() if prints[q] is not None and prints[q] == prints[gold]} == {"same"}
    assert {k for k, q in texts.items() if prints[q] is None} == {"syntax", "column", "write"}
    ordered = execute.fingerprints(spark, SF, [gold + " order by r_name", texts["same"]], ordered=True)
    assert len(set(ordered.values())) == 2
    execute.register(spark, SF)
    assert execute.strict_match(spark.sql(gold), spark.sql(texts["same"])).head()["same"]
    assert not execute.strict_match(spark.sql(gold), spark.sql(texts["twice"])).head()["same"]


def test_decoded_queries_give_the_same_rows(spark):
    pairs = []
    for _, _, q, _ in GOLD:
        ir, reason = sqlshape.encode(q, OWNER, FOREIGN_KEYS)
        assert (ir is None) == (reason is not None)
        if ir:
            pairs.append((q, sqlshape.decode(ir, OWNER, FOREIGN_KEYS)))
    assert len(pairs) >= 20
    prints = execute.fingerprints(spark, SF, list({t for p in pairs for t in p}))
    assert all(prints[a] is not None and prints[a] == prints[b] for a, b in pairs)


def test_udtf_gives_the_generators_beams(spark):
    got = sorted(tuple(r) for r in QUERIES["udtf_generate_beam"](spark, SF).collect())
    assert got == sorted((g, *item) for g, _, q, _ in GOLD for item in generators.beam(g, q, "udtf", 0.8, 0.9, True))


def test_a_failing_candidate_fails_alone(spark):
    texts = [f"select {i} as v" for i in range(10)] + ["select 1 / (r_regionkey - r_regionkey) as v from region"]
    prints = execute.fingerprints(spark, SF, texts)
    assert prints[texts[-1]] is None and len({prints[t] for t in texts[:-1]}) == 10


def test_order_counts_over_many_partitions(spark):
    up, down = "select o_orderkey from orders order by o_orderkey", "select o_orderkey from orders order by o_orderkey desc"
    again = "select o_orderkey from orders where o_orderkey >= 0 order by o_orderkey"
    prints = execute.fingerprints(spark, SF, [up, down, again], ordered=True)
    assert prints[up] == prints[again] != prints[down]
    assert len({execute.fingerprints(spark, SF, [q])[q] for q in (up, down, again)}) == 1


def test_nan_null_and_infinities_differ(spark):
    texts = [f"select cast('{x}' as double) as v" for x in ("NaN", "Infinity", "-Infinity", "1e300", "2e300")] + ["select cast(null as double) as v"]
    assert len(set(execute.fingerprints(spark, SF, texts).values())) == 6


@settings(max_examples=40, deadline=None)
@given(st.lists(st.text(alphabet="abXY_12 ='", max_size=20).filter(lambda t: t.count("'") % 2 == 0 and " _ " not in t and " ~ " not in t), min_size=1, max_size=8))
def test_preprocessing_can_be_undone(texts):
    from pyspark.sql import SparkSession

    spark = SparkSession.getActiveSession() or pytest.skip("no session")
    df = spark.createDataFrame([(t,) for t in texts], "t string").select("t", tokens.restore(tokens.apply(F.col("t"))).alias("r"))
    assert all(r["t"] == r["r"] for r in df.collect())


def test_boundaries_are_kept(spark):
    df = spark.createDataFrame([("pet_age",)], "t string")
    row = df.select(tokens.split_ident(F.col("t")).alias("own"), tokens.naive_pieces(F.col("t"), 2).alias("naive")).head()
    assert row["own"] == ["pet", "_", "age"] and row["naive"] == ["pe", "t_", "ag", "e"]


def test_every_generated_query_is_tested(spark):
    d = "/root/testdata/sf0.01"
    tested = {r["sql"] for r in QUERIES["synth_executable"](spark, d).collect()}
    assert tested == {r["sql"] for r in QUERIES["synth_pairs"](spark, d).select("sql").distinct().collect()}


def test_distances_of_candidates_from_their_gold_queries(spark):
    def distance(a, b):
        row = list(range(len(b) + 1))
        for i, x in enumerate(a, 1):
            last, row[0] = row[0], i
            for j, y in enumerate(b, 1):
                last, row[j] = row[j], min(row[j] + 1, row[j - 1] + 1, last + (x != y))
        return row[-1]

    import duckdb

    n_parts = QUERIES["candidate_sql_edit_distance"](spark, SF)
    assert any(f.endswith("part.parquet") for f in n_parts.inputFiles())
    got = sorted(map(tuple, n_parts.collect()))
    text = lambda r: f"select p_partkey from part where p_type = '{r[2]}' and p_size = {r[3]} and p_name = '{r[4]}'"
    rows = duckdb.sql(f"select p_partkey, p_brand, p_type, p_size, p_name from '{SF}/part.parquet' order by p_partkey").fetchall()
    gold = {}
    for r in rows:
        gold.setdefault(r[1], text(r))
    assert got == [(r[0], distance(text(r), gold[r[1]])) for r in rows]


def test_not_in_broadcasts_no_table(spark, monkeypatch):
    monkeypatch.setattr(execute, "SMALL", -1)
    own = execute._apart(spark, SF)
    for q in ("select o_orderkey from orders where o_orderkey not in (select l_orderkey from lineitem)", "select c_name from customer where c_custkey = 1 or c_custkey NOT IN ( select o_custkey from orders where o_orderstatus <> ')')"):
        plan = execute.planned(own, q)._jdf.queryExecution().executedPlan().toString()
        assert "Broadcast" not in plan and "SortMergeJoin" in plan
        assert sorted(execute.planned(own, q).collect()) == sorted(own.sql(q).collect())


def test_not_in_keeps_the_meaning_of_nulls(spark):
    own = execute._apart(spark, SF)
    left = "(values (1), (2), (cast(null as int))) as a(x)"
    for right, want in (("(1), (cast(null as int))", []), ("(1), (3)", [2]), ("(cast(null as int))", [])):
        for form in ("select x from {l} where x not in (select y from (values {r}) as b(y))", "select x from {l} where x = 7 or x not in (select y from (values {r}) as b(y))"):
            q = form.format(l=left, r=right)
            assert execute.anti_joined(own, q) != q and [r["x"] for r in execute.planned(own, q).collect()] == want
    empty = f"select x from {left} where x not in (select r_regionkey from region where r_name = 'none')"
    assert len(execute.planned(own, empty).collect()) == 3
    for q in ("select 'x not in (select 1)' as v", "select r_name from region r where r_regionkey not in (select n_nationkey from nation where n_regionkey = r_regionkey)"):
        assert sorted(execute.planned(own, q).collect()) == sorted(own.sql(q).collect())


def test_texts_run_with_the_settings_of_the_session_and_leave_no_views(spark):
    spark.catalog.dropTempView("supplier")
    assert execute.fingerprints(spark, SF, ["select count(*) as n from supplier"]) and not spark.catalog.tableExists("supplier")
    assert execute._apart(spark, SF).conf.get("spark.sql.shuffle.partitions") == spark.conf.get("spark.sql.shuffle.partitions")


def test_few_plans_are_on_the_driver_at_once(spark, monkeypatch):
    """Texts were all analysed, and their plans kept, before the first of them ran."""
    analysed, judged, most = set(), set(), [0]
    planned, run = execute.planned, execute._run

    def count_planned(own, sql):
        analysed.add(sql)
        most[0] = max(most[0], len(analysed) - len(judged))
        return planned(own, sql)

    def count_run(ready, ordered):
        found = run(ready, ordered)
        judged.update([f"select {df.first()[0]} as v" for _, df in ready])
        return found

    monkeypatch.setattr(execute, "planned", count_planned)
    monkeypatch.setattr(execute, "_run", count_run)
    texts = [f"select {i} as v" for i in range(24)]
    prints = execute.fingerprints(spark, SF, [*texts, "select no_such_column from region"])
    assert most[0] <= execute.BATCH * execute.JOBS + 1 <= 9
    assert list(prints) == [*texts, "select no_such_column from region"] and prints["select no_such_column from region"] is None
    assert len({prints[q] for q in texts}) == 24


def test_component_match_reads_part_and_equals_its_sql(spark):
    """These queries read no table."""
    import duckdb

    from beamrank.plans.registry import ORACLES

    con = duckdb.connect()
    con.execute(f"create view part as select * from '{SF}/part.parquet'")
    n = con.execute("select count(*) from part").fetchone()[0]
    for name in ("em_accuracy", "em_ignore_values"):
        df = QUERIES[name](spark, SF)
        assert any(f.endswith("part.parquet") for f in df.inputFiles())
        got = sorted(map(tuple, df.collect()))
        assert got == sorted(con.execute(ORACLES[name]).fetchall())
        assert dict((k, c) for k, _, c in got)["alias"] == n
    shares = QUERIES["em_by_component"](spark, SF).head().asDict()
    # of the 12 edits that parse, two change a limit or what is distinct: each stands for as many parts
    assert shares["match_limit"] == shares["match_distinct"] == pytest.approx(11 / 12, abs=1e-6)


def test_plan_match_and_compactness_are_of_queries_generated_from_the_tables(spark):
    """These queries read no table."""
    pairs = [r["sql"] for r in QUERIES["synth_pairs"](spark, SF).collect()]
    plans = {(r["gold"], r["kind"]): r["same_plan"] for r in QUERIES["em_plan"](spark, SF).collect()}
    assert {g for g, k in plans} == set(pairs) and all(plans[g, "gold"] for g in set(pairs))
    assert not any(same for (_, k), same in plans.items() if k in ("comparison", "condition", "syntax"))
    got = QUERIES["ir_compactness"](spark, SF).head()
    texts = [(q, sqlshape.encode(q, OWNER, FOREIGN_KEYS)[0]) for q in pairs]
    kept = [(q, sqlshape.ir_text(ir)) for q, ir in texts if ir]
    assert (got["queries"], got["ir_tokens"], got["sql_tokens"]) == (len(kept), sum(len(t.split()) for _, t in kept), sum(len(sqlshape.tokenize(q)) for q, _ in kept))


def test_texts_of_the_same_plan_run_once(spark, monkeypatch):
    """Each distinct text ran, also those that differ in names only."""
    ran, run = [], execute._run
    monkeypatch.setattr(execute, "_run", lambda ready, ordered: ran.extend(i for i, _ in ready) or run(ready, ordered))
    texts = [
        "select count(*) as n from nation where n_regionkey >= 1 and n_nationkey < 20", "select count(*) as cnt from nation where n_regionkey >= 1 and n_nationkey < 20",
        "select count(*) as n from nation where n_regionkey >= 1 and n_nationkey < 21", "select count(*) as n from nation where n_regionkey >= 2 and n_nationkey < 20",
        "select n_nationkey as x, n_regionkey as y from nation", "select n_regionkey as x, n_nationkey as y from nation", "select n_nationkey as a, n_regionkey as b from nation",
        "select n_name from nation where n_nationkey < 0", "select n_name, n_name from nation where n_nationkey < 0", "select no_such_column from nation",
    ]
    prints = execute.fingerprints(spark, SF, texts)
    assert list(prints) == texts and len(ran) == 7
    alone = {}
    for q in texts:
        alone |= execute.fingerprints(spark, SF, [q])
    assert prints == alone and prints[texts[0]] == prints[texts[1]] and prints[texts[4]] == prints[texts[6]] != prints[texts[5]]
    assert prints[texts[7]][:2] == (1, 0) and prints[texts[8]][:2] == (2, 0) and prints[texts[9]] is None
    # a bag of its own, as the aggregate of one text gives it
    own = execute._apart(spark, SF)
    assert [prints[q] for q in texts[:9]] == [tuple(execute.fingerprint(own.sql(q)).first()) for q in texts[:9]]
