"""The registry: names, oracles and the flagship."""

import duckdb

import __spark_entry__ as entry
from beamrank.operators import synth
from beamrank.sources.tables import TABLES

SF = "/root/testdata/sf0.001"


def test_oracles_have_queries():
    queries, oracles = entry.queries(), entry.oracle_sql()
    assert set(oracles) <= set(queries) and len(queries) > 130


def test_flagship(spark):
    df = entry.entry(spark)
    assert df.columns == ["beam_id", "item_id", "correct"] and df.count() > 0


def test_some_queries_equal_their_sql(spark):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"create view {t} as select * from '{SF}/{t}.parquet'")
    queries, oracles = entry.queries(), entry.oracle_sql()
    for name in ("rerank_hybrid_score", "gold_front5", "join_asof_event", "synth_dedup", "stream_session", "shapley_two_rerankers"):
        ours = queries[name](spark, SF).toPandas()
        theirs = con.execute(oracles[name]).fetchdf()[list(ours.columns)]
        key = lambda df: sorted(map(str, df.round(6).astype(str).itertuples(index=False)))
        assert key(ours) == key(theirs), name


def test_synthesis_is_nested_and_deduplicated(spark):
    pairs = synth.generate(spark, SF, 800)
    assert pairs.count() == 800
    kept = synth.dedup(pairs, "question", "sql")
    rate = synth.dup_rate(pairs, "question", "sql").head()
    assert kept.count() + rate["duplicates"] == rate["generated"] == 800
    assert synth.dedup(kept, "question", "sql").count() == kept.count()
    by = {r["share"]: r["n"] for r in synth.sizes(kept, [0.2, 0.6, 1.0]).groupBy("share").count().withColumnRenamed("count", "n").collect()}
    assert by.get(0.2, 0) <= by[0.6] <= by[1.0] == kept.count()
