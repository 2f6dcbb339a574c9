"""Sources and sinks."""

from pyspark.sql import functions as F

from beamrank.operators import rerank
from beamrank.sources.io import csv_round_trip, json_round_trip, save_bucketed, write_beams
from beamrank.sources.tables import line_beams, schema_columns, table

SF = "/root/testdata/sf0.001"


def test_round_trips(spark):
    for df in (table(spark, SF, "customer"), table(spark, SF, "nation")):
        assert sorted(csv_round_trip(df).collect()) == sorted(json_round_trip(df).collect()) == sorted(df.collect())


def test_partitioned_beams(spark, tmp_path):
    rows = line_beams(spark, SF).withColumn("split", F.when(F.col("beam_id") % 5 < 4, "train").otherwise("dev"))
    write_beams(rows, str(tmp_path / "b"), "split")
    back = spark.read.parquet(str(tmp_path / "b")).where("split = 'dev'")
    assert "PartitionFilters: [isnotnull(split" in back._jdf.queryExecution().toString()
    assert back.count() == rows.where("split = 'dev'").count()


def test_bucketed_beams_need_no_exchange(spark):
    save_bucketed(line_beams(spark, SF), "beams_bucketed", 4)
    picked = rerank.top1(spark.table("beams_bucketed"))
    assert "Exchange" not in picked._jdf.queryExecution().executedPlan().toString()
    assert picked.count() == line_beams(spark, SF).select("beam_id").distinct().count()
    spark.sql("drop table beams_bucketed")


def test_schema_columns(spark):
    cols = schema_columns(spark, SF)
    assert cols.where("fk_table is not null").count() == 8 and cols.where("table_name = 'lineitem'").count() == 11


def test_plans_prune_and_push(spark):
    from beamrank.plans.catalog import QUERIES

    plan = QUERIES["scan_pruned"](spark, SF)._jdf.queryExecution().executedPlan().toString()
    assert "GreaterThanOrEqual(l_quantity,30.0)" in plan and "ReadSchema: struct<l_quantity:double,l_returnflag:string>" in plan
    plan = QUERIES["beam_first5"](spark, SF)._jdf.queryExecution().executedPlan().toString()
    assert "WindowGroupLimit" in plan
    plan = QUERIES["rerank_verifier"](spark, SF)._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange hashpartitioning") == 1 and "SortAggregate" not in plan
