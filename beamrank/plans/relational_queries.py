"""Operators that users of the methods need around them, on the given tables."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from beamrank.operators import generators
from beamrank.plans.registry import query
from beamrank.sources.catalogue import GOLD
from beamrank.sources.io import csv_round_trip, json_round_trip
from beamrank.sources.tables import LINE_SQL, line_beams, table

LINE = f"with {LINE_SQL}"
MONEY = "decimal(18,2)"


@query("scan_pruned", "select l_returnflag, count(*) as n from lineitem where l_quantity >= 30 group by l_returnflag")
def scan_pruned(spark, d):
    return table(spark, d, "lineitem").where("l_quantity >= 30").groupBy("l_returnflag").agg(F.count(F.lit(1)).alias("n"))


@query("scan_csv_roundtrip", "select n_nationkey, n_name, n_regionkey from nation")
def scan_csv_roundtrip(spark, d):
    return csv_round_trip(table(spark, d, "nation"))


@query("scan_json_roundtrip", "select p_partkey, p_name, p_size, p_retailprice from part")
def scan_json_roundtrip(spark, d):
    return json_round_trip(table(spark, d, "part").select("p_partkey", "p_name", "p_size", "p_retailprice"))


@query("filter_predicates", "select o_orderkey from orders where o_totalprice between 1000 and 200000 and o_orderstatus in ('F', 'O') and o_orderpriority like '1-%' and o_orderdate is not null")
def filter_predicates(spark, d):
    o = table(spark, d, "orders")
    return o.where(F.col("o_totalprice").between(1000, 200000) & F.col("o_orderstatus").isin("F", "O") & F.col("o_orderpriority").like("1-%") & F.col("o_orderdate").isNotNull()).select("o_orderkey")


@query("project_exprs", "select l_orderkey, l_linenumber, l_partkey, l_suppkey, (l_extendedprice::decimal(18,2) * (1 - l_discount::decimal(18,2)))::double as net, case when l_quantity > 25 then 'big' else 'small' end as size from lineitem")
def project_exprs(spark, d):
    return table(spark, d, "lineitem").select("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", (F.col("l_extendedprice").cast(MONEY) * (1 - F.col("l_discount").cast(MONEY))).cast("double").alias("net"), F.when(F.col("l_quantity") > 25, "big").otherwise("small").alias("size"))


@query("join_inner", "select n_name, count(*) as n from customer join nation on c_nationkey = n_nationkey group by n_name")
def join_inner(spark, d):
    return table(spark, d, "customer").join(F.broadcast(table(spark, d, "nation")), F.expr("c_nationkey = n_nationkey")).groupBy("n_name").agg(F.count(F.lit(1)).alias("n"))


@query("join_left", "select o_orderkey, count(l_orderkey) as lines from orders left join lineitem on o_orderkey = l_orderkey group by o_orderkey")
def join_left(spark, d):
    lines = table(spark, d, "lineitem").groupBy("l_orderkey").agg(F.count(F.lit(1)).alias("n"))
    return table(spark, d, "orders").join(lines, F.expr("o_orderkey = l_orderkey"), "left").select("o_orderkey", F.coalesce("n", F.lit(0)).alias("lines"))


@query("join_full", "select coalesce(c, s) as nation, coalesce(nc, 0) as customers, coalesce(ns, 0) as suppliers from (select c_nationkey as c, count(*) as nc from customer group by 1) full join (select s_nationkey as s, count(*) as ns from supplier group by 1) on c = s")
def join_full(spark, d):
    c = table(spark, d, "customer").groupBy(F.col("c_nationkey").alias("nation")).agg(F.count(F.lit(1)).alias("customers"))
    s = table(spark, d, "supplier").groupBy(F.col("s_nationkey").alias("nation")).agg(F.count(F.lit(1)).alias("suppliers"))
    return c.join(s, "nation", "full").select("nation", F.coalesce("customers", F.lit(0)).alias("customers"), F.coalesce("suppliers", F.lit(0)).alias("suppliers"))


@query("join_semi_has_correct", "select o_orderkey from orders where exists (select 1 from lineitem where l_orderkey = o_orderkey and l_returnflag = 'R')")
def join_semi_has_correct(spark, d):
    right = table(spark, d, "lineitem").where("l_returnflag = 'R'").select(F.col("l_orderkey").alias("o_orderkey"))
    return table(spark, d, "orders").select("o_orderkey").join(right, "o_orderkey", "left_semi")


@query("join_anti_uncovered", "select o_orderkey from orders where not exists (select 1 from lineitem where l_orderkey = o_orderkey and l_returnflag = 'R')")
def join_anti_uncovered(spark, d):
    right = table(spark, d, "lineitem").where("l_returnflag = 'R'").select(F.col("l_orderkey").alias("o_orderkey"))
    return table(spark, d, "orders").select("o_orderkey").join(right, "o_orderkey", "left_anti")


@query("join_theta_sweep", f"{LINE}, t as (select unnest([0, 10, 20, 30, 40, 50]) as theta) select theta, count(*) filter (correct and score >= theta) as tp, count(*) filter (not correct and score >= theta) as fp from line_beams, t group by theta")
def join_theta_sweep(spark, d):
    """Counts for every threshold from one histogram of scores, summed from above; no pair of item and threshold is made."""
    cells = line_beams(spark, d).groupBy("score").agg(F.count_if("correct").alias("tp"), F.count_if(~F.col("correct")).alias("fp"))
    theta = F.broadcast(spark.createDataFrame([(x,) for x in (0, 10, 20, 30, 40, 50)], "theta int"))
    joined = theta.join(cells, F.col("score") >= F.col("theta"), "left")
    return joined.groupBy("theta").agg(F.coalesce(F.sum("tp"), F.lit(0)).alias("tp"), F.coalesce(F.sum("fp"), F.lit(0)).alias("fp"))


@query("join_range_bucket", f"{LINE}, b as (select unnest(range(0, 5)) as b) select b, count(*) as n from line_beams join b on score > b * 10 and score <= b * 10 + 10 group by b")
def join_range_bucket(spark, d):
    """A range join over equal ranges, as an equality of computed buckets."""
    ranges = spark.range(5).select(F.col("id").alias("b"))
    items = line_beams(spark, d).select((F.ceil(F.col("score") / 10) - 1).alias("b"))
    return items.groupBy("b").agg(F.count(F.lit(1)).alias("n")).join(F.broadcast(ranges), "b").select("b", "n")


@query("join_asof_event", "select event_id, (select max(p.ts) from events p where p.user_id = e.user_id and p.event_type = 'purchase' and p.ts <= e.ts) as last_purchase from events e where event_type = 'view'")
def join_asof_event(spark, d):
    """The last purchase up to each view, by a running maximum over each user's events: one exchange."""
    e = table(spark, d, "events")
    upto = W.partitionBy("user_id").orderBy("ts").rangeBetween(W.unboundedPreceding, W.currentRow)
    return e.withColumn("last_purchase", F.max(F.when(F.col("event_type") == "purchase", F.col("ts"))).over(upto)).where("event_type = 'view'").select("event_id", "last_purchase")


@query("join_interval_event", "select s.event_id, count(e.event_id) as n from events s join events e on s.user_id = e.user_id and e.ts >= s.ts and e.ts <= s.ts + interval 1 hour where s.event_type = 'signup' group by s.event_id")
def join_interval_event(spark, d):
    """Events within an hour of each signup: a band join on hour buckets, each signup in two."""
    e = table(spark, d, "events")
    hour = lambda c: F.unix_micros(c.cast("timestamp")).cast("double") / 3.6e9
    s = e.where("event_type = 'signup'").select("event_id", "user_id", F.col("ts").alias("start"), F.explode(F.array(F.floor(hour(F.col("ts"))), F.floor(hour(F.col("ts"))) + 1)).alias("bucket"))
    others = e.select("user_id", "ts", F.floor(hour(F.col("ts"))).alias("bucket"))
    pairs = s.join(others, ["user_id", "bucket"]).where("ts >= start and ts <= start + interval 1 hour")
    return pairs.groupBy("event_id").agg(F.count(F.lit(1)).alias("n"))


@query("join_cross_lattice", "select r_name, mask from region, (select unnest(range(16))::int as mask)")
def join_cross_lattice(spark, d):
    """Both sides are of fixed size: five regions and sixteen masks."""
    return table(spark, d, "region").select("r_name").crossJoin(F.broadcast(spark.range(16).select(F.col("id").cast("int").alias("mask"))))


@query("agg_basic", "select l_returnflag, l_linestatus, count(*) as n, sum(cast(l_quantity as decimal(18,2)))::double as quantity, min(l_shipdate) as first_ship, max(l_extendedprice) as dearest from lineitem group by 1, 2")
def agg_basic(spark, d):
    return table(spark, d, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("l_quantity").cast(MONEY)).cast("double").alias("quantity"), F.min("l_shipdate").alias("first_ship"), F.max("l_extendedprice").alias("dearest"))


@query("agg_distinct", "select l_returnflag, count(distinct l_partkey) as parts, count(distinct l_suppkey) as suppliers from lineitem group by 1")
def agg_distinct(spark, d):
    return table(spark, d, "lineitem").groupBy("l_returnflag").agg(F.count_distinct("l_partkey").alias("parts"), F.count_distinct("l_suppkey").alias("suppliers"))


@query("agg_filter", "select o_orderstatus, count(*) filter (o_totalprice > 250000) as dear, count(*) as n from orders group by 1")
def agg_filter(spark, d):
    return table(spark, d, "orders").groupBy("o_orderstatus").agg(F.count_if(F.col("o_totalprice") > 250000).alias("dear"), F.count(F.lit(1)).alias("n"))


FLAGS = "select case when beam_id % 5 < 4 then 'train' else 'dev' end as split, case when correct then 'right' else 'wrong' end as label from line_beams"


def _flags(spark, d):
    return line_beams(spark, d).select(F.when(F.col("beam_id") % 5 < 4, "train").otherwise("dev").alias("split"), F.when(F.col("correct"), "right").otherwise("wrong").alias("label"))


@query("agg_rollup", f"{LINE} select coalesce(split, 'all') as split, coalesce(label, 'all') as label, count(*) as n from ({FLAGS}) group by rollup (split, label)")
def agg_rollup(spark, d):
    return _flags(spark, d).rollup("split", "label").agg(F.count(F.lit(1)).alias("n")).na.fill("all", ["split", "label"])


@query("agg_cube", f"{LINE} select coalesce(split, 'all') as split, coalesce(label, 'all') as label, count(*) as n from ({FLAGS}) group by cube (split, label)")
def agg_cube(spark, d):
    return _flags(spark, d).cube("split", "label").agg(F.count(F.lit(1)).alias("n")).na.fill("all", ["split", "label"])


@query("agg_grouping_sets", f"{LINE} select coalesce(split, 'all') as split, coalesce(label, 'all') as label, count(*) as n from ({FLAGS}) group by grouping sets ((split), (label))")
def agg_grouping_sets(spark, d):
    return _flags(spark, d).groupingSets([["split"], ["label"]], "split", "label").agg(F.count(F.lit(1)).alias("n")).na.fill("all", ["split", "label"])


@query("agg_pivot", "select o_orderpriority, count(*) filter (o_orderstatus = 'F') as f, count(*) filter (o_orderstatus = 'O') as o, count(*) filter (o_orderstatus = 'P') as p from orders group by 1")
def agg_pivot(spark, d):
    return table(spark, d, "orders").groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O", "P"]).count().na.fill(0).toDF("o_orderpriority", "f", "o", "p")


@query("approx_distinct", "select true as close")
def approx_distinct(spark, d):
    """Whether the sketch of distinct users is within five percent."""
    return table(spark, d, "events").agg((F.abs(F.approx_count_distinct("user_id", 0.01) / F.count_distinct("user_id") - 1) <= 0.05).alias("close"))


@query("agg_percentiles", "select o_orderstatus, round(quantile_cont(o_totalprice, 0.5), 4) as median, round(quantile_cont(o_totalprice, 0.9), 4) as p90 from orders group by 1")
def agg_percentiles(spark, d):
    return table(spark, d, "orders").groupBy("o_orderstatus").agg(F.round(F.percentile("o_totalprice", 0.5), 4).alias("median"), F.round(F.percentile("o_totalprice", 0.9), 4).alias("p90"))


@query("win_ranking", f"{LINE} select beam_id, pos, row_number() over w as rn, rank() over w as rk, dense_rank() over w as dr, ntile(3) over (partition by beam_id order by score desc, pos) as third, round(percent_rank() over w, 6) as pr from line_beams window w as (partition by beam_id order by score desc, pos)")
def win_ranking(spark, d):
    w = W.partitionBy("beam_id").orderBy(F.desc("score"), "pos")
    return line_beams(spark, d).select("beam_id", "pos", F.row_number().over(w).alias("rn"), F.rank().over(w).alias("rk"), F.dense_rank().over(w).alias("dr"), F.ntile(3).over(w).alias("third"), F.round(F.percent_rank().over(w), 6).alias("pr"))


@query("win_lag_lead", f"{LINE} select beam_id, pos, coalesce(score - lag(score) over w, 0) as rise, coalesce(lead(score) over w, -1) as ahead, first_value(score) over w as top from line_beams window w as (partition by beam_id order by pos)")
def win_lag_lead(spark, d):
    w = W.partitionBy("beam_id").orderBy("pos")
    return line_beams(spark, d).select("beam_id", "pos", F.coalesce(F.col("score") - F.lag("score").over(w), F.lit(0.0)).alias("rise"), F.coalesce(F.lead("score").over(w), F.lit(-1.0)).alias("ahead"), F.first("score").over(w).alias("top"))


@query("win_running_gain", f"{LINE} select beam_id, pos, max(correct::int) over (partition by beam_id order by pos) as covered from line_beams")
def win_running_gain(spark, d):
    w = W.partitionBy("beam_id").orderBy("pos").rowsBetween(W.unboundedPreceding, 0)
    return line_beams(spark, d).select("beam_id", "pos", F.max(F.col("correct").cast("int")).over(w).alias("covered"))


@query("win_sliding", f"{LINE} select beam_id, pos, round(avg(score) over (partition by beam_id order by pos rows between 1 preceding and 1 following), 6) as around from line_beams")
def win_sliding(spark, d):
    w = W.partitionBy("beam_id").orderBy("pos").rowsBetween(-1, 1)
    return line_beams(spark, d).select("beam_id", "pos", F.round(F.avg("score").over(w), 6).alias("around"))


@query("win_range", f"{LINE} select beam_id, pos, count(*) over (partition by beam_id order by score range between 5 preceding and 5 following) as near from line_beams")
def win_range(spark, d):
    w = W.partitionBy("beam_id").orderBy("score").rangeBetween(-5, 5)
    return line_beams(spark, d).select("beam_id", "pos", F.count(F.lit(1)).over(w).alias("near"))


@query("topk_global", "select o_orderkey, o_totalprice from orders order by o_totalprice desc, o_orderkey limit 20")
def topk_global(spark, d):
    return table(spark, d, "orders").select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(20)


@query("topk_per_beam", f"{LINE} select beam_id, pos, score from (select *, row_number() over (partition by beam_id order by score desc, pos) as r from line_beams) where r <= 3")
def topk_per_beam(spark, d):
    w = W.partitionBy("beam_id").orderBy(F.desc("score"), "pos")
    return line_beams(spark, d).withColumn("r", F.row_number().over(w)).where("r <= 3").select("beam_id", "pos", "score")


@query("limit_offset", "select p_partkey from part order by p_partkey limit 10 offset 5")
def limit_offset(spark, d):
    return table(spark, d, "part").select("p_partkey").orderBy("p_partkey").offset(5).limit(10)


@query("set_union", "select c_nationkey as k from customer union select s_nationkey from supplier")
def set_union(spark, d):
    return table(spark, d, "customer").select(F.col("c_nationkey").alias("k")).union(table(spark, d, "supplier").select("s_nationkey")).distinct()


@query("set_union_by_name", "select c_name as name, c_acctbal as balance from customer union all select s_name, s_acctbal from supplier")
def set_union_by_name(spark, d):
    c = table(spark, d, "customer").select(F.col("c_name").alias("name"), F.col("c_acctbal").alias("balance"))
    return c.unionByName(table(spark, d, "supplier").select(F.col("s_acctbal").alias("balance"), F.col("s_name").alias("name")))


@query("set_intersect", "select p_brand from part where p_size < 5 intersect select p_brand from part where p_size > 45")
def set_intersect(spark, d):
    p = table(spark, d, "part")
    return p.where("p_size < 5").select("p_brand").intersect(p.where("p_size > 45").select("p_brand"))


@query("set_except", "select user_id from events where event_type = 'view' except select user_id from events where event_type = 'refund'")
def set_except(spark, d):
    e = table(spark, d, "events")
    return e.where("event_type = 'view'").select("user_id").subtract(e.where("event_type = 'refund'").select("user_id"))


@query("set_except_all", "select o_orderpriority from orders where o_orderstatus = 'F' except all select o_orderpriority from orders where o_orderstatus = 'P'")
def set_except_all(spark, d):
    o = table(spark, d, "orders")
    return o.where("o_orderstatus = 'F'").select("o_orderpriority").exceptAll(o.where("o_orderstatus = 'P'").select("o_orderpriority"))


@query("fn_string", "select p_partkey, lower(p_name) as low, upper(substr(p_brand, 1, 3)) as head, len(string_split(p_name, ' '))::int as words, concat_ws('-', p_brand, p_type) as tag, md5(p_name) as digest, regexp_replace(p_name, '[aeiou]', '', 'g') as bare, length(trim(p_name))::int as n from part")
def fn_string(spark, d):
    return table(spark, d, "part").select("p_partkey", F.lower("p_name").alias("low"), F.upper(F.substring("p_brand", 1, 3)).alias("head"), F.size(F.split("p_name", " ")).alias("words"), F.concat_ws("-", "p_brand", "p_type").alias("tag"), F.md5("p_name").alias("digest"), F.regexp_replace("p_name", "[aeiou]", "").alias("bare"), F.length(F.trim("p_name")).alias("n"))


@query("candidate_edit_distance", "with c as (select n_nationkey as k, n_name as a, lead(n_name) over (order by n_name) as b from nation) select k, levenshtein(a, b)::int as distance from c where b is not null")
def candidate_edit_distance(spark, d):
    c = table(spark, d, "nation").select(F.col("n_nationkey").alias("k"), F.col("n_name").alias("a"), F.lead("n_name").over(W.orderBy("n_name")).alias("b"))
    return c.where("b is not null").select("k", F.levenshtein("a", "b").alias("distance"))


#: A query that finds a part by its values.
PART_QUERY = """'select p_partkey from part where p_type = ''' || p_type || ''' and p_size = ' || p_size || ' and p_name = ''' || p_name || ''''"""


@query("candidate_sql_edit_distance", f"with c as (select p_partkey, p_brand, {PART_QUERY} as sql from part), g as (select p_brand, arg_min(sql, p_partkey) as gold from c group by p_brand) select p_partkey, levenshtein(sql, gold)::int as distance from c join g using (p_brand)")
def candidate_sql_edit_distance(spark, d):
    """Distance of the query that finds each part from the query for the first part of its brand."""
    texts = F.lit("select p_partkey from part where p_type = '"), F.lit("' and p_size = "), F.lit(" and p_name = '"), F.lit("'")
    sql = F.concat(texts[0], "p_type", texts[1], F.col("p_size").cast("string"), texts[2], "p_name", texts[3])
    c = table(spark, d, "part").select("p_partkey", "p_brand", sql.alias("sql"))
    gold = c.groupBy("p_brand").agg(F.min_by("sql", "p_partkey").alias("gold"))
    return c.join(gold, "p_brand").select("p_partkey", F.levenshtein("sql", "gold").alias("distance"))


@query("fn_date", "select o_orderkey, date_trunc('month', o_orderdate)::timestamp as month, datediff('day', timestamp '1992-01-01', date_trunc('day', o_orderdate))::int as days, year(o_orderdate)::int as y, quarter(o_orderdate)::int as q from orders")
def fn_date(spark, d):
    o = table(spark, d, "orders")
    return o.select("o_orderkey", F.date_trunc("month", "o_orderdate").cast("timestamp_ntz").alias("month"), F.datediff(F.to_date("o_orderdate"), F.lit("1992-01-01").cast("date")).alias("days"), F.year("o_orderdate").alias("y"), F.quarter("o_orderdate").alias("q"))


@query("fn_math", "select s_suppkey, round(sqrt(abs(s_acctbal)), 4) as root, round(ln(abs(s_acctbal) + 1), 4) as logged, floor(s_acctbal)::bigint as low, xor(s_suppkey, 5) as bits, round(pow(s_nationkey, 2), 2) as squared from supplier")
def fn_math(spark, d):
    return table(spark, d, "supplier").select("s_suppkey", F.round(F.sqrt(F.abs("s_acctbal")), 4).alias("root"), F.round(F.log(F.abs("s_acctbal") + 1), 4).alias("logged"), F.floor("s_acctbal").alias("low"), F.col("s_suppkey").bitwiseXOR(F.lit(5)).alias("bits"), F.round(F.pow("s_nationkey", F.lit(2)), 2).alias("squared"))


@query("softmax_scores", f"{LINE} select beam_id, pos, round(exp((score - m) / 10) / sum(exp((score - m) / 10)) over (partition by beam_id), 6) as p from (select *, max(score) over (partition by beam_id) as m from line_beams where pos <= 5)")
def softmax_scores(spark, d):
    w = W.partitionBy("beam_id")
    rows = line_beams(spark, d).where("pos <= 5").withColumn("e", F.exp((F.col("score") - F.max("score").over(w)) / 10))
    return rows.select("beam_id", "pos", F.round(F.col("e") / F.sum("e").over(w), 6).alias("p"))


@query("fn_array", f"{LINE} select beam_id, list_sum(list(score))::double as total, len(list_filter(list(score), lambda x: x > 25))::int as big, max(score) as best from line_beams group by beam_id")
def fn_array(spark, d):
    nested = line_beams(spark, d).groupBy("beam_id").agg(F.collect_list("score").alias("s"))
    return nested.select("beam_id", F.aggregate("s", F.lit(0.0), lambda a, x: a + x).alias("total"), F.size(F.filter("s", lambda x: x > 25)).alias("big"), F.array_max("s").alias("best"))


@query("beam_explode", f"{LINE} select beam_id, pos - 1 as i, item_id from line_beams where pos <= 5")
def beam_explode(spark, d):
    nested = line_beams(spark, d).where("pos <= 5").groupBy("beam_id").agg(F.array_sort(F.collect_list(F.struct("pos", "item_id"))).alias("items"))
    return nested.select("beam_id", F.posexplode("items").alias("i", "x")).select("beam_id", "i", "x.item_id")


@query("fn_map", "select o_orderstatus, o_orderpriority, count(*) as n from orders group by 1, 2")
def fn_map(spark, d):
    counts = table(spark, d, "orders").groupBy("o_orderstatus", "o_orderpriority").agg(F.count(F.lit(1)).alias("n"))
    maps = counts.groupBy("o_orderstatus").agg(F.map_from_entries(F.collect_list(F.struct("o_orderpriority", "n"))).alias("m"))
    return maps.select("o_orderstatus", F.explode("m").alias("o_orderpriority", "n"))


@query("fn_json", "select event_id, (props->>'$.k')::bigint as k from events")
def fn_json(spark, d):
    return table(spark, d, "events").select("event_id", F.from_json("props", "k bigint")["k"].alias("k"))


def reciprocal_rank(correct, pos):
    """A user-defined aggregate over a beam's items."""
    return F.pandas_udf(_reciprocal_rank, "double")(correct, pos)


def _reciprocal_rank(correct: pd.Series, pos: pd.Series) -> float:
    hits = pos[correct.astype(bool)]
    return 1.0 / hits.min() if len(hits) else 0.0


@query("udaf_mrr", f"{LINE} select round(avg(r), 6) as mrr from (select coalesce(1 / min(pos) filter (correct), 0) as r from line_beams group by beam_id)")
def udaf_mrr(spark, d):
    rows = line_beams(spark, d).groupBy("beam_id").agg(reciprocal_rank("correct", "pos").alias("r"))
    return rows.agg(F.round(F.avg("r"), 6).alias("mrr"))


def _generated_sql() -> str:
    rows = [(g, *item) for g, _, q, _ in GOLD for item in generators.beam(g, q, "udtf", 0.8, 0.9, True)]
    return "select gold_id, pos::int as pos, kind, sql from (values " + ", ".join(f"('{g}', {p}, '{k}', '" + q.replace("'", "''") + "')" for g, p, k, q in rows) + ") as v(gold_id, pos, kind, sql)"


@query("udtf_generate_beam", _generated_sql())
def udtf_generate_beam(spark, d):
    """A generator as a table function: question in, ranked candidates out."""
    from pyspark.sql.functions import udtf

    from beamrank.operators.generators import beam
    from beamrank.sources.catalogue import GOLD

    class Generate:
        def eval(self, gold_id: str, gold: str):
            yield from beam(gold_id, gold, "udtf", 0.8, 0.9, True)

    spark.udtf.register("generate_beam", udtf(Generate, returnType="pos int, kind string, sql string"))
    spark.createDataFrame([(g, q) for g, _, q, _ in GOLD], "gold_id string, gold string").createOrReplaceTempView("golds")
    return spark.sql("select gold_id, b.pos, b.kind, b.sql from golds, lateral generate_beam(gold_id, gold) b")


@query("map_score", f"{LINE} select beam_id, pos, round(1 / (1 + exp(-(score - 25) / 10)), 6) as p from line_beams where pos <= 5")
def map_score(spark, d):
    """A model applied in Arrow batches."""
    import numpy as np

    def run(batches):
        for b in batches:
            yield b.assign(p=np.round(1 / (1 + np.exp(-(b["score"] - 25) / 10)), 6))[["beam_id", "pos", "p"]]

    return line_beams(spark, d).where("pos <= 5").select("beam_id", "pos", "score").mapInPandas(run, "beam_id bigint, pos int, p double")


@query("fn_sql_udf", "select o_orderkey, case when o_totalprice > 300000 then 'high' when o_totalprice > 100000 then 'mid' else 'low' end as class from orders")
def fn_sql_udf(spark, d):
    """A function in SQL, inlined by the optimiser."""
    spark.sql("create or replace temporary function price_class(p double) returns string return case when p > 300000 then 'high' when p > 100000 then 'mid' else 'low' end")
    table(spark, d, "orders").createOrReplaceTempView("orders")
    return spark.sql("select o_orderkey, price_class(o_totalprice) as class from orders")
