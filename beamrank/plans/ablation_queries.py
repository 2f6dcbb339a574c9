"""Shapley values and ablations over the published scores and over a lattice measured on line beams."""

from __future__ import annotations

from pyspark.sql import functions as F

from beamrank.operators import linelattice, shapley
from beamrank.plans.registry import query
from beamrank.sources import published as P

LATTICE = {"gs": 2, "pp": 4, "rr": 8}
BASE = f"with {P.SCORES_SQL}"
MEASURED = f"with {linelattice.SCORES_SQL}"
FULL = BASE + ", f as (select * from scores where backbone = 'seq' and mask & 1 = 1)"


def _players(players: dict[str, int]) -> str:
    return "players(player, bit) as (values " + ", ".join(f"('{k}', {v})" for k, v in players.items()) + ")"


def _marginals(source: str, players: dict[str, int] = shapley.PLAYERS) -> str:
    return f""", {_players(players)},
marg as (select a.backbone, a.rr_origin, a.metric, player, bit, a.mask as context, b.value - a.value as delta
         from {source} a, players, {source} b
         where a.backbone = b.backbone and a.rr_origin = b.rr_origin and a.metric = b.metric and a.mask & bit = 0 and b.mask = a.mask | bit)"""


AVAILABLE = "select backbone, rr_origin, metric, player, round(avg(delta), 6) as phi, count(*) as contexts from marg group by all"
#: Exact values by going through all orders of three players.
EXACT = ", orders as (select p.player, p.bit, q.bit as b2, r.bit as b3 from players p, players q, players r where p.bit <> q.bit and q.bit <> r.bit and p.bit <> r.bit)" + """,
steps as (
  select player, 1 as before, bit, 1 as way from orders union all
  select player, 1 + b2, bit, 2 from orders union all
  select player, 1 + b2 + b3, bit, 3 from orders)
, exact as (
  select a.backbone, a.rr_origin, a.metric, player, round(avg(b.value - a.value), 6) as phi
  from steps join f a on a.mask = before join f b on b.mask = before + bit and a.backbone = b.backbone and a.rr_origin = b.rr_origin and a.metric = b.metric
  group by a.backbone, a.rr_origin, a.metric, player)"""


@query("config_lattice", MEASURED + " select mask, bit_count(mask)::int as size, array_to_string(list_filter([case when mask & 1 > 0 then 'ir' end, case when mask & 2 > 0 then 'gs' end, case when mask & 4 > 0 then 'pp' end, case when mask & 8 > 0 then 'rr' end], lambda x: x is not null), '+') as components, count(*) as scores, max(value) as best from scores group by mask")
def config_lattice(spark, d):
    """Every set of components, how many scores are measured with it, and the best of them."""
    found = linelattice.scores(spark, d).groupBy("mask").agg(F.count(F.lit(1)).alias("scores"), F.max("value").alias("best"))
    return shapley.lattice(spark, shapley.PLAYERS).join(found, "mask")


@query("shapley_marginals", BASE + _marginals("scores") + " select backbone, rr_origin, metric, player, context, round(delta, 6) as delta from marg")
def shapley_marginals(spark, d):
    return shapley.marginals(P.scores(spark)).withColumn("delta", F.round("delta", 6))


@query("shapley_available", FULL + _marginals("f", LATTICE) + AVAILABLE)
def shapley_available(spark, d):
    """Means over the four contexts of the sequence backbone with IR; equals the published cells."""
    return shapley.available_mean(P.scores(spark, True), LATTICE)


@query("shapley_by_framework", BASE + _marginals("scores") + AVAILABLE)
def shapley_by_framework(spark, d):
    return shapley.available_mean(P.scores(spark))


@query("shapley_weighted", FULL + _marginals("f", LATTICE) + """ select backbone, rr_origin, metric, player, round(sum(w * delta) / sum(w), 6) as phi
from (select *, case bit_count(context & 14) when 1 then 1.0 / 6 else 1.0 / 3 end as w from marg) group by all""")
def shapley_weighted(spark, d):
    return shapley.available_weighted(P.scores(spark, True), LATTICE)


@query("shapley_exact", FULL + ", " + _players(LATTICE) + EXACT + " select * from exact")
def shapley_exact(spark, d):
    return shapley.exact(P.scores(spark, True), LATTICE)


@query("shapley_sampled", FULL + ", " + _players(LATTICE) + """, o as (select n, player, bit from (select unnest(range(200)) as n), players),
pre as (select player, bit, 1 + coalesce(sum(bit) over (partition by n order by md5(n || ':' || player || ':42'), player rows between unbounded preceding and 1 preceding), 0) as m0 from o)
select a.backbone, a.rr_origin, a.metric, player, round(avg(b.value - a.value), 6) as phi from pre join f a on a.mask = m0 join f b on b.mask = m0 + bit and a.backbone = b.backbone and a.rr_origin = b.rr_origin and a.metric = b.metric group by all""")
def shapley_sampled(spark, d):
    scores = P.scores(spark, True).withColumn("mask", F.col("mask") - 1)
    return shapley.sampled(scores, LATTICE, 200)


@query("shapley_overall", BASE + _marginals("scores") + f", a as ({AVAILABLE}) select backbone, metric, player, round(avg(phi), 6) as phi from a group by all")
def shapley_overall(spark, d):
    return shapley.overall(shapley.available_mean(P.scores(spark)))


@query("shapley_overall_published", "with c(backbone, metric, player, phi) as (values " + ", ".join(
    f"('{b}', '{m}', '{p}', {v}::double)" for (b, _), cells in P.COMPONENTS.items() for p, pair in zip(shapley.PLAYERS, cells, strict=True) for m, v in zip(("EX", "EM"), pair, strict=True)
) + ") select backbone, metric, player, round(avg(phi), 6) as phi from c group by all")
def shapley_overall_published(spark, d):
    rows = [(b, m, p, v) for (b, _), cells in P.COMPONENTS.items() for p, pair in zip(shapley.PLAYERS, cells, strict=True) for m, v in zip(("EX", "EM"), pair, strict=True)]
    return shapley.overall(spark.createDataFrame(rows, "backbone string, metric string, player string, phi double"))


FIVE = {"ir": 1, "gs": 2, "pp": 4, "rr_alg": 8, "rr_seq": 16}


@query("shapley_two_rerankers", BASE + ", t as (select distinct backbone, 'both' as rr_origin, metric, case when rr_origin = 'seq' and mask & 8 > 0 then mask + 8 else mask end as mask, value from scores)" + _marginals("t", FIVE) + AVAILABLE)
def shapley_two_rerankers(spark, d):
    return shapley.two_rerankers(P.scores(spark))


@query("shapley_efficiency", FULL + ", " + _players(LATTICE) + EXACT + """
select backbone, rr_origin, metric, round(abs(sum(phi) - any_value(gain)), 4) as gap from exact
join (select backbone, rr_origin, metric, max(value) filter (mask = 15) - max(value) filter (mask = 1) as gain from f group by all) using (backbone, rr_origin, metric) group by all""")
def shapley_efficiency(spark, d):
    return shapley.efficiency(P.scores(spark, True), LATTICE)


@query("shapley_extremes", BASE + _marginals("scores") + f", a as ({AVAILABLE}), o as (select backbone, metric, player, round(avg(phi), 6) as phi from a group by all) select backbone, metric, arg_max(player, (phi, player)) as strongest, arg_min(player, (phi, player)) as weakest from o group by all")
def shapley_extremes(spark, d):
    return shapley.extremes(shapley.overall(shapley.available_mean(P.scores(spark))))


@query("component_delta", MEASURED + " select a.backbone, a.rr_origin, a.metric, 'ir' as player, round(b.value - a.value, 6) as points from scores a join scores b using (backbone, rr_origin, metric) where a.mask = 0 and b.mask = 1")
def component_delta(spark, d):
    return shapley.delta(linelattice.scores(spark, d))


@query("pair_interaction", BASE + """ select z.backbone, z.rr_origin, z.metric, z.mask as context, round(c.value - a.value - b.value + z.value, 6) as interaction
from scores z join scores a using (backbone, rr_origin, metric) join scores b using (backbone, rr_origin, metric) join scores c using (backbone, rr_origin, metric)
where z.mask & 6 = 0 and a.mask = z.mask + 2 and b.mask = z.mask + 4 and c.mask = z.mask + 6""")
def pair_interaction(spark, d):
    return shapley.interactions(P.scores(spark))


@query("leave_one_out", BASE + """ select w.backbone, w.rr_origin, w.metric, case 15 - o.mask when 1 then 'ir' when 2 then 'gs' when 4 then 'pp' else 'rr' end as player, round(w.value - o.value, 6) as loss
from scores w join scores o using (backbone, rr_origin, metric) where w.mask = 15 and bit_count(o.mask) = 3""")
def leave_one_out(spark, d):
    return shapley.leave_one_out(P.scores(spark))


@query("combine_all_vs_best", MEASURED + " select backbone, rr_origin, metric, arg_max(mask, (value, -mask)) as best_mask, round(max(value) - max(value) filter (mask = 15), 6) as lead from scores group by all having max(value) filter (mask = 15) is not null")
def combine_all_vs_best(spark, d):
    return shapley.all_vs_best(linelattice.scores(spark, d))


@query("ablation_staged", MEASURED + """, b as (select backbone, rr_origin, metric, arg_max(mask, (value, -mask)) filter (mask in (0, 1)) as base from scores group by all)
select backbone, rr_origin, metric, base, arg_max(mask, (value, -mask)) as best_mask, count(*) as runs from scores join b using (backbone, rr_origin, metric) where mask & 1 = base group by all""")
def ablation_staged(spark, d):
    return shapley.staged(linelattice.scores(spark, d))


@query("best_system", MEASURED + " select metric, arg_max(backbone, (value, -mask, backbone, rr_origin)) as backbone, arg_max(rr_origin, (value, -mask, backbone, rr_origin)) as rr_origin, arg_max(mask, (value, -mask, backbone, rr_origin)) as mask, max(value) as value from scores group by metric")
def best_system(spark, d):
    return shapley.best_system(linelattice.scores(spark, d))


@query("schema_ablation", "with v(origin, with_schema, p, r, f) as (values " + ", ".join(f"('{o}', {str(s).lower()}, {p}::double, {r}::double, {f}::double)" for (o, s), (p, r, f) in P.VERIFIER.items()) + ") select a.origin, round(a.p - b.p, 6) as precision_gain, round(a.r - b.r, 6) as recall_gain, round(a.f - b.f, 6) as f1_gain from v a join v b using (origin) where a.with_schema and not b.with_schema")
def schema_ablation(spark, d):
    rows = spark.createDataFrame([(o, s, *v) for (o, s), v in P.VERIFIER.items()], "origin string, with_schema boolean, p double, r double, f double")
    pick = lambda c, s: F.max(F.when(F.col("with_schema") == s, F.col(c)))
    names = {"p": "precision_gain", "r": "recall_gain", "f": "f1_gain"}
    return rows.groupBy("origin").agg(*[F.round(pick(c, True) - pick(c, False), 6).alias(n) for c, n in names.items()])


@query("published_labels", "with v(origin, split, positive, negative) as (values " + ", ".join(f"('{o}', '{s}', {p}, {n})" for (o, s), (p, n, _) in P.LABELS.items()) + ") select *, round(100 * positive / (positive + negative), 2) as percent from v")
def published_labels(spark, d):
    rows = spark.createDataFrame([(o, s, p, n) for (o, s), (p, n, _) in P.LABELS.items()], "origin string, split string, positive int, negative int")
    return rows.withColumn("percent", F.round(100 * F.col("positive") / (F.col("positive") + F.col("negative")), 2))
