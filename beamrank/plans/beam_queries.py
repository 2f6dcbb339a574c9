"""Beam construction, analysis, selection and reranking on the carriers."""

from __future__ import annotations

from pyspark.sql import functions as F

from beamrank.operators import beams, metrics, rerank
from beamrank.plans.registry import query
from beamrank.sources.tables import CHAT_SQL, DOC_SQL, LINE_SQL, chat_beams, doc_beams, line_beams, table

COIN = "('0x' || substr(md5({}), 1, 8))::bigint / 4294967296.0::double"
LINE = f"with {LINE_SQL}"


@query("beam_first5", f"{LINE} select beam_id, pos, item_id, correct, verified, score from line_beams where pos <= 5")
def beam_first5(spark, d):
    return beams.first_k(line_beams(spark, d), 5).drop("price")


GOLD = LINE + ", golds as (select beam_id, arg_min(pos, (-price, pos)) as gold_pos, max(pos) as n from line_beams group by beam_id)"


@query("gold_replace_last", GOLD + """
select beam_id, case when pos = gold_pos and gold_pos > 5 then 5 else pos end::int as pos, item_id, pos = gold_pos as is_gold
from line_beams join golds using (beam_id) where (gold_pos <= 5 and pos <= 5) or (gold_pos > 5 and (pos < 5 or pos = gold_pos))""")
def gold_replace_last(spark, d):
    return beams.ensure_gold(beams.with_gold(line_beams(spark, d)), 5).select("beam_id", "pos", "item_id", "is_gold")


def _front_sql(k: int) -> str:
    return GOLD + f"""
select beam_id, case when gold_pos <= {k} then pos when pos = gold_pos then 1 else pos + 1 end::int as pos, item_id, pos = gold_pos as is_gold
from line_beams join golds using (beam_id) where (gold_pos <= {k} and pos <= {k}) or (gold_pos > {k} and (pos < {k} or pos = gold_pos))"""


@query("gold_front5", _front_sql(5))
def gold_front5(spark, d):
    return beams.ensure_gold(beams.with_gold(line_beams(spark, d)), 5, "front").select("beam_id", "pos", "item_id", "is_gold")


@query("gold_front2", _front_sql(2))
def gold_front2(spark, d):
    return beams.ensure_gold(beams.with_gold(line_beams(spark, d)), 2, "front").select("beam_id", "pos", "item_id", "is_gold")


@query("reorder_random", f"{LINE} select beam_id, pos, item_id, row_number() over (partition by beam_id order by md5(beam_id || ':' || pos || ':42'), pos)::int as new_pos from line_beams where pos <= 5")
def reorder_random(spark, d):
    return beams.reorder_random(beams.first_k(line_beams(spark, d), 5)).select("beam_id", "pos", "item_id", "new_pos")


SHIFT_SQL = LINE + """, sized as (select *, count(*) over (partition by beam_id) as n, max(case when pos = 1 then correct end) over (partition by beam_id) as ok from line_beams where pos <= 5),
coins as (select distinct beam_id, n, ok, """ + ", ".join(f"{COIN.format(chr(39).join(['beam_id || ', '|' + str(i), '']))} < 0.7 as keep{i}" for i in range(1, 5)) + """ from sized),
shifts as (select beam_id, case when not ok then 0 else least(n - 1, case when keep1 then 0 when keep2 then 1 when keep3 then 2 when keep4 then 3 else 4 end) end as t from coins)"""


@query("reorder_geometric", SHIFT_SQL + " select beam_id, pos, item_id, case when pos = 1 then t + 1 when pos <= t + 1 then pos - 1 else pos end::int as new_pos from sized join shifts using (beam_id)")
def reorder_geometric(spark, d):
    return beams.reorder_geometric(beams.first_k(line_beams(spark, d), 5)).select("beam_id", "pos", "item_id", "new_pos")


WALK_SQL = LINE + """, sized as (select *, least(count(*) over (partition by beam_id), 5) - min(case when correct then pos end) over (partition by beam_id) + 1 as room, min(case when correct then pos end) over (partition by beam_id) as start from line_beams where pos <= 5),
coins as (select distinct beam_id, room, start, """ + ", ".join(f"{COIN.format(chr(39).join(['beam_id || ', '|' + str(i), '']))} < 0.7 as keep{i}" for i in range(1, 5)) + """ from sized),
walks as (select beam_id, start + least(room - 1, case when keep1 then 0 when keep2 then 1 when keep3 then 2 when keep4 then 3 else 4 end) as goal from coins)
select beam_id, pos, item_id, (case when pos = start then goal when pos > start and pos <= goal then pos - 1 else pos end)::int as new_pos from sized join walks using (beam_id)"""


@query("reorder_geometric_anchor", WALK_SQL)
def reorder_geometric_anchor(spark, d):
    """The same walk from the first correct item, wherever it stands."""
    moved = beams.reorder_geometric(beams.first_k(line_beams(spark, d), 5), anchor="first_correct")
    return moved.select("beam_id", "pos", "item_id", "new_pos")


@query("correct_position_hist", f"{LINE} select first_pos, count(*) as beams from (select beam_id, min(pos) filter (correct) as first_pos from line_beams group by beam_id) group by first_pos")
def correct_position_hist(spark, d):
    return beams.position_hist(line_beams(spark, d))


GAIN_SQL = """firsts as (select beam_id, min(pos) filter (correct) as p from {source} group by beam_id),
ks as (select unnest(range(1, (select max(pos) from {source}) + 1)) as k)"""


@query("gain_curve", f"{LINE}, {GAIN_SQL.format(source='line_beams')} select k::int as k, (select count(*) from firsts where p <= k) as covered, round((select count(*) from firsts where p <= k) / (select count(*) from firsts), 6) as share from ks")
def gain_curve(spark, d):
    return beams.gain_curve(line_beams(spark, d))


#: Four systems over the same items that differ in what counts as correct first: rules by rank and item.
SYSTEM_RULES = {"alg+gs": "correct", "seq_ir": "correct and score > 10", "seq_ir+gs": "correct or (pos > 2 and score > 40)", "seq_ir+pp": "correct and score > 5"}


def _systems(spark, d):
    rows = line_beams(spark, d)
    each = F.array(*[F.struct(F.lit(s).alias("system"), F.expr(rule).alias("ok")) for s, rule in SYSTEM_RULES.items()])
    return rows.select("beam_id", "pos", F.explode(each).alias("s")).select("beam_id", "pos", "s.system", F.col("s.ok").alias("correct"))


SYSTEMS_SQL = LINE + ", systems as (" + " union all ".join(f"select beam_id, pos, '{s}' as system, {rule} as correct from line_beams" for s, rule in SYSTEM_RULES.items()) + """),
firsts as (select system, beam_id, min(pos) filter (correct) as p from systems group by all),
curve as (select system, k::int as k, count(*) filter (p <= k) as covered, round(count(*) filter (p <= k) / count(*), 6) as share
          from firsts, (select unnest(range(1, (select max(pos) from line_beams) + 1)) as k) group by system, k)"""


@query("gain_curve_systems", SYSTEMS_SQL + " select * from curve")
def gain_curve_systems(spark, d):
    return beams.gain_curve(_systems(spark, d), "system")


@query("best_by_potential", SYSTEMS_SQL + " select arg_max(system, (share, system)) as system, max(share) as share from curve where k = 5")
def best_by_potential(spark, d):
    return beams.best_by_potential(beams.gain_curve(_systems(spark, d), "system"), 5)


@query("rerank_headroom", f"{LINE} select round(avg(top), 6) as top1, round(avg(hit), 6) as ceiling, round(avg(hit) - avg(top), 6) as headroom from (select max((correct and pos = 1)::int) as top, max(correct::int) as hit from line_beams group by beam_id)")
def rerank_headroom(spark, d):
    return beams.headroom(line_beams(spark, d))


@query("label_distribution", f"{LINE} select case when beam_id % 5 < 4 then 'train' else 'dev' end as split, count(*) filter (correct) as positive, count(*) filter (not correct) as negative, round(100 * count(*) filter (correct) / count(*), 4) as percent from line_beams where pos <= 5 group by split")
def label_distribution(spark, d):
    rows = beams.first_k(line_beams(spark, d), 5).withColumn("split", F.when(F.col("beam_id") % 5 < 4, "train").otherwise("dev"))
    return beams.label_distribution(rows, "split")


@query("candidate_dictionary", "select text, false as clash from (select distinct text from conversations where role = 'assistant')")
def candidate_dictionary(spark, d):
    return beams.dictionary(table(spark, d, "conversations").where("role = 'assistant'"), "text").select("text", "clash")


def _rank_sql(key: str, where: str = "true", source: str = "line_beams", cte: str = LINE) -> str:
    return f"{cte} select beam_id, arg_min(item_id, {key}) as item_id, arg_min(correct, {key}) as correct from {source} where {where} group by beam_id"


VERIFIED = "(case when verified then 0 else 1 end, pos)"


@query("rerank_top1", _rank_sql("pos"))
def rerank_top1(spark, d):
    return rerank.top1(line_beams(spark, d))


@query("rerank_verifier", _rank_sql(VERIFIED))
def rerank_verifier(spark, d):
    return rerank.verifier(line_beams(spark, d))


@query("rerank_verifier_chat", _rank_sql(VERIFIED, source="chat_beams", cte=f"with {CHAT_SQL}"))
def rerank_verifier_chat(spark, d):
    return rerank.verifier(chat_beams(spark, d))


@query("rerank_selector", _rank_sql("(-score, pos)", "pos <= 5"))
def rerank_selector(spark, d):
    return rerank.selector(line_beams(spark, d))


@query("select_by_score", _rank_sql("(-score, pos)", "pos <= 5"))
def select_by_score(spark, d):
    return rerank.by_score(line_beams(spark, d))


def _pair_sql(key: str) -> str:
    return LINE + f""", one as (select * from line_beams where pos = 1),
two as (select * from (select *, row_number() over (partition by beam_id order by {key}) as r from line_beams where pos > 1 and verified) where r = 1),
pairs as (select o.beam_id, o.item_id as item_id_1, o.correct as correct_1, o.score as score_1, t.item_id as item_id_2, t.correct as correct_2, t.score as score_2
          from one o left join two t using (beam_id))"""


CHOICE_SQL = " select beam_id, case when score_2 > score_1 then item_id_2 else item_id_1 end as item_id, case when score_2 > score_1 then correct_2 else correct_1 end as correct from pairs"


@query("binary_beams", _pair_sql("pos") + " select beam_id, item_id_1, score_1, coalesce(item_id_2, -1) as item_id_2, coalesce(score_2, -1) as score_2 from pairs")
def binary_beams(spark, d):
    pairs = rerank.binary_beams(line_beams(spark, d))
    return pairs.select("beam_id", "item_id_1", "score_1", F.coalesce("item_id_2", F.lit(-1)).alias("item_id_2"), F.coalesce("score_2", F.lit(-1.0)).alias("score_2"))


@query("rerank_hybrid", _pair_sql("pos") + CHOICE_SQL)
def rerank_hybrid(spark, d):
    return rerank.hybrid(line_beams(spark, d))


@query("rerank_hybrid_score", _pair_sql("score desc, pos") + CHOICE_SQL)
def rerank_hybrid_score(spark, d):
    return rerank.hybrid(line_beams(spark, d), "score")


@query("rerank_ceiling", _rank_sql("(case when correct then 0 else 1 end, pos)"))
def rerank_ceiling(spark, d):
    return rerank.ceiling(line_beams(spark, d))


@query("rerank_random", _rank_sql("(('0x' || substr(md5(beam_id || ':' || pos || ':42'), 1, 12))::bigint, pos)"))
def rerank_random(spark, d):
    return rerank.random(line_beams(spark, d))


@query("rerank_linking", _rank_sql("(-score, pos)", source="chat_beams", cte=f"with {CHAT_SQL}"))
def rerank_linking(spark, d):
    return rerank.linking(chat_beams(spark, d))


@query("rerank_waves", _rank_sql(VERIFIED))
def rerank_waves(spark, d):
    rows = line_beams(spark, d)
    return rerank.waves(rows, lambda items: items)


@query("rerank_flips", f"""{LINE}, a as (select beam_id, arg_min(correct, pos) as was, arg_min(correct, {VERIFIED}) as now from line_beams group by beam_id)
select was, now, count(*) as beams from a group by was, now""")
def rerank_flips(spark, d):
    rows = line_beams(spark, d)
    return rerank.flips(rerank.top1(rows), rerank.verifier(rows))


MATRIX = {"top1": "pos", "verifier": VERIFIED, "selector": "(case when pos <= 5 then 0 else 1 end, -score, pos)", "ceiling": "(case when correct then 0 else 1 end, pos)"}


@query("rerank_matrix", SYSTEMS_SQL.replace("select beam_id, pos, '", "select beam_id, pos, verified, score, '") + " " + " union all ".join(
    f"select system, '{name}' as reranker, round(avg(c::int), 6) as accuracy from (select system, beam_id, arg_min(correct, {key}) as c from systems group by system, beam_id) group by system" for name, key in MATRIX.items()))
def rerank_matrix(spark, d):
    """The rerankers of MATRIX on all systems; rerank_matrix_all has all of them."""
    return _matrix(spark, d, list(MATRIX))


@query("rerank_matrix_all")
def rerank_matrix_all(spark, d):
    """All rerankers on all systems, by the one label that line beams have."""
    return _matrix(spark, d, list(rerank.RERANKERS))


def _matrix(spark, d, names: list[str]):
    """Accuracies in one plan over packed keys, grouped by system and beam once."""
    rows = line_beams(spark, d)
    each = F.array(*[F.struct(F.lit(s).alias("system"), F.expr(rule).alias("ok")) for s, rule in SYSTEM_RULES.items()])
    long = rows.select("beam_id", "pos", "verified", "score", F.explode(each).alias("s")).select("beam_id", "pos", "verified", "score", "s.system", F.col("s.ok").alias("correct"))
    pos = F.col("pos").cast("bigint")
    keys = {
        "top1": pos,
        "verifier": F.when(F.col("verified"), 0).otherwise(1 << 32) + pos,
        "selector": F.struct(F.when(F.col("pos") <= 5, 0).otherwise(1).alias("late"), (-F.col("score")).alias("s"), pos.alias("p")),
        "ceiling": F.when(F.col("correct"), 0).otherwise(1 << 32) + pos,
        "random": rerank.random_key(),
    }
    picks = {name: F.min_by("correct", k) for name, k in keys.items()}
    first, second = F.when(pos == 1, pos), F.when((pos > 1) & F.col("verified"), pos)
    takes = F.coalesce(F.min_by("score", second) > F.min_by("score", first), F.lit(False))
    picks["hybrid"] = F.when(takes, F.min_by("correct", second)).otherwise(F.min_by("correct", first))
    chosen = long.groupBy("system", "beam_id").agg(*[picks[name].alias(name) for name in names])
    sums = chosen.groupBy("system").agg(*[F.round(F.avg(F.col(k).cast("int")), 6).alias(k) for k in names])
    return sums.select("system", F.explode(F.map_from_arrays(F.array(*[F.lit(k) for k in names]), F.array(*names))).alias("reranker", "accuracy"))


PRF = """count(*) filter (verified and correct) as tp, count(*) filter (verified and not correct) as fp, count(*) filter (not verified and correct) as fn, count(*) filter (not verified and not correct) as tn"""
PRF_SQL = "select {by} tp, fp, fn, tn, round(tp / nullif(tp + fp, 0), 6) as precision, round(tp / nullif(tp + fn, 0), 6) as recall, round(2 * tp / nullif(2 * tp + fp + fn, 0), 6) as f1 from counts"


@query("verifier_prf", f"{LINE}, counts as (select {PRF} from line_beams where pos <= 5) " + PRF_SQL.format(by=""))
def verifier_prf(spark, d):
    return metrics.prf(beams.first_k(line_beams(spark, d), 5))


@query("verifier_prf_noschema", f"with {CHAT_SQL}, counts as (select {PRF} from chat_beams) " + PRF_SQL.format(by=""))
def verifier_prf_noschema(spark, d):
    return metrics.prf(chat_beams(spark, d))


@query("holdout_eval", f"{LINE}, counts as (select beam_id % 5 = 4 as held_out, {PRF} from line_beams where pos <= 5 group by held_out) " + PRF_SQL.format(by="held_out, "))
def holdout_eval(spark, d):
    return metrics.prf(beams.first_k(line_beams(spark, d), 5).withColumn("held_out", F.col("beam_id") % 5 == 4), "held_out")


@query("selector_accuracy", f"{LINE} select count(*) filter (c) as right, count(*) as total, round(count(*) filter (c) / count(*), 6) as accuracy from (select arg_min(correct, (-score, pos)) as c from line_beams where pos <= 5 group by beam_id)")
def selector_accuracy(spark, d):
    return metrics.accuracy(rerank.by_score(line_beams(spark, d)))


@query("mean_reciprocal_rank", f"{LINE} select round(avg(coalesce(1 / p, 0)), 6) as mrr from (select min(pos) filter (correct) as p from line_beams group by beam_id)")
def mean_reciprocal_rank(spark, d):
    return metrics.mean_reciprocal_rank(line_beams(spark, d))


TRAIN_SQL = "select beam_id, new_pos as pos, item_id from ordered"


@query("selector_random_train", LINE + ", ordered as (select beam_id, item_id, row_number() over (partition by beam_id order by md5(beam_id || ':' || pos || ':42'), pos)::int as new_pos from line_beams where pos <= 5 and beam_id % 5 < 4) " + TRAIN_SQL)
def selector_random_train(spark, d):
    rows = beams.reorder_random(beams.first_k(line_beams(spark, d), 5).where("beam_id % 5 < 4"))
    return rows.select("beam_id", F.col("new_pos").alias("pos"), "item_id")


@query("selector_geometric_train", SHIFT_SQL + ", ordered as (select beam_id, item_id, case when pos = 1 then t + 1 when pos <= t + 1 then pos - 1 else pos end::int as new_pos from sized join shifts using (beam_id) where beam_id % 5 < 4) " + TRAIN_SQL)
def selector_geometric_train(spark, d):
    rows = beams.reorder_geometric(beams.first_k(line_beams(spark, d), 5).where("beam_id % 5 < 4"))
    return rows.select("beam_id", F.col("new_pos").alias("pos"), "item_id")


def _gold_train(spark, d):
    return beams.with_gold_first(line_beams(spark, d), 5).where("beam_id % 5 < 4")


@query("selector_random_train_gold")
def selector_random_train_gold(spark, d):
    """As selector_random_train, with the gold item put in where it is not among the first five."""
    return beams.reorder_random(_gold_train(spark, d)).select("beam_id", F.col("new_pos").alias("pos"), "item_id", "correct", "is_gold")


@query("selector_geometric_train_gold")
def selector_geometric_train_gold(spark, d):
    """As selector_geometric_train, with the gold item put in where it is not among the first five."""
    return beams.reorder_geometric(_gold_train(spark, d)).select("beam_id", F.col("new_pos").alias("pos"), "item_id", "correct", "is_gold")


@query("selector_order_match", f"""{LINE}, f as (select beam_id % 5 < 4 as train, beam_id, min(pos) filter (correct) as p from line_beams where pos <= 5 group by all),
s as (select coalesce(p, 0) as p, count(*) filter (train) / (select count(*) from f where train) as a, count(*) filter (not train) / (select count(*) from f where not train) as b from f group by 1)
select round(sum(abs(a - b)) / 2, 6) as distance from s""")
def selector_order_match(spark, d):
    """Total variation distance of the positions of the correct item in the two splits."""
    rows = beams.first_k(line_beams(spark, d), 5)
    firsts = rows.groupBy("beam_id").agg(F.coalesce(F.min(F.when(F.col("correct"), F.col("pos"))), F.lit(0)).alias("p")).withColumn("train", F.col("beam_id") % 5 < 4)
    hist = firsts.groupBy("p").agg(F.count_if("train").alias("a"), F.count_if(~F.col("train")).alias("b"))
    total = firsts.agg(F.count_if("train").alias("ta"), F.count_if(~F.col("train")).alias("tb"))
    return hist.crossJoin(F.broadcast(total)).agg(F.round(F.sum(F.abs(F.col("a") / F.col("ta") - F.col("b") / F.col("tb"))) / 2, 6).alias("distance"))


@query("doc_beam_shape", f"with {DOC_SQL} select beam_id, max(pos) as items, count(correct) as labelled, count(*) filter (correct) as good from doc_beams group by beam_id")
def doc_beam_shape(spark, d):
    return doc_beams(spark, d).groupBy("beam_id").agg(F.max("pos").alias("items"), F.count("correct").alias("labelled"), F.count_if("correct").alias("good"))


@query("linear_head_argmax", """
with e as (select vec_id, label, embedding::double[] as v from embeddings),
w as (select label, list(m order by i) as w from (select label, i, round(avg(x), 6) as m from (select label, unnest(v) as x, generate_subscripts(v, 1) as i from e) group by label, i) group by label),
s as (select vec_id, e.label, w.label as guess, round(list_sum(list_transform(range(1, 65), lambda i: v[i] * w[i])), 6) as dot from e, w)
select vec_id, arg_min(guess, (-dot, guess)) as guess, arg_min(guess, (-dot, guess)) = any_value(label) as hit from s group by vec_id""")
def linear_head_argmax(spark, d):
    """A linear layer over encoded inputs: weights are the classes' mean vectors, one broadcast row."""
    e = table(spark, d, "embeddings").select("vec_id", "label", F.col("embedding").cast("array<double>").alias("v"))
    parts = e.select("label", F.posexplode("v").alias("i", "x")).groupBy("label", "i").agg(F.round(F.avg("x"), 6).alias("m"))
    w = parts.groupBy("label").agg(F.array_sort(F.collect_list(F.struct("i", "m"))).alias("w"))
    heads = w.agg(F.array_sort(F.collect_list(F.struct("label", F.col("w.m").alias("w")))).alias("heads"))
    dot = lambda h: F.round(F.aggregate(F.zip_with("v", h["w"], lambda a, b: a * b), F.lit(0.0), lambda s, x: s + x), 6)
    scored = e.crossJoin(F.broadcast(heads)).select("vec_id", "label", F.array_min(F.transform("heads", lambda h: F.struct((-dot(h)).alias("d"), h["label"].alias("guess")))).alias("best"))
    return scored.select("vec_id", F.col("best.guess").alias("guess"), (F.col("best.guess") == F.col("label")).alias("hit"))
