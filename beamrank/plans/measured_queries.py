"""Systems, verifiers, selectors and rerankers that are trained and measured on the catalogue's questions."""

from __future__ import annotations

from functools import cache

import pandas as pd
from pyspark.sql import functions as F

from beamrank.functions import sqlshape
from beamrank.operators import beams, execute, lattice, metrics, shapley
from beamrank.operators.lattice import ALL, GS, IR, ORIGINS, PP, QUESTIONS, RERANKERS
from beamrank.plans.registry import query

GOLD_OF = {g: q for g, (_, q) in QUESTIONS.items()}
N = len(QUESTIONS)


def _pairs() -> list[tuple[str, str]]:
    """Every (question, text) that a generator can give."""
    options = [(b, ir, v) for b in lattice.BACKBONES for ir in (False, True) for v in ("v1", "v2", "v3")]
    return list(dict.fromkeys((g, q) for g, gold in GOLD_OF.items() for b, ir, v in options for q in (gold, *lattice.pool(g, gold, b, ir, v)[0])))


def _verdicts(spark, d):
    known = execute.verdicts(spark, d, _pairs(), GOLD_OF)
    return F.broadcast(spark.createDataFrame([(g, q, ex, valid) for (g, q), (ex, valid, _) in known.items()], "gold_id string, sql string, ex boolean, valid boolean"))


def _beams(spark, d, configs):
    return lattice.generated(spark, configs).join(_verdicts(spark, d), ["gold_id", "sql"])


def _choices(spark, d, systems=tuple(ALL), rerankers=RERANKERS):
    """What each reranker of each origin takes from each system's beams."""

    def choose(beam: pd.DataFrame) -> pd.DataFrame:
        out = []
        for g, rows in beam.sort_values(["gold_id", "pos"]).groupby("gold_id"):
            texts = rows["sql"].tolist()
            for name in rerankers:
                for origin in ORIGINS if name != "none" else ("none",):
                    i = lattice.rerank(name, origin, g, texts)
                    out.append((rows["backbone"].iloc[0], int(rows["mask"].iloc[0]), name, origin, g, texts[i], bool(rows["em"].iloc[i])))
        return pd.DataFrame(out, columns=["backbone", "mask", "reranker", "origin", "gold_id", "sql", "em"])

    found = lattice.generated(spark, lattice.configurations(systems)).groupBy("backbone", "mask", "fold")
    taken = found.applyInPandas(choose, "backbone string, mask int, reranker string, origin string, gold_id string, sql string, em boolean")
    return taken.join(_verdicts(spark, d), ["gold_id", "sql"])


def _share(c):
    return F.round(F.count_if(c) / N, 6)


# ---- the SQL of results: beams and component matches as literals, execution by bag difference


def _quoted(*row) -> str:
    return "(" + ", ".join("'" + x.replace("'", "''") + "'" if isinstance(x, str) else str(x).lower() for x in row) + ")"


def _ex_table(pairs) -> str:
    """ex(n, ok, valid): by number of the text among ``pairs``; texts that do not parse, or have other columns in number, are wrong."""
    out = []
    width = lambda q: len((sqlshape.parts(q) or {"items": []})["items"])
    for i, (g, q) in enumerate(pairs):
        runs = q.startswith("select ") and q.count("(") == q.count(")")
        if width(q) != width(GOLD_OF[g]):
            out.append(f"select {i} as n, false as ok, {str(runs).lower()} as valid")
            continue
        same = f"not exists (({q}) except all ({GOLD_OF[g]})) and not exists (({GOLD_OF[g]}) except all ({q}))"
        out.append(f"select {i} as n, {same if runs else 'false'} as ok, {str(runs).lower()} as valid")
    return "ex as (" + " union all ".join(out) + ")"


@cache
def _numbers() -> dict[tuple[str, str], int]:
    return {p: i for i, p in enumerate(_pairs())}


def _choices_sql(systems=tuple(ALL), rerankers=RERANKERS) -> str:
    rows = []
    for b, m in systems:
        for g, found in lattice._by_question(lattice.system(b, m)).items():
            for name in rerankers:
                for origin in ORIGINS if name != "none" else ("none",):
                    q, em = found[lattice.rerank(name, origin, g, [q for q, _ in found])]
                    rows.append((b, m, name, origin, _numbers()[g, q], em))
    return f"with {_ex_table(_numbers())}, c as (select * from (values {', '.join(_quoted(*r) for r in rows)}) as v(backbone, mask, reranker, origin, n, em) join ex using (n))"


def _items_sql(systems) -> str:
    rows = [(b, m, g, pos, _numbers()[g, q], em) for b, m in systems for g, pos, q, _, em in lattice.system(b, m)]
    return f"with {_ex_table(_numbers())}, items as (select * from (values {', '.join(_quoted(*r) for r in rows)}) as v(backbone, mask, gold_id, pos, n, em) join ex using (n))"


def _trained_sql(configs, name: str) -> str:
    """items of the beams of configurations, with one of their fields by its name."""
    fields = [c.split()[0] for c in lattice.CONFIG.split(", ")]
    rows = []
    for c in configs:
        f = dict(zip(fields, c, strict=True))
        found = lattice.beams_of(f["backbone"], f["mask"], f["fold"], f["version"], share=f["share"], mix=f["mix"], stages=f["stages"])
        rows += [(f["backbone"], f[name], g, pos, _numbers()[g, q], em) for g, pos, q, _, em in found]
    return f"with {_ex_table(_numbers())}, items as (select * from (values {', '.join(_quoted(*r) for r in rows)}) as v(backbone, {name}, gold_id, pos, n, em) join ex using (n))"


SCORES = f"round(count(*) filter (ok) / {N}, 6) as ex, round(count(*) filter (em) / {N}, 6) as em"


@query("systems_compare", lambda: _choices_sql(rerankers=("none", "selector")) + f" select backbone, mask, reranker, origin, {SCORES} from c group by all")
def systems_compare(spark, d):
    """Execution and component match of every combination of components, plain and reranked by models of either origin."""
    taken = _choices(spark, d, rerankers=("none", "selector"))
    return taken.groupBy("backbone", "mask", "reranker", "origin").agg(_share("ex").alias("ex"), _share("em").alias("em"))


@query("rerank_matrix_sql", lambda: _choices_sql() + f" select backbone, mask, reranker, origin, {SCORES} from c group by all")
def rerank_matrix_sql(spark, d):
    """Every trained reranker of either origin on every system."""
    return _choices(spark, d).groupBy("backbone", "mask", "reranker", "origin").agg(_share("ex").alias("ex"), _share("em").alias("em"))


@query("rerank_verifier_sql", lambda: _choices_sql(rerankers=("verifier", "verifier_noschema")) + f" select backbone, mask, reranker, origin, {SCORES} from c group by all")
def rerank_verifier_sql(spark, d):
    """Whole beams filtered by the learned verifier, with and without the schema in its input."""
    taken = _choices(spark, d, rerankers=("verifier", "verifier_noschema"))
    return taken.groupBy("backbone", "mask", "reranker", "origin").agg(_share("ex").alias("ex"), _share("em").alias("em"))


#: The two systems that win, as published: by execution and by component match.
WINNERS = (("seq", IR | PP, "alg"), ("seq", IR | GS, "seq"))


@query("winning_systems", lambda: _choices_sql([(b, m) for b, m, _ in WINNERS]) + f" select backbone, mask, reranker, origin, {SCORES} from c where origin = 'none' or (mask = 5 and origin = 'alg') or (mask = 3 and origin = 'seq') group by all")
def winning_systems(spark, d):
    """The two published winners, with each reranker of their origin, beside their plain beams."""
    own = F.col("origin") == "none"
    for _, m, origin in WINNERS:
        own = own | ((F.col("mask") == m) & (F.col("origin") == origin))
    taken = _choices(spark, d, [(b, m) for b, m, _ in WINNERS]).where(own)
    return taken.groupBy("backbone", "mask", "reranker", "origin").agg(_share("ex").alias("ex"), _share("em").alias("em"))


@query("constrained_compare", lambda: _items_sql([("seq", 0), ("seq", IR)]) + f", f as (select mask, gold_id, arg_min(ok, (case when valid then 0 else 1 end, pos)) as ok, arg_min(em, (case when valid then 0 else 1 end, pos)) as em from items group by all) select mask, {SCORES} from f group by mask")
def constrained_compare(spark, d):
    """The comparator with constrained decoding: the first candidate that the grammar and the schema allow."""
    key = F.when(F.col("valid"), 0).otherwise(1 << 32) + F.col("pos")
    one = _beams(spark, d, lattice.configurations([("seq", 0), ("seq", IR)])).groupBy("mask", "gold_id").agg(F.min_by("ex", key).alias("ex"), F.min_by("em", key).alias("em"))
    return one.groupBy("mask").agg(_share("ex").alias("ex"), _share("em").alias("em"))


@query("gain_curve_sql", lambda: _items_sql(ALL) + f", f as (select backbone, mask, gold_id, min(pos) filter (ok) as p from items group by all), k as (select unnest(range(1, {lattice.WIDTH} + 1)) as k) select backbone, mask, k::int as k, count(*) filter (p <= k) as covered, round(count(*) filter (p <= k) / {N}, 6) as share from f, k group by all")
def gain_curve_sql(spark, d):
    """Questions with a right candidate among the first k, for every system."""
    found = _beams(spark, d, lattice.configurations(ALL)).groupBy("backbone", "mask", "gold_id").agg(F.min(F.when(F.col("ex"), F.col("pos"))).alias("p"))
    each = found.withColumn("k", F.explode(F.sequence(F.lit(1), F.lit(lattice.WIDTH))))
    hit = F.count_if(F.col("p") <= F.col("k"))
    return each.groupBy("backbone", "mask", "k").agg(hit.alias("covered"), F.round(hit / N, 6).alias("share"))


#: How many candidates count when systems are compared by what their beams could give.
POTENTIAL = 3


@query("best_by_potential_sql", lambda: _items_sql(ALL) + f", f as (select backbone || mask as system, gold_id, min(pos) filter (ok) as p from items group by all), s as (select system, round(count(*) filter (p <= {POTENTIAL}) / {N}, 6) as share from f group by system) select arg_max(system, (share, system)) as system, max(share) as share from s")
def best_by_potential_sql(spark, d):
    """The system whose first candidates hold the right query most often: the one to learn rerankers from."""
    curves = gain_curve_sql(spark, d).withColumn("system", F.concat(F.col("backbone"), F.col("mask").cast("string")))
    return beams.best_by_potential(curves, POTENTIAL)


VERSIONS = lattice.configurations([("alg", 0)], ("plain",)) + lattice.configurations([("alg", IR)], ("v1", "v2", "v3"))


@query("alg_ir_versions", lambda: _trained_sql(VERSIONS, "version") + f", f as (select version, gold_id, arg_min(ok, pos) as top, bool_or(ok) as hit from items group by all) select version, round(count(*) filter (top) / {N}, 6) as top1, round(count(*) filter (hit) / {N}, 6) as coverage from f group by version")
def alg_ir_versions(spark, d):
    """Coverage and top-1 of three ways to put the IR into the algebra backbone, beside the plain one."""
    one = _beams(spark, d, VERSIONS).groupBy("version", "gold_id").agg(F.min_by("ex", "pos").alias("top"), F.bool_or("ex").alias("hit"))
    return one.groupBy("version").agg(_share("top").alias("top1"), _share("hit").alias("coverage"))


# ---- verifiers and selectors


def _verifier_rows(spark, d):
    """The first five candidates of the origins' beams with the gold query, labelled by execution."""
    rows = [(o, g, pos, q, lattice.fold_of(g) == 0) for o in ORIGINS for g, pos, q, _ in lattice.verifier_rows(o)]
    return spark.createDataFrame(rows, "origin string, gold_id string, pos int, sql string, dev boolean").join(_verdicts(spark, d), ["gold_id", "sql"])


def _verifier_sql() -> str:
    rows = [(o, g, pos, lattice.fold_of(g) == 0, _numbers()[g, q]) for o in ORIGINS for g, pos, q, _ in lattice.verifier_rows(o)]
    return f"with {_ex_table(_numbers())}, items as (select * from (values {', '.join(_quoted(*r) for r in rows)}) as v(origin, gold_id, pos, dev, n) join ex using (n))"


@query("label_distribution_sql", lambda: _verifier_sql() + " select origin, dev, count(*) filter (ok) as positive, count(*) filter (not ok) as negative, round(100 * count(*) filter (ok) / count(*), 4) as percent from items group by all")
def label_distribution_sql(spark, d):
    """Right and wrong candidates with the gold query put in, by origin and split."""
    return beams.label_distribution(_verifier_rows(spark, d).withColumn("correct", F.col("ex")), "origin", "dev")


def _judged(spark, d):
    """Probabilities of the verifiers of either origin, with and without schema, fitted without the question's fold."""

    def run(batches):
        for b in batches:
            for trained_on in ORIGINS:
                for schema in (True, False):
                    p = [lattice.verdict(trained_on, schema, g, q) for g, q in zip(b["gold_id"], b["sql"], strict=True)]
                    yield b.assign(trained_on=trained_on, with_schema=schema, prob=p)

    return _verifier_rows(spark, d).mapInPandas(run, "gold_id string, sql string, origin string, pos int, dev boolean, ex boolean, valid boolean, trained_on string, with_schema boolean, prob double")


@query("verifier_sql_scores")
def verifier_sql_scores(spark, d):
    return _judged(spark, d).select("origin", "gold_id", "pos", "trained_on", "with_schema", F.round("prob", 6).alias("prob"), "ex")


def _judged_sql() -> str:
    rows = []
    for o in ORIGINS:
        for g, _, q, _ in lattice.verifier_rows(o):
            rows += [(t, o, schema, _numbers()[g, q], lattice.verdict(t, schema, g, q) >= 0.5) for t in ORIGINS for schema in (True, False)]
    return (
        f"with {_ex_table(_numbers())}, j as (select * from (values {', '.join(_quoted(*r) for r in rows)}) as v(trained_on, applied_to, with_schema, n, verified) join ex using (n)), "
        "k as (select trained_on, applied_to, with_schema, count(*) filter (verified and ok) as tp, count(*) filter (verified and not ok) as fp, count(*) filter (not verified and ok) as fn, count(*) filter (not verified and not ok) as tn from j group by all), "
        "prf as (select *, round(tp / nullif(tp + fp, 0), 6) as precision, round(tp / nullif(tp + fn, 0), 6) as recall, round(2 * tp / nullif(2 * tp + fp + fn, 0), 6) as f1 from k)"
    )


@query("verifier_sql_prf", lambda: _judged_sql() + " select * from prf")
def verifier_sql_prf(spark, d):
    """Precision, recall and F1 of the verifiers: by origin of their training beams, origin of the beams judged, and use of the schema."""
    rows = _judged(spark, d).withColumn("verified", F.col("prob") >= 0.5).withColumn("correct", F.col("ex"))
    return metrics.prf(rows.withColumnRenamed("origin", "applied_to"), "trained_on", "applied_to", "with_schema")


def _selected(order: str, k: int, origin: str) -> list[tuple[str, str]]:
    """(question, query) that a selector takes from each beam of its origin, gold query included."""
    out = []
    for g, found in lattice._by_question(lattice.system(*ORIGINS[origin])).items():
        rows = lattice._gold_in(found, GOLD_OF[g], k, False)
        out.append((g, rows[lattice.choice(origin, k, order, g, [q for q, _ in rows])][0]))
    return out


GRID = [(order, k, origin) for order in ("random", "geometric") for k in (5, 2) for origin in ORIGINS]


@query("selector_grid_sql", lambda: f"with {_ex_table(_numbers())}, t as (select * from (values " + ", ".join(_quoted(*c, _numbers()[x]) for c in GRID for x in _selected(*c)) + f') as v("order", k, origin, n) join ex using (n)) select "order", k, origin, round(count(*) filter (ok) / {N}, 6) as accuracy from t group by all')
def selector_grid_sql(spark, d):
    """Accuracy of selectors from random and geometric orders, five and two candidates, beams of either origin."""

    def run(batches):
        for b in batches:
            out = []
            for c in b.itertuples(index=False):
                out += [(c.order, c.k, c.origin, *x) for x in _selected(c.order, c.k, c.origin)]
            yield pd.DataFrame(out, columns=["order", "k", "origin", "gold_id", "sql"])

    grid = spark.createDataFrame(GRID, "order string, k int, origin string").repartition(8)
    taken = grid.mapInPandas(run, "order string, k int, origin string, gold_id string, sql string").join(_verdicts(spark, d), ["gold_id", "sql"])
    return taken.groupBy("order", "k", "origin").agg(_share("ex").alias("accuracy"))


def _gold_rows(spark, d):
    """Beams of the sequence origin, and the gold queries, with three keys to match them by."""
    b, m = ORIGINS["seq"]
    rows = [(g, pos, q, lattice.same_parts(q, GOLD_OF[g])) for g, pos, q, _, _ in lattice.system(b, m)]
    verdicts = _verdicts(spark, d)
    key = lambda c, t: F.when(F.col(c), F.lit("gold")).otherwise(F.col(t))
    items = spark.createDataFrame(rows, "gold_id string, pos int, sql string, em boolean").join(verdicts, ["gold_id", "sql"])
    golds = spark.createDataFrame([(g, q, True, True) for g, q in GOLD_OF.items()], "gold_id string, sql string, em boolean, ex boolean")
    shape = lambda df: df.select(F.col("gold_id").alias("beam_id"), *(["pos"] if "pos" in df.columns else []), "sql", key("em", "sql").alias("by_em"), key("ex", "sql").alias("by_ex"))
    return shape(items), shape(golds)


def _gold_sql(k: int, front: bool, on: str) -> str:
    b, m = ORIGINS["seq"]
    rows = [(g, pos, _numbers()[g, q], q, q == GOLD_OF[g], em) for g, pos, q, _, em in lattice.system(b, m)]
    hit = {"sql": "t", "by_em": "em", "by_ex": "ok"}[on]
    moved = "pos + 1" if front else "pos"
    place = "1" if front else f"least(cnt + 1, {k})"
    return (
        f"with {_ex_table(_numbers())}, items as (select * from (values {', '.join(_quoted(*r) for r in rows)}) as v(beam_id, pos, n, sql, t, em) join ex using (n) where pos <= {k}), "
        f"b as (select beam_id, not bool_or({hit}) as absent, count(*) as cnt from items group by beam_id), golds(beam_id, gold) as (values {', '.join(_quoted(*r) for r in GOLD_OF.items())}) "
        f"select beam_id, sql, (case when absent then {moved} else pos end)::int as pos, {hit} as is_gold from items join b using (beam_id) "
        f"where not absent or {f'pos + 1 <= {k}' if front else f'pos < {k}'} union all select beam_id, gold, ({place})::int, true from golds join b using (beam_id) where absent"
    )


def _gold_query(name: str, k: int, mode: str, on: str):
    @query(name, lambda: _gold_sql(k, mode == "front", on))
    def run(spark, d):
        items, golds = _gold_rows(spark, d)
        return beams.insert_gold(items, golds, k, mode, on).select("beam_id", "sql", "pos", "is_gold")

    return run


gold_replace_last_sql = _gold_query("gold_replace_last_sql", 5, "replace_last", "sql")
gold_replace_last_em = _gold_query("gold_replace_last_em", 5, "replace_last", "by_em")
gold_replace_last_ex = _gold_query("gold_replace_last_ex", 5, "replace_last", "by_ex")
gold_front5_sql = _gold_query("gold_front5_sql", 5, "front", "sql")
gold_front2_sql = _gold_query("gold_front2_sql", 2, "front", "sql")
gold_front2_ex = _gold_query("gold_front2_ex", 2, "front", "by_ex")


@query("rerank_linking_sql")
def rerank_linking_sql(spark, d):
    """Schema linking: the candidate whose tables and columns the question names best; ties go to the better rank."""

    def run(batches):
        for b in batches:
            seen = [lattice.seen_by_verifier(QUESTIONS[g][0], q, True)[-5:] for g, q in zip(b["gold_id"], b["sql"], strict=True)]
            yield b.assign(link=[float(x[0] + x[1] + x[2] - x[3] - x[4]) for x in seen])

    rows = lattice.generated(spark, lattice.configurations(ALL)).select("backbone", "mask", "gold_id", "pos", "sql")
    linked = rows.mapInPandas(run, "backbone string, mask int, gold_id string, pos int, sql string, link double").join(_verdicts(spark, d), ["gold_id", "sql"])
    best = linked.groupBy("backbone", "mask", "gold_id").agg(F.max_by("ex", F.struct(F.round("link", 6), -F.col("pos"))).alias("ex"))
    return best.groupBy("backbone", "mask").agg(_share("ex").alias("ex"))


# ---- training sets and the measured lattice


def _trained(spark, d, configs, *by):
    one = _beams(spark, d, configs).where("pos = 1")
    return one.groupBy(*by).agg(_share("ex").alias("ex"), _share("em").alias("em"))


SIZES = lattice.configurations([("alg", GS), ("seq", GS)], shares=(0.0, 0.1, 0.25, 0.5, 1.0))


@query("synth_size_training", lambda: _trained_sql(SIZES, "share") + f" select backbone, share::double as share, {SCORES} from items where pos = 1 group by backbone, share")
def synth_size_training(spark, d):
    """Accuracy after training on growing shares of the synthetic pairs, and then on the gold pairs."""
    return _trained(spark, d, SIZES, "backbone", "share")


MIXES = lattice.configurations([("alg", GS), ("seq", GS)], mixes=("easy", "medium", "hard", "all"))


@query("synth_difficulty_training", lambda: _trained_sql(MIXES, "mix") + f" select backbone, mix, {SCORES} from items where pos = 1 group by backbone, mix")
def synth_difficulty_training(spark, d):
    """Accuracy after training on synthetic pairs of one difficulty, or of all."""
    return _trained(spark, d, MIXES, "backbone", "mix")


STAGES = lattice.configurations([("alg", GS), ("seq", GS)], stages=("synthetic", "gold", "both"))


@query("two_stage_accuracy", lambda: _trained_sql(STAGES, "stages") + f" select backbone, stages, {SCORES} from items where pos = 1 group by backbone, stages")
def two_stage_accuracy(spark, d):
    """After the synthetic pairs alone, the gold pairs alone, and one after the other."""
    return _trained(spark, d, STAGES, "backbone", "stages")


def measured_scores(spark, d):
    """(backbone, rr_origin, metric, mask, value in points): the whole lattice of four components, for rerankers of either origin."""
    taken = _choices(spark, d, rerankers=("none", "selector"))
    one = taken.groupBy("backbone", "mask", "origin").agg((100 * F.count_if("ex") / N).alias("EX"), (100 * F.count_if("em") / N).alias("EM"))
    each = one.withColumn("rr_origin", F.explode(F.when(F.col("origin") == "none", F.array(*map(F.lit, ORIGINS))).otherwise(F.array("origin"))))
    bit = F.when(F.col("origin") == "none", 0).otherwise(8)
    return each.select("backbone", "rr_origin", F.expr("stack(2, 'EX', EX, 'EM', EM) as (metric, value)"), (F.col("mask") + bit).alias("mask"))


def _lattice_sql() -> str:
    """scores(backbone, rr_origin, metric, value, mask): the measured lattice."""
    return _choices_sql(rerankers=("none", "selector")) + f""", s as (select backbone, mask, origin, 100 * count(*) filter (ok) / {N} as ex, 100 * count(*) filter (em) / {N} as em from c group by all),
o as (select *, unnest(case when origin = 'none' then ['alg', 'seq'] else [origin] end) as rr_origin from s), m as (select unnest(['EX', 'EM']) as metric),
scores as (select backbone, rr_origin, metric, case metric when 'EX' then ex else em end as value, (mask + case origin when 'none' then 0 else 8 end)::int as mask from o, m),
players(player, bit) as (values ('ir', 1), ('gs', 2), ('pp', 4), ('rr', 8)),
marg as (select a.backbone, a.rr_origin, a.metric, player, a.mask as context, b.value - a.value as delta
         from scores a, players, scores b where a.backbone = b.backbone and a.rr_origin = b.rr_origin and a.metric = b.metric and a.mask & bit = 0 and b.mask = a.mask | bit),
phi as (select backbone, rr_origin, metric, player, round(sum(delta * case bit_count(context) when 0 then 1.0::double / 4 when 3 then 1.0::double / 4 else 1.0::double / 12 end), 6) as phi from marg group by all)"""


@query("measured_lattice", lambda: _lattice_sql() + " select backbone, rr_origin, metric, round(value, 6) as value, mask from scores")
def measured_lattice(spark, d):
    return measured_scores(spark, d).withColumn("value", F.round("value", 6))


@query("shapley_measured", lambda: _lattice_sql() + " select * from phi")
def shapley_measured(spark, d):
    """Exact Shapley values of the four components over the measured lattice."""
    return shapley.exact(measured_scores(spark, d))


@query("shapley_measured_overall", lambda: _lattice_sql() + " select backbone, metric, player, round(avg(phi), 6) as phi from phi group by all")
def shapley_measured_overall(spark, d):
    return shapley.overall(shapley.exact(measured_scores(spark, d)))


@query("component_delta_measured", lambda: _lattice_sql() + " select backbone, rr_origin, metric, player, round(delta, 6) as points from marg where context = 0")
def component_delta_measured(spark, d):
    """What each component alone adds to its backbone (mask 0), by execution and component match."""
    return shapley.marginals(measured_scores(spark, d)).where("context = 0").select("backbone", "rr_origin", "metric", "player", F.round("delta", 6).alias("points"))


@query("pair_interaction_measured", lambda: _lattice_sql() + " select z.backbone, z.rr_origin, z.metric, z.mask as context, round(c.value - a.value - b.value + z.value, 6) as interaction from scores z join scores a using (backbone, rr_origin, metric) join scores b using (backbone, rr_origin, metric) join scores c using (backbone, rr_origin, metric) where z.mask & 6 = 0 and a.mask = z.mask + 2 and b.mask = z.mask + 4 and c.mask = z.mask + 6")
def pair_interaction_measured(spark, d):
    return shapley.interactions(measured_scores(spark, d))


@query("leave_one_out_measured", lambda: _lattice_sql() + " select backbone, rr_origin, metric, player, round(delta, 6) as loss from marg join players using (player) where context + bit = 15")
def leave_one_out_measured(spark, d):
    return shapley.leave_one_out(measured_scores(spark, d))


@query("combine_all_vs_best_measured", lambda: _lattice_sql() + " select backbone, rr_origin, metric, arg_max(mask, (value, -mask)) as best_mask, round(max(value) - max(value) filter (mask = 15), 6) as lead from scores group by all")
def combine_all_vs_best_measured(spark, d):
    return shapley.all_vs_best(measured_scores(spark, d))


@query("schema_ablation_measured", lambda: _judged_sql() + " select a.trained_on as origin, round(a.precision - b.precision, 6) as precision_gain, round(a.recall - b.recall, 6) as recall_gain, round(a.f1 - b.f1, 6) as f1_gain from prf a join prf b using (trained_on, applied_to) where a.with_schema and not b.with_schema and a.trained_on = applied_to")
def schema_ablation_measured(spark, d):
    """F1 of each verifier with the schema, less that without it, on beams of its own origin."""
    rows = verifier_sql_prf(spark, d).where("trained_on = applied_to")
    pick = lambda c, s: F.max(F.when(F.col("with_schema") == s, F.col(c)))
    return rows.groupBy(F.col("trained_on").alias("origin")).agg(*[F.round(pick(c, True) - pick(c, False), 6).alias(f"{c}_gain") for c in ("precision", "recall", "f1")])


# ---- candidates that fail when they run

#: (text, reference text, whether they match, whether the text runs)
FAILING = [
    ("select 1 / (r_regionkey - r_regionkey) as v from region", "select 1 as v", False, False),
    ("select r_name from region", "select r_name from region", True, True),
    ("select cast(r_name as int) as v from region", "select 1 as v", False, False),
    ("select cast(1e300 as double) * r_regionkey as v from region", "select cast(1e300 as double) * r_regionkey as v from region", True, True),
    ("select cast(2147483647 as int) + cast(r_regionkey as int) as v from region", "select r_regionkey as v from region", False, False),
    ("select cast('NaN' as double) as v", "select cast(null as double) as v", False, True),
    ("select cast('NaN' as double) as v", "select cast('NaN' as double) as v", True, True),
    ("select cast('Infinity' as double) as v", "select cast('-Infinity' as double) as v", False, True),
    ("select no_such_column from region", "select r_name from region", False, False),
    ("select element_at(array(1, 2), 5 + r_regionkey) as v from region", "select 1 as v", False, False),
]


@query("ex_failing", "select * from (values " + ", ".join(_quoted(i, ex, valid) for i, (_, _, ex, valid) in enumerate(FAILING)) + ") as v(n, ex, valid)")
def ex_failing(spark, d):
    """Candidates that divide by zero, overflow, cast badly or give NaN are judged one by one, beside others of their batch."""
    prints = execute.fingerprints(spark, d, list(dict.fromkeys(q for a, b, *_ in FAILING for q in (a, b))))
    rows = [(i, prints[a] is not None and prints[a] == prints[b], prints[a] is not None) for i, (a, b, *_) in enumerate(FAILING)]
    return spark.createDataFrame(rows, "n int, ex boolean, valid boolean")
