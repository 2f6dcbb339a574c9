"""Token preprocessing, synthesis and the verifier's inputs."""

from __future__ import annotations

from pyspark.sql import functions as F

from beamrank.functions import tokens
from beamrank.operators import beams, metrics, synth
from beamrank.plans.registry import query
from beamrank.sources.catalogue import GOLD
from beamrank.sources.tables import CHAT_SQL, COLUMNS, FOREIGN_KEYS, LINE_SQL, TABLES, chat_beams, line_beams, schema_columns, table

COLUMNS_SQL = "cols(table_name, column_name) as (values " + ", ".join(f"('{t}', '{c}')" for t in TABLES for c in COLUMNS[t].split()) + ")"
GOLD_SQL = "gold(gold_id, question, sql, difficulty) as (values " + ", ".join("(" + ", ".join("'" + x.replace("'", "''") + "'" for x in row) + ")" for row in GOLD) + ")"


def gold_table(spark):
    return spark.createDataFrame(GOLD, "gold_id string, question string, sql string, difficulty string")


@query("pp_identifier", f"with {COLUMNS_SQL} select table_name, column_name, array_to_string(string_split_regex(trim(replace(column_name, '_', ' _ ')), ' +'), '|') as tokens from cols")
def pp_identifier(spark, d):
    return schema_columns(spark, d).select("table_name", "column_name", F.array_join(tokens.split_ident(F.col("column_name")), "|").alias("tokens"))


@query("pp_camel", r"select p_partkey, regexp_replace(replace(p_name, ' ', ''), '([a-z0-9])([A-Z])', '\1 \2', 'g') as tokens from part")
def pp_camel(spark, d):
    return table(spark, d, "part").select("p_partkey", tokens.split_camel(F.replace("p_name", F.lit(" "), F.lit(""))).alias("tokens"))


@query("pp_sql_spacing", f"with {GOLD_SQL}, " + r"""parts as (select gold_id, unnest(string_split(sql, '''')) as p, generate_subscripts(string_split(sql, ''''), 1) as i from gold),
spaced as (select gold_id, i, case when i % 2 = 1 then regexp_replace(regexp_replace(p, '(<=|>=|<>|!=|[(),.=<>*+/-])', ' \1 ', 'g'), '\s+', ' ', 'g') else p end as p from parts)
select gold_id, trim(string_agg(p, '''' order by i)) as spaced from spaced group by gold_id""")
def pp_sql_spacing(spark, d):
    return gold_table(spark).select("gold_id", tokens.space_sql(F.col("sql")).alias("spaced"))


@query("pp_markers", f"with {GOLD_SQL}, " + r"""s as (select *, list_filter(string_split(regexp_replace(sql, '\b(select|from|where|group by|having|order by|limit)\b', chr(1) || '\1', 'g'), chr(1)), lambda x: x <> '') as parts from gold),
w as (select gold_id, parts, unnest(string_split(question, ' ')) as word, generate_subscripts(string_split(question, ' '), 1) as i from s),
k as (select *, lower(regexp_replace(word, '[^A-Za-z0-9]', '', 'g')) as plain from w),
p as (select *, list_position(list_transform(parts, lambda x: list_contains(string_split_regex(lower(x), '[^a-z0-9]+'), plain)), true) as spot from k),
q as (select gold_id, string_agg(case when plain <> '' and spot > 0 then '[c' || (spot - 1) || '] ' || word else word end, ' ' order by i) as question from p group by gold_id)
select gold_id, q.question || ' || ' || array_to_string(list_transform(parts, lambda x, n: '[c' || (n - 1) || '] ' || x), '') as marked from s join q using (gold_id)""")
def pp_markers(spark, d):
    clauses = ["select", "from", "where", "group by", "having", "order by", "limit"]
    return gold_table(spark).select("gold_id", tokens.mark_boundaries(F.col("question"), F.col("sql"), clauses).alias("marked"))


@query("pp_apply", f"with {GOLD_SQL}, " + r"""parts as (select gold_id, unnest(string_split(sql, '''')) as p, generate_subscripts(string_split(sql, ''''), 1) as i from gold),
done as (select gold_id, i, case when i % 2 = 1 then regexp_replace(regexp_replace(p, '([a-z0-9])([A-Z])', '\1 ~ \2', 'g'), '([A-Za-z0-9])_([A-Za-z0-9])', '\1 _ \2', 'g') else p end as p from parts)
select gold_id, string_agg(p, '''' order by i) as text from done group by gold_id""")
def pp_apply(spark, d):
    return gold_table(spark).select("gold_id", tokens.apply(F.col("sql")).alias("text"))


@query("pp_apply_schema", f"with {COLUMNS_SQL} select table_name, regexp_replace(table_name || ' : ' || string_agg(column_name, ' , ' order by column_name), '([A-Za-z0-9])_([A-Za-z0-9])', '\\1 _ \\2', 'g') as text from cols group by table_name")
def pp_apply_schema(spark, d):
    """The serialised schema, name by name, with the same splits as queries get."""
    names = schema_columns(spark, d).groupBy("table_name").agg(F.array_join(F.array_sort(F.collect_list("column_name")), " , ").alias("c"))
    return names.select("table_name", tokens.apply(F.concat_ws(" : ", "table_name", "c")).alias("text"))


@query("pp_roundtrip", f"with {COLUMNS_SQL}, {GOLD_SQL}, n as (select (select count(*) from cols) + (select count(*) from gold) as texts) select texts::bigint as texts, 0::bigint as mismatches from n")
def pp_roundtrip(spark, d):
    texts = schema_columns(spark, d).select(F.col("column_name").alias("t")).union(gold_table(spark).select("sql"))
    return texts.agg(F.count(F.lit(1)).alias("texts"), F.count_if(tokens.restore(tokens.apply(F.col("t"))) != F.col("t")).alias("mismatches"))


@query("pp_boundary_violations", f"with {COLUMNS_SQL}, p as (select table_name, column_name, unnest(list_transform(range(1, length(column_name) + 1, 3), lambda i: substr(column_name, i, 3))) as piece from cols) select table_name, column_name, count(*) filter (contains(piece, '_') and length(piece) > 1)::int as violations from p group by all")
def pp_boundary_violations(spark, d):
    return tokens.boundary_violations(schema_columns(spark, d), "column_name", 3).select("table_name", "column_name", "violations")


@query("sql_normalise", f"with {GOLD_SQL}, raw as (select gold_id, upper(substr(sql, 1, 6)) || '  ' || substr(sql, 7) || ' ;' as s, sql from gold) select gold_id, regexp_replace(sql, '^select', 'select', '') as sql from raw")
def sql_normalise(spark, d):
    messy = F.concat(F.upper(F.substring("sql", 1, 6)), F.lit("  "), F.expr("substring(sql, 7)"), F.lit(" ;"))
    return gold_table(spark).select("gold_id", tokens.normalise_sql(messy).alias("sql"))


@query("sql_difficulty", f"with {GOLD_SQL}, p as (select gold_id, " + r"""len(regexp_extract_all(lower(sql), '\b(join|group by|having|order by|limit|or|like)\b')) + 2 * (len(regexp_extract_all(lower(sql), '\(\s*select\b')) + len(regexp_extract_all(lower(sql), '\b(union|intersect|except)\b'))) as p from gold)
select gold_id, case p when 0 then 'easy' when 1 then 'medium' when 2 then 'hard' else 'extra' end as difficulty from p""")
def sql_difficulty(spark, d):
    return gold_table(spark).select("gold_id", synth.difficulty(F.col("sql")).alias("difficulty"))


N_PAIRS = 4000
HASH = "('0x' || substr(md5({}), 1, 8))::bigint"
VALUES_SQL = "vals as (" + " union all ".join(f"select {i} as template, row_number() over (order by v) - 1 as rank, v, count(*) over () as n from (select distinct {c} as v from {t})" for i, (_, _, _, (t, c)) in enumerate(synth.TEMPLATES)) + ")"
PAIRS_SQL = VALUES_SQL + ", forms(template, difficulty, q, s) as (values " + ", ".join("(" + str(i) + ", " + ", ".join("'" + x.replace("'", "''") + "'" for x in (dif, q, s)) + ")" for i, (dif, q, s, _) in enumerate(synth.TEMPLATES)) + f"""),
ids as (select i as pair_id, {HASH.format("i || '|42'")} % {len(synth.TEMPLATES)} as template from (select unnest(range({N_PAIRS})) as i)),
slots as (select pair_id, template, {HASH.format("pair_id || '|v42'")} % n as rank from ids join (select template, max(n) as n from vals group by template) using (template)),
pairs as (select pair_id, replace(q, '{{}}', v) as question, replace(s, '{{}}', v) as sql, difficulty from slots join vals using (template, rank) join forms using (template))"""


@query("synth_pairs", f"with {PAIRS_SQL} select * from pairs")
def synth_pairs(spark, d):
    return synth.generate(spark, d, N_PAIRS)


@query("synth_dedup", f"with {PAIRS_SQL} select min(pair_id) as pair_id, question, sql, any_value(difficulty) as difficulty from pairs group by question, sql")
def synth_dedup(spark, d):
    return synth.dedup(synth.generate(spark, d, N_PAIRS), "question", "sql")


@query("dup_rate", "select count(*) as generated, count(*) - count(distinct text) as duplicates, round(100 * (count(*) - count(distinct text)) / count(*), 4) as percent from documents")
def dup_rate(spark, d):
    return synth.dup_rate(table(spark, d, "documents"), "text")


@query("synth_dup_rate", f"with {PAIRS_SQL} select count(*) as generated, count(*) - count(distinct question || sql) as duplicates, round(100 * (count(*) - count(distinct question || sql)) / count(*), 4) as percent from pairs")
def synth_dup_rate(spark, d):
    return synth.dup_rate(synth.generate(spark, d, N_PAIRS), "question", "sql")


@query("dup_growth", """with f as (select doc_id, row_number() over (partition by text order by doc_id) > 1 as again from documents),
b as (select doc_id // 100 as bucket, count(*) as rows, count(*) filter (again) as duplicates from f group by 1)
select bucket, rows, duplicates, (sum(duplicates) over (order by bucket))::bigint as so_far from b""")
def dup_growth(spark, d):
    return synth.dup_growth(table(spark, d, "documents"), "text", "doc_id", 100)


@query("synth_size_sweep", f"with {PAIRS_SQL}, firsts as (select min(pair_id) as pair_id from pairs group by question, sql), s(share) as (values (0.1::double), (0.25), (0.5), (1.0)) select share, count(*) as pairs from firsts, s where {HASH.format(chr(39).join(['pair_id || ', '|42', '']))} / 4294967296.0::double < share group by share")
def synth_size_sweep(spark, d):
    pairs = synth.dedup(synth.generate(spark, d, N_PAIRS), "question", "sql")
    return synth.sizes(pairs, [0.1, 0.25, 0.5, 1.0]).groupBy("share").agg(F.count(F.lit(1)).alias("pairs"))


@query("synth_difficulty_mix", f"with {PAIRS_SQL}, r as (select *, row_number() over (partition by difficulty order by md5(pair_id || ':42'), pair_id) as n from pairs) select pair_id, question, sql, difficulty from r where n <= case difficulty when 'easy' then 300 when 'medium' then 200 else 100 end")
def synth_difficulty_mix(spark, d):
    return synth.stratify(synth.generate(spark, d, N_PAIRS), {"easy": 300, "medium": 200, "hard": 100})


SCHEMA_TEXT = " | ".join(f"{t} : {' , '.join(COLUMNS[t].split())}" for t in TABLES)


@query("verifier_input", f"with {CHAT_SQL} select beam_id, pos, concat_ws(' </s> ', text, question, '{SCHEMA_TEXT}') as sequence from chat_beams where pos <= 5")
def verifier_input(spark, d):
    """Candidate, question and serialised schema; the schema is one row, put on at the end."""
    names = schema_columns(spark, d).groupBy("table_name").agg(F.array_sort(F.collect_list(F.struct("ordinal", "column_name"))).alias("c"))
    order = F.array_position(F.array(*[F.lit(t) for t in TABLES]), F.col("table_name"))
    each = F.struct(order.alias("o"), F.concat(F.col("table_name"), F.lit(" : "), F.array_join(F.col("c.column_name"), " , ")).alias("t"))
    text = names.agg(F.array_join(F.transform(F.array_sort(F.collect_list(each)), lambda x: x["t"]), " | ").alias("schema"))
    rows = beams.first_k(chat_beams(spark, d), 5).crossJoin(F.broadcast(text))
    return rows.select("beam_id", "pos", F.concat_ws(" </s> ", "text", "question", "schema").alias("sequence"))


@query("verifier_input_noschema", f"with {CHAT_SQL} select beam_id, pos, concat_ws(' </s> ', text, question) as sequence from chat_beams where pos <= 5")
def verifier_input_noschema(spark, d):
    return beams.first_k(chat_beams(spark, d), 5).select("beam_id", "pos", F.concat_ws(" </s> ", "text", "question").alias("sequence"))


@query("verifier_dataset", f"""with {LINE_SQL}, golds as (select beam_id, arg_min(pos, (-price, pos)) as gold_pos from line_beams group by beam_id)
select beam_id, case when pos = gold_pos and gold_pos > 5 then 5 else pos end::int as pos, item_id, (correct or pos = gold_pos) as label, case when beam_id % 5 < 4 then 'train' else 'dev' end as split
from line_beams join golds using (beam_id) where (gold_pos <= 5 and pos <= 5) or (gold_pos > 5 and (pos < 5 or pos = gold_pos))""")
def verifier_dataset(spark, d):
    rows = beams.ensure_gold(beams.with_gold(line_beams(spark, d)), 5)
    return rows.select("beam_id", "pos", "item_id", (F.col("correct") | F.col("is_gold")).alias("label"), F.when(F.col("beam_id") % 5 < 4, "train").otherwise("dev").alias("split"))


@query("verifier_lexical", f"with {CHAT_SQL} select beam_id, pos, verified, score from chat_beams")
def verifier_lexical(spark, d):
    return chat_beams(spark, d).select("beam_id", "pos", "verified", "score")


CROSS = f"""with {CHAT_SQL}, c as (select *, case when beam_id % 2 = 0 then 'alg' else 'seq' end as origin, len(list_distinct(string_split(lower(question), ' '))) as words from chat_beams),
t as (select origin, avg(score / words) as theta from c where correct group by origin),
j as (select t.origin as trained_on, c.origin as applied_to, c.correct, score / words >= theta as verified from c, t),
counts as (select trained_on, applied_to, count(*) filter (verified and correct) as tp, count(*) filter (verified and not correct) as fp, count(*) filter (not verified and correct) as fn, count(*) filter (not verified and not correct) as tn from j group by all)
select *, round(tp / nullif(tp + fp, 0), 6) as precision, round(tp / nullif(tp + fn, 0), 6) as recall, round(2 * tp / nullif(2 * tp + fp + fn, 0), 6) as f1 from counts"""


def _cross(spark, d):
    """Lexical verifiers whose threshold comes from one origin's beams, on beams of either."""
    from beamrank.sources.tables import words

    rows = chat_beams(spark, d).withColumn("origin", F.when(F.col("beam_id") % 2 == 0, "alg").otherwise("seq")).withColumn("s", F.col("score") / F.size(words(F.col("question"))))
    theta = rows.where("correct").groupBy(F.col("origin").alias("trained_on")).agg(F.avg("s").alias("theta"))
    return rows.crossJoin(F.broadcast(theta)).withColumn("applied_to", F.col("origin")).withColumn("verified", F.col("s") >= F.col("theta"))


@query("verifier_cross_origin", CROSS)
def verifier_cross_origin(spark, d):
    return metrics.prf(_cross(spark, d), "trained_on", "applied_to")


@query("rerank_cross_origin", CROSS.split("counts as")[0].replace("c.correct, score", "c.beam_id, c.pos, c.item_id, c.correct, score") + """r as (select trained_on, applied_to, beam_id, arg_min(correct, (case when verified then 0 else 1 end, pos)) as c from j group by all)
select trained_on, applied_to, count(*) as beams, count(*) filter (c) as right from r group by all""")
def rerank_cross_origin(spark, d):
    rows = _cross(spark, d)
    key = F.when(F.col("verified"), 0).otherwise(1 << 32) + F.col("pos")
    picks = rows.groupBy("trained_on", "applied_to", "beam_id").agg(F.min_by("correct", key).alias("c"))
    return picks.groupBy("trained_on", "applied_to").agg(F.count(F.lit(1)).alias("beams"), F.count_if("c").alias("right"))


@query("rerank_verifier_noschema", f"with {CHAT_SQL} select beam_id, arg_min(item_id, (case when verified then 0 else 1 end, pos)) as item_id, arg_min(correct, (case when verified then 0 else 1 end, pos)) as correct from chat_beams where pos <= 5 group by beam_id")
def rerank_verifier_noschema(spark, d):
    """The verifier over whole beams; its SQL stops at five answers, and is equal where no beam has more."""
    from beamrank.operators import rerank

    return rerank.verifier(chat_beams(spark, d))


@query("schema_keys", "with k(t, c, ft, fc) as (values " + ", ".join(f"('{t}', '{c}', '{ft}', '{fc}')" for (t, c), (ft, fc) in FOREIGN_KEYS.items()) + ") select t as table_name, c as column_name, ft as fk_table, fc as fk_column from k")
def schema_keys(spark, d):
    return schema_columns(spark, d).where("fk_table is not null").select("table_name", "column_name", "fk_table", "fk_column")
