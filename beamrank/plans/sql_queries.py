"""Component match, execution match, the simplified IR, and the simulated systems."""

from __future__ import annotations

from itertools import product

import pandas as pd
from pyspark.sql import functions as F

from beamrank.functions import sqlshape
from beamrank.operators import execute
from beamrank.operators.generators import EDITS, candidates, edits
from beamrank.plans.registry import query
from beamrank.operators.lattice import OWNER
from beamrank.plans.text_queries import PAIRS_SQL, gold_table
from beamrank.sources.catalogue import GOLD
from beamrank.sources.tables import FOREIGN_KEYS, table

GOLD_OF = {g: q for g, _, q, _ in GOLD}


def sql_parts_udf(sql):
    """Clauses of each text, in Arrow batches; distinct texts only are worth parsing."""
    return F.pandas_udf(_parts_of, sqlshape.SCHEMA)(sql)


def _parts_of(sql: pd.Series) -> pd.DataFrame:
    empty = {"distinct": False, **{f: [] for f in sqlshape.FIELDS}, "limit": "", "setop": "", "nested": 0}
    rows = [sqlshape.parts(q) for q in sql]
    return pd.DataFrame([{"ok": p is not None, **{k: (p or empty)[k] for k in empty}} for p in rows])


#: Gold queries of a part, with places for its values. All values are categories, so that distinct texts are few.
PART_FORMS = [
    (1, "select count(*) as n from part where p_size >= {s} and p_brand < '{b}'"),
    (2, "select distinct p_type from part where p_brand = '{b}' and p_size between {s} and 50 order by p_type desc limit 3"),
]
#: Edits that apply to each form, by what they do, the gold query itself first.
PART_KINDS = {
    1: ("gold", "alias", "conjuncts", "comparison", "literal", "condition", "syntax"),
    2: ("gold", "two comparisons", "comparison", "limit", "direction", "distinct", "syntax"),
}


def _part_candidates(spark, d):
    """Each distinct gold query that the parts give, with its candidates and how many parts it stands for."""

    def run(batches):
        for b in batches:
            rows = []
            for r in b.itertuples(index=False):
                for form, text in PART_FORMS:
                    gold = text.format(s=r.p_size, b=r.p_brand.replace("'", "''"))
                    made = [("gold", gold), *((k, f(gold)) for k, f in EDITS)]
                    rows += [(form, k, q, gold, r.parts) for k, q in made if k in PART_KINDS[form]]
            yield pd.DataFrame(rows, columns=["form", "kind", "sql", "gold", "parts"])

    seen = table(spark, d, "part").where("p_brand is not null and p_size is not null").groupBy("p_brand", "p_size").agg(F.count(F.lit(1)).alias("parts"))
    return seen.mapInPandas(run, "form int, kind string, sql string, gold string, parts bigint")


def _candidates(spark):
    rows = [(g, k, q, GOLD_OF[g]) for g, k, q in candidates()]
    return spark.createDataFrame(rows, "gold_id string, kind string, sql string, gold string")


CLAUSES = ["distinct", *sqlshape.FIELDS, "limit", "setop"]


def _compared(rows, masked: bool = False):
    """Candidates with their clauses and the gold query's."""
    if masked:
        mask = lambda c: F.regexp_replace(F.regexp_replace(c, "'[^']*'", "'v'"), r"(?<![\w.])\d+(\.\d+)?", "0")
        rows = rows.withColumn("gold", mask("gold")).withColumn("text", mask("sql"))
    else:
        rows = rows.withColumn("text", F.col("sql"))
    return rows.withColumn("p", sql_parts_udf("text")).withColumn("g", sql_parts_udf("gold"))


def _em(rows):
    same = F.col("p.ok") & F.col("g.ok")
    for c in CLAUSES:
        same = same & (F.col(f"p.{c}") == F.col(f"g.{c}"))
    return rows.withColumn("em", same)


@query("sql_parts")
def sql_parts(spark, d):
    return gold_table(spark).withColumn("p", sql_parts_udf("sql")).select("gold_id", *[F.array_join(f"p.{f}", " ; ").alias(f"in_{f}") for f in sqlshape.FIELDS], F.col("p.nested").alias("nested"))


@query("udf_sql_parts", "select s like 'select %' and length(replace(s, '(', '')) = length(replace(s, ')', '')) as parsed, count(*) as texts from (values " + ", ".join("('" + q.replace("'", "''") + "')" for q in dict.fromkeys(q for _, _, q in candidates())) + ") as t(s) group by parsed")
def udf_sql_parts(spark, d):
    return _candidates(spark).select("sql").distinct().withColumn("p", sql_parts_udf("sql")).groupBy(F.col("p.ok").alias("parsed")).agg(F.count(F.lit(1)).alias("texts"))


#: Edits that leave every component as it is, by what they do.
KEEPS = ("gold", "alias", "conjuncts", "two comparisons")
PART_KINDS_SQL = "k(form, kind) as (values " + ", ".join(f"({f}, {k!r})" for f, kinds in PART_KINDS.items() for k in kinds) + ")"
EM_SQL = f"with {PART_KINDS_SQL} select kind, count(*) filter (kind in {KEEPS}) as matches, count(*) as candidates from part, k where p_brand is not null and p_size is not null group by kind"


def _em_by_kind(rows):
    return rows.groupBy("kind").agg(F.sum(F.when(F.col("em"), F.col("parts")).otherwise(0)).alias("matches"), F.sum("parts").alias("candidates"))


@query("em_accuracy", EM_SQL)
def em_accuracy(spark, d):
    """Component match of the candidates for two queries on each part, by what was done to them."""
    return _em_by_kind(_em(_compared(_part_candidates(spark, d))))


#: With values masked, other numbers make no difference either.
EM_MASKED_SQL = EM_SQL.replace(str(KEEPS), str((*KEEPS, "literal", "limit")))


@query("em_ignore_values", EM_MASKED_SQL)
def em_ignore_values(spark, d):
    return _em_by_kind(_em(_compared(_part_candidates(spark, d), True)))


@query("em_by_component")
def em_by_component(spark, d):
    """Share of the candidates that parse whose component is the gold query's, over all parts."""
    rows = _compared(_part_candidates(spark, d)).where("p.ok")
    return rows.agg(*[F.round(F.sum(F.when(F.col(f"p.{c}") == F.col(f"g.{c}"), F.col("parts")).otherwise(0)) / F.sum("parts"), 6).alias(f"match_{c}") for c in CLAUSES])


@query("em_plan")
def em_plan(spark, d):
    """Candidates for the queries generated from the tables whose optimised plan is that of the generated query.

    Analysis is on the driver, once for each distinct text: their number goes by the templates and the
    categories that fill them, and N_PAIRS at most.
    """
    from beamrank.operators import synth
    from beamrank.plans.text_queries import N_PAIRS

    execute.register(spark, d)
    rows = []
    for gold in sorted(r["sql"] for r in synth.generate(spark, d, N_PAIRS).select("sql").distinct().collect()):
        own = execute.analysed(spark, gold)
        for kind, q in [("gold", gold), *edits(gold, gold, True)]:
            df = execute.analysed(spark, q)
            rows.append((gold, kind, df is not None and own is not None and len(df.columns) == len(own.columns) and df.sameSemantics(own)))
    return spark.createDataFrame(rows, "gold string, kind string, same_plan boolean")


def _ex_sql() -> str:
    """Bag difference both ways, for every candidate that parses."""
    out = []
    for g, kind, q in candidates():
        gold = GOLD_OF[g]
        runs = kind != "syntax" and q.count("(") == q.count(")")
        same = f"not exists (({q}) except all ({gold})) and not exists (({gold}) except all ({q}))"
        out.append(f"select '{g}' as gold_id, '{kind}' as kind, {same if runs else 'false'} as ex, {str(runs).lower()} as valid, (select count(*) from ({gold})) as gold_rows")
    return "with ex as (" + " union all ".join(out) + ")"


EX = _ex_sql()


@query("ex_accuracy", EX + " select kind, count(*) filter (ex) as matches, count(*) as candidates from ex group by kind")
def ex_accuracy(spark, d):
    return execute.label_table(spark, d).groupBy("kind").agg(F.count_if("ex").alias("matches"), F.count(F.lit(1)).alias("candidates"))


@query("ex_nonempty", EX + " select kind, count(*) filter (ex) as matches, count(*) as candidates from ex where gold_rows > 0 group by kind")
def ex_nonempty(spark, d):
    return execute.label_table(spark, d).where("gold_rows > 0").groupBy("kind").agg(F.count_if("ex").alias("matches"), F.count(F.lit(1)).alias("candidates"))


@query("ex_invalid_share", EX + " select count(*) filter (not valid) as invalid, count(*) as candidates, round(count(*) filter (not valid) / count(*), 6) as share from ex")
def ex_invalid_share(spark, d):
    bad = F.count_if(~F.col("valid"))
    return execute.label_table(spark, d).agg(bad.alias("invalid"), F.count(F.lit(1)).alias("candidates"), F.round(bad / F.count(F.lit(1)), 6).alias("share"))


@query("constrained_filter", EX + " select gold_id, count(*) as candidates, count(*) filter (valid) as kept from ex group by gold_id")
def constrained_filter(spark, d):
    """Candidates that a decoder bound to the grammar could give."""
    return execute.label_table(spark, d).groupBy("gold_id").agg(F.count(F.lit(1)).alias("candidates"), F.count_if("valid").alias("kept"))


def _ordered_sql() -> str:
    """Rows with their places, by difference both ways."""
    out = []
    for g, k, q in candidates():
        if " order by " in GOLD_OF[g]:
            a, b = (f"select row_number() over () as place, * from ({x})" for x in (q, GOLD_OF[g]))
            same = f"not exists (({a}) except all ({b})) and not exists (({b}) except all ({a}))" if k != "syntax" else "false"
            out.append(f"select '{g}' as gold_id, '{k}' as kind, {same} as ex")
    return " union all ".join(out)


@query("ex_ordered", _ordered_sql())
def ex_ordered(spark, d):
    """Execution match of the sorted gold queries and their candidates, with the order of rows counting."""
    rows = [(g, k, q) for g, k, q in candidates() if " order by " in GOLD_OF[g]]
    prints = execute.fingerprints(spark, d, list(dict.fromkeys(q for _, _, q in rows)), ordered=True)
    golds = {g: prints[GOLD_OF[g]] for g, _, _ in rows}
    return spark.createDataFrame([(g, k, prints[q] is not None and prints[q] == golds[g]) for g, k, q in rows], "gold_id string, kind string, ex boolean")


@query("em_ex_confusion", EX + f" select kind in {KEEPS} as em, count(*) filter (ex) as ex_right, count(*) filter (not ex) as ex_wrong from ex group by 1")
def em_ex_confusion(spark, d):
    em = _em(_compared(_candidates(spark))).select("gold_id", "sql", "em")
    return execute.label_table(spark, d).join(em, ["gold_id", "sql"]).groupBy("em").pivot("ex", [True, False]).agg(F.count(F.lit(1))).na.fill(0).withColumnsRenamed({"true": "ex_right", "false": "ex_wrong"})


PREDICATES = {f"q{q}d{x}": f"l_quantity {op} {q} and l_discount >= {x}" for (op, q), x in product([("<", 10), (">=", 40), ("=", 1)], [0.02, 0.05, 0.09])}


@query("ex_fused_scan", " union all ".join(f"select '{k}' as candidate, count(*) as n from lineitem where {p}" for k, p in PREDICATES.items()))
def ex_fused_scan(spark, d):
    return execute.fused_scan(table(spark, d, "lineitem"), PREDICATES)


def ir_udf(sql):
    """IR, or the reason for none, lengths and the decoded query of each text."""
    return F.pandas_udf(_ir_of, "text string, reason string, n_ir int, n_sql int, decoded string")(sql)


def _ir_of(sql: pd.Series) -> pd.DataFrame:
    out = []
    for q in sql:
        ir, reason = sqlshape.encode(q, OWNER, FOREIGN_KEYS)
        text = sqlshape.ir_text(ir) if ir else None
        out.append((text, reason, len(text.split()) if text else None, len(sqlshape.tokenize(q)), sqlshape.decode(ir, OWNER, FOREIGN_KEYS) if ir else None))
    return pd.DataFrame(out, columns=["text", "reason", "n_ir", "n_sql", "decoded"]).astype({"n_ir": "Int32", "n_sql": "Int32"})


@query("ir_encode")
def ir_encode(spark, d):
    return gold_table(spark).withColumn("ir", ir_udf("sql")).select("gold_id", F.col("ir.text").alias("ir"), F.col("ir.reason").alias("reason"))


@query("ir_decode")
def ir_decode(spark, d):
    return gold_table(spark).withColumn("ir", ir_udf("sql")).where("ir.text is not null").select("gold_id", F.col("ir.decoded").alias("sql"))


@query("ir_compactness")
def ir_compactness(spark, d):
    """Tokens of the IR and of the SQL, over the queries generated from the tables; each distinct text is encoded once."""
    from beamrank.operators import synth
    from beamrank.plans.text_queries import N_PAIRS

    texts = synth.generate(spark, d, N_PAIRS).groupBy("sql").agg(F.count(F.lit(1)).alias("n"))
    rows = texts.withColumn("ir", ir_udf("sql")).where("ir.text is not null")
    ir, sql = F.sum(F.col("ir.n_ir") * F.col("n")), F.sum(F.col("ir.n_sql") * F.col("n"))
    return rows.agg(F.sum("n").alias("queries"), ir.alias("ir_tokens"), sql.alias("sql_tokens"), F.round(ir / sql, 6).alias("ratio"))


@query("synth_executable", f"with {PAIRS_SQL} select distinct sql, true as runs from pairs")
def synth_executable(spark, d):
    """Distinct generated queries that run; each distinct text is analysed once."""
    from beamrank.operators import synth
    from beamrank.plans.text_queries import N_PAIRS

    execute.register(spark, d)
    texts = [r["sql"] for r in synth.generate(spark, d, N_PAIRS).select("sql").distinct().collect()]
    return spark.createDataFrame([(q, execute.analysed(spark, q) is not None) for q in sorted(texts)], "sql string, runs boolean")
