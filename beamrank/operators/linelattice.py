"""The lattice of four components, measured on line beams.

A candidate is a line of an order. The backbone ``alg`` ranks lines as they come, ``seq`` the other way
round. Each component is a test that candidates must pass, and a system takes the first candidate that
passes all of its components' tests, or the first of all if none does. The reranker has a test by origin.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from beamrank.sources.tables import LINE_ORDER, line_beams, table

#: Component -> its test, in SQL that Spark and DuckDB share.
TESTS = {"ir": "l_discount <= 0.05", "gs": "l_tax <= 0.04", "pp": "l_linenumber <= 4"}
RERANK = {"alg": "l_quantity >= 25", "seq": "l_extendedprice < 40000"}
BITS = {"ir": 1, "gs": 2, "pp": 4}
BACKBONES = {"alg": 1, "seq": -1}
#: Whether a candidate is right, by execution and by component match.
RIGHT = {"EX": "l_returnflag = 'R'", "EM": "l_linestatus = 'F'"}
ORIGINS = ("alg", "seq")

#: Distinct systems: (backbone, mask, origin of the reranker or none).
SYSTEMS = [(b, m | (8 if o else 0), o) for b in BACKBONES for m in range(8) for o in ("", *RERANK)]


def _name(b: str, m: int, o: str) -> str:
    return f"{b}{m}{o}"


def _passes(mask: int, origin: str) -> str:
    return " and ".join([*(t for c, t in TESTS.items() if mask & BITS[c]), *([RERANK[origin]] if origin else [])]) or "true"


def scores(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(backbone, rr_origin, metric, mask, value in points) of all systems; those without a reranker stand under both origins.

    One pass over the beams: a system's choice is the least of packed keys, rank first and then its labels.
    """
    lines = line_beams(spark, sf_dir, extra=[c for c in table(spark, sf_dir, "lineitem").columns if c != "l_orderkey"])
    label = F.expr(f"cast({RIGHT['EX']} as bigint) * 2 + cast({RIGHT['EM']} as bigint)")
    keys = {b: F.col("pos").cast("bigint") * (4 * sign) + label for b, sign in BACKBONES.items()}
    taken = lines.groupBy("beam_id").agg(*[F.coalesce(F.min(F.when(F.expr(_passes(m, o)), keys[b])), F.min(keys[b])).alias(_name(b, m, o)) for b, m, o in SYSTEMS])
    bit = {"EX": 2, "EM": 1}
    sums = taken.agg(F.count(F.lit(1)).alias("n"), *[F.count_if(F.col(_name(*s)).bitwiseAND(bit[k]) > 0).alias(f"{_name(*s)}_{k}") for s in SYSTEMS for k in RIGHT])
    each = [
        F.struct(F.lit(b).alias("backbone"), F.lit(r).alias("rr_origin"), F.lit(k).alias("metric"), F.lit(m).alias("mask"), F.round(100 * F.col(f"{_name(b, m, o)}_{k}") / F.col("n"), 6).alias("value"))
        for b, m, o in SYSTEMS for r in ([o] if o else ORIGINS) for k in RIGHT
    ]
    return sums.select(F.inline(F.array(*each)))


def _scores_sql() -> str:
    """The same by the text of the choice: the labels at the least rank that passes, or at the least of all."""
    picks, rows = [], []
    for b, m, o in SYSTEMS:
        rank = {"alg": "pos", "seq": "-pos"}[b]
        for k in RIGHT:
            name = f"{_name(b, m, o)}_{k}"
            picks.append(f"coalesce(arg_min({k.lower()}, {rank}) filter ({_passes(m, o)}), arg_min({k.lower()}, {rank})) as {name}")
            rows += [f"select '{b}' as backbone, '{r}' as rr_origin, '{k}' as metric, {m} as mask, round(100 * count(*) filter ({name}) / count(*), 6) as value from picks" for r in ([o] if o else ORIGINS)]
    return (
        f"lines as (select *, row_number() over (partition by l_orderkey order by {', '.join(LINE_ORDER)}) as pos, {RIGHT['EX']} as ex, {RIGHT['EM']} as em from lineitem), "
        f"picks as (select l_orderkey, {', '.join(picks)} from lines group by l_orderkey), scores as ({' union all '.join(rows)})"
    )


SCORES_SQL = _scores_sql()
