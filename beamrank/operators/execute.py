"""Execution match: do two queries give the same rows?

Results are never collected. A result is one row: number of columns and rows, and two aggregates of
the rows' hashes. Texts of distinct plans run once, some to a job; texts that fail analysis are wrong without
a job, and those that fail by their values (a division by zero, a bad cast) are wrong alone, not their
batch; only SELECT and WITH are accepted.

Nothing that grows with the tables is broadcast: NOT IN, which Spark would run by sending its whole
subquery to the driver, becomes an anti-join with the same meaning, and the texts run in a session
of their own that broadcasts tables of at most ``SMALL`` bytes.
"""

from __future__ import annotations

import gc
import re
from concurrent.futures import ThreadPoolExecutor
from functools import reduce
from threading import Lock

from pyspark.errors import (
    AnalysisException, ArithmeticException, ArrayIndexOutOfBoundsException, DateTimeException, IllegalArgumentException,
    NumberFormatException, ParseException, SparkRuntimeException,
)
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from beamrank.sources.tables import TABLES, table

BATCH = 2
#: Batches that are planned and run at once: the driver's memory goes by the plans that it holds, and to
#: a plan it adds anew each time that one of the stages of its job ends. For each stage and each scan Spark
#: also takes 4 MB on the driver for a moment, however small what it sends.
JOBS = 1
#: Batches after which the driver collects its garbage: only then do shuffles and broadcasts of ended
#: batches go, and does the heap give back what it has taken for them.
COLLECT = 8
#: Bytes of a table that a join may still broadcast, by the size of its files and as it is when it runs.
SMALL = 256 << 10


def register(spark: SparkSession, sf_dir: str) -> None:
    for t in TABLES:
        table(spark, sf_dir, t).createOrReplaceTempView(t)


def analysed(spark: SparkSession, sql: str) -> DataFrame | None:
    """The query's DataFrame, or None if it is no read-only query or fails analysis."""
    if not re.match(r"\s*(select|with)\b", sql, re.IGNORECASE):
        return None
    try:
        df = spark.sql(sql)
        df.schema  # noqa: B018  forces the analysis
        return df
    except (AnalysisException, ParseException):
        return None


_NOT_IN = re.compile(r"([A-Za-z_][\w.]*)\s+not\s+in\s*\((?=\s*select\b)", re.IGNORECASE)
_ALONE = "{x} not in ({s})"
#: NOT IN in three-valued logic: false with a match; without one true over no rows at all, null if the value or any row is null.
_ANTI = (
    "(not exists (select 1 from ({s}) as s__(k__) where k__ = {x}) and ((select count(*) from (select 1 from ({s}) as s__(k__) limit 1)) = 0"
    " or {x} is not null and (select count(*) from (select 1 from ({s}) as s__(k__) where k__ is null limit 1)) = 0 or cast(null as boolean)))"
)


def _closing(sql: str, at: int) -> int:
    """Where the bracket closes that opens just before ``at``, -1 if nowhere; what is quoted does not count."""
    depth, quoted = 1, False
    for i in range(at, len(sql)):
        if sql[i] == "'":
            quoted = not quoted
        elif not quoted:
            depth += (sql[i] == "(") - (sql[i] == ")")
        if not depth:
            return i
    return -1


def anti_joined(spark: SparkSession, sql: str) -> str:
    """The text with each NOT IN over a query that stands alone as an anti-join, which no side has to be broadcast for."""
    out, at = [], 0
    while m := _NOT_IN.search(sql, at):
        end = _closing(sql, m.end())
        if end < 0:
            break
        quoted = sql.count("'", 0, m.start()) % 2
        inner = sql[m.end() : end]
        form = _ANTI if not quoted and analysed(spark, inner) is not None else _ALONE
        out += [sql[at : m.start()], form.format(x=m[1], s=anti_joined(spark, inner)) if not quoted else sql[m.start() : end + 1]]
        at = end + 1
    return "".join([*out, sql[at:]])


def planned(spark: SparkSession, sql: str) -> DataFrame | None:
    """As ``analysed``, ready to run without broadcasts that grow. What is valid is what the text itself says."""
    df = analysed(spark, sql)
    other = sql if df is None else anti_joined(spark, sql)
    return df if other == sql else analysed(spark, other) or df


def _apart(spark: SparkSession, sf_dir: str) -> SparkSession:
    """A session with the tables as views and the settings of ``spark``, but for broadcasts."""
    own = spark.newSession()
    for name, value in spark.conf.getAll.items():
        if own.conf.isModifiable(name):
            own.conf.set(name, value)
    for name in ("spark.sql.autoBroadcastJoinThreshold", "spark.sql.adaptive.autoBroadcastJoinThreshold"):
        own.conf.set(name, str(SMALL))
    register(own, sf_dir)
    return own


def _text_of(c: Column, kind: str) -> Column:
    """A value as text: numbers rounded to six places where they fit, NaN and infinities with marks of their own, null apart from all."""
    if kind in ("double", "float"):
        c = c.cast("double")
        plain = F.coalesce(F.round(c, 6).try_cast("decimal(38,6)").cast("string"), c.cast("string"))
        text = F.when(F.isnan(c), "NaN").when(F.abs(c) == float("inf"), F.when(c > 0, "inf").otherwise("-inf")).otherwise(plain)
    elif kind.startswith("decimal"):
        text = F.coalesce(F.round(c, 6).try_cast("decimal(38,6)").cast("string"), c.cast("string"))
    else:
        text = c.cast("string")
    return F.when(c.isNull(), "null").otherwise(F.concat(F.lit("v"), text))


def _sums() -> list[Column]:
    """Of the hashes of a bag's rows."""
    return [F.count(F.lit(1)).alias("n"), F.sum(F.col("h").cast("decimal(38,0)")).alias("total"), F.bit_xor("h").alias("mixed")]


def _hash(df: DataFrame) -> tuple[DataFrame, Column]:
    """The rows under names of their own, and the hash of a row."""
    named = df.toDF(*[f"c{i}" for i in range(len(df.columns))])
    return named, F.xxhash64(*[_text_of(F.col(name), kind) for name, kind in named.dtypes])


def fingerprint(df: DataFrame, ordered: bool = False) -> DataFrame:
    """One row (arity, n, total, mixed): a bag's sum and xor of row hashes by partial aggregation.

    With ``ordered``, hashes are weighted by the rows' places: each partition of the sorted result gives
    sums over its own places, and the few partitions are put together by the counts before them.
    """
    (named, h), arity = _hash(df), F.lit(len(df.columns))
    if not ordered:
        return named.select(h.alias("h")).agg(arity.alias("arity"), *_sums())
    placed = named.select(h.alias("h"), F.monotonically_increasing_id().alias("at"))
    short, place = F.pmod("h", F.lit(1 << 31)).cast("decimal(38,0)"), F.expr("at & 8589934591").cast("decimal(20,0)")
    parts = placed.groupBy(F.shiftright("at", 33).alias("part")).agg(F.count(F.lit(1)).alias("n"), F.sum(short).alias("s"), F.sum(short * place).alias("sp"), F.bit_xor("h").alias("x"))
    before = F.coalesce(F.sum("n").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    summed = parts.withColumn("w", F.col("sp") + F.col("s") * before)
    return summed.agg(arity.alias("arity"), F.coalesce(F.sum("n"), F.lit(0)).alias("n"), F.sum("w").cast("decimal(38,0)").alias("total"), F.bit_xor("x").alias("mixed"))


#: What a query's own values can raise when it runs; anything else is no verdict on the query.
FAILURES = (ArithmeticException, ArrayIndexOutOfBoundsException, DateTimeException, IllegalArgumentException, NumberFormatException, SparkRuntimeException)


def _run(ready: list[tuple[int, DataFrame]], ordered: bool) -> dict[int, tuple | None]:
    """Fingerprints by number; if a batch fails by its values, its halves run apart, down to the one that fails.

    The bags of a batch are summed by one aggregate, so that they share its two stages.
    """
    try:
        if ordered:
            rows = reduce(DataFrame.union, [fingerprint(df, ordered).select(F.lit(i).alias("i"), "*") for i, df in ready])
            return {r["i"]: (r["arity"], r["n"], r["total"], r["mixed"]) for r in rows.collect()}
        hashes = reduce(DataFrame.union, [named.select(F.lit(i).alias("i"), h.alias("h")) for i, df in ready for named, h in [_hash(df)]])
        found = {r["i"]: (r["n"], r["total"], r["mixed"]) for r in hashes.groupBy("i").agg(*_sums()).collect()}
        return {i: (len(df.columns), *found.get(i, (0, None, None))) for i, df in ready}
    except FAILURES:
        if len(ready) == 1:
            return {ready[0][0]: None}
        half = len(ready) // 2
        return _run(ready[:half], ordered) | _run(ready[half:], ordered)


def _collect_garbage(spark: SparkSession) -> None:
    gc.collect()  # else DataFrames in cycles keep their plans in the JVM
    spark.sparkContext._jvm.System.gc()


def fingerprints(spark: SparkSession, sf_dir: str, sqls: list[str], ordered: bool = False) -> dict[str, tuple | None]:
    """Fingerprint of each text, None if it is invalid or fails when it runs. The driver gets one row for each text.

    Texts are analysed with their batch and forgotten with it, so that few plans are on the driver at once. Of texts
    with the same plan but for names, as Spark's canonical form has it, one runs.
    """
    own, lock = _apart(spark, sf_dir), Lock()
    seen: dict[int, list[str]] = {}
    same: dict[str, str] = {}

    def alike(sql: str, df: DataFrame) -> bool:
        """Whether a text before has the same plan; if none has, those to come are held against this one."""
        with lock:
            before = seen.setdefault(df.semanticHash(), [])
            for q in before:
                if df.sameSemantics(planned(own, q)):
                    same[sql] = q
                    return True
            before.append(sql)
            return False

    def judge(texts: list[str]) -> dict[str, tuple | None]:
        ready = [(i, df) for i, q in enumerate(texts) if (df := planned(own, q)) is not None and not alike(q, df)]
        found = _run(ready, ordered) if ready else {}
        return {q: found.get(i) for i, q in enumerate(texts)}

    out: dict[str, tuple | None] = {}
    with ThreadPoolExecutor(JOBS) as pool:
        for n, found in enumerate(pool.map(judge, (sqls[at : at + BATCH] for at in range(0, len(sqls), BATCH))), 1):
            out |= found
            if n % COLLECT == 0:
                _collect_garbage(spark)
    return out | {q: out[earlier] for q, earlier in same.items()}


_known: dict[tuple[str, str], dict[str, tuple | None]] = {}


def verdicts(spark: SparkSession, sf_dir: str, pairs: list[tuple[str, str]], golds: dict[str, str]) -> dict[tuple[str, str], tuple[bool, bool, int]]:
    """(question, text) -> (right, valid, rows of the gold result). Each distinct text runs once in a session."""
    known = _known.setdefault((spark.sparkContext.applicationId, sf_dir), {})
    texts = dict.fromkeys([*(golds[g] for g, _ in pairs), *(q for _, q in pairs)])
    known |= fingerprints(spark, sf_dir, [q for q in texts if q not in known])
    return {(g, q): (known[q] is not None and known[q] == known[golds[g]], known[q] is not None, known[golds[g]][1]) for g, q in pairs}


def labels(spark: SparkSession, sf_dir: str) -> dict[tuple[str, str], tuple[bool, bool, int]]:
    """The verdicts on all candidates of the catalogue."""
    from beamrank.operators.generators import candidates

    rows = candidates()
    return verdicts(spark, sf_dir, [(g, q) for g, _, q in rows], {g: q for g, kind, q in rows if kind == "gold"})


def label_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    from beamrank.operators.generators import candidates

    known = labels(spark, sf_dir)
    rows = [(g, kind, q, *known[g, q]) for g, kind, q in candidates()]
    return spark.createDataFrame(rows, "gold_id string, kind string, sql string, ex boolean, valid boolean, gold_rows bigint")


def strict_match(a: DataFrame, b: DataFrame) -> DataFrame:
    """One row: whether two results are the same bag, by difference both ways."""
    if len(a.columns) != len(b.columns):
        return a.sparkSession.createDataFrame([(False,)], "same boolean")
    names = [f"c{i}" for i in range(len(a.columns))]
    x, y = a.toDF(*names), b.toDF(*names)
    return x.exceptAll(y).union(y.exceptAll(x)).agg((F.count(F.lit(1)) == 0).alias("same"))


def fused_scan(df: DataFrame, predicates: dict[str, str]) -> DataFrame:
    """Counts of many candidates that differ in their predicate only, in one pass over the table."""
    sums = df.agg(*[F.count_if(F.expr(p)).alias(f"p{i}") for i, p in enumerate(predicates.values())])
    each = F.array(*[F.struct(F.lit(k).alias("candidate"), F.col(f"p{i}").alias("n")) for i, k in enumerate(predicates)])
    return sums.select(F.inline(each))
