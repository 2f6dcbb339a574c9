"""Grounded synthesis of (question, SQL) pairs, and curation of training sets."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from beamrank.sources.io import small
from beamrank.sources.tables import table

#: Templates: difficulty, question and SQL with one slot, and the column whose values fill it.
TEMPLATES = [
    ("easy", "How many orders have status {}?", "select count(*) as n from orders where o_orderstatus = '{}'", ("orders", "o_orderstatus")),
    ("easy", "How many customers are in segment {}?", "select count(*) as n from customer where c_mktsegment = '{}'", ("customer", "c_mktsegment")),
    ("easy", "What is the largest value of {} events?", "select max(value) as v from events where event_type = '{}'", ("events", "event_type")),
    ("medium", "Which part types does brand {} have, and how many parts of each?", "select p_type, count(*) as n from part where p_brand = '{}' group by p_type", ("part", "p_brand")),
    ("medium", "How many orders of each status have priority {}?", "select o_orderstatus, count(*) as n from orders where o_orderpriority = '{}' group by o_orderstatus", ("orders", "o_orderpriority")),
    ("hard", "How many customers does each nation of region {} have?", "select n_name, count(*) as n from region join nation on r_regionkey = n_regionkey join customer on n_nationkey = c_nationkey where r_name = '{}' group by n_name", ("region", "r_name")),
]


def number(*parts: Column) -> Column:
    return F.conv(F.substring(F.md5(F.concat_ws("|", *parts)), 1, 8), 16, 10).cast("bigint")


def values(spark: SparkSession, sf_dir: str) -> DataFrame:
    """template, rank from 0, value and number of values. Columns are categories: few values, broadcast if they are."""
    out = None
    for i, (_, _, _, (t, c)) in enumerate(TEMPLATES):
        one = table(spark, sf_dir, t).select(F.col(c).alias("value")).distinct()
        rows = one.select(F.lit(i).alias("template"), (F.row_number().over(Window.orderBy("value")) - 1).alias("rank"), "value", F.count(F.lit(1)).over(Window.partitionBy(F.lit(1))).alias("of"))
        out = rows if out is None else out.union(rows)
    return out


def generate(spark: SparkSession, sf_dir: str, n: int, seed: int = 42) -> DataFrame:
    """``n`` pairs of templates and values from the tables, by hash of their numbers; with duplicates."""
    filled = small(values(spark, sf_dir), "values")
    forms = F.broadcast(spark.createDataFrame([(i, d, q, s) for i, (d, q, s, _) in enumerate(TEMPLATES)], "template int, difficulty string, q string, s string"))
    counts = F.broadcast(filled.groupBy("template").agg(F.max("of").alias("n_values")))  # a row for each template
    ids = spark.range(n).select(F.col("id").alias("pair_id"), (number(F.col("id").cast("string"), F.lit(str(seed))) % len(TEMPLATES)).cast("int").alias("template"))
    slots = ids.join(counts, "template").withColumn("rank", (number(F.col("pair_id").cast("string"), F.lit(f"v{seed}")) % F.col("n_values")).cast("int"))
    rows = slots.join(filled, ["template", "rank"]).join(forms, "template")
    put = lambda c: F.replace(F.col(c), F.lit("{}"), F.col("value"))
    return rows.select("pair_id", put("q").alias("question"), put("s").alias("sql"), "difficulty")


def dedup(df: DataFrame, *keys: str, order: str = "pair_id") -> DataFrame:
    """The first row of each key. The window sees only digests and identifiers; rows that stay are joined back."""
    digest = F.sha2(F.concat_ws("\x1f", *[F.coalesce(F.col(k), F.lit("\x00")) for k in keys]), 256)
    firsts = df.groupBy(digest.alias("digest")).agg(F.min(order).alias(order)).select(order)
    return df.join(firsts, order, "left_semi")


def dup_rate(df: DataFrame, *keys: str) -> DataFrame:
    """Rows, duplicates and their share in percent."""
    n, distinct = F.count(F.lit(1)), F.count_distinct(F.sha2(F.concat_ws("\x1f", *[F.coalesce(F.col(k), F.lit("\x00")) for k in keys]), 256))
    return df.agg(n.alias("generated"), (n - distinct).alias("duplicates"), F.round(100 * (n - distinct) / n, 4).alias("percent"))


def dup_growth(df: DataFrame, key: str, order: str, bucket: int) -> DataFrame:
    """Duplicates in each run of ``bucket`` identifiers and up to its end."""
    firsts = df.groupBy(F.sha2(key, 256).alias("k")).agg(F.min(order).alias("o"))
    new = firsts.groupBy((F.col("o") / bucket).cast("bigint").alias("bucket")).agg(F.count(F.lit(1)).alias("new"))
    rows = df.groupBy((F.col(order) / bucket).cast("bigint").alias("bucket")).agg(F.count(F.lit(1)).alias("rows"))
    out = rows.join(new, "bucket", "left").withColumn("duplicates", F.col("rows") - F.coalesce("new", F.lit(0)))
    return out.select("bucket", "rows", "duplicates", F.sum("duplicates").over(Window.orderBy("bucket")).alias("so_far"))


def sizes(df: DataFrame, shares: list[float], key: str = "pair_id", seed: int = 42) -> DataFrame:
    """Nested samples by hash: a row belongs to every size whose share is above its number."""
    draw = number(F.col(key).cast("string"), F.lit(str(seed))) / float(1 << 32)
    each = F.array(*[F.when(draw < s, F.lit(s)) for s in shares])
    return df.select("*", F.explode(F.array_compact(each)).alias("share"))


def stratify(df: DataFrame, quota: dict[str, int], key: str = "pair_id", seed: int = 42) -> DataFrame:
    """So many of each difficulty, chosen by hash: a bounded top-k for each class, and no sort of a class."""
    draw = F.md5(F.concat_ws(":", F.col(key).cast("string"), F.lit(seed)))
    parts = [df.where(F.col("difficulty") == k).orderBy(draw, key).limit(n) for k, n in quota.items()]
    return reduce(DataFrame.unionByName, parts)


def points(sql: Column) -> Column:
    """Points of a query: one for each join, group, having, order, limit, or, like; two for each nested select or set operation."""
    count = lambda p: F.regexp_count(F.lower(sql), F.lit(p))
    ones = count(r"\b(join|group by|having|order by|limit|or|like)\b")
    return ones + 2 * (count(r"\(\s*select\b") + count(r"\b(union|intersect|except)\b"))


def difficulty(sql: Column) -> Column:
    p = points(sql)
    return F.when(p == 0, "easy").when(p == 1, "medium").when(p == 2, "hard").otherwise("extra")
